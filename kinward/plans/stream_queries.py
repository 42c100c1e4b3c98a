"""Driver queries over streams and the UDF surface, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from kinward.functions import udfs
from kinward.operators import exact, measures
from kinward.operators.index import HybridIndex
from kinward.operators.proxy import SearchOptions
from kinward.plans.core_queries import _cte, _truth, points
from kinward.plans.core_queries import Set
from kinward.sources.tables import table
from kinward.streaming import streams as st

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def _events(spark, d, slices: int = 4):
    rows = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    return st.sliced(rows, "event_id", slices)


def _start(df):
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


_HOUR = "strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S')"


@query("stream_tumbling", f"SELECT {_HOUR} AS start, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY 1")
def _(spark, d):
    return _start(st.drained(st.tumbling(_events(spark, d)), "complete")).withColumn("total", F.round("total", 2))


@query("stream_sliding", """SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT ts, date_trunc('hour', ts) - x * INTERVAL 1 HOUR AS s FROM events, range(6) r(x))
    WHERE s + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY s""")
def _(spark, d):
    return _start(st.drained(st.sliding(_events(spark, d)), "append"))


@query("stream_session", """WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g)
    SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def _(spark, d):
    return _start(st.drained(st.sessions(_events(spark, d)), "complete"))


@query("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    rows = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    stream = st.sliced(rows.unionByName(rows), "event_id", 4)  # every event arrives twice
    return st.drained(st.deduplicated(stream), "append").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("stream_late", "SELECT true AS dropped")
def _(spark, d):
    rows = table(spark, d, "events").select((-F.col("event_id")).alias("k"), F.col("ts").cast("timestamp").alias("ts"), "value")
    stream = st.tumbling(st.sliced(rows, "k", 4), "1 hour", "1 hour")  # newest first, so the rest is late
    progress = st.run_out(stream, "append", lambda batch, number: batch.write.format("noop").mode("overwrite").save())
    return spark.createDataFrame([(st.late_rows(progress) > 0,)], "dropped boolean")


@query("stream_static_join", _cte("e", 10) + ", m AS (SELECT count(*) AS n FROM b) SELECT events.user_id, count(*) AS n FROM events, m JOIN kn ON kn.dst = events.event_id % m.n GROUP BY 1")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    n = s.points.count()
    joined = _events(spark, d).withColumn("dst", F.col("event_id") % n).join(s.rev.select("dst", "src"), "dst")
    return st.drained(joined.groupBy("user_id").agg(F.count(F.lit(1)).alias("n")), "complete")


@query("stream_interval_join", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts BETWEEN p.ts - INTERVAL 1 HOUR AND p.ts")
def _(spark, d):
    clicks = _events(spark, d).filter("event_type = 'click'")
    purchases = _events(spark, d).filter("event_type = 'purchase'")
    return st.drained(st.clicks_before_purchases(clicks, purchases), "append")


@query("stream_state", "SELECT user_id, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    return st.drained(st.running_counts(_events(spark, d)), "update").groupBy("user_id").agg(F.max("n").alias("n"))


@query("stream_maintenance", "SELECT count(*) AS points, 20 * count(*) AS entries, 20 * count(*) AS postings, true AS in_step, true AS recall_ok FROM embeddings")
def _(spark, d):
    """A third of the members arrives by stream, which is stopped once on the way and goes on from its checkpoint."""
    s = Set(spark, d, "e", 20)
    index = HybridIndex.build(s.points.filter("id % 3 > 0"), st.fresh(spark, "index"), 20, 16, 60, 4)
    rest, folder, check = s.points.filter("id % 3 = 0"), st.fresh(spark, "arrivals"), st.fresh(spark, "check")
    for part in (0, 1):
        rest.filter(F.pmod(F.xxhash64("id"), F.lit(2)) == part).coalesce(1).write.mode("append").parquet(folder)
        arrivals = spark.readStream.schema(rest.schema).option("maxFilesPerTrigger", 1).parquet(folder)
        index = st.maintained(arrivals, index, check)
    knn, rev = index.view("knn"), index.view("rev")
    in_step = rev.select("src", "rank", "dst").exceptAll(knn.select("src", "rank", "dst")).isEmpty()
    recall = measures.graph_recall(knn, s.knn, 10).first()[0]
    return spark.createDataFrame(
        [(index.view("points").count(), knn.count(), rev.count(), in_step, recall >= 0.9)],
        "points long, entries long, postings long, in_step boolean, recall_ok boolean",
    )


@query("stream_search", """SELECT count(*) AS events, true AS recall_ok FROM events""")
def _(spark, d):
    """Events name members; every batch of them is answered by proxy search over the saved index."""
    s = Set(spark, d, "e", 50)
    index = HybridIndex.build(s.points, st.fresh(spark, "index"), 50, 16, 60, 4)
    n = s.points.count()
    rows = table(spark, d, "events").select("event_id", F.pmod("event_id", F.lit(n)).cast("long").alias("vec_id"))
    found = st.searched(st.sliced(rows, "event_id", 2), index, index.fitted(SearchOptions(10, 20, 50)))
    true = s.rev.filter("rank <= 10").select(F.col("dst").alias("vec_id"), F.col("src").alias("id")).join(rows, "vec_id").select("event_id", "id")
    hit = true.join(found, ["event_id", "id"], "left_semi").count()
    return spark.createDataFrame([(rows.count(), hit >= 0.9 * true.count())], "events long, recall_ok boolean")


@query("stream_rate_soak", "SELECT true AS came, 0 AS gaps")
def _(spark, d):
    return st.soak(spark).select((F.col("rows") > 0).alias("came"), F.col("gaps").cast("int").alias("gaps"))


@query("stream_modes", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    counts = _events(spark, d).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return st.drained(counts, "update").groupBy("event_type").agg(F.max("n").alias("n"))


@query("udf_distance", _cte("e", 1) + " SELECT src, dst, round(dist, 6) AS dist FROM al WHERE src % 20 = 0")
def _(spark, d):
    p = points(spark, d, "e")
    q = p.filter("id % 20 = 0").select(F.col("id").alias("src"), F.col("vec").alias("a"))
    pairs = exact.beside(q, p.select(F.col("id").alias("dst"), F.col("vec").alias("b")), "a").filter("src <> dst")
    return pairs.select("src", "dst", F.round(udfs.l2_udf("a", "b"), 6).alias("dist"))


@query("udf_topk", _cte("e", 5) + " SELECT src, array_to_string(list(dst ORDER BY rank), ',') AS ids FROM kn GROUP BY src")
def _(spark, d):
    knn = exact.ranked_graph_exact(points(spark, d, "e"), 8)
    top = knn.groupBy("src").agg(udfs.topk_ids("dist", "dst", F.lit(5)).alias("ids"))
    return top.select("src", F.array_join(F.col("ids").cast("array<string>"), ",").alias("ids"))


@query("udtf_rknn", _cte("e", 10) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_truth(10)}")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    udfs.register_all(spark, (s.points, s.radii))
    s.queries.createOrReplaceTempView("kw_queries")
    return spark.sql("SELECT r.qid, r.id, round(r.dist, 6) AS dist FROM kw_queries q, LATERAL rknn(q.qid, q.vec, 10) r")
