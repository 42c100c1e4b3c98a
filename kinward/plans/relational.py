"""What users of the method need around it: scans, joins, aggregates, windows, sets, scalars, each with its SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinward.sources.shared import cut, shared_folder
from kinward.sources.tables import round_trip, table

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def _path(spark, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def _t(spark, d, name: str) -> DataFrame:
    return table(spark, d, name)


# scans, sources, sinks


@query("scan_columns", "SELECT l_orderkey, l_quantity FROM lineitem")
def _(spark, d):
    return _t(spark, d, "lineitem").select("l_orderkey", "l_quantity")


@query("scan_pushed", "SELECT event_id, user_id FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-12'")
def _(spark, d):
    ts = F.col("ts")
    return _t(spark, d, "events").filter((ts >= F.lit("2024-01-10").cast("timestamp_ntz")) & (ts < F.lit("2024-01-12").cast("timestamp_ntz"))).select("event_id", "user_id")


@query("write_partitioned", "SELECT o_orderstatus AS status, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY 1")
def _(spark, d):
    path = _path(spark, "orders")
    _t(spark, d, "orders").select("o_orderkey", F.col("o_orderstatus").alias("status")).write.partitionBy("status").parquet(path)
    return spark.read.parquet(path).filter("status = 'F'").groupBy("status").agg(F.count(F.lit(1)).alias("n"))


@query("write_bucketed", "SELECT c_mktsegment AS segment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _(spark, d):
    names = [f"kw_{x}_{uuid.uuid4().hex}" for x in ("o", "c")]
    _t(spark, d, "orders").select(F.col("o_custkey").alias("k")).write.bucketBy(8, "k").sortBy("k").saveAsTable(names[0])
    _t(spark, d, "customer").select(F.col("c_custkey").alias("k"), "c_mktsegment").write.bucketBy(8, "k").sortBy("k").saveAsTable(names[1])
    joined = spark.table(names[0]).join(spark.table(names[1]), "k")
    return joined.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("n"))


@query("json_round_trip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def _(spark, d):
    return round_trip(_t(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey"), _path(spark, "json"), "json")


@query("csv_round_trip", "SELECT s_suppkey, s_name, s_acctbal FROM supplier")
def _(spark, d):
    return round_trip(_t(spark, d, "supplier").select("s_suppkey", "s_name", "s_acctbal"), _path(spark, "csv"), "csv")


@query("sql_parameters", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY 1")
def _(spark, d):
    _t(spark, d, "orders").createOrReplaceTempView("kw_orders")
    return spark.sql("SELECT o_orderpriority, count(*) AS n FROM kw_orders WHERE o_totalprice > :least GROUP BY 1", {"least": 100000})


# projection and filter


@query("project_vector", "SELECT l_orderkey, l_linenumber, floor(l_quantity * 20 + 0.5)::BIGINT AS a, floor(l_extendedprice / 100)::BIGINT AS b FROM lineitem")
def _(spark, d):
    return _t(spark, d, "lineitem").select(
        "l_orderkey", "l_linenumber", F.floor(F.col("l_quantity") * 20 + 0.5).alias("a"), F.floor(F.col("l_extendedprice") / 100).alias("b")
    )


@query("filter_predicates", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand IN (SELECT min(p_brand) FROM part UNION SELECT max(p_brand) FROM part) AND p_name LIKE '%a%' AND p_type IS NOT DISTINCT FROM p_type")
def _(spark, d):
    p = _t(spark, d, "part")
    ends = p.agg(F.array(F.min("p_brand"), F.max("p_brand")).alias("ends"))
    return p.join(F.broadcast(ends)).filter(
        F.col("p_size").between(10, 20) & F.array_contains("ends", F.col("p_brand")) & F.col("p_name").like("%a%") & F.col("p_type").eqNullSafe(F.col("p_type"))
    ).select("p_partkey")


@query("case_coalesce", "SELECT d.doc_id, coalesce(l.quality, -1) AS quality, CASE WHEN l.toxic = 1 THEN 'toxic' WHEN l.toxic = 0 THEN 'clean' ELSE 'unknown' END AS state, nullif(d.lang, 'en') AS other FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def _(spark, d):
    rows = _t(spark, d, "documents").select("doc_id", "lang").join(_t(spark, d, "labels"), "doc_id", "left")
    state = F.when(F.col("toxic") == 1, "toxic").when(F.col("toxic") == 0, "clean").otherwise("unknown")
    return rows.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), state.alias("state"), F.nullif("lang", F.lit("en")).alias("other"))


@query("split_queries", "SELECT count(*) FILTER (WHERE vec_id % 20 = 0) AS queries, count(*) AS members FROM embeddings")
def _(spark, d):
    return _t(spark, d, "embeddings").agg(F.count_if(F.col("vec_id") % 20 == 0).alias("queries"), F.count(F.lit(1)).alias("members"))


@query("sample_rows", "SELECT true AS ok")
def _(spark, d):
    docs = _t(spark, d, "documents").select("doc_id", "lang")
    n, got = docs.count(), docs.sample(0.2, seed=3).count()
    strata = docs.sampleBy("lang", {"en": 1.0}, seed=3).filter("lang <> 'en'").count()
    return spark.createDataFrame([(abs(got - 0.2 * n) < 5 * (0.16 * n) ** 0.5 and strata == 0,)], "ok boolean")


# joins


@query("join_broadcast", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def _(spark, d):
    return _t(spark, d, "nation").join(F.broadcast(_t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")  # 5 regions


@query("join_merge", "SELECT o_orderkey, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, d):
    j = _t(spark, d, "lineitem").hint("merge").join(_t(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@query("join_shuffled_hash", "SELECT c_custkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _(spark, d):
    j = _t(spark, d, "orders").join(_t(spark, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("c_custkey").agg(F.count(F.lit(1)).alias("n"))


@query("join_theta", "SELECT s_suppkey, count(*) AS n FROM supplier, nation WHERE s_acctbal <= 1000 * (n_nationkey - 1) GROUP BY 1")
def _(spark, d):
    n = F.broadcast(_t(spark, d, "nation"))  # 25 rows by definition
    return _t(spark, d, "supplier").join(n, F.col("s_acctbal") <= 1000 * (F.col("n_nationkey") - 1)).groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n"))


@query("join_blocks", "SELECT a.s_suppkey AS a, count(*) AS n FROM supplier a, supplier b WHERE a.s_suppkey < b.s_suppkey GROUP BY 1")
def _(spark, d):
    s = _t(spark, d, "supplier").select(F.col("s_suppkey").alias("id"), F.pmod(F.xxhash64("s_suppkey"), F.lit(4)).cast("int").alias("blk"))
    every = F.explode(F.sequence(F.lit(0), F.lit(3)))
    x = s.select(F.col("id").alias("a"), F.col("blk").alias("i"), every.alias("j"))
    y = s.select(F.col("id").alias("b"), F.col("blk").alias("j"), every.alias("i"))
    return x.join(y, ["i", "j"]).filter("a < b").groupBy("a").agg(F.count(F.lit(1)).alias("n"))


@query("join_range", "SELECT s_suppkey, count(*) AS n FROM supplier JOIN customer ON abs(s_acctbal - c_acctbal) <= 50 GROUP BY 1")
def _(spark, d):
    w = 50
    s = _t(spark, d, "supplier").select("s_suppkey", "s_acctbal", F.explode(F.array(*[F.floor(F.col("s_acctbal") / w) + i for i in (-1, 0, 1)])).alias("bin"))
    c = _t(spark, d, "customer").select("c_acctbal", F.floor(F.col("c_acctbal") / w).alias("bin"))
    return s.join(c, "bin").filter(F.abs(F.col("s_acctbal") - F.col("c_acctbal")) <= w).groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n"))


@query("join_asof", "SELECT p.event_id, e.event_id AS last FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type <> 'purchase') e ON p.user_id = e.user_id AND p.ts > e.ts")
def _(spark, d):
    e = _t(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    other = F.when(F.col("event_type") != "purchase", F.col("event_id"))
    return e.withColumn("last", F.last(other, ignorenulls=True).over(w)).filter("event_type = 'purchase'").select("event_id", "last")


@query("join_interval", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts BETWEEN p.ts - INTERVAL 1 HOUR AND p.ts")
def _(spark, d):
    e = _t(spark, d, "events")
    p = e.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("ts").alias("pt"))
    c = e.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("ct"))
    return p.join(c, "user_id").filter((F.col("ct") <= F.col("pt")) & (F.col("ct") >= F.col("pt") - F.expr("INTERVAL 1 HOUR"))).select("purchase", "click")


@query("join_outer", "SELECT coalesce(s.k, c.k) AS k, s.n AS suppliers, c.n AS customers FROM (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) s FULL JOIN (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal < 0 GROUP BY 1) c ON s.k = c.k")
def _(spark, d):
    s = _t(spark, d, "supplier").filter("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    c = _t(spark, d, "customer").filter("c_acctbal < 0").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers"))
    return s.join(c, "k", "full_outer")


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def _(spark, d):
    o = _t(spark, d, "orders").filter("o_totalprice > 200000")
    return _t(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def _(spark, d):
    return _t(spark, d, "customer").join(_t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("join_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def _(spark, d):
    n = _t(spark, d, "nation")
    a, b = n.alias("a"), n.alias("b")
    on = (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))
    return a.join(b, on).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


@query("join_salted", "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def _(spark, d):
    salts = 4
    li = _t(spark, d, "lineitem").select("l_partkey", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(salts)).cast("int").alias("salt"))
    p = _t(spark, d, "part").select("p_partkey", "p_brand", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    j = li.join(p, (li["l_partkey"] == p["p_partkey"]) & (li["salt"] == p["salt"]))
    return j.groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))


@query("join_lateral", "SELECT p_partkey, l_orderkey, l_linenumber FROM (SELECT l_partkey AS p_partkey, l_orderkey, l_linenumber, row_number() OVER (PARTITION BY l_partkey ORDER BY l_extendedprice, l_orderkey, l_linenumber) AS r FROM lineitem JOIN part ON l_partkey = p_partkey) WHERE r <= 2")
def _(spark, d):
    # the window twin of a lateral top-k: a correlated limit would read the other side once a row
    w = Window.partitionBy("l_partkey").orderBy("l_extendedprice", "l_orderkey", "l_linenumber")
    best = _t(spark, d, "lineitem").withColumn("r", F.row_number().over(w)).filter("r <= 2")
    return _t(spark, d, "part").join(best, F.col("p_partkey") == F.col("l_partkey")).select("p_partkey", "l_orderkey", "l_linenumber")


@query("join_star", "SELECT r_name, count(*) AS n, round(sum(l_extendedprice), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def _(spark, d):
    j = _t(spark, d, "lineitem").join(_t(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    j = j.join(_t(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    j = j.join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 rows
    j = j.join(F.broadcast(_t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 5 rows
    return j.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("revenue"))


# aggregation


@query("agg_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS s, round(avg(l_quantity), 6) AS a, min(l_tax) AS lo, max(l_tax) AS hi, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY 1")
def _(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("s"), F.round(F.avg("l_quantity"), 6).alias("a"),
        F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"),
    )


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def _(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_partkey").alias("parts"))


@query("agg_approx", "SELECT true AS distinct_ok, true AS median_ok")
def _(spark, d):
    li = _t(spark, d, "lineitem")
    x = li.agg(
        F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"),
        F.percentile_approx("l_extendedprice", 0.5, 10000).alias("c"), F.expr("percentile(l_extendedprice, 0.5)").alias("e"),
    )
    return x.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("distinct_ok"), (F.abs(F.col("c") - F.col("e")) <= 0.01 * F.col("e")).alias("median_ok"))


@query("agg_argmax", "SELECT o_custkey, max(o_totalprice) AS most, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS at, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS least FROM orders GROUP BY 1")
def _(spark, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return _t(spark, d, "orders").groupBy("o_custkey").agg(
        F.max("o_totalprice").alias("most"), F.max_by("o_orderkey", by).alias("at"), F.min_by("o_orderkey", by).alias("least")
    )


@query("agg_collect", "SELECT n_regionkey, array_to_string(list(n_name ORDER BY n_name), ',') AS names FROM nation GROUP BY 1")
def _(spark, d):
    return _t(spark, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_set("n_name")), ",").alias("names"))


_GS = "SELECT l_returnflag AS f, year(l_shipdate)::BIGINT AS y, count(*) AS n, grouping_id(l_returnflag, year(l_shipdate))::BIGINT AS g FROM lineitem GROUP BY {}"


@query("agg_grouping_sets", _GS.format("GROUPING SETS ((l_returnflag, year(l_shipdate)), (l_returnflag), ())"))
def _(spark, d):
    _t(spark, d, "lineitem").selectExpr("l_returnflag AS f", "CAST(year(l_shipdate) AS BIGINT) AS y").createOrReplaceTempView("kw_li")
    return spark.sql("SELECT f, y, count(*) AS n, grouping_id(f, y) AS g FROM kw_li GROUP BY GROUPING SETS ((f, y), (f), ())")


@query("agg_cube", "SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_size)")
def _(spark, d):
    return _t(spark, d, "part").cube("p_brand", "p_size").agg(F.count(F.lit(1)).alias("n"))


@query("agg_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def _(spark, d):
    j = _t(spark, d, "customer").join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    j = j.join(F.broadcast(_t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


_KINDS = ["click", "error", "purchase", "signup", "view"]


@query("agg_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{k}') AS {k}" for k in _KINDS) + " FROM events GROUP BY 1")
def _(spark, d):
    return _t(spark, d, "events").groupBy("user_id").pivot("event_type", _KINDS).agg(F.count(F.lit(1))).fillna(0, _KINDS)


@query("agg_unpivot", "SELECT l_returnflag, 'q' AS name, round(sum(l_quantity), 2) AS value FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 't', round(sum(l_tax), 2) FROM lineitem GROUP BY 1")
def _(spark, d):
    wide = _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.sum("l_tax"), 2).alias("t"))
    return wide.unpivot("l_returnflag", ["q", "t"], "name", "value")


@query("agg_filtered", "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) >= 12")
def _(spark, d):
    return _t(spark, d, "orders").groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("done"), F.count(F.lit(1)).alias("n")).filter("n >= 12")


@query("agg_sort_based", "SELECT p_brand, max(p_name) AS last FROM part GROUP BY 1")
def _(spark, d):
    return _t(spark, d, "part").groupBy("p_brand").agg(F.max("p_name").alias("last"))


# windows, sorts, sets


@query("win_rank", "SELECT o_orderkey, row_number() OVER w::INT AS rn, rank() OVER r::INT AS rk, dense_rank() OVER r::INT AS dr, ntile(4) OVER w::INT AS nt, round(percent_rank() OVER r, 6) AS pr, round(cume_dist() OVER r, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), r AS (PARTITION BY o_custkey ORDER BY o_orderpriority)".replace(" OVER w::INT", " OVER w").replace(" OVER r::INT", " OVER r"))
def _(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    r = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return _t(spark, d, "orders").select(
        "o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(r).cast("long").alias("rk"), F.dense_rank().over(r).cast("long").alias("dr"),
        F.ntile(4).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(r), 6).alias("pr"), F.round(F.cume_dist().over(r), 6).alias("cd"),
    )


@query("win_offset", "SELECT event_id, lag(event_id) OVER w AS a, lead(event_id) OVER w AS b, first_value(event_id) OVER w AS f, nth_value(event_id, 2) OVER w AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _t(spark, d, "events").select(
        "event_id", F.lag("event_id").over(w).alias("a"), F.lead("event_id").over(w).alias("b"), F.first("event_id").over(w).alias("f"), F.nth_value("event_id", 2).over(w).alias("s")
    )


@query("win_frame_rows", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS run FROM orders")
def _(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return _t(spark, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("run"))


@query("win_frame_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(spark, d):
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return _t(spark, d, "events").withColumn("us", us).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@query("sort_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC NULLS LAST, o_orderkey LIMIT 20 OFFSET 5")
def _(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc_nulls_last("o_totalprice"), "o_orderkey").offset(5).limit(20)


@query("topk_per_group", "SELECT l_partkey, l_orderkey, l_linenumber FROM (SELECT *, row_number() OVER (PARTITION BY l_partkey ORDER BY l_quantity DESC, l_orderkey, l_linenumber, l_suppkey) AS r FROM lineitem) WHERE r <= 3")
def _(spark, d):
    w = Window.partitionBy("l_partkey").orderBy(F.desc("l_quantity"), "l_orderkey", "l_linenumber", "l_suppkey")
    return _t(spark, d, "lineitem").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("l_partkey", "l_orderkey", "l_linenumber")


@query("sort_within", "SELECT o_custkey, o_orderkey FROM orders")
def _(spark, d):
    return _t(spark, d, "orders").select("o_custkey", "o_orderkey").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")


@query("set_union", "SELECT n_name AS name, n_regionkey AS region FROM nation UNION ALL SELECT r_name, NULL FROM region")
def _(spark, d):
    a = _t(spark, d, "nation").select(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region"))
    return a.unionByName(_t(spark, d, "region").select(F.col("r_name").alias("name")), allowMissingColumns=True)


@query("set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def _(spark, d):
    return _t(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(_t(spark, d, "supplier").select("s_nationkey"))


@query("set_except", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def _(spark, d):
    return _t(spark, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(_t(spark, d, "supplier").select("s_nationkey"))


# scalar functions and subqueries


@query("fn_string", "SELECT doc_id, lower(substr(text, 1, 5)) AS a, length(trim(text)) AS b, regexp_extract(text, '[A-Za-z]+', 0) AS c, md5(text) AS e, len(string_split(text, ' ')) AS f, concat_ws('-', lang, source) AS g FROM documents")
def _(spark, d):
    t = F.col("text")
    return _t(spark, d, "documents").select(
        "doc_id", F.lower(F.substring(t, 1, 5)).alias("a"), F.length(F.trim(t)).cast("long").alias("b"), F.regexp_extract(t, "[A-Za-z]+", 0).alias("c"),
        F.md5(t.cast("binary")).alias("e"), F.size(F.split(t, " ", -1)).cast("long").alias("f"), F.concat_ws("-", "lang", "source").alias("g"),
    )


@query("html_to_text", r"SELECT page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \t\n\r]+', ' ', 'g'))) AS digest FROM pages")
def _(spark, d):
    x = F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    x = F.trim(F.regexp_replace(F.regexp_replace(x, r"<[^>]*>", " "), r"[ \t\n\r]+", " "))
    return _t(spark, d, "pages").select("page_id", F.md5(x.cast("binary")).alias("digest"))


@query("fn_dates", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days, strftime(o_orderdate + INTERVAL 2 MONTH, '%Y-%m-%d') AS later, year(o_orderdate) AS y, quarter(o_orderdate) AS q FROM orders")
def _(spark, d):
    t = F.col("o_orderdate")
    return _t(spark, d, "orders").select(
        "o_orderkey", F.date_format(F.trunc(t, "month"), "yyyy-MM-dd").alias("m"), F.datediff(t, F.lit("1992-01-01").cast("date")).cast("long").alias("days"),
        F.date_format(F.add_months(t, 2), "yyyy-MM-dd").alias("later"), F.year(t).cast("long").alias("y"), F.quarter(t).cast("long").alias("q"),
    )


@query("fn_math", "SELECT s_suppkey, round(sqrt(abs(s_acctbal)), 6) AS a, round(ln(abs(s_acctbal) + 1), 6) AS b, round(power(s_nationkey, 2), 6) AS c, floor(s_acctbal)::BIGINT AS e, greatest(s_acctbal, 0) AS f, least(s_acctbal, 0) AS g FROM supplier")
def _(spark, d):
    x = F.col("s_acctbal")
    return _t(spark, d, "supplier").select(
        "s_suppkey", F.round(F.sqrt(F.abs(x)), 6).alias("a"), F.round(F.log(F.abs(x) + 1), 6).alias("b"), F.round(F.pow(F.col("s_nationkey"), 2), 6).alias("c"),
        F.floor(x).alias("e"), F.greatest(x, F.lit(0.0)).alias("f"), F.least(x, F.lit(0.0)).alias("g"),
    )


@query("fn_arrays", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(list_max(embedding)::DOUBLE, 6) AS top, len(list_distinct(list_transform(embedding, lambda x: x > 0))) AS signs, round(embedding[3]::DOUBLE, 6) AS third FROM embeddings")
def _(spark, d):
    e = F.col("embedding")
    return _t(spark, d, "embeddings").select(
        "vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("pos"), F.round(F.array_max(e).cast("double"), 6).alias("top"),
        F.size(F.array_distinct(F.transform(e, lambda x: x > 0))).cast("long").alias("signs"), F.round(F.element_at(e, 3).cast("double"), 6).alias("third"),
    )


@query("fn_maps", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    c = _t(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("c"))
    m = c.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "c"))).alias("m"))
    total = F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x)
    return m.select("user_id", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).cast("long").alias("views"), total.alias("n"))


@query("json_props", "SELECT event_id, (props->>'k')::BIGINT AS k FROM events")
def _(spark, d):
    return _t(spark, d, "events").select("event_id", F.from_json("props", "k BIGINT")["k"].alias("k"))


@query("fn_structs", "SELECT n_nationkey, n_name || '/' || n_regionkey AS tag FROM nation")
def _(spark, d):
    s = F.struct(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region"))
    rows = _t(spark, d, "nation").select("n_nationkey", s.withField("tag", F.concat_ws("/", "n_name", F.col("n_regionkey").cast("string"))).alias("s"))
    return rows.select("n_nationkey", F.inline(F.array(F.struct(F.col("s.tag").alias("tag")))))


@query("subqueries", "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS s FROM orders GROUP BY 1) SELECT c_custkey FROM customer c WHERE c_custkey IN (SELECT o_custkey FROM big WHERE s > (SELECT avg(s) FROM big)) AND EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'F')")
def _(spark, d):
    for t in ("orders", "customer"):
        _t(spark, d, t).createOrReplaceTempView(f"kw_{t}")
    return spark.sql(
        "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS s FROM kw_orders GROUP BY 1) SELECT c_custkey FROM kw_customer c "
        "WHERE c_custkey IN (SELECT o_custkey FROM big WHERE s > (SELECT avg(s) FROM big)) AND EXISTS (SELECT 1 FROM kw_orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'F')"
    )


@query("recursive_closure", "WITH RECURSIVE r(a, b) AS (SELECT n_nationkey, n_regionkey FROM nation UNION SELECT r.a, n_regionkey FROM r JOIN nation ON n_nationkey = r.b) SELECT a, b FROM r")
def _(spark, d):
    edges = cut(_t(spark, d, "nation").select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("b")))
    reached = front = edges.distinct()
    while not front.isEmpty():
        step = front.join(edges.select(F.col("a").alias("b"), F.col("b").alias("c")), "b").select("a", F.col("c").alias("b")).distinct()
        front = cut(step.join(reached, ["a", "b"], "left_anti"))
        reached = cut(reached.unionByName(front))
    return reached
