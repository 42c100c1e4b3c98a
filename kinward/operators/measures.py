"""Measures: recall with its empty-truth cases, precision, counters, coverage, sizes."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def per_query(truth: DataFrame, answer: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, hit, truth, ans, recall, precision). Without truth, recall is 1 for an empty answer and 0 otherwise."""
    pairs = truth.select("qid", "id", F.lit(1).alias("t")).join(
        answer.select("qid", "id", F.lit(1).alias("a")), ["qid", "id"], "full_outer"
    )
    counts = pairs.groupBy("qid").agg(
        F.count_if(F.col("t").isNotNull() & F.col("a").isNotNull()).alias("hit"), F.count("t").alias("truth"), F.count("a").alias("ans")
    )
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    rows = queries.select("qid").join(counts, "qid", "left").select("qid", zero("hit"), zero("truth"), zero("ans"))
    recall = F.when(F.col("truth") > 0, F.col("hit") / F.col("truth")).when(F.col("ans") == 0, 1.0).otherwise(0.0)
    precision = F.when(F.col("ans") > 0, F.col("hit") / F.col("ans")).otherwise(1.0)
    return rows.withColumns({"recall": F.round(recall, 6), "precision": F.round(precision, 6)})


def recall(truth: DataFrame, answer: DataFrame, queries: DataFrame) -> float:
    return per_query(truth, answer, queries).agg(F.avg("recall")).first()[0]


def rank_profile(ranks: DataFrame) -> DataFrame:
    """(n, p50, p90, most) of neighbour ranks."""
    disc = lambda p: F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY rank)").cast("long")
    return ranks.agg(F.count(F.lit(1)).alias("n"), disc(0.5).alias("p50"), disc(0.9).alias("p90"), F.max("rank").cast("long").alias("most"))


def reached(truth: DataFrame, proxies: DataFrame, lists: DataFrame, theta: int) -> DataFrame:
    """(qid, id, rank, prank): of each true pair, the proxies of the query that stand in the member's list up to rank ``theta``.

    Pairs meet lists and proxies as whole arrays, and are taken apart only after that.
    """
    own = lists.select(F.col("src").alias("id"), F.slice("dsts", 1, theta).alias("dsts"))
    near = proxies.groupBy("qid").agg(F.collect_list(F.struct(F.col("id").alias("dst"), "prank")).alias("near"))
    held = truth.select("qid", "id").join(near, "qid").join(own, "id")
    met = F.filter("near", lambda x: F.array_contains("dsts", x["dst"]))
    rows = held.select("qid", "id", "dsts", F.explode(met).alias("x"))
    return rows.select("qid", "id", F.array_position("dsts", F.col("x.dst")).cast("int").alias("rank"), "x.prank")


def precision(truth: DataFrame, proxies: DataFrame, lists: DataFrame, queries: DataFrame, theta: int) -> DataFrame:
    """(qid, hit, ans, precision) of the distinct candidates of proxies, from the owners' lists."""
    from kinward.operators import proxy

    ans = proxy.counters_by_owner(proxies, lists, queries, theta).select("qid", F.col("candidates").alias("ans"))
    hits = reached(truth, proxies, lists, theta).groupBy("qid").agg(F.count_distinct("id").alias("hit"))
    share = F.when(F.col("ans") > 0, F.col("hit") / F.col("ans")).otherwise(1.0)
    rows = ans.join(hits, "qid", "left").select("qid", F.coalesce("hit", F.lit(0)).cast("long").alias("hit"), "ans")
    return rows.withColumn("precision", F.round(share, 6))


def proxy_coverage(truth: DataFrame, proxies: DataFrame, lists: DataFrame, thetas: list[int], ms: list[int]) -> DataFrame:
    """(theta, m, share): true pairs reachable through some proxy of rank m at most."""
    reach = reached(truth, proxies, lists, max(thetas))
    spark = truth.sparkSession
    cells = F.broadcast(spark.createDataFrame([(t, m) for t in thetas for m in ms], "theta int, m int"))  # the grid
    hits = reach.join(cells, (F.col("rank") <= F.col("theta")) & (F.col("prank") <= F.col("m"))).groupBy("theta", "m").agg(
        F.count_distinct("qid", "id").alias("n")
    )
    whole = truth.agg(F.count(F.lit(1)).alias("all"))
    return cells.join(hits, ["theta", "m"], "left").join(F.broadcast(whole)).select(
        "theta", "m", F.round(F.coalesce("n", F.lit(0)) / F.col("all"), 6).alias("share")
    )


def graph_recall(knn: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """(recall): share of the exact k-lists that a graph holds."""
    want = exact.filter(F.col("rank") <= k).select("src", "dst")
    have = knn.filter(F.col("rank") <= k).select("src", "dst", F.lit(1).alias("h"))
    return want.join(have, ["src", "dst"], "left").agg(F.round(F.count("h") / F.count(F.lit(1)), 6).alias("recall"))


def index_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """(both, only_a, only_b, radius_gap) of two ranked graphs."""
    x = a.select("src", "dst", F.col("dist").alias("da"))
    y = b.select("src", "dst", F.col("dist").alias("db"))
    pairs = x.join(y, ["src", "dst"], "full_outer").agg(
        F.count_if(F.col("da").isNotNull() & F.col("db").isNotNull()).alias("both"),
        F.count_if(F.col("db").isNull()).alias("only_a"), F.count_if(F.col("da").isNull()).alias("only_b"),
    )
    far = lambda d, c: d.groupBy("src").agg(F.max("dist").alias(c))
    gap = far(a, "ra").join(far(b, "rb"), "src").agg(F.round(F.max(F.abs(F.col("ra") - F.col("rb"))), 6).alias("radius_gap"))
    return pairs.join(F.broadcast(gap))


def speed_up(rows: DataFrame, base: str) -> DataFrame:
    """(method, factor): throughput against a base method, of (method, qps) rows."""
    one = rows.filter(F.col("method") == base).select(F.col("qps").alias("base"))
    return rows.join(F.broadcast(one)).select("method", F.round(F.col("qps") / F.col("base"), 6).alias("factor"))


def throughput(index, queries: DataFrame, truth: DataFrame, k: int, m: int, theta: int, k_prime: int, methods=("proxy", "one_shot", "one_shot_radii")) -> DataFrame:
    """(method, m, theta, recall, results, seconds, qps): a batch of queries on a built index, timed without the build.

    ``one_shot`` verifies k' neighbours by searches of their own, ``one_shot_radii`` by the stored radii.
    """
    from kinward.operators import baselines, proxy

    def one_shot(radii):
        near = index.proxies(queries, k_prime, 2 * k_prime)
        return baselines.one_shot_rknn(queries, index.view("points"), k, k_prime, radii, near)

    runs = {
        "proxy": (m, theta, lambda: index.search(queries, proxy.SearchOptions(k, m, theta))),
        "one_shot": (k_prime, 0, lambda: one_shot(None)),
        "one_shot_radii": (k_prime, 0, lambda: one_shot(index.view("radii"))),
    }
    asked, rows = queries.count(), []
    for name in methods:
        a, b, make = runs[name]
        began = time.perf_counter()
        answer = make().select("qid", "id").persist()
        n = answer.count()
        took = time.perf_counter() - began
        rows.append((name, a, b, recall(truth, answer, queries), n / max(1, asked), took, asked / took))
        answer.unpersist()
    return queries.sparkSession.createDataFrame(rows, "method string, m int, theta int, recall double, results double, seconds double, qps double")


def best_by_qps(rows: DataFrame, target: float) -> DataFrame:
    """Of the settings of each method that reach the target recall, the one of most queries a second."""
    ok = rows.filter(F.col("recall") >= target)
    cell = F.struct("m", "theta", "recall", "qps")
    return ok.groupBy("method").agg(F.max_by(cell, F.struct("qps", "m", "theta")).alias("b")).select("method", "b.*")
