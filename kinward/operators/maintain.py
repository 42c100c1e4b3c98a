"""Keeping an index current under appended points.

The affected set is read before new points have postings. Lists of affected points take the new
points in and drop their farthest; the postings of changed lists are replaced whole, which covers
removed, added and shifted ranks. Top-K under (distance, id) is associative, so a batch and single
inserts agree wherever their affected sets do.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinward.operators import exact, postings, proxy
from kinward.operators.ranked_graph import top_k
from kinward.sources.shared import cut


def outer_radius(knn: DataFrame, points: DataFrame, K: int) -> DataFrame:
    """(id, radius): distance of the K-th entry; infinite for shorter lists."""
    far = knn.filter(F.col("rank") == K).select(F.col("src").alias("id"), F.col("dist").alias("radius"))
    return points.select("id").join(far, "id", "left").select("id", F.coalesce("radius", F.lit(float("inf"))).alias("radius"))


def affected_exact(points: DataFrame, knn: DataFrame, new: DataFrame, K: int) -> DataFrame:
    """(new_id, id, dist): members strictly nearer to a new point than to their K-th neighbour."""
    outer = outer_radius(knn, points, K)
    radii = outer.select("id", F.array("radius").alias("r"))
    found = exact.exact_rknn(new.select(F.col("id").alias("qid"), "vec"), points, radii, 1)
    return found.join(outer, "id").filter(F.col("dist") < F.col("radius")).select(F.col("qid").alias("new_id"), "id", "dist")


def affected_approx(points: DataFrame, knn: DataFrame, rev: DataFrame, new: DataFrame, K: int, m: int, theta: int, proxies: DataFrame | None = None, include_proxies: bool = False) -> DataFrame:
    """(new_id, id, dist): affected members among the candidates that proxies of the new points give, the proxies too if asked for."""
    asked = new.select(F.col("id").alias("qid"), "vec")
    near = proxy.flat_proxies(asked, points, m) if proxies is None else proxies
    outer = outer_radius(knn, points, K)
    radii = outer.select("id", F.array("radius").alias("r"))
    found = proxy.verify(proxy.candidates(near, rev, theta, include_proxies), asked, points, radii, 1)
    return found.join(outer, "id").filter(F.col("dist") < F.col("radius")).select(F.col("qid").alias("new_id"), "id", "dist")


def own_lists(points: DataFrame, new: DataFrame, K: int) -> DataFrame:
    """(src, dst, dist): the K nearest of each new point, members and other new points alike."""
    every = points.select("id", "vec").unionByName(new.select("id", "vec"))
    near = exact.exact_knn(new.select(F.col("id").alias("qid"), "vec"), every, K, exclude_self=True)
    return near.select(F.col("qid").alias("src"), F.col("id").alias("dst"), "dist")


def refreshed(knn: DataFrame, affected: DataFrame, own: DataFrame, K: int) -> DataFrame:
    """(src, rank, dst, dist): whole lists of the new points and of the affected ones that changed."""
    touched = affected.select(F.col("id").alias("src")).distinct()
    old = knn.join(touched, "src", "left_semi").select("src", "dst", "dist")
    gained = affected.select(F.col("id").alias("src"), F.col("new_id").alias("dst"), "dist")
    return top_k(old.unionByName(gained).unionByName(own), K).select("src", "rank", "dst", "dist")


def synchronised(rev: DataFrame, changed: DataFrame) -> DataFrame:
    """Postings after the lists of the changed owners were replaced."""
    owners = changed.select("src").distinct()
    return rev.join(owners, "src", "left_anti").select("dst", "rank", "src", "dist").unionByName(
        changed.select("dst", "rank", "src", "dist")
    )


def insert_batch(points: DataFrame, knn: DataFrame, new: DataFrame, K: int, m: int | None = None, theta: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(points, knn) with a batch inserted; the affected set is exact unless m and theta are given."""
    rev = postings.transpose(knn)
    hit = affected_exact(points, knn, new, K) if m is None else affected_approx(points, knn, rev, new, K, m, theta)
    changed = refreshed(knn, hit, own_lists(points, new, K), K)
    kept = knn.join(changed.select("src").distinct(), "src", "left_anti")
    return (
        points.select("id", "vec").unionByName(new.select("id", "vec")),
        kept.select("src", "rank", "dst", "dist").unionByName(changed),
    )


def insert_one(points: DataFrame, knn: DataFrame, row: DataFrame, K: int, m: int, theta: int) -> tuple[DataFrame, DataFrame]:
    """One point at a time."""
    return insert_batch(points, knn, row.limit(1), K, m, theta)


def build_by_insertion(points: DataFrame, K: int, share: float, steps: int = 4, m: int = 20, theta: int = 50) -> DataFrame:
    """(src, rank, dst, dist): a graph whose first ``share`` is built at once and whose rest arrives in batches.

    With a share of 0 the first batch holds one point, and batches double until the last ``steps``.
    """
    order = F.row_number().over(Window.partitionBy("b").orderBy(F.xxhash64("id", F.lit(5)), "id"))
    n = points.count()
    blocks = max(1, n // 100_000)
    placed = points.select("id", "vec", F.pmod(F.xxhash64("id", F.lit(9)), F.lit(blocks)).alias("b")).withColumn("r", order)
    marked = cut(placed.select("id", "vec", ((F.col("r") - 1) * blocks + F.col("b")).alias("at")))
    ends = [max(1, round(share * n))]
    while ends[-1] < n:
        ends.append(min(n, max(ends[-1] + -(-(n - ends[0]) // steps) if ends[-1] * 2 > n / steps else ends[-1] * 2, ends[-1] + 1)))
    have = marked.filter(F.col("at") < ends[0]).select("id", "vec")
    knn = cut(exact.ranked_graph_exact(have, K))
    for i, (low, high) in enumerate(zip(ends, ends[1:])):
        top = F.lit(True) if high >= n else F.col("at") < high
        new = marked.filter((F.col("at") >= low) & top).select("id", "vec")
        have, knn = insert_batch(have, knn, new, K, m, theta)
        knn = cut(knn)
    return knn


def rebuild(points: DataFrame, K: int) -> DataFrame:
    return exact.ranked_graph_exact(points, K)


def insertion_cost(points: DataFrame, knn: DataFrame, new: DataFrame, K: int, m: int, theta: int) -> DataFrame:
    """(new_id, scanned, affected, changed): postings read, affected members, entries that change."""
    asked = new.select(F.col("id").alias("qid"), "vec")
    rev = postings.transpose(knn)
    near = proxy.flat_proxies(asked, points, m)
    read = proxy.query_counters(near, rev, asked, theta).select(F.col("qid").alias("new_id"), "scanned")
    hit = affected_approx(points, knn, rev, new, K, m, theta, near).groupBy("new_id").agg(F.count(F.lit(1)).alias("affected"))
    out = read.join(hit, "new_id", "left").select("new_id", "scanned", F.coalesce("affected", F.lit(0)).cast("long").alias("affected"))
    return out.withColumn("changed", (F.col("affected") + 1) * F.lit(K))
