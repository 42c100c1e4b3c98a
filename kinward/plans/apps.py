"""Uses of reverse neighbours: influence, outliers, clusters, mutual pairs, imbalance, two sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinward.sources.shared import cut


def influence_top(counts: DataFrame, n: int) -> DataFrame:
    """(id, n): the n points that stand in most lists."""
    return counts.orderBy(F.desc("n"), "id").limit(n)


def outliers(counts: DataFrame, most: int) -> DataFrame:
    return counts.filter(F.col("n") <= most).select("id", "n")


def mutual_neighbours(knn: DataFrame, k: int) -> DataFrame:
    """(a, b): each in the other's list."""
    near = knn.filter(F.col("rank") <= k)
    x = near.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    return x.intersect(near.select(F.col("dst").alias("a"), F.col("src").alias("b"))).filter("a < b")


def density_components(knn: DataFrame, counts: DataFrame, k: int, least: int) -> DataFrame:
    """(id, cluster): core points joined by mutual edges; the cluster is its least id. Rounds go on until no label moves."""
    core = counts.filter(F.col("n") >= least).select("id")
    edges = mutual_neighbours(knn, k)
    edges = edges.join(core.select(F.col("id").alias("a")), "a", "left_semi").join(core.select(F.col("id").alias("b")), "b", "left_semi")
    both = cut(edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))))
    label = cut(core.select("id", F.col("id").alias("cluster")))
    while True:
        offer = both.join(label.select(F.col("id").alias("b"), "cluster"), "b").groupBy(F.col("a").alias("id")).agg(F.min("cluster").alias("o"))
        moved = label.join(offer, "id", "left").select("id", F.least("cluster", F.coalesce("o", "cluster")).alias("c1"), "cluster")
        # a label is itself a point: jump to that point's label
        jump = moved.select(F.col("id").alias("c1"), F.col("c1").alias("c2"))
        after = cut(moved.join(jump, "c1", "left").select("id", F.least("c1", F.coalesce("c2", "c1")).alias("cluster"), F.col("cluster").alias("was")))
        changed = after.filter("cluster <> was").limit(1).count()
        label = after.select("id", "cluster")
        if not changed:
            break
    return label


def imbalance_points(rev: DataFrame, labels: DataFrame, k: int, minority: int) -> DataFrame:
    """(id, same, other): minority points most of whose reverse neighbours are of other classes."""
    near = rev.filter(F.col("rank") <= k).select(F.col("dst").alias("id"), F.col("src").alias("o"))
    mine = labels.filter(F.col("label") == minority).select("id")
    lab = labels.select(F.col("id").alias("o"), "label")
    c = near.join(mine, "id").join(lab, "o").groupBy("id").agg(
        F.count_if(F.col("label") == minority).alias("same"), F.count_if(F.col("label") != minority).alias("other")
    )
    return c.filter("other > same")


def facility_two_sets(suppliers: DataFrame, customers: DataFrame, k: int) -> DataFrame:
    """(s_id, n): for each supplier, customers of its region that have it among their k nearest by balance.

    A customer's k nearest lie within k places of its own place in the sorted balances of the
    region, so places are compared, not pairs of all.
    """
    s = suppliers.select("region", F.col("id").alias("s_id"), F.col("cents").alias("sc"), F.lit(0).alias("kind"))
    rank = F.row_number().over(Window.partitionBy("region").orderBy("sc", "s_id"))
    placed = s.withColumn("place", rank).select("region", "s_id", "sc", "place")
    both = customers.select("region", F.col("id").alias("c_id"), F.col("cents").alias("v"), F.lit(1).alias("kind")).unionByName(
        placed.select("region", F.col("s_id").alias("c_id"), F.col("sc").alias("v"), F.lit(0).alias("kind"))
    )
    before = F.sum(F.when(F.col("kind") == 0, 1).otherwise(0)).over(
        Window.partitionBy("region").orderBy("v", "kind", "c_id").rowsBetween(Window.unboundedPreceding, 0)
    )
    at = both.withColumn("at", before).filter("kind = 1").select("region", "c_id", F.col("v").alias("cc"), "at")
    reach = at.withColumn("place", F.explode(F.sequence(F.col("at") - k, F.col("at") + k + 1)))
    near = reach.join(placed, ["region", "place"]).withColumn("gap", F.abs(F.col("cc") - F.col("sc")))
    best = near.withColumn("r", F.row_number().over(Window.partitionBy("region", "c_id").orderBy("gap", "s_id"))).filter(F.col("r") <= k)
    return placed.select("s_id").join(best.groupBy("s_id").agg(F.count(F.lit(1)).alias("n")), "s_id", "left").select(
        "s_id", F.coalesce("n", F.lit(0)).cast("long").alias("n")
    )


def chunk_influence(near: DataFrame) -> DataFrame:
    """(id, n): documents by the number of outside questions whose nearest hold them."""
    return near.groupBy("id").agg(F.count_distinct("qid").alias("n"))
