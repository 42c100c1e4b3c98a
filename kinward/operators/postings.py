"""Reverse postings: who holds a point in its list, and at which rank."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def transpose(knn: DataFrame) -> DataFrame:
    """(dst, rank, src, dist), sorted by rank within each point's postings."""
    return knn.select("dst", "rank", "src", "dist").repartition("dst").sortWithinPartitions("dst", "rank", "src")


def scan(rev: DataFrame, ids: DataFrame, theta: int) -> DataFrame:
    """Postings up to a rank of the asked points; the rank bound reaches the file scan."""
    return rev.filter(F.col("rank") <= theta).join(ids.select(F.col("id").alias("dst")), "dst")


def pack(rev: DataFrame) -> DataFrame:
    """(dst, n, items): one row a point, its postings as an array sorted by rank and owner."""
    return rev.groupBy("dst").agg(
        F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_list(F.struct("rank", "src"))).alias("items")
    )


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("dst", F.explode("items").alias("x")).select("dst", "x.rank", "x.src")


def by_owner(rev: DataFrame, theta: int) -> DataFrame:
    """(src, dsts, dists): the postings up to a rank of every owner, by rank; its list again."""
    rows = rev.filter(F.col("rank") <= theta).groupBy("src").agg(F.sort_array(F.collect_list(F.struct("rank", "dst", "dist"))).alias("l"))
    return rows.select("src", F.col("l.dst").alias("dsts"), F.col("l.dist").alias("dists"))


def salted_scan(rev: DataFrame, proxies: DataFrame, theta: int, span: int = 64) -> DataFrame:
    """``scan`` for proxies with hub postings: both sides carry the rank block as a salt."""
    salt = F.floor((F.col("rank") - 1) / span).cast("int")
    blocks = F.explode(F.sequence(F.lit(0), F.lit((theta - 1) // span))).alias("salt")
    left = proxies.select("*", blocks)
    right = rev.filter(F.col("rank") <= theta).withColumn("salt", salt)
    return left.join(right, (left["id"] == right["dst"]) & (left["salt"] == right["salt"])).drop(right["salt"]).drop("salt")


def occurrence(rev: DataFrame, points: DataFrame, k: int) -> DataFrame:
    """(id, n): in how many k-lists a point stands, zeros included."""
    counts = rev.filter(F.col("rank") <= k).groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("n"))
    return points.select("id").join(counts, "id", "left").select("id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def occurrence_profile(rev: DataFrame, points: DataFrame, ks: list[int]) -> DataFrame:
    """(k, most, zero, median) of the occurrence counts, all k from one count a point."""
    held = rev.filter(F.col("rank") <= max(ks)).groupBy(F.col("dst").alias("id")).agg(*[F.count_if(F.col("rank") <= k).alias(f"n{k}") for k in ks])
    every = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.coalesce(f"n{k}", F.lit(0)).cast("long").alias("n")) for k in ks])).alias("x")
    counts = points.select("id").join(held, "id", "left").select(every).select("x.k", "x.n")
    return counts.groupBy("k").agg(
        F.max("n").alias("most"), F.count_if(F.col("n") == 0).alias("zero"),
        F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY n)").cast("long").alias("median"),
    )
