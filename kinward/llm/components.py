"""Connected components of an edge table by alternating star contractions.

Every round joins edges to the least neighbour of their ends, first on the larger side, then on
the smaller one; the edge set shrinks to stars in a logarithmic number of rounds. No adjacency list
is collected, and only two numbers a round reach the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinward.llm.exchange import cut


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


EDGES = 200_000  # of a partition


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node with an edge; the root is the least node. Edges are (a, b).

    Rounds go on until the stars stand still, however many that takes. Few edges are gathered in few
    partitions, as every exchange of a round leaves files for each of its tasks.
    """
    stars = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct())
    state = _state(stars)
    while state[0]:
        few = 8 + state[0] // EDGES
        stars = stars.coalesce(few)
        both = stars.unionByName(stars.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")).coalesce(few)
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).coalesce(few)
        least = large.groupBy("a").agg(F.min("b").alias("m")).coalesce(few)
        joined = large.join(least, "a").coalesce(few)
        small = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        stars = cut(small.filter("a <> b").distinct().coalesce(few))
        after = _state(stars)
        if after == state:
            break
        state = after
    roots = stars.select("a", F.col("b").alias("root")).groupBy("a").agg(F.min("root").alias("root"))
    return roots.select(F.col("a").alias("node"), "root").unionByName(
        stars.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct()
    )
