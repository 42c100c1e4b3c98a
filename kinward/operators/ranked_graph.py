"""Refinement of a ranked neighbour graph: neighbours of neighbours get to know each other.

Every round a point's forward and reverse neighbours meet at it (sampled, new ones first); the
kernel compares only pairs with a new member and passes on those that would enter a list; the best
K of old and new stay. A round ends the loop
if nothing changed, if changes fall under ``delta`` of all entries, or at ``max_iters``.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.functions.vectors import l2
from kinward.operators import exact as exact_graph
from kinward.sources.shared import cut


def top_k(edges: DataFrame, K: int) -> DataFrame:
    """(src, rank, dst, dist, ...) of the K best distinct edges of every source."""
    rank = F.row_number().over(Window.partitionBy("src").orderBy("dist", "dst"))
    return edges.withColumn("rank", rank).filter(F.col("rank") <= K)


def with_distance(pairs: DataFrame, points: DataFrame) -> DataFrame:
    """(src, dst, dist) of id pairs."""
    a = points.select(F.col("id").alias("src"), F.col("vec").alias("a"))
    b = points.select(F.col("id").alias("dst"), F.col("vec").alias("b"))
    return pairs.join(a, "src").join(b, "dst").select("src", "dst", l2(F.col("a"), F.col("b")).alias("dist"))


def seed_random(points: DataFrame, K: int, seed: int = 7) -> DataFrame:
    """A start of K drawn neighbours a point: ring positions in hash order, the same on every run."""
    n = points.count()
    blocks = max(1, n // 4096)
    ring = points.select("id", F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(blocks)).alias("b"))
    order = Window.partitionBy("b").orderBy(F.xxhash64("id", F.lit(seed + 1)))
    ring = ring.withColumn("pos", F.row_number().over(order)).withColumn("size", F.count(F.lit(1)).over(Window.partitionBy("b")))
    steps = F.explode(F.sequence(F.lit(1), F.lit(K))).alias("step")
    ask = ring.select("id", "b", "pos", "size", steps).select(F.col("id").alias("src"), "b", ((F.col("pos") - 1 + F.col("step")) % F.col("size") + 1).alias("pos"))
    pairs = ask.join(ring.select("b", "pos", F.col("id").alias("dst")), ["b", "pos"]).filter("src <> dst").select("src", "dst").distinct()
    return top_k(with_distance(pairs, points), K).select("src", "rank", "dst", "dist")


def seed_from_nav(seeds: DataFrame, K: int) -> DataFrame:
    """A start from what insertion into the nav graph met, offered in both directions."""
    both = seeds.select("src", "dst", "dist").unionByName(seeds.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist"))
    return top_k(both.filter("src <> dst").groupBy("src", "dst").agg(F.min("dist").alias("dist")), K).select("src", "rank", "dst", "dist")


def seed_mixed(points: DataFrame, seeds: DataFrame, K: int, share: float = 0.2) -> DataFrame:
    """Seeds of several cells, which know no neighbour beyond their cell, with a share of each list drawn from all points."""
    drawn = max(2, int(K * share))
    far = seed_random(points, drawn).select("src", "dst", "dist")
    near = seed_from_nav(seeds, max(1, K - drawn)).select("src", "dst", "dist")
    return top_k(near.unionByName(far).groupBy("src", "dst").agg(F.min("dist").alias("dist")), K).select("src", "rank", "dst", "dist")


def _pairs(ids: np.ndarray, new: np.ndarray, x: np.ndarray, far: np.ndarray, K: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, distance) of members that meet, at least one of them new: K a member at most, none farther than the member's last entry."""
    d2 = vx.squared(x, x)
    np.fill_diagonal(d2, np.inf)
    d2[~(new[:, None] | new[None, :])] = np.inf
    room = vx.slack(x, x)
    keep = min(K, len(ids) - 1)
    edge = np.minimum(np.partition(d2, keep - 1, axis=1)[:, keep - 1], far * far * (1 + 1e-9)) + room
    i, j = np.nonzero((d2 <= edge[:, None]) & np.isfinite(d2))
    d = vx.direct(x[i], x[j])
    ok = d <= far[i] * (1 + exact_graph.ROUNDING)
    return i[ok], j[ok], d[ok]


def _meet(frame: pd.DataFrame, K: int) -> pd.DataFrame:
    frame = frame.sort_values("member")
    ids, new = frame["member"].to_numpy(), frame["is_new"].to_numpy()
    if len(ids) < 2 or not new.any():
        return pd.DataFrame({"src": [], "dst": [], "dist": []})
    i, j, d = _pairs(ids, new, vx.matrix(frame["vec"]), frame["far"].to_numpy(), K)
    return pd.DataFrame({"src": ids[i], "dst": ids[j], "dist": d})


def _meetings(batches: Iterator[pa.RecordBatch], block: exact_graph.Block, far: np.ndarray, known: np.ndarray | None, K: int) -> Iterator[pa.RecordBatch]:
    """``_meet`` of rows that come sorted by their meeting point, with vectors, last distances and known entries by row of the block."""
    n, rest = len(block.qid), None

    def groups(o: np.ndarray, at: np.ndarray, new: np.ndarray) -> Iterator[pa.RecordBatch]:
        out, ends = [], np.flatnonzero(np.diff(o)) + 1
        for lo, hi in zip(np.r_[0, ends], np.r_[ends, len(o)]):
            rows, fresh = at[lo:hi], new[lo:hi]
            if hi - lo < 2 or not fresh.any():
                continue
            order = np.argsort(rows)
            rows, fresh = rows[order], fresh[order]
            i, j, d = _pairs(rows, fresh, block.q[rows].astype(np.float64), far[rows], K)
            out.append((rows[i], rows[j], d))
        if out:
            i, j, d = (np.concatenate(c) for c in zip(*out))
            if known is not None and len(known):
                code = i * n + j
                ok = known[np.minimum(np.searchsorted(known, code), len(known) - 1)] != code
                i, j, d = i[ok], j[ok], d[ok]
            best = pd.DataFrame({"i": i, "j": j, "d": d}).groupby(["i", "j"], as_index=False)["d"].min()
            cols = [pa.array(block.qid[best["i"].to_numpy()]), pa.array(block.qid[best["j"].to_numpy()]), pa.array(best["d"].to_numpy())]
            yield pa.RecordBatch.from_arrays(cols, ["src", "dst", "dist"])

    for b in batches:
        if not b.num_rows:
            continue
        o, member, new = (b.column(c).to_numpy(zero_copy_only=False) for c in ("o", "member", "is_new"))
        cols = o, np.searchsorted(block.qid, member), new
        if rest is not None:
            cols = tuple(np.concatenate(c) for c in zip(rest, cols))
        last = int(np.searchsorted(cols[0], cols[0][-1]))
        rest = tuple(c[last:] for c in cols)
        yield from groups(*(c[:last] for c in cols))
    if rest is not None:
        yield from groups(*rest)


def _held(knn: DataFrame, ids: np.ndarray, K: int) -> tuple[np.ndarray, np.ndarray | None]:
    """Last distance of every id's list (infinite for shorter lists), and the entries as sorted codes if they fit a block."""
    ends = knn.groupBy("src").agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("far")).toPandas()  # a row a shared vector
    far = np.full(len(ids), np.inf)
    full = ends[ends["n"] >= K]
    far[np.searchsorted(ids, full["src"].to_numpy())] = full["far"].to_numpy()
    if 8 * len(ids) * K > exact_graph.QUERY_BLOCK:
        return far, None
    held = knn.select("src", "dst").toArrow()  # of a checked size
    src, dst = (np.searchsorted(ids, held.column(c).to_numpy()) for c in ("src", "dst"))
    return far, np.sort(src * len(ids) + dst)


def refine(
    points: DataFrame, seeds: DataFrame, K: int, max_iters: int = 8, delta: float = 0.001, sample: int | None = None,
    exact: DataFrame | None = None, k_recall: int = 10,
) -> tuple[DataFrame, list[dict]]:
    """The refined graph and a log of its rounds (seconds, changes, recall where ``exact`` is given). Seeds may say which of them are new (``is_new``)."""
    from kinward.operators.measures import graph_recall

    n = points.count()
    S = sample or K
    block = exact_graph.shared_block(points)  # vectors travel once; a round then shuffles ids only
    if block is not None:
        sent = points.sparkSession.sparkContext.broadcast(block)
    session = points.sparkSession
    parts = max(int(session.conf.get("spark.sql.shuffle.partitions")), 2 * session.sparkContext.defaultParallelism)
    flag = F.col("is_new") if "is_new" in seeds.columns else F.lit(True)
    knn = cut(seeds.select("src", "rank", "dst", "dist", flag.alias("is_new")))
    log = []
    if exact is not None:
        log.append({"round": 0, "seconds": 0.0, "changed": 0, "recall": graph_recall(knn, exact, k_recall).first()[0]})
    began = time.time()
    for r in range(1, max_iters + 1):
        by = lambda key: F.row_number().over(Window.partitionBy(key).orderBy(F.desc("is_new"), F.xxhash64("src", "dst", F.lit(r))))
        fore = knn.withColumn("s", by("src")).filter(F.col("s") <= S).select(F.col("src").alias("o"), F.col("dst").alias("member"), "is_new")
        back = knn.withColumn("s", by("dst")).filter(F.col("s") <= S).select(F.col("dst").alias("o"), F.col("src").alias("member"), "is_new")
        own = points.select(F.col("id").alias("o"), F.col("id").alias("member"), F.lit(False).alias("is_new"))
        every = fore.unionByName(back).unionByName(own).repartition(parts, "o")  # the count keeps small meetings on all cores
        members = every.groupBy("o", "member").agg(F.max("is_new").alias("is_new"))
        if block is None:
            far = knn.groupBy(F.col("src").alias("member")).agg(F.when(F.count(F.lit(1)) >= K, F.max("dist")).alias("far"))
            held = members.join(points.select(F.col("id").alias("member"), "vec"), "member").join(far, "member", "left")
            held = held.withColumn("far", F.coalesce("far", F.lit(float("inf"))))
            met = held.groupBy("o").applyInPandas(lambda f: _meet(f, K), "src long, dst long, dist double")
        else:
            told = session.sparkContext.broadcast(_held(knn, block.qid, K))
            met = members.sortWithinPartitions("o").mapInArrow(
                lambda batches, told=told: _meetings(batches, sent.value, *told.value, K), "src long, dst long, dist double"
            )
        old = knn.select("src", "dst", "dist", F.lit(False).alias("is_new"))
        fresh = met.groupBy("src", "dst").agg(F.min("dist").alias("dist")).join(old.select("src", "dst"), ["src", "dst"], "left_anti")
        knn = cut(top_k(old.unionByName(fresh.withColumn("is_new", F.lit(True))), K).select("src", "rank", "dst", "dist", "is_new"))
        changed = knn.filter("is_new").count()
        entry = {"round": r, "seconds": time.time() - began, "changed": changed}
        if exact is not None:
            entry["recall"] = graph_recall(knn, exact, k_recall).first()[0]
        log.append(entry)
        if changed == 0 or changed <= delta * n * K:
            break
    return knn.select("src", "rank", "dst", "dist"), log
