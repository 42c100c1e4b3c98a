"""Baselines that expand from the query and verify: one shot, incremental, hop by hop.

What the published texts leave open in the incremental and hop methods follows the public
literature on reverse-neighbour search: witness counts, the early-acceptance rule, a stop by
dimension test, and relative-neighbourhood pruning.
"""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.functions.vectors import l2
from kinward.operators import exact, proxy
from kinward.sources.shared import cut


def filter_verify(candidates: Callable[[], DataFrame], check: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """The frame that all of these share."""
    return check(candidates())


def as_candidates(near: DataFrame) -> DataFrame:
    return near.select("qid", "id", F.col("pdist").alias("low"), F.col("pdist").alias("high"))


def one_shot_rknn(queries: DataFrame, points: DataFrame, k: int, k_prime: int, radii: DataFrame | None = None, proxies: DataFrame | None = None) -> DataFrame:
    """(qid, id, dist): the k' nearest points are candidates; verified online, or by given radii."""
    near = proxy.flat_proxies(queries, points, k_prime) if proxies is None else proxies
    if radii is None:
        return filter_verify(lambda: as_candidates(near), lambda c: proxy.online_radius_rknn(c, queries, points, k))
    return filter_verify(lambda: as_candidates(near), lambda c: proxy.verify(c, queries, points, radii, k))


def local_elimination(near: DataFrame, points: DataFrame, k: int) -> DataFrame:
    """Candidates with fewer than k other candidates nearer to them than the query."""
    held = near.join(points.select("id", "vec"), "id").select("qid", "id", "pdist", "vec")
    other = held.select("qid", F.col("id").alias("oid"), F.col("vec").alias("ovec"))
    pairs = held.join(other, "qid").filter("id <> oid")
    nearer = pairs.filter(l2(F.col("vec"), F.col("ovec")) < F.col("pdist")).groupBy("qid", "id").agg(F.count(F.lit(1)).alias("w"))
    return near.join(nearer, ["qid", "id"], "left").filter(F.coalesce("w", F.lit(0)) < k).select("qid", "id", "prank", "pdist")


def _pull(ids: np.ndarray, d: np.ndarray, x: np.ndarray, k: int, t: float, lean: bool) -> tuple[np.ndarray, np.ndarray, bool]:
    """Of one query's sorted stream: rows that survive witness counting, those that need no verification, and whether the test stopped it."""
    hold, n_held, seen = np.zeros(len(ids), np.int64), 0, 0
    witness, sure = np.zeros(len(ids), int), np.zeros(len(ids), bool)
    bound, stopped, lo, block, room = np.inf, False, 0, np.zeros((0, 0)), vx.slack(x, x)

    def nearer(rows: np.ndarray, v: int, d2: np.ndarray, than: np.ndarray) -> np.ndarray:
        """Which of the rows are nearer to v than given; summed anew where rounding could decide."""
        gap = d2 - than * than
        out, close = gap < 0, np.flatnonzero(np.abs(gap) <= room)
        if len(close):
            out[close] = vx.direct(x[rows[close]], np.broadcast_to(x[v], (len(close), x.shape[1]))) < than[close]
        return out

    every = np.arange(len(ids))
    for v in range(len(ids)):
        if d[v] > bound:
            stopped = True
            break
        if v == lo + len(block):
            lo = v
            block = vx.squared(x[lo : lo + AHEAD], x[: lo + AHEAD])
        seen += 1
        if v:
            h, apart = hold[:n_held], block[v - lo, :v]
            witness[h] += nearer(h, v, apart[h], d[h])
            witness[v] = int(nearer(every[:v], v, apart, np.full(v, d[v])).sum())  # pruned ones count too, or acceptance would be unsound
            sure[h] |= (witness[h] < k) & (d[v] >= 2 * d[h])
        if not lean or witness[v] < k:
            hold[n_held] = v
            n_held += 1
        if seen > k:
            ratio = (seen / k) ** (1 / t) - 1
            if ratio > 0:
                bound = min(bound, d[v] / ratio)
    kept = hold[:n_held]
    kept = kept[witness[kept] < k]
    return kept, sure[kept], stopped


AHEAD = 128  # members whose distances to all before them are computed at once
PULLED = "qid long, stopped boolean, id long, pdist double, sure boolean"


def _row(qid: int, ids: np.ndarray, d: np.ndarray, sure: np.ndarray, stopped: bool) -> pd.DataFrame:
    """A query's survivors; a row without id where there is none."""
    if not len(ids):
        return pd.DataFrame({"qid": [qid], "stopped": [stopped], "id": pd.array([None], "Int64"), "pdist": [0.0], "sure": [False]})
    return pd.DataFrame({"qid": qid, "stopped": stopped, "id": pd.array(ids, "Int64"), "pdist": d, "sure": sure})


def _pulled(stream: DataFrame, k: int, t: float, lean: bool) -> DataFrame:
    """(qid, stopped, id, pdist, sure) of every query's neighbours with their vectors."""

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["pdist", "id"])
        ids, d = frame["id"].to_numpy(), frame["pdist"].to_numpy()
        kept, sure, stopped = _pull(ids, d, vx.matrix(frame["vec"]), k, t, lean)
        return _row(frame["qid"].iloc[0], ids[kept], d[kept], sure, stopped)

    return stream.groupBy("qid").applyInPandas(one, PULLED)


def _pulled_beside(queries: DataFrame, block: exact.Block, k: int, t: float, max_pull: int, lean: bool) -> DataFrame:
    """``_pulled`` of queries that are dealt to tasks which hold all members, so that nothing but survivors leaves a task."""
    session = queries.sparkSession
    sent = session.sparkContext.broadcast(block)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, x = sent.value.qid, sent.value.q.astype(np.float64)
        widest = x[[np.einsum("ij,ij->i", x, x).argmax()]] if len(x) else x
        for f in frames:
            for lo in range(0, len(f), 16):
                some, q = f["qid"].to_numpy()[lo : lo + 16], vx.matrix(f["vec"].iloc[lo : lo + 16])
                for qid, row in zip(some, vx.squared(q, x)):
                    row[ids == qid] = np.inf
                    members, pull = int(np.isfinite(row).sum()), max_pull
                    vec, room = q[some == qid], vx.slack(q, widest)
                    while True:
                        last = np.partition(row, pull - 1)[pull - 1] if pull < members else row[np.isfinite(row)].max(initial=0)
                        at = np.flatnonzero(row <= last + room)
                        d = vx.direct(x[at], np.broadcast_to(vec[0], (len(at), len(vec[0]))))
                        order = np.lexsort((ids[at], d))[:pull]
                        at, d = at[order], d[order]
                        kept, sure, stopped = _pull(ids[at], d, x[at], k, t, lean)
                        if stopped or pull >= members:
                            break
                        pull *= GROWTH
                    yield _row(qid, ids[at[kept]], d[kept], sure, stopped)

    parts = 4 * session.sparkContext.defaultParallelism
    return queries.select("qid", "vec").repartition(parts, "qid").mapInPandas(run, PULLED)


GROWTH = 4  # a query that was not stopped starts anew with so many times the neighbours
LOT_BYTES = 500_000_000  # vectors of pulled neighbours that are shuffled at once


def incremental_rknn(queries: DataFrame, points: DataFrame, k: int, t: float = 4.0, max_pull: int = 200, lean: bool = True) -> DataFrame:
    """(qid, id, dist): neighbours are pulled in order, pruned by witnesses, and stopped by a dimension test.

    ``max_pull`` neighbours are pulled at first; queries that the test has not stopped by then pull
    ever more, until it stops them or the members end. It fires by k * 2 ** t neighbours at the latest.
    Members of a block are held by every task; beyond it neighbours are joined with their vectors, lot by lot of the queries.
    """
    members, done, left, pull = points.count(), [], queries, max_pull
    block = exact.shared_block(points)
    if block is not None:
        done.append(cut(_pulled_beside(queries, block, k, t, max_pull, lean)))
    while block is None:
        asked, slots = left.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.max(F.size("vec")), F.lit(0)).alias("s")).first()
        lots, kept = max(1, -(-asked * min(pull, members) * 8 * slots // LOT_BYTES)), []
        for lot in range(lots):
            some = left.filter(F.pmod(F.xxhash64("qid"), F.lit(lots)) == lot)
            stream = proxy.flat_proxies(some, points, pull).join(points.select("id", "vec"), "id")
            kept.append(cut(_pulled(stream, k, t, lean)))
        kept = functools.reduce(DataFrame.unionByName, kept)
        if pull >= members:
            done.append(kept)
            break
        done.append(kept.filter("stopped"))
        left = cut(left.join(kept.filter("NOT stopped").select("qid").distinct(), "qid", "left_semi"))
        if left.isEmpty():
            break
        pull *= GROWTH
    kept = functools.reduce(DataFrame.unionByName, done).filter("id IS NOT NULL").select("qid", "id", "pdist", "sure")
    sure = kept.filter("sure").select("qid", "id", F.col("pdist").alias("dist"))
    rest = as_candidates(kept.filter("NOT sure"))
    return sure.unionByName(proxy.online_radius_rknn(rest, queries, points, k))


def build_hop_graph(knn: DataFrame, points: DataFrame, d_max: int = 80) -> DataFrame:
    """(src, dst): of each point's sorted pool, those that no kept one is nearer to; then both ways."""

    def prune(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["dist", "dst"])
        ids, d, x = frame["dst"].to_numpy(), frame["dist"].to_numpy(), vx.matrix(frame["vec"])
        kept: list[int] = []
        for v in range(len(ids)):
            if len(kept) >= d_max:
                break
            if not kept or not (np.sqrt(((x[kept] - x[v]) ** 2).sum(axis=1)) < d[v]).any():
                kept.append(v)
        return pd.DataFrame({"src": frame["src"].iloc[0], "dst": ids[kept]})

    pool = knn.join(points.select(F.col("id").alias("dst"), "vec"), "dst")
    edges = pool.select("src", "dst", "dist", "vec").groupBy("src").applyInPandas(prune, "src long, dst long")
    return edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def hop_candidates(graph: DataFrame, entries: DataFrame, hops: int) -> DataFrame:
    """(qid, id, hop): everything within some hops of each query's entry."""
    reached = cut(entries.select("qid", "id", F.lit(0).alias("hop")))
    front = reached
    for h in range(1, hops + 1):
        step = front.select("qid", F.col("id").alias("src")).join(graph, "src").select("qid", F.col("dst").alias("id")).distinct()
        front = cut(step.join(reached, ["qid", "id"], "left_anti").withColumn("hop", F.lit(h)))
        if front.isEmpty():
            break
        reached = cut(reached.unionByName(front))
    return reached


def hop_rknn(
    graph: DataFrame, queries: DataFrame, points: DataFrame, k: int, hops: int | None = None, entries: DataFrame | None = None
) -> DataFrame:
    """(qid, id, dist): expansion by ``hops`` (default k) from the nearest member, verified online.

    ``entries`` (qid, id) come from the upper layers of a hierarchy (``nav_entries``); without them a scan finds them.
    """
    entry = proxy.flat_proxies(queries, points, 1) if entries is None else entries
    entry, hops = entry.select("qid", "id"), k if hops is None else hops
    found = hop_candidates(graph, entry, hops).filter("qid <> id")
    cands = found.select("qid", "id", F.lit(0.0).alias("low"), F.lit(0.0).alias("high"))
    return filter_verify(lambda: cands, lambda c: proxy.online_radius_rknn(c, queries, points, k))


def nav_entries(index, queries: DataFrame, ef: int = 64) -> DataFrame:
    """(qid, id): each query's nearest member by greedy descent through the layers of a saved index."""
    return index.proxies(queries, 1, ef).select("qid", "id")


SMALL = 3000  # points whose exact relative-neighbour graph may be asked for


def _small(points: DataFrame) -> None:
    if points.limit(SMALL + 1).count() > SMALL:
        raise ValueError(f"the exact graph is for {SMALL} points at most; build_hop_graph serves larger sets")


def monotonic_neighbours(points: DataFrame, knn_all: DataFrame) -> DataFrame:
    """(src, dst): the hop graph over whole lists with no bound on links, for small sets only.

    If q has no link to p, one of q's links is strictly nearer to p than q is. So walks from q to p come nearer with
    every step, and p with q among its k nearest is reached in k hops. The graph of empty lunes
    (``relative_neighbours``) is a part of this one and does not hold it.
    """
    _small(points)
    return build_hop_graph(knn_all, points, SMALL)


def relative_neighbours(points: DataFrame, knn_all: DataFrame) -> DataFrame:
    """(a, b): pairs with no third point nearer to both, from whole neighbour lists; cubic, so for small sets only."""
    _small(points)
    d = knn_all.select("src", "dst", "dist")
    pair = d.filter("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"), "dist")
    to_a = d.select(F.col("src").alias("a"), F.col("dst").alias("c"), F.col("dist").alias("ac"))
    to_b = d.select(F.col("src").alias("b"), F.col("dst").alias("c"), F.col("dist").alias("bc"))
    blocked = pair.join(to_a, "a").filter("ac < dist").join(to_b, ["b", "c"]).filter("bc < dist").select("a", "b").distinct()
    return pair.join(blocked, ["a", "b"], "left_anti").select("a", "b")
