"""Exact neighbours, k-radii, reverse neighbours and the exact ranked graph.

Queries that fit one block of a checked size travel with the scan of the points, which then stay in
their partitions; more of them are dealt into blocks as rows and meet blocks of points, so that the
driver never holds more than one block. In the all-pairs graph a task holds the lists of one stripe of
points while all points pass by, packed. It is the truth to measure against; its work is quadratic,
and indexes are built by refinement instead.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.sources.shared import cut

QUERY_BLOCK = 50_000_000  # bytes of vectors in a block

#: Relative difference that two ways of summing one distance may show; a query that is a member sits
#: exactly on the radius of those that hold it as their k-th neighbour.
ROUNDING = 1e-12

KNN = "src long, rank int, dst long, dist double"


@dataclass
class Block:
    """Queries: ids, matrix, and further columns by name."""

    qid: np.ndarray
    q: np.ndarray
    more: dict[str, np.ndarray]

    @staticmethod
    def of(rows: pd.DataFrame, extra: tuple[str, ...]) -> Block:
        rows = rows.sort_values("qid")
        return Block(rows["qid"].to_numpy(), vx.matrix(rows["vec"]), {c: rows[c].to_numpy() for c in extra})


def shared_block(points: DataFrame) -> Block | None:
    """All points as a block in the narrowest floats that hold them, if it fits ``QUERY_BLOCK``; for tasks that need any point."""
    single = F.forall("vec", lambda x: x == x.cast("float").cast("double"))
    size = points.agg(F.count(F.lit(1)).alias("n"), F.sum(F.size("vec").cast("long")).alias("slots"), F.min(single).alias("single")).first()
    if (4 if size.single else 8) * (size.slots or 0) + 8 * size.n > QUERY_BLOCK:
        return None
    block = Block.of(points.select(F.col("id").alias("qid"), "vec").toPandas(), ())  # of a checked size
    block.q = block.q.astype(np.float32 if size.single else np.float64)
    return block


def against(
    queries: DataFrame, points: DataFrame, kernel: Callable[[Block, Iterator[pd.DataFrame]], Iterator[pd.DataFrame]], schema: str,
    extra: tuple[str, ...] = (), block_bytes: int | None = None,
) -> DataFrame:
    """What ``kernel`` gives for all queries against every part of the points, whose frames it gets one by one. Queries: qid, vec and ``extra``."""
    limit = block_bytes or QUERY_BLOCK
    asked = queries.select("qid", "vec", *extra)
    slots = F.size("vec").cast("long") + 2
    for c in extra:
        if dict(asked.dtypes)[c].startswith("array"):
            slots = slots + F.size(c)
    total = asked.agg(F.sum(slots * 8).alias("b")).first().b or 0
    if not total:
        return points.sparkSession.createDataFrame([], schema)
    if total <= limit:
        block = Block.of(asked.toPandas(), extra)  # of a checked size
        # a part gives a row or more a query, so parts are no more than keep the cores busy
        return points.coalesce(2 * points.sparkSession.sparkContext.defaultParallelism).mapInPandas(lambda frames: kernel(block, (f for f in frames if len(f))), schema)
    held = points.agg(F.sum((F.size("vec").cast("long") + 2) * 8).alias("b")).first().b or 0
    nq, np_ = -(-total // limit), max(1, -(-held // limit))
    to = lambda df, key, mine, n, other, m: df.withColumn(mine, F.pmod(F.xxhash64(key), F.lit(n)).cast("int")).withColumn(
        other, F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    )
    asked = asked.select(*[F.col(c).alias(c) for c in asked.columns])  # queries may come from the points themselves
    left = to(asked, "qid", "kw_i", nq, "kw_j", np_).groupBy("kw_i", "kw_j")
    right = to(points, "id", "kw_j", np_, "kw_i", nq).groupBy("kw_i", "kw_j")
    names = [f.split()[0] for f in schema.split(", ")]

    def meet(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out = list(kernel(Block.of(a, extra), iter([b]))) if len(a) and len(b) else []
        return pd.concat(out) if out else pd.DataFrame({c: [] for c in names})

    return left.cogroup(right).applyInPandas(meet, schema)


def beside(queries: DataFrame, points: DataFrame, vec: str, block_bytes: int | None = None) -> DataFrame:
    """Rows of a query set (vectors in ``vec``) beside all points, for functions over pairs of columns.

    A set of one block is broadcast; a larger one meets the points block by block, as rows of an equi-join.
    """
    limit = block_bytes or QUERY_BLOCK
    total = queries.agg(F.sum((F.size(vec).cast("long") + 2) * 8).alias("b")).first().b or 0
    if total <= limit:
        return points.join(F.broadcast(queries))  # of a checked size
    nq, np_ = -(-total // limit), int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    to = lambda df, mine, n, other, m: df.withColumn(mine, F.pmod(F.xxhash64(*df.columns), F.lit(n)).cast("int")).withColumn(
        other, F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    )
    left = to(points, "kw_j", np_, "kw_i", nq)
    return left.join(to(queries, "kw_i", nq, "kw_j", np_).hint("merge"), ["kw_i", "kw_j"]).drop("kw_i", "kw_j")


def exact_knn(queries: DataFrame, points: DataFrame, k: int, exclude_self: bool = False, block_bytes: int | None = None) -> DataFrame:
    """(qid, rank, id, dist): the k nearest points of every query, ties by id."""

    def near(block: Block, frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        few, later = 0 < block.q.shape[1] <= FEW, []
        order = _by_place(block.q) if few else np.arange(len(block.qid))
        best = _Nearest(block.qid[order], _narrow(block.q[order]), k, exclude_self)
        for f in frames:
            ids, p = f["id"].to_numpy(), _narrow(vx.matrix(f["vec"]))
            if few:
                later.append((ids, p))
                if sum(len(x[0]) for x in later) >= GROUP:
                    best.meet_near(*(np.concatenate(x) for x in zip(*later)))
                    later.clear()
                continue
            for lo in range(0, len(ids), TILE):
                best.meet(ids[lo : lo + TILE], p[lo : lo + TILE])
        if later:
            best.meet_near(*(np.concatenate(x) for x in zip(*later)))
        yield from best.rows()

    found = against(queries, points.select("id", "vec"), near, "qid long, id long, dist double", block_bytes=block_bytes)
    rank = F.row_number().over(Window.partitionBy("qid").orderBy("dist", "id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("qid", "rank", "id", "dist")


def ranks_of(pairs: DataFrame, queries: DataFrame, points: DataFrame, block_bytes: int | None = None) -> DataFrame:
    """(qid, id, rank): where each (qid, id, dist) stands in the query's own order, by counting the members before it."""
    lists = pairs.groupBy("qid").agg(F.sort_array(F.collect_list(F.struct("dist", "id"))).alias("l"))
    asked = queries.join(lists, "qid").select("qid", "vec", F.col("l.dist").alias("ds"), F.col("l.id").alias("os"))

    def count(block: Block, frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n = [np.zeros(len(ds), np.int64) for ds in block.more["ds"]]
        most = np.array([np.max(ds) for ds in block.more["ds"]])
        for f in frames:
            ids, p = f["id"].to_numpy(), vx.matrix(f["vec"])
            room = vx.slack(block.q, p)
            edge = most * most * (1 + 1e-9) + room
            for lo in range(0, len(block.q), 256):
                d2 = vx.squared(block.q[lo : lo + 256], p)
                for i, row in enumerate(d2, lo):
                    at = np.flatnonzero((row <= edge[i]) & (ids != block.qid[i]))
                    near = row[at]
                    ordered = np.sort(near)
                    for x, (d, o) in enumerate(zip(block.more["ds"][i], block.more["os"][i])):
                        width = room + d * d * 1e-9
                        n[i][x] += np.searchsorted(ordered, d * d - width)
                        close = at[np.abs(near - d * d) <= width]
                        if len(close):
                            true = vx.direct(np.repeat(block.q[i : i + 1], len(close), axis=0), p[close])
                            n[i][x] += ((true < d) | ((true == d) & (ids[close] < o))).sum()
        if len(n):
            sizes = [len(x) for x in n]
            yield pd.DataFrame({"qid": np.repeat(block.qid, sizes), "id": np.concatenate(list(block.more["os"])), "n": np.concatenate(n)})

    counted = against(asked, points.select("id", "vec"), count, "qid long, id long, n long", ("ds", "os"), block_bytes)
    return counted.groupBy("qid", "id").agg((F.sum("n") + 1).cast("int").alias("rank"))


LIST_BYTES, STRIPE, CHUNK, TILE = 220_000_000, 100_000, 1024, 4096  # a stripe's lists and points; rows of two sides compared at once
FEW, GROUP = 8, 65_536  # slots up to which rows are compared by place; rows that are put in order of place at once
_EXACT = 2.0**24  # whole numbers up to here are exact in float32
LISTS = "src long, dsts array<long>, dists array<double>"


def _slots(x: np.ndarray) -> tuple[str, bytes]:
    """A matrix by the narrowest slots that hold it without loss; 16-bit ones as two planes of bytes, which compress."""
    if np.abs(x).max(initial=0) < 32768 and (x == np.rint(x)).all():
        return "i2", x.astype("<i2").view(np.uint8).reshape(-1, 2).T.tobytes()
    narrow = x.astype("<f4")
    return ("f4", narrow.tobytes()) if (narrow == x).all() else ("f8", x.astype("<f8").tobytes())


def _unslotted(kind: str, data: bytes, n: int) -> np.ndarray:
    if kind == "i2":
        flat = np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(2, -1).T).view("<i2")
        return flat.reshape(n, -1).astype(np.float32)
    flat = np.frombuffer(data, "<" + kind).reshape(n, -1)
    return flat.astype(np.float64)


def _narrow(x: np.ndarray) -> np.ndarray:
    """The matrix in float32 if its slots are small whole numbers."""
    return x.astype(np.float32) if np.abs(x).max(initial=0) < 32768 and (x == np.rint(x)).all() else x


def _widest(q: np.ndarray, p: np.ndarray) -> float:
    """Bound on all parts of a sum that makes a squared distance."""
    norm = lambda x: np.sqrt((x.astype(np.float64) ** 2).sum(1).max(initial=0))
    return float((norm(q) + norm(p)) ** 2)


def _by_place(x: np.ndarray) -> np.ndarray:
    """An order of the rows in which runs of ``CHUNK`` lie close together: halves along the widest slot, again and again."""
    order, parts = np.arange(len(x)), [(0, len(x))]
    while parts:
        lo, hi = parts.pop()
        if hi - lo <= CHUNK:
            continue
        mine = x[order[lo:hi]]
        half = CHUNK * -(-(hi - lo) // (2 * CHUNK))
        slot = mine[:, np.ptp(mine, axis=0).argmax()]
        order[lo:hi] = order[lo:hi][np.argpartition(slot, half - 1)]
        parts += [(lo, lo + half), (lo + half, hi)]
    return order


def _boxes(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least and greatest slots of every ``CHUNK`` rows."""
    at = np.arange(0, len(x), CHUNK)
    x = x.astype(np.float64)
    return np.minimum.reduceat(x, at, axis=0), np.maximum.reduceat(x, at, axis=0)


class _Nearest:
    """The K nearest of some rows among blocks that come one by one; hits are gathered, then cut to K by distance and id."""

    def __init__(self, ids: np.ndarray, q: np.ndarray, K: int, drop_self: bool = True):
        self.ids, self.q, self.K, self.drop_self, n = ids, q, K, drop_self, len(ids)
        self.whole, self.norm = q.dtype == np.float32, (q.astype(np.float64) ** 2).sum(1)
        self.left = np.concatenate([-2 * q, np.ones((n, 1), q.dtype)], axis=1)
        parts = range(0, n, CHUNK)
        self.edge, self.last = np.full(n, np.inf), np.full(n, np.iinfo(np.int64).max)
        self.far = np.full(len(parts), np.inf)  # the greatest edge of a chunk
        self.low, self.high = _boxes(q) if n else (q, q)
        self.kept = [(np.zeros(0, np.int32), np.zeros(0), np.zeros(0, np.int64)) for _ in parts]
        self.wait: list[list] = [[] for _ in parts]
        self.held = [0] * len(parts)

    def meet(self, ids: np.ndarray, p: np.ndarray) -> None:
        side = self._side(ids, p)
        for c in range(len(self.far)):
            self._met(c, *side)

    def meet_near(self, ids: np.ndarray, p: np.ndarray) -> None:
        """As ``meet``, for rows of few slots: every chunk takes tiles by their distance and ends where they lie beyond all its edges."""
        if not len(ids):
            return
        order = _by_place(p)
        ids, p = ids[order], p[order]
        low, high = _boxes(p)
        sides: list = [None] * len(low)
        for c in range(len(self.far)):
            gap, mid = self._gap(c, low, high), (((low + high - self.low[c] - self.high[c]) / 2) ** 2).sum(1)
            for t in np.lexsort((mid, gap)):
                if gap[t] > self.far[c] ** 2 * (1 + 1e-9):
                    break
                if sides[t] is None:
                    sides[t] = self._side(ids[t * CHUNK : (t + 1) * CHUNK], p[t * CHUNK : (t + 1) * CHUNK])
                self._met(c, *sides[t])

    def beyond(self, p: np.ndarray) -> bool:
        """Whether no row of the block can enter any list."""
        gap = self._gap(slice(None), p.min(axis=0), p.max(axis=0))
        return bool((gap > self.far**2 * (1 + 1e-9)).all())

    def _gap(self, c, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Squared distances between boxes: no two of their rows are nearer."""
        return (np.maximum(np.maximum(low - self.high[c], self.low[c] - high), 0) ** 2).sum(-1)

    def _side(self, ids: np.ndarray, p: np.ndarray) -> tuple:
        norm = (p.astype(np.float64) ** 2).sum(1)
        exact = self.whole and p.dtype == np.float32 and (np.sqrt(self.norm.max(initial=0)) + np.sqrt(norm.max(initial=0))) ** 2 < _EXACT
        kind = np.float32 if exact else np.float64
        right = np.concatenate([p.astype(kind), norm.astype(kind)[:, None]], axis=1).T
        room = 0.0 if exact else 1e-12 * (self.norm.max(initial=0) + norm.max(initial=0)) * max(1, p.shape[1]) + 1e-300
        return ids, p, exact, kind, right, room

    def _met(self, c: int, ids: np.ndarray, p: np.ndarray, exact: bool, kind, right: np.ndarray, room: float) -> None:
        lo = c * CHUNK
        rows = slice(lo, lo + CHUNK)
        d2 = self.left[rows].astype(kind, copy=False) @ right
        edge = self.edge[rows] ** 2 * (1 if exact else 1 + 1e-12) + room - self.norm[rows]
        if exact:  # the edge is the root of a whole number
            edge = np.rint(edge)
        edge = edge.astype(kind)
        found = np.flatnonzero(d2 <= edge[:, None])
        want = self.K + 1  # the row itself may be among them
        if len(found) > 4 * want * len(d2) and want < d2.shape[1]:
            edge = np.minimum(edge, np.partition(d2, want - 1, axis=1)[:, want - 1] + kind(room))
            found = np.flatnonzero(d2 <= edge[:, None])
        if not len(found):
            return
        i, j = np.divmod(found, d2.shape[1])
        d = np.sqrt(d2.ravel()[found] + self.norm[rows][i]) if exact else vx.direct(self.q[lo + i].astype(np.float64), p[j].astype(np.float64))
        other = ids[j]
        ok = ((other != self.ids[lo + i]) | (not self.drop_self)) & ((d < self.edge[lo + i]) | (d == self.edge[lo + i]) & (other < self.last[lo + i]))
        if ok.any():
            self.wait[c].append((i[ok].astype(np.int32), d[ok], other[ok]))
            self.held[c] += int(ok.sum())
            if self.held[c] > self.K * len(d2) // 2:
                self._cut(c)

    def _cut(self, c: int) -> None:
        i, d, o = (np.concatenate(x) for x in zip(self.kept[c], *self.wait[c]))
        order = np.lexsort((o, d, i))
        i, d, o = i[order], d[order], o[order]
        n = len(self.ids[c * CHUNK : (c + 1) * CHUNK])
        begin = np.searchsorted(i, np.arange(n + 1))
        keep = np.arange(len(i)) - begin[i] < self.K
        full = begin[1:] - begin[:-1] >= self.K
        at = begin[:-1][full] + self.K - 1
        rows = c * CHUNK + np.flatnonzero(full)
        self.edge[rows], self.last[rows] = d[at], o[at]
        self.far[c] = self.edge[c * CHUNK : (c + 1) * CHUNK].max()
        self.kept[c], self.wait[c], self.held[c] = (i[keep], d[keep], o[keep]), [], 0

    def _chunks(self):
        for c, lo in enumerate(range(0, len(self.ids), CHUNK)):
            if self.wait[c]:
                self._cut(c)
            yield lo, *self.kept[c]

    def rows(self) -> Iterator[pd.DataFrame]:
        for lo, i, d, o in self._chunks():
            yield pd.DataFrame({"qid": self.ids[lo + i], "id": o, "dist": d})

    def lists(self) -> Iterator[pa.RecordBatch]:
        for lo, i, d, o in self._chunks():
            src = self.ids[lo : lo + CHUNK]
            ends = pa.array(np.searchsorted(i, np.arange(len(src) + 1)).astype(np.int32))
            some = np.diff(ends.to_numpy()) > 0
            rows = [pa.array(src), pa.ListArray.from_arrays(ends, pa.array(o)), pa.ListArray.from_arrays(ends, pa.array(d))]
            yield pa.RecordBatch.from_arrays(rows, ["src", "dsts", "dists"]).filter(pa.array(some))


def _place(points: DataFrame, dim: int) -> Column:
    """The place of a point as a number, the bits of its slots by turns; points of near numbers mostly lie close together."""
    ends = points.agg(*[f(F.col("vec")[j]).alias(f"{f.__name__}{j}") for j in range(dim) for f in (F.min, F.max)]).first() if dim else {}
    ends = [(ends[f"min{j}"], ends[f"max{j}"]) for j in range(dim)]
    wide, bits = max([hi - lo for lo, hi in ends if lo is not None] or [0]), min(16, 62 // max(1, dim))
    out = F.lit(0).cast("long")
    if not 0 < wide < float("inf"):
        return out
    for j, (lo, _) in enumerate(ends):
        step = F.floor((F.col("vec")[j] - lo) * (((1 << bits) - 1) / wide)).cast("long")
        for b in range(bits):
            out = out + F.shiftleft(F.shiftright(step, b).bitwiseAND(F.lit(1).cast("long")), b * dim + j)
    return out


def ranked_lists(points: DataFrame, K: int) -> DataFrame:
    """(src, dsts, dists): the K nearest others of every point, a row a point.

    The points are dealt into stripes by hash; a task holds one stripe with its lists and sees all points as packed
    blocks that stream by, so K entries a point leave it and nothing is merged afterwards. The blocks are written once
    to the shared folder and every task reads them there, so no copies of them are shuffled. Whole numbers that
    float32 holds exactly are compared in it; other slots are compared with room for rounding, and their hits anew.
    Points of few slots are dealt by place instead, and a stripe passes over blocks beyond the K-th distances of all its points.
    """
    head, cores = points.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("vec")).alias("dim")).first(), points.sparkSession.sparkContext.defaultParallelism
    n, few = head.n, 0 < (head.dim or 0) <= FEW
    stripes = max(1, -(-n // min(STRIPE, max(CHUNK, LIST_BYTES // (24 * K)))), min(cores, -(-n // TILE)))
    if stripes > cores:
        stripes = -(-stripes // cores) * cores

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}

        def block(s: int) -> pa.RecordBatch:
            ids, x = (np.concatenate(c) for c in zip(*held.pop(s)))
            kind, data = _slots(x)
            row = [[s], [kind], [len(ids)], [ids.astype("<i8").tobytes()], [data]]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, (pa.int32(), pa.string(), pa.int32(), pa.binary(), pa.binary()))], ["home", "kind", "n", "ids", "data"])

        for b in batches:
            if not b.num_rows:
                continue
            ids, x = b.column("id").to_numpy(zero_copy_only=False), vx.matrix(b.column("vec"))
            home = np.full(len(ids), TaskContext.get().partitionId()) if few else b.column("home").to_numpy(zero_copy_only=False)
            for s in np.unique(home):
                mine = home == s
                held.setdefault(int(s), []).append((ids[mine], x[mine]))
                if sum(len(c[0]) for c in held[int(s)]) >= TILE:
                    yield block(int(s))
        for s in list(held):
            yield block(s)

    def run(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[pa.RecordBatch]:
        own, near, later, missing = [], None, [], size

        def meet() -> None:
            ids, p = (np.concatenate(x) for x in zip(*later))
            later.clear()
            if few:
                near.meet_near(ids, p)
                return
            for lo in range(0, len(ids), TILE):
                near.meet(ids[lo : lo + TILE], p[lo : lo + TILE])

        for b in batches:
            for r in range(b.num_rows):
                mine, kind, n, ids, data = (b.column(c)[r].as_py() for c in ("own", "kind", "n", "ids", "data"))
                block = np.frombuffer(ids, "<i8"), _unslotted(kind, data, n)
                if near is None or mine or not few or not near.beyond(block[1]):
                    (own if mine else later).append(block)
                missing -= n if mine else 0
                if near is None and not missing:  # the stripe's own blocks are first in the plan
                    ids, x = (np.concatenate(c) for c in zip(*own))
                    order = _by_place(x) if few else slice(None)
                    near = _Nearest(ids[order], x[order], K)
                    if few:
                        near.meet_near(ids, x)
                    else:
                        later += own
                if near is not None and sum(len(x[0]) for x in later) >= (GROUP if few else TILE):
                    meet()
        if later:
            meet()
        if near is not None:
            yield from near.lists()

    if few:
        homes = points.select("id", "vec", _place(points, head.dim or 0).alias("place")).repartitionByRange(stripes, "place", "id").select("id", "vec")
    else:
        homes = points.select("id", "vec", F.pmod(F.xxhash64("id"), F.lit(stripes)).cast("int").alias("home"))
    blocks = cut(homes.mapInArrow(deal, "home int, kind string, n int, ids binary, data binary"))
    sizes = {r.home: r.n for r in blocks.groupBy("home").agg(F.sum("n").alias("n")).collect()}  # a row a stripe
    # Spark zips a union of single partitions into one task; a part of two partitions and no rows keeps the stripes apart
    out = blocks.filter("home < 0").coalesce(2).withColumn("own", F.lit(True)).mapInArrow(lambda batches: run(batches, 0), LISTS)
    for stripe, size in sorted(sizes.items()):
        first = blocks.filter(F.col("home") == stripe).withColumn("own", F.lit(True))
        stream = first.unionAll(blocks.filter(F.col("home") != stripe).withColumn("own", F.lit(False))).coalesce(1)
        out = out.unionAll(stream.mapInArrow(lambda batches, size=size: run(batches, size), LISTS))
    return out


def unlisted(lists: DataFrame) -> DataFrame:
    """(src, rank, dst, dist) of lists."""
    rows = lists.select("src", F.posexplode(F.arrays_zip("dsts", "dists")).alias("at", "z"))
    return rows.select("src", (F.col("at") + 1).alias("rank"), F.col("z.dsts").alias("dst"), F.col("z.dists").alias("dist"))


def radii_of(lists: DataFrame) -> DataFrame:
    """(id, r) of lists, as ``k_radii`` gives of their rows."""
    return lists.select(F.col("src").alias("id"), F.col("dists").alias("r"))


def ranked_graph_exact(points: DataFrame, K: int) -> DataFrame:
    """(src, rank, dst, dist): the K nearest others of every point."""
    return unlisted(ranked_lists(points, K))


def k_radii(knn: DataFrame, K: int | None = None) -> DataFrame:
    """(id, r): ascending neighbour distances, so ``element_at(r, k)`` is the k-radius."""
    rows = knn if K is None else knn.filter(F.col("rank") <= K)
    return rows.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("dist")).alias("r"))


def radius_at(radii: DataFrame, k: int) -> DataFrame:
    """(id, radius); a list shorter than k counts as infinite."""
    return radii.select("id", F.when(F.size("r") >= k, F.col("r")[k - 1]).otherwise(F.lit(float("inf"))).alias("radius"))


def exact_rknn(queries: DataFrame, points: DataFrame, radii: DataFrame, k: int, block_bytes: int | None = None) -> DataFrame:
    """(qid, id, dist): points that count the query among their k nearest, by the definition."""
    scored = points.select("id", "vec").join(radius_at(radii, k), "id")

    def within(block: Block, frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        narrow = _narrow(block.q)
        for f in frames:
            ids, r, p = f["id"].to_numpy(), f["radius"].to_numpy(), vx.matrix(f["vec"])
            q, slim = (narrow, _narrow(p)) if narrow.dtype == np.float32 else (block.q, p)
            if slim.dtype != q.dtype or _widest(q, slim) >= _EXACT:
                q, slim = block.q, p
            for lo in range(0, len(block.q), 1024):
                qid, part = block.qid[lo : lo + 1024], block.q[lo : lo + 1024]
                edge = ((r * r)[None, :] * (1 + 1e-9) + vx.slack(part, p)).astype(slim.dtype)
                i, j = np.nonzero(vx.squared(q[lo : lo + 1024], slim) <= np.nextafter(edge, slim.dtype.type(np.inf)))
                d = vx.direct(part[i], p[j])
                ok = (d <= r[j] * (1 + ROUNDING)) & (qid[i] != ids[j])
                yield pd.DataFrame({"qid": qid[i][ok], "id": ids[j][ok], "dist": d[ok]})

    return against(queries, scored, within, "qid long, id long, dist double", block_bytes=block_bytes)


def rknn_of_member(rev: DataFrame, ids: DataFrame, k: int) -> DataFrame:
    """(qid, id, rank): reverse neighbours of members, read off their postings."""
    return rev.filter(F.col("rank") <= k).join(ids.select(F.col("id").alias("dst")), "dst").select(
        F.col("dst").alias("qid"), F.col("src").alias("id"), "rank"
    )


def ground_truth(points: DataFrame, queries: DataFrame, ks: list[int], path: str | None = None) -> DataFrame:
    """(k, qid, id, dist) for several k from one graph; written to ``path`` if given."""
    radii = k_radii(ranked_graph_exact(points, max(ks)))
    out = None
    for k in ks:
        one = exact_rknn(queries, points, radii, k).withColumn("k", F.lit(k))
        out = one if out is None else out.unionByName(one)
    out = out.select("k", "qid", "id", "dist")
    if path:
        out.write.mode("overwrite").parquet(path)
        return points.sparkSession.read.parquet(path)
    return out
