"""Navigation: layered small-world graphs by cell, a flat-graph alternative, and searches on them.

A cell is what one task builds: its points are inserted in hash order. Cells are the regions of
pivots (a bounded hash sample); a region that holds more than a task should is split by a hash of
the id, however alike its points are. Queries are routed to the nearest regions, in all their
splits. Layers follow the usual exponential law of a hash, so levels agree on every run.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.sources.shared import cut

CELL_ROWS = 20_000
MAX_PIVOTS = 65_536
DEAL = 256  # queries that are worth a task of their own
NAV = "kind string, cell int, layer int, src long, dsts array<long>, dists array<double>"


def pivots(points: DataFrame, cells: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of the points of least hash, one a cell; bounded by MAX_PIVOTS."""
    if cells > MAX_PIVOTS:
        raise ValueError("more cells than a routing table may hold; raise the cell size")
    rows = points.orderBy(F.xxhash64("id"), "id").limit(cells).toPandas()
    return rows["id"].to_numpy(), vx.matrix(rows["vec"])


def splits_of(points: DataFrame, centres: np.ndarray, cell_rows: int = CELL_ROWS) -> np.ndarray:
    """Into how many cells every pivot's region is split, so that none holds much more than ``cell_rows``."""
    counts = assign_cells(points, centres).groupBy("cell").count().collect()  # MAX_PIVOTS rows at most
    out = np.ones(len(centres), np.int32)
    for cell, n in counts:
        out[cell] = max(1, -(-n // cell_rows))
    return out


def _mixed(ids: np.ndarray) -> np.ndarray:
    x = ids.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ x >> np.uint64(29)


def assign_cells(points: DataFrame, centres: np.ndarray, splits: np.ndarray | None = None) -> DataFrame:
    """``points`` with the cell of their nearest pivot; split s of region c is cell c + s * len(centres)."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            cell = vx.squared(vx.matrix(f["vec"]), centres).argmin(axis=1) if len(f) else np.zeros(0, np.int64)
            if splits is not None and len(f):
                cell = cell + (_mixed(f["id"].to_numpy()) % splits[cell].astype(np.uint64)).astype(np.int64) * len(centres)
            yield f.assign(cell=cell.astype(np.int32))

    return points.select("id", "vec").mapInPandas(run, "id long, vec array<double>, cell int")


def route(queries: DataFrame, centres: np.ndarray, n_probe: int, splits: np.ndarray | None = None) -> DataFrame:
    """(qid, vec, cell): every query with its ``n_probe`` nearest regions, in all their splits."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            if not len(f):
                continue
            near = np.argsort(vx.squared(vx.matrix(f["vec"]), centres), axis=1, kind="stable")[:, :n_probe]
            at, cell = np.repeat(np.arange(len(f)), near.shape[1]), near.ravel()
            if splits is not None:
                n = splits[cell]
                step = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                at, cell = np.repeat(at, n), np.repeat(cell, n) + step * len(centres)
            yield pd.DataFrame({"qid": f["qid"].to_numpy()[at], "vec": f["vec"].to_numpy()[at], "cell": cell.astype(np.int32)})

    return queries.select("qid", "vec").mapInPandas(run, "qid long, vec array<double>, cell int")


class Layers:
    """A layered graph over the rows of one matrix."""

    def __init__(self, x: np.ndarray, M: int = 16, ef_c: int = 100):
        self.x, self.M, self.ef_c = x, M, ef_c
        self.links: list[dict[int, list[int]]] = []
        self.entry = -1
        self.changed: set[tuple[int, int]] = set()  # (layer, node) whose links were written

    def far(self, q: np.ndarray, nodes: list[int]) -> np.ndarray:
        d = self.x[nodes] - q
        return np.sqrt(np.einsum("ij,ij->i", d, d))

    def search(self, q: np.ndarray, starts: list[tuple[float, int]], ef: int, layer: int, beam: str = "classic", k: int | None = None):
        """Best-first search of a layer: (distance, node) of at most ``ef`` (``split``: ``k``) results, ascending."""
        keep = (k or ef) if beam == "split" else ef
        seen = {v for _, v in starts}
        frontier = list(starts)
        heapq.heapify(frontier)
        best = [(-d, -v) for d, v in starts]
        heapq.heapify(best)
        while len(best) > keep:
            heapq.heappop(best)
        links = self.links[layer]
        while frontier:
            d, v = heapq.heappop(frontier)
            if len(best) >= keep and d > -best[0][0]:
                break
            new = [u for u in links.get(v, ()) if u not in seen]
            if not new:
                continue
            seen.update(new)
            for du, u in zip(self.far(q, new).tolist(), new):
                if len(best) < keep or du < -best[0][0]:
                    heapq.heappush(frontier, (du, u))
                    heapq.heappush(best, (-du, -u))
                    if len(best) > keep:
                        heapq.heappop(best)
            if beam == "split" and len(frontier) > ef:
                frontier = heapq.nsmallest(ef, frontier)
                heapq.heapify(frontier)
        return sorted((-d, -v) for d, v in best)

    def descend(self, q: np.ndarray, to: int, starts=None) -> list[tuple[float, int]]:
        """Greedy from the top to the layer above ``to``."""
        at = starts or [(float(self.far(q, [self.entry])[0]), self.entry)]
        for layer in range(len(self.links) - 1, to, -1):
            at = self.search(q, at, 1, layer)[:1]
        return at

    def pick(self, found: list[tuple[float, int]], room: int) -> list[int]:
        """Diverse neighbours: one is kept if it is nearer to the node than to any kept before it.

        A copy of the node is kept once and hides nothing: all else is as far from the copy as from the node.
        """
        nodes = [v for _, v in found]
        x, d = self.x[nodes], np.array([d for d, _ in found])
        norm, d2 = np.einsum("ij,ij->i", x, x), d * d
        apart = norm[:, None] + norm - 2 * (x @ x.T)
        hides = apart <= d2[:, None]  # whether column hides row
        close = np.abs(apart - d2[:, None]) <= 4 * vx.slack(x, x) + 1e-12 * d2[:, None]
        if close.any():  # rounding may decide
            i, j = np.nonzero(close)
            hides[i, j] = vx.direct(x[i], x[j]) <= d[i]
        hidden, taken = np.zeros(len(found), bool), []
        for i, (di, _) in enumerate(found):
            if len(taken) >= room:
                break
            if di == 0:
                if not taken:
                    taken.append(i)
            elif not hidden[i]:
                taken.append(i)
                hidden |= hides[:, i]
        kept = [nodes[i] for i in taken]
        if len(kept) < room:  # fill up with the nearest of the rest
            done = set(taken)
            kept += [v for i, v in enumerate(nodes) if i not in done][: room - len(kept)]
        return kept

    def insert(self, v: int, level: int) -> list[tuple[float, int]]:
        """Add row v; what its search of the ground layer met."""
        q = self.x[v]
        self.changed.update((layer, v) for layer in range(level + 1))
        if self.entry < 0:
            self.links = [{v: []} for _ in range(level + 1)]
            self.entry = v
            return []
        top = len(self.links) - 1
        at = self.descend(q, min(level, top))
        met: list[tuple[float, int]] = []
        for layer in range(min(level, top), -1, -1):
            found = self.search(q, at, self.ef_c, layer)
            at = met = found
            room = self.M if layer else 2 * self.M
            links = self.links[layer]
            links[v] = self.pick(found, self.M)
            self.changed.update((layer, u) for u in links[v])
            for u in links[v]:
                links[u].append(v)
                if len(links[u]) > room:
                    near = sorted(zip(self.far(self.x[u], links[u]).tolist(), links[u]))
                    links[u] = self.pick(near, room)
        for _ in range(top + 1, level + 1):
            self.links.append({v: []})
        if level > top:
            self.entry = v
        return met

    def nearest(self, q: np.ndarray, m: int, ef: int, beam: str = "classic") -> list[tuple[float, int]]:
        at = self.descend(q, 0)
        return self.search(q, at, max(ef, m), 0, beam, m)[:m]


def _levels(ids: np.ndarray, M: int) -> np.ndarray:
    u = (((ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(11)).astype(float) + 1) / 2.0**53
    return np.floor(-np.log(u) / math.log(M)).astype(int)


def build_layers(ids: np.ndarray, x: np.ndarray, M: int, ef_c: int) -> tuple[Layers, list]:
    g = Layers(x, M, ef_c)
    met = [g.insert(v, int(level)) for v, level in enumerate(_levels(ids, M))]
    return g, met


def build_nav(points: DataFrame, centres: np.ndarray, M: int = 16, ef_c: int = 100, K: int = 100, splits: np.ndarray | None = None) -> DataFrame:
    """Rows of kind 'edge' (layered links) and 'seed' (what insertion met), one task a cell."""

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("id").reset_index(drop=True)
        frame = frame.iloc[np.argsort((frame["id"].to_numpy().astype(np.uint64) * np.uint64(0xD1342543DE82EF95)), kind="stable")]
        ids, x, cell = frame["id"].to_numpy(), vx.matrix(frame["vec"]), int(frame["cell"].iloc[0])
        g, met = build_layers(ids, x, M, ef_c)
        rows = [("edge", cell, layer, ids[v], ids[near].tolist() if near else [], []) for layer, links in enumerate(g.links) for v, near in links.items()]
        rows.append(("entry", cell, len(g.links) - 1, ids[g.entry], [], []))
        rows += [("seed", cell, 0, ids[v], [int(ids[u]) for _, u in m[:K]], [d for d, _ in m[:K]]) for v, m in enumerate(met) if m]
        return pd.DataFrame(rows, columns=["kind", "cell", "layer", "src", "dsts", "dists"])

    return _in_cells(points, centres, splits).groupBy("cell").applyInPandas(build, NAV)


def _in_cells(points: DataFrame, centres: np.ndarray, splits: np.ndarray | None = None) -> DataFrame:
    """Points with their cell: the stored one, or assigned now."""
    return points.select("id", "vec", "cell") if "cell" in points.columns else assign_cells(points, centres, splits)


def restored(g: pd.DataFrame, M: int = 16, ef_c: int = 100) -> tuple[np.ndarray, Layers]:
    """Ids and graph of a cell from its rows (kind, layer, src, dsts, vec)."""
    ground = g[(g["kind"] == "edge") & (g["layer"] == 0)].sort_values("src")
    ids = ground["src"].to_numpy()
    layers = Layers(vx.matrix(ground["vec"]), M, ef_c)
    at = {int(v): i for i, v in enumerate(ids)}
    edges = g[g["kind"] == "edge"]
    layers.links = [{} for _ in range(int(edges["layer"].max()) + 1)]
    for layer, src, dsts in zip(edges["layer"], edges["src"], edges["dsts"]):
        layers.links[layer][at[int(src)]] = [at[int(d)] for d in dsts]
    layers.entry = at[int(g[g["kind"] == "entry"]["src"].iloc[0])]
    return ids, layers


def nav_insert(
    nav: DataFrame, points: DataFrame, new: DataFrame, centres: np.ndarray, M: int = 16, ef_c: int = 100, n_probe: int = 4,
    splits: np.ndarray | None = None,
) -> DataFrame:
    """Rows of NAV that inserting the new points writes: changed links, entries, and what the searches met as seeds.

    Only cells that arrivals fall into, or look into, are read. A new point is linked in its own cell
    and also searched for in the other probed cells, so its list may cross borders.
    """
    home = _in_cells(new, centres, splits).select(F.col("id").alias("qid"), F.col("cell").alias("home"))
    asked = route(new.select(F.col("id").alias("qid"), "vec"), centres, n_probe, splits).join(home, "qid")
    asked = asked.unionByName(  # the own cell, should the routing not name it
        _in_cells(new, centres, splits).select(F.col("id").alias("qid"), "vec", "cell", F.col("cell").alias("home"))
    ).dropDuplicates(["qid", "cell"])
    held = _in_cells(points, centres, splits).select("cell", F.col("id").alias("src"), "vec")
    probed = asked.select("cell").distinct()
    graph = nav.filter("kind <> 'seed'").select("cell", "kind", "layer", "src", "dsts").join(probed, "cell", "left_semi").join(held, ["cell", "src"])

    def grow(key, q: pd.DataFrame, g: pd.DataFrame) -> pd.DataFrame:
        if not len(q):
            return pd.DataFrame({c: [] for c in ("kind", "cell", "layer", "src", "dsts", "dists")})
        cell = int(key[0])
        q = q.sort_values("qid")
        x, mine = vx.matrix(q["vec"]), (q["home"] == cell).to_numpy()
        fresh = q["qid"].to_numpy()
        if len(g):
            ids, layers = restored(g, M, ef_c)
        else:
            ids, layers = np.zeros(0, np.int64), Layers(np.zeros((0, x.shape[1])), M, ef_c)
        entry = (len(layers.links), layers.entry)
        seeds = []
        if len(ids):
            seeds += [(fresh[i], layers.nearest(x[i], ef_c, ef_c)) for i in np.flatnonzero(~mine)]
        base = len(ids)
        layers.x, ids = np.concatenate([layers.x, x[mine]]), np.concatenate([ids, fresh[mine]])
        for i, (qid, level) in enumerate(zip(fresh[mine], _levels(fresh[mine], M))):
            seeds.append((qid, layers.insert(base + i, int(level))))
        rows = [("edge", cell, layer, ids[v], ids[layers.links[layer][v]].tolist() if layers.links[layer][v] else [], []) for layer, v in sorted(layers.changed)]
        if layers.entry >= 0 and (len(layers.links), layers.entry) != entry:
            rows.append(("entry", cell, len(layers.links) - 1, ids[layers.entry], [], []))
        rows += [("seed", cell, 0, qid, [int(ids[u]) for _, u in met], [d for d, _ in met]) for qid, met in seeds if met]
        return pd.DataFrame(rows, columns=["kind", "cell", "layer", "src", "dsts", "dists"])

    return asked.groupBy("cell").cogroup(graph.groupBy("cell")).applyInPandas(grow, NAV)


def seeds_of(nav: DataFrame) -> DataFrame:
    """(src, dst, dist) of the build's side output."""
    zipped = F.explode(F.arrays_zip("dsts", "dists")).alias("z")
    return nav.filter("kind = 'seed'").select("src", zipped).select("src", F.col("z.dsts").alias("dst"), F.col("z.dists").alias("dist"))


def build_nsg(points: DataFrame, knn: DataFrame, centres: np.ndarray, R: int = 32, L: int = 100) -> DataFrame:
    """A flat graph by cell: medoid entry, pool by search on the neighbour graph, monotone edges, repair."""

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("id")
        ids, x, cell = frame["id"].to_numpy(), vx.matrix(frame["vec"]), int(frame["cell"].iloc[0])
        at = {int(v): i for i, v in enumerate(ids)}
        base = Layers(x)
        base.links = [{i: [at[int(d)] for d in ds if int(d) in at] for i, ds in enumerate(frame["dsts"])}]
        base.entry = int(vx.squared(x.mean(axis=0)[None, :], x).argmin())
        out: dict[int, list[int]] = {}
        for v in range(len(ids)):
            pool = base.search(x[v], [(float(base.far(x[v], [base.entry])[0]), base.entry)], L, 0)
            near = base.links[0][v]
            pool = sorted(set(pool) | set(zip(base.far(x[v], near).tolist(), near) if near else ()))
            kept: list[int] = []
            for d, u in pool:
                if u != v and len(kept) < R and (not kept or d < base.far(x[u], kept).min()):
                    kept.append(u)
            out[v] = kept
        for v in range(len(ids)):  # links both ways while there is room
            for u in out[v]:
                if v not in out[u] and len(out[u]) < R:
                    out[u].append(v)
        reached, queue = {base.entry}, [base.entry]
        while queue:
            for u in out[queue.pop()]:
                if u not in reached:
                    reached.add(u)
                    queue.append(u)
        for v in range(len(ids)):
            if v not in reached:
                old = np.fromiter(reached, int)
                near = int(old[base.far(x[v], old).argmin()])
                out[near].append(v)
                stack = [v]
                reached.add(v)
                while stack:
                    for u in out[stack.pop()]:
                        if u not in reached:
                            reached.add(u)
                            stack.append(u)
        rows = [("edge", cell, 0, ids[v], ids[near].tolist(), []) for v, near in out.items()]
        rows.append(("entry", cell, 0, ids[base.entry], [], []))
        return pd.DataFrame(rows, columns=["kind", "cell", "layer", "src", "dsts", "dists"])

    lists = knn.groupBy("src").agg(F.collect_list("dst").alias("dsts"))
    held = _in_cells(points, centres).join(lists.withColumnRenamed("src", "id"), "id", "left")
    held = held.withColumn("dsts", F.coalesce("dsts", F.array().cast("array<long>")))
    return held.groupBy("cell").applyInPandas(build, NAV)


def graph_search(
    nav: DataFrame, points: DataFrame, queries: DataFrame, centres: np.ndarray, m: int, ef: int, n_probe: int = 4, beam: str = "classic",
    drop_self: bool = True, splits: np.ndarray | None = None,
) -> DataFrame:
    """(qid, id, prank, pdist): the m nearest found by a beam in each probed cell, merged.

    Points that carry their ``cell`` are not assigned anew, and only probed cells are read. Where cells are fewer than
    cores, the many queries of a cell are dealt to several tasks, each with the cell's graph.
    """
    if ef < m:
        raise ValueError("ef must be at least m")
    asked = route(queries, centres, n_probe, splits)
    probed = asked.select("cell").distinct()
    held = _in_cells(points, centres, splits).join(probed, "cell", "left_semi").select("cell", F.col("id").alias("src"), "vec")
    graph = nav.filter("kind <> 'seed'").select("cell", "kind", "layer", "src", "dsts").join(held, ["cell", "src"])
    want = m + (1 if drop_self else 0)
    cells = len(centres) if splits is None else int(splits.sum())
    deals = max(1, min(-(-points.sparkSession.sparkContext.defaultParallelism // cells), queries.count() // DEAL))
    asked = asked.withColumn("deal", F.pmod(F.xxhash64("qid"), F.lit(deals)).cast("int"))
    graph = graph.withColumn("deal", F.explode(F.sequence(F.lit(0), F.lit(deals - 1))))

    def find(key, q: pd.DataFrame, g: pd.DataFrame) -> pd.DataFrame:
        if not len(g) or not len(q):
            return pd.DataFrame({"qid": [], "id": [], "pdist": []})
        ids, layers = restored(g)
        rows = [
            (qid, int(ids[v]), d)
            for qid, vec in zip(q["qid"], q["vec"])
            for d, v in layers.nearest(np.asarray(vec, float), want, max(ef, want), beam)
        ]
        return pd.DataFrame(rows, columns=["qid", "id", "pdist"])

    found = asked.groupBy("cell", "deal").cogroup(graph.groupBy("cell", "deal")).applyInPandas(find, "qid long, id long, pdist double")
    if drop_self:
        found = found.filter("qid <> id")
    rank = F.row_number().over(Window.partitionBy("qid").orderBy("pdist", "id"))
    return found.withColumn("prank", rank).filter(F.col("prank") <= m).select("qid", "id", "prank", "pdist")


def beam_relational(adjacency: DataFrame, points: DataFrame, queries: DataFrame, entry: int, m: int, ef: int, width: int = 4) -> DataFrame:
    """(qid, id, prank, pdist) by joins: all queries advance together, ``width`` expansions a round.

    Rounds go on until every query has expanded all it keeps; a node is visited once, so they end.
    """
    from kinward.functions.vectors import l2

    q = queries.select("qid", F.col("vec").alias("qvec"))
    start = points.filter(F.col("id") == entry).select(F.col("id").alias("node"), "vec")
    kept = cut(q.crossJoin(F.broadcast(start)).select("qid", "node", l2(F.col("qvec"), F.col("vec")).alias("d"), F.lit(False).alias("done")))  # one entry
    visited = cut(kept.select("qid", "node"))
    while True:
        by = Window.partitionBy("qid").orderBy("d", "node")
        picks = cut(kept.filter("NOT done").withColumn("r", F.row_number().over(by)).filter(F.col("r") <= width).select("qid", "node"))
        if picks.isEmpty():
            break
        reached = picks.join(adjacency.select(F.col("src").alias("node"), "dst"), "node").select("qid", F.col("dst").alias("node")).distinct()
        fresh = reached.join(visited, ["qid", "node"], "left_anti")
        fresh = fresh.join(points.select(F.col("id").alias("node"), "vec"), "node").join(q, "qid")
        fresh = cut(fresh.select("qid", "node", l2(F.col("qvec"), F.col("vec")).alias("d"), F.lit(False).alias("done")))
        visited = cut(visited.unionByName(fresh.select("qid", "node")))
        mark = kept.join(picks.withColumn("p", F.lit(True)), ["qid", "node"], "left").select("qid", "node", "d", (F.col("done") | F.col("p").isNotNull()).alias("done"))
        kept = cut(mark.unionByName(fresh).withColumn("r", F.row_number().over(by)).filter(F.col("r") <= ef).drop("r"))
    by = Window.partitionBy("qid").orderBy("d", "node")
    return kept.withColumn("prank", F.row_number().over(by)).filter(F.col("prank") <= m).select("qid", F.col("node").alias("id"), "prank", F.col("d").alias("pdist"))
