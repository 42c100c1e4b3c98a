"""The experiment workloads: trade-off, phases, grid, build, ablations, k, insertion, scale, locality.

Every workload gives rows of (experiment, set, method, k, m, theta, recall, candidates, results,
seconds, qps); seconds are of one batch of all queries on this machine, without the build.
``CLAIMS`` holds what is asserted of the rows: figures that do not depend on the machine. The
driver's queries run a workload and return (claim, holds), which SQL states too; ``rows`` or
``python -m kinward.plans.experiments SF_DIR NAME`` gives the figures themselves.
Sets: e embeddings, t hashed documents, p parts, l lineitem.
"""

from __future__ import annotations

import sys
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.operators import baselines, exact, maintain, measures, navigate, postings, proxy, ranked_graph
from kinward.operators.index import HybridIndex
from kinward.plans.core_queries import Set
from kinward.sources.shared import cut, shared_folder

SCHEMA = (
    "experiment string, `set` string, method string, k int, m int, theta int, recall double, candidates long, results double, seconds double, qps double"
)
#: Settings of the published grid; thresholds and proxies beyond the lists' length K are left out.
MS, THETAS = (1, 3, 5, 10, 20, 30, 50, 100, 150, 200), (10, 20, 30, 50, 100, 200, 300, 500)
K_PRIMES, TS = (10, 20, 30, 50, 100, 200, 400), (2.0, 4.0, 8.0)
TARGETS = (0.90, 0.95, 0.99)
SHARES = (0.0, 0.1, 0.25, 0.5, 0.75, 0.9, 0.99, 1.0)


class Log:
    def __init__(self, s: Set, experiment: str, kind: str):
        self.s, self.experiment, self.kind, self.rows = s, experiment, kind, []

    def run(self, method: str, make, truth: DataFrame, k: int, m: int = 0, theta: int = 0, candidates: int | None = None) -> DataFrame:
        began = time.perf_counter()
        out = cut(make())
        took = time.perf_counter() - began
        n, asked = out.count(), self.s.queries.count()
        value = measures.recall(truth, out.select("qid", "id"), self.s.queries)
        self.note(method, k=k, m=m, theta=theta, recall=value, candidates=candidates, results=n / max(1, asked), seconds=took, qps=asked / took)
        return out

    def note(self, method: str, **values) -> None:
        row = {"k": 0, "m": 0, "theta": 0, "recall": None, "candidates": None, "results": None, "seconds": None, "qps": None} | values
        self.rows.append((self.experiment, self.kind, method, *row.values()))

    def table(self) -> DataFrame:
        return self.s.points.sparkSession.createDataFrame(self.rows, SCHEMA)


def _cells(s: Set, k: int = 10, ms=MS, thetas=THETAS, truth: DataFrame | None = None, knn: DataFrame | None = None) -> list:
    """(m, theta, recall, scanned, candidates) of the grid, cut at the lists' length, in one pass."""
    n = s.points.count()
    ms, thetas = [m for m in ms if m < n], [t for t in thetas if t <= s.depth]
    near = cut(proxy.flat_proxies(s.queries, s.points, max(ms)))
    rev, radii = (s.rev, s.radii) if knn is None else (postings.transpose(knn), exact.k_radii(knn))
    return proxy.grid(s.queries, s.points, rev, radii, s.truth if truth is None else truth, k, ms, thetas, near).collect()  # a cell a row


def _cheapest(cells: list, target: float):
    """The cell of least candidates that reaches a target recall, or none."""
    ok = [c for c in cells if c.recall >= target]
    return min(ok, key=lambda c: (c.candidates, c.scanned, c.m, c.theta)) if ok else None


def _index(s: Set, K: int = 50, **options) -> HybridIndex:
    return HybridIndex.build(s.points, f"{shared_folder(s.points.sparkSession)}/index-{uuid.uuid4().hex}", K, 16, 60, 6, **options)


def tradeoff(spark: SparkSession, d: str, kind: str = "t") -> DataFrame:
    """Recall against candidates: the whole grid of proxy search, one shot, incremental, hops up to k."""
    s = _set(spark, d, kind)
    log = Log(s, "tradeoff", kind)
    asked, n = s.queries.count(), s.points.count()
    for c in _cells(s):
        log.note("proxy", k=10, m=c.m, theta=c.theta, recall=c.recall, candidates=c.candidates)
    primes = [kp for kp in K_PRIMES if kp < n]
    widest = cut(proxy.flat_proxies(s.queries, s.points, max(primes)))
    for kp in primes:
        near = widest.filter(F.col("prank") <= kp)
        log.run("one_shot_radii", lambda: baselines.one_shot_rknn(s.queries, s.points, 10, kp, s.radii, near), s.truth, 10, kp, 0, kp * asked)
    log.run("one_shot", lambda: baselines.one_shot_rknn(s.queries, s.points, 10, 50, proxies=widest.filter("prank <= 50")), s.truth, 10, 50, 0, 50 * asked)
    for t in TS:
        log.run(f"incremental_t{t:g}", lambda: baselines.incremental_rknn(s.queries, s.points, 10, t, 200), s.truth, 10)
    graph = cut(baselines.build_hop_graph(s.knn, s.points))
    entries = cut(widest.filter("prank = 1"))
    for hops in (1, 2, 3, 10):
        found = cut(baselines.hop_candidates(graph, entries, hops).filter("qid <> id"))
        bounds = found.select("qid", "id", F.lit(0.0).alias("low"), F.lit(0.0).alias("high"))
        log.run("hop", lambda: proxy.verify(bounds, s.queries, s.points, s.radii, 10), s.truth, 10, hops, 0, found.count())
    return log.table()


def phases(spark: SparkSession, d: str, kind: str = "t") -> DataFrame:
    """Seconds of proxy retrieval, posting scan and verification at recall .95 and .99, each materialised."""
    s = _set(spark, d, kind)
    log = Log(s, "phases", kind)
    cells, index = _cells(s), _index(s, s.depth)
    for target in (0.95, 0.99):
        c = _cheapest(cells, target)
        if c is None:
            log.note(f"none_{target:g}")
            continue
        began = time.perf_counter()
        near = cut(index.proxies(s.queries, c.m, max(2 * c.m, 64)))
        log.note(f"proxies_{target:g}", m=c.m, theta=c.theta, seconds=time.perf_counter() - began)
        began = time.perf_counter()
        cands = cut(proxy.candidates(near, index.view("rev"), c.theta))
        log.note(f"scan_{target:g}", m=c.m, theta=c.theta, candidates=cands.count(), seconds=time.perf_counter() - began)
        log.run(f"verify_{target:g}", lambda: proxy.verify(cands, s.queries, index.view("points"), index.view("radii"), 10), s.truth, 10, c.m, c.theta)
    return log.table()


def grid(spark: SparkSession, d: str, kind: str = "t") -> DataFrame:
    """The sensitivity grid, and the cheapest cell of each target."""
    s = _set(spark, d, kind)
    log, cells = Log(s, "grid", kind), _cells(s)
    for c in cells:
        log.note("cell", k=10, m=c.m, theta=c.theta, recall=c.recall, candidates=c.candidates)
    for target in TARGETS:
        c = _cheapest(cells, target)
        if c:
            log.note(f"best_{target:g}", k=10, m=c.m, theta=c.theta, recall=c.recall, candidates=c.candidates)
    return log.table()


def build(spark: SparkSession, d: str, kind: str = "e") -> DataFrame:
    """Seconds and bytes (column candidates) of the nav graph, the hybrid index and the hop graph."""
    s = _set(spark, d, kind, 50)
    log = Log(s, "build", kind)
    _, centres = navigate.pivots(s.points, 1)
    began = time.perf_counter()
    nav = cut(navigate.build_nav(s.points, centres, 16, 60, 50))
    log.note("nav", candidates=8 * nav.filter("kind = 'edge'").agg(F.sum(F.size("dsts"))).first()[0], seconds=time.perf_counter() - began)
    began = time.perf_counter()
    index = _index(s)
    took = time.perf_counter() - began
    held = {r.view: r.bytes for r in index.describe().collect()}
    log.note("hybrid", candidates=sum(v for k, v in held.items() if k != "points"), seconds=took, results=sum(held.values()) / held["points"])
    began = time.perf_counter()
    pool = exact.ranked_graph_exact(s.points, min(400, s.points.count() - 1))
    hop = cut(baselines.build_hop_graph(pool, s.points))
    log.note("hop", candidates=8 * hop.count(), seconds=time.perf_counter() - began)
    log.note("points", candidates=held["points"])
    return log.table()


def ablations(spark: SparkSession, d: str, kind: str = "e") -> DataFrame:
    """Nav graph, start of refinement, radii and postings swapped one at a time."""
    s = _set(spark, d, kind)
    log = Log(s, "ablation", kind)
    opt = proxy.SearchOptions(10, 20, 50)
    cells = max(1, -(-s.points.count() // 2000))
    _, centres = navigate.pivots(s.points, cells)
    nav = cut(navigate.build_nav(s.points, centres, 16, 60, 50))
    nsg = cut(navigate.build_nsg(s.points, s.knn, centres, 32, 60))
    for name, g in (("hnsw", nav), ("nsg", nsg)):
        near = cut(navigate.graph_search(g, s.points, s.queries, centres, 20, 80, cells))
        log.run(name, lambda: proxy.proxy_rknn(s.queries, s.points, s.rev, s.radii, opt, near), s.truth, 10, 20, 50)
    for name, start in (("warm_start", ranked_graph.seed_from_nav(navigate.seeds_of(nav), 20)), ("random_start", ranked_graph.seed_random(s.points, 20))):
        for r in ranked_graph.refine(s.points, start, 20, 4, exact=s.knn)[1]:
            log.note(name, k=10, m=r["round"], recall=r["recall"], candidates=r["changed"], seconds=r["seconds"])
    rough, _ = ranked_graph.refine(s.points, ranked_graph.seed_random(s.points, 50), 50, 1)
    rough = cut(rough)
    log.run("stored_radii", lambda: proxy.proxy_rknn(s.queries, s.points, postings.transpose(rough), exact.k_radii(rough), opt, s.proxies), s.truth, 10, 20, 50)
    log.run("exact_radii", lambda: proxy.proxy_rknn(s.queries, s.points, postings.transpose(rough), s.radii, opt, s.proxies), s.truth, 10, 20, 50)
    n, asked = s.points.count(), s.queries.count()
    log.run("no_postings", lambda: proxy.no_postings_rknn(s.queries, s.points, s.radii, 10), s.truth, 10, candidates=(n - 1) * asked)
    cands = cut(proxy.candidates(s.proxies, s.rev, 50))
    log.run("postings", lambda: proxy.verify(cands, s.queries, s.points, s.radii, 10), s.truth, 10, 20, 50, cands.count())
    log.run("online_radius", lambda: proxy.online_radius_rknn(cands, s.queries, s.points, 10), s.truth, 10, 20, 50, cands.count())
    return log.table()


def by_k(spark: SparkSession, d: str, kind: str = "t") -> DataFrame:
    """The same index at k of 1, 10, 30, 50 and 90, and the cheapest cell of either target."""
    s = _set(spark, d, kind)
    log = Log(s, "k", kind)
    for k in (1, 10, 30, 50, 90):
        truth = cut(exact.exact_rknn(s.queries, s.points, s.radii, k))
        cells = _cells(s, k, truth=truth)
        for target in (0.95, 0.99):
            c = _cheapest(cells, target)
            if c is None:
                log.note(f"none_{target:g}", k=k)
                continue
            opt = proxy.SearchOptions(k, c.m, c.theta)
            log.run(f"proxy_{target:g}", lambda: proxy.proxy_rknn(s.queries, s.points, s.rev, s.radii, opt), truth, k, c.m, c.theta, c.candidates)
    return log.table()


def insertion(spark: SparkSession, d: str, kind: str = "e") -> DataFrame:
    """By the share that is built at once: build seconds, graph recall, and the cheapest cell of each target."""
    s = _set(spark, d, kind, 50)
    log = Log(s, "insertion", kind)
    for share in SHARES:
        began = time.perf_counter()
        knn = cut(exact.ranked_graph_exact(s.points, 50) if share == 1.0 else maintain.build_by_insertion(s.points, 50, share, 2))
        log.note(f"build_{share:g}", k=10, recall=measures.graph_recall(knn, s.knn, 10).first()[0], seconds=time.perf_counter() - began)
        cells = _cells(s, 10, (10, 20, 50), (20, 50), knn=knn)
        for target in TARGETS:
            c = _cheapest(cells, target)
            if c:
                log.note(f"share_{share:g}_{target:g}", k=10, m=c.m, theta=c.theta, recall=c.recall, candidates=c.candidates)
    return log.table()


def scale(spark: SparkSession, d: str, kind: str = "t", parts: tuple[int, ...] = (20, 40, 60, 80, 100), indexed: bool = True) -> DataFrame:
    """Growing shares of a set, by hash: build seconds, and recall and candidates of four methods."""
    whole, out = _set(spark, d, kind), None
    for part in parts:
        s = Set.__new__(Set)
        s.points = cut(whole.points.filter(F.pmod(F.xxhash64("id"), F.lit(100)) < part))
        s.queries, s.depth, s._cut = s.points.filter("id % 20 = 0").select(F.col("id").alias("qid"), "vec"), whole.depth, cut
        log, opt = Log(s, f"scale_{part}", kind), proxy.SearchOptions(10, 20, 50)
        _ = s.knn, s.truth
        if indexed:
            began = time.perf_counter()
            index = _index(s)
            log.note("build", seconds=time.perf_counter() - began)
            log.run("proxy", lambda: index.search(s.queries, opt), s.truth, 10, 20, 50)
        else:
            n = proxy.candidates(s.proxies, s.rev, 50).count()
            log.run("proxy", lambda: proxy.proxy_rknn(s.queries, s.points, s.rev, s.radii, opt, s.proxies), s.truth, 10, 20, 50, n)
        asked = s.queries.count()
        log.run("one_shot", lambda: baselines.one_shot_rknn(s.queries, s.points, 10, 50), s.truth, 10, 50, 0, 50 * asked)
        log.run("incremental", lambda: baselines.incremental_rknn(s.queries, s.points, 10, 4.0, 200), s.truth, 10)
        began = time.perf_counter()
        graph = cut(baselines.build_hop_graph(s.knn, s.points))
        log.note("build_hop", seconds=time.perf_counter() - began)
        log.run("hop", lambda: baselines.hop_rknn(graph, s.queries, s.points, 10, 2), s.truth, 10, 2)
        out = log.table() if out is None else out.unionByName(log.table())
    return out


def scale_lineitem(spark: SparkSession, d: str) -> DataFrame:
    """The same on growing shares of lineitem: four columns, many points, no mismatch."""
    return scale(spark, d, "l", (2, 4, 8), indexed=False)


def locality(spark: SparkSession, d: str, kind: str = "t") -> DataFrame:
    """What proxies reach (method ``proxy``), and which share the m nearest points hold (``plain``)."""
    s = _set(spark, d, kind)
    log = Log(s, "locality", kind)
    ranks = exact.ranks_of(s.truth, s.queries, s.points)
    total = s.truth.count()
    plain = ranks.groupBy().agg(*[F.round(F.count_if(F.col("rank") <= m) / total, 6).alias(str(m)) for m in (1, 5, 20)]).first()
    for m in (1, 5, 20):
        log.note("plain", k=10, m=m, recall=plain[str(m)])
    for c in measures.proxy_coverage(s.truth, s.proxies, s.lists, [10, 50, 100], [1, 5, 20]).collect():
        log.note("proxy", k=10, m=c.m, theta=c.theta, recall=c.share)
    return log.table()


def _set(spark: SparkSession, d: str, kind: str, depth: int = 100) -> Set:
    if kind != "l":
        return Set(spark, d, kind, depth)
    s = Set.__new__(Set)
    s.points = cut(vx.vectors_lineitem(spark, d))
    _, s.queries = vx.split_base_queries(s.points)
    s.depth, s._cut = depth, cut
    return s


EXPERIMENTS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "exp_tradeoff": tradeoff, "exp_tradeoff_e": lambda spark, d: tradeoff(spark, d, "e"), "exp_tradeoff_part": lambda spark, d: tradeoff(spark, d, "p"),
    "exp_phases": phases, "exp_grid": grid, "exp_build": build, "exp_ablations": ablations, "exp_k": by_k, "exp_insertion": insertion,
    "exp_scale": scale, "exp_scale_lineitem": scale_lineitem, "exp_locality": locality,
}


def _by(rows: list, method: str) -> list:
    return [r for r in rows if r.method == method]


def _rising(rows: list, method: str, value: str = "recall") -> bool:
    """Whether a value never falls when m or theta grows."""
    cells = {(r.m, r.theta): r[value] for r in _by(rows, method)}
    return bool(cells) and all(cells[a] <= cells[b] + 1e-9 for a in cells for b in cells if a[0] <= b[0] and a[1] <= b[1])


def _at(rows: list, method: str, m: int, theta: int = 0) -> float:
    return next(r.recall for r in _by(rows, method) if r.m == m and r.theta == theta)


def _most(rows: list, method: str) -> float:
    return max((r.recall for r in rows if r.method.startswith(method) and r.recall is not None), default=0.0)


_TRADE = {
    "recall rises with proxies and threshold": lambda x: _rising(x, "proxy"),
    "candidates rise with proxies and threshold": lambda x: _rising(x, "proxy", "candidates"),
    "one shot rises with k prime": lambda x: _rising(x, "one_shot_radii"),
    "stored radii do not change one shot": lambda x: abs(_at(x, "one_shot", 50) - _at(x, "one_shot_radii", 50)) < 1e-9,
    "hops add recall": lambda x: _rising(x, "hop"),
    "a later dimension test adds recall": lambda x: _most(x, "incremental_t2") <= _most(x, "incremental_t8") + 1e-9,
    "proxy search reaches .99": lambda x: _most(x, "proxy") >= 0.99,
}
CLAIMS: dict[str, dict[str, Callable[[list], bool]]] = {
    "exp_tradeoff": _TRADE | {"proxy search beats one shot at its candidates": lambda x: _at(x, "proxy", 5, 20) > _at(x, "one_shot_radii", 100)},
    "exp_tradeoff_e": _TRADE,
    "exp_tradeoff_part": _TRADE,
    "exp_phases": {"both targets are reached": lambda x: not any(r.method.startswith("none") for r in x) and all(r.recall >= 0.9 for r in x if r.method.startswith("verify"))},
    "exp_grid": {
        "recall rises": lambda x: _rising(x, "cell"),
        "targets cost more and more": lambda x: (lambda c: c == sorted(c) and len(c) == 3)([r.candidates for t in TARGETS for r in _by(x, f"best_{t:g}")]),
    },
    "exp_build": {
        "the hybrid index is larger than its nav graph": lambda x: _by(x, "hybrid")[0].candidates > _by(x, "nav")[0].candidates,
        "the hybrid index is larger than the hop graph": lambda x: _by(x, "hybrid")[0].candidates > _by(x, "hop")[0].candidates,
    },
    "exp_ablations": {
        "nav graphs give equal recall": lambda x: abs(_most(x, "hnsw") - _most(x, "nsg")) <= 0.02,
        "a warm start begins higher": lambda x: _by(x, "warm_start")[0].recall > _by(x, "random_start")[0].recall + 0.2,
        "exact radii do not change recall": lambda x: abs(_most(x, "stored_radii") - _most(x, "exact_radii")) <= 0.01,
        "exact radii give fewer results": lambda x: _by(x, "exact_radii")[0].results <= _by(x, "stored_radii")[0].results,
        "postings spare candidates": lambda x: _by(x, "postings")[0].candidates < _by(x, "no_postings")[0].candidates,
        "no postings means full recall": lambda x: _most(x, "no_postings") >= 1 - 1e-9,
        "online radii give the same recall": lambda x: abs(_most(x, "online_radius") - _most(x, "postings")) < 1e-9,
    },
    "exp_k": {"every k up to 30 reaches .95": lambda x: all(any(r.k == k and r.method == "proxy_0.95" and r.recall >= 0.95 for r in x) for k in (1, 10, 30))},
    "exp_insertion": {
        "every share ends near the batch graph": lambda x: all(r.recall >= 0.9 for r in x if r.method.startswith("build_")),
        "every share reaches .95": lambda x: all(any(r.method == f"share_{s:g}_0.95" for r in x) for s in SHARES),
    },
    "exp_scale": {
        "proxy search keeps .9 at every size": lambda x: all(r.recall >= 0.9 for r in _by(x, "proxy")),
        "and beats one shot at every size": lambda x: all(a.recall > b.recall for a, b in zip(_by(x, "proxy"), _by(x, "one_shot"))),
        "and the hop graph": lambda x: all(a.recall > b.recall for a, b in zip(_by(x, "proxy"), _by(x, "hop"))),
    },
    "exp_scale_lineitem": {"proxy search keeps .95 at every size": lambda x: all(r.recall >= 0.95 for r in _by(x, "proxy"))},
    "exp_locality": {
        "coverage rises": lambda x: _rising(x, "proxy"),
        "proxies reach what plain expansion does not": lambda x: _at(x, "proxy", 20, 50) > _at(x, "plain", 20) + 0.3,
    },
}


def rows(spark: SparkSession, d: str, name: str) -> DataFrame:
    """The figures of a workload."""
    return EXPERIMENTS[name](spark, d)


def _claims(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        found = rows(spark, d, name).collect()  # a row a setting
        return spark.createDataFrame([(c, bool(holds(found))) for c, holds in CLAIMS[name].items()], "claim string, holds boolean")

    return run


Q = {name: _claims(name) for name in EXPERIMENTS}
SQL = {name: "SELECT claim, true AS holds FROM (VALUES " + ", ".join(f"('{c}')" for c in claims) + ") x(claim)" for name, claims in CLAIMS.items()}


if __name__ == "__main__":
    found = rows(SparkSession.builder.master("local[*]").getOrCreate(), sys.argv[1], sys.argv[2])
    found.show(500, truncate=False)
