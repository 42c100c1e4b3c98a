"""The hybrid index: nav graph, ranked graph, reverse postings and radii as versioned Parquet views.

Every view lies in folders by version. A version is visible once its manifest is written, so a
batch that fails, or runs again, leaves readers with the version before. A row of knn, rev and
radii is live if its owner's list has not been written since, a row of nav if its links have not;
``compact`` writes the live rows as a new base.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.operators import exact, maintain, navigate, postings, proxy, ranked_graph
from kinward.sources.shared import cut

VIEWS = ("points", "nav", "knn", "rev", "radii")
OWNER = {"knn": "src", "rev": "src", "radii": "id"}
NAV_KEY = ["kind", "cell", "layer", "src"]

#: Bytes of an entry of each view, without file format: a slot, a link, (id, rank, distance) twice, a distance.
#: Refinement works on lists of this length at least, which are cut to K at its end: short lists know too few neighbours of neighbours.
WORKING = 50

#: Width of searches is fitted on so many points of least hash, against brute force over all rows, until so much is found.
SAMPLE, TARGET = 200, 0.95

WIDTH = {"points": 8, "nav": 8, "knn": 20, "rev": 20, "radii": 8}


class _Least:
    """The fewest proxies by which each pair of a sample is reached."""

    def __init__(self, ranks: np.ndarray):
        self.ranks = np.sort(ranks)

    def within(self, m: int) -> int:
        """Proxies, m at least, that reach ``TARGET`` of the pairs; beyond any number if none do."""
        if not len(self.ranks):
            return m
        return max(m, int(self.ranks[int(np.ceil(TARGET * len(self.ranks))) - 1]))


def _least(pairs: DataFrame, near: DataFrame, rev: DataFrame, theta: int, include_proxies: bool) -> _Least:
    reach = proxy.candidate_postings(near, rev, theta).select("qid", "id", "prank")
    if include_proxies:
        reach = reach.unionByName(near.select("qid", "id", "prank"))
    rows = pairs.join(reach.groupBy("qid", "id").agg(F.min("prank").alias("least")), ["qid", "id"], "left")
    rows = rows.select(F.coalesce("least", F.lit(np.iinfo(np.int32).max)).cast("long").alias("least"))
    return _Least(rows.toPandas()["least"].to_numpy())  # pairs of a sample


@dataclass
class HybridIndex:
    spark: SparkSession
    path: str
    manifest: dict

    def _rows(self, name: str) -> DataFrame:
        rows = self.spark.read.parquet(f"{self.path}/{name}")
        return rows.filter(F.col("version").between(self.manifest["base"], self.manifest["version"]))

    def view(self, name: str) -> DataFrame:
        """The live rows of a view."""
        rows, base = self._rows(name), self.manifest["base"]
        own = [c for c in rows.columns if c != "version"]
        if name == "points" or self.manifest["version"] == base:
            return rows.select(own)
        key = NAV_KEY if name == "nav" else [OWNER[name]]
        if name == "nav":  # a cell has one entry, wherever it lies
            rows = rows.withColumn("kw_src", F.when(F.col("kind") == "entry", -1).otherwise(F.col("src")))
            rows = rows.withColumn("kw_layer", F.when(F.col("kind") == "entry", -1).otherwise(F.col("layer")))
            key = ["kind", "cell", "kw_layer", "kw_src"]
            last = rows.filter(F.col("version") > base).groupBy(*key).agg(F.max("version").alias("kw_last"))
        else:
            touched = self._rows("touched")
            last = touched.groupBy(F.col("src").alias(key[0])).agg(F.max("version").alias("kw_last"))
        live = rows.join(last, key, "left").filter(F.col("version") == F.coalesce("kw_last", F.lit(base)))
        return live.select(own)

    @property
    def centres(self) -> np.ndarray:
        return np.array(self.manifest["pivots"])

    @property
    def splits(self) -> np.ndarray:
        return np.array(self.manifest["splits"], np.int32)

    def _put(self, name: str, rows: DataFrame, version: int) -> None:
        rows.write.mode("overwrite").parquet(f"{self.path}/{name}/version={version}")

    def _commit(self, **changes) -> HybridIndex:
        manifest = self.manifest | changes
        text = self.spark.createDataFrame([(json.dumps(manifest),)], "manifest string")
        text.coalesce(1).write.mode("overwrite").text(f"{self.path}/manifest/version={manifest['version']}")
        return HybridIndex(self.spark, self.path, manifest)

    @staticmethod
    def build(
        points: DataFrame, path: str, K: int = 100, M: int = 16, ef_c: int = 100, max_iters: int = 6, seed_mode: str = "nav",
        cell_rows: int = navigate.CELL_ROWS, sample: int | None = None,
    ) -> HybridIndex:
        """Three phases: nav graph with its seeds, refinement, transposition; every view is written once."""
        spark = points.sparkSession
        dim = vx.checked(points)
        n = points.count()
        asked, K = K, max(1, min(K, n - 1))
        _, centres = navigate.pivots(points, max(1, -(-n // cell_rows)))
        splits = navigate.splits_of(points, centres, cell_rows)
        index = HybridIndex(spark, path, {
            "n": n, "dim": dim, "K": K, "K_asked": asked, "M": M, "ef_c": ef_c, "seed_mode": seed_mode, "version": 1, "base": 1,
            "pivots": centres.tolist(), "splits": splits.tolist(), "batch": -1,
        })
        index._put("points", navigate.assign_cells(points, centres, splits), 1)
        points = index.view("points")
        index._put("nav", navigate.build_nav(points, centres, M, ef_c, max(K, WORKING), splits), 1)
        seeds, deep = navigate.seeds_of(index.view("nav")), max(1, min(max(K, WORKING), n - 1))
        if seed_mode != "nav":
            start = ranked_graph.seed_random(points, deep)
        elif int(splits.sum()) == 1:
            start = ranked_graph.seed_from_nav(seeds, deep)
        else:
            start = ranked_graph.seed_mixed(points, seeds, deep)
        knn, log = ranked_graph.refine(points, start, deep, max_iters, sample=sample)
        index._put("knn", knn.filter(F.col("rank") <= K), 1)
        index._put("rev", postings.transpose(index.view("knn")), 1)
        index._put("radii", exact.k_radii(index.view("knn")), 1)
        return index._commit(rounds=log)

    @staticmethod
    def load(spark: SparkSession, path: str) -> HybridIndex:
        """The newest version that was finished."""
        rows = spark.read.text(f"{path}/manifest").orderBy(F.desc("version")).limit(1).select("value").first()
        return HybridIndex(spark, path, json.loads(rows[0]))

    def insert(self, new: DataFrame, m: int = 20, theta: int = 50, n_probe: int = 4, batch: int | None = None) -> HybridIndex:
        """The index with a batch of points (id, vec): nav links, own lists from the insertion search, refreshed lists, postings, radii.

        ``batch`` numbers the batches of a stream; one that was finished is passed over.
        """
        if batch is not None and batch <= self.manifest["batch"]:
            return self
        K, version = self.manifest["K"], self.manifest["version"] + 1
        new = cut(new.select("id", "vec"))
        added = new.count()
        numbered = self.manifest["batch"] if batch is None else batch
        if not added:
            return self._commit(batch=numbered)
        dim = vx.checked(new, "new points")
        old = self.view("points")
        if dim != self.manifest["dim"]:
            raise ValueError(f"new points have {dim} slots, the index {self.manifest['dim']}")
        if not old.join(new, "id", "left_semi").isEmpty():
            raise ValueError("new points repeat ids of the index")
        m, ef = self._insertion_width(new, m, min(theta, K), max(self.manifest["ef_c"], K, m))
        self._put("nav", navigate.nav_insert(self.view("nav"), old, new, self.centres, self.manifest["M"], ef, n_probe, self.splits), version)
        met = navigate.seeds_of(self.spark.read.parquet(f"{self.path}/nav/version={version}"))
        met = cut(met.filter("src <> dst").groupBy("src", "dst").agg(F.min("dist").alias("dist")))
        fresh = new.select(F.col("id").alias("dst"))
        both = met.unionByName(met.join(fresh, "dst", "left_semi").select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")).distinct()
        own = ranked_graph.top_k(both, K).select("src", "dst", "dist")
        members = ranked_graph.top_k(met.join(fresh, "dst", "left_anti"), m)
        near = members.select(F.col("src").alias("qid"), F.col("dst").alias("id"), F.col("rank").alias("prank"), F.col("dist").alias("pdist"))
        knn, rev = self.view("knn"), self.view("rev")
        hit = maintain.affected_approx(old, knn, rev, new, K, m, min(theta, K), near, True)
        changed = cut(maintain.refreshed(knn, hit, own, K))
        self._put("points", navigate.assign_cells(new, self.centres, self.splits), version)
        self._put("touched", changed.select("src").distinct(), version)
        self._put("knn", changed, version)
        self._put("rev", postings.transpose(changed), version)
        self._put("radii", exact.k_radii(changed), version)
        return self._commit(version=version, n=self.manifest["n"] + added, batch=numbered, widths=[m, ef])

    def _insertion_width(self, new: DataFrame, m: int, theta: int, ef: int) -> tuple[int, int]:
        """Proxies and beam, m and ef at least, by which a sample of new points finds its own lists and the members it affects."""
        K, points, knn, rev = self.manifest["K"], self.view("points").select("id", "vec"), self.view("knn"), self.view("rev")
        some = cut(new.orderBy(F.xxhash64("id", F.lit(3)), "id").limit(SAMPLE))
        asked = some.select(F.col("id").alias("qid"), "vec")
        own = cut(exact.exact_knn(asked, points, K).select("qid", "id"))
        hit = cut(maintain.affected_exact(points, knn, some, K).select(F.col("new_id").alias("qid"), "id"))
        wanted, n = own.count(), self.manifest["n"]
        while True:
            found = cut(self.proxies(asked, ef, ef))
            held = own.join(found, ["qid", "id"], "left_semi").count()
            wide = _least(hit, found, rev, theta, True).within(m)
            if held >= TARGET * wanted and wide <= ef or ef >= n:
                return min(wide, ef), ef
            ef *= 2

    def fitted(self, opt: proxy.SearchOptions) -> proxy.SearchOptions:
        """``opt`` with as many proxies as find ``TARGET`` of the true pairs of a sample of members, by brute force; never fewer than asked.

        The sample sets the width of the search only: every query is answered over all rows.
        """
        points, rev, m = self.view("points"), self.view("rev"), opt.m
        asked = cut(points.orderBy(F.xxhash64("id", F.lit(3)), "id").limit(SAMPLE).select(F.col("id").alias("qid"), "vec"))
        near = cut(exact.exact_rknn(asked, points, self.view("radii"), opt.k).select("qid", "id"))  # stored radii are never too small
        true = cut(proxy.online_radius_rknn(near, asked, points, opt.k).select("qid", "id"))
        while True:
            most = 4 * m
            ef = max(opt.ef or 64, 2 * most)
            least = _least(true, self.proxies(asked, most, ef), rev, opt.theta, False)
            wide = least.within(opt.m)
            if wide <= most or most >= self.manifest["n"]:
                return replace(opt, m=min(wide, most), ef=ef)
            m = most

    def compact(self) -> HybridIndex:
        """The live rows of all views as a new base; folders of older versions may be removed afterwards."""
        version = self.manifest["version"] + 1
        for name in VIEWS:
            self._put(name, self.view(name), version)
        return self._commit(version=version, base=version)

    def describe(self) -> DataFrame:
        """(view, entries, bytes, ratio): list entries, their bytes without file format, and (view + points) / points."""
        size = lambda name, e: self.view(name).agg(F.coalesce(F.sum(e), F.lit(0)).cast("long").alias("entries")).select(F.lit(name).alias("view"), "entries")
        out = size("points", F.size("vec"))
        for name, e in (("nav", F.when(F.col("kind") == "edge", F.size("dsts")).otherwise(0)), ("knn", F.lit(1)), ("rev", F.lit(1)), ("radii", F.size("r"))):
            out = out.unionByName(size(name, e))
        width = F.create_map(*[F.lit(x) for pair in WIDTH.items() for x in pair])
        base = self.manifest["n"] * self.manifest["dim"] * WIDTH["points"]
        out = out.withColumn("bytes", F.col("entries") * width[F.col("view")])
        more = F.when(F.col("view") == "points", 0).otherwise(F.col("bytes"))
        return out.withColumn("ratio", F.round((more + base) / base, 6))

    def file_bytes(self) -> dict[str, int]:
        """Bytes of every view's files, older versions included."""
        sc = self.spark.sparkContext
        out = {}
        for name in VIEWS:
            at = sc._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
            out[name] = int(at.getFileSystem(sc._jsc.hadoopConfiguration()).getContentSummary(at).getLength())
        return out

    def proxies(self, queries: DataFrame, m: int, ef: int, nav: str = "hnsw", n_probe: int = 4, width: int = 8) -> DataFrame:
        """The m nearest members by the nav graph; ``flat`` by a scan, ``relational`` by joins over the ground links, ``nsg`` by a flat graph."""
        points = self.view("points")
        if nav == "flat":
            return proxy.flat_proxies(queries, points, m)
        if nav == "nsg":
            graph = cut(navigate.build_nsg(points, self.view("knn"), self.centres))
            return navigate.graph_search(graph, points, queries, self.centres, m, ef, n_probe, splits=self.splits)
        if nav == "relational":
            links = self.view("knn").select("src", "dst").unionByName(self.view("rev").select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
            entry = points.agg(F.min_by("id", F.xxhash64("id"))).first()[0]
            found = navigate.beam_relational(links, points, queries, entry, m + 1, ef, width).filter("qid <> id")
            by = F.row_number().over(navigate.Window.partitionBy("qid").orderBy("pdist", "id"))
            return found.withColumn("prank", by).filter(F.col("prank") <= m)
        if nav != "hnsw":
            raise ValueError(f"no navigation called {nav}")
        return navigate.graph_search(self.view("nav"), points, queries, self.centres, m, ef, n_probe, splits=self.splits)

    def search(
        self, queries: DataFrame, opt: proxy.SearchOptions, nav: str = "hnsw", bounds: bool = True, radii: DataFrame | None = None
    ) -> DataFrame:
        """(qid, id, dist): reverse neighbours of the queries; ``radii`` replace the stored ones (an ablation)."""
        opt.check(self.manifest["K"])
        near = cut(self.proxies(queries, opt.m, opt.ef or max(2 * opt.m, 64), nav))
        points, rev, held = self.view("points"), self.view("rev"), self.view("radii") if radii is None else radii
        if near.count() >= self.manifest["n"]:  # a batch that reads as many postings as there are meets them at their owners
            return proxy.proxy_rknn_by_owner(queries, points, postings.by_owner(rev, opt.theta), opt, near, bounds, held)
        return proxy.proxy_rknn(queries, points, rev, held, opt, near, bounds)

    def all_rknn(self, k: int) -> DataFrame:
        """Influence join: reverse neighbours of every member."""
        return self.view("rev").filter(F.col("rank") <= k).select(F.col("dst").alias("qid"), F.col("src").alias("id"), "dist")

    def create_views(self, prefix: str = "") -> None:
        for name in VIEWS:
            self.view(name).createOrReplaceTempView(f"{prefix}{name}")
