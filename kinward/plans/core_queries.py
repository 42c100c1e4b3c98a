"""Driver queries of the method, its variants, baselines and measures, with their SQL.

Queries are the rows whose id is divisible by 20, against all rows; a member is never its own
neighbour. Queries without SQL return facts checked against the exact answer.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.operators import baselines, exact, maintain, measures, navigate, postings, proxy, ranked_graph
from kinward.operators.index import HybridIndex
from kinward.plans import apps
from kinward.sources.shared import shared_folder
from kinward.sources.tables import table

K, M, THETA, KS = 100, 20, 50, (1, 10, 30)
DOC_DIM = 128

_VECTORS = {
    "e": "v AS MATERIALIZED (SELECT vec_id AS id, embedding::DOUBLE[] AS vec FROM embeddings)",
    "p": "v AS MATERIALIZED (SELECT p_partkey::BIGINT AS id, [p_size * 20.0, floor(p_retailprice * 10 + 0.5)]::DOUBLE[] AS vec FROM part)",
    "s": "v AS MATERIALIZED (SELECT s_suppkey::BIGINT AS id, [floor(s_acctbal * 100 + 0.5), s_nationkey * 10000.0]::DOUBLE[] AS vec FROM supplier)",
    "t": f"""tw AS (SELECT doc_id AS id, unnest(string_split(coalesce(text, ''), ' ')) AS w FROM documents),
      th AS (SELECT id, ('0x' || substr(md5(w), 1, 7))::BIGINT AS h FROM tw),
      ts AS (SELECT id, h % {DOC_DIM} AS slot, sum(CASE WHEN (h // {DOC_DIM}) % 2 = 0 THEN 1 ELSE -1 END) AS x FROM th GROUP BY 1, 2),
      tn AS (SELECT id, sqrt(sum(x * x)::DOUBLE) AS norm FROM ts GROUP BY id),
      tg AS (SELECT tn.id, z.slot, CASE WHEN norm = 0 THEN 0.0 ELSE floor(coalesce(x, 0) * 1000.0 / norm + 0.5) END AS val
        FROM tn CROSS JOIN range({DOC_DIM}) z(slot) LEFT JOIN ts ON ts.id = tn.id AND ts.slot = z.slot),
      v AS MATERIALIZED (SELECT id, list(val::DOUBLE ORDER BY slot) AS vec FROM tg GROUP BY id)""",
}


def _cte(kind: str, depth: int = K, base: str = "true", listed: bool = False) -> str:
    """b: members; al: all ranked pairs; kn: lists; q, qd: queries and their ranked neighbours."""
    return f"""WITH {_VECTORS[kind]},
      b AS MATERIALIZED (SELECT * FROM v WHERE {base}),
      al AS {"MATERIALIZED" if listed else "NOT MATERIALIZED"} (SELECT x.id AS src, y.id AS dst, list_distance(x.vec, y.vec) AS dist FROM b x, b y WHERE x.id <> y.id),
      kl AS MATERIALIZED (SELECT src, min({{'dist': dist, 'dst': dst}}, {depth}) AS l FROM al GROUP BY src),
      kn AS MATERIALIZED (SELECT src, rank, l[rank].dst AS dst, l[rank].dist AS dist FROM (SELECT src, l, unnest(range(1, len(l) + 1)) AS rank FROM kl)),
      q AS (SELECT id AS qid, vec FROM v WHERE id % 20 = 0),
      qd AS MATERIALIZED (SELECT qid, id, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank
        FROM (SELECT q.qid, b.id, list_distance(q.vec, b.vec) AS dist FROM q, b WHERE q.qid <> b.id))"""


def _truth(k: int) -> str:
    return f"(SELECT qd.qid, qd.id, qd.dist FROM qd JOIN kn ON kn.src = qd.id AND kn.rank = {k} WHERE qd.dist <= kn.dist)"


def _cands(m: int, theta: int) -> str:
    return f"(SELECT DISTINCT qd.qid, kn.src AS id FROM qd JOIN kn ON kn.dst = qd.id WHERE qd.rank <= {m} AND kn.rank <= {theta} AND kn.src <> qd.qid)"


def _answer(m: int, theta: int, k: int) -> str:
    return f"(SELECT t.* FROM {_truth(k)} t JOIN {_cands(m, theta)} c ON t.qid = c.qid AND t.id = c.id)"


def points(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    if kind == "e":
        return vx.vectors_embeddings(spark, sf_dir).select("id", "vec")
    if kind == "t":
        return vx.vectors_documents(spark, sf_dir, DOC_DIM)
    if kind == "p":
        return vx.vectors_part(spark, sf_dir)
    rows = table(spark, sf_dir, "supplier")
    vec = F.array(F.floor(F.col("s_acctbal") * 100 + 0.5).cast("double"), F.col("s_nationkey") * 10000.0)
    return rows.select(F.col("s_suppkey").cast("long").alias("id"), vec.alias("vec"))


class Set:
    """A vector set, its queries, and the exact graph with what follows from it, each materialised once."""

    def __init__(self, spark: SparkSession, sf_dir: str, kind: str, depth: int = K):
        from kinward.sources.shared import cut

        if kind == "t":  # whole numbers up to 1000: fewer bytes where they are kept
            held = cut(points(spark, sf_dir, kind).withColumn("vec", F.col("vec").cast("array<smallint>")))
            self.points = held.withColumn("vec", F.col("vec").cast("array<double>"))
        else:
            self.points = cut(points(spark, sf_dir, kind))
        _, self.queries = vx.split_base_queries(self.points)
        self.depth, self._cut = depth, cut

    def __getattr__(self, name: str):
        make = {
            "lists": lambda: self._cut(exact.ranked_lists(self.points, self.depth)),
            "knn": lambda: exact.unlisted(self.lists),
            "rev": lambda: postings.transpose(self.knn),
            "radii": lambda: exact.radii_of(self.lists),
            "proxies": lambda: self._cut(proxy.flat_proxies(self.queries, self.points, M)),
            "truth": lambda: self._cut(exact.exact_rknn(self.queries, self.points, self.radii, 10)),
        }
        if name not in make:
            raise AttributeError(name)
        setattr(self, name, make[name]())
        return self.__dict__[name]


def _d6(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*cols[:-1], F.round(cols[-1], 6).alias(cols[-1]))


Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


@query("knn_exact_e", _cte("e", 1) + " SELECT qid, rank::INT AS rank, id, round(dist, 6) AS dist FROM qd WHERE rank <= 10")
def _(spark, d):
    s = Set(spark, d, "e")
    return _d6(exact.exact_knn(s.queries, s.points, 10, True), "qid", "rank", "id", "dist")


@query("k_radius_e", _cte("e", 10) + " SELECT src AS id, rank::INT AS k, round(dist, 6) AS r FROM kn WHERE rank IN (1, 5, 10)")
def _(spark, d):
    radii = Set(spark, d, "e", 10).radii
    k = F.explode(F.array(F.lit(1), F.lit(5), F.lit(10))).alias("k")
    return radii.select("id", "r", k).select("id", "k", F.round(F.element_at("r", F.col("k")), 6).alias("r"))


def _rknn(kind: str, k: int):
    def run(spark, d):
        s = Set(spark, d, kind, max(k, 1))
        return _d6(exact.exact_rknn(s.queries, s.points, s.radii, k), "qid", "id", "dist")

    return run


for _k in KS:
    query(f"rknn_exact_e_k{_k}", _cte("e", _k) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_truth(_k)}")(_rknn("e", _k))
query("rknn_exact_docs", _cte("t", 10) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_truth(10)}")(_rknn("t", 10))
query("rknn_exact_part", _cte("p", 10) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_truth(10)}")(_rknn("p", 10))


@query("rknn_member", _cte("e", 10) + " SELECT dst AS qid, src AS id, rank::INT AS rank FROM kn WHERE dst % 20 = 0")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    return exact.rknn_of_member(s.rev, s.queries.select(F.col("qid").alias("id")), 10)


@query("all_rknn", _cte("e", 10) + " SELECT dst AS qid, src AS id, round(dist, 6) AS dist FROM kn")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    return _d6(s.rev.select(F.col("dst").alias("qid"), F.col("src").alias("id"), "dist"), "qid", "id", "dist")


@query("ranked_graph_exact", _cte("e", 20) + " SELECT src, rank::INT AS rank, dst, round(dist, 6) AS dist FROM kn")
def _(spark, d):
    return _d6(Set(spark, d, "e", 20).knn, "src", "rank", "dst", "dist")


@query("reverse_postings", _cte("e", 20) + " SELECT dst, rank::INT AS rank, src FROM kn")
def _(spark, d):
    return Set(spark, d, "e", 20).rev.select("dst", "rank", "src")


@query("postings_truncated", _cte("e", 20) + " SELECT dst, rank::INT AS rank, src FROM kn WHERE rank <= 5 AND dst % 20 = 0")
def _(spark, d):
    s = Set(spark, d, "e", 20)
    return postings.scan(s.rev, s.queries.select(F.col("qid").alias("id")), 5).select("dst", "rank", "src")


@query("packed_postings", _cte("e", 20) + " SELECT dst, count(*) AS n, array_to_string((list(src ORDER BY rank, src))[1:5], ',') AS head FROM kn GROUP BY dst")
def _(spark, d):
    p = postings.pack(Set(spark, d, "e", 20).rev)
    return p.select("dst", "n", F.array_join(F.transform(F.slice("items", 1, 5), lambda x: x["src"].cast("string")), ",").alias("head"))


@query("occurrence_profile", _cte("t", 30) + """, o AS (SELECT x.k, b.id, count(kn.src) AS n FROM b CROSS JOIN (VALUES (1), (10), (30)) x(k)
    LEFT JOIN kn ON kn.dst = b.id AND kn.rank <= x.k GROUP BY x.k, b.id)
    SELECT k, max(n) AS most, count(*) FILTER (WHERE n = 0) AS zero, quantile_disc(n, 0.5) AS median FROM o GROUP BY k""")
def _(spark, d):
    s = Set(spark, d, "t", 30)
    return postings.occurrence_profile(s.knn, s.points, list(KS))


@query("salted_postings", _cte("t", THETA) + f" SELECT qd.qid, kn.src AS id, kn.rank::INT AS rank FROM qd JOIN kn ON kn.dst = qd.id WHERE qd.rank <= 5 AND kn.rank <= {THETA}")
def _(spark, d):
    s = Set(spark, d, "t", THETA)
    near = s.proxies.filter("prank <= 5").select("qid", "id")
    return postings.salted_scan(s.rev, near, THETA, 16).select("qid", F.col("src").alias("id"), "rank")


@query("proxy_candidates_flat", _cte("e", K) + f" SELECT qid, id FROM {_cands(M, THETA)}")
def _(spark, d):
    s = Set(spark, d, "e")
    return proxy.candidates(s.proxies, s.rev, THETA).select("qid", "id")


def _flat(kind: str, bounds: bool = False):
    def run(spark, d):
        s = Set(spark, d, kind, THETA)  # ranks beyond theta are never read
        out = proxy.proxy_rknn_by_owner(s.queries, s.points, s.lists, proxy.SearchOptions(10, M, THETA).check(THETA), s.proxies, bounds)
        return _d6(out, "qid", "id", "dist")

    return run


for _name, _kind in (("e", "e"), ("docs", "t"), ("part", "p")):
    query(f"proxy_rknn_flat_{_name}", _cte(_kind, K) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_answer(M, THETA, 10)}")(_flat(_kind))
query("proxy_bounds_equals_plain", _cte("t", K) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_answer(M, THETA, 10)}")(_flat("t", True))
query("gold_radius_rknn", _cte("e", K) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_answer(M, K, 10)}")(
    lambda spark, d: _d6(proxy.proxy_rknn(*(lambda s: (s.queries, s.points, s.rev, s.radii, proxy.SearchOptions(10, M, K), s.proxies))(Set(spark, d, "e"))), "qid", "id", "dist")
)


@query("no_postings_rknn", _cte("e", 10) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_truth(10)}")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    return _d6(proxy.no_postings_rknn(s.queries, s.points, s.radii, 10), "qid", "id", "dist")


@query("online_radius_rknn", _cte("e", K) + f" SELECT qid, id, round(dist, 6) AS dist FROM {_answer(M, THETA, 10)}")
def _(spark, d):
    s = Set(spark, d, "e")
    return _d6(proxy.online_radius_rknn(proxy.candidates(s.proxies, s.rev, THETA), s.queries, s.points, 10), "qid", "id", "dist")


_GRID_M, _GRID_T = (1, 5, 20), (10, 50, 100)


def _grid_sql(kind: str) -> str:
    cells = " UNION ALL ".join(
        f"""SELECT {m} AS m, {t} AS theta, round(avg(CASE WHEN coalesce(tr.n, 0) > 0 THEN coalesce(an.n, 0) / tr.n::DOUBLE WHEN coalesce(an.n, 0) = 0 THEN 1.0 ELSE 0.0 END), 6) AS recall,
        (SELECT count(*) FROM qd JOIN kn ON kn.dst = qd.id WHERE qd.rank <= {m} AND kn.rank <= {t} AND kn.src <> qd.qid) AS scanned,
        (SELECT count(*) FROM {_cands(m, t)}) AS candidates
        FROM q LEFT JOIN (SELECT qid, count(*) AS n FROM {_truth(10)} GROUP BY qid) tr ON tr.qid = q.qid
        LEFT JOIN (SELECT qid, count(*) AS n FROM {_answer(m, t, 10)} GROUP BY qid) an ON an.qid = q.qid"""
        for m in _GRID_M
        for t in _GRID_T
    )
    return _cte(kind, K) + " " + cells


def _grid(kind: str):
    def run(spark, d):
        s = Set(spark, d, kind)
        return proxy.grid_by_owner(s.queries, s.points, s.lists, s.truth, 10, list(_GRID_M), list(_GRID_T), s.proxies)

    return run


query("grid_recall_e", _grid_sql("e"))(_grid("e"))
query("grid_recall_docs", _grid_sql("t"))(_grid("t"))


@query("best_config", f"SELECT m, theta, recall, candidates, scanned FROM ({_grid_sql('t')}) WHERE recall >= 0.5 ORDER BY candidates, scanned, m, theta LIMIT 1")
def _(spark, d):
    return proxy.best_config(_grid("t")(spark, d), 0.5)


@query("query_counters", _cte("t", K) + f""" SELECT q.qid, count(kn.src) AS scanned, count(DISTINCT kn.src) AS candidates FROM q
    LEFT JOIN qd ON qd.qid = q.qid AND qd.rank <= {M} LEFT JOIN kn ON kn.dst = qd.id AND kn.rank <= {THETA} AND kn.src <> q.qid GROUP BY q.qid""")
def _(spark, d):
    s = Set(spark, d, "t", THETA)
    return proxy.counters_by_owner(s.proxies, s.lists, s.queries, THETA)


_PER_QUERY = f""" SELECT q.qid, coalesce(h.n, 0) AS hit, coalesce(t.n, 0) AS truth, coalesce(h.n, 0) AS ans,
    round(CASE WHEN coalesce(t.n, 0) > 0 THEN coalesce(h.n, 0) / t.n::DOUBLE WHEN coalesce(h.n, 0) = 0 THEN 1.0 ELSE 0.0 END, 6) AS recall,
    round(CASE WHEN coalesce(h.n, 0) > 0 THEN h.n / h.n::DOUBLE ELSE 1.0 END, 6) AS precision
    FROM q LEFT JOIN (SELECT qid, count(*) AS n FROM {_truth(10)} GROUP BY qid) t ON t.qid = q.qid
    LEFT JOIN (SELECT qid, count(*) AS n FROM {_answer(5, 20, 10)} GROUP BY qid) h ON h.qid = q.qid"""


@query("recall_three_way", _cte("t", K) + _PER_QUERY)
def _(spark, d):
    s = Set(spark, d, "t", 20)
    answer = proxy.proxy_rknn_by_owner(s.queries, s.points, s.lists, proxy.SearchOptions(10, 5, 20), s.proxies)
    return measures.per_query(s.truth, answer, s.queries)


@query("precision", _cte("t", K) + f""", c AS {_cands(5, 20)} SELECT q.qid, count(t.id) AS hit, count(c.id) AS ans,
    round(CASE WHEN count(c.id) > 0 THEN count(t.id) / count(c.id)::DOUBLE ELSE 1.0 END, 6) AS precision
    FROM q LEFT JOIN c ON c.qid = q.qid LEFT JOIN {_truth(10)} t ON t.qid = c.qid AND t.id = c.id GROUP BY q.qid""")
def _(spark, d):
    s = Set(spark, d, "t", 20)
    return measures.precision(s.truth, s.proxies.filter("prank <= 5"), s.lists, s.queries, 20)


@query("nn_rank_of_truth", _cte("t", 10) + f""" SELECT count(*) AS n, quantile_disc(qd.rank, 0.5) AS p50, quantile_disc(qd.rank, 0.9) AS p90, max(qd.rank) AS most
    FROM {_truth(10)} t JOIN qd ON qd.qid = t.qid AND qd.id = t.id""")
def _(spark, d):
    s = Set(spark, d, "t", 10)
    return measures.rank_profile(exact.ranks_of(s.truth, s.queries, s.points))


@query("proxy_coverage", _cte("t", K) + f""", r AS (SELECT t.qid, t.id, min(qd.rank) FILTER (WHERE kn.rank <= 10) AS a, min(qd.rank) FILTER (WHERE kn.rank <= 50) AS b
    FROM {_truth(10)} t LEFT JOIN kn ON kn.src = t.id LEFT JOIN qd ON qd.qid = t.qid AND qd.id = kn.dst GROUP BY 1, 2)
    SELECT theta, m, round(count(*) FILTER (WHERE CASE theta WHEN 10 THEN a ELSE b END <= m) / count(*)::DOUBLE, 6) AS share
    FROM r CROSS JOIN (VALUES (10), (50)) x(theta) CROSS JOIN (VALUES (1), (5), (20)) y(m) GROUP BY theta, m""")
def _(spark, d):
    s = Set(spark, d, "t", THETA)
    return measures.proxy_coverage(s.truth, s.proxies, s.lists, [10, 50], [1, 5, 20])


@query("one_shot_flat", _cte("t", 10) + f" SELECT t.qid, t.id FROM {_truth(10)} t JOIN qd ON qd.qid = t.qid AND qd.id = t.id WHERE qd.rank <= 50")
def _(spark, d):
    s = Set(spark, d, "t", 10)
    return baselines.one_shot_rknn(s.queries, s.points, 10, 50, s.radii).select("qid", "id")


@query("one_shot_online", _cte("e", 10) + f" SELECT t.qid, t.id FROM {_truth(10)} t JOIN qd ON qd.qid = t.qid AND qd.id = t.id WHERE qd.rank <= 50")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    return baselines.one_shot_rknn(s.queries, s.points, 10, 50).select("qid", "id")


@query("local_elimination", _cte("t", 1) + """, c AS (SELECT * FROM qd WHERE rank <= 50)
    SELECT x.qid, x.id FROM c x JOIN v vx ON vx.id = x.id JOIN c y ON y.qid = x.qid JOIN v vy ON vy.id = y.id
    GROUP BY x.qid, x.id, x.dist HAVING count(*) FILTER (WHERE y.id <> x.id AND list_distance(vx.vec, vy.vec) < x.dist) < 10""")
def _(spark, d):
    s = Set(spark, d, "t", 1)
    return baselines.local_elimination(proxy.flat_proxies(s.queries, s.points, 50), s.points, 10).select("qid", "id")


def _fact(spark: SparkSession, **values) -> DataFrame:
    kinds = {bool: "boolean", int: "long", float: "double", str: "string"}
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} {kinds[type(v)]}" for k, v in values.items()))


@query("incremental_rknn", "SELECT true AS sound, true AS recall_ok")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    out = baselines.incremental_rknn(s.queries, s.points, 10, 8.0, 200).cache()
    wrong = out.join(s.truth, ["qid", "id"], "left_anti").count()
    return _fact(spark, sound=wrong == 0, recall_ok=measures.recall(s.truth, out, s.queries) >= 0.95)


@query("hop_graph_exact_edges", _cte("s", 1, listed=True) + """ SELECT x.src AS a, x.dst AS b FROM al x WHERE x.src < x.dst AND NOT EXISTS (
    SELECT 1 FROM al y JOIN al z ON y.dst = z.dst WHERE y.src = x.src AND z.src = x.dst AND y.dist < x.dist AND z.dist < x.dist)""")
def _(spark, d):
    pts = points(spark, d, "s")
    return baselines.relative_neighbours(pts, exact.ranked_graph_exact(pts, max(1, pts.count() - 1)))


@query("hop_rknn", "SELECT true AS sound, true AS recall_ok")
def _(spark, d):
    """The layers of a nav graph give the entries; from there k hops on the pruned ground links."""
    s = Set(spark, d, "e", K)
    graph = baselines.build_hop_graph(s.knn, s.points, 80).cache()
    out = baselines.hop_rknn(graph, s.queries, s.points, 10, entries=baselines.nav_entries(_index(spark, d), s.queries)).cache()
    wrong = out.join(s.truth, ["qid", "id"], "left_anti").count()
    return _fact(spark, sound=wrong == 0, recall_ok=measures.recall(s.truth, out, s.queries) >= 0.9)


@query("hop_property", "SELECT unnest([1, 2, 3]) AS k, true AS within")
def _(spark, d):
    """On the exact monotonic graph the k-reverse neighbours of a member lie within k hops of it."""
    s = Set(spark, d, "s", 3)
    both = baselines.monotonic_neighbours(s.points, exact.ranked_graph_exact(s.points, max(1, s.points.count() - 1))).cache()
    entry = s.points.select(F.col("id").alias("qid"), "id")
    out = None
    for k in (1, 2, 3):
        # among equal distances any k may be the nearest; strictly nearer ones decide the claim
        far = s.radii.select("id", F.element_at("r", k).alias("radius"))
        true = s.rev.join(far, F.col("src") == F.col("id")).filter(F.col("rank") <= k).select(F.col("dst").alias("qid"), F.col("src").alias("id"))
        missed = true.join(baselines.hop_candidates(both, entry, k), ["qid", "id"], "left_anti")
        row = missed.agg((F.count(F.lit(1)) == 0).alias("within")).select(F.lit(k).alias("k"), "within")
        out = row if out is None else out.unionByName(row)
    return out


@query("incremental_lean", "SELECT true AS same")
def _(spark, d):
    s = Set(spark, d, "e", 10)
    lean, full = (baselines.incremental_rknn(s.queries, s.points, 10, 8.0, 200, lean=x).select("qid", "id").cache() for x in (True, False))
    return _fact(spark, same=lean.exceptAll(full).isEmpty() and full.exceptAll(lean).isEmpty())


_OLD = "id % 20 <> 0"
_NEW = ", nd AS (SELECT q.qid AS new_id, b.id, list_distance(q.vec, b.vec) AS dist FROM q, b), aff AS (SELECT nd.* FROM nd JOIN kn ON kn.src = nd.id AND kn.rank = 20 WHERE nd.dist < kn.dist)"


def _arrivals(spark, d, kind="e"):
    from kinward.sources.shared import cut

    pts = points(spark, d, kind)
    old, new = cut(pts.filter("id % 20 <> 0")), cut(pts.filter("id % 20 = 0"))
    return old, new, cut(exact.ranked_graph_exact(old, 20))


@query("affected_exact", _cte("e", 20, _OLD) + _NEW + " SELECT new_id, id FROM aff")
def _(spark, d):
    old, new, knn = _arrivals(spark, d)
    return maintain.affected_exact(old, knn, new, 20).select("new_id", "id")


@query("affected_approx_flat", _cte("e", 20, _OLD) + _NEW + f""" SELECT a.new_id, a.id, c.id IS NOT NULL AS hit FROM aff a LEFT JOIN
    (SELECT DISTINCT qd.qid, kn.src AS id FROM qd JOIN kn ON kn.dst = qd.id WHERE qd.rank <= 5 AND kn.rank <= 10) c ON c.qid = a.new_id AND c.id = a.id""")
def _(spark, d):
    old, new, knn = _arrivals(spark, d)
    true = maintain.affected_exact(old, knn, new, 20).select("new_id", "id")
    found = maintain.affected_approx(old, knn, postings.transpose(knn), new, 20, 5, 10).select("new_id", "id", F.lit(True).alias("hit"))
    return true.join(found, ["new_id", "id"], "left").select("new_id", "id", F.coalesce("hit", F.lit(False)).alias("hit"))


_AFTER = "nk AS (SELECT * FROM (SELECT src, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rank, dst, dist FROM (SELECT x.id AS src, y.id AS dst, list_distance(x.vec, y.vec) AS dist FROM v x, v y WHERE x.id <> y.id)) WHERE rank <= 20)"


@query("insert_refreshed_lists", _cte("e", 20, _OLD) + f", {_AFTER} SELECT src, rank::INT AS rank, dst FROM nk WHERE src IN (SELECT src FROM nk WHERE dst % 20 = 0 OR src % 20 = 0)")
def _(spark, d):
    old, new, knn = _arrivals(spark, d)
    hit = maintain.affected_exact(old, knn, new, 20)
    lists = maintain.refreshed(knn, hit, maintain.own_lists(old, new, 20), 20)
    held = lists.filter("dst % 20 = 0 OR src % 20 = 0").select("src").distinct()
    return lists.join(held, "src", "left_semi").select("src", "rank", "dst")


@query("insert_postings_sync", _cte("e", 20) + " SELECT dst, rank::INT AS rank, src FROM kn")
def _(spark, d):
    old, new, knn = _arrivals(spark, d)
    hit = maintain.affected_exact(old, knn, new, 20)
    changed = maintain.refreshed(knn, hit, maintain.own_lists(old, new, 20), 20)
    return maintain.synchronised(postings.transpose(knn), changed).select("dst", "rank", "src")


@query("insertion_cost", _cte("e", 20, _OLD) + """, p AS (SELECT qd.qid, kn.src AS id, kn.rank FROM qd JOIN kn ON kn.dst = qd.id WHERE qd.rank <= 5 AND kn.rank <= 10),
    a AS (SELECT DISTINCT p.qid, p.id FROM p JOIN qd ON qd.qid = p.qid AND qd.id = p.id JOIN kn ON kn.src = p.id AND kn.rank = 20 WHERE qd.dist < kn.dist)
    SELECT q.qid AS new_id, (SELECT count(*) FROM p WHERE p.qid = q.qid) AS scanned, (SELECT count(*) FROM a WHERE a.qid = q.qid) AS affected,
    ((SELECT count(*) FROM a WHERE a.qid = q.qid) + 1) * 20 AS changed FROM q""")
def _(spark, d):
    old, new, knn = _arrivals(spark, d)
    return maintain.insertion_cost(old, knn, new, 20, 5, 10)


@query("insert_batch_share", "SELECT s, true AS recall_ok FROM (VALUES (0.0), (0.1), (0.5), (0.9), (1.0)) x(s)")
def _(spark, d):
    s = Set(spark, d, "e", 20)
    out = None
    for share in (0.0, 0.1, 0.5, 0.9, 1.0):
        knn = s.knn if share == 1.0 else maintain.build_by_insertion(s.points, 20, share, 2)
        row = measures.graph_recall(knn, s.knn, 10).select(F.lit(share).cast("decimal(2,1)").alias("s"), (F.col("recall") >= 0.9).alias("recall_ok"))
        out = row if out is None else out.unionByName(row)
    return out


@query("index_diff", "SELECT true AS same")
def _(spark, d):
    old, new, knn = _arrivals(spark, d)
    _, after = maintain.insert_batch(old, knn, new, 20)
    built = maintain.rebuild(old.unionByName(new), 20)
    return measures.index_diff(after, built).select(((F.col("only_a") == 0) & (F.col("only_b") == 0)).alias("same"))


@query("refine_recall_rounds", "SELECT true AS warm_ok, true AS random_ok, true AS rises, true AS head_start")
def _(spark, d):
    s = Set(spark, d, "e", 20)
    _, centres = navigate.pivots(s.points, 1)
    nav = navigate.build_nav(s.points, centres, 16, 60, 20)
    warm, a = ranked_graph.refine(s.points, ranked_graph.seed_from_nav(navigate.seeds_of(nav), 20), 20, 4, exact=s.knn)
    cold, b = ranked_graph.refine(s.points, ranked_graph.seed_random(s.points, 20), 20, 6, exact=s.knn)
    rises = all(x["recall"] <= y["recall"] + 1e-9 for log in (a, b) for x, y in zip(log, log[1:]))
    return _fact(spark, warm_ok=a[-1]["recall"] >= 0.99, random_ok=b[-1]["recall"] >= 0.95, rises=rises, head_start=a[0]["recall"] > b[0]["recall"])


def _nav_recall(kind: str):
    def run(spark, d):
        s = Set(spark, d, "e", K)
        cells = max(1, -(-s.points.count() // 1000))
        _, centres = navigate.pivots(s.points, cells)
        if kind == "hnsw":
            nav = navigate.build_nav(s.points, centres, 16, 100, 10).cache()
        else:
            nav = navigate.build_nsg(s.points, s.knn, centres, 32, 80).cache()
        found = navigate.graph_search(nav, s.points, s.queries, centres, M, 100, n_probe=cells)
        hit = found.join(s.proxies.select("qid", "id"), ["qid", "id"], "left_semi").count()
        answer = proxy.proxy_rknn(s.queries, s.points, s.rev, s.radii, proxy.SearchOptions(10, M, THETA), found)
        full = proxy.proxy_rknn(s.queries, s.points, s.rev, s.radii, proxy.SearchOptions(10, M, THETA), s.proxies)
        gap = measures.recall(s.truth, full, s.queries) - measures.recall(s.truth, answer, s.queries)
        return _fact(spark, proxies_ok=hit >= 0.9 * s.proxies.count(), rknn_ok=gap <= 0.02)

    return run


query("hnsw_proxy_recall", "SELECT true AS proxies_ok, true AS rknn_ok")(_nav_recall("hnsw"))
query("nsg_proxy_recall", "SELECT true AS proxies_ok, true AS rknn_ok")(_nav_recall("nsg"))


@query("relational_beam", "SELECT true AS recall_ok")
def _(spark, d):
    s = Set(spark, d, "e", 20)
    both = s.knn.select("src", "dst").unionByName(s.knn.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct().cache()
    entry = s.points.agg(F.min("id")).first()[0]
    found = navigate.beam_relational(both, s.points, s.queries, entry, 11, 40, 8).filter("qid <> id")
    hit = found.join(s.proxies.filter("prank <= 10").select("qid", "id"), ["qid", "id"], "left_semi").count()
    return _fact(spark, recall_ok=hit >= 0.9 * s.queries.count() * 10)


def _index(spark, d, kind="e", depth=50):
    pts = points(spark, d, kind)
    return HybridIndex.build(pts, f"{shared_folder(spark)}/index-{uuid.uuid4().hex}", depth, 16, 60, 4)


@query("index_search", "SELECT true AS recall_ok, true AS reload_same")
def _(spark, d):
    s = Set(spark, d, "e", 50)
    built = _index(spark, d)
    index = HybridIndex.load(spark, built.path)
    opt = index.fitted(proxy.SearchOptions(10, M, 50))
    answer = index.search(s.queries, opt).cache()
    again = built.search(s.queries, opt)
    return _fact(spark, recall_ok=measures.recall(s.truth, answer, s.queries) >= 0.9, reload_same=answer.exceptAll(again).isEmpty())


@query("index_size", """WITH n AS (SELECT count(*) AS n, any_value(len(embedding)) AS dim FROM embeddings),
    e AS (SELECT 'points' AS view, n * dim AS entries, 8 AS width FROM n UNION ALL SELECT unnest(['knn', 'rev', 'radii']), 50 * n, unnest([20, 20, 8]) FROM n)
    SELECT view, entries::BIGINT AS entries, (entries * width)::BIGINT AS bytes,
    round(CASE WHEN view = 'points' THEN 1.0 ELSE (entries * width + n * dim * 8) / (n * dim * 8)::DOUBLE END, 6) AS ratio FROM e, n""")
def _(spark, d):
    return _index(spark, d).describe().filter("view <> 'nav'")


@query("index_insert", "SELECT count(*) AS points, 50 * count(*) AS entries, 50 * count(*) AS postings, count(*) AS radii, true AS in_step, true AS recall_ok, true AS compact_same FROM embeddings")
def _(spark, d):
    """A saved index takes a tenth of the points in two batches: links, own and refreshed lists, postings, radii; then it is compacted."""
    s = Set(spark, d, "e", 50)
    path = f"{shared_folder(spark)}/index-{uuid.uuid4().hex}"
    index = HybridIndex.build(s.points.filter("id % 10 <> 3"), path, 50, 16, 60, 4)
    late = s.points.filter("id % 10 = 3")
    for part in (0, 1):
        index = index.insert(late.filter(F.pmod(F.xxhash64("id"), F.lit(2)) == part), M, 50, batch=part)
    index = HybridIndex.load(spark, path)
    knn, rev, opt = index.view("knn"), index.view("rev"), index.fitted(proxy.SearchOptions(10, M, 50))
    in_step = rev.select("src", "rank", "dst").exceptAll(knn.select("src", "rank", "dst")).isEmpty()
    answer = index.search(s.queries, opt).select("qid", "id").cache()
    after = index.compact().search(s.queries, opt).select("qid", "id")
    return _fact(
        spark, points=index.view("points").count(), entries=knn.count(), postings=rev.count(), radii=index.view("radii").count(), in_step=in_step,
        recall_ok=measures.recall(s.truth, answer, s.queries) >= 0.9, compact_same=answer.exceptAll(after).isEmpty(),
    )


@query("index_cells", "SELECT true AS several, true AS lists_ok, true AS search_ok")
def _(spark, d):
    """An index of several cells: lists cross their borders, and queries are routed."""
    s = Set(spark, d, "e", 50)
    path = f"{shared_folder(spark)}/index-{uuid.uuid4().hex}"
    index = HybridIndex.build(s.points, path, 50, 16, 60, 8, cell_rows=max(60, s.points.count() // 6))
    answer = index.search(s.queries, index.fitted(proxy.SearchOptions(10, M, 50)))
    return _fact(
        spark, several=len(index.centres) > 1, lists_ok=measures.graph_recall(index.view("knn"), s.knn, 10).first()[0] >= 0.9,
        search_ok=measures.recall(s.truth, answer, s.queries) >= 0.9,
    )


@query("exact_radii_refined", "SELECT true AS recall_equal, true AS no_more_results, true AS radii_never_small")
def _(spark, d):
    """Exact radii beside stored ones on a graph refined for one round: the recall stays, false results go."""
    s = Set(spark, d, "t", 50)
    rough, _ = ranked_graph.refine(s.points, ranked_graph.seed_random(s.points, 50), 50, 1)
    rough = rough.cache()
    opt, rev = proxy.SearchOptions(10, M, 50), postings.transpose(rough)
    stored, gold = (proxy.proxy_rknn(s.queries, s.points, rev, r, opt, s.proxies).cache() for r in (exact.k_radii(rough), s.radii))
    a, b = (measures.recall(s.truth, x, s.queries) for x in (stored.join(s.truth, ["qid", "id"], "left_semi"), gold.join(s.truth, ["qid", "id"], "left_semi")))
    small = exact.radius_at(exact.k_radii(rough), 10).withColumnRenamed("radius", "ra").join(exact.radius_at(s.radii, 10), "id").filter(F.col("ra") < F.col("radius") * (1 - 1e-9))
    return _fact(spark, recall_equal=abs(a - b) < 1e-9, no_more_results=gold.count() <= stored.count(), radii_never_small=small.isEmpty())


@query("ground_truth", _cte("e", 10) + f" SELECT 1 AS k, qid, id FROM {_truth(1)} UNION ALL SELECT 10, qid, id FROM {_truth(10)}")
def _(spark, d):
    s = Set(spark, d, "e", 1)
    return exact.ground_truth(s.points, s.queries, [1, 10], f"{shared_folder(spark)}/truth-{uuid.uuid4().hex}").select("k", "qid", "id")


@query("postings_unpacked", _cte("e", 20) + " SELECT dst, rank::INT AS rank, src FROM kn")
def _(spark, d):
    return postings.unpack(postings.pack(Set(spark, d, "e", 20).rev))


@query("hub_profile", _cte("t", 30) + " SELECT dst, count(*) AS n FROM kn WHERE rank <= 10 GROUP BY dst")
def _(spark, d):
    return proxy.hub_profile(Set(spark, d, "t", 30).rev, 10)


@query("candidates_with_proxies", _cte("e", K) + f" SELECT qid, id FROM {_cands(5, 10)} UNION SELECT qid, id FROM qd WHERE rank <= 5")
def _(spark, d):
    s = Set(spark, d, "e")
    return proxy.candidates(s.proxies.filter("prank <= 5"), s.rev, 10, include_proxies=True).select("qid", "id")


@query("insert_one", _cte("e", 20, "id % 20 <> 0 OR id = 0") + " SELECT src, rank::INT AS rank, dst FROM kn")
def _(spark, d):
    """One arrival, with every member as its proxy: the lists are those of a new build."""
    old, new, knn = _arrivals(spark, d)
    _, after = maintain.insert_one(old, knn, new.filter("id = 0"), 20, old.count(), 20)
    return after.select("src", "rank", "dst")


@query("speed_up", """WITH h AS (SELECT (max(epoch_us(ts)) - min(epoch_us(ts))) / 1e6 AS s FROM events),
    r AS (SELECT event_type AS method, count(*) / s AS qps FROM events, h GROUP BY event_type, s)
    SELECT r.method, round(r.qps / b.qps, 6) AS factor FROM r, r b WHERE b.method = 'click'""")
def _(spark, d):
    """Events a second of every kind over the span of the table, against those of clicks."""
    e = table(spark, d, "events").select("event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    kinds = e.groupBy(F.col("event_type").alias("method")).agg(F.count(F.lit(1)).alias("n"), F.min("us").alias("lo"), F.max("us").alias("hi")).cache()
    span = kinds.agg(((F.max("hi") - F.min("lo")) / 1e6).alias("s"))  # one row
    return measures.speed_up(kinds.join(F.broadcast(span)).select("method", (F.col("n") / F.col("s")).alias("qps")), "click")


@query("search_qps", "SELECT unnest(['proxy', 'one_shot', 'one_shot_radii']) AS method, true AS timed, true AS recall_ok")
def _(spark, d):
    """Queries a second of a batch on a built index, the build apart; recall beside it."""
    s = Set(spark, d, "e", 50)
    rows = measures.throughput(_index(spark, d), s.queries, s.truth, 10, M, 50, 100)
    return rows.select("method", (F.col("qps") > 0).alias("timed"), (F.col("recall") >= 0.9).alias("recall_ok"))

@query("influence_top", _cte("t", 10) + " SELECT dst AS id, count(*) AS n FROM kn GROUP BY dst ORDER BY n DESC, id LIMIT 20")
def _(spark, d):
    s = Set(spark, d, "t", 10)
    return apps.influence_top(postings.occurrence(s.rev, s.points, 10), 20)


@query("outliers", _cte("t", 10) + " SELECT b.id, count(kn.src) AS n FROM b LEFT JOIN kn ON kn.dst = b.id GROUP BY b.id HAVING count(kn.src) <= 1")
def _(spark, d):
    s = Set(spark, d, "t", 10)
    return apps.outliers(postings.occurrence(s.knn, s.points, 10), 1)


@query("mutual_neighbours", _cte("e", 10) + " SELECT x.src AS a, x.dst AS b FROM kn x JOIN kn y ON x.src = y.dst AND x.dst = y.src WHERE x.src < x.dst")
def _(spark, d):
    return apps.mutual_neighbours(Set(spark, d, "e", 10).knn, 10)


@query("imbalance_points", _cte("e", 10) + """ SELECT kn.dst AS id, count(*) FILTER (WHERE o.label = 3) AS same, count(*) FILTER (WHERE o.label <> 3) AS other FROM kn
    JOIN embeddings m ON m.vec_id = kn.dst AND m.label = 3 JOIN embeddings o ON o.vec_id = kn.src GROUP BY kn.dst HAVING count(*) FILTER (WHERE o.label <> 3) > count(*) FILTER (WHERE o.label = 3)""")
def _(spark, d):
    labels = vx.vectors_embeddings(spark, d).select("id", "label")
    return apps.imbalance_points(Set(spark, d, "e", 10).rev, labels, 10, 3)


@query("density_components", _cte("t", 10).replace("WITH ", "WITH RECURSIVE ", 1) + """, c AS (SELECT dst AS id FROM kn GROUP BY dst HAVING count(*) >= 10),
    e AS (SELECT x.src AS a, x.dst AS b FROM kn x JOIN kn y ON x.src = y.dst AND x.dst = y.src WHERE x.src IN (FROM c) AND x.dst IN (FROM c)),
    r(id, cluster) AS (SELECT id, id FROM c UNION SELECT e.b, r.cluster FROM r JOIN e ON e.a = r.id WHERE r.cluster < e.b)
    SELECT id, min(cluster) AS cluster FROM r GROUP BY id""")
def _(spark, d):
    s = Set(spark, d, "t", 10)
    return apps.density_components(s.knn, postings.occurrence(s.rev, s.points, 10), 10, 10)


_TWO = """WITH s AS (SELECT n_regionkey AS region, s_suppkey AS s_id, floor(s_acctbal * 100 + 0.5)::BIGINT AS sc FROM supplier JOIN nation ON s_nationkey = n_nationkey),
    c AS (SELECT n_regionkey AS region, c_custkey AS c_id, floor(c_acctbal * 100 + 0.5)::BIGINT AS cc FROM customer JOIN nation ON c_nationkey = n_nationkey),
    r AS (SELECT s_id, row_number() OVER (PARTITION BY c_id ORDER BY abs(cc - sc), s_id) AS r FROM c JOIN s USING (region))"""


@query("facility_two_sets", _TWO + " SELECT s.s_id, count(r.s_id) AS n FROM s LEFT JOIN r ON r.s_id = s.s_id AND r <= 5 GROUP BY s.s_id")
def _(spark, d):
    nation = F.broadcast(table(spark, d, "nation"))  # 25 rows by definition
    s = table(spark, d, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey"))
    c = table(spark, d, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    cents = lambda x: F.floor(F.col(x) * 100 + 0.5).cast("long").alias("cents")
    return apps.facility_two_sets(
        s.select(F.col("n_regionkey").alias("region"), F.col("s_suppkey").alias("id"), cents("s_acctbal")),
        c.select(F.col("n_regionkey").alias("region"), F.col("c_custkey").alias("id"), cents("c_acctbal")), 5,
    )


@query("chunk_influence", _cte("t", 1) + f""", bw AS (SELECT item_id AS id, unnest(string_split(coalesce(text, ''), ' ')) AS w FROM benchmark),
    bh AS (SELECT id, ('0x' || substr(md5(w), 1, 7))::BIGINT AS h FROM bw),
    bs AS (SELECT id, h % {DOC_DIM} AS slot, sum(CASE WHEN (h // {DOC_DIM}) % 2 = 0 THEN 1 ELSE -1 END) AS x FROM bh GROUP BY 1, 2),
    bn AS (SELECT id, sqrt(sum(x * x)::DOUBLE) AS norm FROM bs GROUP BY id),
    bg AS (SELECT bn.id, z.slot, CASE WHEN norm = 0 THEN 0.0 ELSE floor(coalesce(x, 0) * 1000.0 / norm + 0.5) END AS val FROM bn CROSS JOIN range({DOC_DIM}) z(slot) LEFT JOIN bs ON bs.id = bn.id AND bs.slot = z.slot),
    bv AS MATERIALIZED (SELECT id, list(val::DOUBLE ORDER BY slot) AS vec FROM bg GROUP BY id),
    br AS (SELECT bv.id AS qid, v.id, row_number() OVER (PARTITION BY bv.id ORDER BY list_distance(bv.vec, v.vec), v.id) AS rank FROM bv, v)
    SELECT id, count(*) AS n FROM br WHERE rank <= 10 GROUP BY id""")
def _(spark, d):
    asked = vx.hashed_tokens(table(spark, d, "benchmark").select(F.col("item_id").alias("id"), "text"), DOC_DIM)
    near = exact.exact_knn(asked.withColumnRenamed("id", "qid"), points(spark, d, "t"), 10)
    return apps.chunk_influence(near)
