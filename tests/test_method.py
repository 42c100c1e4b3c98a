"""Worked examples, invariants and accuracy of the reverse-neighbour operators."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from kinward.functions import vectors as vx
from kinward.operators import baselines, exact, maintain, measures, navigate, postings, proxy, ranked_graph
from kinward.operators.index import HybridIndex
from kinward.sources.shared import cut

SEVEN = {1: (2, 6), 2: (0, 0), 3: (5, 0), 4: (-16, -12), 5: (-20, -12), 6: (-6, -3), 7: (-12, -8)}


def frame(spark, rows, name="id"):
    return spark.createDataFrame([(i, [float(x) for x in v]) for i, v in rows], f"{name} long, vec array<double>")


@pytest.fixture(scope="module")
def seven(spark):
    points = frame(spark, SEVEN.items()).cache()
    knn = exact.ranked_graph_exact(points, 2).cache()
    return points, knn, postings.transpose(knn).cache(), exact.k_radii(knn).cache()


@pytest.fixture(scope="module")
def cloud(spark):
    rng = np.random.default_rng(1)
    points = frame(spark, enumerate(rng.normal(size=(120, 5)))).cache()
    queries = frame(spark, [(1000 + i, v) for i, v in enumerate(rng.normal(size=(12, 5)))], "qid").cache()
    return points, queries


def pairs(df, a="qid", b="id"):
    return sorted((r[a], r[b]) for r in df.select(a, b).collect())


def test_definition(spark):
    points = frame(spark, [(1, (-10, 0)), (2, (-9, 0)), (3, (0, 5)), (4, (2, 0))])
    radii = exact.k_radii(exact.ranked_graph_exact(points, 1))
    got = exact.exact_rknn(frame(spark, [(0, (0, 0))], "qid"), points, radii, 1)
    assert pairs(got) == [(0, 3), (0, 4)]


def test_ranked_graph_and_postings(seven):
    _, knn, rev, _ = seven
    lists = {r.src: (r.l[0], r.l[1]) for r in knn.groupBy("src").agg(F.transform(F.sort_array(F.collect_list(F.struct("rank", "dst"))), lambda x: x["dst"]).alias("l")).collect()}
    assert lists == {1: (2, 3), 2: (3, 1), 3: (2, 1), 4: (5, 7), 5: (4, 7), 6: (2, 7), 7: (4, 6)}
    packed = {r.dst: [(x.src, x["rank"]) for x in r["items"]] for r in postings.pack(rev).collect()}
    assert packed[2] == [(1, 1), (3, 1), (6, 1)] and packed[3] == [(2, 1), (1, 2)] and packed[7] == [(4, 2), (5, 2), (6, 2)]
    assert rev.count() == 14


def test_refinement_reaches_the_graph(seven):
    points, knn, _, _ = seven
    start = knn.filter("src <> 6").select("src", "rank", "dst", "dist").unionByName(
        ranked_graph.with_distance(points.sparkSession.createDataFrame([(6, 2), (6, 3)], "src long, dst long"), points).withColumn("rank", F.lit(1)).select("src", "rank", "dst", "dist")
    )
    out, _ = ranked_graph.refine(points, start, 2, 5)
    assert sorted(r.dst for r in out.filter("src = 6").collect()) == [2, 7]


def test_proxy_search(spark, seven):
    points, _, rev, radii = seven
    q = frame(spark, [(0, (5, -4))], "qid")
    near = proxy.flat_proxies(q, points, 2)
    assert [r.id for r in near.orderBy("prank").collect()] == [3, 2]
    assert pairs(proxy.candidates(near, rev, 1)) == [(0, 1), (0, 2), (0, 3), (0, 6)]
    counters = proxy.query_counters(near, rev, q, 1).first()
    assert (counters.scanned, counters.candidates) == (4, 4)
    for k, theta in ((1, 1), (2, 2)):
        assert pairs(proxy.proxy_rknn(q, points, rev, radii, proxy.SearchOptions(k, 2, theta))) == [(0, 3)]


def test_insertion(spark, seven):
    points, knn, rev, _ = seven
    new = frame(spark, [(8, (-6, -6))])
    assert pairs(maintain.affected_exact(points, knn, new, 2), "new_id") == [(8, 6), (8, 7)]
    approx = {mt: sorted(r.id for r in maintain.affected_approx(points, knn, rev, new, 2, *mt).collect()) for mt in ((1, 2), (2, 2), (2, 1))}
    assert approx == {(1, 2): [7], (2, 2): [6, 7], (2, 1): []}
    every, after = maintain.insert_batch(points, knn, new, 2)
    fresh = exact.ranked_graph_exact(every, 2)
    assert measures.index_diff(after, fresh).select("only_a", "only_b").first() == (0, 0)
    changed = maintain.refreshed(knn, maintain.affected_exact(points, knn, new, 2), maintain.own_lists(points, new, 2), 2)
    assert maintain.synchronised(rev, changed).exceptAll(postings.transpose(fresh).select("dst", "rank", "src", "dist")).isEmpty()


def test_layered_search_trace():
    at = {1: 1, 2: 2, 9: 3, 5: 4, 7: 6, 8: 7, 3: 10, 4: 12, 6: 15}
    x = np.zeros((10, 1))
    for v, d in at.items():
        x[v] = d
    g = navigate.Layers(x)
    both = lambda es: {v: [b if a == v else a for a, b in es if v in (a, b)] for e in es for v in e}
    g.links = [both([(7, 5), (5, 2), (5, 9), (2, 8), (9, 1), (3, 7), (4, 6), (4, 7)]), both([(3, 4), (3, 7)]), both([(4, 3)])]
    g.entry = 4
    q = np.zeros(1)
    assert [v for _, v in g.descend(q, 0)] == [7]
    for beam in ("classic", "split"):
        assert {v for _, v in g.search(q, [(6.0, 7)], 2, 0, beam, 2)} == {1, 2}


def test_recall_rule(spark):
    q = spark.createDataFrame([(1,), (2,), (3,)], "qid long")
    truth = spark.createDataFrame([(1, 1), (1, 2), (1, 3)], "qid long, id long")
    answer = spark.createDataFrame([(1, 2), (1, 3), (1, 9), (3, 5)], "qid long, id long")
    rows = {r.qid: (round(r.recall, 4), round(r.precision, 4)) for r in measures.per_query(truth, answer, q).collect()}
    assert rows == {1: (0.6667, 0.6667), 2: (1.0, 1.0), 3: (0.0, 0.0)}
    assert round(measures.recall(truth, answer, q), 4) == 0.5556


def test_full_lists_are_exact(spark):
    rng = np.random.default_rng(2)
    points = frame(spark, enumerate(rng.normal(size=(12, 3))))
    q = frame(spark, [(100, rng.normal(size=3))], "qid")
    knn = exact.ranked_graph_exact(points, 11).cache()
    radii, rev = exact.k_radii(knn), postings.transpose(knn)
    for k in (1, 4, 11):
        assert pairs(proxy.proxy_rknn(q, points, rev, radii, proxy.SearchOptions(k, 2, 11))) == pairs(exact.exact_rknn(q, points, radii, k))


def test_ties(spark):
    points = frame(spark, [(i, (i,)) for i in range(4)])
    knn = exact.ranked_graph_exact(points, 1)
    radii = exact.k_radii(knn)
    for x, want in ((1.5, [1, 2]), (2.0, [1, 2, 3])):
        assert [i for _, i in pairs(exact.exact_rknn(frame(spark, [(9, (x,))], "qid"), points, radii, 1))] == want
    assert [r.id for r in maintain.affected_exact(points, knn, frame(spark, [(9, (2.0,))]), 1).collect()] == [2]


def test_bad_input(spark):
    for opt in (proxy.SearchOptions(0, 1, 1), proxy.SearchOptions(11, 1, 1), proxy.SearchOptions(1, 1, 11), proxy.SearchOptions(1, 0, 1), proxy.SearchOptions(1, 5, 1, 2)):
        with pytest.raises(ValueError):
            opt.check(10)
    for rows in ([(1, [1.0]), (2, [1.0, 2.0])], [(1, None)], [(1, [None])], [(1, [float("nan")])], [(1, [1.0]), (1, [2.0])]):
        with pytest.raises(ValueError):
            vx.checked(spark.createDataFrame(rows, "id long, vec array<double>"))


def test_invariants(cloud):
    points, queries = cloud
    knn = exact.ranked_graph_exact(points, 30).cache()
    rev, radii = postings.transpose(knn).cache(), exact.k_radii(knn).cache()
    truth = exact.exact_rknn(queries, points, radii, 5).cache()
    assert pairs(proxy.no_postings_rknn(queries, points, radii, 5)) == pairs(truth)
    small = set(pairs(proxy.candidates(proxy.flat_proxies(queries, points, 3), rev, 5)))
    large = set(pairs(proxy.candidates(proxy.flat_proxies(queries, points, 6), rev, 20)))
    assert small <= large
    opt = proxy.SearchOptions(5, 6, 20)
    assert pairs(proxy.proxy_rknn(queries, points, rev, radii, opt)) == pairs(proxy.proxy_rknn(queries, points, rev, radii, opt, bounds=True))
    assert pairs(baselines.one_shot_rknn(queries, points, 5, 120)) == pairs(truth)
    counts = postings.occurrence(rev, points, 5).agg(F.sum("n")).first()[0]
    assert counts == 5 * 120
    start = ranked_graph.seed_random(points, 10)
    _, log = ranked_graph.refine(points, start, 10, 5, exact=knn)
    assert all(a["recall"] <= b["recall"] for a, b in zip(log, log[1:])) and log[-1]["recall"] >= 0.99


def test_incremental_pulls_until_the_test_stops_it(cloud):
    points, queries = cloud
    radii = exact.k_radii(exact.ranked_graph_exact(points, 5)).cache()
    truth = pairs(exact.exact_rknn(queries, points, radii, 5))
    assert pairs(baselines.incremental_rknn(queries, points, 5, 50.0, 8)) == truth
    whole = pairs(baselines.incremental_rknn(queries, points, 5, 2.0, 120))
    assert pairs(baselines.incremental_rknn(queries, points, 5, 2.0, 3)) == whole


def test_index_round_trip(spark, cloud, tmp_path):
    points, queries = cloud
    index = HybridIndex.build(points, str(tmp_path / "index"), 30, 8, 40, 4)
    again = HybridIndex.load(spark, str(tmp_path / "index"))
    opt = proxy.SearchOptions(5, 10, 30)
    assert pairs(index.search(queries, opt)) == pairs(again.search(queries, opt))
    radii = exact.k_radii(exact.ranked_graph_exact(points, 30))
    assert measures.recall(exact.exact_rknn(queries, points, radii, 5), index.search(queries, opt), queries) >= 0.95
    assert index.view("rev").count() == index.view("knn").count() == 120 * 30


def test_rank_bound_reaches_the_scan(spark, cloud, tmp_path):
    points, _ = cloud
    postings.transpose(exact.ranked_graph_exact(points, 10)).write.parquet(str(tmp_path / "rev"))
    plan = postings.scan(spark.read.parquet(str(tmp_path / "rev")), points.select("id"), 3)._jdf.queryExecution().executedPlan().toString()
    assert "LessThanOrEqual(rank,3)" in plan


def test_package_stands_without_the_operators():
    import pathlib
    import re

    root = pathlib.Path(__file__).resolve().parent.parent
    for p in root.glob("kinward/**/*.py"):
        if "llm" not in p.parts:
            assert not re.search(r"kinward\.llm|corpus_pipeline", p.read_text()), p


def test_queries_in_many_blocks_give_the_same(cloud):
    points, queries = cloud
    radii = exact.k_radii(exact.ranked_graph_exact(points, 5)).cache()
    one, many = (exact.exact_knn(queries, points, 7, block_bytes=b).collect() for b in (None, 200))
    assert sorted(one) == sorted(many)
    one, many = (exact.exact_rknn(queries, points, radii, 5, b) for b in (None, 200))
    assert pairs(one) == pairs(many) and one.count()
    every = exact.exact_knn(queries, points, 120)
    want = {(r.qid, r.id): r["rank"] for r in one.select("qid", "id").join(every, ["qid", "id"]).collect()}
    for b in (None, 300):
        assert {(r.qid, r.id): r["rank"] for r in exact.ranks_of(one, queries, points, b).collect()} == want


def test_a_large_query_set_stands_beside_the_points_by_blocks(cloud):
    points, queries = cloud
    q = queries.select(F.col("qid").alias("src"), F.col("vec").alias("a"))
    one, many = exact.beside(q, points, "a"), exact.beside(q, points, "a", block_bytes=150)
    assert "Broadcast" in one._jdf.queryExecution().executedPlan().toString()
    assert not any(x in many._jdf.queryExecution().executedPlan().toString() for x in ("Broadcast", "Cartesian"))
    assert pairs(one, "src") == pairs(many, "src") and one.count() == 12 * 120


def test_index_insertion(spark, cloud, tmp_path):
    points, queries = cloud
    index = HybridIndex.build(points.filter("id < 90"), str(tmp_path / "grown"), 20, 8, 40, 4, cell_rows=30)
    assert len(index.centres) == 3
    for lo, hi in ((90, 105), (105, 120)):
        index = index.insert(points.filter(f"id >= {lo} AND id < {hi}"), 15, 20, batch=lo)
    index.insert(points.filter("id >= 105"), batch=105)  # a batch that is delivered twice
    with pytest.raises(ValueError):
        index.insert(points.filter("id = 3"))
    index = HybridIndex.load(spark, index.path)
    assert index.manifest["n"] == index.view("points").count() == 120
    opt, fresh = proxy.SearchOptions(5, 10, 20), exact.ranked_graph_exact(points, 20).cache()
    truth = exact.exact_rknn(queries, points, exact.k_radii(fresh), 5).cache()

    def consistent(i):
        knn = i.view("knn").cache()
        assert knn.count() == 120 * 20 and knn.select("src", "rank").distinct().count() == 2400
        assert i.view("rev").exceptAll(postings.transpose(knn)).isEmpty() and i.view("rev").count() == 2400
        assert i.view("radii").exceptAll(exact.k_radii(knn)).isEmpty() and i.view("radii").count() == 120
        nav = i.view("nav")
        assert nav.filter("kind = 'edge' AND layer = 0").count() == nav.filter("kind = 'edge' AND layer = 0").select("src").distinct().count() == 120
        assert nav.filter("kind = 'entry'").count() == nav.select("cell").distinct().count()
        assert measures.graph_recall(knn, fresh, 10).first()[0] >= 0.9
        return pairs(i.search(queries, opt))

    before = consistent(index)
    assert measures.recall(truth, index.search(queries, opt), queries) >= 0.9
    assert consistent(index.compact()) == before
    for nav in ("flat", "relational", "nsg"):
        assert measures.recall(truth, index.search(queries, opt, nav), queries) >= 0.9, nav


def test_cells_of_alike_points_are_split(spark):
    rng = np.random.default_rng(5)
    points = frame(spark, [(i, (1.0, 1.0)) for i in range(200)] + [(200 + i, v) for i, v in enumerate(rng.normal(size=(100, 2)))]).cache()
    _, centres = navigate.pivots(points, 4)
    splits = navigate.splits_of(points, centres, 60)
    cells = navigate.assign_cells(points, centres, splits).groupBy("cell").count().collect()
    assert max(r[1] for r in cells) < 120 and splits.max() >= 3
    q = frame(spark, [(1000, (1.0, 1.0)), (1001, (0.0, 0.0))], "qid")
    # a beam must be wider than the copies of a cell, or it sees nothing else
    nav = navigate.build_nav(points, centres, 8, 120, 10, splits).cache()
    near = navigate.graph_search(nav, points, q, centres, 5, 120, len(centres), splits=splits)
    flat = proxy.flat_proxies(q, points, 5)
    assert sorted(round(r.pdist, 9) for r in near.collect()) == sorted(round(r.pdist, 9) for r in flat.collect())


def test_reverse_neighbours_lie_within_k_hops_of_the_monotonic_graph(spark):
    rng = np.random.default_rng(3)
    points = frame(spark, enumerate(rng.integers(0, 60, size=(80, 2)))).cache()
    lists = exact.ranked_graph_exact(points, 79).cache()
    own = points.select(F.col("id").alias("qid"), "id")
    lunes = baselines.relative_neighbours(points, lists)
    lunes = lunes.selectExpr("a AS src", "b AS dst").union(lunes.selectExpr("b AS src", "a AS dst")).cache()
    missed = {}
    for name, graph in (("monotonic", baselines.monotonic_neighbours(points, lists).cache()), ("lunes", lunes)):
        for k in (1, 2, 3):
            true = lists.filter(F.col("rank") <= k).select(F.col("dst").alias("qid"), F.col("src").alias("id"))
            missed[name, k] = true.join(baselines.hop_candidates(graph, own, k), ["qid", "id"], "left_anti").count()
    assert not any(missed["monotonic", k] for k in (1, 2, 3)) and missed["lunes", 3]


def test_speed_up_reads_the_events(spark, tmp_path):
    from kinward.plans import core_queries

    kinds = ["click"] * 4 + ["view"] * 10 + ["error"]
    rows = spark.range(len(kinds)).selectExpr("id AS event_id", f"element_at(array({str(kinds)[1:-1]}), int(id + 1)) AS event_type", "timestampadd(SECOND, id, TIMESTAMP_NTZ '2024-01-01') AS ts")
    rows.write.parquet(str(tmp_path / "events.parquet"))
    assert {r.method: r.factor for r in core_queries.Q["speed_up"](spark, str(tmp_path)).collect()} == {"click": 1.0, "view": 2.5, "error": 0.25}


def test_lists_of_stripes_equal_brute_force_without_a_merge(spark, monkeypatch):
    monkeypatch.setattr(exact, "TILE", 300)
    rng = np.random.default_rng(8)
    sets = {"whole": rng.integers(-3, 4, size=(900, 5)), "copies": np.concatenate([np.ones((500, 3)), rng.integers(0, 9, size=(300, 3))]), "slots": rng.normal(size=(700, 6))}
    for name, x in sets.items():
        x = x.astype(float)
        lists = exact.ranked_lists(frame(spark, enumerate(x)).repartition(3), 9)
        got = {r.src: (r.dsts, r.dists) for r in lists.collect()}
        for i in range(len(x)):
            d = vx.direct(np.repeat(x[i : i + 1], len(x), axis=0), x)
            order = [j for j in np.lexsort((np.arange(len(x)), d)) if j != i][:9]
            assert got[i] == (order, d[order].tolist()), (name, i)
    # one exchange brings blocks to the stripes; lists leave a task whole
    plan = lists._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroups" not in plan and "Window" not in plan


def test_hashed_texts_of_one_id_add_up(spark):
    one, parts = [(1, "a b  c a"), (2, None)], [(1, "a b "), (1, "c a"), (2, None)]
    # "a b " ends with an empty word, as "a b  c a" holds one
    whole, dealt = ({r.id: r.vec for r in vx.hashed_tokens(spark.createDataFrame(x, "id long, text string"), 16).collect()} for x in (one, parts))
    assert whole == dealt and len(whole[1]) == 16 and any(whole[1])


def test_refinement_by_shared_vectors_equals_that_by_joined_ones(spark, cloud, monkeypatch):
    points, _ = cloud
    start = ranked_graph.seed_random(points, 10).cache()
    lists = lambda: sorted(map(tuple, ranked_graph.refine(points, start, 10, 2)[0].select("src", "rank", "dst").collect()))
    shared = lists()
    monkeypatch.setattr(exact, "QUERY_BLOCK", 100)
    assert shared == lists() and len(shared) == 1200


def test_refinement_passes_on_what_enters_a_list_only(spark):
    """of points that know their true neighbours nothing leaves a meeting (it sent K pairs a member)."""
    rng = np.random.default_rng(3)
    x, ids = rng.normal(size=(60, 4)), np.arange(60)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
    np.fill_diagonal(d, np.inf)
    far = np.sort(d, axis=1)[:, 4]
    new = np.ones(60, bool)
    i, j, found = ranked_graph._pairs(ids, new, x, far, 5)
    assert len(i) == 300 and (found <= far[i] * (1 + 1e-9)).all()
    block = exact.Block(ids, x, {})
    rows = pa.RecordBatch.from_pydict({"o": np.zeros(60, np.int64), "member": ids, "is_new": new})
    assert not list(b for b in ranked_graph._meetings(iter([rows]), block, far, np.sort(i * 60 + j), 5) if b.num_rows)
    none = list(ranked_graph._meetings(iter([rows.slice(0, 7), rows.slice(7)]), block, np.full(60, np.inf), None, 5))
    assert sum(b.num_rows for b in none) == 300


def _sphere(spark, n, dim, seed):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, dim)).astype(np.float32)
    return frame(spark, enumerate(x / np.linalg.norm(x, axis=1)[:, None])).cache()


def test_insertion_is_as_wide_as_lists_need(spark, tmp_path):
    """on isotropic points a narrow insertion search missed a part of the lists; its width is measured now."""
    points = _sphere(spark, 700, 32, 5)
    index = HybridIndex.build(points.filter("id % 3 > 0"), str(tmp_path / "wide"), 10, 8, 10, 4)
    index = index.insert(points.filter("id % 3 = 0"), 2, 2)
    knn = index.view("knn").cache()
    assert knn.count() == 7000
    assert measures.graph_recall(knn, exact.ranked_graph_exact(points, 10), 10).first()[0] >= 0.9


def test_search_is_as_wide_as_recall_needs(spark, tmp_path):
    """on isotropic points two proxies find a small part; the fitted search finds nine tenths."""
    points = _sphere(spark, 600, 32, 6)
    index = HybridIndex.build(points, str(tmp_path / "fit"), 10, 8, 20, 4)
    queries = points.filter("id % 20 = 0").select(F.col("id").alias("qid"), "vec")
    truth = exact.exact_rknn(queries, points, exact.radii_of(exact.ranked_lists(points, 5)), 5).cache()
    asked = proxy.SearchOptions(5, 2, 5)
    opt = index.fitted(asked)
    assert measures.recall(truth, index.search(queries, asked), queries) < 0.9
    assert opt.m > 2 and (opt.k, opt.theta) == (5, 5)
    assert measures.recall(truth, index.search(queries, opt), queries) >= 0.9


def test_incremental_by_lots_and_by_held_members_agree(cloud, monkeypatch):
    """members that fit a block are held by the tasks; beyond it queries are taken in lots."""
    points, queries = cloud
    held = pairs(baselines.incremental_rknn(queries, points, 5, 2.0, 8))
    calls = []
    whole = proxy.flat_proxies
    monkeypatch.setattr(proxy, "flat_proxies", lambda *a: calls.append(a) or whole(*a))
    assert pairs(baselines.incremental_rknn(queries, points, 5, 2.0, 8)) == held and not calls
    monkeypatch.setattr(exact, "QUERY_BLOCK", 100)
    monkeypatch.setattr(baselines, "LOT_BYTES", 2000)
    assert pairs(baselines.incremental_rknn(queries, points, 5, 2.0, 8)) == held and len(calls) >= 2


def test_documents_keep_no_longer_lists_than_are_read(spark, monkeypatch, tmp_path):
    """Lists end at the greatest rank that the query reads, and hashed texts are kept as short integers."""
    from kinward.plans import core_queries

    words = np.random.default_rng(8).integers(0, 50, size=(60, 30))
    texts = [(i, " ".join(f"w{w}" for w in row), "en", "s", 1) for i, row in enumerate(words)]
    spark.createDataFrame(texts, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    depths, lists = [], exact.ranked_lists
    monkeypatch.setattr(exact, "ranked_lists", lambda p, K: depths.append(K) or lists(p, K))
    for name in ("precision", "recall_three_way", "query_counters", "proxy_coverage"):
        core_queries.Q[name](spark, str(tmp_path))
    assert depths == [20, 20, 50, 50]
    s = core_queries.Set(spark, str(tmp_path), "t", 10)
    plain = {r.id: r.vec for r in core_queries.points(spark, str(tmp_path), "t").collect()}
    assert {r.id: r.vec for r in s.points.collect()} == plain and dict(s.points.dtypes)["vec"] == "array<double>"
    assert "smallint" in s.points._jdf.queryExecution().analyzed().toString()


@pytest.mark.parametrize("block", [50_000_000, 400])
def test_counters_by_owner_shuffle_no_postings(cloud, monkeypatch, block):
    """postings are met where their owners' lists are; only counts of queries are shuffled, also when proxies go in lots."""
    points, queries = cloud
    lists, near = cut(exact.ranked_lists(points, 9)), cut(proxy.flat_proxies(queries, points, 6))
    want = sorted(map(tuple, proxy.query_counters(near, postings.transpose(exact.unlisted(lists)), queries, 7).collect()))
    monkeypatch.setattr(exact, "QUERY_BLOCK", block)
    monkeypatch.setattr(proxy, "MET", 50)
    got = proxy.counters_by_owner(near, lists, queries, 7)
    assert sorted(map(tuple, got.collect())) == want and any(r[1] > r[2] for r in want)
    plan = got._jdf.queryExecution().analyzed().toString()
    assert "explode" not in plan and (plan.count("MapInArrow") == 1) == (block > 400)


@pytest.fixture(scope="module")
def cut_cloud(spark):
    """Points with their queries, lists, proxies and truth; some queries have no true pair."""
    rng = np.random.default_rng(3)
    points = cut(frame(spark, enumerate(np.concatenate([rng.normal(size=(150, 4)), np.zeros((10, 4))]))))
    queries = cut(points.filter("id % 5 = 0").select(F.col("id").alias("qid"), "vec"))
    lists = cut(exact.ranked_lists(points, 12))
    return points, queries, lists, cut(proxy.flat_proxies(queries, points, 6)), cut(exact.exact_rknn(queries, points, exact.radii_of(lists), 4))


def test_precision_shuffles_no_candidates(cut_cloud):
    """candidates are counted where their lists are; only true pairs meet lists."""
    points, queries, lists, near, truth = cut_cloud
    rev = postings.transpose(exact.unlisted(lists))
    want = measures.per_query(truth, proxy.candidates(near.filter("prank <= 3"), rev, 7), queries).select("qid", "hit", "ans", "precision")
    got = measures.precision(truth, near.filter("prank <= 3"), lists, queries, 7)
    assert got.dtypes == want.dtypes and sorted(got.collect()) == sorted(want.collect())
    assert "posexplode" not in got._jdf.queryExecution().analyzed().toString()


@pytest.mark.parametrize("block", [50_000_000, 400])
def test_recall_verifies_candidates_by_owner(cut_cloud, monkeypatch, block):
    """every candidate reaches verification once, with its queries."""
    points, queries, lists, near, _ = cut_cloud
    rev, radii, opt = postings.transpose(exact.unlisted(lists)), exact.radii_of(lists), proxy.SearchOptions(4, 3, 7)
    want = sorted(proxy.proxy_rknn(queries, points, rev, radii, opt, near).collect())
    monkeypatch.setattr(exact, "QUERY_BLOCK", block)
    got = proxy.proxy_rknn_by_owner(queries, points, lists, opt, near)
    close = lambda rows: [(r.qid, r.id, round(r.dist, 9)) for r in rows]
    assert close(sorted(got.collect())) == close(want) and want
    assert "posexplode" not in got._jdf.queryExecution().analyzed().toString()


def test_coverage_takes_lists_whole(cut_cloud):
    """True pairs meet whole lists; every list taken apart was shuffled before."""
    _, _, lists, near, truth = cut_cloud
    knn, p = exact.unlisted(lists).collect(), near.collect()
    rows, ranks = truth.collect(), {(r.src, r.dst): r["rank"] for r in knn}
    got = measures.proxy_coverage(truth, near, lists, [2, 7, 12], [1, 3, 6])
    for cell in got.collect():
        hit = sum(any(x.qid == t.qid and x.prank <= cell.m and ranks.get((t.id, x.id), 99) <= cell.theta for x in p) for t in rows)
        assert cell.share == round(hit / len(rows), 6), cell
    assert "posexplode" not in got._jdf.queryExecution().analyzed().toString()


def test_stripes_read_blocks_without_a_shuffle(spark, monkeypatch):
    """Blocks of points were shuffled once a stripe; now every stripe reads the written blocks, whatever their order."""
    monkeypatch.setattr(exact, "TILE", 100)
    x = np.random.default_rng(4).integers(-9, 9, size=(600, 5))
    points = cut(frame(spark, enumerate(x)).repartition(3))
    lists = exact.ranked_lists(points, 7)
    assert lists.rdd.getNumPartitions() > 4  # a task a stripe
    assert "Exchange" not in lists._jdf.queryExecution().executedPlan().toString()
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    for r in lists.collect():
        order = [j for j in np.lexsort((np.arange(600), d[r.src])) if j != r.src][:7]
        assert r.dsts == order and r.dists == d[r.src][order].tolist()
    assert exact.ranked_lists(points.filter("id < 0"), 7).count() == 0 and exact.ranked_lists(points.filter("id < 1"), 7).count() == 0


def test_occurrence_is_counted_before_the_shuffle(cut_cloud):
    """Counts are added up where the lists are, and the profile counts all k at once."""
    points, _, lists, _, _ = cut_cloud
    knn = exact.unlisted(lists)
    out = postings.occurrence_profile(knn, points, [1, 4, 12])
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1 and "RepartitionByExpression" not in plan
    rows = knn.collect()
    for got in out.collect():
        n = sorted(sum(r.dst == p and r["rank"] <= got.k for r in rows) for p in range(160))
        assert (got.most, got.zero, got.median) == (n[-1], n.count(0), n[79])
    assert out.count() == 3


@pytest.mark.parametrize("block", [50_000_000, 2000])
def test_grid_counts_candidates_by_owner(cut_cloud, monkeypatch, block):
    """a cell's candidates are counted and verified where their lists are; every candidate was shuffled by step of m before."""
    points, queries, lists, near, truth = cut_cloud
    rev, radii = postings.transpose(exact.unlisted(lists)), exact.radii_of(lists)
    want = sorted(proxy.grid(queries, points, rev, radii, truth, 4, [1, 3, 6], [2, 7, 12], near).collect())
    monkeypatch.setattr(exact, "QUERY_BLOCK", block)
    monkeypatch.setattr(proxy, "MET", 50)
    monkeypatch.setattr(proxy, "candidate_postings", None)
    got = proxy.grid_by_owner(queries, points, lists, truth, 4, [6, 1, 3], [12, 2, 7], near)
    assert sorted(got.collect()) == want
    assert len({r.recall for r in want}) > 3


def test_grid_queries_pass_by_owner(spark, monkeypatch, tmp_path):
    """both queries take the grid from the owners' lists; few texts, some empty, give cells with and without answers."""
    from kinward.plans import core_queries

    words = np.random.default_rng(8).integers(0, 50, size=(120, 30))
    texts = [(i, " ".join(f"w{w}" for w in row) if i % 7 else "", "en", "s", 1) for i, row in enumerate(words)]
    spark.createDataFrame(texts, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    s = core_queries.Set(spark, str(tmp_path), "t")
    want = proxy.grid(s.queries, s.points, s.rev, s.radii, s.truth, 10, [1, 5, 20], [10, 50, 100], s.proxies)
    rows = sorted(want.collect())
    best = proxy.best_config(want, 0.5).collect()
    monkeypatch.setattr(proxy, "grid", None)
    assert sorted(core_queries.Q["grid_recall_docs"](spark, str(tmp_path)).collect()) == rows and len(rows) == 9
    assert core_queries.Q["best_config"](spark, str(tmp_path)).collect() == best and len(best) == 1


@pytest.mark.parametrize("block", [50_000_000, 2000])
def test_bounds_are_taken_by_owner(cut_cloud, monkeypatch, block):
    """bounds of a candidate are gathered where its owner's list is, and spare vectors there; every posting was shuffled with its bounds before."""
    points, queries, lists, near, _ = cut_cloud
    rev, radii, opt = postings.transpose(exact.unlisted(lists)), exact.radii_of(lists), proxy.SearchOptions(4, 3, 7)
    want = sorted(proxy.proxy_rknn(queries, points, rev, radii, opt, near, True).collect())
    met = proxy.candidates(near.filter("prank <= 3"), rev, 7)
    assert met.join(exact.radius_at(radii, 4), "id").filter("low > radius * (1 + 1e-9) + 1e-9").count() > 0  # some are spared
    monkeypatch.setattr(exact, "QUERY_BLOCK", block)
    got = proxy.proxy_rknn_by_owner(queries, points, lists, opt, near, True)
    close = lambda rows: [(r.qid, r.id, round(r.dist, 9)) for r in rows]
    assert close(sorted(got.collect())) == close(want) and want
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == (1 if block > 2000 else plan.count("MapInArrow")) and "Generate" not in plan


def test_few_slots_are_compared_by_place(spark, monkeypatch):
    """of points of few slots a list meets those near by; every pair was compared before."""
    rng = np.random.default_rng(5)
    line = np.stack([rng.integers(0, 50, 3000) * 20, rng.integers(0, 9000, 3000)], 1)
    sets = {"line": line, "copies": np.repeat(line[:40], 60, axis=0), "slots": np.concatenate([rng.normal(size=(2000, 3)), 1e6 + rng.normal(size=(5, 3)), np.zeros((300, 3))]), "one": np.ones((200, 2))}
    for name, x in sets.items():
        x, ids = x.astype(float), rng.permutation(len(x))
        want = {}
        for i in range(0, len(x), 7):
            d = vx.direct(np.repeat(x[i : i + 1], len(x), axis=0), x)
            order = [j for j in np.lexsort((ids, d)) if j != i][:9]
            want[ids[i]] = (ids[order].tolist(), d[order].tolist())
        points = cut(frame(spark, [(int(i), row) for i, row in zip(ids, x)]).repartition(3))
        lists = {r.src: (r.dsts, r.dists) for r in exact.ranked_lists(points, 9).collect()}
        assert len(lists) == len(x) and {i: lists[i] for i in want} == want, name
        asked = points.select(F.col("id").alias("qid"), "vec")
        near = {}
        for r in exact.exact_knn(asked, points, 9, True).orderBy("qid", "rank").collect():
            near.setdefault(r.qid, ([], []))[0].append(r.id)
            near[r.qid][1].append(r.dist)
        assert {i: near[i] for i in want} == want, name
    monkeypatch.setattr(exact, "CHUNK", 100)
    calls, met = [], exact._Nearest._met
    monkeypatch.setattr(exact._Nearest, "_met", lambda *a: calls.append(a[1]) or met(*a))
    order = exact._by_place(line)
    one = exact._Nearest(order[:1000], line[order[:1000]].astype(float), 9)
    one.meet_near(np.arange(3000), line.astype(float))
    assert len(calls) < 10 * 30 / 2  # of ten parts by thirty
    assert one.beyond(line + 1e6) and not one.beyond(line)


def test_large_batches_meet_postings_by_owner(spark, cloud, monkeypatch, tmp_path):
    """a batch that names as many proxies as there are points meets the index's postings at their owners; they were shuffled by proxy before."""
    points, queries = cloud
    index = HybridIndex.build(points, str(tmp_path / "index"), 12, 8, 40, 3)
    few, opt, n = cut(queries.limit(3)), proxy.SearchOptions(4, 30, 9), points.count()
    near = cut(index.proxies(queries, 30, 64))
    assert near.count() >= n > 30 * 3
    close = lambda df: sorted((r.qid, r.id, round(r.dist, 9)) for r in df.collect())
    far = index.view("radii").select("id", F.transform("r", lambda x: x * 0.7).alias("r"))
    want = {b: close(proxy.proxy_rknn(queries, index.view("points"), index.view("rev"), index.view("radii"), opt, near, b)) for b in (True, False)}
    less = close(proxy.proxy_rknn(queries, index.view("points"), index.view("rev"), far, opt, near))
    some = close(index.search(few, opt))
    monkeypatch.setattr(proxy, "candidate_postings", None)
    assert {b: close(index.search(queries, opt, bounds=b)) for b in (True, False)} == want and len(want[True]) > len(less) > 0
    assert close(index.search(queries, opt, radii=far)) == less
    asked = {q for q, _, _ in some}
    assert some == [r for r in want[True] if r[0] in asked]


def test_diverse_neighbours_are_picked_as_one_by_one():
    """distances among found nodes are taken at once; a call for every node was made before."""
    rng = np.random.default_rng(6)
    for x in (rng.normal(size=(300, 8)), rng.integers(0, 3, size=(300, 3)).astype(float)):
        g, calls = navigate.Layers(x), []
        for v in range(0, 60):
            found = sorted(zip(g.far(x[v], list(range(60, 120))).tolist(), range(60, 120)))
            kept, apart = [], []
            for d, u in found:
                if len(kept) < 16 and (d > 0 or not kept) and (d == 0 or not apart or d < g.far(x[u], apart).min()):
                    kept.append(u)
                    apart += [u] * (d > 0)
            kept += [u for _, u in found if u not in kept][: 16 - len(kept)]
            g.far = lambda *a: calls.append(a)
            assert g.pick(found, 16) == kept and not calls
            del g.far
    assert g.pick([], 4) == []
