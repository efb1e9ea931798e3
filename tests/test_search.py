import numpy as np
import pytest
from pyspark.sql import functions as F

from labelroute.functions import labels as lb
from labelroute.functions import wide
from labelroute.index import graph, store
from labelroute.operators import baselines, metrics
from labelroute.operators import route
from labelroute.operators import search as sr
from labelroute.operators import select as sel
from labelroute.operators import universe as un
from labelroute.operators.searcher import LabelSearcher
from labelroute.plans import inspect
from labelroute.queries.common import small_selection, split


def _chain():
    """x1..x7 as nodes 0..6; a hand-made graph with fixed edges."""
    edges = {0: [1, 2], 1: [2], 2: [3, 4], 3: [6], 4: [5], 5: [], 6: []}
    return edges


def _graph(vecs, bits):
    e = _chain()
    return graph.Graph(np.arange(7), np.array(bits), np.array(vecs, float), [[np.array(e[i], np.int32) for i in range(7)]], 0)


def test_pre_loses_what_mismatches_hide_and_post_does_not():
    vecs = [[7, 0], [6, 0], [5, 0], [4, 1], [4, 0], [0, 0], [3, 3]]
    g = _graph(vecs, [1, 1, 1, 0, 0, 1, 1])
    pre, _ = graph.search(g, [0, 0], 1, 1, 1, "pre")
    post, _ = graph.search(g, [0, 0], 1, 1, 2, "post")
    assert pre[0][1] != 5 and post[0][1] == 5


def test_post_never_returns_a_mismatch():
    vecs = [[7, 0], [6, 0], [5, 0], [1, 0], [9, 9], [9, 8], [0, 0]]
    g = _graph(vecs, [1, 1, 1, 0, 1, 1, 1])
    found, st = graph.search(g, [0, 0], 1, 1, 2, "post")
    assert found[0][1] == 6 and st.expanded >= 4
    assert graph.search(g, [0, 0], 1, 1, 1, "pre")[0][0][1] != 6


def test_graph_recall_and_marks():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 16))
    bits = rng.integers(0, 4, 400)
    g = graph.build(np.arange(400), x, bits, graph.Params(12, 60))
    assert graph.Graph.load(g.dump()).entry == g.entry and g.link_bytes > 0
    hits = total = 0
    for q in rng.normal(size=(20, 16)):
        for dead in (frozenset(), frozenset(range(0, 400, 3))):
            ok = (bits & 1 == 1) & ~np.isin(np.arange(400), list(dead))
            truth = set(np.flatnonzero(ok)[np.argsort(graph.distances(q, x[ok]))[:10]].tolist())
            found = {i for _, i in graph.search(g, q, 1, 10, 80, "post", dead)[0]}
            assert all(ok[i] for i in found)
            hits += len(found & truth)
            total += len(truth)
    assert hits / total >= 0.95


def test_label_graph_is_complete():
    rng = np.random.default_rng(4)
    x, bits = rng.normal(size=(200, 8)), rng.integers(0, 8, 200)
    g = graph.build_label_graph(np.arange(200), x, bits, graph.Params(8, 40, 1.2, False))
    for b in range(8):
        want = int(((bits & b) == b).sum())
        found, st = graph.search(g, x[0], b, 500, 500, "label")
        assert len(found) == want and st.matched == want


def test_neighbours_come_one_by_one():
    rng = np.random.default_rng(5)
    x = rng.normal(size=(100, 4))
    g = graph.build(np.arange(100), x, np.zeros(100, int), graph.Params(8, 40, layered=False))
    first = [i for _, (_, i) in zip(range(5), graph.neighbours(g, x[7]), strict=False)]
    assert 7 in first


def test_flat_search_is_exact(spark, small):
    b, q, _w = split(spark, small)
    truth = sr.exact_knn(b, q).collect()
    r = route.route(small_selection(b), q)
    for f in (sr.pre_flat, lambda *a: sr.post_flat(*a).drop("examined")):
        assert sorted(f(b, q, r).collect()) == sorted(truth)
    chosen = sel.select_for_factor(un.universe_all(b), 0.2).df(spark)
    flat = LabelSearcher(b, chosen, "flat", scan_rows=20).build().search(q)
    assert metrics.mean_recall(flat, sr.exact_knn(b, q)) == 1.0


def test_routed_graphs_find_the_answers(spark, small):
    b, q, _w = split(spark, small)
    b, q = b.cache(), q.cache()
    chosen = sel.select_for_factor(un.universe_all(b), 0.2).df(spark)
    for rows in (20_000, 150):
        s = LabelSearcher(b, chosen, "graph", graph.Params(12, 60), scan_rows=20, shard_rows=rows).build()
        assert metrics.mean_recall(s.search(q, ef=80), sr.exact_knn(b, q)) >= 0.95


def test_selection_reads_no_vectors_and_joins_are_not_products(spark, small):
    from labelroute.sources import datasets as ds

    base = lb.encode(ds.doc_labels(spark, small), ["lang:en"])
    u = un.universe_all(base)
    assert not {"text", "embedding"} & inspect.scanned_columns(u)
    b, q, _w = split(spark, small)
    found = sr.exact_knn(b, q)
    assert inspect.no_cartesian(found) and inspect.has(found, "WindowGroupLimit")
    assert inspect.no_cartesian(route.route(small_selection(b), q))


def test_examined_rows_are_bounded_on_average(spark):
    rows = [(i, [float((i * 7919) % 1000)], 1 if i % 5 == 0 else 0) for i in range(1000)]
    b = spark.createDataFrame(rows, "vec_id long, vec array<double>, bits long")
    q = spark.createDataFrame([(i, [float(i * 97 % 1000)], 1, 10) for i in range(20)], "qid long, qvec array<double>, bits long, k int")
    top = un.universe_all(b).filter("bits = 0")
    t = sr.post_examined(b, q, route.route(top, q)).collect()
    assert all(r["examined"] >= 10 for r in t)
    assert sum(r["examined"] for r in t) / 20 <= 10 / 0.2 * 1.3


def test_interpolated_throughput():
    assert metrics.at_recall([(0.9, 100.0), (1.0, 50.0)], 0.95) == pytest.approx(75.0)
    assert metrics.at_recall([(0.9, 100.0)], 0.95) is None


def test_sketches_and_samples_are_near(spark, small):
    from labelroute.queries import QUERIES

    for r in QUERIES["b05_universe_sketch"](spark, small).collect():
        assert abs(r["estimate"] - r["n"]) <= max(5, 0.1 * 1500)


def test_sets_meet_groups_without_nested_loops(spark):
    rng = np.random.default_rng(11)
    sets = [0, -1, 1 << 62, (1 << 30) - 1, *rng.integers(0, 64, 20).tolist()]
    groups = [0, (1 << 62) | 5, (1 << 40) - 1, *rng.integers(0, 64, 40).tolist()]
    q = spark.createDataFrame([(x,) for x in sets], "bits long")
    g = spark.createDataFrame([(x, 1) for x in set(groups)], "bits long, n long")
    tests = {"contain": lambda a, b: b & a == a, "overlap": lambda a, b: a & b != 0, "equal": lambda a, b: a == b}
    for mode, ok in tests.items():
        df = lb.meeting(q, g, mode)
        assert inspect.no_cartesian(df)
        want = sorted((a, b) for a in set(sets) if a >= 0 for b in set(groups) if ok(a, b))
        assert sorted((r["qbits"], r["bits"]) for r in df.collect()) == want
    counted = {r["bits"]: r["match_count"] for r in lb.counted(q, g).collect()}
    assert counted == {a: sum(a >= 0 and b & a == a for b in set(groups)) for a in set(sets)}


def test_subsets_by_doubling(spark):
    row = spark.createDataFrame([(0,), (1 << 62,), (0b10110,)], "bits long").select("bits", lb.subsets("bits").alias("s")).collect()
    for r in row:
        assert sorted(r["s"]) == sorted({r["bits"] & m for m in range(64)} | {r["bits"]})


def test_wide_alphabets_equal_the_bit_form(spark, small):
    b, q, words = split(spark, small)
    far = wide.exact_knn(b, q.withColumn("labels", F.col("qlabels")))
    assert sorted(far.collect()) == sorted(sr.exact_knn(b, q).collect())
    rows = spark.createDataFrame([(i, [float(i)], [f"l{i}", f"l{i + 1}", None]) for i in range(200)] + [(200, [0.0], None)], "vec_id long, vec array<double>, labels array<string>")
    asked = spark.createDataFrame([(0, [5.0], ["l7"], 5), (1, [9.0], [], 3), (2, [1.0], ["none"], 2)], "qid long, qvec array<double>, labels array<string>, k int")
    got = sorted((r["qid"], r["rank"], r["vec_id"]) for r in wide.exact_knn(rows, asked).collect())
    assert got == [(0, 1, 6), (0, 2, 7), (1, 1, 9), (1, 2, 8), (1, 3, 10)]
    sizes = {tuple(r["labels"]): r["n"] for r in wide.universe(rows, asked).collect()}
    assert sizes == {(): 201, ("l7",): 2}
    assert wide.universe(rows.limit(0), asked).count() == 0


def _equal_shards(spark):
    """Two shards of five rows each, so that their counters are alike."""
    rows = [(i, [float(i % 5), 0.0], 0) for i in range(10)]
    base = spark.createDataFrame(rows, "vec_id long, vec array<double>, bits long")
    top = spark.createDataFrame([(0, 10)], "bits long, n long")
    one = store.build(base.filter("vec_id < 5"), top)
    built = one.unionByName(store.build(base.filter("vec_id >= 5"), top, first_shard=1))
    q = spark.createDataFrame([(1, [0.0, 0.0], 0, 10)], "qid long, qvec array<double>, bits long, k int")
    return base, top, built, q


def test_counters_are_summed_over_equal_shards(spark):
    base, top, built, q = _equal_shards(spark)
    parts = store.search(built, q, route.route(top, q), 10)
    assert not inspect.has(parts, "Exchange")  # indexes stay where they lie
    each = parts.select("shard", "examined", "distances").distinct().collect()
    total = store.work(parts).first()
    assert len(each) == 2 and each[0]["examined"] == each[1]["examined"] == 5
    assert total["examined"] == 10 and total["distances"] == sum(r["distances"] for r in each)
    assert [r["vec_id"] for r in store.merge(parts, q).orderBy("rank").collect()] == [0, 5, 1, 6, 2, 7, 3, 8, 4, 9]


def test_beams_blocks_and_marks(spark, monkeypatch):
    base, top, built, q = _equal_shards(spark)
    q = q.unionByName(q.withColumn("qid", F.lit(2).cast("long")))
    routes = route.route(top, q)
    marked = store.marks(built, base.filter("vec_id IN (0, 6)"))
    assert not inspect.scanned_columns(marked) & {"blob"}
    monkeypatch.setattr(store, "QUERY_BLOCK", 1)
    parts = store.search(built, q, routes, (10, 20), "post", marked)
    got = store.merge_beams(parts, q).collect()
    assert {(r["qid"], r["ef"]) for r in got} == {(1, 10), (1, 20), (2, 10), (2, 20)}
    assert {r["vec_id"] for r in got} == set(range(10)) - {0, 6}


def test_dense_graphs_have_all_their_edges(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(600, 12))
    g = graph.build(np.arange(600), x, np.zeros(600, int), graph.Params(8, 100, gamma=12, dense=True))
    order = np.argsort(((x[:, None] - x[None]) ** 2).sum(2), axis=1)
    for i in range(0, 600, 37):
        assert set(order[i, 1:97].tolist()) <= set(g.layers[0][i].tolist())
    less = graph.build(np.arange(600), x, np.zeros(600, int), graph.Params(8, 100, gamma=12, dense=True, m_beta=16))
    assert less.link_bytes < g.link_bytes
    for i in range(0, 600, 37):
        near = less.layers[0][i].tolist()
        two = set(near).union(*(less.layers[0][j].tolist() for j in near))
        assert set(order[i, 1:97].tolist()) <= two | {i}
    assert baselines.DENSE == {"m": 32, "gamma": 12, "m_beta": 64}


def test_a_walk_is_counted_not_ranked(spark, small):
    """The rank covers matches behind a limit; no window runs over an index's rows."""
    b, q, _w = split(spark, small)
    r = route.route(small_selection(b), q)
    brute = {}
    rows = [(x["vec_id"], np.array(x["vec"]), x["bits"]) for x in b.collect()]
    index = {x["bits"]: x["index_bits"] for x in r.collect()}
    for x in q.collect():
        inside = sorted((float(((v - np.array(x["qvec"])) ** 2).sum()), i, bits) for i, v, bits in rows if bits & index[x["bits"]] == index[x["bits"]])
        seen = 0
        for at, (_d, i, bits) in enumerate(inside, 1):
            if bits & x["bits"] == x["bits"] and seen < x["k"]:
                seen += 1
                brute[x["qid"], i] = at
    got = sr.post_flat(b, q, r)
    assert inspect.has(sr.pre_flat(b, q, r), "WindowGroupLimit") and inspect.has(got, "partial_count")
    assert {(x["qid"], x["vec_id"]): x["examined"] for x in got.collect()} == brute


def test_fused_queries_go_in_blocks(spark, small, monkeypatch):
    b, q, _w = split(spark, small)
    whole = sorted(sr.fused_knn(b, q, 0.5).collect())
    monkeypatch.setattr(sr, "FUSED_QUERIES", 3)
    assert sorted(sr.fused_knn(b, q, 0.5).collect()) == whole


def test_inserts_are_found_and_versions_stay(spark, small):
    from labelroute.operators.versioned import IndexStore, membership
    from labelroute.sources import datasets as ds
    from labelroute.sources.sinks import scratch

    rows, q, _w = split(spark, small)
    before, batch = ds.arrivals(rows)
    home = IndexStore(spark, scratch(spark, "v"), params=graph.Params(12, 60))
    first = home.create(before, sel.select_for_factor(un.universe_all(before), 0.2).df(spark))
    old = home.reader(first)
    second = home.insert(batch, "b1")
    assert home.insert(batch, "b1") == second  # a replay
    assert membership(home.waiting()).filter("index_bits = 0").first()["rows"] == batch.count()
    new = home.reader()
    assert metrics.mean_recall(new.search(q, 120), sr.exact_knn(rows, q)) >= 0.95
    third = home.refresh(0.01)
    assert third == second + 1 and home.waiting().count() == 0 and home.refresh(0.01) == third
    assert metrics.mean_recall(home.reader().search(q, 120), sr.exact_knn(rows, q)) >= 0.95
    fresh = {r["vec_id"] for r in batch.collect()}
    assert not fresh & {r["vec_id"] for r in old.search(q, 120).collect()}
