"""Measured queries share what they measure; several methods are built and searched at once."""

import numpy as np
from pyspark.sql import functions as F

from labelroute.index import graph, store
from labelroute.operators import baselines, route
from labelroute.operators import select as sel
from labelroute.operators import universe as un
from labelroute.queries import search as qs


def test_the_document_set_is_made_once_for_the_floors(spark, small, monkeypatch):
    """F1: e00_recall_floors made the set, its universe and its exact answers again for every query."""
    made, plain = [], qs.split
    monkeypatch.setattr(qs, "split", lambda *a, **kw: made.append(1) or plain(*a, **kw))
    monkeypatch.setattr(qs, "_doc_sets", {})
    monkeypatch.setattr(qs, "_tables", {})
    for name in ("e04_flat_graph", "e03_hyperplane_buckets"):
        assert qs.Q[name](spark, small).count()
    assert len(made) == 1


def test_long_walks_go_together(monkeypatch):
    """F1 to F4: queries of rare sets, whose walks are long, were dealt over all blocks."""
    rng = np.random.default_rng(3)
    x, bits = rng.normal(size=(400, 6)), np.where(np.arange(400) % 40 == 0, 3, 1)
    g = graph.build(np.arange(400), x, bits, graph.Params(8, 40))
    qbits = np.where(np.arange(40) % 10 == 0, 2, 1)
    blocks, plain = [], graph._walks
    monkeypatch.setattr(graph, "_MARKS", 4 * 400)
    monkeypatch.setattr(graph, "_walks", lambda g, links, q, b, *a: blocks.append(b.tolist()) or plain(g, links, q, b, *a))
    got = graph.sweep_many(g, x[:40], qbits, 5, (10, 20))
    assert blocks[0] == [2, 2, 2, 2] and len(blocks) == 10
    for q, b, found in zip(x[:40], qbits.tolist(), got, strict=True):
        want = graph.sweep(g, q, b, 5, (10, 20))
        assert all(found[ef][:1] == want[ef][:1] and vars(found[ef][1]) == vars(want[ef][1]) for ef in want)


def test_methods_built_and_searched_at_once_are_those_built_alone(spark, small, monkeypatch):
    """F2 to F4: every method had jobs of its own for its build, its routes and its search."""
    b, q = (x.cache() for x in qs.split(spark, small)[:2])
    u = un.universe_all(b).cache()
    written, plain = [], store.build_forms
    monkeypatch.setattr(store, "build_forms", lambda *a, **kw: written.append(1) or plain(*a, **kw))
    built, chosen, made = qs.methods(spark, b, u)
    assert written == [1] and built.groupBy("form", "index_bits", "shard").count().filter("count > 1").count() == 0
    parts = store.search_forms(built, q, route.route(chosen, q, by=("method",)), made, (10, 40)).cache()
    alone = {"label graph": baselines.label_graph(b, u), "dense graph": baselines.dpg(b, u, gamma=12), "thin graph": baselines.dpg(b, u), "post-filter": baselines.hpg_post(b, u)}
    alone["factor 0.2"] = baselines.selected(b, sel.select_for_factor(u, 0.2).df(spark))
    cols = "qid", "ef", "index_bits", "shard", "vec_id", "dist", "examined", "distances"
    rows = lambda df: sorted(map(tuple, df.select(*cols).collect()), key=repr)
    assert set(made) == {*alone, "budget 2.0"}
    for name, (sets, index, rule) in alone.items():
        assert rows(parts.filter(F.col("method") == name)) == rows(store.search(index, q, route.route(sets, q), (10, 40), rule))
