"""Many walks side by side answer as one walk after the other."""

import numpy as np

from labelroute.index import graph, store
from labelroute.operators import baselines
from labelroute.operators import select as sel
from labelroute.operators import universe as un
from labelroute.queries.common import split


def _graphs(ids, vecs, bits):
    p = graph.Params(6, 30)
    return {
        "post": graph.build(ids, vecs, bits, p), "label": graph.build_label_graph(ids, vecs, bits, p),
        "pre": graph.build(ids, vecs, bits, graph.Params(6, 30, gamma=12, dense=True)), "twohop": graph.build(ids, vecs, bits, graph.Params(6, 30, dense=True)),
    }


def test_many_walks_answer_and_count_as_single_ones():
    rng = np.random.default_rng(8)
    bits, ids = rng.integers(0, 32, 400), rng.permutation(900)[:400]
    for vecs in (rng.standard_normal((400, 8)), rng.integers(-1, 2, (400, 4)).astype(float)):  # the second with copies and ties
        qs, asked = vecs[:40] + 0.25, bits[:40] & rng.integers(0, 64, 40)  # some sets match nothing
        for rule, g in _graphs(ids, vecs, bits).items():
            for dead in (frozenset(), frozenset(ids[:60].tolist())):
                for k, beams in ((10, (40, 1, 10)), (300, (20, 350))):
                    many = graph.sweep_many(g, qs, asked, k, beams, rule, dead)
                    for q, b, walks in zip(qs, asked.tolist(), many, strict=True):
                        one = graph.sweep(g, q, b, k, beams, rule, dead)
                        assert all(walks[ef][:2] == one[ef][:2] for ef in beams)


def test_many_walks_take_a_step_at_once(monkeypatch):
    rng = np.random.default_rng(9)
    vecs, bits = rng.standard_normal((500, 8)), rng.integers(0, 8, 500)
    g, steps = graph.build(np.arange(500), vecs, bits, graph.Params(6, 30)), []
    plain = np.einsum
    monkeypatch.setattr(np, "einsum", lambda *a: steps.append(1) or plain(*a))
    asked = [(i, vecs[i], 10, 0) for i in range(64)]
    store._walked(g, asked, (40,), "post", frozenset())
    walked = len(steps)
    steps.clear()
    for _qid, q, k, b in asked:
        graph.sweep(g, q, b, k, (40,))
    assert 4 * walked < len(steps)


def test_vectors_that_are_not_finite_are_walked_one_by_one():
    rng = np.random.default_rng(10)
    vecs = rng.standard_normal((60, 4))
    g, qs = graph.build(np.arange(60), vecs, np.zeros(60), graph.Params(4, 20)), vecs[:6].copy()
    qs[2, 1] = np.inf
    got = graph.sweep_many(g, qs, np.zeros(6), 3, (8,))
    assert [str(w[8][:2]) for w in got] == [str(graph.sweep(g, q, 0, 3, (8,))[8][:2]) for q in qs]
    empty = graph.build(np.zeros(0), np.zeros((0, 1)), np.zeros(0), graph.Params())
    assert [w[8][0] for w in graph.sweep_many(empty, vecs[:5], np.zeros(5), 3, (8,))] == [[]] * 5


def test_pruning_looks_at_each_cover_edge_a_few_times():
    rng, seen = np.random.default_rng(11), [0]
    rows = [int(sum((rng.random() < 0.6 / (j + 1)) << j for j in range(12))) for _ in range(1_500)]
    sets = sorted({m for r in set(rows) for m in range(1 << 12) if m & r == m})

    class Counted(list):
        def __iter__(self):
            for x in super().__iter__():
                seen[0] += 1
                yield x

    class Lattice(sel.Lattice):
        def covered_by(self, src, c_milli):
            return Counted(super().covered_by(src, c_milli))

    lat = Lattice.of({s: sum(r & s == s for r in rows) for s in sets})
    edges = sum(len(lat.covered_by(s, 300)) for s in sets)
    seen[0] = 0
    kept = sel.prune(lat, sets, 300)
    assert seen[0] <= 4 * edges
    reach = {s: set(sel.Lattice.covered_by(lat, s, 300)) for s in sets}
    assert set().union(*(reach[s] for s in kept)) == set(sets) and len(kept) < len(sets)
    assert all(not reach[s] <= set().union(*(reach[o] for o in kept if o != s)) for s in kept if s)


def test_sets_that_several_selections_hold_are_built_once(spark, small, monkeypatch):
    b, _q, _w = split(spark, small)
    u = un.universe_all(b)
    top, more = sel.select_top(u), u.filter("bits = 0 or n > 20").select("bits", "n")
    made, plain = [], store.build
    monkeypatch.setattr(store, "build", lambda *a, **kw: made.append(plain(*a, **kw)) or made[-1])
    one, many = baselines.selected_each(b, [top, more])
    assert len(made) == 1 and made[0].groupBy("index_bits", "shard").count().filter("count > 1").count() == 0
    held = lambda x: {(r["index_bits"], r["shard"], r["n"], bytes(r["blob"])) for r in x.collect()}
    assert held(one) == held(plain(b, top)) and held(many) == held(plain(b, more))
