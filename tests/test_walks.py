"""A sweep of beams is one walk; few shards are read by several tasks; jobs go side by side."""

import threading

import numpy as np

from labelroute.index import graph, store
from labelroute.operators import baselines, route
from labelroute.operators import universe as un
from labelroute.operators.jobs import at_once
from labelroute.queries.common import split


def test_a_sweep_answers_as_its_beams_do(monkeypatch):
    rng = np.random.default_rng(6)
    vecs, bits, ids = rng.standard_normal((400, 8)), rng.integers(0, 8, 400), rng.permutation(900)[:400]
    vecs[50:60] = vecs[3]  # copies
    p, beams = graph.Params(6, 30), (40, 1, 10)
    made = {
        "post": graph.build(ids, vecs, bits, p), "label": graph.build_label_graph(ids, vecs, bits, p),
        "pre": graph.build(ids, vecs, bits, graph.Params(6, 30, gamma=12, dense=True)), "twohop": graph.build(ids, vecs, bits, graph.Params(6, 30, dense=True)),
    }
    for rule, g in made.items():
        for i in range(20):
            got = graph.sweep(g, vecs[i] + 0.1, int(bits[i]) & 5, 10, beams, rule)
            for ef in beams:
                assert got[ef][:2] == graph.search(g, vecs[i] + 0.1, int(bits[i]) & 5, 10, ef, rule)
    calls, plain = [], graph.distances
    monkeypatch.setattr(graph, "distances", lambda *a: calls.append(1) or plain(*a))
    graph.search(made["post"], vecs[0], 1, 10, 40)
    alone = len(calls)
    graph.sweep(made["post"], vecs[0], 1, 10, beams)
    assert len(calls) == 2 * alone


def test_one_shard_is_searched_by_several_tasks(spark, small):
    b, q, _w = split(spark, small)
    q = q.unionByName(q.withColumn("qid", q["qid"] + 1_000_000))  # enough for a piece
    for i in range(4):
        q = q.unionByName(q.withColumn("qid", q["qid"] + 10_000_000 * (i + 1)))
    top, built, rule = baselines.hpg_post(b, un.universe_all(b))
    parts = store.search(built, q, route.route(top, q), 20, rule)
    wanted = q.select("qid").distinct().count()
    assert wanted >= 2 * store.QUERY_PIECE and parts.select("qid").distinct().count() == wanted
    assert parts.rdd.getNumPartitions() > built.rdd.getNumPartitions()
    assert built.filter("seconds > 0").count() == built.count()


def test_jobs_go_side_by_side(spark):
    meet = threading.Barrier(3, timeout=20)
    assert at_once(spark, [lambda i=i: (meet.wait(), i)[1] for i in range(3)]) == [0, 1, 2]
