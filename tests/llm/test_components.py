"""Components of small graphs, on the driver, and of large ones in rounds."""

import numpy as np
import pytest

from labelroute.llm import common


def _plain(edges):
    label = {x: x for e in edges for x in e}
    while moved := [(a, b) for a, b in edges if label[a] != label[b]]:
        for a, b in moved:
            label[a] = label[b] = min(label[a], label[b])
    return label


@pytest.mark.parametrize("local_edges", [common.LOCAL_EDGES, 0])
def test_components_are_those_of_a_plain_search(spark, local_edges):
    rng = np.random.default_rng(3)
    edges = rng.integers(-400, 400, (300, 2)).tolist() + [[1000 + (7 * i) % 61, 1000 + (7 * i + 7) % 61] for i in range(60)] + [[5, 5]]
    edges += [[2000, 2000 + i] for i in range(1, 40)] + [[3000 - i, 3000] for i in range(1, 40)]
    df = spark.createDataFrame(edges, "a long, b long")
    got = common.connected_components(df, spark, local_edges=local_edges).collect()
    want = _plain([e for e in edges if e[0] != e[1]])
    assert len(got) == len(want) and {r["node"]: r["component"] for r in got} == want


def test_a_small_graph_takes_one_written_table(spark, monkeypatch):
    made, cut = [], common.cut
    monkeypatch.setattr(common, "cut", lambda *a: made.append(a[2]) or cut(*a))
    df = spark.createDataFrame([(i, i + 1) for i in range(0, 90, 3)], "a long, b long")
    assert common.connected_components(df, spark).count() == 60
    assert made == ["cc"]
    assert common.connected_components(df.filter("a < 0"), spark).count() == 0
