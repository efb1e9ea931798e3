"""Facts about dense links are found where the shards are."""

import numpy as np
import pandas as pd
from pyspark.sql.classic.dataframe import DataFrame

from labelroute.operators import universe as un
from labelroute.queries import search
from labelroute.queries.common import split


def test_no_graph_comes_to_the_driver(spark, small, monkeypatch):
    b, _q, _w = split(spark, small)
    seen = []
    collect = DataFrame.collect
    monkeypatch.setattr(DataFrame, "collect", lambda self: seen.append(dict(self.dtypes)) or collect(self))
    held = search.degree_facts(b, un.universe_all(b), shard_rows=40)
    assert all(held.values()) and len(held) == 3
    assert seen and not any("binary" in x.values() for x in seen)


def test_a_link_out_of_reach_is_found():
    def side(name, links):
        ends = np.append(0, np.cumsum([len(x) for x in links]))
        return {"name": name, "starts": ends.astype(np.int64).tobytes(), "links": np.concatenate(links).astype(np.int32).tobytes()}

    full = [[1, 2, 3], [0], [0], [2]]
    for less, within in (([[1], [0, 2, 3], [0], [2]], True), ([[1], [0, 2], [0], [2]], False)):
        assert search._reached(pd.DataFrame([side("dense", full), side("less", less)]))["within"].tolist() == [within]
