"""Selection, indexes and routing put together."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import labels as lb
from ..index import graph, store
from ..sources.sinks import saved
from . import route as rt
from . import search as sr


class LabelSearcher:
    """Answers label-constrained queries from a family of selected indexes.

    ``kind``: ``flat`` (exact), ``graph``, ``cells``.  Sets with fewer than
    ``scan_rows`` matches are scanned.
    """

    def __init__(self, base: DataFrame, selection: DataFrame, kind: str = "graph", params: graph.Params | None = None, shard_rows: int = store.SHARD_ROWS, scan_rows: int = rt.SCAN_ROWS):
        self.base, self.selection, self.kind, self.params = base, selection, kind, params
        self.shard_rows, self.scan_rows, self.built, self._groups = shard_rows, scan_rows, None, None

    def build(self, path: str | None = None) -> LabelSearcher:
        if self.kind != "flat":
            self.built = store.build(self.base, self.selection, self.kind, self.params, self.shard_rows, path)
        return self

    @property
    def groups(self) -> DataFrame:
        """Rows per label set of the base, counted once."""
        if self._groups is None:
            self._groups = saved(lb.groups(self.base), "groups")
        return self._groups

    def explain(self, queries: DataFrame) -> DataFrame:
        return rt.plan(self.selection, queries, self.groups, self.scan_rows)

    def search(self, queries: DataFrame, ef: int = 64, rule: str = "post", dead: DataFrame | None = None) -> DataFrame:
        """qid, rank, vec_id, dist; ``dead(vec_id)`` are deleted rows."""
        # one row per query set, read by both branches
        plan = saved(self.explain(queries), "plan").select(F.col("bits").alias("pb"), "plan", "index_bits", "n_i")
        q = queries.join(plan.select("pb", "plan"), queries["bits"] == plan["pb"]).drop("pb")
        cols = queries.columns
        base = self.base if dead is None else self.base.join(dead.select("vec_id").distinct(), "vec_id", "left_anti")
        scanned = sr.exact_knn(base, q.filter("plan = 'scan'").select(cols), groups=self.groups)
        through = q.filter("plan = 'index'").select(cols)
        routes = plan.filter("plan = 'index'").select(F.col("pb").alias("bits"), "index_bits", "n_i")
        if self.kind == "flat":
            found = sr.pre_flat(base, through, routes, self.groups)  # the answers of a walk, without counting it
        else:
            marked = None if dead is None else store.marks(self.built, dead)
            found = store.merge(store.search(self.built, through, routes, ef, rule, marked), through)
        return scanned.unionByName(found)
