"""An index set that takes inserts while it is read.

A version names folders: base rows, the selection, built shards, and inserted
rows that no shard holds yet.  An insert writes a batch's rows with every index
that they belong to and publishes the next version; a batch that comes again
changes nothing.  ``refresh`` builds shards of the waiting rows once they reach a
share of the base.  A reader keeps the version that it pinned.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import labels as lb
from ..index import graph, store
from . import search as sr
from .dynamic import Manifest, needs_refresh
from .searcher import LabelSearcher

_ROW = "vec_id long, vec array<float>, bits long"
_MEMBER = f"index_bits long, {_ROW}"


class IndexStore:
    def __init__(self, spark: SparkSession, root: str, kind: str = "graph", params: graph.Params | None = None, shard_rows: int = store.SHARD_ROWS):
        self.spark, self.root, self.kind, self.params, self.shard_rows = spark, root.rstrip("/"), kind, params, shard_rows
        self.manifest = Manifest(spark, f"{self.root}/versions")

    def _put(self, df: DataFrame, what: str) -> str:
        """Folders have unique names, so a writer that failed blocks nobody."""
        path = f"{self.root}/{what}-{uuid.uuid4().hex}"
        df.write.parquet(path)
        return path

    def _state(self, version: int | None = None) -> dict:
        got = self.manifest.read(version)
        return got[0] if got else {}

    def create(self, base: DataFrame, selection: DataFrame) -> int:
        rows = base.select("vec_id", F.col("vec").cast("array<float>").alias("vec"), "bits")
        chosen = self._put(selection.select("bits", "n"), "selection")
        state = {"base": [self._put(rows, "base")], "selection": chosen, "built": [], "waiting": [], "batches": []}
        if self.kind != "flat":
            path = f"{self.root}/built-{uuid.uuid4().hex}"
            store.build(rows, self.spark.read.parquet(chosen), self.kind, self.params, self.shard_rows, path)
            state["built"] = [path]
        return self.manifest.publish([state], self.manifest.version())

    def insert(self, batch: DataFrame, batch_id: int | str) -> int:
        """The version that holds the batch; unchanged if it had come before."""
        version = self.manifest.version()
        state = self._state(version)
        if str(batch_id) in state["batches"]:
            return version
        rows = batch.select("vec_id", F.col("vec").cast("array<float>").alias("vec"), "bits")
        put = self._put(store.members(rows, self.spark.read.parquet(state["selection"])), "waiting")
        state["waiting"].append(put)
        state["base"].append(self._put(rows, "base"))
        state["batches"].append(str(batch_id))
        return self.manifest.publish([state], version)

    def _read(self, paths: list[str], schema: str) -> DataFrame:
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def waiting(self, version: int | None = None) -> DataFrame:
        """(index_bits, vec_id, vec, bits) of inserted rows that no shard holds."""
        return self._read(self._state(version).get("waiting", []), _MEMBER)

    def refresh(self, share: float = 0.1) -> int:
        """Shards of the waiting rows, once they reach ``share`` of the base."""
        version = self.manifest.version()
        state = self._state(version)
        fresh = self.waiting(version).filter("index_bits = 0").select("vec_id", "vec", "bits")
        n, m = self._read(state["base"], _ROW).count(), fresh.count()
        if self.kind == "flat" or not m or not needs_refresh(n - m, m, share):
            return version
        path = f"{self.root}/built-{uuid.uuid4().hex}"
        built = self._read(state["built"], store.SCHEMA)
        store.extend(built, fresh, self.spark.read.parquet(state["selection"]), self.kind, self.params, self.shard_rows, path)
        state["built"].append(path)
        state["waiting"] = []
        return self.manifest.publish([state], version)

    def reader(self, version: int | None = None, scan_rows: int = 0) -> Reader:
        return Reader(self, self.manifest.version() if version is None else version, scan_rows)


class Reader:
    """Answers from one version, whatever is published after it."""

    def __init__(self, owner: IndexStore, version: int, scan_rows: int):
        state = owner._state(version)
        self.version, self.kind = version, owner.kind
        self.base = owner._read(state["base"], _ROW)
        self.selection = owner.spark.read.parquet(state["selection"])
        self.waiting = owner.waiting(version)
        self.inner = LabelSearcher(self.base, self.selection, owner.kind, owner.params, owner.shard_rows, scan_rows)
        if owner.kind != "flat":
            self.inner.built = owner._read(state["built"], store.SCHEMA)

    def search(self, queries: DataFrame, ef: int = 64, rule: str = "post") -> DataFrame:
        """qid, rank, vec_id, dist; waiting rows are compared one by one."""
        found = self.inner.search(queries, ef, rule)
        if self.kind == "flat":  # a flat index is the base rows themselves
            return found
        fresh = sr.exact_knn(self.waiting.filter("index_bits = 0").drop("index_bits"), queries)
        both = found.unionByName(fresh).select("qid", "vec_id", "dist").distinct()
        return sr.cut(both.join(queries.select("qid", "k"), "qid"), queries)


def membership(waiting: DataFrame) -> DataFrame:
    return waiting.groupBy("index_bits").agg(F.count("*").alias("rows"))


def workload_sizes(base: DataFrame, sets: DataFrame) -> DataFrame:
    """(bits, n) of given sets, as a selection."""
    return lb.counted(sets, lb.groups(base)).withColumnRenamed("match_count", "n")
