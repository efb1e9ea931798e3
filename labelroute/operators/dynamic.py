"""Maintenance: inserts, deletion marks, refresh, changing query sets, versions."""

from __future__ import annotations

import json
import uuid
from fractions import Fraction

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import labels as lb
from ..index import store
from . import select as sel
from .route import SCAN_ROWS, lb_counts, route


def insert(selection: DataFrame, batch: DataFrame) -> DataFrame:
    """Rows of a batch with every index they belong to (appended as a delta)."""
    return store.members(batch, selection)


def delete(base: DataFrame, ids: DataFrame) -> DataFrame:
    """Base without marked rows; marks are a table, searches walk past them."""
    return base.join(ids.select("vec_id").distinct(), "vec_id", "left_anti")


def needs_refresh(base_rows, delta_rows, share: float = 0.1):
    """Whether new rows reach ``share`` of the base (a tenth to a fifth)."""
    return delta_rows >= share * base_rows


def route_new(selection: DataFrame, new_sets: DataFrame, grouped: DataFrame, scan_rows: int = SCAN_ROWS) -> DataFrame:
    """A set not seen before: scan if it has few matches, else the best subset's index."""
    counts = lb_counts(new_sets, grouped)
    r = route(selection, new_sets)
    return counts.join(r, "bits", "left").select(
        "bits", "n_q", F.when(F.col("n_q") < scan_rows, "scan").otherwise("index").alias("plan"),
        F.when(F.col("n_q") >= scan_rows, F.col("index_bits")).alias("index_bits"),
    )


def admit_sets(universe: DataFrame, new_sets: DataFrame, grouped: DataFrame, min_rows: int = SCAN_ROWS) -> DataFrame:
    """The universe with those new sets that are large enough for an index."""
    counts = lb_counts(new_sets, grouped).filter(F.col("n_q") >= min_rows).select("bits", F.col("n_q").alias("n"))
    return universe.select("bits", "n").unionByName(counts.join(universe.select("bits"), "bits", "left_anti"))


def update_for_factor(lattice: sel.Lattice, current: list[int], c: float, charge_top: bool = False) -> sel.Selection:
    """Keep the selection while the bound holds; else go on from it greedily."""
    m = round(c * sel.MILLI)
    kept = [s for s in current if s in lattice.size]
    if sel.TOP not in kept and sel.TOP in lattice.size:
        kept.insert(0, sel.TOP)
    if lattice.factor(kept) >= Fraction(m, sel.MILLI):
        picks = [sel.Pick(s, lattice.size[s], 0, 0, lattice.size[s]) for s in kept]
        return sel.Selection(picks, lattice.cost(kept, charge_top), lattice.factor(kept), m, 0, lattice)
    return sel.select_for_factor(lattice, c, start=tuple(kept), charge_top=charge_top)


def update_for_budget(lattice: sel.Lattice, current: list[int], tau: int, c_milli: int, charge_top: bool = False, step: int = 1) -> sel.Selection:
    """Spare space raises c from the current selection; too little lowers c,
    prunes indexes that became redundant and goes on."""
    kept = [s for s in current if s in lattice.size] or [sel.TOP]

    def grown(c: int, start) -> sel.Selection:
        picks, n = sel.greedy(lattice, c, "lazy", tuple(start))
        chosen = sel.prune(lattice, [p.bits for p in picks], c)
        picks = [p for p in picks if p.bits in set(chosen)]
        return sel.Selection(picks, lattice.cost(chosen, charge_top), lattice.factor(chosen), c, n, lattice)

    best = None
    low, high = 0, sel.MILLI
    start = kept if lattice.cost(kept, charge_top) <= tau else [sel.TOP]
    first = grown(max(1, c_milli), start)
    if first.cost <= tau:
        best, low = first, c_milli
    else:
        high = c_milli
    while high - low > step:
        mid = max(1, (low + high) // 2)
        seed = start if mid >= c_milli else sel.prune(lattice, kept, mid)
        got = grown(mid, seed)
        if got.cost > tau:
            got = grown(mid, [sel.TOP])
        if got.cost <= tau:
            if best is None or got.realised >= best.realised:
                best = got
            low = mid
        else:
            high = mid
    if best is None:
        best = sel.Selection([sel.Pick(sel.TOP, lattice.size[sel.TOP], 0, 0, lattice.size[sel.TOP])], lattice.cost([sel.TOP], charge_top), lattice.factor([sel.TOP]), 1, 0, lattice)
    return best


class Manifest:
    """Versions of an index set.  A reader pins a version; a writer publishes
    the next by a rename that never replaces a file, and fails if another got
    there first."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self._jvm = spark.sparkContext._jvm
        self._conf = spark.sparkContext._jsc.hadoopConfiguration()
        self._fs = self._path(root).getFileSystem(self._conf)

    def _path(self, p: str):
        return self._jvm.org.apache.hadoop.fs.Path(p)

    def version(self) -> int:
        if not self._fs.exists(self._path(self.root)):
            return 0
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(self.root))]
        return max([int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json")], default=0)

    def read(self, version: int | None = None) -> list[dict]:
        v = self.version() if version is None else version
        if v == 0:
            return []
        stream = self._fs.open(self._path(f"{self.root}/v{v:08d}.json"))
        try:
            return json.loads(self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def publish(self, indexes: list[dict], base: int) -> int:
        final, aside = self._path(f"{self.root}/v{base + 1:08d}.json"), self._path(f"{self.root}/.{uuid.uuid4().hex}")
        out = self._fs.create(aside, False)
        try:
            out.write(json.dumps(indexes).encode())
        finally:
            out.close()
        options = self.spark.sparkContext._gateway.new_array(self._jvm.org.apache.hadoop.fs.Options.Rename, 0)
        try:
            files = self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._fs.getUri(), self._conf)
            files.rename(self._fs.makeQualified(aside), self._fs.makeQualified(final), options)
        except Py4JJavaError as e:
            name = e.java_exception.getClass().getName()
            if "UnsupportedFileSystem" in name and not self._fs.exists(final) and self._fs.rename(aside, final):
                return base + 1  # a scheme that only has the older interface
            self._fs.delete(aside, False)
            if "FileAlreadyExists" in name or "UnsupportedFileSystem" in name:
                raise RuntimeError("another writer published this version") from e
            raise
        return base + 1


def workload_of(sets: DataFrame) -> DataFrame:
    return sets.groupBy("bits").agg(F.count("*").alias("weight")).filter(lb._col("bits") >= 0)
