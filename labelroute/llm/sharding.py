"""Sharding with size-tiered compaction and a versioned manifest.

Main path: DataFrame functions, and the file system's listing and rename on the
driver.  Arrivals are appended as small immutable shards, one run per feed and
append.  Shard files below the target size form tiers by their size (powers of
``fanout`` over a floor), whatever the size of their run; a tier with ``fanout``
files or more is merged by narrow reads, without a shuffle, into files of the
target size, or into one smaller file that joins a higher tier.  A merge step
takes at most ``MERGE_FILES`` target files; the next step goes on with the rest.

Every change is a new manifest version, written aside and published by a rename
that fails if the version exists; readers see only whole runs.  (A store without
an atomic rename needs a committer of its own in ``_publish``.)  Folders have
unique names, so what a crashed writer left behind blocks nobody.  A writer that
finds its version taken fails and leaves the table as it was.  Files are deleted
by ``vacuum`` only: until then every older version stays readable.

Defined results: null feeds form a feed of their own; null and empty texts are
kept as they are; repeated rows are kept as often as they come; an empty arrival
commits a version without new runs; extra columns are stored whatever their
names; an empty store reads as an empty table.
"""

from __future__ import annotations

import json
import math
import re
import uuid
from dataclasses import asdict, dataclass, replace

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

TARGET_BYTES = 256 << 20
FANOUT = 4
#: Files up to this size are one tier.
FLOOR_BYTES = 1 << 20
#: Files that one merge writes at most; a full tier beyond takes several merges.
MERGE_FILES = 32


@dataclass(frozen=True)
class Run:
    name: str
    path: str
    bytes: int
    level: int
    #: Name and bytes of each file; others in the folder are not part of the run.
    files: list


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target_bytes: int = TARGET_BYTES, fanout: int = FANOUT):
        if fanout < 2:
            raise ValueError("fanout must be 2 or more")
        self.spark, self.root, self.target, self.fanout = spark, root.rstrip("/"), target_bytes, fanout
        self._jvm = spark.sparkContext._jvm
        self._fs = self._path(root).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _path(self, p: str):
        return self._jvm.org.apache.hadoop.fs.Path(p)

    # manifest -----------------------------------------------------------

    def versions(self) -> list[int]:
        folder = self._path(f"{self.root}/manifest")
        if not self._fs.exists(folder):
            return []
        names = [s.getPath().getName() for s in self._fs.listStatus(folder)]
        return sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))

    def runs(self, version: int | None = None) -> list[Run]:
        known = self.versions()
        if not known:
            return []
        v = known[-1] if version is None else version
        stream = self._fs.open(self._path(f"{self.root}/manifest/v{v:010d}.json"))
        try:
            text = self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return [Run(**r) for r in json.loads(text)["runs"]]

    def commit(self, runs: list[Run], base: int) -> int:
        """Publish ``runs`` as version ``base + 1``; fails if that exists."""
        aside = self._path(f"{self.root}/manifest/.tmp-{uuid.uuid4().hex}")
        out = self._fs.create(aside, False)
        try:
            out.write(json.dumps({"version": base + 1, "runs": [asdict(r) for r in runs]}).encode())
        finally:
            out.close()
        if not self._publish(aside, self._path(f"{self.root}/manifest/v{base + 1:010d}.json")):
            self._fs.delete(aside, False)
            raise RuntimeError(f"version {base + 1} was committed by another writer")
        return base + 1

    def _publish(self, aside, final) -> bool:
        """Rename that never replaces what is there."""
        conf = self.spark.sparkContext._jsc.hadoopConfiguration()
        options = self.spark.sparkContext._gateway.new_array(self._jvm.org.apache.hadoop.fs.Options.Rename, 0)
        try:
            files = self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._fs.getUri(), conf)
            files.rename(self._fs.makeQualified(aside), self._fs.makeQualified(final), options)
        except Py4JJavaError as e:
            name = e.java_exception.getClass().getName()
            if "FileAlreadyExists" in name:
                return False
            if "UnsupportedFileSystem" not in name:
                raise
            # a scheme that only has the older interface: its rename is as good as the store's
            return not self._fs.exists(final) and self._fs.rename(aside, final)
        return True

    def _version(self) -> int:
        known = self.versions()
        return known[-1] if known else 0

    # writing ------------------------------------------------------------

    def append(self, df: DataFrame, feed: Column | None = None) -> int:
        """One immutable run per feed (null feeds are one), no shuffle."""
        base, known = self._version(), self.runs()
        batch = f"{self.root}/runs/a{base + 1:010d}-0-{uuid.uuid4().hex}"
        taken, part = {c.lower() for c in df.columns}, "__feed__"
        while part in taken:  # names are compared without case
            part += "_"
        name = F.lit("all") if feed is None else F.coalesce(feed.cast("string"), F.lit("__null__"))
        df.withColumn(part, name).write.partitionBy(part).parquet(batch)
        new = []
        for s in self._fs.listStatus(self._path(batch)):
            folder = s.getPath().getName()
            if folder.startswith(f"{part}="):
                new.append(self._run(f"a{base + 1}/{folder.split('=', 1)[1]}", f"{batch}/{folder}", 0))
        return self.commit(known + sorted(new, key=lambda r: r.name), base)

    def _run(self, name: str, path: str, level: int) -> Run:
        files = []
        for s in self._fs.listStatus(self._path(path)):
            file = s.getPath().getName()
            if not file.startswith(("_", ".")):
                files.append([file, int(s.getLen())])
        return Run(name, path, sum(n for _, n in files), level, sorted(files))

    def tier(self, size: int) -> int:
        return 0 if size <= FLOOR_BYTES else 1 + int(math.log(size / FLOOR_BYTES, self.fanout))

    def compact(self, schema) -> int:
        """Merge full tiers until none is left; each merge is one version.

        Merged files stay for the readers of older versions; see ``vacuum``."""
        while True:
            base, runs = self._version(), self.runs()
            tiers: dict[int, list[tuple[str, int]]] = {}
            for r in runs:
                for file, size in r.files:
                    if size < self.target:
                        tiers.setdefault(self.tier(size), []).append((f"{r.path}/{file}", size))
            full = sorted(t for t, fs in tiers.items() if len(fs) >= self.fanout)
            if not full:
                return base
            bins = self._bins(tiers[full[0]])
            gone = {f for b in bins for f in b}
            kept, level = [], 0
            for r in runs:
                files = [f for f in r.files if f"{r.path}/{f[0]}" not in gone]
                if len(files) < len(r.files):
                    level = max(level, r.level)
                if files:
                    kept.append(replace(r, bytes=sum(n for _, n in files), files=files))
            self.commit([*kept, self._merge(bins, base + 1, level + 1, schema)], base)

    def vacuum(self, keep: int = 1) -> int:
        """Forget all but the newest ``keep`` versions and delete the files that
        only the forgotten ones named; returns how many files went."""
        known = self.versions()
        old, live = known[:-keep], {f"{r.path}/{f[0]}" for v in known[-keep:] for r in self.runs(v) for f in r.files}
        gone = {f"{r.path}/{f[0]}" for v in old for r in self.runs(v) for f in r.files} - live
        for v in old:  # a version goes before its files, so none is ever half there
            self._fs.delete(self._path(f"{self.root}/manifest/v{v:010d}.json"), False)
        for f in gone:
            self._fs.delete(self._path(f), False)
        return len(gone)

    def _bins(self, group: list[tuple[str, int]]) -> list[list[str]]:
        """Files to be merged into one each: of target size, but for a last one.
        Every bin has two files or more, so a merge leaves fewer files."""
        bins, now, held = [], [], 0
        for file, size in group:
            now.append(file)
            held += size
            if held >= self.target:
                bins.append(now)
                now, held = [], 0
                if len(bins) == MERGE_FILES:
                    break
        return [*bins, now] if len(now) > 1 else bins

    def _merge(self, bins: list[list[str]], version: int, level: int, schema) -> Run:
        """One task and one file for each bin; nothing is shuffled."""
        path = f"{self.root}/runs/m{version:010d}-{level}-{uuid.uuid4().hex}"
        out = None
        for b in bins:
            part = self.spark.read.schema(schema).parquet(*b).coalesce(1)
            out = part if out is None else out.union(part)
        # Spark otherwise lays single partitions of a union on top of each other
        name = "spark.sql.unionOutputPartitioning"
        old = self.spark.conf.get(name, None)
        self.spark.conf.set(name, "false")
        try:
            out.write.option("maxRecordsPerFile", 0).parquet(path)
        finally:
            if old is None:
                self.spark.conf.unset(name)
            else:
                self.spark.conf.set(name, old)
        return self._run(f"m{version}", path, level)

    # reading ------------------------------------------------------------

    def read(self, schema, version: int | None = None, origin: str | None = None) -> DataFrame:
        """All rows of a version, in one scan of its files.

        ``origin`` names a struct column (level, batch) to be added, which says
        in what merge or append a row was written last."""
        if origin and origin.lower() in {f.name.lower() for f in schema.fields}:
            raise ValueError(f"the table has a column {origin}")
        files = [f"{r.path}/{file}" for r in self.runs(version) for file, _ in r.files]
        out = self.spark.read.schema(schema).parquet(*files) if files else self.spark.createDataFrame([], schema)
        if not origin:
            return out
        at = re.escape(f"{self.root.rsplit('/', 1)[-1]}/runs/")
        part = lambda i: F.regexp_extract(F.input_file_name(), rf"{at}([am]\d+)-(\d+)-", i)
        return out.withColumn(origin, F.struct(part(2).cast("int").alias("level"), part(1).alias("batch")))


def compact_documents(docs: DataFrame, feed: str = "source", target_bytes: int = TARGET_BYTES, fanout: int = FANOUT) -> DataFrame:
    """Append ``docs`` by feed, compact, and read the newest version back."""
    spark = docs.sparkSession
    store = ShardStore(spark, common.shared_dir(spark, "shards"), target_bytes, fanout)
    store.append(docs, F.col(feed))
    store.compact(docs.schema)
    return store.read(docs.schema).select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col(feed).alias("feed"),
        F.octet_length("text").cast("long").alias("text_bytes"),
        F.md5("text").alias("text_md5"),
    )


ORACLE = """
SELECT doc_id, source AS feed, strlen(text)::BIGINT AS text_bytes, md5(text) AS text_md5 FROM documents
"""
