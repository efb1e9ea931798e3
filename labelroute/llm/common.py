"""Shared helpers of the training-data operators: table access, the shared
scratch folder, Arrow batch sizes and distributed connected components."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows and bytes of one Arrow batch sent to a Python worker.  Bytes bound the
#: worker's memory even where single texts are very long.
BATCH_ROWS = 2000
BATCH_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tune_arrow(spark: SparkSession) -> None:
    """Bound Arrow batches by bytes as well as rows (runtime settings)."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def shared_dir(spark: SparkSession, purpose: str) -> str:
    """A fresh folder that the driver and every executor can reach.

    ``spark.checkpoint.dir`` names it on a cluster.  Only a local session that
    does not set it falls back to a temporary folder of this machine.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="labelroute-")
        spark.conf.set("spark.checkpoint.dir", base)
    return f"{base.rstrip('/')}/{purpose}-{uuid.uuid4().hex}"


def cut(df: DataFrame, spark: SparkSession, purpose: str) -> DataFrame:
    """Cut lineage: write ``df`` to the shared folder and read it back.

    The folder goes when the application ends."""
    path = shared_dir(spark, purpose)
    df.write.parquet(path)
    _file_system(spark, path).deleteOnExit(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path))
    return spark.read.schema(df.schema).parquet(path)


def _file_system(spark: SparkSession, path: str):
    return spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def numbers(spark: SparkSession, **columns: list[int] | np.ndarray) -> DataFrame:
    """A small table of long columns, handed over as Arrow: no Python worker is
    started on the executors for it."""
    return spark.createDataFrame(pa.table({name: pa.array(x, pa.int64()) for name, x in columns.items()}))


#: Words of 64 bits in the bitmap that ``may_be_in`` sends, its bound at any size.
BITMAP_WORDS = 1 << 19


def free_name(name: str, *frames: DataFrame) -> str:
    """``name``, lengthened until no column of ``frames`` has it."""
    taken = {c.lower() for df in frames for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def may_be_in(rows: DataFrame, key: str, ids: DataFrame, flag: str) -> DataFrame:
    """``rows`` with a boolean ``flag`` that is true wherever ``key`` is among
    the values of the only column of ``ids``, and rarely elsewhere.

    The values are hashed to a bitmap of ``BITMAP_WORDS`` words, summed on the
    executors and broadcast, so rows that a join would drop need not be shuffled
    for it.  Far more values than bits prune less; the join decides in any case.
    """
    bits = BITMAP_WORDS * 64
    at = lambda c: F.pmod(F.xxhash64(F.col(f"`{c}`").cast("string")), F.lit(bits))
    mask = lambda bit: F.expr(f"shiftleft(1L, cast({bit} % 64 AS int))")
    word, held, bit = (free_name(n, rows) for n in ("_word", "_held", "_bit"))
    table = (
        ids.select(at(ids.columns[0]).alias("bit"))
        .groupBy(F.expr("bit div 64").alias(word))
        .agg(F.bit_or(mask("bit")).alias(held))
    )
    probed = rows.withColumn(bit, at(key)).withColumn(word, F.expr(f"{bit} div 64")).join(F.broadcast(table), word, "left")
    return probed.withColumn(flag, F.coalesce(F.col(held).bitwiseAND(mask(bit)) != 0, F.lit(False))).select(*[f"`{c}`" for c in rows.columns], flag)


def delete_path(spark: SparkSession, path: str) -> None:
    _file_system(spark, path).delete(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path), True)


#: Distinct edges, of 16 bytes, up to which components are found on the driver.
LOCAL_EDGES = 1 << 18


def _components(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the edges ``a``-``b`` and the smallest node of each one's component."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    u, v = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while True:
        x, y = root[u], root[v]
        if (x == y).all():
            return nodes, nodes[root]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(root, up := root[root]):
            root = up


def connected_components(edges: DataFrame, spark: SparkSession, max_rounds: int = 60, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """Connected components of ``edges(a, b)`` as ``(node, component)``, the
    component being its smallest node.

    Up to ``local_edges`` distinct edges go to the driver; with more, rounds
    alternate the large-star and small-star contractions on distributed edge
    tables; each round is cut by a written table, so a lost executor costs one
    round.  The hot centre of a star meets only aggregates with map-side
    combine and joins that adaptive execution can split.
    """

    def star(e: DataFrame, large: bool) -> DataFrame:
        # e holds (a, b) with a > b
        both = e.select("a", "b").unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        view = both if large else e.select("a", "b")
        low = view.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        joined = view.join(low, "a")
        if large:
            out = joined.filter(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        else:
            out = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(
                low.select("a", F.col("m").alias("b"))
            )
        return out.filter("a > b").distinct()

    base = edges.filter("a IS NOT NULL AND b IS NOT NULL AND a <> b")
    now = cut(
        base.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), spark, "cc"
    )
    if now.count() <= local_edges:  # as written: a count reads no rows
        few = now.select(F.col("a").cast("long"), F.col("b").cast("long")).toArrow()
        node, component = _components(*(few[c].to_numpy() for c in ("a", "b")))
        return numbers(spark, node=node, component=component)
    seen = None
    for _ in range(max_rounds):
        now = cut(star(star(now, True), False), spark, "cc")
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError("components did not settle")
    members = now.select(F.col("a").alias("node"), F.col("b").alias("component"))
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return members.unionByName(roots)
