"""Writers and round trips through the shared folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def scratch(spark: SparkSession, name: str) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="labelroute-")
        spark.conf.set("spark.checkpoint.dir", base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def saved(df: DataFrame, name: str = "cut") -> DataFrame:
    """``df`` as a table of the shared folder: computed once, and lineage ends
    there.  The folder goes when the application ends."""
    spark, path = df.sparkSession, scratch(df.sparkSession, name)
    df.write.parquet(path)
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    folder = jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(conf).deleteOnExit(folder)
    return spark.read.schema(df.schema).parquet(path)


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    spark, path = df.sparkSession, scratch(df.sparkSession, fmt)
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.format(fmt).options(**options).save(path)
    return spark.read.format(fmt).options(**options).schema(df.schema).load(path)


def partitioned(df: DataFrame, by: str) -> DataFrame:
    path = scratch(df.sparkSession, "partitioned")
    df.write.partitionBy(by).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def overwritten(df: DataFrame, by: str, gone: Column) -> DataFrame:
    """Replace only the partitions that ``gone`` names, here by null rows."""
    spark, path = df.sparkSession, scratch(df.sparkSession, "overwritten")
    df.write.partitionBy(by).parquet(path)
    empty = df.filter(gone).limit(1).select(*[(F.col(c) if c == by else F.lit(None).cast(t).alias(c)) for c, t in df.dtypes])
    empty.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, by: str, buckets: int) -> DataFrame:
    """``df`` as a table in the shared folder whose joins on ``by`` need no shuffle."""
    spark, name = df.sparkSession, f"bucketed_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, by).sortBy(by).option("path", scratch(spark, "bucketed")).saveAsTable(name)
    return spark.table(name)
