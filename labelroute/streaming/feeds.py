"""Streams: live query sets, inserts, late and repeated rows, refresh triggers.

Each function takes a streaming (or batch) DataFrame and stays declarative;
``drain`` runs a stream to the end of its present input.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.sinks import scratch
from ..sources.tables import SCHEMAS, path


def event_stream(spark: SparkSession, sf_dir: str, rows_per_trigger: int | None = None) -> DataFrame:
    """The events table as a file stream with an instant as event time."""
    raw = spark.readStream.schema(SCHEMAS["events"]).parquet(path(sf_dir, "events") + "*")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def workload_counts(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts per event window and query key; state is the open windows' keys."""
    w = F.window("ts", size, slide or size)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "key").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour", by: str = "user_id") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count("*").alias("n"))


def once(events: DataFrame, key: str = "event_id", late: str = "2 days") -> DataFrame:
    """Repeated ids inside the watermark pass once; later ones are dropped as late."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def insert_stream(rows: DataFrame, apply: Callable[[DataFrame, int], None], checkpoint: str):
    """Micro-batches of new rows handed to ``apply`` (an idempotent append by batch id)."""
    return rows.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def refresh_trigger(inserts: DataFrame, base_rows: int, share: float = 0.1) -> DataFrame:
    """(index, new_rows) whenever an index has gathered ``share`` of its base rows.

    State is one counter per index.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    limit = max(1, int(base_rows * share))

    def count(key, batches, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        fired = n // limit
        state.update((n % limit,))
        yield pd.DataFrame({"key": [key[0]] * fired, "new_rows": [limit] * fired})

    return inserts.groupBy("key").applyInPandasWithState(
        count, "key string, new_rows long", "n long", "append", GroupStateTimeout.NoTimeout
    )


def drain(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what its source holds now; the result as a table.

    Every micro-batch is written under its own number in the shared folder, so one
    that comes again replaces itself; of a ``complete`` stream the last is the
    result.
    """
    spark, folder = df.sparkSession, scratch(df.sparkSession, f"stream-{name}")
    last: list[int] = []

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/b{batch_id:08d}")
        last.append(batch_id)

    q = df.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    if not last:
        return spark.createDataFrame([], df.schema)
    paths = [f"{folder}/out/b{i:08d}" for i in sorted(set(last))]
    return spark.read.schema(df.schema).parquet(*(paths[-1:] if mode == "complete" else paths))


def file_stream(spark: SparkSession, parts: list[DataFrame]) -> DataFrame:
    """A stream whose micro-batches are the given tables, in order."""
    folder = scratch(spark, "arrivals")
    for part in parts:  # one file each; sources take files by their time
        part.coalesce(1).write.mode("append").parquet(folder)
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(folder)


def local_checkpoints(spark: SparkSession) -> None:
    """The session's shared folder for ``DataFrame.checkpoint``; a temporary one
    only in local sessions that name none."""
    spark.sparkContext.setCheckpointDir(scratch(spark, "checkpoints"))
