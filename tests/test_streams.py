from pyspark.sql import functions as F

from labelroute.queries import QUERIES
from labelroute.streaming import feeds


def test_repeated_events_pass_once(spark, small):
    assert QUERIES["f12_dedup_late"](spark, small).count() == 1000


def test_late_rows_are_dropped(spark, small):
    ids = [r["event_id"] for r in QUERIES["f12_dedup_late"](spark, small).collect()]
    assert min(ids) >= 0 and len(ids) == len(set(ids))


def test_replayed_batches_count_once(spark, small):
    got = {r["index_key"]: r["rows"] for r in QUERIES["f10_stream_insert"](spark, small).collect()}
    events = spark.read.parquet(f"{small}/events.parquet").filter("event_id % 2 = 1")
    assert got["∅"] == events.count()
    assert got["type:click"] == events.filter("event_type = 'click'").count()


def test_stream_counts_equal_batch(spark, small):
    e = spark.read.parquet(f"{small}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("key", F.col("event_type"))
    batch = {(str(r["w"]["start"])[:16], r["key"], r["n"]) for r in feeds.workload_counts(e).collect()}
    live = {tuple(r) for r in QUERIES["f11_window_workload"](spark, small).select("start", "key", "n").collect()}
    assert batch == live


def test_refresh_trigger_fires(spark, small):
    fired = QUERIES["f13_refresh_trigger_state"](spark, small).agg(F.sum("refreshes")).first()[0]
    assert 15 <= fired <= 20
