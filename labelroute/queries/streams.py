"""Streaming queries.  Each runs its stream to the end of the present input."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..functions import labels as lb
from ..operators import universe as un
from ..operators import versioned
from ..operators.versioned import IndexStore
from ..sources import datasets as ds
from ..sources.sinks import scratch
from ..sources.tables import load
from ..streaming import feeds
from .common import key

Q, O = {}, {}  # noqa: E741


def query(name, sql=None):
    def put(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f

    return put


def _name(stem):
    return f"{stem}_{uuid.uuid4().hex[:8]}"


def _events(s, d):
    return feeds.event_stream(s, d)


_EVENT_LABELS = """list_sort(['type:' || event_type, 'day:' || (dayofweek(ts) + 1), 'user:' || (user_id % 4)])"""


@query(
    "f10_stream_insert",
    f"""WITH base AS (SELECT event_id, {_EVENT_LABELS} AS labels FROM events),
sel AS (SELECT DISTINCT [x] AS labels FROM (SELECT unnest(labels) AS x FROM base WHERE event_id % 2 = 0) UNION ALL SELECT []::VARCHAR[])
SELECT CASE WHEN len(sel.labels) = 0 THEN '∅' ELSE sel.labels[1] END AS index_key, count(*) AS rows
FROM base JOIN sel ON list_has_all(base.labels, sel.labels) WHERE event_id % 2 = 1 GROUP BY 1""",
)
def _(s, d):
    """Every other event is inserted from a stream, with its own labels, into the
    indexes of the others; each micro-batch comes twice and counts once."""
    e = load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    words = lb.dictionary(ds.event_rows(e))
    base = lb.encode(ds.event_rows(e.filter("event_id % 2 = 0")), words)
    u = un.universe_all(base)
    home = IndexStore(s, scratch(s, "inserts"), "flat")
    home.create(base, u.filter(F.bit_count("bits") <= 1))

    def apply(batch, batch_id):
        rows = lb.encode(ds.event_rows(batch), words)
        home.insert(rows, batch_id)
        home.insert(rows, batch_id)  # a replay after a failure

    arriving = feeds.file_stream(s, [e.filter(f"event_id % 2 = 1 AND event_id % 3 {sign} 0") for sign in ("=", "<>")])
    feeds.insert_stream(arriving, apply, scratch(s, "inserts-state")).awaitTermination()
    return versioned.membership(home.waiting()).select(key(words, "index_bits", "index_key"), "rows")


def _windowed(s, d, size, slide=None):
    e = _events(s, d).withColumn("key", F.col("event_type"))
    out = feeds.drain(feeds.workload_counts(e, size, slide), _name("wl"), "complete")
    return out.select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "key", "n")


_DAY = "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS start, event_type AS key, count(*) AS n FROM events GROUP BY 1, 2"


@query("f11_window_workload", _DAY)
def _(s, d):
    return _windowed(s, d, "1 day")


@query("o_stream_tumbling", _DAY.replace("'day'", "'hour'"))
def _(s, d):
    return _windowed(s, d, "1 hour")


@query(
    "o_stream_sliding",
    "SELECT strftime(b, '%Y-%m-%d %H:%M') AS start, event_type AS key, count(*) AS n FROM "
    "(SELECT event_type, unnest([date_trunc('day', ts), CASE WHEN hour(ts) >= 12 THEN date_trunc('day', ts) + INTERVAL 12 HOUR ELSE date_trunc('day', ts) - INTERVAL 12 HOUR END]) AS b FROM events) GROUP BY 1, 2",
)
def _(s, d):
    return _windowed(s, d, "1 day", "12 hours")


@query(
    "o_stream_session",
    """WITH a AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events),
b AS (SELECT user_id, ts, sum(CASE WHEN p IS NULL OR ts >= p + INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, p ROWS UNBOUNDED PRECEDING) AS g FROM a)
SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, g, count(*) AS n FROM b GROUP BY user_id, g) GROUP BY user_id, n""",
)
def _(s, d):
    w = feeds.drain(feeds.sessions(_events(s, d)), _name("sessions"), "complete")
    return w.groupBy("user_id", "n").agg(F.count("*").alias("sessions"))


@query("f12_dedup_late", "SELECT event_id, event_type FROM events")
def _(s, d):
    """Every event comes twice, then rows that are later than the watermark: those
    with a year-old instant are dropped, whatever their id."""
    e = load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    twice = e.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    first, second = (twice.filter(f"event_id % 2 = {i}") for i in (0, 1))
    # a micro-batch is held against the watermark of the one before it
    late = e.withColumn("event_id", -1 - F.col("event_id")).withColumn("ts", F.col("ts") - F.expr("INTERVAL 400 DAYS"))
    return feeds.drain(feeds.once(feeds.file_stream(s, [first, second, late])).select("event_id", "event_type"), _name("once"))


@query("o_stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(s, d):
    return Q["f12_dedup_late"](s, d).groupBy("event_type").agg(F.count("*").alias("n"))


@query("o_stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def _(s, d):
    c = load(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return feeds.drain(_events(s, d).join(c, "user_id").select("event_id", "c_mktsegment"), _name("static"))


@query(
    "o_stream_stream_join",
    "SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR",
)
def _(s, d):
    a = _events(s, d).select(F.col("event_id").alias("left_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "3 hours")
    b = _events(s, d).select(F.col("event_id").alias("right_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "3 hours")
    on = F.expr("u1 = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL 2 HOURS")
    return feeds.drain(a.join(b, on).select("left_id", "right_id"), _name("pairs"))


@query("f13_refresh_trigger_state")
def _(s, d):
    e = _events(s, d).select(F.col("event_type").alias("key"), "event_id")
    fired = feeds.drain(feeds.refresh_trigger(e, 1000, 0.05), _name("fired"))
    return fired.groupBy("key").agg(F.count("*").alias("refreshes"))


@query("o_stream_rate")
def _(s, d):
    r = s.readStream.format("rate-micro-batch").option("rowsPerBatch", 100).option("numPartitions", 2).load()
    return feeds.drain(r.select("value"), _name("rate"))
