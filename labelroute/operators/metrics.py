"""Measures: recall, sizes, selectivity, work."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Per query the share of the exact answer that was found (1 if that is empty)."""
    hit = found.select("qid", "vec_id").distinct().withColumn("hit", F.lit(1))
    return truth.select("qid", "vec_id").join(hit, ["qid", "vec_id"], "left").groupBy("qid").agg(
        (F.count("hit") / F.count("*")).alias("recall")
    )


def mean_recall(found: DataFrame, truth: DataFrame) -> float:
    return recall(found, truth).agg(F.avg("recall")).first()[0]


def label_precision(result: DataFrame) -> DataFrame:
    return result.groupBy("qid").agg(F.avg(F.col("match").cast("int")).alias("label_precision"))


def index_rows(selection: DataFrame) -> DataFrame:
    return selection.agg(F.count("*").alias("indexes"), F.sum("n").cast("long").alias("rows"))


def link_bytes(selection: DataFrame, m: int = 16) -> DataFrame:
    """Estimated bytes of links, a four-byte id each, ``2m`` on the ground layer."""
    return selection.agg((F.sum("n") * F.lit(8 * m)).cast("long").alias("bytes"))


def timed(action: Callable):
    began = time.perf_counter()
    out = action()
    return out, time.perf_counter() - began


def at_recall(sweep: list[tuple[float, float]], target: float) -> float | None:
    """Throughput at a recall, by a straight line between the bracketing points."""
    points = sorted(sweep)
    for (r0, q0), (r1, q1) in zip(points, points[1:], strict=False):
        if r0 <= target <= r1:
            return q0 if r1 == r0 else q0 + (q1 - q0) * (target - r0) / (r1 - r0)
    return None


def approximation_gap(greedy_cost: int, optimal_cost: int) -> float:
    return greedy_cost / optimal_cost
