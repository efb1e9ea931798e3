"""Which index answers which query set."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import labels as lb

SCAN_ROWS = 4_000


def route(selection: DataFrame, query_sets: DataFrame, max_card: int = 16, by: tuple[str, ...] = ()) -> DataFrame:
    """(bits, index_bits, n_i): the smallest selected index whose labels the query contains;
    for each value of the selection's columns ``by``, if any are named."""
    s = selection.select(*by, F.col("bits").alias("index_bits"), F.col("n").alias("n_i"))
    q = query_sets.select("bits").distinct().filter("bits >= 0")
    return (
        q.select("bits", F.explode(lb.subsets("bits", max_card)).alias("index_bits"))
        .join(s, "index_bits")
        .groupBy(*by, "bits")
        .agg(F.min(F.struct("n_i", "index_bits")).alias("b"))
        .select(*by, "bits", F.col("b.index_bits").alias("index_bits"), F.col("b.n_i").alias("n_i"))
    )


def plan(selection: DataFrame, query_sets: DataFrame, grouped: DataFrame, scan_rows: int = SCAN_ROWS) -> DataFrame:
    """Adds match counts: sets with fewer than ``scan_rows`` matches are scanned."""
    counts = lb_counts(query_sets, grouped)
    return counts.join(route(selection, query_sets), "bits", "left").select(
        "bits",
        F.when(F.col("n_q") < scan_rows, "scan").otherwise("index").alias("plan"),
        F.when(F.col("n_q") >= scan_rows, F.col("index_bits")).alias("index_bits"),
        "n_q",
        "n_i",
    )


def lb_counts(query_sets: DataFrame, grouped: DataFrame) -> DataFrame:
    return lb.counted(query_sets, grouped).withColumnRenamed("match_count", "n_q")


def auto_strategy(match_count, total, k, flat_cost: float = 1.0):
    """Pre- or post-filtering by estimated work: scanning the matches against
    walking k/selectivity nodes."""
    walk = F.lit(float(k)) * total / F.greatest(match_count, F.lit(1)) * 10.0
    return F.when(match_count * flat_cost <= walk, "pre").otherwise("post")
