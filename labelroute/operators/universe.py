"""Candidate index sets and their sizes.

A universe is ``(bits, n)``: one candidate per query-label set, its size the
number of matching rows.  The label lattice is computed from the groups of
exact sets, never from rows: one scan, one small shuffle, then work on at most
one row per group.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import labels as lb

MIN_ROWS = 4_000


def universe_all(base: DataFrame, max_card: int = 16, min_rows: int = 0) -> DataFrame:
    """Every set that at least one row contains, the empty set included."""
    return from_groups(lb.groups(base), max_card, min_rows)


def from_groups(grouped: DataFrame, max_card: int = 16, min_rows: int = 0) -> DataFrame:
    out = (
        grouped.select(F.explode(lb.subsets("bits", max_card)).alias("bits"), "n")
        .groupBy("bits")
        .agg(F.sum("n").cast("long").alias("n"))
    )
    return drop_small(out, min_rows) if min_rows else out


def universe_workload(base: DataFrame, workload: DataFrame, how: str = "auto", max_card: int = 16, min_rows: int = 0) -> DataFrame:
    """Only the workload's sets (and the empty set); sets without a match go.

    ``explode`` meets the subsets of each group with the workload in an
    equi-join; ``rarest`` meets each set with the groups that hold its rarest
    label, at any width.  ``auto`` explodes when the widest group allows it.
    """
    spark = base.sparkSession
    grouped = lb.groups(base)
    wanted = workload.select("bits").unionByName(spark.createDataFrame([(0,)], "bits long")).distinct()
    if how == "auto":
        widest = grouped.agg(F.max(F.bit_count("bits"))).first()[0] or 0
        how = "explode" if widest <= max_card else "rarest"
    if how == "explode":
        out = from_groups(grouped, max_card).join(wanted, "bits", "left_semi")
    else:
        out = lb.counted(wanted, grouped).filter("match_count > 0").select("bits", F.col("match_count").alias("n"))
    return drop_small(out, min_rows) if min_rows else out


def drop_small(universe: DataFrame, min_rows: int = MIN_ROWS) -> DataFrame:
    """Sets under ``min_rows`` are answered by a scan and need no candidate."""
    return universe.filter((F.col("n") >= min_rows) | (F.col("bits") == 0))


def universe_sampled(base: DataFrame, one_in: int, seed: str = "", ident: str = "vec_id", max_card: int = 16) -> DataFrame:
    """Sizes from a hashed sample, scaled; with the standard error of each."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit(seed), F.col(ident).cast("string"))), 1, 8), 16, 10).cast("long")
    small = universe_all(base.filter(F.pmod(h, F.lit(one_in)) == 0), max_card)
    f = 1.0 / one_in
    return small.select(
        "bits",
        (F.col("n") * one_in).alias("n"),
        F.sqrt(F.col("n") * (1 - f) / (f * f)).alias("std_error"),
    )


def universe_sketch(base: DataFrame, workload: DataFrame, words: list[str], lg_k: int = 12, ident: str = "vec_id") -> DataFrame:
    """Sizes from one theta sketch per label, intersected per workload set.

    One scan, one sketch per label; what grows with the data is the scan alone.
    """
    base = base.withColumn("bits", F.col("bits"))
    per = (
        base.select(F.explode(F.array(*[F.when(F.col("bits").bitwiseAND(F.lit(1 << i).cast("long")) != 0, F.lit(i)) for i in range(len(words))])).alias("i"), ident)
        .filter("i IS NOT NULL")
        .groupBy("i")
        .agg(F.expr(f"theta_sketch_agg({ident}, {lg_k})").alias("sk"))
    )
    whole = base.agg(F.expr(f"theta_sketch_agg({ident}, {lg_k})").alias("all"))
    member = [F.when(F.col("bits").bitwiseAND(F.lit(1 << i).cast("long")) != 0, F.lit(i)) for i in range(len(words))]
    wide = workload.select("bits", F.array_compact(F.array(*member)).alias("need")).distinct()
    table = per.agg(F.map_from_entries(F.collect_list(F.struct("i", "sk"))).alias("t"))  # one sketch per label
    met = wide.crossJoin(F.broadcast(table)).crossJoin(F.broadcast(whole))
    out = F.aggregate(F.col("need"), F.col("all"), lambda a, i: F.call_function("theta_intersection", a, F.element_at("t", i)))
    return met.select("bits", F.call_function("theta_sketch_estimate", out).cast("long").alias("n"))


def universe_independent(base: DataFrame, workload: DataFrame, words: list[str]) -> DataFrame:
    """Sizes if labels were independent: N times the product of frequencies."""
    counts = [F.sum(F.when(F.col("bits").bitwiseAND(F.lit(1 << i).cast("long")) != 0, F.col("n")).otherwise(0)).alias(f"c{i}") for i in range(len(words))]
    row = lb.groups(base).agg(F.sum("n").alias("total"), *counts)
    met = workload.select("bits").distinct().crossJoin(F.broadcast(row))
    share = F.lit(1.0)
    for i in range(len(words)):
        share = share * F.when(F.col("bits").bitwiseAND(F.lit(1 << i).cast("long")) != 0, F.col(f"c{i}") / F.col("total")).otherwise(1.0)
    return met.select("bits", (F.col("total") * share).alias("n"))


def closures(universe: DataFrame, grouped: DataFrame, max_card: int = 16) -> DataFrame:
    """Adds ``closure``: the labels that all matching rows share."""
    per = (
        grouped.select(F.explode(lb.subsets("bits", max_card)).alias("bits"), F.col("bits").alias("g"))
        .groupBy("bits")
        .agg(F.bit_and("g").alias("closure"))
    )
    return universe.join(per, "bits")


def collapse_equal_extents(universe: DataFrame) -> DataFrame:
    """One set per closure: the smallest key among sets with the same rows."""
    return universe.groupBy("closure").agg(F.min("bits").alias("bits"), F.first("n").alias("n"))


def expected_examined(k: int, matching, total):
    """Nodes that a post-filter walk is expected to examine: the bound k/c and
    the exact value for matches placed at random."""
    return F.lit(float(k)) * total / matching, F.lit(float(k)) * (total + 1) / (matching + 1)
