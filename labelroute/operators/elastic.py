"""Elastic factors and cover relations.

The factor of an index for a query set is the share of the index that matches;
of all indexes that hold every match the smallest has the largest factor.
Ratios are tested in LONG arithmetic with the bound in thousandths.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import labels as lb

MILLI = 1_000


def pair_factor(n_q, n_i):
    return n_q / n_i


def _held(universe: DataFrame, containment: str) -> str:
    if containment == "extents":
        if "closure" not in universe.columns:
            raise ValueError("extent containment needs universe.closures first")
        return "closure"
    return "bits"


def cover_edges(universe: DataFrame, c_milli: int | None = None, containment: str = "labels", max_card: int = 16) -> DataFrame:
    """Pairs (src, dst): the index ``src`` answers ``dst`` with factor ``>= c``.

    The containment join is an equi-join on exploded subsets of ``dst``.
    """
    col = _held(universe, containment)
    dst = universe.select(F.col("bits").alias("dst"), F.col("n").alias("n_dst"), F.explode(lb.subsets(col, max_card)).alias("src"))
    src = universe.select(F.col("bits").alias("src"), F.col("n").alias("n_src"))
    out = dst.join(src, "src")
    if c_milli is not None:
        out = out.filter(F.col("n_dst") * MILLI >= F.lit(c_milli).cast("long") * F.col("n_src"))
    return out.select("src", "dst", "n_src", "n_dst")


def serving(universe: DataFrame, selection: DataFrame, containment: str = "labels", max_card: int = 16) -> DataFrame:
    """For each set of ``universe`` the smallest selected index that serves it."""
    col = _held(universe, containment)
    s = selection.select(F.col("bits").alias("index_bits"), F.col("n").alias("n_i"))
    q = universe.select("bits", F.col("n").alias("n_q"), F.explode(lb.subsets(col, max_card)).alias("index_bits"))
    return q.join(s, "index_bits").groupBy("bits", "n_q").agg(F.min(F.struct("n_i", "index_bits")).alias("b")).select(
        "bits", "n_q", F.col("b.index_bits").alias("index_bits"), F.col("b.n_i").alias("n_i")
    )


def elastic_factor(universe: DataFrame, selection: DataFrame, containment: str = "labels") -> DataFrame:
    return serving(universe, selection, containment).select("bits", (F.col("n_q") / F.col("n_i")).alias("factor"))


def factor_summary(universe: DataFrame, selection: DataFrame, containment: str = "labels") -> DataFrame:
    f = elastic_factor(universe, selection, containment)
    return f.agg(F.min("factor").alias("min_factor"), F.avg("factor").alias("mean_factor"), F.count("*").alias("sets"))


def is_feasible(universe: DataFrame, selection: DataFrame, c_milli: int, tau: int, charge_top: bool = True) -> DataFrame:
    """One row: the cost, the sets below the bound and whether both limits hold."""
    s = serving(universe, selection).agg(
        F.sum(F.when(F.col("n_q") * MILLI < F.lit(c_milli).cast("long") * F.col("n_i"), 1).otherwise(0)).cast("long").alias("violations")
    )
    counted = selection if charge_top else selection.filter("bits <> 0")
    cost = counted.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("cost"))
    return s.crossJoin(cost).select("violations", "cost", ((F.col("violations") == 0) & (F.col("cost") <= tau)).alias("feasible"))


def overlap_sizes(sets: DataFrame, grouped: DataFrame) -> DataFrame:
    """Rows that share at least one label with each set."""
    return lb.counted(sets, grouped, "overlap").filter("match_count > 0").select("bits", F.col("match_count").alias("n"))


def overlap_factor(sets: DataFrame, selection: DataFrame, grouped: DataFrame) -> DataFrame:
    """Overlap queries: sharing runs upward, an index of a superset serves a set.

    The index of everything serves whatever no selected superset does.
    """
    q = overlap_sizes(sets, grouped).select("bits", F.col("n").alias("n_q"))
    i = overlap_sizes(selection.filter("bits <> 0"), grouped).select(F.col("bits").alias("i"), F.col("n").alias("n_i"))
    total = grouped.agg(F.sum("n").cast("long").alias("total"))
    above = lb.meeting(q, i.withColumnRenamed("i", "bits")).select("qbits", F.col("bits").alias("i"))
    least = above.join(i, "i").groupBy("qbits").agg(F.min("n_i").alias("n_i"))
    met = q.join(least, q["bits"] == least["qbits"], "left")
    return met.crossJoin(F.broadcast(total)).select("bits", (F.col("n_q") / F.least(F.coalesce("n_i", "total"), "total")).alias("factor"))


def equality_factor(grouped: DataFrame, selection: DataFrame) -> DataFrame:
    """Equality queries: the exact group over the smallest containment index."""
    return elastic_factor(grouped, selection)
