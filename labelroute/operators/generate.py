"""Label generators of the synthetic sets and query-set generators.

All numbers come from ``rng.u``, which SQL reproduces exactly.  Labels are named
``L01``, ``L02``, ...
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import labels as lb
from ..functions.rng import u

P0 = 0.6


def name(j: int) -> str:
    return f"L{j:02d}"


def _present(conds: list[Column]) -> Column:
    return F.array_compact(F.array(*[F.when(c, F.lit(name(j + 1))) for j, c in enumerate(conds)]))


def zipf(df: DataFrame, alphabet: int = 12, p0: float = P0, s: float = 1.0, seed: str = "", ident: str = "vec_id") -> DataFrame:
    """Label j is present with probability ``p0 / j^s``."""
    return df.withColumn("labels", _present([u(F.col(ident), j, seed) * (j**s) < p0 for j in range(1, alphabet + 1)]))


def uniform(df: DataFrame, alphabet: int = 12, p: float = 0.25, seed: str = "", ident: str = "vec_id") -> DataFrame:
    return df.withColumn("labels", _present([u(F.col(ident), j, seed) < p for j in range(1, alphabet + 1)]))


def poisson_cuts(rate: float, most: int) -> list[float]:
    """Cumulative probabilities of 0, 1, ... of a Poisson variable, rounded to 9 digits."""
    out, p = [], math.exp(-rate)
    total = p
    for k in range(most):
        out.append(round(total, 9))
        p *= rate / (k + 1)
        total += p
    return out


def poisson(df: DataFrame, alphabet: int = 12, rate: float = 2.0, seed: str = "", ident: str = "vec_id") -> DataFrame:
    """Set size by inverse distribution, labels by the rank of their numbers."""
    size = sum((F.when(u(F.col(ident), 0, seed) >= c, 1).otherwise(0) for c in poisson_cuts(rate, alphabet)), F.lit(0))
    order = F.array_sort(F.array(*[F.struct(u(F.col(ident), j, seed).alias("x"), F.lit(name(j)).alias("l")) for j in range(1, alphabet + 1)]))
    taken = F.transform(F.slice(order, F.lit(1), F.least(size, F.lit(alphabet))), lambda s: s["l"])
    return df.withColumn("labels", F.array_sort(taken))


def multinomial_cuts(alphabet: int) -> list[float]:
    """Cumulative weights proportional to 1/sqrt(j), rounded to 9 digits."""
    w = [1 / math.sqrt(j) for j in range(1, alphabet + 1)]
    out, total = [], 0.0
    for x in w:
        total += x / sum(w)
        out.append(round(total, 9))
    return out


def multinomial(df: DataFrame, alphabet: int = 12, draws: int = 3, seed: str = "", ident: str = "vec_id") -> DataFrame:
    """``draws`` draws from a categorical table; repeats collapse."""
    cuts = multinomial_cuts(alphabet)

    def one(d: int) -> Column:
        x = u(F.col(ident), d, seed + "m")
        at = sum((F.when(x >= c, 1).otherwise(0) for c in cuts[:-1]), F.lit(0))
        return F.element_at(F.array(*[F.lit(name(j + 1)) for j in range(alphabet)]), at + 1)

    return df.withColumn("labels", F.array_sort(F.array_distinct(F.array(*[one(d) for d in range(draws)]))))


def at_selectivity(universe: DataFrame, targets: list[float], total: int) -> DataFrame:
    """For each target the set whose share of the rows is nearest, ties by key."""
    t = universe.sparkSession.createDataFrame([(float(x),) for x in targets], "target double")
    gap = F.abs(F.col("n") / F.lit(float(total)) - F.col("target"))
    best = universe.join(F.broadcast(t), F.lit(True)).groupBy("target").agg(F.min(F.struct(gap.alias("gap"), "key", "n")).alias("b"))
    return best.select("target", F.col("b.key").alias("key"), F.col("b.n").alias("n"))


def factor_bins(factors: DataFrame, edges: tuple[float, ...] = (0.001, 0.01, 0.1, 1.0)) -> DataFrame:
    """Sets by the decade of their elastic factor (bin = lower edge)."""
    b = F.lit(0.0)
    for e in edges:
        b = F.when(F.col("factor") >= e, F.lit(e)).otherwise(b)
    return factors.withColumn("bin", b)


def phases(df: DataFrame, first: int = 12, second: int = 24, ident: str = "vec_id") -> tuple[DataFrame, DataFrame]:
    """Half of the rows with a small alphabet, the other half with a larger one."""
    even = F.pmod(F.col(ident), F.lit(2)) == 0
    return zipf(df.filter(even), first), zipf(df.filter(~even), second)


def query_sets(queries: DataFrame, alphabet: int = 12, seed: str = "q", ident: str = "vec_id") -> DataFrame:
    """Query labels from the base's distribution under another seed."""
    return zipf(queries, alphabet, seed=seed, ident=ident)


def own_subsets(base: DataFrame, seed: str = "s", p: float = 0.5, ident: str = "vec_id") -> DataFrame:
    """Query labels as a random subset of the row's own labels (never without a match)."""
    kept = F.filter(lb.canon("labels"), lambda x: u(F.col(ident), x, seed) < p)
    return base.withColumn("qlabels", kept)
