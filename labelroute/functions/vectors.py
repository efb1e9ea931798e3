"""Vector expressions, JVM-side.  Distances are squared Euclidean in DOUBLE."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .labels import _col


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + v)


def l2sq(a, b) -> Column:
    d = lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))
    return _sum(F.zip_with(_col(a), _col(b), d))


def dot(a, b) -> Column:
    return _sum(F.zip_with(_col(a), _col(b), lambda x, y: x.cast("double") * y.cast("double")))


def norm(a) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a, b) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def distance(a, b, metric: str = "l2") -> Column:
    """Smaller is nearer, whatever the metric."""
    return {"l2": l2sq, "ip": lambda x, y: -dot(x, y), "cosine": lambda x, y: 1 - cosine(x, y)}[metric](a, b)


def scale(a, s) -> Column:
    return F.transform(_col(a), lambda x: x.cast("double") * s)


def normalise(a) -> Column:
    n = norm(a)
    return F.transform(_col(a), lambda x: x.cast("double") / n)


def add(a, b) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x.cast("double") + y.cast("double"))


def hyperplane_bits(a, planes: list[list[float]]) -> Column:
    """Sign bits against fixed planes: the bucket of a random-hyperplane table."""
    out = F.lit(0).cast("long")
    for i, p in enumerate(planes):
        side = dot(a, F.array(*map(F.lit, p))) >= 0
        out = out + F.when(side, F.lit(1 << i).cast("long")).otherwise(F.lit(0).cast("long"))
    return out
