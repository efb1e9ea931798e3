"""Deterministic numbers in [0, 1) from md5, the same in Spark and in SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def u(ident, j, seed: str = "") -> Column:
    """First eight hex digits of ``md5(seed || id || ':' || j)`` over 2^32."""
    text = F.concat(F.lit(seed), ident.cast("string"), F.lit(":"), j.cast("string") if isinstance(j, Column) else F.lit(str(j)))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)
