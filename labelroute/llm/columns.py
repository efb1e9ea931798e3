"""Column functions from plain Python functions, by Arrow batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import functions as F


def mapped(fn: Callable, returns: str):
    """A column function that applies ``fn`` to every value."""

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            yield pd.Series([fn(t) for t in s], dtype=object)

    return F.pandas_udf(run, returns)
