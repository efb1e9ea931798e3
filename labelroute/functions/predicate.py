"""Boolean trees of label tests, compiled to one expression over bit forms."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from .labels import _col


@dataclass(frozen=True)
class LabelPredicate:
    op: str
    args: tuple

    @staticmethod
    def has(label: str) -> LabelPredicate:
        return LabelPredicate("has", (label,))

    def __and__(self, other: LabelPredicate) -> LabelPredicate:
        return LabelPredicate("and", (self, other))

    def __or__(self, other: LabelPredicate) -> LabelPredicate:
        return LabelPredicate("or", (self, other))

    def __invert__(self) -> LabelPredicate:
        return LabelPredicate("not", (self,))

    def column(self, bits, words: list[str]) -> Column:
        if self.op == "has":
            if self.args[0] not in words:
                return F.lit(False)
            return _col(bits).bitwiseAND(F.lit(1 << words.index(self.args[0])).cast("long")) != 0
        parts = [a.column(bits, words) for a in self.args]
        return ~parts[0] if self.op == "not" else parts[0] & parts[1] if self.op == "and" else parts[0] | parts[1]
