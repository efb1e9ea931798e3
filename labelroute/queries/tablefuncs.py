"""Python table functions, for SQL users of the label algebra."""

from __future__ import annotations

from pyspark.sql.functions import udtf


@udtf(returnType="key string")
class LabelSubsets:
    """All subsets of a label array, as keys."""

    def eval(self, labels):
        names = sorted({x for x in labels or [] if x is not None})
        for m in range(1 << len(names)):
            picked = [x for i, x in enumerate(names) if m >> i & 1]
            yield ("|".join(picked) if picked else "∅",)


@udtf(returnType="round int, key long, num long, den long")
class GreedyTrace:
    """Rounds of the greedy selection over sizes given as ``"bits:n,..."``."""

    def eval(self, sizes: str, c: float):
        from labelroute.operators.select import Lattice, greedy

        size = {int(a): int(b) for a, b in (x.split(":") for x in sizes.split(","))}
        trace: list = []
        greedy(Lattice.of(size), round(c * 1000), "plain", trace=trace)
        yield from trace


@udtf(returnType="vec_id long, dist double")
class NearestOf:
    """The ``k`` nearest rows of a table argument's partition to a vector, by
    squared distance; holds ``k`` rows."""

    def __init__(self):
        self.best, self.k = [], 0

    def eval(self, row, vec, k):
        import heapq

        d = sum((float(a) - float(b)) ** 2 for a, b in zip(row["vec"], vec, strict=True))
        self.k = int(k)
        heapq.heappush(self.best, (-d, -row["vec_id"]))
        if len(self.best) > self.k:
            heapq.heappop(self.best)

    def terminate(self):
        for d, i in sorted(self.best, reverse=True):
            yield -i, -d
