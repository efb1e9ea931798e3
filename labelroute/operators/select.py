"""Selection of index sets.

``select_for_factor``: least space such that every set has factor ``>= c``.
``select_for_budget``: largest minimum factor such that the space is ``<= tau``.

The cover relation is one Spark job; up to ``driver_limit`` edges the greedy
loop runs on the driver with a lazy heap, above it on the executors, a block of
candidates a round whose edges are bounded too.  Both make the same picks:
benefit (a fraction, compared by cross-multiplication) descending, then size,
then key ascending.  The budget search runs either loop.
"""

from __future__ import annotations

import heapq
from collections import Counter
from dataclasses import dataclass, field
from fractions import Fraction
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.sinks import saved as written
from .elastic import MILLI, cover_edges, serving

DRIVER_LIMIT = 5_000_000
#: Edges of one block of candidates that the distributed greedy brings to the driver.
BLOCK_EDGES = 1_000_000
TOP = 0


@dataclass
class Lattice:
    """Sizes, and for every pair of sets in relation who serves whom."""

    size: dict
    serves: dict  # src -> [dst, ...], src included
    weight: dict = field(default_factory=dict)

    @classmethod
    def collect(cls, universe: DataFrame, containment: str = "labels", driver_limit: int = DRIVER_LIMIT) -> Lattice | None:
        """The lattice on the driver, or None if it has more edges than allowed."""
        universe = written(universe)  # both sides of the relation and the sizes read it
        edges = cover_edges(universe, None, containment).select("src", "dst")
        table = edges.limit(driver_limit + 1).toArrow()
        if table.num_rows > driver_limit:
            return None
        src, dst = (table.column(i).to_numpy() for i in (0, 1))
        size = {r["bits"]: r["n"] for r in universe.select("bits", "n").collect()}
        order = np.lexsort((dst, src))
        src, dst = src[order], dst[order]
        starts = np.flatnonzero(np.concatenate(([True], src[1:] != src[:-1]))) if len(src) else np.empty(0, np.int64)
        serves: dict = {k: [] for k in size}
        for at, part in zip(starts.tolist(), np.split(dst, starts[1:]) if len(src) else (), strict=True):
            serves[int(src[at])] = part.tolist()
        return cls(size, serves)

    @classmethod
    def of(cls, size: dict) -> Lattice:
        """From sizes by bit sets, with label containment."""
        return cls(dict(size), {s: [d for d in size if d & s == s] for s in size})

    def covered_by(self, src, c_milli: int) -> list:
        n = self.size[src]
        return [d for d in self.serves[src] if self.size[d] * MILLI >= c_milli * n]

    def factor(self, chosen) -> Fraction:
        best: dict = {}
        for s in chosen:
            for d in self.serves[s]:
                best[d] = min(best.get(d, self.size[s]), self.size[s])
        if len(best) < len(self.size):
            return Fraction(0)
        return min((Fraction(self.size[d], n) for d, n in best.items()), default=Fraction(1))

    def cost(self, chosen, charge_top: bool) -> int:
        return sum(self.size[s] for s in chosen if charge_top or s != TOP)

    def breakpoints(self) -> list[Fraction]:
        return sorted({Fraction(self.size[d], self.size[s]) for s, ds in self.serves.items() for d in ds}, reverse=True)


@dataclass
class Pick:
    bits: int
    n: int
    round: int
    num: int
    den: int


@dataclass
class Selection:
    picks: list[Pick]
    cost: int
    realised: Fraction
    c_milli: int
    evaluations: int = 0
    lattice: Lattice | None = None

    @property
    def sets(self) -> list[int]:
        return [p.bits for p in self.picks]

    @property
    def realised_factor(self) -> float:
        return float(self.realised)

    def df(self, spark: SparkSession) -> DataFrame:
        rows = [(p.bits, p.n, p.round, p.num, p.den) for p in self.picks]
        return spark.createDataFrame(rows, "bits long, n long, round int, benefit_num long, benefit_den long")

    def stats(self) -> dict:
        a, s = len(self.lattice.size), len(self.picks)
        total = sum(self.lattice.size.values())
        return {"candidates": a, "selected": s, "candidate_rows": total, "selected_rows": sum(p.n for p in self.picks), "reduction": a / s}


def _milli(c: float) -> int:
    m = round(c * MILLI)
    if not 0 < m <= MILLI:
        raise ValueError("c must lie in (0, 1]")
    return m


def _gain(lat: Lattice, src, reach: list, covered: set) -> int:
    if lat.weight:
        return sum(lat.size[d] * lat.weight.get(d, 1) for d in reach if d not in covered)
    return sum(lat.size[d] for d in reach if d not in covered)


def greedy(lat: Lattice, c_milli: int, method: str = "lazy", start=(), trace: list | None = None) -> tuple[list[Pick], int]:
    """Picks in order, the top first; and how many benefits were evaluated.

    ``trace`` gets (round, set, num, den) of every benefit evaluated by
    ``plain``.
    """
    reach = {s: lat.covered_by(s, c_milli) for s in lat.size}
    covered: set = set()
    picks: list[Pick] = []
    count = 0

    def take(s, rnd, num):
        covered.update(reach[s])
        picks.append(Pick(s, lat.size[s], rnd, num, lat.size[s]))

    if not lat.size:
        return picks, count
    first = [s for s in (start or (TOP,)) if s in lat.size]
    if trace is not None and method == "plain" and not start:
        trace.extend((1, s, _gain(lat, s, reach[s], covered), lat.size[s]) for s in sorted(lat.size))
    for s in first:
        take(s, 0, _gain(lat, s, reach[s], covered))
    chosen = set(first)
    rnd = 0
    if method == "plain":
        while len(covered) < len(lat.size):
            rnd += 1
            best = None
            for s in lat.size:
                if s in chosen:
                    continue
                g = _gain(lat, s, reach[s], covered)
                count += 1
                if trace is not None:
                    trace.append((rnd + 1, s, g, lat.size[s]))
                rank = (-Fraction(g, lat.size[s]), lat.size[s], s)
                if best is None or rank < best[0]:
                    best = rank, s, g
            take(best[1], rnd, best[2])
            chosen.add(best[1])
        return picks, count
    heap = []
    for s in lat.size:
        if s not in chosen:
            heap.append((-Fraction(_gain(lat, s, reach[s], covered), lat.size[s]), lat.size[s], s, 0))
            count += 1
    heapq.heapify(heap)
    while len(covered) < len(lat.size):
        stale = heapq.heappop(heap)
        if stale[3] != rnd:  # benefits only fall as cover grows: a stale one is an upper bound
            s = stale[2]
            count += 1
            heapq.heappush(heap, (-Fraction(_gain(lat, s, reach[s], covered), lat.size[s]), lat.size[s], s, rnd))
            continue
        rnd += 1
        take(stale[2], rnd, int(-stale[0] * lat.size[stale[2]]))
    return picks, count


def select_for_factor(
    universe: DataFrame | Lattice,
    c: float = 0.2,
    method: str = "lazy",
    charge_top: bool = False,
    containment: str = "labels",
    start=(),
    driver_limit: int = DRIVER_LIMIT,
    trace: list | None = None,
) -> Selection:
    lat = universe if isinstance(universe, Lattice) else Lattice.collect(universe, containment, driver_limit)
    if lat is None:
        return _distributed(universe, _milli(c), charge_top, containment)
    picks, count = greedy(lat, _milli(c), method, start, trace)
    return _selection(lat, picks, _milli(c), charge_top, count)


def _selection(lat: Lattice, picks: list[Pick], c_milli: int, charge_top: bool, count: int = 0) -> Selection:
    chosen = [p.bits for p in picks]
    return Selection(picks, lat.cost(chosen, charge_top), lat.factor(chosen), c_milli, count, lat)


def _distributed(universe: DataFrame, c_milli: int, charge_top: bool, containment: str, block: int = 64, block_edges: int = BLOCK_EDGES) -> Selection:
    """Greedy with the cover relation on the executors.

    A round computes all current benefits (an upper bound for later rounds),
    brings the best candidates, at most ``block`` with ``block_edges`` edges, with
    their still uncovered sets' sizes to the driver and takes them in order
    while a fresh benefit precedes the next stale one, so picks equal those of
    the plain loop.  A first candidate with more edges is taken without them.
    What the picks cover is joined on the executors.
    """
    spark = universe.sparkSession
    universe = written(universe)
    edges = written(cover_edges(universe, c_milli, containment))
    top = universe.filter(F.col("bits") == TOP).first()
    if top is None:
        return Selection([], 0, Fraction(1), c_milli)
    picks = [Pick(TOP, top["n"], 0, 0, top["n"])]
    covered = edges.filter(F.col("src") == TOP).select("dst")
    picks[0].num = universe.join(covered.withColumnRenamed("dst", "bits"), "bits", "left_semi").agg(F.sum("n")).first()[0]
    live = written(edges.filter(F.col("src") != TOP).join(covered, "dst", "left_anti"))
    rnd = 0
    while True:
        gain = live.groupBy("src", "n_src").agg(F.sum("n_dst").alias("num"), F.count("*").alias("edges"))
        # the exact order of fractions is settled on the driver; doubles only choose the block
        best = gain.orderBy((F.col("num") / F.col("n_src")).desc(), "n_src", "src").limit(block + 1).collect()
        if not best:
            break
        many = {r["src"]: r["edges"] for r in best}
        ranked = sorted((-Fraction(r["num"], r["n_src"]), r["n_src"], r["src"]) for r in best)
        order, held = [], 0
        for o in ranked[:block]:
            held += many[o[2]]
            if order and held > block_edges:
                break
            order.append(o)
        stale_after = ranked[len(order)] if len(order) < len(ranked) else None
        names = [s for _, _, s in order]
        reach: dict = {s: [] for s in names}
        if held <= block_edges:
            for r in live.filter(F.col("src").isin(names)).select("src", "dst", "n_dst").collect():
                reach[r["src"]].append((r["dst"], r["n_dst"]))
        heap = [(*o, 0) for o in order]
        heapq.heapify(heap)
        done: set = set()
        chosen: list = []
        while heap:
            f, n, s, stamp = heap[0]
            if stamp != len(chosen):
                heapq.heappop(heap)
                g = sum(x for d, x in reach[s] if d not in done)
                if g:
                    heapq.heappush(heap, (-Fraction(g, n), n, s, len(chosen)))
                continue
            if chosen and stale_after is not None and (f, n, s) > stale_after:
                break
            heapq.heappop(heap)
            rnd += 1
            chosen.append(s)
            picks.append(Pick(s, n, rnd, int(-f * n), n))
            done.update(d for d, _ in reach[s])
        gone = live.filter(F.col("src").isin(chosen)).select("dst").distinct()
        live = written(live.join(gone, "dst", "left_anti"))
    taken = spark.createDataFrame([(p.bits, p.n) for p in picks], "bits long, n long")
    worst = serving(universe, taken, containment).agg(F.min(F.struct((F.col("n_q") / F.col("n_i")).alias("f"), "n_q", "n_i")).alias("w")).first()["w"]
    cost = sum(p.n for p in picks if charge_top or p.bits != TOP)
    return Selection(picks, cost, Fraction(worst["n_q"], worst["n_i"]), c_milli)


def select_for_budget(
    universe: DataFrame | Lattice,
    tau: int | None = None,
    space_ratio: float = 2.0,
    eps: float = 0.001,
    search: str = "bisect",
    charge_top: bool = False,
    containment: str = "labels",
    start=(),
    driver_limit: int = DRIVER_LIMIT,
) -> Selection:
    """Largest c whose greedy selection fits ``tau`` rows.

    ``bisect``: bisection on c in steps of ``eps``; ``descending``: from 1 down
    in the same steps, first fit wins; ``breakpoints``: only the ratios at which
    the cover relation changes, from the largest down.
    """
    lat = universe if isinstance(universe, Lattice) else Lattice.collect(universe, containment, driver_limit)
    if lat is None:
        return _budget_on_executors(universe, tau, space_ratio, eps, search, charge_top, containment)
    limit = tau if tau is not None else int(space_ratio * lat.size.get(TOP, 0))
    if charge_top and limit < lat.size.get(TOP, 0):
        raise ValueError("the budget is below the size of the top index")
    step = max(1, round(eps * MILLI))
    top = _selection(lat, [Pick(TOP, lat.size[TOP], 0, sum(lat.size.values()), lat.size[TOP])] if TOP in lat.size else [], step, charge_top)
    best = top
    runs = 0

    def attempt(c_milli: int) -> Selection | None:
        nonlocal runs
        runs += 1
        picks, n = greedy(lat, c_milli, "lazy", start)
        got = _selection(lat, picks, c_milli, charge_top, n)
        return got if got.cost <= limit else None

    if search == "bisect":
        low, high = 0, MILLI  # low fits (the top alone), high may not
        got = attempt(high)
        if got is not None:
            best, low = got, high
        while high - low > step:
            mid = (low + high) // 2
            got = attempt(mid)
            if got is None:
                high = mid
            else:
                low = mid
                if got.realised >= best.realised:
                    best = got
    elif search == "descending":
        for c in range(MILLI, 0, -step):
            got = attempt(c)
            if got is not None:
                best = got
                break
    elif search == "breakpoints":
        for f in lat.breakpoints():
            picks, n = _greedy_at(lat, f)
            got = _selection(lat, picks, int(f * MILLI), charge_top, n)
            if got.cost <= limit:
                best = got
                break
    else:
        raise ValueError(search)
    best.evaluations = runs or best.evaluations
    return best


def _budget_on_executors(universe: DataFrame, tau: int | None, space_ratio: float, eps: float, search: str, charge_top: bool, containment: str) -> Selection:
    """The same search where the cover relation is too large for the driver: each
    attempt is a distributed greedy.  ``breakpoints`` would need every ratio on
    the driver; in steps of ``eps`` it is ``descending``."""
    universe = written(universe)
    top = universe.filter(F.col("bits") == TOP).first()
    limit = tau if tau is not None else int(space_ratio * (top["n"] if top else 0))
    if charge_top and top and limit < top["n"]:
        raise ValueError("the budget is below the size of the top index")
    step, runs = max(1, round(eps * MILLI)), 0

    def attempt(c_milli: int) -> Selection | None:
        nonlocal runs
        runs += 1
        got = _distributed(universe, c_milli, charge_top, containment)
        return got if got.cost <= limit else None

    best = None
    if search == "bisect":
        low, high = 0, MILLI
        got = attempt(high)
        if got is not None:
            best, low = got, high
        while high - low > step:
            mid = (low + high) // 2
            got = attempt(mid)
            if got is None:
                high = mid
            else:
                low = mid
                if best is None or got.realised >= best.realised:
                    best = got
    elif search in ("descending", "breakpoints"):
        best = next((got for c in range(MILLI, 0, -step) if (got := attempt(c)) is not None), None)
    else:
        raise ValueError(search)
    if best is None:  # the top alone
        least, total = universe.agg(F.min("n"), F.sum("n")).first()
        picks = [Pick(TOP, top["n"], 0, total, top["n"])] if top else []
        best = Selection(picks, top["n"] if charge_top and top else 0, Fraction(least, top["n"]) if top else Fraction(1), step)
    best.evaluations = runs
    return best


def _greedy_at(lat: Lattice, f: Fraction) -> tuple[list[Pick], int]:
    """Greedy at an exact ratio, by scaling sizes so that thousandths suffice."""

    class Exact(Lattice):
        def covered_by(self, src, c_milli):
            n = self.size[src]
            return [d for d in self.serves[src] if self.size[d] * f.denominator >= f.numerator * n]

    return greedy(Exact(lat.size, lat.serves, lat.weight), MILLI)


def select_optimal(lat: Lattice, c: float, charge_top: bool = False, most: int = 20) -> tuple[list[int], int]:
    """Cheapest selection with the top that covers every set; tiny lattices only."""
    if len(lat.size) > most:
        raise ValueError(f"more than {most} candidates")
    m = _milli(c)
    reach = {s: set(lat.covered_by(s, m)) for s in lat.size}
    rest = sorted(s for s in lat.size if s != TOP)
    best = None
    for r in range(len(rest) + 1):
        for combo in combinations(rest, r):
            got = set(reach[TOP]).union(*(reach[s] for s in combo)) if combo else set(reach[TOP])
            if len(got) == len(lat.size):
                chosen = [TOP, *combo]
                rank = (lat.cost(chosen, charge_top), chosen)
                if best is None or rank < best:
                    best = rank
    return best[1], best[0]


def prune(lat: Lattice, chosen: list[int], c_milli: int) -> list[int]:
    """Drop indexes, largest first, while every covered set stays covered."""
    reach = {s: lat.covered_by(s, c_milli) for s in dict.fromkeys(chosen)}
    held = Counter(d for reached in reach.values() for d in reached)  # how many indexes serve a set
    gone = set()
    for s in sorted((x for x in reach if x != TOP), key=lambda x: (-lat.size[x], x)):
        if all(held[d] > 1 for d in reach[s]):
            gone.add(s)
            held.subtract(reach[s])
    return [s for s in chosen if s not in gone]


def select_all(universe: DataFrame) -> DataFrame:
    return universe.select("bits", "n")


def select_top(universe: DataFrame) -> DataFrame:
    return universe.filter(F.col("bits") == TOP).select("bits", "n")


def select_by(universe: DataFrame, tau: int, order: str = "frequent", weight: str | None = None) -> DataFrame:
    """Ablations: the top plus sets in a fixed order while the budget lasts.

    ``frequent``: by query weight (or size) descending, ``small``: by size
    ascending, ``random``: by the hash of the set.
    """
    rank = {
        "frequent": [F.col(weight or "n").desc(), F.col("bits")],
        "small": [F.col("n"), F.col("bits")],
        "random": [F.md5(F.col("bits").cast("string")), F.col("bits")],
    }[order]
    rest = universe.filter(F.col("bits") != TOP)
    used = rest.withColumn("used", F.sum("n").over(Window.orderBy(*rank).rowsBetween(Window.unboundedPreceding, 0)))
    return select_top(universe).unionByName(used.filter(F.col("used") <= tau).select("bits", "n"))


def benefits(universe: DataFrame, edges: DataFrame, covered: DataFrame | None = None) -> DataFrame:
    """(src, num, den) of every candidate given the covered sets."""
    live = edges if covered is None else edges.join(covered.select(F.col("bits").alias("dst")), "dst", "left_anti")
    g = live.groupBy("src").agg(F.sum("n_dst").alias("num"))
    return universe.join(g, universe["bits"] == g["src"], "left").select(
        "bits", F.coalesce("num", F.lit(0)).cast("long").alias("num"), F.col("n").alias("den")
    )


def set_cover_instance(elements: list[int], sets: list[list[int]]) -> tuple[Lattice, int]:
    """The hardness reduction: sizes b + 1 for elements, 2b for sets, a top of
    more than 4b; a set covers its elements only at a factor above 2b/N."""
    b = len(elements)
    big = 4 * b + 4
    size: dict = {TOP: big}
    serves: dict = {TOP: [TOP]}
    for e in elements:
        size[("e", e)] = b + 1
        serves[("e", e)] = [("e", e)]
    for i, members in enumerate(sets):
        size[("s", i)] = 2 * b
        serves[("s", i)] = [("s", i), *[("e", e) for e in members]]
    serves[TOP] += [k for k in size if k != TOP]
    return Lattice(size, serves), b


def cover_of_elements(lat: Lattice, c_milli: int) -> list:
    """Greedy picks among the sets of ``set_cover_instance`` until they cover all
    elements at the factor ``c``."""
    kind = lambda x: x[0] if isinstance(x, tuple) else None
    reach = {x: {y for y in lat.covered_by(x, c_milli) if kind(y) == "e"} for x in lat.size if kind(x) == "s"}
    want, got, picks = {x for x in lat.size if kind(x) == "e"}, set(), []
    while got != want:
        best = max(reach, key=lambda x: (Fraction(len(reach[x] - got), lat.size[x]), str(x)))
        if reach[best] <= got:
            raise ValueError("the sets do not cover every element")
        picks.append(best)
        got |= reach[best]
    return picks
