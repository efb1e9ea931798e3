from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from labelroute.functions import labels as lb
from labelroute.operators import dynamic
from labelroute.operators import elastic as el
from labelroute.operators import select as sel
from labelroute.operators import universe as un
from labelroute.queries.selection import R1

GROUPS = {0: 3, 1: 3, 2: 1, 4: 1, 3: 1, 5: 3, 6: 2, 7: 3}


def test_sizes_of_the_running_example(spark):
    rows = [(b,) for b, n in GROUPS.items() for _ in range(n)]
    base = spark.createDataFrame(rows, "bits long")
    assert {r["bits"]: r["n"] for r in un.universe_all(base).collect()} == R1


def test_running_example_greedy_and_optimum():
    lat = sel.Lattice.of(R1)
    got = sel.select_for_factor(lat, 0.3, charge_top=True)
    assert got.sets == [0, 3, 6] and got.cost == 26
    assert sel.select_for_factor(lat, 0.3).cost == 9
    assert sel.select_optimal(lat, 0.3, charge_top=True) == ([0, 2], 24)
    assert Fraction(lat.size[7], lat.size[1]) == Fraction(3, 10) and lat.factor([0]) == Fraction(3, 17)


@pytest.mark.parametrize("c,cost", list(zip((0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8), (17, 20, 26, 30, 30, 47, 53, 61), strict=True)))
def test_greedy_costs(c, cost):
    assert sel.select_for_factor(sel.Lattice.of(R1), c, charge_top=True).cost == cost


@pytest.mark.parametrize(
    "tau,sets,cost,factor",
    [
        (17, {0}, 17, Fraction(3, 17)), (20, {0, 7}, 20, Fraction(4, 17)), (24, {0, 3}, 21, Fraction(5, 17)), (26, {0, 3, 6}, 26, Fraction(6, 17)),
        (30, {0, 2, 5}, 30, Fraction(1, 2)), (34, {0, 2, 5, 7}, 33, Fraction(9, 17)), (44, {0, 3, 2, 4}, 37, Fraction(10, 17)), (61, set(R1), 61, Fraction(1)),
    ],
)
def test_budget_bisection(tau, sets, cost, factor):
    got = sel.select_for_budget(sel.Lattice.of(R1), tau=tau, charge_top=True)
    assert (set(got.sets), got.cost, got.realised) == (sets, cost, factor)
    other = sel.select_for_budget(sel.Lattice.of(R1), tau=tau, charge_top=True, search="breakpoints")
    assert other.realised >= got.realised and other.cost <= tau


def test_budget_below_the_top_is_an_error():
    with pytest.raises(ValueError):
        sel.select_for_budget(sel.Lattice.of(R1), tau=16, charge_top=True)


@st.composite
def lattices(draw):
    groups = draw(st.dictionaries(st.integers(0, 31), st.integers(1, 9), min_size=1, max_size=12))
    size = {}
    for b, n in groups.items():
        s = b
        while True:
            size[s] = size.get(s, 0) + n
            if s == 0:
                break
            s = (s - 1) & b
    return sel.Lattice.of(size)


@settings(max_examples=60, deadline=None)
@given(lattices(), st.integers(1, 1000))
def test_lazy_equals_plain_and_covers(lat, m):
    lazy, _ = sel.greedy(lat, m, "lazy")
    plain, _ = sel.greedy(lat, m, "plain")
    assert lazy == plain
    chosen = [p.bits for p in lazy]
    assert lat.factor(chosen) >= Fraction(m, 1000)
    assert set(sel.prune(lat, chosen, m)) <= set(chosen)
    assert lat.cost(chosen, True) <= lat.cost(list(lat.size), True)


@settings(max_examples=30, deadline=None)
@given(lattices(), st.integers(1, 1000))
def test_greedy_never_beats_the_optimum(lat, m):
    if len(lat.size) <= 12:
        assert sel.select_for_factor(lat, m / 1000).cost >= sel.select_optimal(lat, m / 1000)[1]


def test_executor_rounds_equal_the_driver_loop(spark):
    u = spark.createDataFrame(list(R1.items()), "bits long, n long")
    for c in (0.3, 0.6):
        assert sel.select_for_factor(u, c, driver_limit=0).picks == sel.select_for_factor(u, c).picks


def test_blocks_are_bounded_by_edges_too(spark, monkeypatch):
    u = spark.createDataFrame(list(R1.items()), "bits long, n long")
    monkeypatch.setattr(sel._distributed, "__defaults__", (64, 2))
    for c in (0.3, 0.6):
        assert sel.select_for_factor(u, c, driver_limit=0).picks == sel.select_for_factor(u, c).picks


@pytest.mark.parametrize("search", ["bisect", "descending"])
def test_budget_on_executors_equals_the_driver(spark, search):
    u = spark.createDataFrame(list(R1.items()), "bits long, n long")
    for tau in (17, 26):
        near, far = (sel.select_for_budget(u, tau=tau, eps=0.1, charge_top=True, search=search, driver_limit=n) for n in (10**6, 0))
        assert (near.picks, near.cost, near.realised) == (far.picks, far.cost, far.realised)
    with pytest.raises(ValueError):
        sel.select_for_budget(u, tau=16, charge_top=True, driver_limit=0)


def test_extents_and_closures(spark):
    # B (2) occurs only with A (1)
    base = spark.createDataFrame([(3,)] * 3 + [(1,)] * 2, "bits long")
    u = un.closures(un.universe_all(base), lb.groups(base))
    assert {r["bits"]: r["closure"] for r in u.collect()} == {0: 1, 1: 1, 2: 3, 3: 3}
    by_label = {(r["src"], r["dst"]) for r in el.cover_edges(u).collect()}
    by_extent = {(r["src"], r["dst"]) for r in el.cover_edges(u, None, "extents").collect()}
    assert by_label < by_extent and (1, 2) in by_extent
    assert {r["bits"] for r in un.collapse_equal_extents(u).collect()} == {0, 2}


def test_canonical_sets(spark):
    rows = [(1, ["b", "a", "a", None]), (2, None), (3, [])]
    df = spark.createDataFrame(rows, "vec_id long, labels array<string>")
    assert lb.dictionary(df) == ["a", "b"]
    got = {r["vec_id"]: (r["k"], r["bits"]) for r in lb.encode(df.withColumn("k", lb.key_of("labels")), ["a", "b"]).collect()}
    assert got == {1: ("a|b", 3), 2: ("∅", 0), 3: ("∅", 0)}


def test_too_wide_sets_fail_loudly(spark):
    base = spark.createDataFrame([((1 << 20) - 1,)], "bits long")
    with pytest.raises(Exception, match="more than 16 labels"):
        un.universe_all(base).collect()


def test_empty_base(spark):
    base = spark.createDataFrame([], "bits long")
    assert un.universe_all(base).count() == 0
    assert sel.select_for_factor(un.universe_all(base), 0.2).picks == []


def test_updates_keep_the_bound():
    lat = sel.Lattice.of(R1)
    kept = dynamic.update_for_factor(lat, [0, 3, 6], 0.3)
    assert kept.sets == [0, 3, 6]
    more = dynamic.update_for_factor(lat, [0, 3, 6], 0.6)
    assert set(more.sets) >= {0, 3, 6} and more.realised >= Fraction(6, 10)
    fit = dynamic.update_for_budget(lat, list(R1), 30, 900, charge_top=True)
    assert fit.cost <= 30


def test_set_cover_reduction():
    lat, b = sel.set_cover_instance([1, 2, 3, 4], [[1, 2, 3], [2, 3, 4], [1, 4, 2]])
    n = lat.size[sel.TOP]
    c = Fraction(2 * b, n)
    assert Fraction(lat.size[("s", 0)], n) >= c > Fraction(lat.size[("e", 1)], n)
    assert Fraction(lat.size[("e", 1)], lat.size[("s", 0)]) > c and 2 * lat.size[("e", 1)] > lat.size[("s", 0)]


def test_manifest_versions(spark, tmp_path):
    m = dynamic.Manifest(spark, f"file://{tmp_path}/m")
    assert m.version() == 0 and m.publish([{"key": "∅"}], 0) == 1
    with pytest.raises(RuntimeError):
        m.publish([], 0)
    assert m.publish([{"key": "∅"}, {"key": "A"}], 1) == 2 and m.read(1) == [{"key": "∅"}]
