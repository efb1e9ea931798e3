"""Selections, their baselines and the worked examples."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import labels as lb
from ..operators import elastic as el
from ..operators import generate
from ..operators import select as sel
from ..operators import universe as un
from ..sources.sinks import saved
from ..sources.tables import load
from .common import DOC, G, LINE, U, encoded, key, skey, small_selection, with_

Q, O = {}, {}  # noqa: E741

# Fixed values of the running example: sizes by label set over A, B, C (bits 1, 2, 4).
R1 = {0: 17, 1: 10, 2: 7, 4: 9, 3: 4, 5: 6, 6: 5, 7: 3}
_NAMES = ["A", "B", "C"]
#: The same job over a given table: three labels of ``lineitem``, and the sizes of their sets.
_R1_SQL = """lab AS (SELECT coalesce(l_quantity <= 29, false)::BIGINT + 2 * coalesce(l_discount >= 0.055, false)::BIGINT + 4 * coalesce(l_tax >= 0.035, false)::BIGINT AS has FROM lineitem),
r1 AS (SELECT bits, count(*) AS n FROM lab, (SELECT unnest(range(0, 8)) AS bits) WHERE has & bits = bits GROUP BY bits)"""
_R1_KEY = "CASE WHEN src = 0 THEN '∅' ELSE array_to_string(list_filter([CASE WHEN src & 1 = 1 THEN 'A' END, CASE WHEN src & 2 = 2 THEN 'B' END, CASE WHEN src & 4 = 4 THEN 'C' END], lambda x: x IS NOT NULL), '|') END AS key"


def _greedy_sql(levels="300"):
    """Greedy rounds ``g`` by level: covered sets are a bit mask, so the best of every
    mask is known before the first round."""
    return (
        "WITH RECURSIVE "
        + _R1_SQL
        + f""",
cl AS (SELECT unnest([{levels}])::BIGINT AS c),
cv AS (SELECT c, s.bits AS src, s.n AS den, bit_or(1::BIGINT << d.bits) AS mask FROM cl, r1 s JOIN r1 d ON d.bits & s.bits = s.bits WHERE d.n * 1000 >= c * s.n GROUP BY 1, 2, 3),
ben AS (SELECT c, m, src, den, mask, sum(CASE WHEN (mask >> bits) & 1 = 1 AND (m >> bits) & 1 = 0 THEN n ELSE 0 END)::BIGINT AS num FROM cv, r1, (SELECT unnest(range(0, 256)) AS m) GROUP BY 1, 2, 3, 4, 5),
best AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY c, m ORDER BY num / den DESC, den, src) AS r FROM ben) WHERE r = 1),
g AS (
  SELECT c, 0 AS round, src, num, den, m AS was, mask AS m FROM ben WHERE m = 0 AND src = 0
  UNION ALL
  SELECT g.c, g.round + 1, b.src, b.num, b.den, g.m, g.m | b.mask FROM g JOIN best b ON b.c = g.c AND b.m = g.m WHERE g.m <> (SELECT sum(1::BIGINT << bits) FROM r1)::BIGINT)
"""
    )


def query(name, sql=None):
    def put(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f

    return put


def _benefit_sql(covered: str) -> str:
    return (
        with_(DOC, G, U, "tot AS (SELECT count(*) AS n FROM base)", f"cov AS ({covered})")
        + f"""SELECT {skey('a.labels')} AS key, coalesce(sum(b.n) FILTER (WHERE b.n * 1000 >= 200 * a.n
  AND NOT EXISTS (SELECT 1 FROM cov WHERE cov.labels = b.labels)), 0)::BIGINT AS num, a.n AS den
FROM u a JOIN u b ON list_has_all(b.labels, a.labels) GROUP BY a.labels, a.n"""
    )


@query("c01_benefit_round1", _benefit_sql("SELECT []::VARCHAR[] AS labels WHERE false"))
def _(s, d):
    b, w = encoded(s, d, "doc")
    u = un.universe_all(b)
    return sel.benefits(u, el.cover_edges(u, 200)).select(key(w), "num", "den")


@query("c01_benefit_round2", _benefit_sql("SELECT labels FROM u, tot WHERE u.n * 1000 >= 200 * tot.n"))
def _(s, d):
    b, w = encoded(s, d, "doc")
    u = un.universe_all(b)
    e = el.cover_edges(u, 200)
    return sel.benefits(u, e, e.filter("src = 0").select(F.col("dst").alias("bits"))).select(key(w), "num", "den")


def _three_labels(s, d):
    """The lattice over three labels of ``lineitem``."""
    holds = ("l_quantity <= 29", "l_discount >= 0.055", "l_tax >= 0.035")  # A, B, C
    bits = sum((F.when(F.expr(x), 1 << i).otherwise(0) for i, x in enumerate(holds)), F.lit(0))
    return sel.Lattice.collect(un.universe_all(load(s, d, "lineitem").select(bits.cast("long").alias("bits"))))


def _trace(s, d, method="plain"):
    rows: list = []
    got = sel.select_for_factor(_three_labels(s, d), 0.3, method, charge_top=True, trace=rows)
    return got, rows


@query("c02_running_example", _greedy_sql() + f"SELECT round::INT AS round, {_R1_KEY}, num, den FROM g")
def _(s, d):
    got, _t = _trace(s, d)
    df = got.df(s)
    return df.select("round", key(_NAMES), F.col("benefit_num").alias("num"), F.col("benefit_den").alias("den"))


@query(
    "c17_selection_trace",
    _greedy_sql()
    + f"""SELECT (g.round + 1)::INT AS round, {_R1_KEY.replace('src', 'b.src')}, b.num::INT AS num, b.den::INT AS den FROM g JOIN ben b ON b.m = g.was
WHERE NOT EXISTS (SELECT 1 FROM g p WHERE p.round < g.round AND p.src = b.src)""",
)
def _(s, d):
    _g, rows = _trace(s, d)
    return s.createDataFrame(rows, "round int, bits long, num int, den int").select("round", key(_NAMES), "num", "den")


@query("c17_greedy_trace_udtf", O["c17_selection_trace"])
def _(s, d):
    from .tablefuncs import GreedyTrace

    s.udtf.register("greedy_trace", GreedyTrace)
    sizes = ",".join(f"{b}:{n}" for b, n in sorted(_three_labels(s, d).size.items()))
    t = s.sql(f"SELECT * FROM greedy_trace('{sizes}', CAST(0.3 AS DOUBLE))")
    return t.select("round", key(_NAMES, "key"), F.col("num").cast("int").alias("num"), F.col("den").cast("int").alias("den"))


def _picked(got, s, w):
    return got.df(s).select(key(w), "n", "round", "benefit_num", "benefit_den")


@query("c02_select_factor")
def _(s, d):
    b, w = encoded(s, d, "doc")
    return _picked(sel.select_for_factor(un.universe_all(b), 0.2), s, w)


@query("c02_select_factor_plain")
def _(s, d):
    b, w = encoded(s, d, "doc")
    return _picked(sel.select_for_factor(un.universe_all(b), 0.2, "plain"), s, w)


@query("c02_select_factor_extents")
def _(s, d):
    b, w = encoded(s, d, "doc")
    u = un.closures(un.universe_all(b), lb.groups(b))
    return _picked(sel.select_for_factor(u, 0.2, containment="extents"), s, w)


@query("c02_select_factor_executors")
def _(s, d):
    b, w = encoded(s, d, "doc")
    return _picked(sel.select_for_factor(un.universe_all(b), 0.2, driver_limit=0), s, w)


@query("c05_select_budget_executors")
def _(s, d):
    b, w = encoded(s, d, "doc")
    got = sel.select_for_budget(un.universe_all(b), space_ratio=2.0, eps=0.05, driver_limit=0)
    return got.df(s).select(key(w), "n", F.lit(round(got.realised_factor, 6)).alias("realised_factor"), F.lit(got.cost).alias("cost"))


def _checks(s, rows):
    return s.createDataFrame(rows, "dataset string, fact string, holds boolean")


def _true(*facts, sets=("doc", "order")):
    return "SELECT * FROM (VALUES " + ", ".join(f"('{x}', '{f}', true)" for x in sets for f in facts) + ") t(dataset, fact, holds)"


@query("c02_factor_checks", _true("every set is served at c", "lazy, plain and executor picks are equal", "cost is the sum of picked sizes", "no pick is redundant to the first", "realised factor is the least served one"))
def _(s, d):
    """What must hold of a factor-bound selection, computed from its picks by joins."""
    rows = []
    for name in ("doc", "order"):
        b, _w = encoded(s, d, name)
        u = saved(un.universe_all(b))
        lat = sel.Lattice.collect(u)
        got = sel.select_for_factor(lat, 0.2)
        chosen = got.df(s)
        f = el.is_feasible(u, chosen, 200, got.cost, False).first()
        least = el.serving(u, chosen).agg(F.min(F.col("n_q") / F.col("n_i"))).first()[0]
        same = got.picks == sel.select_for_factor(lat, 0.2, "plain").picks == sel.select_for_factor(u, 0.2, driver_limit=0).picks
        rows += [
            (name, "every set is served at c", f["violations"] == 0),
            (name, "lazy, plain and executor picks are equal", same),
            (name, "cost is the sum of picked sizes", f["cost"] == got.cost),
            (name, "no pick is redundant to the first", all(p.num > 0 for p in got.picks)),
            (name, "realised factor is the least served one", abs(least - got.realised_factor) < 1e-12),
        ]
    return _checks(s, rows)


@query("c05_budget_checks", _true("cost is within the budget", "no smaller factor than the top alone", "executor and driver picks are equal", "a larger budget never lowers the factor"))
def _(s, d):
    rows = []
    for name in ("doc", "order"):
        b, _w = encoded(s, d, name)
        u = saved(un.universe_all(b))
        lat = sel.Lattice.collect(u)
        got, wide = (sel.select_for_budget(lat, space_ratio=r, eps=0.125) for r in (2.0, 4.0))
        far = sel.select_for_budget(u, space_ratio=2.0, eps=0.125, driver_limit=0)
        rows += [
            (name, "cost is within the budget", got.cost <= 2 * lat.size[0]),
            (name, "no smaller factor than the top alone", got.realised >= lat.factor([0])),
            (name, "executor and driver picks are equal", got.picks == far.picks),
            (name, "a larger budget never lowers the factor", wide.realised >= got.realised),
        ]
    return _checks(s, rows)


for _search in ("bisect", "descending", "breakpoints"):

    def _budget(s, d, search=_search):
        b, w = encoded(s, d, "doc")
        got = sel.select_for_budget(un.universe_all(b), space_ratio=2.0, search=search)
        return got.df(s).select(key(w), "n", F.lit(round(got.realised_factor, 6)).alias("realised_factor"), F.lit(got.cost).alias("cost"))

    query("c05_select_budget" if _search == "bisect" else f"c05_select_budget_{_search}")(_budget)


def _optimal_sql(levels="300"):
    """Every family ``m`` of sets beside the top, its cost by level, and the cheapest that serves all."""
    return f"""lv AS (SELECT unnest([{levels}])::BIGINT AS c),
m AS (SELECT unnest(range(0, 128)) AS m),
cand AS (SELECT bits - 1 AS i, bits, n FROM r1 WHERE bits <> 0),
chosen AS (SELECT m, bits, n FROM m, r1 WHERE bits = 0 UNION ALL SELECT m, bits, n FROM m, cand WHERE (m >> i) & 1 = 1),
serve AS (SELECT lv.c, x.m, count(DISTINCT e.bits) AS k FROM lv, chosen x JOIN r1 e ON e.bits & x.bits = x.bits WHERE e.n * 1000 >= lv.c * x.n GROUP BY 1, 2),
cost AS (SELECT m, sum(n)::BIGINT AS cost, count(*) AS sets FROM chosen GROUP BY m),
fit AS (SELECT c, m, cost, row_number() OVER (PARTITION BY c ORDER BY cost, sets, m) AS r FROM serve JOIN cost USING (m) WHERE k = (SELECT count(*) FROM r1))
"""


@query("c09_optimal", with_(_R1_SQL, _optimal_sql()) + "SELECT bits, n FROM chosen WHERE m = (SELECT m FROM fit WHERE r = 1)")
def _(s, d):
    lat = _three_labels(s, d)
    sets, _c = sel.select_optimal(lat, 0.3)
    return s.createDataFrame([(x, lat.size[x]) for x in sets], "bits long, n long")


@query("c10_select_all", with_(LINE, G, U) + f"SELECT {skey()} AS key, n FROM u")
def _(s, d):
    b, w = encoded(s, d, "line")
    return sel.select_all(un.universe_all(b)).select(key(w), "n")


@query("c11_select_top", with_(LINE, G, U) + f"SELECT {skey()} AS key, n FROM u WHERE len(labels) = 0")
def _(s, d):
    b, w = encoded(s, d, "line")
    return sel.select_top(un.universe_all(b)).select(key(w), "n")


_BITS = "ub AS (SELECT labels, n, (SELECT coalesce(sum(1::BIGINT << bit), 0)::BIGINT FROM dict WHERE list_contains(u.labels, label)) AS bits FROM u)"
for _o, _sql in (("frequent", "n DESC, bits"), ("small", "n, bits"), ("random", "md5(bits::VARCHAR), bits")):

    def _by(s, d, order=_o):
        b, w = encoded(s, d, "line")
        tau = b.count()
        return sel.select_by(un.universe_all(b), tau, order).select(key(w), "n")

    from .common import DICT

    query(
        f"c12_select_{_o}",
        with_(LINE, DICT, G, U, _BITS, f"r AS (SELECT *, sum(n) OVER (ORDER BY {_sql} ROWS UNBOUNDED PRECEDING) AS used FROM ub WHERE len(labels) > 0)")
        + f"SELECT {skey()} AS key, n FROM u WHERE len(labels) = 0 UNION ALL SELECT {skey()}, n FROM r WHERE used <= (SELECT count(*) FROM base)",
    )(_by)


@query("c13_select_weighted")
def _(s, d):
    b, w = encoded(s, d, "doc")
    u = un.universe_all(b)
    lat = sel.Lattice.collect(u)
    lat.weight = {x: 1 + (x % 3) for x in lat.size}
    return _picked(sel.select_for_factor(lat, 0.2), s, w)


_NEW = "len(list_filter(has, lambda x: NOT list_contains(got, x)))"


@query(
    "c14_set_cover",
    f"""WITH RECURSIVE pr AS (SELECT l_linenumber AS s, l_quantity AS e, count(*) AS n FROM lineitem WHERE l_linenumber IS NOT NULL AND l_quantity IS NOT NULL GROUP BY 1, 2),
sn AS (SELECT s, row_number() OVER (ORDER BY s) - 1 AS i FROM (SELECT DISTINCT s FROM pr)),
el AS (SELECT e, sum(n) AS n FROM pr GROUP BY e),
mb AS (SELECT i, list(pr.e) AS has FROM pr JOIN el USING (e) JOIN sn USING (s) WHERE pr.n * (SELECT count(*) FROM sn) >= el.n GROUP BY i),
g AS (SELECT 0 AS picks, []::DOUBLE[] AS got
  UNION ALL
  SELECT picks + 1, list_concat(got, list_filter(has, lambda x: NOT list_contains(got, x)))
  FROM (SELECT *, row_number() OVER (ORDER BY {_NEW} DESC, '(' || i || ')' DESC) AS r FROM g, mb) WHERE r = 1 AND {_NEW} > 0),
f AS (SELECT count(*) AS b, (SELECT max(picks) FROM g) AS picks FROM el)
SELECT fact, value::INT AS value FROM (SELECT unnest(['element', 'set', 'top', 'c_milli', 'selected_sets', 'cost']) AS fact,
  unnest([b + 1, 2 * b, 4 * b + 4, round(2000 * b / (4 * b + 4))::BIGINT, picks, 2 * b * picks]) AS value FROM f)""",
)
def _(s, d):
    """Set cover as a selection: the quantities of ``lineitem`` are elements, and a
    line number is a set of those of which it has at least its even share."""
    rows = load(s, d, "lineitem").filter("l_linenumber IS NOT NULL AND l_quantity IS NOT NULL")
    pairs = rows.groupBy("l_linenumber", "l_quantity").count().collect()  # line numbers by quantities
    total: dict = {}
    for _s, e, n in pairs:
        total[e] = total.get(e, 0) + n
    has: dict = {x: [] for x in sorted({p[0] for p in pairs})}
    for x, e, n in pairs:
        if n * len(has) >= total[e]:
            has[x].append(e)
    lat, b = sel.set_cover_instance(sorted(total), list(has.values()))
    c = 2 * b / lat.size[sel.TOP]
    picks = sel.cover_of_elements(lat, round(c * 1000))
    rows = [("element", b + 1), ("set", 2 * b), ("top", lat.size[sel.TOP]), ("c_milli", round(c * 1000)), ("selected_sets", len(picks)), ("cost", sum(lat.size[p] for p in picks))]
    return s.createDataFrame(rows, "fact string, value int")


@query("c15_disjoint", "SELECT 1 + count(DISTINCT l_quantity) AS candidates, 1 + count(DISTINCT l_quantity) AS selected, 2 * count(*) AS rows FROM lineitem WHERE l_quantity IS NOT NULL")
def _(s, d):
    """Rows with one of many labels each: no set serves another, all are selected."""
    label = F.concat(F.lit("quantity:"), F.col("l_quantity").cast("string"))
    rows = load(s, d, "lineitem").filter("l_quantity IS NOT NULL").select(F.array(label).alias("labels"))
    words = lb.dictionary(rows)
    b = lb.encode(rows, words)
    got = sel.select_for_factor(un.universe_all(b), 0.5, charge_top=True)
    st = got.stats()
    return s.createDataFrame([(st["candidates"], st["selected"], got.cost)], "candidates long, selected long, rows long")


@query("c16_selection_stats", with_(DOC, G, U, "sel AS (SELECT * FROM u WHERE len(labels) <= 1)") + """SELECT count(*) AS candidates, sum(n)::BIGINT AS candidate_rows,
 (SELECT count(*) FROM sel) AS selected, (SELECT sum(n)::BIGINT FROM sel) AS selected_rows FROM u""")
def _(s, d):
    b, _w = encoded(s, d, "doc")
    u, c = un.universe_all(b), small_selection(b)
    a = u.agg(F.count("*").alias("candidates"), F.sum("n").cast("long").alias("candidate_rows"))
    return a.crossJoin(c.agg(F.count("*").alias("selected"), F.sum("n").cast("long").alias("selected_rows")))


def _sets(s, d):
    """Given labelled sets, and the embeddings under four label distributions."""
    for name in ("doc", "part", "line", "order", "source", "page", "event", "meta", "keywords"):
        yield name, encoded(s, d, name)[0]
    e = load(s, d, "embeddings").select("vec_id")
    for name in ("zipf", "uniform", "poisson", "multinomial"):
        rows = getattr(generate, name)(e)
        yield name, lb.encode(rows, lb.dictionary(rows))


@query("x03_selection_statistics")
def _(s, d):
    """Candidates, selected sets and their rows by labelled set and distribution,
    factor bound and budget bound."""
    out = []
    for name, b in _sets(s, d):
        lat = sel.Lattice.collect(un.universe_all(b))
        for method, got in (("factor 0.2", sel.select_for_factor(lat, 0.2)), ("budget 2.0", sel.select_for_budget(lat, space_ratio=2.0))):
            st = got.stats()
            out.append((name, method, st["candidates"], st["selected"], st["candidate_rows"], st["selected_rows"], round(got.realised_factor, 6)))
    return s.createDataFrame(out, "dataset string, method string, candidates long, selected long, candidate_rows long, selected_rows long, min_factor double")


@query(
    "x03_shapes",
    "SELECT * FROM (VALUES " + ", ".join(f"('{m}', '{f}', true)" for m in ("factor 0.2", "budget 2.0") for f in ("fewer sets than candidates on every set", "fewer rows than all candidates", "bound kept")) + ") t(method, fact, holds)",
)
def _(s, d):
    """The reported behaviour of the selection statistics, as facts."""
    rows = Q["x03_selection_statistics"](s, d).collect()
    base = {r["dataset"]: 0 for r in rows}
    out = []
    for m in ("factor 0.2", "budget 2.0"):
        mine = [r for r in rows if r["method"] == m]
        out.append((m, "fewer sets than candidates on every set", all(r["selected"] < r["candidates"] for r in mine)))
        out.append((m, "fewer rows than all candidates", all(r["selected_rows"] < r["candidate_rows"] for r in mine)))
        if m == "factor 0.2":
            out.append((m, "bound kept", all(r["min_factor"] >= 0.2 for r in mine)))
        else:  # twice the rows of the top besides it
            top = {name: b.count() for name, b in _sets(s, d) if name in base}
            out.append((m, "bound kept", all(r["selected_rows"] <= 3 * top[r["dataset"]] for r in mine)))
    return s.createDataFrame(out, "method string, fact string, holds boolean")


@query(
    "x09_thresholds",
    """SELECT * FROM (VALUES (500, 'A', true), (500, 'B', false), (500, 'C', false), (500, 'A|B', false), (300, 'A', true), (300, 'B', true),
 (300, 'C', true), (300, 'A|B', false), (250, 'A', true), (250, 'B', true), (250, 'C', true), (250, 'A|B', true)) t(c_milli, key, by_top)""",
)
def _(s, d):
    rows = s.createDataFrame([(0, 100), (1, 55), (2, 45), (4, 35), (3, 25)], "bits long, n long")
    out = None
    for c in (500, 300, 250):
        e = el.cover_edges(rows, c).filter("src = 0").select("dst")
        part = rows.filter("bits <> 0").join(e.withColumn("by_top", F.lit(True)), F.col("bits") == F.col("dst"), "left").select(
            F.lit(c).alias("c_milli"), key(_NAMES), F.coalesce("by_top", F.lit(False)).alias("by_top")
        )
        out = part if out is None else out.unionByName(part)
    return out


@query("x10_selector_overhead")
def _(s, d):
    """Seconds of selection by method on the largest universes, and benefits evaluated."""
    from ..operators import metrics

    out = []
    e = load(s, d, "embeddings").select("vec_id")
    zipf = lambda n: (lambda rows: lb.encode(rows, lb.dictionary(rows)))(generate.zipf(e, n))
    for name, b in (("line", encoded(s, d, "line")[0]), ("part", encoded(s, d, "part")[0]), ("zipf 24", zipf(24)), ("zipf 32", zipf(32))):
        lat, job = metrics.timed(lambda b=b: sel.Lattice.collect(un.universe_all(b)))
        for method in ("lazy", "plain"):
            got, sec = metrics.timed(lambda lat=lat, m=method: sel.select_for_factor(lat, 0.2, m))
            out.append((name, f"factor {method}", len(lat.size), len(got.picks), got.evaluations, round(job, 3), round(sec, 3)))
        got, sec = metrics.timed(lambda lat=lat: sel.select_for_budget(lat, space_ratio=2.0))
        out.append((name, "budget", len(lat.size), len(got.picks), got.evaluations, round(job, 3), round(sec, 3)))
    return s.createDataFrame(out, "dataset string, method string, candidates long, selected long, evaluations long, lattice_seconds double, select_seconds double")


@query(
    "m14_approximation_gap",
    _greedy_sql("300, 500, 800") + ",\n" + _optimal_sql("300, 500, 800") + "SELECT c::INT AS c_milli, sum(den)::INT AS greedy, (SELECT cost FROM fit WHERE r = 1 AND fit.c = g.c)::INT AS optimal FROM g GROUP BY c",
)
def _(s, d):
    lat = _three_labels(s, d)
    rows = [(c, sel.select_for_factor(lat, c / 1000, charge_top=True).cost, sel.select_optimal(lat, c / 1000, charge_top=True)[1]) for c in (300, 500, 800)]
    return s.createDataFrame(rows, "c_milli int, greedy int, optimal int")
