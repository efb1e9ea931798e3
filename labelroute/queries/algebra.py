"""Label algebra, universes and elastic factors."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import labels as lb
from ..operators import elastic as el
from ..operators import universe as un
from ..sources.tables import load
from .common import D2, DICT, DOC, G, LINE, ORDER, PART, SUB, U, encoded, key, skey, small_selection, with_

Q, O = {}, {}  # noqa: E741


def query(name, sql=None):
    def put(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f

    return put


@query("a01_canonical_labels", with_(DOC) + f"SELECT vec_id AS doc_id, {skey()} AS labels FROM base")
def _(s, d):
    b, _w = encoded(s, d, "doc")
    return b.select(F.col("vec_id").alias("doc_id"), lb.key_of("labels").alias("labels"))


@query(
    "a02_label_bits",
    with_(DOC, DICT) + "SELECT vec_id AS doc_id, coalesce(sum(1::BIGINT << bit), 0)::BIGINT AS bits FROM "
    "(SELECT vec_id, unnest(labels) AS label FROM base) JOIN dict USING (label) GROUP BY vec_id",
)
def _(s, d):
    b, _w = encoded(s, d, "doc")
    return b.select(F.col("vec_id").alias("doc_id"), "bits")


def _pairs(test):
    def run(s, d):
        b, w = encoded(s, d, "doc")
        u = un.universe_all(b)
        small = u.filter(F.bit_count("bits") <= 2).select(F.col("bits").alias("q"))
        g = lb.groups(b)
        return (
            small.join(g, test("bits", "q"))
            .groupBy("q")
            .agg(F.count("*").alias("sets"), F.sum("n").cast("long").alias("n"))
            .select(key(w, "q"), "sets", "n")
        )

    return run


_SMALL = "sm AS (SELECT labels AS q FROM u WHERE len(labels) <= 2)"
for _name, _test, _sql in (
    ("a03_contains_all", lb.contains_all, "list_has_all(labels, q)"),
    ("a04_overlaps", lb.overlaps, "list_has_any(labels, q)"),
    ("a05_same_set", lb.same_set, "labels = q"),
):
    query(_name, with_(DOC, G, U, _SMALL) + f"SELECT {skey('q')} AS key, count(*) AS sets, sum(n)::BIGINT AS n FROM sm JOIN g ON {_sql} GROUP BY q")(
        _pairs(_test)
    )


@query("a06_subsets_udtf", with_(PART, G, U) + f"SELECT {skey()} AS key, n FROM u")
def _(s, d):
    from .tablefuncs import LabelSubsets

    b, _w = encoded(s, d, "part")
    s.udtf.register("label_subsets", LabelSubsets)
    g = b.groupBy("labels").agg(F.count("*").alias("n"))
    g.createOrReplaceTempView("_part_groups")
    return s.sql("SELECT t.key, sum(n) AS n FROM _part_groups, LATERAL label_subsets(labels) t GROUP BY t.key")


@query(
    "a07_minimal_supersets",
    with_(DOC, G)
    + f"""SELECT {skey('a.labels')} AS key, {skey('b.labels')} AS superset FROM g a JOIN g b
ON list_has_all(b.labels, a.labels) AND a.labels <> b.labels
WHERE NOT EXISTS (SELECT 1 FROM g c WHERE c.labels <> a.labels AND c.labels <> b.labels
  AND list_has_all(c.labels, a.labels) AND list_has_all(b.labels, c.labels))""",
)
def _(s, d):
    b, w = encoded(s, d, "doc")
    return lb.minimal_supersets(lb.groups(b)).select(key(w), key(w, "superset", "superset"))


@query("a08_label_groups", with_(LINE, G) + f"SELECT {skey()} AS key, n FROM g")
def _(s, d):
    b, w = encoded(s, d, "line")
    return lb.groups(b).select(key(w), "n")


@query(
    "a09_matching_rows",
    with_(DOC) + "SELECT vec_id FROM base JOIN embeddings USING (vec_id) WHERE list_has_all(labels, ['lang:en', 'len:m'])",
)
def _(s, d):
    b, w = encoded(s, d, "doc_vec")
    q = sum(1 << w.index(x) for x in ("lang:en", "len:m"))
    return b.filter(lb.contains_all("bits", F.lit(q).cast("long"))).select("vec_id")


_IMPLIED = LINE.replace("['flag:'", "list_filter(['flag:'").replace(
    "round(l_discount * 100)::INT])", "round(l_discount * 100)::INT, CASE WHEN l_returnflag = 'R' THEN 'returned' END], lambda x: x IS NOT NULL))"
)


def _implied(s, d):
    b, _w = encoded(s, d, "line")
    b = b.withColumn("labels", F.when(F.array_contains("labels", "flag:R"), F.array_append("labels", F.lit("returned"))).otherwise(F.col("labels")))
    words = lb.dictionary(b.select("labels"))
    return lb.encode(b.drop("bits"), words), words


_CLOSURE = f"""cl AS (SELECT s AS labels, array_agg(DISTINCT labels) AS sets, sum(n)::BIGINT AS n
  FROM (SELECT labels, n, unnest({SUB.format('labels')}) AS s FROM g) GROUP BY s),
cx AS (SELECT labels, n, list_filter(sets[1], lambda x: len(list_filter(sets, lambda t: list_contains(t, x))) = len(sets)) AS closure FROM cl)"""


@query("a10_closure", with_(_IMPLIED, G, _CLOSURE) + f"SELECT {skey()} AS key, {skey('list_sort(closure)')} AS closure FROM cx")
def _(s, d):
    b, w = _implied(s, d)
    return un.closures(un.universe_all(b), lb.groups(b)).select(key(w), key(w, "closure", "closure"))


_SEL = with_(ORDER, G, U)


@query("a11_selectivity", _SEL + f"SELECT {skey()} AS key, n AS match_count, round(n / (SELECT count(*) FROM base), 6) AS selectivity FROM u WHERE len(labels) <= 2")
def _(s, d):
    b, w = encoded(s, d, "order")
    q = un.universe_all(b).filter(F.bit_count("bits") <= 2)
    return lb.match_counts(b, q).select(key(w), F.col("match_count").cast("long").alias("match_count"), F.round("selectivity", 6).alias("selectivity"))


@query("a11_average_selectivity", _SEL + "SELECT round(avg(n / (SELECT count(*) FROM base)), 6) AS average_selectivity FROM u WHERE len(labels) <= 2")
def _(s, d):
    b, _w = encoded(s, d, "order")
    q = un.universe_all(b).filter(F.bit_count("bits") <= 2)
    return lb.match_counts(b, q).agg(F.round(F.avg("selectivity"), 6).alias("average_selectivity"))


for _n, _cte, _set in (("line", LINE, "line"), ("documents", DOC, "doc"), ("part", PART, "part")):

    def _all(s, d, which=_set):
        b, w = encoded(s, d, which)
        return un.universe_all(b).select(key(w), "n")

    query(f"b01_universe_all_{_n}", with_(_cte, G, U) + f"SELECT {skey()} AS key, n FROM u")(_all)


def _event_sets(s, d, words):
    """A workload from the change feed: year and discount asked for in turn."""
    e = load(s, d, "events").select(
        F.array(F.concat(F.lit("year:"), (F.lit(1992) + F.pmod("user_id", F.lit(7))).cast("string")), F.concat(F.lit("disc:"), F.pmod("event_id", F.lit(11)).cast("string"))).alias("labels")
    )
    return e.withColumn("bits", lb.bits_of("labels", words)).filter("bits >= 0")


@query(
    "b02_universe_workload",
    with_(
        LINE, G, U,
        "wl AS (SELECT DISTINCT list_sort(['year:' || (1992 + user_id % 7), 'disc:' || (event_id % 11)]) AS labels FROM events UNION SELECT []::VARCHAR[])",
    )
    + f"SELECT {skey()} AS key, n FROM u JOIN wl USING (labels)",
)
def _(s, d):
    b, w = encoded(s, d, "line")
    return un.universe_workload(b, _event_sets(s, d, w)).select(key(w), "n")


@query(
    "b02_universe_workload_nested",
    O["b02_universe_workload"],
)
def _(s, d):
    b, w = encoded(s, d, "line")
    return un.universe_workload(b, _event_sets(s, d, w), how="rarest").select(key(w), "n")


@query("b03_universe_min_rows", with_(LINE, G, U) + f"SELECT {skey()} AS key, n FROM u WHERE n >= 4000 OR len(labels) = 0")
def _(s, d):
    b, w = encoded(s, d, "line")
    return un.universe_all(b, min_rows=4000).select(key(w), "n")


@query(
    "b04_universe_sampled",
    with_(ORDER.replace("base AS", "full_ AS", 1), "base AS (SELECT * FROM full_ WHERE ('0x' || substr(md5(vec_id::VARCHAR), 1, 8))::BIGINT % 4 = 0)", G, U)
    + f"SELECT {skey()} AS key, n * 4 AS n, round(sqrt(n * 0.75 / 0.0625), 6) AS std_error FROM u",
)
def _(s, d):
    b, w = encoded(s, d, "order")
    return un.universe_sampled(b, 4).select(key(w), "n", F.round("std_error", 6).alias("std_error"))


@query("b05_universe_sketch")
def _(s, d):
    b, w = encoded(s, d, "order")
    u = un.universe_all(b).filter(F.bit_count("bits") <= 2)
    got = un.universe_sketch(b, u, w).withColumnRenamed("n", "estimate")
    return u.join(got, "bits").select(key(w), "n", "estimate")


@query("b06_universe_independent")
def _(s, d):
    b, w = encoded(s, d, "line")
    u = un.universe_all(b).filter(F.bit_count("bits").between(1, 2))
    return un.universe_independent(b, u, w).select(key(w), F.round("n", 2).alias("n"))


O["b06_universe_independent"] = (
    with_(LINE, G, U, "f AS (SELECT label, count(*) / (SELECT count(*) FROM base) AS p FROM (SELECT unnest(labels) AS label FROM base) GROUP BY label)")
    + f"""SELECT key, round((SELECT count(*) FROM base) * product(p), 2) AS n FROM
 (SELECT {skey('labels')} AS key, unnest(labels) AS label FROM u WHERE len(labels) BETWEEN 1 AND 2) JOIN f USING (label) GROUP BY key"""
)

_S = "sel AS (SELECT * FROM u WHERE len(labels) <= 1)"
_F = "fx AS (SELECT q.labels, min(i.n) AS n_i, any_value(q.n) AS n_q FROM u q JOIN sel i ON list_has_all(q.labels, i.labels) GROUP BY q.labels)"


@query(
    "b07_pair_factor",
    with_(DOC, G, U, _S) + f"SELECT {skey('q.labels')} AS key, {skey('i.labels')} AS index_key, round(q.n / i.n, 6) AS factor FROM u q JOIN sel i ON list_has_all(q.labels, i.labels)",
)
def _(s, d):
    b, w = encoded(s, d, "doc")
    u = un.universe_all(b)
    e = el.cover_edges(u).join(small_selection(b).select(F.col("bits").alias("src")), "src", "left_semi")
    return e.select(key(w, "dst"), key(w, "src", "index_key"), F.round(el.pair_factor(F.col("n_dst"), F.col("n_src")), 6).alias("factor"))


@query("b08_elastic_factor", with_(DOC, G, U, _S, _F) + f"SELECT {skey()} AS key, round(n_q / n_i, 6) AS factor FROM fx")
def _(s, d):
    b, w = encoded(s, d, "doc")
    return el.elastic_factor(un.universe_all(b), small_selection(b)).select(key(w), F.round("factor", 6).alias("factor"))


@query(
    "b09_factor_summary",
    with_(DOC, G, U, _S, _F) + "SELECT round(min(n_q / n_i), 6) AS min_factor, round(avg(n_q / n_i), 6) AS mean_factor, count(*) AS sets FROM fx",
)
def _(s, d):
    b, _w = encoded(s, d, "doc")
    r = el.factor_summary(un.universe_all(b), small_selection(b))
    return r.select(F.round("min_factor", 6).alias("min_factor"), F.round("mean_factor", 6).alias("mean_factor"), "sets")


def _edges_sql(c):
    return (
        with_(DOC, G, U) + f"SELECT {skey('a.labels')} AS src, {skey('b.labels')} AS dst FROM u a JOIN u b "
        f"ON list_has_all(b.labels, a.labels) AND b.n * 1000 >= {c} * a.n"
    )


for _c in (200, 500):

    def _edges(s, d, c=_c):
        b, w = encoded(s, d, "doc")
        return el.cover_edges(un.universe_all(b), c).select(key(w, "src", "src"), key(w, "dst", "dst"))

    query(f"b10_cover_edges_{_c}", _edges_sql(_c))(_edges)


@query(
    "b10_cover_edges_extents",
    with_(_IMPLIED, G, _CLOSURE)
    + f"SELECT {skey('a.labels')} AS src, {skey('b.labels')} AS dst FROM cx a JOIN cx b ON list_has_all(b.closure, a.labels) AND b.n * 1000 >= 500 * a.n",
)
def _(s, d):
    b, w = _implied(s, d)
    u = un.closures(un.universe_all(b), lb.groups(b))
    return el.cover_edges(u, 500, "extents").select(key(w, "src", "src"), key(w, "dst", "dst"))


@query(
    "b11_feasible",
    with_(DOC, G, U, _S, _F)
    + """SELECT count(*) FILTER (WHERE n_q * 1000 < 200 * n_i) AS violations, (SELECT sum(n)::BIGINT FROM sel) AS cost,
  count(*) FILTER (WHERE n_q * 1000 < 200 * n_i) = 0 AND (SELECT sum(n) FROM sel) <= 4000 AS feasible FROM fx""",
)
def _(s, d):
    b, _w = encoded(s, d, "doc")
    return el.is_feasible(un.universe_all(b), small_selection(b), 200, 4000)


@query(
    "b12_work_bound",
    with_(DOC, G, U)
    + f"SELECT {skey()} AS key, round(10.0 * t.n / u.n, 6) AS bound, round(10.0 * (t.n + 1) / (u.n + 1), 6) AS expected FROM u, (SELECT count(*) AS n FROM base) t",
)
def _(s, d):
    b, w = encoded(s, d, "doc")
    u = un.universe_all(b)
    total = u.filter("bits = 0").select(F.col("n").alias("total"))
    bound, exact = un.expected_examined(10, F.col("n"), F.col("total"))
    return u.crossJoin(F.broadcast(total)).select(key(w), F.round(bound, 6).alias("bound"), F.round(exact, 6).alias("expected"))


@query("b13_top_cost", with_(DOC, G, U, _S) + "SELECT sum(n)::BIGINT AS charged, sum(n) FILTER (WHERE len(labels) > 0)::BIGINT AS uncharged FROM sel")
def _(s, d):
    b, _w = encoded(s, d, "doc")
    return small_selection(b).agg(F.sum("n").cast("long").alias("charged"), F.sum(F.when(F.col("bits") != 0, F.col("n"))).cast("long").alias("uncharged"))


@query("b15_equal_extents", with_(_IMPLIED, G, _CLOSURE) + f"SELECT {skey('list_sort(closure)')} AS closure, any_value(n) AS n, count(*) AS sets FROM cx GROUP BY list_sort(closure)")
def _(s, d):
    b, w = _implied(s, d)
    u = un.closures(un.universe_all(b), lb.groups(b))
    kept = un.collapse_equal_extents(u)
    sets = u.groupBy("closure").agg(F.count("*").alias("sets"))
    return kept.join(sets, "closure").select(key(w, "closure", "closure"), "n", "sets")


@query(
    "b16_overlap_factor",
    with_(
        DOC, G, U,
        "sz AS (SELECT a.labels, sum(g.n)::BIGINT AS n FROM u a JOIN g ON list_has_any(g.labels, a.labels) GROUP BY a.labels)",
        "tot AS (SELECT count(*) AS n FROM base)",
    )
    + f"""SELECT {skey('q.labels')} AS key, round(any_value(q.n) / least(coalesce(min(i.n), (SELECT n FROM tot)), (SELECT n FROM tot)), 6) AS factor
FROM sz q LEFT JOIN sz i ON list_has_all(i.labels, q.labels) AND len(i.labels) = 2 WHERE len(q.labels) <= 2 GROUP BY q.labels""",
)
def _(s, d):
    b, w = encoded(s, d, "doc")
    u = un.universe_all(b)
    q = u.filter("bits <> 0").filter(F.bit_count("bits") <= 2)
    chosen = u.filter(F.bit_count("bits") == 2)
    return el.overlap_factor(q, chosen, lb.groups(b)).select(key(w), F.round("factor", 6).alias("factor"))


@query(
    "b17_equality_factor",
    with_(DOC, G, U, _S) + f"SELECT {skey('q.labels')} AS key, round(any_value(q.n) / min(i.n), 6) AS factor FROM g q JOIN sel i ON list_has_all(q.labels, i.labels) GROUP BY q.labels",
)
def _(s, d):
    b, w = encoded(s, d, "doc")
    return el.equality_factor(lb.groups(b), small_selection(b)).select(key(w), F.round("factor", 6).alias("factor"))


_ = D2
