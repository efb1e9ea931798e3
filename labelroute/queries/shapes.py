"""Operators around the methods: scans, sinks, filters, joins, aggregates,
windows, sets, functions, UDFs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import labels as lb
from ..functions import vectors as vx
from ..operators import route
from ..operators import search as sr
from ..operators import universe as un
from ..plans import inspect
from ..sources import sinks
from ..sources.tables import SCHEMAS, load, views
from .common import D2, DOC, G, LINE, SUB, U, encoded, key, skey, small_selection, split, with_

Q, O = {}, {}  # noqa: E741


def query(name, sql=None):
    def put(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f

    return put


def same(name, sql, duck=None, *tables):
    """One statement for both engines (``duck`` where the dialects part)."""

    def run(s, d):
        views(s, d)
        return s.sql(sql)

    query(name, duck or sql)(run)


# scans --------------------------------------------------------------------

_PRINT = {
    "region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey",
    "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id",
    "labels": "doc_id", "conversations": "conv_id",
}
for _t, _k in _PRINT.items():
    same(f"o_scan_{_t}", f"SELECT count(*) AS n, min({_k}) AS lo, max({_k}) AS hi, count(DISTINCT {_k}) AS keys FROM {_t}")

for _fmt in ("csv", "json", "orc"):

    def _trip(s, d, fmt=_fmt):
        return sinks.round_trip(load(s, d, "supplier"), fmt).select("s_suppkey", "s_name", "s_nationkey", "s_acctbal")

    query(f"o_source_{_fmt}", "SELECT s_suppkey, s_name, s_nationkey, s_acctbal FROM supplier")(_trip)


@query("o_sink_partitioned", "SELECT c_mktsegment, count(*) AS n FROM customer WHERE c_mktsegment = 'BUILDING' GROUP BY c_mktsegment")
def _(s, d):
    got = sinks.partitioned(load(s, d, "customer"), "c_mktsegment")
    return got.filter("c_mktsegment = 'BUILDING'").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("o_sink_overwrite_partition", "SELECT c_mktsegment, CASE WHEN c_mktsegment = 'BUILDING' THEN 0 ELSE count(*) END AS n FROM customer GROUP BY c_mktsegment HAVING c_mktsegment <> 'BUILDING'")
def _(s, d):
    got = sinks.overwritten(load(s, d, "customer"), "c_mktsegment", F.col("c_mktsegment") == "BUILDING")
    return got.filter("c_custkey IS NOT NULL").groupBy("c_mktsegment").agg(F.count("*").cast("int").alias("n"))


# filters and projection -----------------------------------------------------

same("o_filter_pushdown", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_returnflag = 'R'")
same("o_filter_in_between", "SELECT p_partkey, p_brand FROM part WHERE p_size BETWEEN 5 AND 9 AND p_type IN (SELECT min(p_type) FROM part)")
same("o_filter_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%1%' AND p_name NOT LIKE '%2%'")
same("o_filter_rlike", "SELECT page_id FROM pages WHERE url RLIKE '^https://.*/en/'", "SELECT page_id FROM pages WHERE regexp_matches(url, '^https://.*/en/')")
same(
    "o_filter_nulls",
    "SELECT d.doc_id, quality IS NULL AS missing, CASE WHEN quality = 1 THEN 'good' WHEN quality = 0 THEN 'bad' ELSE 'unknown' END AS grade FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
)
same("o_filter_three_valued", "SELECT count(*) AS n FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE NOT (quality = 1 OR toxic = 1)")


@query(
    "o_filter_label_tree",
    with_(DOC) + "SELECT vec_id FROM base WHERE (list_contains(labels, 'lang:en') OR list_contains(labels, 'lang:fr')) AND NOT list_contains(labels, 'toxic') AND list_contains(labels, 'len:m')",
)
def _(s, d):
    b, w = encoded(s, d, "doc")
    from ..functions.predicate import LabelPredicate as P

    tree = (P.has("lang:en") | P.has("lang:fr")) & ~P.has("toxic") & P.has("len:m")
    return b.filter(tree.column("bits", w)).select("vec_id")


# joins ------------------------------------------------------------------------

_JOIN = "SELECT {hint} l_orderkey, l_linenumber, l_partkey, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey"
for _n, _h in (("broadcast", "BROADCAST(part)"), ("merge", "MERGE(part)"), ("shufflehash", "SHUFFLE_HASH(part)")):
    same(f"o_join_{_n}", _JOIN.format(hint=f"/*+ {_h} */"), _JOIN.format(hint=""))
same("o_join_left", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey AND o_totalprice > 300000")
same("o_join_right", "SELECT c_custkey, o_orderkey FROM orders RIGHT JOIN customer ON c_custkey = o_custkey AND o_totalprice > 300000")
same("o_join_full", "SELECT s.s_suppkey, c.c_custkey FROM supplier s FULL OUTER JOIN customer c ON s.s_suppkey = c.c_custkey")
same("o_join_semi", "SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE c_custkey = o_custkey)")
same("o_join_anti", "SELECT c_custkey FROM customer LEFT ANTI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE c_custkey = o_custkey)")
same("o_join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")
same("o_join_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
same(
    "o_join_chain",
    "SELECT r_name, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name",
)
same(
    "o_join_lateral",
    "SELECT n_name, s_suppkey FROM nation, LATERAL (SELECT s_suppkey FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2)",
)


@query("o_join_range", "SELECT p_partkey, b FROM part JOIN (SELECT unnest(range(0, 30)) AS b) ON p_retailprice >= b * 100 AND p_retailprice < (b + 1) * 100")
def _(s, d):
    """A price-band join: the band is computed, so the range test is an equality."""
    bands = s.range(30).select(F.col("id").alias("b"))
    p = load(s, d, "part").withColumn("b", F.floor(F.col("p_retailprice") / 100))
    return p.join(bands, "b").select("p_partkey", "b")


_IV = "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"
same("o_join_interval", _IV)


@query(
    "o_join_asof",
    "SELECT e.event_id, v.event_id AS version FROM events e ASOF LEFT JOIN (SELECT event_id, ts, user_id FROM events WHERE event_type = 'purchase') v ON e.user_id = v.user_id AND e.ts >= v.ts",
)
def _(s, d):
    """Latest earlier purchase per user: one window over the union, no range join."""
    e = load(s, d, "events")
    at = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    return e.select("event_id", F.max(at).over(w)["event_id"].alias("version"))


_CONT = with_(DOC, G, U) + f"SELECT {skey('q.labels')} AS key, {skey('g.labels')} AS set FROM u q JOIN g ON list_has_all(g.labels, q.labels)"


@query("o_containment_join_bits", _CONT)
def _(s, d):
    from ..operators import universe as un

    b, w = encoded(s, d, "doc")
    u, g = un.universe_all(b).select(F.col("bits").alias("q")), lb.groups(b)
    return u.join(g, lb.contains_all("bits", "q")).select(key(w, "q"), key(w, "bits", "set"))


@query("o_containment_join_explode", _CONT)
def _(s, d):
    from ..operators import universe as un

    b, w = encoded(s, d, "doc")
    u = un.universe_all(b).select(F.col("bits").alias("q"))
    g = lb.groups(b).select("bits", F.explode(lb.subsets("bits")).alias("q"))
    return u.join(g, "q").select(key(w, "q"), key(w, "bits", "set"))


@query("o_join_vector_range", f"SELECT a.vec_id AS a, b.vec_id AS b FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id AND {D2.format('a.embedding', 'b.embedding')} <= 0.3")
def _(s, d):
    e = load(s, d, "embeddings")
    a = e.select("label", F.col("vec_id").alias("a"), F.col("embedding").alias("va"))
    b = e.select("label", F.col("vec_id").alias("b"), F.col("embedding").alias("vb"))
    met = a.join(b, "label").filter("a < b").select("a", "b", vx.l2sq("va", "vb").alias("d2"))
    return met.filter("d2 <= 0.3").select("a", "b")


# aggregates ---------------------------------------------------------------------

same(
    "o_agg_basic",
    "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY l_returnflag, l_linestatus",
)
same("o_agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY l_returnflag")
same(
    "o_agg_gsets",
    "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())",
)
same("o_agg_cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
same(
    "o_agg_rollup",
    "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
)
same("o_agg_percentile", "SELECT l_returnflag, round(percentile(l_quantity, 0.5), 6) AS med FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS med FROM lineitem GROUP BY l_returnflag")
same("o_agg_minby", "SELECT lang, min_by(doc_id, struct(n_chars, doc_id)) AS shortest FROM documents GROUP BY lang", "SELECT lang, arg_min(doc_id, (n_chars, doc_id)) AS shortest FROM documents GROUP BY lang")
same("o_agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 15")
same("o_agg_stats", "SELECT round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")
same("o_agg_filter", "SELECT lang, count(*) FILTER (WHERE n_chars > 1000) AS long FROM documents GROUP BY lang")


@query("o_agg_pivot", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'O') AS O, count(*) FILTER (WHERE l_linestatus = 'F') AS F FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    p = load(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["O", "F"]).count()
    return p.select("l_returnflag", F.coalesce("O", F.lit(0)).alias("O"), F.coalesce("F", F.lit(0)).alias("F"))


@query(
    "o_agg_bitand",
    with_(LINE, "x AS (SELECT labels[4] AS y, unnest(labels) AS label FROM base)", "t AS (SELECT labels[4] AS y, count(*) AS n FROM base GROUP BY 1)", "c AS (SELECT y, label, count(*) AS c FROM x GROUP BY y, label)")
    + "SELECT y, string_agg(label, '|' ORDER BY label) AS common FROM c JOIN t USING (y) WHERE c = n GROUP BY y",
)
def _(s, d):
    b, w = encoded(s, d, "line")
    # labels shared by all rows of a year: the AND of their bit forms
    y = F.element_at("labels", 4)
    return b.groupBy(y.alias("y")).agg(F.bit_and("bits").alias("c")).select("y", key(w, "c", "common"))


@query("o_agg_approx")
def _(s, d):
    t = load(s, d, "lineitem")
    return t.agg(
        F.approx_count_distinct("l_partkey", 0.02).alias("parts"),
        F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 12)).alias("hll"),
        F.percentile_approx("l_quantity", 0.5).alias("med"),
        F.array_join(F.transform(F.expr("approx_top_k(l_returnflag, 2)"), lambda x: x["item"]), ",").alias("top"),
    )


@query("o_agg_kll")
def _(s, d):
    t = load(s, d, "lineitem")
    return t.agg(F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_quantity), 0.5D)").alias("median"))


@query("o_agg_centroid", "SELECT label AS c, i - 1 AS i, round(avg(embedding[i]::DOUBLE), 6) AS m FROM (SELECT label, embedding, unnest(range(1, 65)) AS i FROM embeddings) GROUP BY label, i")
def _(s, d):
    from ..sources.datasets import centroids

    c = centroids(load(s, d, "embeddings"))
    return c.select("c", F.posexplode("centre").alias("i", "m")).select("c", F.col("i").cast("long").alias("i"), F.round("m", 6).alias("m"))


@query("o_agg_label_mode", with_(DOC, G) + f"SELECT {skey()} AS key, n FROM g ORDER BY n DESC, labels LIMIT 1")
def _(s, d):
    b, w = encoded(s, d, "doc")
    return lb.groups(b).select(key(w), "n").orderBy(F.desc("n"), "key").limit(1)


# windows ---------------------------------------------------------------------------

same(
    "o_win_rank",
    "SELECT p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS rn, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS rk, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr FROM part",
)
same(
    "o_win_ntile",
    "SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_partkey) AS q, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_partkey), 6) AS pr, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_partkey), 6) AS cd FROM part",
)
same("o_win_lag", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next FROM events")
same("o_win_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS total FROM events")
same("o_win_rows", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS n FROM events")
same("o_win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM part")
same(
    "o_win_nth",
    "SELECT event_id, first_value(event_id) OVER w AS f, last_value(event_id) OVER w AS l, nth_value(event_id, 2) OVER w AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
)
same("o_win_max", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS hi FROM events")
same("o_topk_group", "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) t WHERE r <= 3")
same("o_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
same("o_sort_offset", "SELECT c_custkey FROM customer ORDER BY c_custkey LIMIT 10 OFFSET 20")

# sets -------------------------------------------------------------------------------

_A, _B = "SELECT p_brand AS x FROM part WHERE p_size < 20", "SELECT p_brand AS x FROM part WHERE p_size > 15"
for _n, _op in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    same(f"o_set_{_n}", f"{_A} {_op} {_B}")


@query("o_set_union_by_name", "SELECT n_nationkey, n_name, NULL AS r_name FROM nation UNION ALL SELECT NULL, NULL, r_name FROM region")
def _(s, d):
    return load(s, d, "nation").select("n_nationkey", "n_name").unionByName(load(s, d, "region").select("r_name"), allowMissingColumns=True)


# functions ------------------------------------------------------------------------------


@query("o_fn_array", with_(DOC) + "SELECT vec_id, len(labels)::INT AS n, list_contains(labels, 'quality') AS good, array_to_string(list_filter(labels, lambda x: starts_with(x, 'l')), '|') AS ls, labels[1] AS first FROM base")
def _(s, d):
    b, _w = encoded(s, d, "doc")
    return b.select(
        "vec_id", F.size("labels").alias("n"), F.array_contains("labels", "quality").alias("good"),
        F.array_join(F.filter("labels", lambda x: x.startswith("l")), "|").alias("ls"), F.element_at("labels", 1).alias("first"),
    )


@query("o_fn_array_sets", with_(DOC, G) + "SELECT a.n AS n, array_to_string(list_sort(list_intersect(a.labels, ['lang:en','len:m'])), '|') AS both, list_has_any(a.labels, ['toxic','quality']) AS flag FROM g a")
def _(s, d):
    b, _w = encoded(s, d, "doc")
    g = b.groupBy("labels").agg(F.count("*").alias("n"))
    two = F.array(F.lit("lang:en"), F.lit("len:m"))
    return g.select("n", F.array_join(F.array_sort(F.array_intersect("labels", two)), "|").alias("both"), F.arrays_overlap("labels", F.array(F.lit("toxic"), F.lit("quality"))).alias("flag"))


@query("o_fn_array_explode", with_(DOC) + "SELECT vec_id, i - 1 AS pos, labels[i] AS label FROM (SELECT vec_id, labels, unnest(range(1, len(labels) + 1)) AS i FROM base)")
def _(s, d):
    b, _w = encoded(s, d, "doc")
    return b.select("vec_id", F.posexplode("labels").alias("pos", "label")).select("vec_id", F.col("pos").cast("long").alias("pos"), "label")


@query("o_fn_map", with_(DOC) + "SELECT vec_id, split_part(list_filter(labels, lambda x: starts_with(x, 'lang:'))[1], ':', 2) AS lang, len(list_filter(labels, lambda x: contains(x, ':')))::INT AS families FROM base")
def _(s, d):
    b, _w = encoded(s, d, "doc")
    kv = F.map_from_entries(F.transform(F.filter("labels", lambda x: x.contains(":")), lambda x: F.struct(F.split(x, ":")[0].alias("k"), F.split(x, ":")[1].alias("v"))))
    return b.select("vec_id", F.try_element_at(kv, F.lit("lang")).alias("lang"), F.size(F.map_keys(kv)).alias("families"))


same(
    "o_fn_string",
    "SELECT p_partkey, upper(p_name) AS u, substring(p_brand, 1, 5) AS b, length(p_name) AS n, concat_ws('-', p_brand, p_type) AS c, levenshtein(p_brand, 'Brand#11') AS d, md5(p_name) AS h FROM part",
    "SELECT p_partkey, upper(p_name) AS u, substring(p_brand, 1, 5) AS b, length(p_name)::INT AS n, concat_ws('-', p_brand, p_type) AS c, levenshtein(p_brand, 'Brand#11')::INT AS d, md5(p_name) AS h FROM part",
)
same(
    "o_fn_string_tokens",
    "SELECT doc_id, size(split(text, ' ')) AS n, regexp_extract(text, '^([A-Za-z]+)', 1) AS first, sha2(text, 256) AS h FROM documents",
    "SELECT doc_id, len(string_split(text, ' '))::INT AS n, regexp_extract(text, '^([A-Za-z]+)', 1) AS first, sha256(text) AS h FROM documents",
)
same(
    "o_fn_date",
    "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, datediff(o_orderdate, DATE'1992-01-01') AS days, weekday(o_orderdate) AS wd, date_format(date_trunc('month', o_orderdate), 'yyyy-MM-dd') AS mon FROM orders",
    "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days, (isodow(o_orderdate) - 1)::INT AS wd, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mon FROM orders",
)
same(
    "o_fn_math",
    "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS l, round(pow(l_discount, 2), 6) AS p, CAST(floor(l_quantity / 7) AS BIGINT) AS f, l_partkey % 7 AS m, abs(l_tax - l_discount) AS a FROM lineitem",
)
same("o_fn_math_bucket", "SELECT l_orderkey, width_bucket(l_quantity, 0, 50, 10) AS b FROM lineitem", "SELECT l_orderkey, (floor(l_quantity / 5.0) + 1)::BIGINT AS b FROM lineitem")
same("o_fn_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k, to_json(named_struct('t', event_type)) AS j FROM events", "SELECT event_id, json_extract(props, '$.k')::BIGINT AS k, to_json({'t': event_type})::VARCHAR AS j FROM events")
same(
    "o_fn_url",
    "SELECT page_id, parse_url(url, 'PROTOCOL') AS p, parse_url(url, 'HOST') AS h, parse_url(url, 'PATH') AS path, parse_url(url, 'QUERY') AS q FROM pages",
    "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS p, regexp_extract(url, '://([^/?#]*)', 1) AS h, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) AS path, nullif(regexp_extract(url, '[?]([^#]*)', 1), '') AS q FROM pages",
)
same(
    "o_fn_html",
    "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '')) AS n, (length(html) - length(replace(html, '<p>', ''))) / 3 AS paragraphs FROM pages",
    "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g'))::INT AS n, (length(html) - length(replace(html, '<p>', ''))) / 3 AS paragraphs FROM pages",
)


@query("o_fn_vector", f"SELECT vec_id, round(sqrt({D2.replace('z[1]::DOUBLE - z[2]::DOUBLE', 'z[1]::DOUBLE').format('embedding', 'embedding')}), 6) AS norm, round({D2.format('embedding', 'embedding')}, 6) AS zero FROM embeddings")
def _(s, d):
    e = load(s, d, "embeddings")
    return e.select("vec_id", F.round(vx.norm("embedding"), 6).alias("norm"), F.round(vx.l2sq("embedding", "embedding"), 6).alias("zero"))


# UDFs ----------------------------------------------------------------------------------------


@query("o_udf_pandas", f"SELECT a.vec_id, round({D2.format('a.embedding', 'b.embedding')}, 6) AS d2 FROM embeddings a, (SELECT embedding FROM embeddings WHERE vec_id = 0) b")
def _(s, d):
    @F.pandas_udf("double")
    def dist(a: pd.Series, b: pd.Series) -> pd.Series:
        import numpy as np

        x, y = np.stack(a).astype(float), np.stack(b).astype(float)
        return pd.Series(((x - y) ** 2).sum(1))

    e = load(s, d, "embeddings")
    q = e.filter("vec_id = 0").select(F.col("embedding").alias("q"))
    return e.crossJoin(F.broadcast(q)).select("vec_id", F.round(dist("embedding", "q"), 6).alias("d2"))


@query("o_udf_grouped", "SELECT label, count(*) AS n, max(vec_id) AS hi FROM embeddings GROUP BY label")
def _(s, d):
    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"label": [pdf["label"].iloc[0]], "n": [len(pdf)], "hi": [pdf["vec_id"].max()]})

    return load(s, d, "embeddings").select("label", "vec_id").groupBy("label").applyInPandas(one, "label int, n long, hi long")


@query("o_udf_agg", "SELECT lang, round(avg(n_chars), 6) AS mean FROM documents GROUP BY lang")
def _(s, d):
    @F.pandas_udf("double")
    def mean(x: pd.Series) -> float:
        return float(x.mean())

    return load(s, d, "documents").groupBy("lang").agg(F.round(mean("n_chars"), 6).alias("mean"))


@query("o_udf_map", "SELECT doc_id, n_chars * 2 AS n FROM documents")
def _(s, d):
    def run(batches):
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "n": b["n_chars"] * 2})

    return load(s, d, "documents").select("doc_id", "n_chars").mapInPandas(run, "doc_id long, n long")


@query("o_udf_udtf", with_(DOC, G, f"x AS (SELECT unnest({SUB.format('labels')}) AS s FROM g)") + f"SELECT {skey('s')} AS key, count(*) AS sets FROM x GROUP BY s")
def _(s, d):
    from .tablefuncs import LabelSubsets

    s.udtf.register("label_subsets", LabelSubsets)
    encoded(s, d, "doc")[0].select("labels").distinct().createOrReplaceTempView("_doc_sets")
    return s.sql("SELECT t.key, count(*) AS sets FROM _doc_sets, LATERAL label_subsets(labels) t GROUP BY t.key")


@query("o_sql_functions", with_(DOC) + "SELECT vec_id FROM base WHERE list_has_all(labels, ['lang:en', 'len:s'])")
def _(s, d):
    encoded(s, d, "doc")[0].createOrReplaceTempView("_doc_base")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION label_contains(l ARRAY<STRING>, q ARRAY<STRING>) RETURNS BOOLEAN RETURN forall(q, x -> array_contains(l, x))")
    return s.sql("SELECT vec_id FROM _doc_base WHERE label_contains(labels, array('lang:en', 'len:s'))")


@query("o_quality_checks", "SELECT count(*) AS rows, count(*) - count(DISTINCT vec_id) AS repeated, count(*) FILTER (WHERE embedding IS NULL OR len(embedding) <> 64) AS odd, count(*) FILTER (WHERE label IS NULL) AS unlabelled FROM embeddings")
def _(s, d):
    e = load(s, d, "embeddings")
    return e.agg(
        F.count("*").alias("rows"), (F.count("*") - F.countDistinct("vec_id")).alias("repeated"),
        F.count(F.when(F.col("embedding").isNull() | (F.size("embedding") != 64), 1)).alias("odd"), F.count(F.when(F.col("label").isNull(), 1)).alias("unlabelled"),
    )


@query("o_quality_rejects", "SELECT vec_id FROM embeddings WHERE false")
def _(s, d):
    """Rows whose vector is missing or of another length."""
    e = load(s, d, "embeddings")
    return e.filter(F.col("embedding").isNull() | (F.size("embedding") != 64)).select("vec_id")


@query("o_udtf_nearest", f"""SELECT label, vec_id FROM (SELECT label, vec_id, row_number() OVER (PARTITION BY label ORDER BY {D2.format('e.embedding', 'q.embedding')}, vec_id) AS r
 FROM embeddings e, (SELECT embedding FROM embeddings WHERE vec_id = 0) q) WHERE r <= 3""")
def _(s, d):
    """The three nearest rows of every label to one vector, by a table function."""
    from .tablefuncs import NearestOf

    s.udtf.register("nearest_of", NearestOf)
    e = load(s, d, "embeddings")
    e.select("vec_id", F.col("embedding").alias("vec"), "label").createOrReplaceTempView("_labelled")
    first = ", ".join(f"{float(x)!r}D" for x in e.filter("vec_id = 0").select("embedding").first()[0])
    got = s.sql(f"SELECT * FROM nearest_of(TABLE(_labelled) PARTITION BY (label), array({first}), 3)")
    return got.join(s.table("_labelled").select("vec_id", "label"), "vec_id").select("label", "vec_id")


@query("o_topk_merge", f"""SELECT qid, rank, vec_id FROM (SELECT q.vec_id AS qid, e.vec_id, row_number() OVER (PARTITION BY q.vec_id ORDER BY {D2.format('e.embedding', 'q.embedding')}, e.vec_id)::INT AS rank
 FROM embeddings e, (SELECT * FROM embeddings WHERE vec_id % 20 = 0) q) WHERE rank <= 5""")
def _(s, d):
    """Best answers of four parts of the base, merged."""
    e = load(s, d, "embeddings").select("vec_id", F.col("embedding").alias("vec"), F.lit(0).cast("long").alias("bits"))
    q = e.filter("vec_id % 20 = 0").select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"), "bits", F.lit(5).alias("k"))
    parts = None
    for i in range(4):
        some = sr.exact_knn(e.filter(F.pmod(F.xxhash64("vec_id"), F.lit(4)) == i), q).drop("rank")
        parts = some if parts is None else parts.unionByName(some)
    return sr.merge_topk(parts, 5).select("qid", "rank", "vec_id")


@query("o_sink_bucketed", "SELECT o_orderkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def _(s, d):
    """Two tables bucketed alike: their join exchanges nothing."""
    left = sinks.bucketed(load(s, d, "orders").select("o_orderkey"), "o_orderkey", 8)
    right = sinks.bucketed(load(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_linenumber"), "o_orderkey", 8)
    return left.join(right, "o_orderkey").groupBy("o_orderkey").agg(F.count("*").alias("lines"))


@query("o_plan_checks", "SELECT * FROM (VALUES ('no product of queries and rows', true), ('answers are ranked before the shuffle', true), ('a walk is counted, not ranked', true), ('selection reads no vectors', true), ('filters reach the scan', true)) t(fact, holds)")
def _(s, d):
    """What the plans of search and selection must look like."""
    b, q, _w = split(s, d)
    found = sr.exact_knn(b, q)
    routes = route.route(small_selection(b), q)
    walk = sr.post_flat(b, q, routes)
    counted = encoded(s, d, "doc")[0]
    rows = [
        ("no product of queries and rows", inspect.no_cartesian(found) and inspect.no_cartesian(routes) and inspect.no_cartesian(walk)),
        ("answers are ranked before the shuffle", inspect.has(found, "WindowGroupLimit")),
        ("a walk is counted, not ranked", inspect.has(walk, "partial_count") and inspect.has(sr.pre_flat(b, q, routes), "WindowGroupLimit")),
        ("selection reads no vectors", not {"text", "embedding"} & inspect.scanned_columns(un.universe_all(counted))),
        ("filters reach the scan", any("l_quantity" in x for x in inspect.pushed(load(s, d, "lineitem").filter("l_quantity > 40").select("l_orderkey")))),
    ]
    return s.createDataFrame(rows, "fact string, holds boolean")


_ = DataFrame, T, SCHEMAS
