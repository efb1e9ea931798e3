"""Encoded datasets for the queries and the same sets in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import labels as lb
from ..operators import universe as un
from ..sources import datasets as ds

SETS = {
    "doc": ds.doc_labels,
    "doc_vec": ds.doc,
    "part": ds.part_labels,
    "part_vec": ds.part,
    "line": ds.line_labels,
    "order": ds.order_labels,
    "source": lambda s, d: ds.doc_labels(s, d, source=True),
    "page": ds.page_labels,
    "event": ds.event_labels,
    "meta": ds.meta,
    "keywords": ds.keywords,
}


def encoded(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, list[str]]:
    base = SETS[name](spark, sf_dir)
    words = lb.dictionary(base.select("labels"))
    return lb.encode(base, words), words


def split(spark: SparkSession, sf_dir: str, k: int = 10, take: int = 2) -> tuple[DataFrame, DataFrame, list[str]]:
    """All rows of the document set and its queries, the rows whose id 20
    divides; a query asks for the first ``take`` of its own labels."""
    all_rows, words = encoded(spark, sf_dir, "doc_vec")
    base, held = ds.split(all_rows)
    q = held.select(
        F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"), F.slice("labels", 1, take).alias("qlabels"), F.lit(k).alias("k")
    )
    return base, q.withColumn("bits", lb.bits_of("qlabels", words)), words


def small_selection(base: DataFrame) -> DataFrame:
    """The top and all one-label sets: a selection that SQL can state."""
    return un.universe_all(base).filter(F.bit_count("bits") <= 1)


def key(words: list[str], col: str = "bits", name: str = "key"):
    return lb.key_of_bits(col, words).alias(name)


# SQL ---------------------------------------------------------------------

_NN = "lambda x: x IS NOT NULL"
DOC = f"""base AS (
  SELECT d.doc_id AS vec_id, list_sort(list_filter(['lang:' || d.lang,
    CASE WHEN n_chars < 500 THEN 'len:s' WHEN n_chars < 2000 THEN 'len:m' ELSE 'len:l' END,
    CASE WHEN quality = 1 THEN 'quality' END, CASE WHEN toxic = 1 THEN 'toxic' END], {_NN})) AS labels
  FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id)"""
PART = """base AS (
  SELECT p_partkey AS vec_id, list_sort(['brand:' || p_brand, 'type:' || p_type, 'size:' || ((p_size - 1) // 10)]) AS labels FROM part)"""
LINE = """base AS (
  SELECT list_sort(['flag:' || l_returnflag, 'status:' || l_linestatus, 'year:' || year(l_shipdate),
    'disc:' || round(l_discount * 100)::INT]) AS labels FROM lineitem)"""
ORDER = f"""base AS (
  SELECT o_orderkey AS vec_id, list_sort(list_filter(['status:' || o_orderstatus, 'prio:' || o_orderpriority, 'year:' || year(o_orderdate),
    'seg:' || c_mktsegment], {_NN})) AS labels FROM orders LEFT JOIN customer ON o_custkey = c_custkey)"""
#: Document set with vectors and its queries.
SPLIT = DOC.replace("base AS", "alld AS", 1) + """,
allv AS (SELECT vec_id, embedding AS vec, labels FROM alld JOIN embeddings USING (vec_id)),
base AS (SELECT * FROM allv),
q AS (SELECT vec_id AS qid, vec AS qvec, labels[1:{take}] AS ql FROM allv WHERE vec_id % 20 = 0)"""
#: The same set without the rows that stand for inserts.
BEFORE = DOC.replace("base AS", "alld AS", 1) + """,
allv AS (SELECT vec_id, embedding AS vec, labels FROM alld JOIN embeddings USING (vec_id)),
base AS (SELECT * FROM allv WHERE vec_id % 20 <> 7)"""
DICT = "dict AS (SELECT label, row_number() OVER (ORDER BY label) - 1 AS bit FROM (SELECT DISTINCT unnest(labels) AS label FROM base))"
G = "g AS (SELECT labels, count(*) AS n FROM base GROUP BY labels)"
SUB = "list_transform(range(0, (1 << len({0}))::BIGINT), lambda m: list_filter({0}, lambda x, i: ((m >> (i - 1)) & 1) = 1))"
U = f"u AS (SELECT s AS labels, sum(n)::BIGINT AS n FROM (SELECT n, unnest({SUB.format('labels')}) AS s FROM g) GROUP BY s)"
D2 = "list_sum(list_transform(list_zip({0}, {1}), lambda z: (z[1]::DOUBLE - z[2]::DOUBLE) * (z[1]::DOUBLE - z[2]::DOUBLE)))"


def skey(col: str = "labels") -> str:
    return f"CASE WHEN len({col}) = 0 THEN '∅' ELSE array_to_string({col}, '|') END"


def with_(*ctes: str) -> str:
    return "WITH " + ",\n".join(ctes) + "\n"


def split_sql(take: int = 2) -> str:
    return SPLIT.replace("{take}", str(take))
