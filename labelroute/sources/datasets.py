"""Labelled-vector sets on the given tables.

Each function returns ``(vec_id, vec, labels)``; where only label sets matter
(selection never reads vectors) use the ``*_labels`` form, whose scan prunes
every other column.  Queries are the rows whose id 20 divides, against all rows;
inserts are the rows of another remainder, held out of their base.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import rng, vectors
from ..functions.labels import canon
from .tables import load

QUERY_EVERY = 20
#: Remainder of the rows that stand for inserts.
ARRIVING = 7


def _labels(*cols: Column) -> Column:
    return canon(F.array(*cols))


def _tag(family: str, c: Column) -> Column:
    return F.concat(F.lit(f"{family}:"), c.cast("string"))


def doc_labels(spark: SparkSession, sf_dir: str, source: bool = False) -> DataFrame:
    """lang, length band, quality and toxicity (documents without a label row lack the flags)."""
    d, f = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    size = F.when(F.col("n_chars") < 500, "len:s").when(F.col("n_chars") < 2000, "len:m").otherwise("len:l")
    cols = [
        _tag("lang", F.col("lang")),
        size,
        F.when(F.col("quality") == 1, "quality"),
        F.when(F.col("toxic") == 1, "toxic"),
    ]
    if source:
        cols.append(_tag("source", F.col("source")))
    return d.join(f, "doc_id", "left").select(F.col("doc_id").alias("vec_id"), _labels(*cols).alias("labels"))


def _vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("vec"))


def doc(spark: SparkSession, sf_dir: str, source: bool = False) -> DataFrame:
    return _vectors(spark, sf_dir).join(doc_labels(spark, sf_dir, source), "vec_id")


def part_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "part")
    band = F.floor((F.col("p_size") - 1) / 10).cast("int")
    return p.select(
        F.col("p_partkey").alias("vec_id"),
        _labels(_tag("brand", F.col("p_brand")), _tag("type", F.col("p_type")), _tag("size", band)).alias("labels"),
    )


def part_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts with their exact size: more labels than one number holds."""
    p = load(spark, sf_dir, "part").withColumnRenamed("p_partkey", "vec_id")
    names = _labels(_tag("brand", F.col("p_brand")), _tag("type", F.col("p_type")), _tag("size", F.col("p_size")))
    return _vectors(spark, sf_dir).join(p.select("vec_id", names.alias("labels")), "vec_id")


def part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vectors(spark, sf_dir).join(part_labels(spark, sf_dir), "vec_id")


def line_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(spark, sf_dir, "lineitem")
    percent = F.round(F.col("l_discount") * 100).cast("int")
    return t.select(
        F.xxhash64(*t.columns).alias("vec_id"),
        _labels(
            _tag("flag", F.col("l_returnflag")),
            _tag("status", F.col("l_linestatus")),
            _tag("year", F.year("l_shipdate")),
            _tag("disc", percent),
        ).alias("labels"),
        F.array(
            (F.col("l_quantity") / 50).cast("float"),
            (F.col("l_extendedprice") / 100000).cast("float"),
            (F.col("l_discount") * 10).cast("float"),
            (F.col("l_tax") * 10).cast("float"),
        ).alias("vec"),
    )


def line(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_labels(spark, sf_dir).select("vec_id", "vec", "labels")


def order_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c = load(spark, sf_dir, "orders"), load(spark, sf_dir, "customer")
    return o.join(c, o["o_custkey"] == c["c_custkey"], "left").select(
        F.col("o_orderkey").alias("vec_id"),
        _labels(
            _tag("status", F.col("o_orderstatus")),
            _tag("prio", F.col("o_orderpriority")),
            _tag("year", F.year("o_orderdate")),
            _tag("seg", F.col("c_mktsegment")),
        ).alias("labels"),
        F.array(
            (F.col("o_totalprice") / 100000).cast("float"), (F.datediff(F.col("o_orderdate"), F.lit("1992-01-01")) / 1000).cast("float")
        ).alias("vec"),
    )


def page_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "pages")
    lang = F.regexp_extract("url", r"://[^/]*/([a-z]{2})/", 1)
    return p.select(
        F.col("page_id").alias("vec_id"),
        _labels(
            F.when(lang != "", _tag("lang", lang)),
            F.when(F.col("url").contains("?"), "query"),
            F.when(F.col("url").contains("#"), "anchor"),
            F.when(F.col("url").startswith("https:"), "https"),
        ).alias("labels"),
    )


def event_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_rows(load(spark, sf_dir, "events"))


def meta(spark: SparkSession, sf_dir: str, nearest: int = 3) -> DataFrame:
    """Labels by metadata: the ``nearest`` centroids of the ten ``label`` values."""
    e = load(spark, sf_dir, "embeddings")
    centres = centroids(e)
    d = vectors.l2sq("embedding", "centre")
    near = (
        e.select("vec_id", "embedding")
        .crossJoin(F.broadcast(centres))  # ten rows
        .select("vec_id", "embedding", "c", F.round(d, 9).alias("d"))
        .groupBy("vec_id")
        .agg(F.first("embedding").alias("vec"), F.slice(F.array_sort(F.collect_list(F.struct("d", "c"))), 1, nearest).alias("top"))
    )
    return near.select("vec_id", "vec", canon(F.transform("top", lambda x: _tag("c", x["c"]))).alias("labels"))


def centroids(e: DataFrame) -> DataFrame:
    """Mean vector of each label (c, centre)."""
    flat = e.filter("label IS NOT NULL").select("label", F.posexplode("embedding").alias("i", "x"))
    mean = flat.groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("m"))
    ordered = F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda s: s["m"])
    return mean.groupBy(F.col("label").alias("c")).agg(ordered.alias("centre"))


def keywords(spark: SparkSession, sf_dir: str, dims: int = 256, top: int = 3, min_docs: int = 5, max_labels: int = 28) -> DataFrame:
    """Hashed word vectors labelled by each text's rarest frequent words."""
    d = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), F.explode(F.split(F.lower("text"), r"\s+")).alias("w"))
    tf = d.filter("length(w) > 2").groupBy("vec_id", "w").agg(F.count("*").alias("tf"))
    df = tf.groupBy("w").agg(F.count("*").alias("df")).filter(F.col("df") >= min_docs)
    names = df.orderBy(F.desc("df"), "w").limit(max_labels)  # the alphabet, a bounded table
    ranked = tf.join(F.broadcast(names), "w").withColumn(
        "r", F.row_number().over(Window.partitionBy("vec_id").orderBy("df", F.desc("tf"), "w"))
    )
    chosen = ranked.filter(F.col("r") <= top).groupBy("vec_id").agg(F.collect_set("w").alias("labels"))
    slot = F.pmod(F.xxhash64("w"), F.lit(dims)).cast("int")
    hashed = tf.groupBy("vec_id", slot.alias("s")).agg(F.sum("tf").alias("x"))
    cells = F.map_from_entries(F.collect_list(F.struct("s", "x")))
    vec = hashed.groupBy("vec_id").agg(cells.alias("m")).select(
        "vec_id",
        F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0)).cast("float")).alias("vec"),
    )
    return vec.join(chosen, "vec_id", "left").select("vec_id", "vec", canon("labels").alias("labels"))


def amplified(spark: SparkSession, sf_dir: str, copies: int, alphabet: int = 12) -> DataFrame:
    """Embeddings times ``copies`` with a deterministic jitter, for scale runs."""
    from ..operators import generate

    e = _vectors(spark, sf_dir).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    ident = F.col("vec_id") * copies + F.col("copy")
    jitter = lambda x, i: (x + (rng.u(ident, i, "jitter") - 0.5).cast("float") * F.lit(0.05)).cast("float")
    rows = e.select(ident.alias("vec_id"), F.when(F.col("copy") == 0, F.col("vec")).otherwise(F.transform("vec", jitter)).alias("vec"))
    return generate.zipf(rows, alphabet)


def split(base: DataFrame) -> tuple[DataFrame, DataFrame]:
    """All rows, and those that are queries."""
    return base, base.filter(F.pmod("vec_id", F.lit(QUERY_EVERY)) == 0)


def arrivals(base: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows that were there before, and rows that are inserted."""
    new = F.pmod("vec_id", F.lit(QUERY_EVERY)) == ARRIVING
    return base.filter(~new), base.filter(new)


def event_rows(e: DataFrame) -> DataFrame:
    """Labelled vectors of (streamed or stored) events."""
    return e.select(
        F.col("event_id").alias("vec_id"),
        F.array(
            F.col("value").cast("float"), (F.hour("ts") / 24).cast("float"), F.get_json_object("props", "$.k").cast("float")
        ).alias("vec"),
        _labels(_tag("type", F.col("event_type")), _tag("day", F.dayofweek("ts")), _tag("user", F.pmod("user_id", F.lit(4)))).alias("labels"),
    )
