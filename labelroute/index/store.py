"""Index sets on Spark: membership, sharded builds, sharded search.

One Parquet row holds one shard of one index (links, vectors, bits as a blob).
Builds run one task per (index, shard).  A search scans the built table where it
lies: queries, a stated set, are sent to the shards in blocks of a fixed size,
so no blob is ever shuffled; each shard answers by one kernel and the answers
are merged by rank.
"""

from __future__ import annotations

import pickle
import time
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import labels as lb
from ..operators.search import cut, most
from ..sources.sinks import scratch
from . import cells, graph

#: Rows of one shard; a shard is one task's work and one row's blob.
SHARD_ROWS = 20_000
#: Queries that one scan of the built table answers.
QUERY_BLOCK = 20_000
#: Queries that are worth a task of their own.
QUERY_PIECE = 32
#: Tasks of a build for each core, and of a build of several forms.
BUILD_TASKS, FORM_TASKS = 2, 8
#: Bytes of one Arrow batch of blobs; a larger blob travels alone.
BATCH_BYTES = 32 << 20


def members(base: DataFrame, selection: DataFrame) -> DataFrame:
    """(index_bits, vec_id, vec, bits): rows of every selected index.

    Groups meet the selection (both small), then rows meet their group by
    equality: the base is read once.
    """
    inside = lb.meeting(selection, lb.groups(base)).withColumnRenamed("qbits", "index_bits")
    return base.select("vec_id", "vec", "bits").join(inside, "bits").select("index_bits", "vec_id", "vec", "bits")


def sharded(rows: DataFrame, selection: DataFrame, shard_rows: int = SHARD_ROWS, *more: str) -> DataFrame:
    """Adds ``shard``: large indexes, the top first of all, are split by hash.  ``more``
    names columns of the selection that a row gets."""
    shards = selection.select(F.col("bits").alias("index_bits"), F.ceil(F.col("n") / shard_rows).cast("int").alias("shards"), *more)
    return rows.join(shards, "index_bits").withColumn(
        "shard", F.pmod(F.xxhash64("vec_id"), F.greatest(F.col("shards"), F.lit(1))).cast("int")
    )


SCHEMA = "index_bits long, shard int, n long, link_bytes long, ids array<bigint>, blob binary, seconds double"


def build(
    base: DataFrame,
    selection: DataFrame,
    kind: str = "graph",
    params: graph.Params | None = None,
    shard_rows: int = SHARD_ROWS,
    path: str | None = None,
    first_shard: int = 0,
) -> DataFrame:
    """(index_bits, shard, n, link_bytes, ids, blob, seconds), one row per shard, stored
    at ``path``; ``seconds`` are those that its kernel took."""
    rows = sharded(members(base, selection), selection, shard_rows).withColumn("shard", F.col("shard") + first_shard)
    path = path or scratch(base.sparkSession, "index")
    _tune(base.sparkSession)
    # few bytes make much work: indexes are dealt over all cores, not by their size
    rows = rows.repartition(BUILD_TASKS * base.sparkSession.sparkContext.defaultParallelism, "index_bits", "shard")
    rows.groupBy("index_bits", "shard").applyInPandas(_built([(kind, params)]), SCHEMA).write.mode("overwrite").parquet(path)
    return base.sparkSession.read.schema(SCHEMA).parquet(path)


def build_forms(base: DataFrame, wanted: DataFrame, forms: list[tuple[str, graph.Params]], shard_rows: int = SHARD_ROWS) -> DataFrame:
    """``build`` of several forms (kind, params) on one base in one job: ``wanted`` has
    the sets (form, bits, n) of each, by its place; adds ``form``."""
    spark, schema = base.sparkSession, f"form int, {SCHEMA}"
    path = scratch(spark, "index")
    _tune(spark)
    by = "form", "index_bits", "shard"
    rows = sharded(members(base, wanted.select("bits").distinct()), wanted, shard_rows, "form")
    rows = rows.repartition(FORM_TASKS * spark.sparkContext.defaultParallelism, *by)
    rows.groupBy(*by).applyInPandas(_built(forms), schema).write.parquet(path)
    return spark.read.schema(schema).parquet(path)


def _built(forms: list):
    """One shard of an index, in the form that its key begins with, if there are several."""

    def one(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        *form, index, shard = key
        kind, params = forms[form[0] if form else 0]
        p = params or graph.Params()
        began = time.perf_counter()
        pdf = pdf.sort_values("vec_id")
        vecs = np.stack(pdf["vec"].to_numpy()) if len(pdf) else np.zeros((0, 1))
        args = pdf["vec_id"].to_numpy(), vecs, pdf["bits"].to_numpy()
        if kind == "label":
            g = graph.build_label_graph(*args, p)
        elif kind == "cells":
            g = cells.build(*args)
        elif kind == "buckets":
            g = cells.build_buckets(*args)
        else:
            g = graph.build(*args, p)
        took = time.perf_counter() - began
        row = {"index_bits": [index], "shard": [shard], "n": [len(pdf)], "link_bytes": [g.link_bytes], "ids": [args[0]], "blob": [g.dump()], "seconds": [took]}
        return pd.DataFrame(({"form": form} if form else {}) | row)

    return one


def build_each(base: DataFrame, selections: list[DataFrame], kind: str = "graph", params: graph.Params | None = None, shard_rows: int = SHARD_ROWS) -> list[DataFrame]:
    """``build`` of several selections on one base: a set that more than one of them
    holds, the top first of all, is built once."""
    wanted = selections[0].select("bits", "n")
    for more in selections[1:]:
        wanted = wanted.unionByName(more.select("bits", "n"))
    built = build(base, wanted.distinct(), kind, params, shard_rows)
    return [indexes_of(built, x) for x in selections]


def indexes_of(built: DataFrame, selection: DataFrame) -> DataFrame:
    """The indexes of a selection, a stated set."""
    sets = selection.select(F.col("bits").alias("index_bits"))
    return built.join(F.broadcast(sets), "index_bits", "left_semi").select(built.columns)


def extend(built: DataFrame, fresh: DataFrame, selection: DataFrame, kind: str = "graph", params: graph.Params | None = None, shard_rows: int = SHARD_ROWS, path: str | None = None) -> DataFrame:
    """Shards of the rows ``fresh`` for every selected index that they belong to,
    to stand beside those of ``built``: answers of shards are merged by rank, so
    nothing that was built is touched."""
    sizes = lb.counted(selection, lb.groups(fresh)).filter("match_count > 0").withColumnRenamed("match_count", "n")
    last = built.agg(F.max("shard")).first()[0]
    return build(fresh, sizes, kind, params, shard_rows, path, 0 if last is None else last + 1)


def marks(built: DataFrame, dead: DataFrame) -> DataFrame:
    """(index_bits, shard, dead): deleted ids (``dead(vec_id)``) of each shard, no
    more than it has rows.  Reads the shards' ids alone."""
    held = built.select("index_bits", "shard", F.explode("ids").alias("vec_id"))
    gone = held.join(dead.select("vec_id").distinct(), "vec_id", "left_semi")
    return gone.groupBy("index_bits", "shard").agg(F.collect_list("vec_id").alias("dead"))


def _tune(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


@lru_cache(maxsize=2)
def _load(blob: bytes):
    return graph.Graph.load(blob)


_ANSWER = "method string, qid long, ef int, index_bits long, shard int, vec_id long, dist double, examined long, distances long, seconds double"


def search(
    built: DataFrame,
    queries: DataFrame,
    routes: DataFrame,
    ef: int | tuple[int, ...] = 64,
    rule: str = "post",
    marked: DataFrame | None = None,
) -> DataFrame:
    """Answers of each shard before the merge, with its counters and the seconds
    that its kernel took: qid, ef, index_bits, shard, vec_id, dist, examined,
    distances, seconds.  Several ``ef`` are answered in one scan.

    ``marked`` (of ``marks``) names deleted ids; searches walk past them.
    """
    routed = routes.select(F.lit("").alias("method"), "bits", "index_bits")
    return search_forms(built.withColumn("form", F.lit(0)), queries, routed, {"": (0, rule)}, ef, marked).drop("method")


def search_forms(
    built: DataFrame, queries: DataFrame, routes: DataFrame, methods: dict[str, tuple[int, str]], ef: int | tuple[int, ...] = 64, marked: DataFrame | None = None
) -> DataFrame:
    """``search`` by several methods in one scan of the forms of ``build_forms``: adds
    ``method``.  ``methods`` has the form and the rule of each, ``routes`` the index of
    each method and query set."""
    spark = built.sparkSession
    _tune(spark)
    beams = (ef,) if isinstance(ef, int) else tuple(ef)
    r = routes.select("method", F.col("bits").alias("qb"), "index_bits")
    q = queries.select("qid", F.col("qvec").cast("array<double>").alias("qvec"), "k", F.col("bits").alias("qb"))
    shards = built.select("form", "index_bits", "shard", "blob")
    if marked is None:
        shards = shards.withColumn("dead", F.lit(None).cast("array<bigint>"))
    else:  # Spark broadcasts the marks only under its own threshold
        shards = shards.join(marked, ["index_bits", "shard"], "left").select("form", "index_bits", "shard", "blob", "dead")
    blocks = max(1, -(-q.count() // QUERY_BLOCK))
    held = {(x[0], x[1]): x[2] for x in built.groupBy("form", "index_bits").count().collect()}
    out = None
    for i in range(blocks):
        some = q if blocks == 1 else q.filter(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == i)
        rows = [(x[0], np.asarray(x[1]), x[2], x[3]) for x in some.select("qid", "qvec", "k", "qb").collect()]  # about QUERY_BLOCK rows
        places: dict[int, list[int]] = {}
        for at, x in enumerate(rows):
            places.setdefault(x[3], []).append(at)
        asked: dict[tuple, dict[str, list[int]]] = {}
        there = r if blocks == 1 else r.join(some.select("qb").distinct(), "qb", "left_semi")
        for method, qb, index in there.select("method", "qb", "index_bits").collect():  # one row a method and set of the block
            if qb in places:
                asked.setdefault((methods[method][0], index), {}).setdefault(method, []).extend(places[qb])
        pieces = _pieces({unit: sum(map(len, x.values())) for unit, x in asked.items()}, held, spark.sparkContext.defaultParallelism)
        sent = spark.sparkContext.broadcast(pickle.dumps((rows, asked, pieces, methods)))
        for piece in range(max(pieces.values(), default=1)):  # much asked indexes are read by several tasks, each with its share of the queries
            read = shards if not piece else shards.filter(_any_of([unit for unit, n in pieces.items() if n > piece]))
            part = read.mapInArrow(_answers(sent, beams, piece), _ANSWER)
            out = part if out is None else out.unionByName(part)
    return out


def _pieces(load: dict, held: dict, cores: int) -> dict:
    """By index (form, bits): the tasks that share its ``load``, the queries that each
    of its shards (``held``) answers.  Together about a task more for each core."""
    total = sum(n * held.get(unit, 0) for unit, n in load.items())
    return {unit: max(1, min(cores, n * cores // max(1, total), n // QUERY_PIECE)) for unit, n in load.items()}


def _any_of(units: list) -> Column:
    """Rows of any of the indexes (form, bits), few of them."""
    out = F.lit(False)
    for form, index in units:
        out = out | ((F.col("form") == form) & (F.col("index_bits") == index))
    return out


def _walked(g: graph.Graph, asked: list, beams: tuple[int, ...], rule: str, gone: frozenset) -> list[dict]:
    """The walks of the queries (qid, vec, k, bits), those of one k and size side by side."""
    alike: dict[tuple, list[int]] = {}
    for at, (_qid, vec, k, _bits) in enumerate(asked):
        alike.setdefault((k, len(vec)), []).append(at)
    out: list = [None] * len(asked)
    for (k, _size), some in alike.items():
        walks = graph.sweep_many(g, np.stack([asked[at][1] for at in some]), np.array([asked[at][3] for at in some], np.int64), k, beams, rule, gone)
        for at, w in zip(some, walks, strict=True):
            out[at] = w
    return out


#: Queries whose answers a task holds at a time.
ANSWERED = 1_024


def _answers(sent, beams, piece: int):
    def run(batches):
        queries, asked, pieces, methods = pickle.loads(sent.value)
        types = (pa.string(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.float64())
        names = [x.split(" ")[0] for x in _ANSWER.split(", ")]
        for b in batches:
            for i in range(b.num_rows):
                unit = form, index = b.column(0)[i].as_py(), b.column(1)[i].as_py()
                if piece >= pieces.get(unit, 0):
                    continue
                shard, blob, dead = (b.column(j)[i].as_py() for j in range(2, 5))
                g = _load(blob)
                kernel = {cells.Cells: cells.search, cells.Buckets: cells.search_buckets}.get(type(g))
                gone = frozenset(dead or ())
                for method, places in asked[unit].items():
                    rule, all_mine = methods[method][1], places[piece :: pieces[unit]]
                    for lo in range(0, len(all_mine), ANSWERED):
                        mine, rows = [queries[at] for at in all_mine[lo : lo + ANSWERED]], []
                        for (qid, vec, k, bits), walks in zip(mine, [{}] * len(mine) if kernel else _walked(g, mine, beams, rule, gone), strict=True):
                            for ef in beams:
                                if kernel:
                                    began = time.perf_counter()
                                    found, st = kernel(g, vec, bits, k, ef, rule, gone)
                                    took = time.perf_counter() - began
                                else:
                                    found, st, took = walks[ef]
                                for d, x in found or [(None, None)]:
                                    rows.append((method, qid, ef, index, shard, x, d, st.expanded, st.distances, took))
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names)

    return run


def work(parts: DataFrame, *by: str) -> DataFrame:
    """Nodes expanded, distances computed and kernel seconds per query and beam,
    summed over its shards; ``by`` names more columns of the key."""
    each = parts.select(*by, "qid", "ef", "index_bits", "shard", "examined", "distances", "seconds").dropDuplicates([*by, "qid", "ef", "index_bits", "shard"])
    return each.groupBy(*by, "qid", "ef").agg(F.sum("examined").alias("examined"), F.sum("distances").alias("distances"), F.sum("seconds").alias("seconds"))


def merge(parts: DataFrame, queries: DataFrame) -> DataFrame:
    """Best k of the shards' answers; of one beam."""
    found = parts.filter("vec_id IS NOT NULL").select("qid", "vec_id", "dist").distinct()
    return cut(found.join(queries.select("qid", "k").distinct(), "qid"), queries)


def merge_beams(parts: DataFrame, queries: DataFrame, *by: str) -> DataFrame:
    """(qid, ef, rank, vec_id, dist): the same for every beam of a sweep, and for each
    value of the columns ``by``."""
    found = parts.filter("vec_id IS NOT NULL").select(*by, "qid", "ef", "vec_id", "dist").distinct()
    w = Window.partitionBy(*by, "qid", "ef").orderBy("dist", "vec_id")
    ranked = found.join(queries.select("qid", "k").distinct(), "qid").withColumn("rank", F.row_number().over(w))
    return ranked.filter((F.col("rank") <= F.lit(most(queries))) & (F.col("rank") <= F.col("k"))).drop("k")
