"""Exact and flat search: constrained nearest neighbours as joins and windows.

Query sets meet label *groups* first (both small), then base rows by equality
on the group, so rows that cannot match are never compared and no product of
queries and rows is formed.  Distances are computed behind the label join; the
per-query cut is a rank filter, which Spark applies before its shuffle
(``WindowGroupLimit``).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import labels as lb
from ..functions import vectors as vx
from ..sources.sinks import saved
from . import scan


#: Queries that a fused search sends to the executors at a time.
FUSED_QUERIES = 4_096


def admitted(queries: DataFrame, grouped: DataFrame, mode: str = "contain") -> DataFrame:
    """(qbits, bits): for each query set the groups whose rows match it."""
    return lb.meeting(queries, grouped, mode)


def candidates(base: DataFrame, queries: DataFrame, mode: str = "contain", groups: DataFrame | None = None) -> DataFrame:
    """(qid, k, vec_id, qvec, vec) of every matching pair, by equi-joins.

    ``groups`` are the base's, where they are known already."""
    pairs = admitted(queries, lb.groups(base) if groups is None else groups, mode)
    q = queries.select("qid", "qvec", "k", F.col("bits").alias("qbits")).join(pairs, "qbits")
    return q.join(base.select("vec_id", "vec", "bits"), "bits")


def exact_knn(base: DataFrame, queries: DataFrame, metric: str = "l2", mode: str = "contain", groups: DataFrame | None = None) -> DataFrame:
    """qid, rank, vec_id, dist of the nearest ``k`` matches; fewer if fewer match."""
    if metric == "l2" and scan.regular(base, queries):
        return _ranked(scan.nearest(base, queries, most(queries), mode), queries)
    pairs = candidates(base, queries, mode, groups).select("qid", "k", "vec_id", vx.distance("qvec", "vec", metric).alias("dist"))
    return cut(pairs, queries)


def _ranked(found: DataFrame, queries: DataFrame, *more: str) -> DataFrame:
    """The cut of a scan's answers, at most k a query and task."""
    return cut(found.join(queries.select("qid", "k").distinct(), "qid"), queries, *more)


def most(queries: DataFrame) -> int:
    """The largest k: a literal bound, from which Spark ranks before its shuffle."""
    return queries.agg(F.max("k")).first()[0] or 0


def within(queries: DataFrame):
    return (F.col("rank") <= F.lit(most(queries))) & (F.col("rank") <= F.col("k"))


def cut(pairs: DataFrame, queries: DataFrame, *more: str) -> DataFrame:
    w = Window.partitionBy("qid").orderBy("dist", "vec_id")
    return pairs.withColumn("rank", F.row_number().over(w)).filter(within(queries)).select("qid", "rank", "vec_id", "dist", *more)


def bruteforce_stats(base: DataFrame, queries: DataFrame) -> DataFrame:
    """Rows that a scan compares, per query."""
    counts = lb.match_counts(base, queries).select(F.col("bits").alias("b"), "match_count")
    q = queries.select("qid", "bits")
    return q.join(counts, q["bits"] == counts["b"], "left").select("qid", F.coalesce("match_count", F.lit(0)).cast("long").alias("scanned"))


def index_pairs(base: DataFrame, queries: DataFrame, routes: DataFrame, *more: str, groups: DataFrame | None = None) -> DataFrame:
    """Every row of a query's routed index with its distance and whether it matches."""
    r = routes.select(F.col("bits").alias("qbits"), "index_bits")
    q = queries.select("qid", "qvec", "k", F.col("bits").alias("qbits"), *more).join(r, "qbits")
    g = (lb.groups(base) if groups is None else groups).select("bits")
    inside = lb.meeting(q.select(F.col("index_bits").alias("bits")), g).withColumnRenamed("qbits", "index_bits")
    met = q.join(inside, "index_bits").join(base.select("vec_id", "vec", "bits"), "bits")
    return met.select(
        "qid", "k", "vec_id", "index_bits", lb.contains_all("bits", "qbits").alias("match"), vx.l2sq("qvec", "vec").alias("dist"), *more
    )


def pre_flat(base: DataFrame, queries: DataFrame, routes: DataFrame, groups: DataFrame | None = None) -> DataFrame:
    return cut(index_pairs(base, queries, routes, groups=groups).filter("match"), queries)


def _nearer(base: DataFrame, queries: DataFrame, routes: DataFrame, found: DataFrame, groups: DataFrame) -> DataFrame:
    """(qid, slot, n): rows of the routed index between a query's answers; slot 0
    holds those up to the first, slot 1 those from there up to the second.

    The answers, at most k a query, go along with their query as sorted bounds,
    so the rows are only counted, by partial sums, and never ranked."""
    bounds = found.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("dist", "vec_id"))).alias("bounds"))
    asked = queries.join(bounds, "qid")
    at = F.struct("dist", "vec_id")
    slot = F.size(F.filter("bounds", lambda x: x < at))
    rows = index_pairs(base, asked, routes, "bounds", groups=groups).select("qid", slot.alias("slot"), F.size("bounds").alias("last"))
    return rows.filter("slot < last").groupBy("qid", "slot").agg(F.count("*").alias("n"))


def post_flat(base: DataFrame, queries: DataFrame, routes: DataFrame) -> DataFrame:
    """Walk each index in distance order until k rows match: result rows with
    the number of rows examined up to each.

    The answers come from a limited rank over the matches; what the walk would
    have examined is then counted, not walked."""
    groups, routes = saved(lb.groups(base), "groups"), saved(routes, "routes")  # one row per label set each
    found = saved(pre_flat(base, queries, routes, groups), "answers")  # at most k rows a query, used twice
    n = _nearer(base, queries, routes, found, groups).withColumn("rank", F.col("slot") + 1)
    w = Window.partitionBy("qid").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)  # k rows a query
    upto = n.withColumn("examined", F.sum("n").over(w)).select("qid", "rank", "examined")
    return found.join(upto, ["qid", "rank"]).select("qid", "rank", "vec_id", "dist", "examined")


def post_examined(base: DataFrame, queries: DataFrame, routes: DataFrame) -> DataFrame:
    """Rows examined until the k-th match, the whole index if there are fewer."""
    groups, routes = saved(lb.groups(base), "groups"), saved(routes, "routes")  # one row per label set each
    if scan.regular(base, queries):
        # a routed index holds all matches of its queries
        routed = queries.join(routes.select("bits", "index_bits"), "bits")
        found = saved(exact_knn(base, routed), "answers").join(routed.select("qid", "qvec", "index_bits", "k"), "qid").filter("rank = k")
        upto = scan.within(base, found).withColumnRenamed("n", "upto")
    else:
        found = saved(pre_flat(base, queries, routes, groups), "answers")
        full = found.join(queries.select("qid", "k"), "qid").filter("rank = k").drop("k")
        upto = _nearer(base, queries, routes, full, groups).select("qid", F.col("n").alias("upto"))
    sizes = lb.counted(routes.select(F.col("index_bits").alias("bits")), groups).withColumnRenamed("bits", "index_bits")
    whole = queries.select("qid", "bits").join(routes.select("bits", "index_bits"), "bits").join(sizes, "index_bits")
    return whole.join(upto, "qid", "left").select("qid", F.coalesce("upto", "match_count").cast("long").alias("examined"))


def fused_knn(base: DataFrame, queries: DataFrame, weight: float) -> DataFrame:
    """Distance plus ``weight`` per missing label; answers may miss labels.

    A fused distance filters nothing, so each query is scored against all rows:
    a stated query set, sent in blocks of ``FUSED_QUERIES`` by the hash of its id.
    """
    if scan.regular(base, queries):
        return _ranked(scan.nearest(base, queries, most(queries), None, float(weight)), queries, "match")
    q = queries.select("qid", "qvec", "k", F.col("bits").alias("qbits"))
    blocks = -(-queries.count() // FUSED_QUERIES)
    missing = F.bit_count(F.col("qbits").bitwiseAND(F.bitwise_not("bits")))
    out = None
    for i in range(max(1, blocks)):
        some = q if blocks <= 1 else q.filter(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == i)
        pairs = base.crossJoin(F.broadcast(some)).select(
            "qid", "k", "vec_id", (vx.l2sq("qvec", "vec") + F.lit(float(weight)) * missing).alias("dist"), (missing == 0).alias("match")
        )
        part = cut(pairs, queries, "match")
        out = part if out is None else out.unionByName(part)
    return out


def merge_topk(parts: DataFrame, k: int) -> DataFrame:
    """Best ``k`` of the shards' answers ``(qid, vec_id, dist)``."""
    w = Window.partitionBy("qid").orderBy("dist", "vec_id")
    return parts.dropDuplicates(["qid", "vec_id"]).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
