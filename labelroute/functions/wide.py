"""Label sets over alphabets of any size.

The bit form holds 63 labels in one number.  Here a set stays a canonical array of
strings and no dictionary is needed: sets meet by equi-joins on their rarest
label and each pair is then tested in full.  Functions mirror those of
``labels``; ``lattice`` hands selection a numbered form of the same relation.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as vx
from .labels import canon, contains_all_arrays


def groups(base: DataFrame) -> DataFrame:
    """(labels, n): rows of each exact label set."""
    return base.groupBy(canon("labels").alias("labels")).agg(F.count("*").alias("n"))


def meeting(sets: DataFrame, grouped: DataFrame) -> DataFrame:
    """(asked, labels): for each distinct set ``labels`` of ``sets`` the groups that
    contain it."""
    q = sets.select(canon("labels").alias("asked")).distinct()
    held = grouped.select(F.explode("labels").alias("label"), "labels")
    counts = held.groupBy("label").count()
    rarest = (
        q.select("asked", F.explode("asked").alias("label"))
        .join(counts, "label", "left")
        .groupBy("asked")
        .agg(F.min(F.struct(F.coalesce("count", F.lit(0)).alias("c"), "label")).alias("m"))
        .select("asked", F.col("m.label").alias("label"))
    )
    some = rarest.join(held, "label").filter(contains_all_arrays("labels", "asked")).select("asked", "labels")
    empty = q.filter(F.size("asked") == 0)  # one row at most
    return some.unionByName(grouped.select("labels").join(F.broadcast(empty)).select("asked", "labels"))


def universe(base: DataFrame, workload: DataFrame) -> DataFrame:
    """(labels, n) of the workload's sets and the empty set; sets without a match go."""
    spark = base.sparkSession
    g = groups(base)
    wanted = workload.select(canon("labels").alias("labels")).unionByName(spark.createDataFrame([([],)], "labels array<string>")).distinct()
    return meeting(wanted, g).join(g, "labels").groupBy(F.col("asked").alias("labels")).agg(F.sum("n").cast("long").alias("n"))


def numbered(universe: DataFrame) -> DataFrame:
    """Adds ``bits``, a number for each set, 0 for the empty set, as selection names
    its candidates; one row per set of the workload."""
    from pyspark.sql import Window

    order = F.row_number().over(Window.orderBy(F.size("labels"), "labels"))
    return universe.withColumn("bits", (order - 1).cast("long"))


def lattice(universe: DataFrame):
    """The cover relation of a numbered universe on the driver, for the greedy."""
    from ..operators.select import Lattice

    pairs = meeting(universe, universe)
    name = universe.select("bits", "labels")
    edges = (
        pairs.join(name.select(F.col("labels").alias("asked"), F.col("bits").alias("src")), "asked")
        .join(name.select("labels", F.col("bits").alias("dst")), "labels")
        .select("src", "dst")
    )
    size = {r["bits"]: r["n"] for r in universe.select("bits", "n").collect()}
    serves: dict = {k: [] for k in size}
    for r in edges.collect():
        serves[r["src"]].append(r["dst"])
    return Lattice(size, {k: sorted(v) for k, v in serves.items()})


def exact_knn(base: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, rank, vec_id, dist; ``queries(qid, qvec, labels, k)``."""
    from ..operators.search import cut

    rows = base.select("vec_id", "vec", canon("labels").alias("labels"))
    asked = queries.select("qid", "qvec", "k", canon("labels").alias("asked"))
    met = asked.join(meeting(queries, groups(base)), "asked").join(rows, "labels")
    return cut(met.select("qid", "k", "vec_id", vx.l2sq("qvec", "vec").alias("dist")), queries)
