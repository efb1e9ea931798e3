"""Label algebra: canonical sets, bit forms, containment, subsets, groups.

A label set is an array of strings.  Its bit form is one BIGINT over a sorted
dictionary of at most 63 labels, so containment is one ``AND`` inside generated
code.  Null sets are empty, null elements are dropped, repeats and order do not
matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MAX_LABELS = 63
EMPTY_KEY = "∅"


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def canon(c) -> Column:
    c = _col(c)
    return F.array_sort(F.array_distinct(F.array_compact(F.coalesce(c, F.array().cast("array<string>")))))


def key_of(c) -> Column:
    """Sorted labels joined by ``|``; the empty set is ``∅``."""
    s = canon(c)
    return F.when(F.size(s) == 0, F.lit(EMPTY_KEY)).otherwise(F.array_join(s, "|"))


def dictionary(df: DataFrame, col: str = "labels", max_labels: int = MAX_LABELS) -> list[str]:
    """Sorted labels of ``df``; a bounded result, checked before it is used."""
    rows = df.select(F.explode(canon(col)).alias("label")).distinct().limit(max_labels + 1).collect()
    if len(rows) > max_labels:
        raise ValueError(f"more than {max_labels} labels; keep the most frequent with top_labels first")
    return sorted(r["label"] for r in rows)


def bits_of(c, words: list[str]) -> Column:
    """Bit form of a label array; a label outside ``words`` gives -1 (matches nothing)."""
    if not words:
        return F.when(F.size(canon(c)) == 0, F.lit(0).cast("long")).otherwise(F.lit(-1).cast("long"))
    table = F.create_map(*[x for i, w in enumerate(words) for x in (F.lit(w), F.lit(1 << i).cast("long"))])
    got = F.transform(canon(c), lambda x: F.coalesce(F.try_element_at(table, x), F.lit(-1).cast("long")))
    return F.aggregate(got, F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x))


def key_of_bits(b, words: list[str]) -> Column:
    b = _col(b)
    if not words:
        return F.lit(EMPTY_KEY)
    parts = [F.when(b.bitwiseAND(F.lit(1 << i).cast("long")) != 0, F.lit(w)) for i, w in enumerate(words)]
    return F.when(b == 0, F.lit(EMPTY_KEY)).otherwise(F.concat_ws("|", *parts))


def encode(df: DataFrame, words: list[str], col: str = "labels") -> DataFrame:
    return df.withColumn("bits", bits_of(col, words))


def contains_all(base, query) -> Column:
    """``query`` is a subset of ``base`` (bit forms)."""
    q = _col(query)
    return _col(base).bitwiseAND(q) == q


def overlaps(base, query) -> Column:
    return _col(base).bitwiseAND(_col(query)) != 0


def same_set(base, query) -> Column:
    return _col(base) == _col(query)


def matches(base, query, mode: str = "contain") -> Column:
    return {"contain": contains_all, "overlap": overlaps, "equal": same_set}[mode](base, query)


def contains_all_arrays(base, query) -> Column:
    return F.size(F.array_except(_col(query), _col(base))) == 0


def cardinality(b) -> Column:
    return F.bit_count(_col(b))


def subsets(b, max_card: int = 16) -> Column:
    """All sub-masks of a bit form; sets with more labels than ``max_card`` fail loudly.

    The masks are made by doubling: each label adds itself to all masks so far.
    """
    b = _col(b)
    masks = F.aggregate(
        singles(b),
        F.array(F.lit(0).cast("long")),
        lambda made, x: F.concat(made, F.transform(made, lambda m: m + x)),
    )
    return F.when(F.bit_count(b) <= max_card, masks).otherwise(
        F.raise_error(F.lit(f"a label set has more than {max_card} labels")).cast("array<bigint>")
    )


def singles(b) -> Column:
    """The one-label masks of a bit form."""
    b = _col(b)
    powers = F.array(*[F.lit(1 << j).cast("long") for j in range(MAX_LABELS)])
    return F.filter(powers, lambda p: b.bitwiseAND(p) != 0)


def meeting(sets: DataFrame, grouped: DataFrame, mode: str = "contain") -> DataFrame:
    """(qbits, bits): for each distinct set ``bits`` of ``sets`` the groups that match.

    Always an equi-join, at any width: a set meets the groups that hold the one
    of its labels that the fewest groups hold, and each pair is then tested in
    full.  The empty set is one row and meets every group.
    """
    q = sets.select(F.col("bits").alias("qbits")).distinct().filter("qbits >= 0")
    g = grouped.select("bits").distinct()
    if mode == "equal":
        return q.join(g, q["qbits"] == g["bits"]).select("qbits", "bits")
    held = g.select(F.explode(singles("bits")).alias("label"), "bits")
    asked = q.select("qbits", F.explode(singles("qbits")).alias("label"))
    if mode == "overlap":
        return asked.join(held, "label").select("qbits", "bits").distinct()
    counts = held.groupBy("label").count()
    # a label that no group holds ends the set's search, so an inner join would not do
    rarest = (
        asked.join(counts, "label", "left")
        .groupBy("qbits")
        .agg(F.min(F.struct(F.coalesce("count", F.lit(0)).alias("c"), "label")).alias("m"))
        .select("qbits", F.col("m.label").alias("label"))
    )
    some = rarest.join(held, "label").filter(contains_all("bits", "qbits")).select("qbits", "bits")
    empty = q.filter("qbits = 0")  # one row at most
    return some.unionByName(g.join(F.broadcast(empty)).select("qbits", "bits"))


def groups(base: DataFrame) -> DataFrame:
    """Rows per exact label set: one scan, partial sums, at most one row per set and task."""
    return base.groupBy("bits").agg(F.count("*").alias("n"))


def minimal_supersets(grouped: DataFrame, max_card: int = 16) -> DataFrame:
    """Pairs (bits, superset) of groups without a group strictly between.

    Containment as an equi-join: a group's proper subsets are exploded and met
    with the groups, so no nested loop over all pairs is run.
    """
    g = grouped.select("bits")
    pairs = (
        g.select(F.col("bits").alias("superset"), F.explode(subsets("bits", max_card)).alias("bits"))
        .join(g, "bits")
        .filter("bits <> superset")
    )
    between = (
        pairs.select("bits", F.col("superset").alias("mid"))
        .join(pairs.select(F.col("bits").alias("mid"), "superset"), "mid")
        .select("bits", "superset")
        .distinct()
    )
    return pairs.join(between, ["bits", "superset"], "left_anti").select("bits", "superset")


def top_labels(base: DataFrame, k: int = 28, col: str = "labels") -> DataFrame:
    """``base`` with only the ``k`` most frequent labels kept in each set."""
    counts = base.select(F.explode(canon(col)).alias("label")).groupBy("label").count()
    kept = [r["label"] for r in counts.orderBy(F.desc("count"), "label").limit(k).collect()]
    return base.withColumn(col, F.array_intersect(canon(col), F.array(*map(F.lit, kept)).cast("array<string>")))


def match_counts(base: DataFrame, sets: DataFrame, mode: str = "contain") -> DataFrame:
    """Matching rows of each distinct set ``bits`` of ``sets`` and the selectivity."""
    g = groups(base)
    total = g.agg(F.sum("n").alias("total"))
    return counted(sets, g, mode).crossJoin(F.broadcast(total)).select(  # one row
        "bits", "match_count", (F.col("match_count") / F.col("total")).alias("selectivity")
    )


def counted(sets: DataFrame, grouped: DataFrame, mode: str = "contain") -> DataFrame:
    """(bits, match_count) of each distinct set, 0 where nothing matches."""
    met = meeting(sets, grouped, mode).join(grouped.select("bits", "n"), "bits").groupBy("qbits").agg(F.sum("n").alias("c"))
    q = sets.select("bits").distinct()
    return q.join(met, q["bits"] == met["qbits"], "left").select("bits", F.coalesce("c", F.lit(0)).cast("long").alias("match_count"))


def ranked(df: DataFrame, by: list, order: list, name: str = "rank") -> DataFrame:
    return df.withColumn(name, F.row_number().over(Window.partitionBy(*by).orderBy(*order)))
