"""Exact substring deduplication by prefix-partitioned suffix trees over words.

A window is ``n`` consecutive words; a word goes when a window over it has a
word sequence that also starts earlier.  Windows are what the suffixes of the
corpus begin with, so equal windows are the leaves under one node of depth ``n``
or more of its suffix tree.  The tree is built in parts that fit into memory:

1. Exact copies of a text are found by digest; a copy is wholly repeated, so
   only the first of each text goes on.
2. Every window selects the ``k``-word prefix of smallest hash among those that
   start inside it (its anchor).  Equal windows select the same anchor at the
   same offset, so an anchor that occurs once in the corpus has no repeated
   window: its suffixes lead to no internal node and are left out.  Tasks first
   merge the anchors that they see twice, so a hot passage crosses the network
   once per task.
3. The suffixes of a repeated anchor are one group.  Suffixes of an anchor with
   more than ``deep`` occurrences are partitioned by a prefix of their own
   instead, which is lengthened a step at a time, from ``k`` words to ``n``,
   wherever a group still has more than ``deep`` rows (variable-length
   prefixes).  A group that is too large at ``n`` words is one window; its first
   leaf is found by an aggregate.
4. Each task builds the subtree of one group at a time: it sorts the suffixes,
   takes the common-prefix lengths of neighbours in words, and closes the
   internal nodes of depth ``n`` or more from the deepest up.  Such a node is a
   repeat that cannot be extended to the right; a leaf that is not the earliest
   of its node repeats as many words as the deepest such node has.
5. Repeats return to their documents as spans.

The documents' text is exchanged once; both joins reuse that exchange.

Defined results: null and empty texts have no words; a document shorter than
``n`` words keeps them all; rows with the same doc_id and text are one document
that comes twice (both keep what the first keeps), rows with the same doc_id
and different texts are ordered by digest; a null doc_id sorts last.  Very
long texts are handled whole.  Extra columns pass through ``remove_repeats``.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

N = 20
K = 8
#: Occurrences of a prefix above which it is lengthened.
DEEP = 4_000
#: Hot anchors (of eight bytes) that may be broadcast.
HOT_ROWS = 500_000
#: Anchors that a task holds to merge those it sees twice.
MERGE_ROWS = 400_000
_MULT = np.uint64(0x9E3779B97F4A7C15)
_LAST = (1 << 63) - 1


class _Hashes(dict):
    """Word hashes, kept for as many words as fit the bound."""

    def __missing__(self, w: bytes) -> int:
        v = xxhash.xxh64_intdigest(w)
        if len(self) > 300_000:
            self.clear()
        self[w] = v
        return v


def words_of(text: str | None) -> list[bytes]:
    """Runs without ASCII white space (space, \\t, \\n, \\v, \\f, \\r)."""
    return text.encode("utf-8", "surrogatepass").split() if text else []


def anchors(h: np.ndarray, n: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Anchor hashes, and of each the first and last window start that select it.

    Windows that select one anchor in a row are one row, so an anchor position
    may come twice if its value is equalled in between.
    """
    m = len(h) - k + 1
    g = np.zeros(m, np.uint64)
    for j in range(k):
        g = (g ^ h[j : j + m]) * _MULT
        g ^= g >> np.uint64(32)
    w = n - k + 1
    # leftmost minimum of each window of w grams, by doubling
    best, at, span = g.copy(), np.arange(m), 1
    while span < w:
        step = min(span, w - span)
        a, b = best[: len(best) - step], best[step:]
        right = b < a
        at = np.where(right, at[step:], at[: len(at) - step])
        best = np.where(right, b, a)
        span += step
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    last = np.concatenate((first[1:] - 1, [len(at) - 1]))
    return best[first].view(np.int64), first, last


def _scan(n: int, k: int):
    """Anchor rows of every text; within a task an anchor is sent once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _Hashes()
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        rows = 0

        def flush():
            h, d, x, s = (np.concatenate(c) for c in zip(*held, strict=True))
            held.clear()
            order = np.argsort(h, kind="stable")
            h, d, x, s = h[order], d[order], x[order], s[order]
            new = np.concatenate(([True], h[1:] != h[:-1]))
            group = np.cumsum(new) - 1
            size = np.bincount(group)
            # the first row of a group speaks for it; the others are known to repeat
            sent = pa.array(np.where(new, size[group], -1).astype(np.int32))
            for i in range(0, len(h), 1 << 16):
                j = slice(i, i + (1 << 16))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(h[j]), pa.array(d[j]), pa.array(x[j]), pa.array(s[j].astype(np.int32)), sent[j.start : j.stop]],
                    ["anchor", "doc", "digest", "start", "seen"],
                )

        for b in batches:
            docs, digests = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)
            for d, x, t in zip(docs, digests, b.column(2).to_pylist(), strict=True):
                w = words_of(t)
                if len(w) < n:
                    continue
                h = np.fromiter(map(cache.__getitem__, w), np.uint64, len(w))
                a, first, _ = anchors(h, n, k)
                held.append((a, np.full(len(a), d), np.full(len(a), x), first))
                rows += len(a)
            if rows >= MERGE_ROWS:
                yield from flush()
                rows = 0
        if held:
            yield from flush()

    return run


def lengths(n: int, k: int) -> tuple[int, ...]:
    """Words of the prefixes that a frequent anchor's suffixes are grouped by."""
    return (*range(k, n, 4), n)


def _suffixes(n: int, k: int):
    """Suffix rows of a document's repeated anchors, words and all."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _Hashes()
        types = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
        for b in batches:
            out: tuple[list, ...] = [], [], [], [], [], []
            for d, x, t, starts, deep, copy in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                if not starts or copy:
                    continue
                w = words_of(t)
                h = np.fromiter(map(cache.__getitem__, w), np.uint64, len(w))
                a, first, last = anchors(h, n, k)
                where = {s: i for i, s in enumerate(first.tolist())}
                for s in sorted(set(starts).difference(deep or ())):
                    i = where[s]
                    e = int(last[i])
                    for c, v in zip(out, (int(a[i]), d, x, s, e - s + 1, b" ".join(w[s : e + n])), strict=True):
                        c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], _SUFFIX)

    return run


_SUFFIX = ["prefix", "doc", "digest", "start", "windows", "words"]


def _windows(n: int, k: int):
    """The windows of a document's frequent anchors with the hashes of their
    prefixes; of equal windows in a batch only the first carries its words."""
    steps = lengths(n, k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _Hashes()
        types = (pa.list_(pa.int64()), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
        for b in batches:
            best: dict[bytes, tuple[int, int, int]] = {}
            again: list[tuple[int, int, int]] = []
            for d, x, t, deep in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                w = words_of(t)
                h = np.fromiter(map(cache.__getitem__, w), np.uint64, len(w))
                _, first, last = anchors(h, n, k)
                where = {s: i for i, s in enumerate(first.tolist())}
                for s in sorted(set(deep)):
                    for p in range(s, int(last[where[s]]) + 1):
                        key, now = b" ".join(w[p : p + n]), (d, x, p)
                        was = best.get(key)
                        if was is None or now < was:
                            best[key], now = now, was
                        if now:
                            again.append(now)
            rows = []
            for key, (d, x, p) in best.items():
                ends, at = [], -1
                for _ in range(n - 1):
                    at = key.find(b" ", at + 1)
                    ends.append(at)
                ends.append(len(key))
                rows.append(([xxhash.xxh64_intdigest(key[: ends[m - 1]], m) - (1 << 63) for m in steps], d, x, p, 1, key))
            again.sort()
            i = 0
            while i < len(again):  # neighbours of one document are one row
                j = i
                while j + 1 < len(again) and again[j + 1] == (*again[j][:2], again[j][2] + 1):
                    j += 1
                rows.append((None, *again[i], j - i + 1, None))
                i = j + 1
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], ["hashes", *_SUFFIX[1:]])

    return run


def _common(a: bytes, b: bytes, least: int) -> int:
    """Words that two suffixes share; 0 if their first ``least`` bytes differ.
    Every word ends with a space."""
    if a[:least] != b[:least]:
        return 0
    if a == b:
        return a.count(b" ")
    lo, hi = least, min(len(a), len(b))
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid - 1
    return a[:lo].count(b" ")


def subtree(leaves: list[tuple], n: int) -> Iterator[tuple[tuple, int]]:
    """Every leaf that repeats an earlier one, with the most words it repeats.

    ``leaves`` are ``(suffix, bytes of its first n words, place)``.  Sorted, their
    common-prefix lengths give the internal nodes; a stack holds the open nodes
    of depth ``n`` or more as ``[depth, earliest leaf]``."""
    leaves.sort()
    stack: list[list] = []
    before, now = None, None  # the last suffix, and the earliest leaf of what was closed last
    for suffix, least, place in leaves:
        depth = 0 if before is None else _common(before, suffix, least)
        depth = depth if depth >= n else 0
        while stack and stack[-1][0] > depth:
            d, first = stack.pop()
            if first != now:  # equal where a row repeats
                yield max(first, now), d
            now = min(first, now)
        if depth and stack and stack[-1][0] == depth:
            if stack[-1][1] != now:
                yield max(stack[-1][1], now), depth
            stack[-1][1] = min(stack[-1][1], now)
        elif depth:
            stack.append([depth, now])
        before, now = suffix, place
    while stack:
        d, first = stack.pop()
        if first != now:
            yield max(first, now), d
        now = min(first, now)


def _subtrees(n: int):
    """Spans of repeated words, group by group of a sorted partition."""

    def repeats(group):
        if len(group) == 1 and group[0][3] == 1:
            return
        leaves = []
        for d, x, s, m, words in group:
            words += b" "
            ends, at = [0], words.find(b" ")
            while at >= 0:
                ends.append(at + 1)
                at = words.find(b" ", at + 1)
            for i in range(m):
                leaves.append((words[ends[i] :], ends[i + n] - ends[i], (d, x, s + i)))
        again: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for (d, x, s), words in subtree(leaves, n):
            again.setdefault((d, x), []).append((s, s + words))
        for (d, x), spans in again.items():
            spans.sort()
            lo, hi = spans[0]
            for s, e in spans:
                if s > hi:
                    yield d, x, lo, hi
                    lo, hi = s, e
                hi = max(hi, e)
            yield d, x, lo, hi

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = (pa.int64(), pa.int64(), pa.int32(), pa.int32())
        group, key = [], None
        out: list[tuple] = []

        def batch():
            cols = list(zip(*out, strict=True)) or [[]] * 4
            got = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], _SPAN)
            out.clear()
            return got

        for b in batches:
            for p, *row in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                if p != key:
                    if group:
                        out.extend(repeats(group))
                    group, key = [], p
                group.append(row)
            yield batch()
        if group:
            out.extend(repeats(group))
        yield batch()

    return run


_SPAN = ["doc", "digest", "from_word", "to_word"]


def _lengthened(found: DataFrame, n: int, k: int, deep: int) -> tuple[DataFrame, DataFrame]:
    """Groups of the windows ``found`` (of ``_windows``) by prefixes as long as
    need be, as suffix rows, and the spans that need no subtree."""
    spark = found.sparkSession
    spans = found.filter("words IS NULL").select("doc", "digest", F.col("start").alias("from_word"), (F.col("start") + F.col("windows") - 1 + n).alias("to_word"))
    left, groups = found.filter("words IS NOT NULL"), None
    for i in range(len(lengths(n, k))):
        keyed = left.withColumn("prefix", F.col("hashes")[i])
        over = common.cut(keyed.groupBy("prefix").count().filter(F.col("count") > deep).select("prefix"), spark, "long-prefixes")
        some = over.limit(1).count() > 0
        fit = (keyed.join(over, "prefix", "left_anti") if some else keyed).select(_SUFFIX)
        groups = fit if groups is None else groups.unionByName(fit)
        if not some:
            return groups, spans
        left = common.cut(keyed.join(over, "prefix", "left_semi").drop("prefix"), spark, "long-prefixes")
    # one window each, however often: only its first leaf stays
    leaf = F.struct("doc", "digest", "start")
    lead = common.cut(left.groupBy("words").agg(F.min(leaf).alias("lead")), spark, "first-leaves")
    late = left.join(lead, "words").filter(leaf > F.col("lead"))
    return groups, spans.unionByName(late.select("doc", "digest", F.col("start").alias("from_word"), (F.col("start") + n).alias("to_word")))


def _kept(n: int, digest: bool):
    def words(t, spans, copy):
        w = words_of(t)
        if copy and len(w) >= n:
            return w, [], len(w)
        if not spans:
            return w, w, 0
        gone = np.zeros(len(w) + 1, np.int32)
        for s in spans:
            gone[s["from_word"]] += 1
            gone[s["to_word"]] -= 1
        gone = np.cumsum(gone)[:-1] > 0
        return w, [x for x, g in zip(w, gone.tolist(), strict=True) if not g], int(gone.sum())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols: tuple[list, ...] = [], [], [], []
            for t, spans, copy in zip(*(b.column(i).to_pylist() for i in (2, 3, 4)), strict=True):
                w, kept, gone = words(t, spans, copy)
                text = b" ".join(kept)
                cols[0].append(len(w))
                cols[1].append(gone)
                cols[2].append(hashlib.sha256(text).hexdigest())
                if not digest:
                    cols[3].append(t if not gone else text.decode("utf-8", "surrogatepass"))
            head = [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64())]
            if digest:
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), *head, pa.array(cols[2], pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"]
                )
            else:
                rest = [b.column(i) for i in range(5, b.num_columns)]
                yield pa.RecordBatch.from_arrays(
                    [*head, pa.array(cols[3], pa.string()), *rest],
                    ["n_words", "n_removed", "kept_text", *b.schema.names[5:]],
                )

    return run


def _marked(docs: DataFrame, n: int, k: int, deep: int, extra: list[str]) -> DataFrame:
    """Every row as ``doc_id, doc, text, spans, copy`` and the columns ``extra``."""
    spark = docs.sparkSession
    common.tune_arrow(spark)
    doc = F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST))
    ambiguous = docs.groupBy(doc.alias("doc")).count().filter("count > 1").limit(1).count() > 0
    base = docs.select(
        doc.alias("doc"),
        # tells texts under one doc_id apart; constant where none repeats
        (F.xxhash64(F.coalesce("text", F.lit(""))) if ambiguous else F.lit(0).cast("long")).alias("digest"),
        F.col("text").alias("text"),
        *[F.col(c).alias(f"_x{i}") for i, c in enumerate(extra)],
    )

    # 1. exact copies by strong digest
    strong = base.filter("text IS NOT NULL").select("doc", "digest", F.unhex(F.sha2("text", 256)).alias("sha"))
    first = strong.groupBy("sha").agg(F.min("doc").alias("first_doc"), F.count("*").alias("copies")).filter("copies > 1")
    # written, so that the join below is of plain exchanges and a hot text's rows are split
    first = common.cut(first.drop("copies"), spark, "first-of-text")
    copies = strong.join(first, "sha").filter("doc > first_doc").select("doc", "digest").distinct()

    # 2. repeated anchors: one speaker per anchor and task meets the others
    scan = base.select("doc", "digest", "text").mapInArrow(
        _scan(n, k), "anchor long, doc long, digest long, start int, seen int"
    )
    # speakers and known repeats are stored apart; the speakers, most rows of a
    # corpus, go as soon as those that met no other are dropped
    root = common.shared_dir(spark, "anchors")
    scan.withColumn("known", F.col("seen") < 0).write.partitionBy("known").parquet(root)
    kind = "anchor long, doc long, digest long, start int, seen int, known boolean"
    marks = spark.read.schema(kind).parquet(root)
    spoken = common.cut(
        marks.filter("NOT known")
        .drop("known")
        .withColumn("total", F.sum("seen").over(Window.partitionBy("anchor")))
        .filter("total > 1"),
        spark,
        "spoken",
    )
    common.delete_path(spark, f"{root}/known=false")
    hot = spoken.filter(F.col("total") > deep).select("anchor").distinct().withColumn("deep", F.lit(True))
    any_hot = hot.limit(1).count() > 0
    # few anchors are hot, and their number is checked; beyond the bound the join
    # is a shuffle whose skewed side Spark splits
    if hot.limit(HOT_ROWS + 1).count() <= HOT_ROWS:
        hot = F.broadcast(hot)
    silent = spark.read.schema(kind).parquet(root).filter("known").drop("known").join(hot, "anchor", "left")
    part = lambda df, d, c: df.select("doc", "digest", "start", d.alias("deep"), F.lit(c).alias("copy"))
    found = part(spoken, F.col("total") > deep, False).unionByName(
        part(silent, F.coalesce("deep", F.lit(False)), False)
    ).unionByName(part(copies.withColumn("start", F.lit(None).cast("int")), F.lit(False), True))
    # lists no longer than their document
    per_doc = found.groupBy("doc", "digest").agg(
        F.collect_list("start").alias("starts"),
        F.collect_list(F.when(F.col("deep"), F.col("start"))).alias("far"),
        F.max("copy").alias("copy"),
    )

    # 3. suffixes of repeated anchors, 4. their subtrees
    keys = ["doc", "digest"]
    names = ["doc", "digest", "text", "starts", "far", "copy", *[f"_x{i}" for i in range(len(extra))]]
    suffixes = base.join(per_doc, keys, "left").select(names).mapInArrow(
        _suffixes(n, k), "prefix long, doc long, digest long, start int, windows int, words binary"
    )
    known = None
    if any_hot:
        far = common.cut(per_doc.filter("NOT copy AND size(far) > 0").select("doc", "digest", "far"), spark, "far")
        texts = common.may_be_in(base.select("doc", "digest", "text"), "doc", far.select("doc"), "maybe").filter("maybe")
        windows = texts.join(far, keys).select("doc", "digest", "text", "far").mapInArrow(
            _windows(n, k), "hashes array<long>, doc long, digest long, start int, windows int, words binary"
        )
        groups, known = _lengthened(common.cut(windows, spark, "windows"), n, k, deep)
        suffixes = suffixes.unionByName(groups)
    spans = (
        suffixes.repartition("prefix")
        .sortWithinPartitions("prefix")
        .mapInArrow(_subtrees(n), "doc long, digest long, from_word int, to_word int")
    )
    if known is not None:
        spans = spans.unionByName(known)
    spans = spans.groupBy("doc", "digest").agg(F.collect_list(F.struct("from_word", "to_word")).alias("spans"))
    flagged = copies.withColumn("copy", F.lit(True))
    # 5. spans return to the rows; the exchange of the text is the one of step 3
    side = spans.join(flagged, keys, "full")
    return base.join(side, keys, "left").select(
        F.when(F.col("doc") != _LAST, F.col("doc")).alias("doc_id"),
        "digest",
        "text",
        "spans",
        F.coalesce("copy", F.lit(False)).alias("copy"),
        *[F.col(f"_x{i}") for i in range(len(extra))],
    )


def digests(docs: DataFrame, n: int = N, k: int = K, deep: int = DEEP) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every row."""
    return _marked(docs, n, k, deep, []).mapInArrow(
        _kept(n, True), "doc_id long, n_words long, n_removed long, kept_sha256 string"
    )


def remove_repeats(docs: DataFrame, n: int = N, k: int = K, deep: int = DEEP) -> DataFrame:
    """``docs`` with repeated words cut out of ``text`` (kept words joined by a
    space; texts without repeats stay unchanged).  A document of which nothing
    is left goes; rows that had no words stay.  All columns stay."""
    # the text is carried once, as ``text``
    extra = [c for c in docs.columns if c != "text"]
    at = {c: i for i, c in enumerate(extra)}
    marked = _marked(docs, n, k, deep, extra)
    types = "".join(f", _x{i} {docs.schema[c].dataType.simpleString()}" for c, i in at.items())
    out = marked.mapInArrow(_kept(n, False), f"n_words long, n_removed long, kept_text string{types}")
    out = out.filter("n_words = 0 OR n_removed < n_words")
    return out.select(
        *[(F.col("kept_text") if c == "text" else F.col(f"_x{at[c]}")).alias(c) for c in docs.columns]
    )


ORACLE = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS i FROM d WHERE len(w) >= 20),
g AS (
  SELECT doc_id, i, md5(array_to_string(w[i : i + 19], ' ')) AS g FROM s),
r AS (
  SELECT doc_id, i, row_number() OVER (PARTITION BY g ORDER BY doc_id, i) AS k FROM g),
x AS (
  SELECT doc_id, list(DISTINCT j) AS gone FROM (SELECT doc_id, unnest(range(i, i + 20)) AS j FROM r WHERE k > 1) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(len(gone), 0)::BIGINT AS n_removed,
  sha256(coalesce(array_to_string(list_filter(w, lambda x, i: gone IS NULL OR NOT list_contains(gone, i)), ' '), '')) AS kept_sha256
FROM d LEFT JOIN x USING (doc_id)
"""
