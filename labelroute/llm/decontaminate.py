"""Benchmark decontamination by a broadcast set of normalised test n-grams.

The benchmark's windows (``n`` consecutive words; an item with fewer is one
window of its own length) go to every executor as sorted hashes with the place
of each window among the items' word numbers, about 24 bytes a word and the
vocabulary.  The benchmark is measured first: one above ``BLOCK_BYTES`` of text
is taken in blocks, gathered, scanned and released one after the other, and the
hits of all blocks are merged by row before anything is decided or cut, so the
number of blocks never changes a result.  A document's words are mapped to the
benchmark's vocabulary; only runs of known words are hashed, looked up and then
verified word by word.

Defined results: null or wordless texts have no words and are clean; items
without words have no windows; repeated items count once per distinct item_id;
null item_ids are named ``""``; an empty table or benchmark gives no hits.
Extra columns pass through ``remove`` untouched and are ignored by ``annotate``.
"""

from __future__ import annotations

import hashlib
import pickle
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

N = 10
#: Bytes of benchmark text in one broadcast block.
BLOCK_BYTES = 16 << 20
#: A document with at least this share of hit words is dropped, else its spans go.
DROP_SHARE = 0.8

# Fixed: A-Z lower-cased; every other ASCII byte but 0-9 and a-z separates words.
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_FOLD = bytes(
    b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256)
)
_MULT = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []


class Grams:
    """Windows of one block of the benchmark, ready to be looked up."""

    def __init__(self, items: list[tuple[str, str | None]], n: int = N):
        self.vocab: dict[bytes, int] = {}
        self.names = sorted({item for item, _ in items})
        name_at = {x: i for i, x in enumerate(self.names)}
        ids, starts, owners, sizes, end = [], [], [], [], 0
        for item, text in items:
            w = words_of(text)
            if not w:
                continue
            ids.append(np.array([self.vocab.setdefault(x, len(self.vocab) + 1) for x in w], np.int32))
            size = min(n, len(w))
            m = len(w) - size + 1
            starts.append(np.arange(end, end + m))
            owners.append(np.full(m, name_at[item], np.int32))
            sizes.append(np.full(m, size, np.int16))
            end += len(w)
        join = lambda xs, t: np.concatenate(xs) if xs else np.empty(0, t)
        self.ids = join(ids, np.int32)
        start, owner, length = join(starts, np.int64), join(owners, np.int32), join(sizes, np.int16)
        #: size -> hashes (sorted), place of each window, and its owners from one offset to the next
        self.windows: dict[int, tuple[np.ndarray, ...]] = {}
        for size in np.unique(length).tolist():
            at, own = start[length == size], owner[length == size]
            _, first, same = np.unique(self.ids[at[:, None] + np.arange(size)], axis=0, return_index=True, return_inverse=True)
            hashes = self._roll(self.ids, at[first], size)
            order = np.argsort(hashes, kind="stable")
            rank = np.empty(len(order), np.int64)
            rank[order] = np.arange(len(order))
            pairs = np.unique(rank[same.reshape(-1)] * len(self.names) + own)
            offsets = np.searchsorted(pairs, np.arange(len(order) + 1) * len(self.names))
            self.windows[size] = hashes[order], at[first][order], offsets, (pairs % len(self.names)).astype(np.int32)

    @staticmethod
    def _roll(ids: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
        acc = np.zeros(len(at), np.uint64)
        for j in range(size):
            acc = acc * _MULT + ids[at + j].astype(np.uint64)
        return acc

    def hits(self, w: list[bytes]) -> tuple[np.ndarray, set[str]]:
        """Which words are inside an occurrence of a window, and whose windows occur."""
        hit, found = np.zeros(len(w), bool), set()
        if not w or not self.windows:
            return hit, found
        get = self.vocab.get
        ids = np.array([get(x, 0) for x in w], np.int32)
        known = np.concatenate(([0], np.cumsum(ids > 0)))
        for size, (hashes, places, offsets, owners) in self.windows.items():
            if len(w) < size:
                continue
            at = np.flatnonzero(known[size:] - known[:-size] == size)
            if not len(at):
                continue
            acc = self._roll(ids, at, size)
            slot = np.searchsorted(hashes, acc)
            span = np.arange(size)
            while len(at):  # once more for every window that shares the hash
                on = slot < len(hashes)
                on[on] = hashes[slot[on]] == acc[on]
                at, acc, slot = at[on], acc[on], slot[on]
                same = (ids[at[:, None] + span] == self.ids[places[slot][:, None] + span]).all(1)
                hit[(at[same][:, None] + span).ravel()] = True
                for k in np.unique(slot[same]).tolist():
                    found.update(self.names[o] for o in owners[offsets[k] : offsets[k + 1]].tolist())
                slot = slot + 1
        return hit, found


def _blocks(benchmark: DataFrame, block_bytes: int, n: int) -> Iterator[Grams]:
    """The benchmark in blocks of a size measured first, one at a time."""
    items = benchmark.select(
        F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("i"), F.col("text").alias("t")
    ).distinct()
    total = items.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    parts = max(1, -(-total // block_bytes))
    for k in range(parts):
        part = items if parts == 1 else items.filter(F.pmod(F.xxhash64("i", "t"), F.lit(parts)) == k)
        yield Grams([tuple(r) for r in part.collect()], n)


def _single(benchmark: DataFrame, block_bytes: int) -> bool:
    return (benchmark.agg(F.sum(F.octet_length("text"))).first()[0] or 0) <= block_bytes


def annotate(docs: DataFrame, benchmark: DataFrame, n: int = N, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    spark = docs.sparkSession
    common.tune_arrow(spark)
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if _single(benchmark, block_bytes):
        sent = spark.sparkContext.broadcast(pickle.dumps(next(_blocks(benchmark, block_bytes, n))))

        def run(batches):
            grams = pickle.loads(sent.value)
            for b in batches:
                rows = [], [], [], []
                for t in b.column(1).to_pylist():
                    w = words_of(t)
                    hit, found = grams.hits(w)
                    rows[0].append(len(w))
                    rows[1].append(int(hit.sum()))
                    rows[2].append(len(found))
                    rows[3].append(hashlib.sha256(",".join(sorted(found)).encode()).hexdigest())
                cols = [pa.array(rows[i], pa.int64()) for i in range(3)] + [pa.array(rows[3], pa.string())]
                yield pa.RecordBatch.from_arrays([b.column(0), *cols], ["doc_id", "n_words", "n_hit", "n_items", "items_sha256"])

        out = base.mapInArrow(run, "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string")
        return out.withColumn("contaminated", F.col("n_hit") > 0)

    rows = common.cut(base.withColumn("_row", F.monotonically_increasing_id()), spark, "numbered")
    merged = _merged(rows, benchmark, block_bytes, n)
    n_words = F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"([^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+)"), 1))
    return rows.join(merged, "_row", "left").select(
        "doc_id",
        n_words.cast("long").alias("n_words"),
        F.coalesce(F.size("hit"), F.lit(0)).cast("long").alias("n_hit"),
        F.coalesce(F.size("found"), F.lit(0)).cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", F.coalesce("found", F.array().cast("array<string>"))), 256).alias("items_sha256"),
        (F.coalesce(F.size("hit"), F.lit(0)) > 0).alias("contaminated"),
    )


def _merged(rows: DataFrame, benchmark: DataFrame, block_bytes: int, n: int) -> DataFrame:
    """``_row, hit, found`` of the rows ``(_row, text)`` that any block hits.

    Each block's scan is written and its broadcast released before the next
    block is gathered."""
    spark, parts = rows.sparkSession, None
    for grams in _blocks(benchmark, block_bytes, n):
        sent = spark.sparkContext.broadcast(pickle.dumps(grams))
        found = rows.select("_row", "text").mapInArrow(_scan(sent), "_row long, hit array<int>, found array<string>")
        found = common.cut(found, spark, "block-hits")
        sent.destroy()
        parts = found if parts is None else parts.unionByName(found)
    # one row's hits, bounded by its length
    return parts.groupBy("_row").agg(
        F.array_sort(F.array_distinct(F.flatten(F.collect_list("hit")))).alias("hit"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_list("found")))).alias("found"),
    )


def _scan(sent):
    def run(batches):
        grams = pickle.loads(sent.value)
        for b in batches:
            out = [], [], []
            for row, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                hit, found = grams.hits(words_of(t))
                if found:
                    for col, v in zip(out, (row, np.flatnonzero(hit).tolist(), sorted(found)), strict=True):
                        col.append(v)
            types = (pa.int64(), pa.list_(pa.int32()), pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], ["_row", "hit", "found"])

    return run


def cut_spans(text: str, hit: np.ndarray) -> str:
    """``text`` without the words that ``hit`` marks and what stands between them."""
    spans = [m.span() for m in _WORD.finditer(_lower(text))]
    out, at, i = [], 0, 0
    while i < len(hit):
        if hit[i]:
            j = i
            while j + 1 < len(hit) and hit[j + 1]:
                j += 1
            out.append(text[at : spans[i][0]])
            at = spans[j][1]
            i = j
        i += 1
    return "".join(out) + text[at:]


def clean_text(text: str, grams: Grams, drop_share: float = DROP_SHARE) -> str | None:
    """``text`` without the spans of its hit words; null if it is mostly hits.

    Removing a span joins what stood around it, so the scan repeats until
    nothing is hit.
    """
    first = None
    while True:
        w = words_of(text)
        hit, found = grams.hits(w)
        if not found:
            return text
        first = first or len(w)
        if len(w) - int(hit.sum()) <= (1 - drop_share) * first:
            return None
        text = cut_spans(text, hit)


_UPPER = {c: c + 32 for c in range(65, 91)}


def _lower(text: str) -> str:
    return text.translate(_UPPER)


def remove(
    docs: DataFrame, benchmark: DataFrame, n: int = N, drop_share: float = DROP_SHARE, block_bytes: int = BLOCK_BYTES
) -> DataFrame:
    """``docs`` with hit spans cut out of ``text``; documents that are mostly
    hits go.  Clean rows, null texts and all other columns stay as they are."""
    spark = docs.sparkSession
    common.tune_arrow(spark)
    at, schema = docs.columns.index("text"), docs.schema
    if not _single(benchmark, block_bytes):
        return _remove_in_blocks(docs, benchmark, n, drop_share, block_bytes)
    sent = spark.sparkContext.broadcast(pickle.dumps(next(_blocks(benchmark, block_bytes, n))))

    def run(batches):
        grams = pickle.loads(sent.value)
        for b in batches:
            texts = b.column(at).to_pylist()
            new = [t if t is None else clean_text(t, grams, drop_share) for t in texts]
            keep = pa.array([a is None or c is not None for a, c in zip(texts, new, strict=True)], pa.bool_())
            cols = [pa.array(new, pa.string()) if i == at else c for i, c in enumerate(b.columns)]
            yield pa.RecordBatch.from_arrays(cols, b.schema.names).filter(keep)

    return docs.mapInArrow(run, schema)


def _remove_in_blocks(docs: DataFrame, benchmark: DataFrame, n: int, drop_share: float, block_bytes: int) -> DataFrame:
    """The same rounds as ``clean_text``, each over all blocks: scan, merge the
    hits of a row, drop or cut it.  Only rows that were cut are scanned again."""
    spark, names = docs.sparkSession, docs.columns
    # own names, so that no column of the input clashes
    rows = docs.select(
        F.monotonically_increasing_id().alias("_row"), F.col("text").alias("text"), *[F.col(f"`{c}`").alias(f"_x{i}") for i, c in enumerate(names) if c != "text"]
    )
    rows = common.cut(rows, spark, "numbered")
    active, done, cuts = rows.select("_row", "text", F.lit(0).alias("first")), None, 0

    def cut_rows(batches):
        for b in batches:
            out = [], [], []
            for row, t, first, hit in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                mark = np.zeros(len(words_of(t)), bool)
                mark[hit] = True
                first = first or len(mark)
                left = len(mark) - int(mark.sum())
                for col, v in zip(out, (row, None if left <= (1 - drop_share) * first else cut_spans(t, mark), first), strict=True):
                    col.append(v)
            types = (pa.int64(), pa.string(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], ["_row", "text", "first"])

    while True:
        hits = common.cut(_merged(active, benchmark, block_bytes, n), spark, "merged-hits")
        if cuts:  # cut rows that are hit no more
            settled = active.join(hits, "_row", "left_anti").select("_row", F.col("text").alias("_new"))
            done = settled if done is None else done.unionByName(settled)
        if not hits.limit(1).count():
            break
        changed = active.join(hits, "_row").select("_row", "text", "first", "hit").mapInArrow(cut_rows, "_row long, text string, first int")
        active, cuts = common.cut(changed, spark, "cut-rows"), cuts + 1
    if done is None:
        return docs
    kept = rows.join(done.withColumn("_cut", F.lit(True)), "_row", "left")
    text = F.when(F.col("_cut"), F.col("_new")).otherwise(F.col("text"))
    return kept.filter("_cut IS NULL OR _new IS NOT NULL").select(
        *[(text if c == "text" else F.col(f"_x{i}")).alias(c) for i, c in enumerate(names)]
    )


ORACLE = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS size,
    array_to_string(w[i : i + least(10, len(w)) - 1], ' ') AS g
  FROM (SELECT item_id, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT size FROM bw),
dw AS (
  SELECT doc_id, i, size, array_to_string(w[i : i + size - 1], ' ') AS g
  FROM (SELECT doc_id, w, size, unnest(range(1, (len(w) - size + 2)::BIGINT)) AS i FROM d, sizes WHERE len(w) >= size)),
m AS (SELECT doc_id, i, dw.size, item_id FROM dw JOIN bw USING (size, g)),
hit AS (
  SELECT doc_id, count(DISTINCT j) AS n_hit
  FROM (SELECT doc_id, unnest(range(i, i + size)) AS j FROM (SELECT DISTINCT doc_id, i, size FROM m)) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names
  FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM m) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN items USING (doc_id)
"""
