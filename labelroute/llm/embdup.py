"""Embedding near-duplicates by product quantisation.

1. One pass checks each vector and digests its bytes; equal vectors of a label
   are one node, and only one row of each node goes on (rows that a bounded
   bitmap rules out are not exchanged for it).  Vectors travel in the precision
   in which they are given and are compared in double precision.
2. Coarse cells (k-means on a bounded sample), ordered so that neighbours follow
   each other and joined to regions, split every label into inverted lists; a
   vector lies in the list of its nearest cell and asks every cell that can hold
   a link: beyond the plane halfway between two centres by at most the largest
   distance of a link.  That test is exact, so no link is missed.  A pair of
   regions is asked from one side.  A list above ``LIST_ROWS`` is split into
   blocks by hash, so no task holds more, whatever share of the rows a label or
   cell has.
3. In a list the residuals are coded per subspace.  A query sums table look-ups
   (asymmetric distances); as each code keeps its own reconstruction error, the
   triangle inequality rules a vector out exactly, and what is left is reranked
   by the exact cosine in double precision.
4. Links are counted where they are found: a task passes on, for each block of a
   list, one partial count per node and an edge to the smallest node that it is
   connected with there, never the links themselves, so what is exchanged grows with the nodes asked and not
   with the square of a group.

The index is fitted on at most ``SAMPLE_ROWS`` vectors and holds every vector;
the fit decides the cost, never the links found.  Vectors without structure are
asked of nearly all lists of their label, so their cost grows with its square.

Defined results: vectors that are null, empty, zero, or hold null or non-finite
components, and rows with a null label, link with nothing; vectors of different
dimension never link; a repeated row counts as a copy; rows that share a vec_id
but not the vector or label have each their own links; a null vec_id has a null
component and is kept.  Extra columns of the input are not read.
"""

from __future__ import annotations

import hashlib
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

THRESHOLD = 0.93
SAMPLE_ROWS = 20_000
MAX_CELLS = 4_096
#: Rows per coarse cell that the number of cells aims at.
CELL_ROWS = 256
#: Added to every bound on a distance, far above what rounding can lose.
SLACK = 1e-6
LIST_ROWS = 8_192
#: Questions to a block whose counts are held before they are passed on.
ASK_ROWS = 1 << 16
SUBSPACES = 8
CODES = 128


def _checked(whole: bool):
    """Dimension and digest of valid vectors, null for the others; ``whole`` adds
    the components as bytes and leaves the others out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(2)
            values = lists.values.to_numpy(zero_copy_only=False)  # null components are NaN
            values = values + values.dtype.type(0)  # -0.0 becomes 0.0
            wrong, full = (np.concatenate(([0], np.cumsum(x))) for x in (~np.isfinite(values), values != 0))
            at = lists.offsets.to_numpy()
            good = (wrong[at[1:]] == wrong[at[:-1]]) & (full[at[1:]] > full[at[:-1]]) & lists.is_valid().to_numpy(zero_copy_only=False)
            dims, digests, raws = np.diff(at).astype(np.int32), [], []
            for ok, lo, hi in zip(good.tolist(), at[:-1].tolist(), at[1:].tolist(), strict=True):
                raw = values[lo:hi].tobytes() if ok else None
                digests.append(hashlib.blake2b(raw, digest_size=16).digest() if ok else None)
                raws.append(raw if whole else None)
            cols = [b.column(0), b.column(1), pa.array(dims, mask=~good), pa.array(digests, pa.binary())]
            if whole:
                got = pa.RecordBatch.from_arrays([*cols, pa.array(raws, pa.binary())], ["vec_id", "label", "dim", "digest", "vec"])
                yield got.filter(pa.array(good))
            else:
                yield pa.RecordBatch.from_arrays(cols, ["vec_id", "label", "dim", "digest"])

    return run


def _kmeans(x: np.ndarray, k: int, rounds: int, seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    k = max(1, min(k, len(x)))
    c = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        near = np.argmin((c * c).sum(1)[None, :] - 2 * x @ c.T, 1)
        count = np.bincount(near, minlength=k)
        total = np.stack([np.bincount(near, weights=x[:, j], minlength=k) for j in range(x.shape[1])], 1)
        full = count > 0
        c[full] = total[full] / count[full][:, None]
    return c


def _chained(c: np.ndarray) -> np.ndarray:
    """``c`` in an order in which each row's successor is its nearest yet unused."""
    left, order, at = np.ones(len(c), bool), [], 0
    for _ in range(len(c)):
        left[at] = False
        order.append(at)
        d = (c * c).sum(1) - 2 * c @ c[at]
        d[~left] = np.inf
        at = int(d.argmin())
    return c[order]


class Quantiser:
    """Coarse cells, their regions and residual codebooks of one dimension."""

    def __init__(self, sample: np.ndarray, cells: int, regions: int = 1, subspaces: int = SUBSPACES, codes: int = CODES):
        self.dim = sample.shape[1]
        self.sub = min(subspaces, self.dim)
        self.width = -(-self.dim // self.sub)
        self.cells = _chained(_kmeans(sample, cells, 8, 1))
        self.regions = max(1, min(regions, len(self.cells)))
        self.region = np.arange(len(self.cells)) * self.regions // len(self.cells)
        r = self._split(sample - self.cells[self.squares(sample).argmin(1)])
        self.books = [_kmeans(r[:, m], codes, 6, m) for m in range(self.sub)]

    def _split(self, r: np.ndarray) -> np.ndarray:
        pad = self.sub * self.width - self.dim
        return np.pad(r, ((0, 0), (0, pad))).reshape(len(r), self.sub, self.width)

    def squares(self, x: np.ndarray) -> np.ndarray:
        """Squared distances to every centre, rows x cells."""
        return (x * x).sum(1)[:, None] + (self.cells * self.cells).sum(1)[None, :] - 2 * x @ self.cells.T

    def ask(self, x: np.ndarray, radius: float) -> tuple[np.ndarray, np.ndarray]:
        """Own cell of each row, and the regions (rows x regions) that may hold
        a vector within ``radius`` of it.

        What lies in cell c is no nearer to the own centre o than to c, so its
        distance from a row is at least that of the row from the plane between:
        (d(x, c)^2 - d(x, o)^2) / (2 d(c, o))."""
        d = self.squares(x)
        own = d.argmin(1)
        apart = np.sqrt(np.maximum(self.squares(self.cells[own]), 0))
        near = d - np.take_along_axis(d, own[:, None], 1) <= 2 * radius * apart + SLACK
        near[np.arange(len(x)), own] = True
        starts = np.searchsorted(self.region, np.arange(self.regions))
        return own, np.logical_or.reduceat(near, starts, axis=1)

    def encode(self, x: np.ndarray, cell: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Codes of the residuals, each vector's reconstruction error, and the
        part of a squared distance that does not depend on the query."""
        c = self._split(self.cells[cell])
        r = self._split(x) - c
        codes, error, fixed = np.empty((len(x), self.sub), np.int64), np.zeros(len(x)), np.zeros(len(x))
        for m, book in enumerate(self.books):
            d = (r[:, m] ** 2).sum(1)[:, None] + (book * book).sum(1)[None, :] - 2 * r[:, m] @ book.T
            codes[:, m] = d.argmin(1)
            mine = book[codes[:, m]]
            error += ((r[:, m] - mine) ** 2).sum(1)
            fixed += (mine * mine).sum(1) + 2 * (mine * c[:, m]).sum(1)
        return codes, np.sqrt(error), fixed

    def distances(self, q: np.ndarray, cell: np.ndarray, codes: np.ndarray, fixed: np.ndarray) -> np.ndarray:
        """Asymmetric distances by table look-up, queries x list."""
        out = self.squares(q)[:, cell] + fixed[None, :]
        parts = self._split(q)
        for m, book in enumerate(self.books):
            out += (-2 * parts[:, m] @ book.T)[:, codes[:, m]]
        return np.sqrt(np.maximum(out, 0))


def _unit(raw: list[bytes], dim: int) -> np.ndarray:
    """Unit vectors in double precision of vectors of either precision."""
    if not raw:
        return np.empty((0, dim))
    x = np.stack([np.frombuffer(r, np.float32 if len(r) == 4 * dim else np.float64) for r in raw]).astype(np.float64)
    x /= np.abs(x).max(1)[:, None]
    return x / np.linalg.norm(x, axis=1)[:, None]


def _fit(vectors: DataFrame, nodes: DataFrame, sample_rows: int, cell_rows: int, list_rows: int) -> dict[int, Quantiser]:
    """Quantisers by dimension, of about ``sample_rows`` different vectors;
    ``vectors(label, dim, vec)``, ``nodes(label, dim)``."""
    parts = 1 << 20
    total = nodes.count()
    if total > sample_rows:
        vectors = vectors.filter(F.pmod(F.xxhash64("label", "vec"), F.lit(parts)) < int(parts * sample_rows / total))
    rows = vectors.select("dim", "label", "vec").distinct().collect()
    by: dict[int, list] = {}
    for r in rows:
        by.setdefault(r["dim"], []).append(bytes(r["vec"]))
    cells = min(MAX_CELLS, max(1, total // cell_rows))
    # regions such that the largest label has about list_rows vectors in each
    sizes = nodes.groupBy("label", "dim").count().groupBy("dim").agg(F.max("count").alias("n"))
    regions = {r["dim"]: -(-r["n"] // list_rows) for r in sizes.filter(F.col("dim").isin(list(by))).collect()}
    return {d: Quantiser(_unit(sorted(v), d), max(1, cells * len(v) // max(1, len(rows))), regions[d]) for d, v in by.items()}


def _joined(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """``label`` (each number's smallest known companion) after the links a-b."""
    while len(a):
        x, y = label[a], label[b]
        open_ = x != y
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    return label


class _Block:
    """Vectors of one block of a list and what asks it."""

    def __init__(self, key, quantiser: Quantiser | None, radius: float, threshold: float):
        self.key, self.q, self.radius, self.threshold = key, quantiser, radius, threshold
        self.ids, self.copies, self.cell, self.vec = [], [], [], []
        self.held = None

    def hold(self, ids, copies, cell, vec) -> None:
        self.ids += ids
        self.copies += copies
        self.cell += cell
        self.vec += vec

    def _ready(self) -> None:
        """Code what is held and link it among itself."""
        if self.held is not None:
            return
        self.held, dim = len(self.ids), self.key[1]
        self.x, self.weight = _unit(self.vec, dim), np.array(self.copies, np.int64)
        self.cells = np.array(self.cell, np.int64)
        self.codes = self.q.encode(self.x, self.cells) if self.q else None
        self.vec = self.cell = None
        self._clear()
        self._link(self.x, self.weight, 0, True)

    def _clear(self) -> None:
        self.count, self.label, self.found = np.zeros(self.held, np.int64), np.arange(self.held), []

    def ask(self, ids, copies, vec) -> None:
        self._ready()
        at = len(self.ids)
        self.ids += ids
        self.count = np.concatenate((self.count, np.zeros(len(ids), np.int64)))
        self.label = np.concatenate((self.label, np.arange(at, len(self.ids))))
        self._link(_unit(vec, self.key[1]), np.array(copies, np.int64), at, False)

    def _link(self, u: np.ndarray, copies: np.ndarray, at: int, same: bool) -> None:
        """Count the links of the rows ``u``, whose numbers start at ``at``."""
        x = self.x
        for lo in range(0, len(u) if len(x) else 0, 256):
            v = u[lo : lo + 256]
            near = np.ones((len(v), len(x)), bool)
            if self.q is not None:
                codes, error, fixed = self.codes
                near = self.q.distances(v, self.cells, codes, fixed) <= self.radius + error[None, :] + SLACK
            if same:  # each pair once
                near &= np.arange(len(x))[None, :] < np.arange(lo, lo + len(v))[:, None]
            s, t = np.nonzero(near)
            if len(s) > 1 << 16:  # most are near: one product is cheaper than the pairs
                s, t = np.nonzero(near & (v @ x.T >= self.threshold))
            else:
                good = np.einsum("ij,ij->i", v[s], x[t]) >= self.threshold
                s, t = s[good], t[good]
            s = s + lo
            self.count += np.bincount(at + s, self.weight[t], len(self.count)).astype(np.int64)
            self.count[: self.held] += np.bincount(t, copies[s], self.held).astype(np.int64)
            self.label = _joined(self.label, at + s, t)

    def close(self) -> pa.RecordBatch:
        """Counts and edges so far; what is held stays for more questions."""
        self._ready()
        ids = np.array(self.ids, np.int64)
        counted, tied = np.flatnonzero(self.count), np.flatnonzero(self.label != np.arange(len(ids)))
        a = np.concatenate((ids[counted], ids[tied]))
        b = np.concatenate((np.zeros(len(counted), np.int64), ids[self.label[tied]]))
        n = np.concatenate((self.count[counted], np.zeros(len(tied), np.int64)))
        is_edge = np.arange(len(a)) >= len(counted)
        self.ids = self.ids[: self.held]
        self._clear()
        return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b, mask=~is_edge), pa.array(n, mask=is_edge)], ["a", "b", "n"])


def links(reps: DataFrame, models: dict[int, Quantiser], threshold: float, list_rows: int) -> DataFrame:
    """All links among the nodes ``(node, label, dim, copies, vec)``, as rows
    ``a, b, n``: either an edge to a linked node (``n`` null), enough of them to
    connect what is connected, or a partial count of the vectors that ``a`` is
    linked with (``b`` null)."""
    spark = reps.sparkSession
    sent = spark.sparkContext.broadcast(pickle.dumps(models))
    radius = float(np.sqrt(max(0.0, 2 - 2 * threshold))) + SLACK
    kind = "node long, label string, dim int, copies long, cell int, region int, asked array<int>, vec binary"

    def assign(batches):
        m = pickle.loads(sent.value)
        for b in batches:
            placed = [None] * b.num_rows
            dims, raws = b.column(2).to_pylist(), b.column(4).to_pylist()
            for dim in set(dims):
                mine = [i for i, d in enumerate(dims) if d == dim]
                for lo in range(0, len(mine), 256):
                    some = mine[lo : lo + 256]
                    if dim not in m:  # a dimension that the sample did not hold: one cell
                        for i in some:
                            placed[i] = 0, 0, []
                        continue
                    q = m[dim]
                    own, near = q.ask(_unit([raws[i] for i in some], dim), radius)
                    g, all_ = q.region[own][:, None], np.arange(q.regions)[None, :]
                    # of two regions one asks the other, in turns; the own one needs no asking
                    near &= (g != all_) & ((g < all_) == ((g + all_) % 2 == 0))
                    for i, c, r, at in zip(some, own.tolist(), q.region[own].tolist(), near, strict=True):
                        placed[i] = c, r, np.flatnonzero(at)
            cell, region, asked = zip(*placed, strict=True) if placed else ((), (), ())
            yield pa.RecordBatch.from_arrays(
                [*(b.column(i) for i in range(4)), pa.array(cell, pa.int32()), pa.array(region, pa.int32()), pa.array(asked, pa.list_(pa.int32())), b.column(4)],
                ["node", "label", "dim", "copies", "cell", "region", "asked", "vec"],
            )

    placed = common.cut(reps.select("node", "label", "dim", "copies", "vec").mapInArrow(assign, kind), spark, "cells")
    key = ["label", "dim", "region"]
    lists = placed.groupBy(key).agg(F.ceil(F.count("*") / list_rows).cast("int").alias("blocks"))
    block = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    # a vector is held by its own block and asks the blocks before it, which so
    # meets each pair of a list once; it asks all blocks of the other lists
    away = placed.withColumn("target", F.explode("asked")).withColumn("home", F.col("region"))
    away = away.drop("region").withColumnRenamed("target", "region").join(lists, key)
    every = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    before = F.explode(F.sequence(F.lit(0), F.col("mine")))
    shape = ["label", "dim", "region", "block", "kind", "node", "copies", "cell", "vec"]
    inside = placed.join(lists, key).withColumn("mine", block).select("*", before.alias("block"))
    inside = inside.withColumn("kind", F.when(F.col("block") == F.col("mine"), 0).otherwise(1)).select(shape)
    outside = away.select("*", every.alias("block")).withColumn("kind", F.lit(1)).select(shape)

    def search(batches):
        m, block = pickle.loads(sent.value), None
        for b in batches:
            label, dim, region, part, role, node, copies, cell, vec = (b.column(i).to_pylist() for i in range(9))
            i = 0
            while i < len(node):
                key = (label[i], dim[i], region[i], part[i])
                if block is None or key != block.key:
                    if block is not None:
                        yield block.close()
                    block = _Block(key, m.get(dim[i]), radius, threshold)
                j = i
                while j < len(node) and (label[j], dim[j], region[j], part[j], role[j]) == (*key, role[i]):
                    j += 1
                if role[i] == 0:
                    block.hold(node[i:j], copies[i:j], cell[i:j], vec[i:j])
                else:
                    block.ask(node[i:j], copies[i:j], vec[i:j])
                    if len(block.ids) - block.held > ASK_ROWS:
                        yield block.close()
                i = j
        if block is not None:
            yield block.close()

    group = ["label", "dim", "region", "block"]
    found = inside.unionByName(outside).repartition(*group).sortWithinPartitions(*group, "kind").mapInArrow(search, "a long, b long, n long")
    return common.cut(found, spark, "links")


def near_duplicates(
    vectors: DataFrame,
    threshold: float = THRESHOLD,
    sample_rows: int = SAMPLE_ROWS,
    cell_rows: int = CELL_ROWS,
    list_rows: int = LIST_ROWS,
) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row of ``vectors``."""
    spark = vectors.sparkSession
    common.tune_arrow(spark)
    single = vectors.schema["embedding"].dataType.simpleString() == "array<float>"
    base = vectors.select(
        F.col("vec_id").cast("long").alias("vec_id"),
        F.col("label").cast("string").alias("label"),
        F.col("embedding").cast("array<float>" if single else "array<double>").alias("e"),
    )
    rows = common.cut(base.mapInArrow(_checked(False), "vec_id long, label string, dim int, digest binary"), spark, "vectors")
    valid = rows.filter("digest IS NOT NULL AND label IS NOT NULL AND vec_id IS NOT NULL")
    first = valid.groupBy("label", "digest", "dim").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"))
    # written, so that numbers are fixed and a hot vector's rows are split in the joins
    first = common.cut(first.withColumn("node", F.monotonically_increasing_id()), spark, "first-of-vector")
    whole = base.mapInArrow(_checked(True), "vec_id long, label string, dim int, digest binary, vec binary").filter("label IS NOT NULL")
    models = _fit(whole, first, sample_rows, cell_rows, list_rows)
    reps = (
        whole.withColumnRenamed("vec_id", "rep")
        .join(first.drop("dim"), ["label", "digest", "rep"])
        .dropDuplicates(["label", "digest", "rep"])
        .select("node", "label", "dim", "copies", "vec")
    )
    found = links(reps, models, threshold, list_rows)
    degree = found.filter("n IS NOT NULL").groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("others"))
    comps = common.connected_components(found.filter("n IS NULL").select("a", "b"), spark)
    placed = common.cut(comps.join(first.select("node", "rep"), "node"), spark, "placed")
    least = common.cut(placed.groupBy("component").agg(F.min("rep").alias("least")), spark, "least")
    facts = (
        first.join(degree, "node", "left")
        .join(placed.join(least, "component").select("node", "least"), "node", "left")
        .select(
            "label",
            "digest",
            (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"),
            F.coalesce("least", "rep").alias("component_id"),
        )
    )
    facts = common.cut(facts, spark, "facts")
    return (
        rows.join(facts, ["label", "digest"], "left")
        .select(
            "vec_id",
            # a row without an id is no copy of any
            F.when(F.col("vec_id").isNotNull(), F.col("n_links")).alias("n_links"),
            F.when(F.col("vec_id").isNotNull(), F.col("component_id")).alias("component_id"),
        )
        .select(
            "vec_id",
            F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
            F.coalesce("component_id", "vec_id").alias("component_id"),
            F.coalesce(F.col("component_id") == F.col("vec_id"), F.lit(True)).alias("kept"),
        )
    )


ORACLE = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
n AS (SELECT vec_id, label, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS norm FROM v),
u AS (SELECT * FROM n WHERE label IS NOT NULL AND norm > 0 AND isfinite(norm)),
l AS (
  SELECT a.vec_id AS x, b.vec_id AS y FROM u a JOIN u b ON a.label = b.label AND a.vec_id <> b.vec_id
  WHERE list_dot_product(a.e, b.e) / (a.norm * b.norm) >= 0.93),
r(x, y) AS (SELECT vec_id, vec_id FROM v UNION SELECT r.x, l.y FROM r JOIN l ON r.y = l.x),
c AS (SELECT x, min(y) AS c FROM r GROUP BY x),
d AS (SELECT x, count(*) AS n FROM l GROUP BY x)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, c AS component_id, c = vec_id AS kept
FROM v JOIN c ON c.x = vec_id LEFT JOIN d ON d.x = vec_id
"""
