"""Near-duplicate documents with SetSketch registers.

A document is the set of its distinct ``shingle``-word shingles.  Its sketch is
``M`` registers, each an exponentially spaced, truncated minimum
``1 - floor(log_B(min))`` of hash values: mergeable by the maximum and equal
with a probability close to the Jaccard similarity.  Runs of ``ROWS`` registers
are bands; texts that share a band are candidates.

1. Sketch every text (one pass).  Texts with one shingle set are one node;
   every node is met by the smallest doc_id that carries it.
2. Bands: each bucket links its nodes to its smallest one (a star, never all
   pairs); connected components of the stars are candidate clusters, which
   hold every link that shares a band.  Only texts that a bounded bitmap of the
   clusters' doc_ids lets through are exchanged.
3. Clusters are searched for links breadth first: a member is compared with
   the members not reached yet.  The similarity of two sketches is estimated
   jointly by maximum likelihood from both set sizes and the counts of greater,
   smaller and equal registers; pairs within ``SLACK`` of the threshold are
   verified on their full shingle sets.  Members already reached need no
   comparison, so a group of near copies costs about one pass.
4. A cluster beyond ``CLUSTER_DOCS`` or ``CLUSTER_WORDS`` is not given to one
   task: the same search runs over all executors.  A round asks a block of
   members, bounded in number and bytes, of all members that its component has
   not reached; reached members are asked while their cluster has others left or
   more than one component waits.

At similarity ``t`` a link shares no band with probability
``(1 - t**ROWS) ** (M / ROWS)``: 6e-11 at 0.85, 5e-8 at 0.8.

Defined results: null texts and texts without words have the empty set and are
linked with nothing; a text with fewer words than a shingle is one shingle;
repeated rows are copies; a doc_id that carries several texts is one document
that is linked by each of them; a null doc_id forms no group (component null,
kept).  ``keep_first`` keeps every row of a document that stays, but of its rows
with one doc_id and one text that has words only one; null and wordless texts
all stay.  Extra columns pass through it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

M = 128
ROWS = 4
BASE = 1.001
RATE = 20.0
LIMIT = (1 << 16) - 2
#: Estimates this far under the threshold (over five standard errors) still verify.
SLACK = 0.2
CLUSTER_DOCS = 1_000
CLUSTER_WORDS = 2_000_000
#: Members of oversized clusters that one round asks, and the bytes of their sets.
BLOCK = 1_024
BLOCK_BYTES = 32 << 20

_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_rng = np.random.default_rng(20240117)
_A = (_rng.integers(0, 1 << 31, M, dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
_C = _rng.integers(0, 1 << 32, M, dtype=np.uint32)
_BAND = _rng.integers(0, 1 << 63, M // ROWS, dtype=np.uint64)
_MULT = np.uint64(0x9E3779B97F4A7C15)


class _Hashes(dict):
    def __missing__(self, w: bytes) -> int:
        v = xxhash.xxh64_intdigest(w)
        if len(self) > 300_000:
            self.clear()
        self[w] = v
        return v


def shingles(text: str | None, k: int, cache: dict) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles."""
    w = text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []
    if not w:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(cache.__getitem__, w), np.uint64, len(w))
    size = min(k, len(w))
    acc = np.full(len(w) - size + 1, size, np.uint64)
    for j in range(size):
        acc = (acc ^ h[j : j + len(acc)]) * _MULT
        acc ^= acc >> np.uint64(29)
    return np.unique(acc)


def sketch(s: np.ndarray) -> np.ndarray:
    """SetSketch registers of a set of 64-bit hashes (uint16)."""
    if not len(s):
        return np.zeros(M, np.uint16)
    x = (s >> np.uint64(32)).astype(np.uint32) ^ s.astype(np.uint32)
    low = np.full(M, np.iinfo(np.uint32).max, np.uint32)
    for at in range(0, len(x), 1024):
        low = np.minimum(low, (_A[:, None] * x[None, at : at + 1024] + _C[:, None]).min(1))
    value = -np.log1p(-(low + 0.5) / 2.0**32) / RATE
    return np.clip(np.floor(1.0 - np.log(value) / np.log(BASE)), 0, LIMIT + 1).astype(np.uint16)


def merge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Registers of the union of two sets."""
    return np.maximum(a, b)


def bands(registers: np.ndarray) -> np.ndarray:
    packed = np.ascontiguousarray(registers).view(np.uint64)  # ROWS x 16 bits
    return ((packed ^ _BAND) * _MULT ^ _BAND).view(np.int64)


def estimate(reg: np.ndarray, n: float, regs: np.ndarray, ns: np.ndarray, grid: int = 41) -> np.ndarray:
    """Joint maximum likelihood estimates of the Jaccard similarity of one
    sketch with each row of ``regs``, the set sizes being known."""
    more, less = (reg > regs).sum(1), (reg < regs).sum(1)
    same = M - more - less
    u = n / (n + ns)
    v = 1.0 - u
    top = np.minimum(u / v, v / u)
    j = top[:, None] * np.linspace(0, 1, grid)[None, :]
    p = lambda x: -np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / np.log(BASE)
    above, below = p(u[:, None] - v[:, None] * j), p(v[:, None] - u[:, None] * j)
    log = lambda x: np.log(np.maximum(x, 1e-12))
    fit = more[:, None] * log(above) + less[:, None] * log(below) + same[:, None] * log(1 - above - below)
    return np.take_along_axis(j, fit.argmax(1)[:, None], 1)[:, 0]


def linked(inter, a, b, percent: int):
    return 100 * inter >= percent * (a + b - inter)


def _name(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def _sketches(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _Hashes()
        types = (pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.int64()))
        for b in batches:
            cols: tuple[list, ...] = [], [], [], []
            for t in b.column(1).to_pylist():
                s = shingles(t, k, cache)
                r = sketch(s)
                cols[0].append(len(s))
                cols[1].append(_name(s) if len(s) else None)
                cols[2].append(r.tobytes() if len(s) else None)
                cols[3].append(bands(r) if len(s) else None)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), *[pa.array(c, t) for c, t in zip(cols, types, strict=True)]],
                ["doc", "n", "set", "registers", "bands"],
            )

    return run


class _Cluster:
    """Breadth-first search for links among a set of members."""

    def __init__(self, nodes, sets, regs, percent: int):
        self.nodes, self.percent = np.array(nodes, np.int64), percent
        self.sizes = np.array([len(s) for s in sets], np.int64)
        self.sets, self.regs = sets, np.stack(regs)

    def components(self) -> np.ndarray:
        """Smallest node of each member's component."""
        order = np.argsort(self.nodes, kind="stable")
        label = np.full(len(order), -1, np.int64)
        left = order
        for i in order.tolist():
            if label[i] >= 0:
                continue
            label[i] = self.nodes[i]
            left = left[label[left] < 0]
            queue = [i]
            while queue and len(left):
                x = queue.pop()
                near = self.near(x, left)
                if len(near):
                    label[near] = label[i]
                    queue += near.tolist()
                    left = left[label[left] < 0]
        return label

    def near(self, x: int, left: np.ndarray) -> np.ndarray:
        return left[near_mask(self.sets[x], self.regs[x], [self.sets[i] for i in left], self.regs[left], self.sizes[left], self.percent)]


def near_mask(s, reg, sets, regs, sizes, percent: int) -> np.ndarray:
    """Which of ``sets`` are linked with ``s``: size, likelihood, full sets."""
    n, t = len(s), percent / 100
    ok = 100 * np.minimum(sizes, n) >= percent * np.maximum(sizes, n)
    at = np.flatnonzero(ok)
    at = at[(regs[at] == reg).sum(1) >= max(1, (t - 2 * SLACK) * M)]
    if len(at):
        at = at[estimate(reg, float(n), regs[at], sizes[at].astype(float)) >= t - SLACK]
    out = np.zeros(len(sizes), bool)
    for lo in range(0, len(at), 256):
        part = at[lo : lo + 256]
        joined = np.concatenate([sets[i] for i in part])
        pos = np.minimum(np.searchsorted(s, joined), n - 1)
        inter = np.add.reduceat((s[pos] == joined).astype(np.int64), np.concatenate(([0], np.cumsum(sizes[part])[:-1])))
        out[part] = linked(inter, sizes[part], n, percent)
    return out


def _own(b: pa.RecordBatch, k: int, cache: dict) -> Iterator[tuple[int, np.ndarray]]:
    """Rows of ``cluster, node, set, text, ...`` whose text is the node's."""
    for i, (name, t) in enumerate(zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)):
        s = shingles(t, k, cache)
        if len(s) and _name(s) == name:
            yield i, s


def _searched(k: int, percent: int):
    """Components of whole clusters, from partitions sorted by cluster."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _Hashes()
        now, rows = None, {}

        def close():
            sets, regs = zip(*rows.values(), strict=True)
            nodes = list(rows)
            found = _Cluster(nodes, sets, regs, percent).components()
            return pa.RecordBatch.from_arrays(
                [pa.array(nodes, pa.int64()), pa.array(found, pa.int64())], ["node", "component"]
            )

        for b in batches:
            cluster, node, regs = (b.column(i).to_pylist() for i in (0, 1, 4))
            for i, s in _own(b, k, cache):
                if cluster[i] != now:
                    if rows:
                        yield close()
                    now, rows = cluster[i], {}
                rows[node[i]] = s, np.frombuffer(regs[i], np.uint16)
        if rows:
            yield close()

    return run


def _roots(merged: list[tuple[int, int]]) -> dict[int, int]:
    """Smallest of the components that ``merged`` pairs join, by component."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while root.setdefault(x, x) != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in merged:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    return {x: find(x) for x in list(root)}


def _oversized(members: DataFrame, percent: int, k: int, block: int, block_bytes: int) -> DataFrame:
    """Edges ``(a, b)`` that connect the linked members of clusters that no
    single task may hold; ``members(cluster, node, set, text, registers)``.

    ``part`` is the component that reached a member, null if none has.  A member
    is compared with every asked one of another component, so a link that joins
    two components is found as well.  New members are asked only in a block that
    holds all waiting ones, so at most ``block`` components are open at a time."""
    spark = members.sparkSession
    kind = "cluster long, node long, members binary, registers binary, part long"

    def sets(batches):
        cache = _Hashes()
        for b in batches:
            got = list(_own(b, k, cache))
            at = pa.array([i for i, _ in got], pa.int64())
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(at), b.column(1).take(at), pa.array([s.tobytes() for _, s in got], pa.binary()), b.column(4).take(at), pa.nulls(len(got), pa.int64())],
                ["cluster", "node", "members", "registers", "part"],
            )

    pool = common.cut(members.mapInArrow(sets, kind).dropDuplicates(["node"]), spark, "neardup-large")
    edges, rounds, waiting = common.numbers(spark, a=[], b=[]), 0, {}
    while pool.limit(1).count():
        rounds += 1
        # the members of the smaller components first: those of the largest may need no turn
        sizes = F.broadcast(common.numbers(spark, part=list(waiting), size=list(waiting.values())))
        order = [F.col("part").isNull(), "size", F.xxhash64("node"), "node"]
        turns = pool.select("node", "part", F.octet_length("members").alias("n")).join(sizes, "part", "left")
        asked, held = [], 0
        for r in turns.orderBy(*order).limit(block).collect():
            held += r["n"]
            if asked and held > block_bytes:
                break
            asked.append(r["node"])
        asked = F.broadcast(common.numbers(spark, node=asked))  # at most ``block``
        by: dict[int, list] = {}
        for r in pool.join(asked, "node", "left_semi").collect():  # at most ``block_bytes``, or one member
            by.setdefault(r["cluster"], []).append((r["node"], np.frombuffer(bytes(r["members"]), np.uint64), bytes(r["registers"]), r["part"]))
        inner, was = [], []
        labelled = {}
        for c, rows in by.items():
            nodes, full, regs, parts = zip(*rows, strict=True)
            label = _Cluster(nodes, full, [np.frombuffer(r, np.uint16) for r in regs], percent).components().tolist()
            inner += [(n, m) for n, m in zip(nodes, label, strict=True) if n != m]
            was += [(m, p) for m, p in zip(label, parts, strict=True) if p is not None]
            labelled[c] = label, full, regs
        root = _roots(was)  # at most ``block`` components wait, and as many were asked
        speakers = {
            c: sorted(zip([root.get(m, m) for m in label], [s.tobytes() for s in full], regs, strict=True), key=lambda x: x[0])
            for c, (label, full, regs) in labelled.items()
        }
        sent = spark.sparkContext.broadcast((speakers, root))

        def compare(batches, sent=sent):
            speakers, root = sent.value
            for b in batches:
                cluster = b.column(0).to_numpy(zero_copy_only=False)
                full = [np.frombuffer(x, np.uint64) for x in b.column(2).to_pylist()]
                regs = [np.frombuffer(x, np.uint16) for x in b.column(3).to_pylist()]
                parts = [None if p is None else root.get(p, p) for p in b.column(4).to_pylist()]
                known = np.array([-1 if p is None else p for p in parts], np.int64)
                sizes = np.array([len(x) for x in full], np.int64)
                labels: list[list[int]] = [[] for _ in full]
                for c in np.unique(cluster).tolist():
                    mine = np.flatnonzero(cluster == c)
                    open_at: dict[int, np.ndarray] = {}  # members that a component has not reached
                    for component, s, r in speakers.get(c, ()):
                        at = open_at[component] if component in open_at else mine[known[mine] != component]
                        if len(at):
                            hit = near_mask(
                                np.frombuffer(s, np.uint64), np.frombuffer(r, np.uint16), [full[i] for i in at], np.stack([regs[i] for i in at]), sizes[at], percent
                            )
                            for i in at[hit].tolist():
                                labels[i].append(component)
                            at = at[~hit]
                        open_at[component] = at
                columns = [*b.columns[:4], pa.array(parts, pa.int64()), pa.array(labels, pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(columns, [*b.schema.names, "labels"])

        rest = pool.join(asked, "node", "left_anti").select(pool.columns)
        met = common.cut(rest.mapInArrow(compare, f"{kind}, labels array<long>"), spark, "neardup-large")
        sent.destroy()
        edges = edges.unionByName(common.numbers(spark, a=[a for a, _ in inner], b=[b for _, b in inner])).unionByName(
            met.filter(F.size("labels") > 0).select(F.col("node").alias("a"), F.explode("labels").alias("b"))
        )
        if rounds % 32 == 0:
            edges = common.cut(edges, spark, "neardup-large")
        # a member without a component goes to the first that reached it, which all others of its own join
        placed = met.withColumn("part", F.coalesce("part", F.try_element_at("labels", F.lit(1))))
        # one pass gives pairs of open components, members of each (at most ``block``) and, with neither, clusters beyond a bound
        other = F.explode(F.array_union(F.array(F.lit(None).cast("long")), F.coalesce("labels", F.array().cast("array<long>"))))
        state = placed.select("cluster", "part", other.alias("other")).groupBy("cluster", "part", "other").count().collect()
        root = _roots([(r["part"], r["other"]) for r in state if r["other"] is not None and r["other"] != r["part"]])
        waiting, open_in, left = {}, {}, set()
        for r in state:
            if r["part"] is None:
                left.add(r["cluster"])
            elif r["other"] is None:
                p = root.get(r["part"], r["part"])
                waiting[p] = waiting.get(p, 0) + r["count"]
                open_in.setdefault(r["cluster"], set()).add(p)
        going = left | {c for c, ps in open_in.items() if len(ps) > 1}
        now = F.broadcast(common.numbers(spark, part=list(root), root=list(root.values())))
        placed = placed.drop("labels").join(now, "part", "left").withColumn("part", F.coalesce("root", "part"))
        placed = placed.join(F.broadcast(common.numbers(spark, cluster=sorted(going))), "cluster", "left_semi")
        pool = common.cut(placed.select(pool.columns), spark, "neardup-large")
    return edges


def components(
    docs: DataFrame,
    shingle: int = 5,
    percent: int = 80,
    cluster_docs: int = CLUSTER_DOCS,
    cluster_words: int = CLUSTER_WORDS,
    block: int = BLOCK,
    block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row of ``docs``."""
    spark = docs.sparkSession
    common.tune_arrow(spark)
    base = docs.select(F.col("doc_id").cast("long").alias("doc"), "text")
    sk = common.cut(
        base.mapInArrow(_sketches(shingle), "doc long, n long, set binary, registers binary, bands array<long>"), spark, "sketches"
    )
    # 1. nodes: written, so that numbers are fixed, joins with them are of plain
    # exchanges and a hot set's rows are split
    named = sk.filter("n > 0 AND doc IS NOT NULL")
    first = named.groupBy("set").agg(F.min("doc").alias("rep")).withColumn("node", F.monotonically_increasing_id())
    first = common.cut(first, spark, "first-of-set")
    reps = named.join(first.withColumnRenamed("rep", "doc"), ["doc", "set"])
    # 2. stars of buckets
    rows = reps.select("node", F.explode("bands").alias("band"))
    roots = rows.groupBy("band").agg(F.min("node").alias("root"), F.max("node").alias("other")).filter("root < other")
    stars = rows.join(roots.select("band", "root"), "band").filter("node > root").select(F.col("node").alias("a"), F.col("root").alias("b"))
    clusters = common.connected_components(stars, spark).withColumnRenamed("component", "cluster")
    marked = common.cut(clusters.join(reps.select("node", "doc", "set", "n", "registers"), "node"), spark, "clusters")
    sizes = marked.groupBy("cluster").agg(F.count("*").alias("docs"), F.sum("n").alias("words"))
    large = sizes.filter((F.col("docs") > cluster_docs) | (F.col("words") > cluster_words)).select("cluster")
    large = common.cut(large, spark, "large")
    any_large = large.limit(1).count() > 0
    # 3. links in clusters
    texts = common.may_be_in(base, "doc", marked.select("doc"), "maybe").filter("maybe").drop("maybe")
    members = marked.join(texts, "doc").select("cluster", "node", "set", "text", "registers")
    small = members.join(large, "cluster", "left_anti") if any_large else members
    found = (
        small.repartition("cluster").sortWithinPartitions("cluster").mapInArrow(_searched(shingle, percent), "node long, component long")
    )
    # texts of one doc_id are one document
    several = named.groupBy("doc").agg(F.min(F.xxhash64("set")).alias("x"), F.max(F.xxhash64("set")).alias("y")).filter("x <> y").select("doc")
    any_several = several.limit(1).count() > 0
    if any_large or any_several:
        edges = found.toDF("a", "b")
        if any_large:
            big = members.join(large, "cluster", "left_semi")
            edges = edges.unionByName(_oversized(big, percent, shingle, block, block_bytes))
        if any_several:
            of = named.join(several, "doc").select("doc", "set").distinct().join(first, "set").select("doc", "node")
            edges = edges.unionByName(of.join(of.groupBy("doc").agg(F.min("node").alias("b")), "doc").select(F.col("node").alias("a"), "b"))
        found = common.connected_components(edges, spark)
    # the smallest doc_id of each component, and back to every row
    placed = common.cut(found.join(first.select("node", "rep"), "node"), spark, "placed")
    least = common.cut(placed.groupBy("component").agg(F.min("rep").alias("least")), spark, "least")
    whole = (
        sk.select("doc", "n", "set")
        .join(first, "set", "left")
        .join(placed.join(least, "component").select("node", "least"), "node", "left")
        .select(
            F.col("doc").alias("doc_id"),
            F.col("n").alias("n_shingles"),
            F.when(F.col("doc").isNotNull(), F.coalesce("least", "rep", "doc")).alias("component_id"),
        )
    )
    return whole.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_first(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with one document of each near-duplicate group, the smallest
    doc_id; all columns stay."""
    spark = docs.sparkSession
    name = common.free_name("_id", docs)
    # three uses below: written once, not computed again for each
    found = common.cut(components(docs, shingle, percent), spark, "components")
    gone = found.filter("NOT kept").select(F.col("doc_id").alias(name)).distinct()
    again = found.filter("kept AND n_shingles > 0 AND doc_id IS NOT NULL").groupBy(F.col("doc_id").alias(name)).count().filter("count > 1")
    doubted = common.cut(gone.withColumn("gone", F.lit(True)).unionByName(again.select(name, F.lit(False).alias("gone"))), spark, "doubted")
    # rows that the bitmap clears stay where they are; the others are exchanged
    flag = common.free_name("_maybe", docs)
    flagged = common.may_be_in(docs, "doc_id", doubted.select(name), flag)
    clear, rest = flagged.filter(~F.col(flag)).drop(flag), flagged.filter(F.col(flag)).drop(flag)
    rest = rest.join(doubted.filter("gone").select(name), F.col("doc_id") == F.col(name), "left_anti")
    twice = doubted.filter("NOT gone").select(name)
    if not twice.limit(1).count():
        return clear.unionByName(rest)
    wordy = F.coalesce(F.col("text").rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    single = rest.join(twice, F.col("doc_id") == F.col(name), "left_anti")
    double = rest.join(twice, F.col("doc_id") == F.col(name), "left_semi")
    return (
        clear.unionByName(single).unionByName(double.filter(~wordy)).unionByName(double.filter(wordy).dropDuplicates(["doc_id", "text"]))
    )


ORACLE = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT DISTINCT doc_id, md5(array_to_string(w[i : i + least(3, len(w)) - 1], ' ')) AS g
  FROM (SELECT doc_id, w, unnest(range(1, (len(w) - least(3, len(w)) + 2)::BIGINT)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (
  SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * c >= 85 * (a.n + b.n - c)),
r(x, y) AS (
  SELECT doc_id, doc_id FROM d UNION SELECT r.x, e.y FROM r JOIN e ON r.y = e.x),
m AS (SELECT x, min(y) AS c FROM r GROUP BY x)
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, c AS component_id, c = doc_id AS kept
FROM d LEFT JOIN n USING (doc_id) JOIN m ON m.x = doc_id
"""
