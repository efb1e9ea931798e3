"""Coarse-cell inverted file of one shard, and hyperplane buckets."""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np

from .graph import Stats, distances


@dataclass
class Cells:
    ids: np.ndarray
    bits: np.ndarray
    vecs: np.ndarray
    centres: np.ndarray
    cell: np.ndarray

    def dump(self) -> bytes:
        return pickle.dumps(self, protocol=5)

    @property
    def link_bytes(self) -> int:
        return 4 * len(self.ids)


def build(ids, vecs, bits, per_cell: int = 32, rounds: int = 6) -> Cells:
    ids, vecs, bits = np.asarray(ids, np.int64), np.asarray(vecs, np.float64), np.asarray(bits, np.int64)
    k = max(1, int(np.sqrt(len(ids))) if len(ids) > per_cell else 1)
    rng = np.random.default_rng(0)
    c = vecs[rng.choice(len(ids), k, replace=False)].copy() if len(ids) else vecs[:0]
    near = np.zeros(len(ids), np.int64)
    for _ in range(rounds if len(ids) else 0):
        near = np.argmin((c * c).sum(1)[None, :] - 2 * vecs @ c.T, 1)
        for j in range(k):
            if (near == j).any():
                c[j] = vecs[near == j].mean(0)
    return Cells(ids, bits, vecs, c, near)


def search(g: Cells, q, qbits: int, k: int, ef: int, rule: str = "post", dead: frozenset = frozenset()):
    """Probes cells by distance until ``ef`` rows are seen and ``k`` match."""
    st, got = Stats(), []
    if not len(g.ids):
        return [], st
    q = np.asarray(q, np.float64)
    for j in np.argsort(distances(q, g.centres), kind="stable"):
        at = np.flatnonzero(g.cell == j)
        st.expanded += len(at)
        if rule == "pre":
            at = at[(g.bits[at] & qbits) == qbits]
        d = distances(q, g.vecs[at])
        st.distances += len(at)
        for x, i in zip(d.tolist(), at.tolist(), strict=True):
            if g.bits[i] & qbits == qbits and int(g.ids[i]) not in dead:
                got.append((x, int(g.ids[i])))
        if st.expanded >= ef and len(got) >= k:
            break
    return sorted(got)[:k], st


@dataclass
class Buckets:
    """Hyperplane tables: a row's bucket in each is the signs of its projections."""

    ids: np.ndarray
    bits: np.ndarray
    vecs: np.ndarray
    normals: np.ndarray  # tables x planes x dimensions
    buckets: list  # per table: bucket -> rows

    def dump(self) -> bytes:
        return pickle.dumps(self, protocol=5)

    @property
    def link_bytes(self) -> int:
        return 4 * len(self.ids) * len(self.buckets)


def _signs(normals: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Buckets, tables x rows."""
    return ((np.einsum("tpd,nd->tnp", normals, x) >= 0) << np.arange(normals.shape[1])).sum(2)


def build_buckets(ids, vecs, bits, tables: int = 16, per_bucket: int = 32) -> Buckets:
    ids, vecs, bits = np.asarray(ids, np.int64), np.asarray(vecs, np.float64), np.asarray(bits, np.int64)
    count = max(1, int(np.log2(max(2, len(ids) / per_bucket))))
    normals = np.stack([np.array(planes(vecs.shape[1], count, t)) for t in range(tables)])
    out = []
    for row in _signs(normals, vecs):
        order = np.argsort(row, kind="stable")
        keys, starts = np.unique(row[order], return_index=True)
        out.append(dict(zip(keys.tolist(), np.split(order, starts[1:]), strict=True)) if len(keys) else {})
    return Buckets(ids, bits, vecs, normals, out)


def search_buckets(g: Buckets, q, qbits: int, k: int, ef: int, rule: str = "post", dead: frozenset = frozenset()):
    """Looks up the query's bucket in every table, then those one sign away,
    until ``ef`` rows are seen and ``k`` match."""
    st = Stats()
    if not len(g.ids):
        return [], st
    q = np.asarray(q, np.float64)
    own, seen, got = _signs(g.normals, q[None])[:, 0], np.zeros(len(g.ids), bool), []
    for flip in (0, *(1 << p for p in range(g.normals.shape[1]))):
        for t, rows in enumerate(g.buckets):
            at = rows.get(int(own[t]) ^ flip, np.empty(0, np.int64))
            at = at[~seen[at]]
            seen[at] = True
            st.expanded += len(at)
            if rule == "pre":
                at = at[(g.bits[at] & qbits) == qbits]
            st.distances += len(at)
            for d, i in zip(distances(q, g.vecs[at]).tolist(), at.tolist(), strict=True):
                if g.bits[i] & qbits == qbits and int(g.ids[i]) not in dead:
                    got.append((d, int(g.ids[i])))
        if st.expanded >= ef and len(got) >= k:
            break
    return sorted(got)[:k], st


def planes(dim: int, bits: int, seed: int = 0) -> list[list[float]]:
    return np.random.default_rng(seed).normal(size=(bits, dim)).round(6).tolist()
