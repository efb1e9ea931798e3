"""Proximity-graph kernels in numpy: build, and search under four rules.

Graphs are built per shard, so a shard's vectors fit one task.  Candidates of a
node are its exact nearest nodes among those inserted before it (blocked matrix
products rule out the others), in the order of a hash of the id, which makes builds deterministic.
A neighbour is kept only if it is nearer to the node than (``alpha`` times) to
any neighbour already kept.
"""

from __future__ import annotations

import bisect
import heapq
import math
import pickle
import time
from dataclasses import dataclass, replace

import numpy as np
import xxhash


@dataclass
class Params:
    m: int = 16
    ef_build: int = 200
    alpha: float = 1.0
    layered: bool = True
    gamma: int = 1  # edges per node are gamma * m on the ground layer
    dense: bool = False  # the ground layer's edges are the nearest nodes, none occluded
    m_beta: int | None = None  # of a dense node's edges, the nearest that are always stored


@dataclass
class Graph:
    ids: np.ndarray
    bits: np.ndarray
    vecs: np.ndarray
    layers: list  # per layer: list of neighbour arrays (empty above a node's level)
    entry: int
    entries: dict | None = None  # group bits -> entry nodes (label-navigating graph)

    def dump(self) -> bytes:
        return pickle.dumps(self, protocol=5)

    @staticmethod
    def load(blob: bytes) -> Graph:
        return pickle.loads(blob)

    @property
    def link_bytes(self) -> int:
        return sum(4 * len(x) for layer in self.layers for x in layer)


def _hash(i: int) -> int:
    return xxhash.xxh64_intdigest(int(i).to_bytes(8, "little", signed=True))


def distances(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    d = x - q
    return np.einsum("ij,ij->i", d, d)


def _unoccluded(near: np.ndarray, far: np.ndarray, m: int, alpha: float) -> list[int]:
    """Places, among candidates in order of their distances ``far``, of those that
    no kept one occludes, ``m`` at most."""
    kept: list[int] = []
    places = np.arange(len(near))
    while len(kept) < m and len(places):
        kept.append(int(places[0]))
        free = alpha * distances(near[0], near[1:]) > far[1:]
        near, far, places = near[1:][free], far[1:][free], places[1:][free]
    return kept


def occlude(order: np.ndarray, dist: np.ndarray, vecs: np.ndarray, m: int, alpha: float) -> list[int]:
    """Of candidates by distance, those no kept neighbour occludes, ``m`` at most."""
    order = np.asarray(order, np.int64)
    if not len(order):
        return []
    kept = _unoccluded(vecs[order], np.array([dist[i] for i in order.tolist()]), m, alpha)
    return order[kept].tolist()


def _nearest_before(x: np.ndarray, ids: np.ndarray, ef: int):
    """Of each row of ``x`` but the first: the ``ef`` nearest earlier rows and their
    distances, in order.  Matrix products rule out what is farther than the
    ``ef``-th by more than their error; the rest is evaluated term by term."""
    norms = np.einsum("ij,ij->i", x, x)
    slack = 1e-12 * x.shape[1] * norms.max(initial=0.0)
    for lo in range(1, len(x), 256):
        hi = min(lo + 256, len(x))
        about = None
        if hi - 1 > ef:
            about = norms[None, :hi] - 2 * (x[lo:hi] @ x[:hi].T)  # less the norm of the row itself
        for at in range(lo, hi):
            some = np.arange(at)
            if at > ef:
                row = about[at - lo, :at]
                bound = np.partition(row, ef - 1)[ef - 1] + slack
                if np.isfinite(bound):
                    some = np.flatnonzero(row <= bound)
            d = distances(x[at], x[some])
            o = np.lexsort((ids[some], d))[:ef]
            yield at, some[o], d[o]


def _unoccluded_each(x: np.ndarray, near: list, far: list, m: int, alpha: float) -> list[list[int]]:
    """``_unoccluded`` of many candidate lists (places in ``x``), a step of all at once.
    Matrix products decide what their error leaves no doubt about."""
    kept: list[list[int]] = [[] for _ in near]
    sizes = np.array([len(c) for c in near], np.int64)
    if not sizes.sum():
        return kept
    inside = np.arange(sizes.max())[None, :] < sizes[:, None]
    cand, dist = np.zeros(inside.shape, np.int64), np.full(inside.shape, np.inf)
    cand[inside], dist[inside] = np.concatenate(near), np.concatenate(far)
    there, row, free = x[cand], np.arange(len(near)), inside.copy()
    with np.errstate(invalid="ignore", over="ignore"):  # what is not finite stays in doubt
        norms = np.einsum("ijk,ijk->ij", there, there)
        slack = 1e-12 * x.shape[1] * norms.max() * max(alpha, 1.0)
        for _ in range(m):
            at = free.argmax(1)
            live = free[row, at]
            if not live.any():
                break
            for r, i in zip(np.flatnonzero(live).tolist(), at[live].tolist(), strict=True):
                kept[r].append(i)
            centre = there[row, at]
            free[row, at] = False
            gap = alpha * (norms + norms[row, at][:, None] - 2 * np.matmul(there, centre[:, :, None])[:, :, 0]) - dist
            i, j = np.nonzero(free & ~(np.abs(gap) > slack))
            free &= gap > slack
            between = there[i, j] - centre[i]
            free[i, j] = alpha * np.einsum("ij,ij->i", between, between) > dist[i, j]
    return kept


#: Candidates that are compared at a time.
_PAIRS = 8_192


def _layer(members: np.ndarray, vecs: np.ndarray, m: int, cap: int, ef: int, alpha: float) -> dict[int, list[int]]:
    """Links of each member, all of them kept within the order of insertion.

    What a node links to at its insertion does not depend on other links, and a list
    changes only by the nodes that link to it, in their order: so all lists take
    their next node at once.  A full list whose members do not occlude each other,
    in order of distance, is ``settled``: a new node is compared with its members alone."""
    n, x = len(members), vecs[members]
    links, far = np.zeros((n, cap), np.int64), np.zeros((n, cap))  # places in ``members``
    size, settled = np.zeros(n, np.int64), np.zeros(n, bool)
    to, new, dist = [np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0)]

    def link(block) -> None:
        kept = _unoccluded_each(x, [b[1] for b in block], [b[2] for b in block], m, alpha)
        for (v, near, d), k in zip(block, kept, strict=True):
            size[v] = len(k)
            links[v, : len(k)], far[v, : len(k)] = near[k], d[k]
            to.append(near[k])
            new.append(np.full(len(k), v))
            dist.append(d[k])

    block: list = []
    for one in _nearest_before(x, members, ef):
        block.append(one)
        if len(block) * min(ef, one[0]) >= _PAIRS:
            link(block)
            block = []
    link(block)

    to, new, dist = np.concatenate(to), np.concatenate(new), np.concatenate(dist)
    turn = np.argsort(to, kind="stable")
    turn = turn[np.argsort(_rank_in_run(to[turn]), kind="stable")]
    bounds = np.append(0, np.cumsum(np.bincount(_rank_in_run(np.sort(to)))))
    for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        now = turn[lo:hi]  # at most one node for every list
        u, v, d = to[now], new[now], dist[now]
        room = size[u] < cap
        links[u[room], size[u[room]]], far[u[room], size[u[room]]] = v[room], d[room]
        size[u[room]] += 1
        settled[u[room]] = False
        u, v, d = u[~room], v[~room], d[~room]
        calm = settled[u]
        left = np.concatenate([np.flatnonzero(~calm), np.flatnonzero(calm)[_settle(u[calm], v[calm], d[calm], links, far, size, members, x, cap, alpha)]])
        if not len(left):
            continue
        nodes, at = [], []
        for i in left.tolist():
            b, db = np.append(links[u[i]], v[i]), np.append(far[u[i]], d[i])
            o = np.lexsort((members[b], db))
            nodes.append(b[o])
            at.append(db[o])
        for i, b, db, kept in zip(u[left].tolist(), nodes, at, _unoccluded_each(x, nodes, at, cap, alpha), strict=True):
            settled[i] = len(kept) >= cap // 2
            if len(kept) < cap // 2:
                rest = np.ones(len(b), bool)
                rest[kept] = False
                kept = (kept + np.flatnonzero(rest).tolist())[: cap // 2]
            size[i] = len(kept)
            links[i, : len(kept)], far[i, : len(kept)] = b[kept], db[kept]
    return {int(i): members[links[v, : size[v]]].tolist() for v, i in enumerate(members)}


def _rank_in_run(x: np.ndarray) -> np.ndarray:
    """Of each of sorted values: how many equal ones stand before it."""
    return np.arange(len(x)) - np.searchsorted(x, x, side="left")


def _settle(u, v, d, links, far, size, members, x, cap: int, alpha: float) -> np.ndarray:
    """Puts each ``v`` into the full settled list of its ``u``, unless it is too far or
    occluded; which of them leave too few in the list, which is then as it was."""
    if not len(u):
        return np.empty(0, np.int64)
    b, db = links[u], far[u]
    before = (db < d[:, None]) | ((db == d[:, None]) & (members[b] < members[v][:, None]))
    some = np.flatnonzero(~before.all(1))
    b, db, before = b[some], db[some], before[some]
    apart = x[b] - x[v[some]][:, None, :]
    apart = apart.reshape(-1, x.shape[1])
    apart = alpha * np.einsum("ij,ij->i", apart, apart).reshape(b.shape)
    fine = (~before | (apart > d[some][:, None])).all(1)
    few = []
    for i, bi, dbi, first, stay in zip(some[fine].tolist(), b[fine], db[fine], before[fine].sum(1).tolist(), (before | (apart > db))[fine], strict=True):
        after = np.flatnonzero(stay[first:]) + first
        keep = np.concatenate([bi[:first], [v[i]], bi[after]])[:cap]
        if len(keep) < cap // 2:
            few.append(i)
            continue
        size[u[i]] = len(keep)
        links[u[i], : len(keep)], far[u[i], : len(keep)] = keep, np.concatenate([dbi[:first], [d[i]], dbi[after]])[:cap]
    return np.array(few, np.int64)


def _dense_layer(order: np.ndarray, vecs: np.ndarray, p: Params) -> list[np.ndarray]:
    """``gamma * m`` nearest nodes of every node, blind to labels, and its nearest
    earlier node both ways, which keeps the graph in one piece.

    With ``m_beta`` only the nearest ``m_beta`` are all stored; of the others those
    that a stored one leads to in one more step are left out."""
    n, most = len(vecs), min(p.m * p.gamma, len(vecs) - 1)
    links, earlier = np.empty((n, max(most, 0)), np.int32), np.full(n, -1, np.int64)
    place = np.empty(n, np.int64)
    place[order] = np.arange(n)
    norms = (vecs * vecs).sum(1)
    for lo in range(0, n, 512):
        d = norms[None, :] + norms[lo : lo + 512, None] - 2 * vecs[lo : lo + 512] @ vecs.T
        for i, row in enumerate(d, lo):
            row[i] = np.inf
            near = np.argpartition(row, most - 1)[:most] if most else np.empty(0, np.int64)
            links[i] = near[np.lexsort((near, row[near]))]
            if place[i]:
                before = order[: place[i]]
                earlier[i] = before[np.argmin(row[before])]
    more: list[list[int]] = [[] for _ in range(n)]  # beside the nearest
    for i, back in enumerate(earlier.tolist()):
        if back >= 0 and back not in links[i]:
            more[i].append(back)
    for i in order.tolist():
        back = int(earlier[i])
        if back >= 0 and i not in more[back] and i not in links[back]:
            more[back].append(i)
    if p.m_beta is None or p.m_beta >= most:
        return [np.concatenate([x, np.array(y, np.int32)]) for x, y in zip(links, more, strict=True)]
    stored, reached = links[:, : p.m_beta], np.full(n, -1, np.int64)  # of every node, whatever else is left out
    pruned = []
    for i, x in enumerate(links):
        kept, rest = x[: p.m_beta].tolist(), x[p.m_beta :]
        reached[stored[x[: p.m_beta]]] = i
        while len(rest := rest[reached[rest] != i]):
            y, rest = int(rest[0]), rest[1:]
            kept.append(y)
            reached[stored[y]] = i
        pruned.append(np.array(kept + more[i], np.int32))
    return pruned


def build(ids, vecs, bits, p: Params) -> Graph:
    ids, vecs, bits = np.asarray(ids, np.int64), np.asarray(vecs, np.float64), np.asarray(bits, np.int64)
    n = len(ids)
    hashes = [_hash(i) for i in ids]
    order = np.array(sorted(range(n), key=lambda i: (hashes[i], ids[i])), np.int64)
    if p.layered and p.m > 1:
        unit = 1 / math.log(p.m)
        level = np.array([min(8, int(-math.log(((h >> 11) + 1) / 2.0**53) * unit)) for h in hashes], np.int64)
    else:
        level = np.zeros(n, np.int64)
    layers = []
    for l in range(int(level.max(initial=0)) + 1):  # noqa: E741
        members = order[level[order] >= l]
        if l == 0 and p.dense:
            layers.append(_dense_layer(order, vecs, p))
            continue
        per, cap = (p.m * p.gamma, 2 * p.m * p.gamma) if l == 0 else (p.m, p.m)
        links = _layer(members, vecs, per, cap, max(p.ef_build, per), p.alpha)
        layers.append([np.array(links.get(i, []), np.int32) for i in range(n)])
    top = order[level[order] == level.max(initial=0)]
    return Graph(ids, bits, vecs, layers, int(top[0]) if n else -1)


def build_label_graph(ids, vecs, bits, p: Params, cross: int = 4) -> Graph:
    """One subgraph per exact label set, joined to its minimal supersets.

    A query enters the minimal sets that contain its labels; whatever it visits
    from there matches, and every match can be reached.
    """
    ids, vecs, bits = np.asarray(ids, np.int64), np.asarray(vecs, np.float64), np.asarray(bits, np.int64)
    links: list[list[int]] = [[] for _ in ids]
    sets = sorted(set(bits.tolist()))
    where = {b: np.flatnonzero(bits == b) for b in sets}
    for b in sets:
        m = where[b]
        order = m[np.argsort([_hash(i) for i in ids[m]], kind="stable")]
        for v, near in _layer(order, vecs, p.m, 2 * p.m, p.ef_build, p.alpha).items():
            links[v] += near
    entries = {}
    for b in sets:
        above = [s for s in sets if s != b and s & b == b]
        minimal = [s for s in above if not any(t != s and t & b == b and t & s == t for t in above)]
        for s in minimal:
            target = where[s]
            there = vecs[target]
            for v in where[b]:
                d = distances(vecs[v], there)
                near = np.arange(len(d))
                if len(d) > cross and np.isfinite(far := np.partition(d, cross - 1)[cross - 1]):
                    near = np.flatnonzero(d <= far)
                links[v] += target[near[np.argsort(d[near], kind="stable")[:cross]]].tolist()
        m = where[b]
        entries[b] = int(m[np.argmin(distances(vecs[m].mean(0), vecs[m]))])
    layer = [np.array(list(dict.fromkeys(x)), np.int32) for x in links]
    return Graph(ids, bits, vecs, [layer], entries.get(0, next(iter(entries.values()), -1)), entries)


def minimal_entries(g: Graph, q: int) -> list[int]:
    over = [s for s in g.entries if s & q == q]
    return [g.entries[s] for s in over if not any(t != s and t & q == q and t & s == t for t in over)]


@dataclass
class Stats:
    expanded: int = 0
    distances: int = 0
    matched: int = 0


def search(g: Graph, q: np.ndarray, qbits: int, k: int, ef: int, rule: str = "post", dead: frozenset = frozenset()):
    """(distance, id) of up to ``k`` matches, and counters.

    ``post``: mismatches are walked through and never returned; ``pre``:
    mismatches are dropped on sight; ``twohop``: a mismatch is replaced by its
    own neighbours; ``label``: a label-navigating graph from its minimal sets;
    ``next``: nodes are taken one at a time in growing distance until k match.
    Deleted ids (``dead``) count as mismatches.
    """
    return sweep(g, q, qbits, k, (ef,), rule, dead)[ef][:2]


def _starts(g: Graph, q: np.ndarray, qbits: int, rule: str, st: Stats) -> list[int]:
    """Nodes of the ground layer from which a walk starts."""
    if rule == "label":
        return minimal_entries(g, qbits)
    if len(g.layers) < 2:
        return [g.entry]
    at, d = g.entry, float(distances(q, g.vecs[[g.entry]])[0])
    for layer in reversed(g.layers[1:]):
        while True:
            near = layer[at]
            if not len(near):
                break
            ds = distances(q, g.vecs[near])
            st.distances += len(near)
            i = int(np.argmin(ds))
            if ds[i] >= d:
                break
            at, d = int(near[i]), float(ds[i])
    return [at]


def sweep(g: Graph, q: np.ndarray, qbits: int, k: int, beams: tuple[int, ...], rule: str = "post", dead: frozenset = frozenset()) -> dict:
    """By beam: the answers and counters of ``search``, and the seconds it takes.

    A walk takes nodes in one order whatever its beam, which only says when it
    ends, so a narrower one is the start of a wider one: all are one walk."""
    began, st = time.perf_counter(), Stats()
    if g.entry < 0:
        return {ef: ([], st, 0.0) for ef in beams}
    q = np.asarray(q, np.float64)
    ok = (g.bits & qbits) == qbits
    if dead:
        ok = ok & ~np.isin(g.ids, list(dead))
    if rule == "next":
        got = []
        for d, i in neighbours(g, q, st):
            st.expanded += 1
            if ok[i]:
                st.matched += 1
                got.append((d, int(g.ids[i])))
                if len(got) == k:
                    break
        return {ef: (sorted(got), st, time.perf_counter() - began) for ef in beams}
    dist = lambda at: distances(q, g.vecs[at])
    start = _starts(g, q, qbits, rule, st)
    ground, met, fits = g.layers[0], bytearray(len(g.ids)), ok.tobytes()
    seen = np.frombuffer(met, bool)  # the same marks: bytes are quicker for few nodes, numpy for many
    open_: list[tuple[float, int]] = []
    best: list[tuple[float, int]] = []  # the nearest matches in order, as many as the widest beam needs
    ends = [(ef, k if rule == "post" else max(k, ef), ef if rule == "post" else 0) for ef in sorted(set(beams))]
    _ef, need, least = ends[-1]
    drops, out = rule in ("pre", "twohop"), {}

    def admit(nodes: np.ndarray) -> None:
        if many := len(nodes) > 48:
            nodes = nodes[~seen[nodes]]
            seen[nodes] = True
        else:
            nodes = [x for x in nodes.tolist() if not met[x]]
            for x in nodes:
                met[x] = 1
        if not len(nodes):
            return
        st.distances += len(nodes)
        far = dist(nodes)
        if rule == "twohop":
            for i in nodes.tolist() if many else nodes:
                if not fits[i]:
                    two = ground[i]
                    two = two[ok[two] & ~seen[two]]
                    if len(two):
                        admit(two)
        if many:
            good = ok[nodes]
            st.matched += int(good.sum())
            if drops:
                nodes, far = nodes[good], far[good]
            if len(best) >= need and st.expanded >= least:
                near = far <= best[-1][0]  # of the others, none is an answer or is walked
                nodes, far = nodes[near], far[near]
            nodes = nodes.tolist()
        for d, i in zip(far.tolist(), nodes, strict=True):
            if fits[i]:
                st.matched += not many
                if len(best) < need:
                    bisect.insort(best, (d, int(g.ids[i])))
                elif d <= best[-1][0]:
                    bisect.insort(best, (d, int(g.ids[i])))
                    best.pop()
            elif drops:
                continue
            heapq.heappush(open_, (d, i))

    if rule in ("pre", "twohop"):
        # a filtered walk starts from the entry even if that does not match
        for s in start:
            seen[s] = True
            st.distances += 1
            d = float(dist([s])[0])
            heapq.heappush(open_, (d, s))
            if ok[s]:
                bisect.insort(best, (d, int(g.ids[s])))
    else:
        admit(np.asarray(start, np.int64))
    while open_:
        d, i = heapq.heappop(open_)
        while ends and len(best) >= ends[0][1] and d > best[ends[0][1] - 1][0] and st.expanded >= ends[0][2]:
            out[ends.pop(0)[0]] = best[:k], replace(st), time.perf_counter() - began
        if not ends:
            break
        st.expanded += 1
        admit(ground[i])
    for ef, _need, _least in ends:
        out[ef] = best[:k], replace(st), time.perf_counter() - began
    return out


#: Query and node pairs whose marks one walk of many queries holds at once.
_MARKS = 1 << 21
#: Nodes of one group, of which the nearest open one is known.
_GROUP = 128
#: Queries that are worth a walk of many at once.
_MANY = 4


def sweep_many(g: Graph, qs: np.ndarray, qbits: np.ndarray, k: int, beams: tuple[int, ...], rule: str = "post", dead: frozenset = frozenset()) -> list[dict]:
    """``sweep`` of each query: their walks go side by side, a step of all at once.

    Walks do not touch each other, so answers and counters are those of ``sweep``;
    the seconds of a step are shared by the queries that are still on their way."""
    qs, qbits = np.asarray(qs, np.float64), np.asarray(qbits, np.int64)
    with np.errstate(invalid="ignore"):
        fine = g.entry >= 0 and qs.ndim == 2 and bool((np.abs(g.vecs) < 1e100).all() and (np.abs(qs) < 1e100).all())
    if rule == "next" or len(qs) < _MANY or not fine:
        return [sweep(g, q, int(b), k, beams, rule, dead) for q, b in zip(qs, qbits, strict=True)]
    links = _Links(g)
    step, out = min(256, max(_MANY, _MARKS // len(g.ids))), [{}] * len(qs)
    sets, each = np.unique(qbits, return_inverse=True)
    held = np.array([((g.bits & b) == b).sum() for b in sets])[each]
    turn = np.argsort(held, kind="stable")  # the rarer a set the longer its walk: long walks go together
    for lo in range(0, len(qs), step):
        some = turn[lo : lo + step]
        for at, walk in zip(some.tolist(), _walks(g, links, qs[some], qbits[some], k, beams, rule, dead), strict=True):
            out[at] = walk
    return out


class _Links:
    """The ground layer as one array."""

    def __init__(self, g: Graph):
        self.size = np.array([len(x) for x in g.layers[0]], np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.to = np.concatenate([np.asarray(x, np.int64) for x in g.layers[0]])

    def of(self, rows: np.ndarray, nodes: np.ndarray):
        """The neighbours of each node, each with the row of the node."""
        n = self.size[nodes]
        at = np.arange(n.sum()) + np.repeat(self.start[nodes] - np.cumsum(n) + n, n)
        return np.repeat(rows, n), self.to[at]


def _walks(g: Graph, links: _Links, qs, qbits, k: int, beams, rule: str, dead: frozenset) -> list[dict]:
    clock, many, n = time.perf_counter(), len(qs), len(g.ids)
    ends = [(ef, k if rule == "post" else max(k, ef), ef if rule == "post" else 0) for ef in sorted(set(beams))]
    need = ends[-1][1]
    drops, out = rule in ("pre", "twohop"), [{} for _ in range(many)]
    groups = -(-n // _GROUP)
    wide = groups * _GROUP
    query = np.arange(many)  # which query a row is; rows that have ended go
    ok = (g.bits[None, :] & qbits[:, None]) == qbits[:, None]
    if dead:
        ok &= ~np.isin(g.ids, list(dead))
    seen, last = np.zeros((many, n), bool), np.empty((many, n), np.int32)
    open_ = np.full((many, wide), np.inf)  # distances of the open nodes
    nearest = np.full((many, groups), np.inf)  # of each group of them
    match = np.full((many, n), np.inf)  # distances of the matches that were met
    best = np.full((many, need), np.inf)  # the nearest of these in order
    expanded, made, matched = (np.zeros(many, np.int64) for _ in range(3))
    seconds, end = np.zeros(many), np.zeros(many, np.int64)
    least, rank = np.array([e[2] for e in ends]), np.array([e[1] - 1 for e in ends])

    def far_of(rows, nodes):
        far = np.empty(len(nodes))
        for lo in range(0, len(nodes), _PAIRS):
            d = g.vecs[nodes[lo : lo + _PAIRS]]
            d = d - qs[query[rows[lo : lo + _PAIRS]]]
            far[lo : lo + _PAIRS] = np.einsum("ij,ij->i", d, d)
        return far

    def push(rows, nodes, far):
        open_[rows, nodes] = far
        np.minimum.at(nearest.reshape(-1), rows * groups + nodes // _GROUP, far)

    def keep(rows, nodes, far):
        """Matches, by row."""
        match[rows, nodes] = far
        near = far < best[rows, -1]
        rows, far = rows[near], far[near]
        if not len(rows):
            return
        at = _rank_in_run(rows)
        some = rows[at == 0]
        new = np.full((len(some), int(at.max()) + 1), np.inf)
        new[np.searchsorted(some, rows), at] = far
        best[some] = np.sort(np.concatenate([best[some], new], axis=1), axis=1)[:, :need]

    def admit(rows, nodes, twice: bool):
        """Unseen nodes, by row and once in it."""
        seen[rows, nodes] = True
        made[:] += np.bincount(rows, minlength=len(made))
        fits = ok[rows, nodes]
        if rule == "twohop" and not twice and not fits.all():
            r, x = links.of(rows[~fits], nodes[~fits])
            free = ok[r, x] & ~seen[r, x]
            r, x = r[free], x[free]
            turn = np.arange(len(r), dtype=np.int32)
            last[r, x] = turn
            once = last[r, x] == turn
            if len(r):
                admit(r[once], x[once], True)
        if drops:  # a mismatch is counted, neither walked nor an answer
            rows, nodes = rows[fits], nodes[fits]
            far = far_of(rows, nodes)
            matched[:] += np.bincount(rows, minlength=len(matched))
            push(rows, nodes, far)
            keep(rows, nodes, far)
            return
        far = far_of(rows, nodes)
        push(rows, nodes, far)
        rows, nodes, far = rows[fits], nodes[fits], far[fits]
        matched[:] += np.bincount(rows, minlength=len(matched))
        keep(rows, nodes, far)

    def close(row: int, ef: int):
        found, bound = match[row], best[row, k - 1]
        at = np.flatnonzero(found <= bound) if np.isfinite(bound) else np.flatnonzero(np.isfinite(found))
        ids = g.ids[at]
        first = np.lexsort((ids, found[at]))[:k]
        answer = list(zip(found[at][first].tolist(), ids[first].tolist(), strict=True))
        out[query[row]][ef] = answer, Stats(int(expanded[row]), int(made[row]), int(matched[row])), float(seconds[row])

    rows, starts = [], []
    for i, (q, b) in enumerate(zip(qs, qbits.tolist(), strict=True)):
        st = Stats()
        for s in _starts(g, q, b, rule, st):
            rows.append(i)
            starts.append(s)
        made[i] += st.distances
    rows, starts = np.array(rows, np.int64), np.array(starts, np.int64)
    if drops:  # a filtered walk starts from the entry even if that does not match
        seen[rows, starts] = True
        made += np.bincount(rows, minlength=many)
        far, fits = far_of(rows, starts), ok[rows, starts]
        push(rows, starts, far)
        keep(rows[fits], starts[fits], far[fits])
    elif len(rows):
        admit(rows, starts, True)
    while True:
        seconds += (time.perf_counter() - clock) / len(query)
        clock = time.perf_counter()
        row = np.arange(len(query))
        group = nearest.argmin(1)
        inside = open_.reshape(len(query), groups, _GROUP)[row, group]
        slot = inside.argmin(1)
        d = inside[row, slot]
        while True:
            live = end < len(ends)
            at = np.minimum(end, len(ends) - 1)
            done = live & ((d > best[row, rank[at]]) & (expanded >= least[at]) | np.isinf(d))
            if not done.any():
                break
            for r in np.flatnonzero(done).tolist():
                close(r, ends[end[r]][0])
            end[done] += 1
        live = end < len(ends)
        if not live.any():
            return out
        if 4 * live.sum() <= 3 * len(live):
            query, ok, seen, last, open_, nearest, match, best = (x[live] for x in (query, ok, seen, last, open_, nearest, match, best))
            expanded, made, matched, seconds, end = (x[live] for x in (expanded, made, matched, seconds, end))
            group, slot, inside = group[live], slot[live], inside[live]
            row = np.arange(len(query))
            live = np.ones(len(query), bool)
        row, group, slot, inside = row[live], group[live], slot[live], inside[live]
        node = group * _GROUP + slot
        open_[row, node] = np.inf
        inside[np.arange(len(row)), slot] = np.inf
        nearest[row, group] = inside.min(1)
        expanded[row] += 1
        rows, nodes = links.of(row, node)
        fresh = ~seen[rows, nodes]
        rows, nodes = rows[fresh], nodes[fresh]
        if len(rows):
            admit(rows, nodes, False)


def neighbours(g: Graph, q: np.ndarray, st: Stats | None = None):
    """(distance, node) in (approximately) increasing distance, one at a time."""
    st = st or Stats()
    q = np.asarray(q, np.float64)
    seen = np.zeros(len(g.ids), bool)
    at, d = g.entry, float(distances(q, g.vecs[[g.entry]])[0])
    for layer in reversed(g.layers[1:]):  # down to the ground, nearer at each step
        while len(near := layer[at]):
            ds = distances(q, g.vecs[near])
            st.distances += len(near)
            i = int(np.argmin(ds))
            if ds[i] >= d:
                break
            at, d = int(near[i]), float(ds[i])
    open_ = [(d, at)]
    seen[at] = True
    while open_:
        d, i = heapq.heappop(open_)
        yield d, i
        near = [x for x in g.layers[0][i].tolist() if not seen[x]]
        if near:
            seen[near] = True
            st.distances += len(near)
            for dd, x in zip(distances(q, g.vecs[near]).tolist(), near, strict=True):
                heapq.heappush(open_, (dd, x))
