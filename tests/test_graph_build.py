"""Occlusion at once is occlusion one by one."""

import numpy as np

from labelroute.index import graph


def test_occlusion_keeps_what_a_plain_loop_keeps():
    rng = np.random.default_rng(4)
    for n, m, alpha in ((0, 4, 1.0), (1, 4, 1.0), (60, 5, 1.0), (60, 60, 1.2), (40, 7, 1.0)):
        vecs = rng.integers(0, 3, (80, 4)).astype(float)  # copies and ties among them
        d = graph.distances(vecs[79], vecs[:n])
        order, kept = np.lexsort((np.arange(n), d)), []
        for i in order:
            if len(kept) < m and all(alpha * graph.distances(vecs[i], vecs[[x]])[0] > d[i] for x in kept):
                kept.append(int(i))
        assert graph.occlude(order, dict(enumerate(d.tolist())), vecs, m, alpha) == kept


def test_a_layer_has_the_links_of_a_plain_build_with_fewer_distances(monkeypatch):
    """A new node meets a full list whose members do not occlude each other: it is
    compared with them once, they are not compared with each other again."""
    rng = np.random.default_rng(5)
    vecs = rng.standard_normal((300, 24))
    vecs[40:44] = vecs[7]  # copies
    members, m, cap, ef, alpha = rng.permutation(300), 6, 12, 60, 1.2
    links, prunes = {int(members[0]): []}, 0
    for at in range(1, len(members)):
        v, before = int(members[at]), members[:at]
        d = graph.distances(vecs[v], vecs)
        near = before[np.lexsort((before, d[before]))][:ef]
        links[v] = graph.occlude(near, d, vecs, m, alpha)
        for u in links[v]:
            links[u].append(v)
            if len(links[u]) > cap:
                prunes += 1
                b = np.array(links[u])
                db = graph.distances(vecs[u], vecs)
                o = b[np.lexsort((b, db[b]))]
                keep = graph.occlude(o, db, vecs, cap, alpha)
                links[u] = (keep + [int(x) for x in o if int(x) not in keep])[: max(len(keep), cap // 2)]
    full, plain = [], graph._unoccluded
    monkeypatch.setattr(graph, "_unoccluded", lambda *a: full.append(1) or plain(*a))
    assert graph._layer(members, vecs, m, cap, ef, alpha) == links
    assert len(full) < 299 + prunes / 2
