"""Hierarchical k-NN graph: small exact groups, layers of representatives, merge by search from above."""

from __future__ import annotations

import numpy as np

from shardgraph.operators.arrays import sq_distances
from shardgraph.operators.beams import batch_size, compact, distinct, padded, pair_distances, search_beams
from shardgraph.operators.builders.knn import knn_exact

#: Nodes of a layer that search it at once.
BATCH = 256


def knn_hier(ids: np.ndarray, x: np.ndarray, degree: int, working: int = 0, group: int = 64, reps: int = 8, **_) -> np.ndarray:
    """Degree: three quarters found by search, the rest reserved for symmetric edges."""
    n = len(x)
    r = min(degree, n - 1)
    if r <= 0:
        return np.full((n, 0), -1, np.int64)
    if n <= group:
        return knn_exact(ids, x, r)
    layers = [np.arange(n)]
    while len(layers[-1]) > group:
        top = layers[-1]
        layers.append(np.concatenate([top[a : a + group][:: max(1, group // reps)][:reps] for a in range(0, len(top), group)]))
    keep = max(1, (3 * r) // 4)
    upper: np.ndarray | None = None
    lists: list[np.ndarray] = []
    for nodes in reversed(layers):
        lists = [np.empty(0, np.int64)] * len(nodes)
        for a in range(0, len(nodes), group):
            part = np.arange(a, min(len(nodes), a + group))
            near = knn_exact(ids[nodes[part]], x[nodes[part]], keep)
            for i, row in zip(part.tolist(), near, strict=True):
                lists[i] = part[row]
        if upper is not None:
            place = {int(v): i for i, v in enumerate(nodes)}
            roots = np.array([place[int(v)] for v in upper])
            # links between groups come from the layer above, whose nodes are in this one as well
            for i, row in zip(roots.tolist(), above, strict=True):
                lists[i] = np.unique(np.r_[lists[i], roots[row]])
            xs, links, found = compact(x[nodes]), padded(lists), []
            step = min(BATCH, batch_size(len(nodes)))
            for a in range(0, len(nodes), step):
                part = np.arange(a, min(len(nodes), a + step))
                entry = roots[sq_distances(xs[part], xs[roots]).argmin(axis=1)]
                seen = search_beams(xs, links, entry[:, None], xs[part], max(working, 2 * r)).visited
                via = seen[:, :4]
                around = np.where(via[:, :, None] >= 0, links[via], -1).reshape(len(part), -1)
                cand = distinct(np.c_[seen, links[part], around])
                cand[cand == part[:, None]] = -1
                d, (row, col) = np.full(cand.shape, np.inf), np.nonzero(cand >= 0)
                d[row, col] = pair_distances(xs, cand[row, col], xs, part[row])
                best = np.take_along_axis(cand, np.lexsort((ids[nodes[cand]], d), axis=1)[:, :keep], axis=1)
                found += [b[b >= 0] for b in best]
            lists = found
        upper, above = nodes, [row for row in lists]
    back: list[list[int]] = [[] for _ in range(n)]
    for u, row in enumerate(lists):
        for v in row.tolist():
            back[v].append(u)
    out = np.full((n, r), -1, np.int64)
    for u in range(n):
        pool = dict.fromkeys(lists[u].tolist())
        for v in back[u]:
            if len(pool) == r:
                break
            pool.setdefault(v)
        out[u, : len(pool)] = list(pool)
    return out
