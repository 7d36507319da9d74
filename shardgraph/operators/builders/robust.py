"""Occlusion-pruned graph, built by searching from the medoid."""

from __future__ import annotations

import numpy as np

from shardgraph.operators.arrays import sq_distances
from shardgraph.operators.beams import batch_size, compact, distinct, pair_distances, search_beams

#: Nodes whose searches see the same graph: a share of the nodes, so that few miss each other, and a bound of memory.
TOGETHER, SHARE = 256, 16
#: Components of candidates that a prune gathers at once.
PRUNE_CELLS = 4_000_000


def medoid(x: np.ndarray) -> int:
    return int(sq_distances(x, x.mean(axis=0, keepdims=True))[:, 0].argmin())


def prune(nodes: np.ndarray, cand: np.ndarray, x: np.ndarray, degree: int, alpha: float, ids: np.ndarray) -> np.ndarray:
    """A row per node: its nearest candidate first; one that is ``alpha`` times nearer to a kept neighbour than to the node is occluded.

    ``cand`` and the result have -1 where there is none.
    """
    out = np.full((len(nodes), degree), -1, np.int64)
    width = max(4 * degree, 64)
    step = max(1, PRUNE_CELLS // (x.shape[1] * min(width, cand.shape[1]) + width * width))
    for a in range(0, len(nodes), step):
        u = nodes[a : a + step]
        c = distinct(cand[a : a + step])
        c[c == u[:, None]] = -1
        d = np.full(c.shape, np.inf)
        r, at = np.nonzero(c >= 0)
        d[r, at] = pair_distances(x, c[r, at], x, u[r])
        order = np.lexsort((ids[c], d), axis=1)[:, :width]
        c, d = np.take_along_axis(c, order, axis=1), np.take_along_axis(d, order, axis=1)
        alive = c >= 0
        filled = int(alive.sum(axis=1).max(initial=0))
        c, d, alive = c[:, :filled], d[:, :filled], alive[:, :filled]
        y = x[c]
        norm = np.einsum("ijk,ijk->ij", y, y)
        between = np.maximum(norm[:, :, None] + norm[:, None, :] - 2 * (y @ y.transpose(0, 2, 1)), 0) * (alpha * alpha)
        kept = np.zeros(len(u), np.int64)
        for i in range(filled):
            on = np.flatnonzero(alive[:, i] & (kept < degree))
            if len(on):
                out[a + on, kept[on]] = c[on, i]
                kept[on] += 1
                alive[on] &= between[on, i] > d[on]
    return out


def robust(ids: np.ndarray, x: np.ndarray, degree: int, working: int = 0, alpha: float = 1.2, seed: int = 0, **_) -> np.ndarray:
    """Two passes over all nodes in seeded order, alpha 1 and then ``alpha``; back edges are pruned when a node holds twice the degree, and at the end.

    A batch of nodes searches the graph that the batches before it left.
    """
    n = len(x)
    r = min(degree, n - 1)
    if r <= 0:
        return np.full((n, 0), -1, np.int64)
    rng = np.random.default_rng(seed)
    start, beam = medoid(x), max(working, degree)
    x = compact(x)
    graph, size = np.full((n, 2 * r), -1, np.int64), np.full(n, r)
    for u in range(n):
        graph[u, :r] = (rng.choice(n - 1, r, replace=False) + u + 1) % n
    step = min(TOGETHER, batch_size(n), max(8, n // SHARE))
    for a in (1.0, alpha):
        order = rng.permutation(n)
        for at in range(0, n, step):
            us = order[at : at + step]
            seen = search_beams(x, graph, np.full((len(us), 1), start), x[us], beam)
            near = prune(us, np.c_[seen.visited[:, : seen.reads.max()], graph[us]], x, r, a, ids)
            graph[us] = -1
            graph[us, :r], size[us] = near, (near >= 0).sum(axis=1)
            row, col = np.nonzero(near >= 0)
            src, dst = us[row], near[row, col]
            by = np.argsort(dst, kind="stable")
            src, dst = src[by], dst[by]
            new = ~(graph[dst] == src[:, None]).any(axis=1)
            src, dst = src[new], dst[new]
            nodes, begin, more = np.unique(dst, return_index=True, return_counts=True)
            slot = np.arange(len(dst)) - np.repeat(begin, more)
            full = size[nodes] + more > 2 * r
            fits = np.repeat(~full, more)
            graph[dst[fits], size[dst[fits]] + slot[fits]] = src[fits]
            size[nodes[~full]] += more[~full]
            if full.any():
                v = nodes[full]
                cand = np.full((len(v), more[full].max()), -1, np.int64)
                cand[np.repeat(np.arange(len(v)), more[full]), slot[~fits]] = src[~fits]
                near = prune(v, np.c_[graph[v], cand], x, r, a, ids)
                graph[v] = -1
                graph[v, :r], size[v] = near, (near >= 0).sum(axis=1)
    over = np.flatnonzero(size > r)
    for at in range(0, len(over), 4096):
        v = over[at : at + 4096]
        near = prune(v, graph[v], x, r, alpha, ids)
        graph[v] = -1
        graph[v, :r] = near
    return graph[:, :r].copy()
