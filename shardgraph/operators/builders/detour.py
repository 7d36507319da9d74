"""Fixed-degree graph: k-NN edges ordered by their detours, with reverse edges."""

from __future__ import annotations

import numpy as np

from shardgraph.operators.builders.knn import knn_descent, knn_exact


#: Vectors up to which exact lists, matrix products that grow with their square, cost less than refining random ones, which gathers components.
EXACT_UNDER = 400_000


def detours(lists: np.ndarray, block: int = 64) -> np.ndarray:
    """For each edge u -> v at rank j: the ranks i < j whose neighbour w lists v before rank j, too.

    Such a w offers a path of two better-ranked legs. Ranks alone count; no distance is used.
    """
    n, width = lists.shape
    rank = np.arange(width)
    out = np.zeros((n, width), np.int32)
    for a in range(0, n, block):
        own = lists[a : a + block]
        theirs = lists[own]  # row, via i, its rank
        # position of v_j in the list of w_i, or width if it is not there
        match = theirs[:, :, None, :] == own[:, None, :, None]
        place = np.where(match.any(axis=3), match.argmax(axis=3), width)
        out[a : a + block] = ((place < rank[None, None, :]) & (rank[None, :, None] < rank[None, None, :])).sum(axis=1)
    return out


def knn_detour(ids: np.ndarray, x: np.ndarray, degree: int, working: int = 0, seed: int = 0, **_) -> np.ndarray:
    n = len(x)
    r, width = min(degree, n - 1), min(max(working, degree), n - 1)
    if r <= 0:
        return np.full((n, 0), -1, np.int64)
    base = knn_exact(ids, x, width) if n <= EXACT_UNDER else knn_descent(ids, x, width, width, seed=seed)
    order = np.argsort(detours(base), axis=1, kind="stable")  # fewest detours first, ties by rank
    kept = np.take_along_axis(base, order, axis=1)[:, :r]
    reverse: list[list[int]] = [[] for _ in range(n)]
    for j in range(r):  # better-ranked edges offer their reverse first
        for u, v in enumerate(kept[:, j].tolist()):
            reverse[v].append(u)
    rest = np.take_along_axis(base, order, axis=1)
    out = np.full((n, r), -1, np.int64)
    for u in range(n):
        half = kept[u, : (r + 1) // 2].tolist()
        pool = dict.fromkeys(half)
        for v in (*reverse[u], *kept[u].tolist(), *rest[u].tolist()):
            if len(pool) == r:
                break
            pool.setdefault(v)
        out[u, : len(pool)] = list(pool)
    return out
