"""Exact k-nearest-neighbour lists, and their refinement from random lists."""

from __future__ import annotations

import numpy as np

from shardgraph.operators.arrays import sq_distances
from shardgraph.operators.beams import compact, pair_distances


def nearest(d: np.ndarray, ids: np.ndarray, r: int) -> np.ndarray:
    """Columns of the r smallest distances per row, ordered by (distance, id)."""
    r = min(r, d.shape[1])
    if r < d.shape[1]:
        worst = np.partition(d, r - 1, axis=1)[:, r - 1 : r]
        out = np.empty((len(d), r), np.int64)
        for i in range(len(d)):
            at = np.flatnonzero(d[i] <= worst[i])
            out[i] = at[np.lexsort((ids[at], d[i, at]))[:r]]
        return out
    return np.stack([np.lexsort((ids, row)) for row in d]) if len(d) else np.empty((0, r), np.int64)


#: Vectors on a side of a tile of distances.
TILE = 1024


def _hits(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``np.nonzero`` of a matrix with few hits: eight marks are looked at in one step."""
    flat = mask.ravel()
    end = len(flat) // 8 * 8
    near = (np.flatnonzero(flat[:end].view(np.uint64))[:, None] * 8 + np.arange(8)).ravel()
    return np.divmod(np.r_[near[flat[near]], end + np.flatnonzero(flat[end:])], mask.shape[1])


def _offer(dist: np.ndarray, at: np.ndarray, own: np.ndarray, new: np.ndarray, d: np.ndarray) -> None:
    """Puts vectors ``new`` at distances ``d`` into the lists of ``own``, which rises; all listed before are lower positions and win ties."""
    if not len(own):
        return
    first = np.r_[True, own[1:] != own[:-1]]
    rows, group = own[first], np.cumsum(first) - 1
    r, slot = dist.shape[1], np.arange(len(own)) - np.flatnonzero(first)[group]
    wide_d = np.full((len(rows), r + slot.max() + 1), np.inf, dist.dtype)
    wide_at = np.full(wide_d.shape, -1, np.int64)
    wide_d[:, :r], wide_at[:, :r] = dist[rows], at[rows]
    wide_d[group, r + slot], wide_at[group, r + slot] = d, new
    order = np.argsort(wide_d, axis=1, kind="stable")[:, :r]
    dist[rows], at[rows] = np.take_along_axis(wide_d, order, axis=1), np.take_along_axis(wide_at, order, axis=1)


def knn_exact(ids: np.ndarray, x: np.ndarray, degree: int, working: int = 0, tile: int = TILE, **_) -> np.ndarray:
    """Brute force in square tiles; the distances of a tile serve its rows and its columns, so each pair is computed once.

    Vectors meet the others by rising position, so later ones enter a list only if they are strictly
    nearer than its last; few are, and only these are sorted. Memory is a tile beside lists and vectors.
    """
    n, r = len(x), min(degree, len(x) - 1)
    if r <= 0:
        return np.full((n, 0), -1, np.int64)
    by = np.argsort(ids, kind="stable")  # positions rise with the ids, which decide ties
    x = compact(x[by])
    whole = x.dtype == np.float32
    if whole:  # (-2x, |x|^2, 1) by (y, 1, |y|^2): one product is the squared distance, exact for these integers
        norm = np.einsum("ij,ij->i", x, x)
        x = np.c_[x, np.ones(n, x.dtype), norm]
    dist, at = np.full((n, r), np.inf, x.dtype), np.full((n, r), -1, np.int64)
    tile = max(tile, r + 1)
    for a in range(0, n, tile):
        rows = np.arange(a, min(n, a + tile))
        left = np.c_[-2 * x[rows, :-2], norm[rows], np.ones(len(rows), x.dtype)] if whole else x[rows]
        for b in range(a, n, tile):
            cols = np.arange(b, min(n, b + tile))
            d = left @ x[cols].T if whole else sq_distances(left, x[cols])
            if a == b:
                np.fill_diagonal(d, np.inf)
            if a == b == 0:
                at[rows] = nearest(d, rows, r)
                dist[rows] = np.take_along_axis(d, at[rows], axis=1)
                continue
            i, j = _hits(d < dist[rows, -1:])
            _offer(dist, at, rows[i], cols[j], d[i, j])
            if a == b:
                continue
            if a == 0:  # the first that these vectors meet
                near = nearest(d.T, rows, r)
                at[cols], dist[cols] = near, np.take_along_axis(d.T, near, axis=1)
            else:
                i, j = _hits(d < dist[cols, -1])
                turn = np.argsort(j, kind="stable")
                i, j = i[turn], j[turn]
                _offer(dist, at, cols[j], rows[i], d[i, j])
    out = np.empty_like(at)
    out[by] = by[at]
    return out


def knn_descent(ids: np.ndarray, x: np.ndarray, degree: int, working: int = 0, iters: int = 12, sample: int = 12, seed: int = 0, block: int = 256, **_) -> np.ndarray:
    """Lists of ``max(degree, working)`` from random starts: neighbours of neighbours, forward and reverse, replace worse entries until few do."""
    n = len(x)
    r = min(max(degree, working), n - 1)
    if r <= 0:
        return np.full((n, 0), -1, np.int64)
    if n <= 4 * r:
        return knn_exact(ids, x, degree)
    x = compact(x)
    rng = np.random.default_rng(seed)
    lists = np.argsort(rng.random((n, min(n, 4 * r))), axis=1)[:, :r] if n <= 4 * r else (np.arange(n)[:, None] + 1 + np.stack([rng.choice(n - 1, r, replace=False) for _ in range(n)])) % n
    for _ in range(iters):
        take = min(sample, r)
        forward = lists[:, :take]
        reverse = np.full((n, take), -1, np.int64)
        src, dst = np.repeat(np.arange(n), take), forward.ravel()
        order = rng.permutation(len(src))
        src, dst = src[order], dst[order]
        by = np.argsort(dst, kind="stable")
        src, dst = src[by], dst[by]
        slot = np.arange(len(dst)) - np.searchsorted(dst, dst)
        m = slot < take
        reverse[dst[m], slot[m]] = src[m]
        around = np.where(np.c_[forward, reverse] < 0, np.arange(n)[:, None], np.c_[forward, reverse])
        changed, new = 0, np.empty_like(lists)
        for a in range(0, n, block):
            rows = np.arange(a, min(n, a + block))
            cand = np.c_[lists[rows], around[around[rows]].reshape(len(rows), -1), around[rows]]
            cand.sort(axis=1)
            fresh = np.c_[np.ones(len(rows), bool)[:, None], cand[:, 1:] != cand[:, :-1]] & (cand != rows[:, None])
            row, col = np.nonzero(fresh)
            d = np.full(cand.shape, np.inf)
            d[row, col] = pair_distances(x, cand[row, col], x, rows[row])
            at = np.argpartition(d, r - 1, axis=1)[:, :r] if r < d.shape[1] else np.broadcast_to(np.arange(d.shape[1]), d.shape)
            cand, d = np.take_along_axis(cand, at, axis=1), np.take_along_axis(d, at, axis=1)
            best = np.take_along_axis(cand, np.lexsort((ids[cand], d), axis=1), axis=1)
            changed += (np.sort(best, axis=1) != np.sort(lists[rows], axis=1)).sum()
            new[rows] = best
        lists = new
        if changed < 0.001 * n * r:
            break
    return lists[:, : min(degree, n - 1)]
