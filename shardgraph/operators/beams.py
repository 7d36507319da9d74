"""Best-first search of many queries at once: a step expands a node of each query in a few numpy calls."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np

#: Bytes of the visited marks of a batch of queries, components gathered at once, and queries in a batch.
SEEN_BYTES, PAIR_CELLS, BATCH = 64 << 20, 2_000_000, 512


class Beams(NamedTuple):
    """A row per query: nodes and distances by (distance, node), -1 and inf behind the last; expanded nodes in order."""

    node: np.ndarray
    dist: np.ndarray
    hops: np.ndarray
    dist_count: np.ndarray
    reads: np.ndarray
    visited: np.ndarray


def batch_size(n: int) -> int:
    return max(1, min(BATCH, SEEN_BYTES // max(n, 1)))


def compact(x: np.ndarray) -> np.ndarray:
    """``x`` in single precision where all squared distances stay exact, as they do for integers."""
    exact = not len(x) or (np.array_equal(x, np.floor(x)) and 4 * np.einsum("ij,ij->i", x, x).max() < 1 << 24)
    return np.ascontiguousarray(x, np.float32 if exact else np.float64)


def padded(lists: list[np.ndarray]) -> np.ndarray:
    """Neighbour lists as a matrix of distinct nodes, -1 behind the last of a row."""
    size = np.array([len(v) for v in lists], np.int64)
    out = np.full((len(lists), max(1, size.max(initial=0))), -1, np.int64)
    if size.sum():
        out[np.arange(out.shape[1])[None, :] < size[:, None]] = np.concatenate(lists)
    return out


def distinct(rows: np.ndarray) -> np.ndarray:
    """Each row sorted, repeated entries as -1."""
    rows = np.sort(rows, axis=1)
    rows[:, 1:][rows[:, 1:] == rows[:, :-1]] = -1
    return rows


def pair_distances(x: np.ndarray, at: np.ndarray, q: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Squared distances between ``x[at]`` and ``q[row]``, gathered block by block."""
    out = np.empty(len(at))
    step = max(1, PAIR_CELLS // max(1, x.shape[1]))
    for a in range(0, len(at), step):
        diff = x[at[a : a + step]] - q[row[a : a + step]]
        out[a : a + step] = np.einsum("ij,ij->i", diff, diff)
    return out


def _ranked(dist: np.ndarray, node: np.ndarray, m: int) -> np.ndarray:
    """Columns of the m first entries of each row by (distance, node)."""
    order = np.argsort(dist, axis=1, kind="stable")
    d = np.take_along_axis(dist, order, axis=1)
    tied = ((d[:, 1:] == d[:, :-1]) & np.isfinite(d[:, 1:])).any(axis=1)
    if tied.any():
        order[tied] = np.lexsort((node[tied], dist[tied]), axis=1)
    return order[:, :m]


def search_beams(x: np.ndarray, graph: np.ndarray, entries: np.ndarray, q: np.ndarray, beam: int, width: int = 1) -> Beams:
    """Every query expands the ``width`` nearest unexpanded nodes of its beam until none is left; ties by position.

    ``graph`` is a matrix of distinct neighbours with -1 behind the last; ``entries`` has a row of
    distinct nodes per query. Give at most ``batch_size`` queries at once.
    """
    b, n = len(q), len(x)
    beam = max(1, min(beam, n))
    seen = np.zeros((b, n), bool)
    seen[np.arange(b)[:, None], entries] = True
    first = pair_distances(x, entries.ravel(), q, np.repeat(np.arange(b), entries.shape[1])).reshape(entries.shape)
    order = _ranked(first, entries, beam)
    node, dist, done = np.full((b, beam), -1, np.int64), np.full((b, beam), np.inf), np.ones((b, beam), bool)
    got = order.shape[1]
    node[:, :got], dist[:, :got], done[:, :got] = np.take_along_axis(entries, order, axis=1), np.take_along_axis(first, order, axis=1), False
    hops, count, reads = np.zeros(b, np.int64), np.full(b, entries.shape[1], np.int64), np.zeros(b, np.int64)
    visited, active = np.full((b, 2 * beam), -1, np.int64), np.arange(b)
    while True:
        todo = ~done[active]
        some = todo.any(axis=1)
        active, todo = active[some], todo[some]
        if not len(active):
            return Beams(node, dist, hops, count, reads, visited)
        if reads.max() + width > visited.shape[1]:
            visited = np.c_[visited, np.full(visited.shape, -1, np.int64)]
        rows = np.arange(len(active))
        if width == 1:
            at = todo.argmax(axis=1)
            now = node[active, at]
            done[active, at] = True
            visited[active, reads[active]] = now
            reads[active] += 1
            near = graph[now]
        else:
            take = todo & (np.cumsum(todo, axis=1) <= width)
            r, c = np.nonzero(take)
            slot = (np.cumsum(take, axis=1) - 1)[r, c]
            near = np.full((len(active), width, graph.shape[1]), -1, np.int64)
            now = node[active[r], c]
            near[r, slot] = graph[now]
            near = distinct(near.reshape(len(active), -1))
            done[active[r], c] = True
            visited[active[r], reads[active[r]] + slot] = now
            reads[active] += take.sum(axis=1)
        hops[active] += 1
        fresh = (near >= 0) & ~seen[active[:, None], near]
        r, c = np.nonzero(fresh)
        if not len(r):
            continue
        new, of = near[r, c], active[r]
        seen[of, new] = True
        count[active] += fresh.sum(axis=1)
        far = np.full(near.shape, np.inf)
        far[r, c] = pair_distances(x, new, q, of)
        hit = fresh.any(axis=1)
        rows, on = rows[hit], active[hit]
        all_d, all_n = np.c_[dist[on], far[rows]], np.c_[node[on], np.where(fresh[rows], near[rows], -1)]
        all_done = np.c_[done[on], ~fresh[rows]]
        order = _ranked(all_d, all_n, beam)
        node[on], dist[on], done[on] = np.take_along_axis(all_n, order, axis=1), np.take_along_axis(all_d, order, axis=1), np.take_along_axis(all_done, order, axis=1)
