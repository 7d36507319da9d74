"""Centroids from a bounded sample: Lloyd rounds, seeding, and a two-level tree for many shards."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.operators.arrays import lists, matrix, sq_distances
from shardgraph.workspace import Workspace


#: Distances that a task holds at once: 32 MB, whatever the number of shards.
MATRIX_CELLS = 4_000_000
#: A sample is held on the driver up to this many components (128 MB), and a Lloyd round over it up to this many multiplications.
HELD_CELLS, HELD_WORK = 16_000_000, 2_000_000_000


def bounded_sample(vectors: DataFrame, rows: int, seed: int = 0) -> DataFrame:
    """About ``rows`` vectors by a seeded hash of the id, the same in every run and partitioning."""
    n = vectors.count()
    if n <= rows:
        return vectors
    return vectors.where(F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(1 << 30)) < int((1 << 30) * rows / n))


def _gathered(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows and sums of the vectors nearest to each centroid, ties to the lower shard."""
    near = np.concatenate([sq_distances(x[a : a + 8192], c).argmin(axis=1) for a in range(0, len(x), 8192)])
    order = np.argsort(near, kind="stable")
    n, sums = np.bincount(near, minlength=len(c)), np.zeros(c.shape)
    at = np.flatnonzero(n)
    sums[at] = np.add.reduceat(x[order], (np.cumsum(n) - n)[at], axis=0)
    return n, sums


def lloyd_round(vectors: DataFrame, centroids: np.ndarray, col: str = "q") -> DataFrame:
    """Rows (shard_id, n, sums): each vector counted at its nearest centroid, ties to the lower shard.

    Every partition hands over at most one row per shard, so the shuffle is k rows per task.
    """
    shared = vectors.sparkSession.sparkContext.broadcast(centroids)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        n, sums = np.zeros(len(c), np.int64), np.zeros(c.shape)
        for b in batches:
            if b.num_rows:
                more = _gathered(matrix(b.column(0)), c)
                n, sums = n + more[0], sums + more[1]
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_pydict({"shard_id": pa.array(at.astype(np.int32)), "n": pa.array(n[at]), "sums": lists(pa.array(sums[at].ravel()), np.full(len(at), c.shape[1]))})

    def total(t: pa.Table) -> pa.Table:
        sums = matrix(t.column("sums")).sum(axis=0)
        return pa.table({"shard_id": t.column("shard_id").slice(0, 1), "n": pa.array([sum(t.column("n").to_pylist())]), "sums": lists(pa.array(sums), np.array([len(sums)]))})

    schema = "shard_id int, n bigint, sums array<double>"
    return vectors.select(col).mapInArrow(partial, schema).groupBy("shard_id").applyInArrow(total, schema)


def seeds_lowest_id(vectors: DataFrame, k: int, col: str = "q") -> np.ndarray:
    rows = vectors.orderBy("vec_id").limit(k).select(col).collect()
    return np.array([r[0] for r in rows], np.float64)


def seeds_parallel(vectors: DataFrame, k: int, col: str = "q", rounds: int = 3, seed: int = 0) -> np.ndarray:
    """Oversampled seeding: each round adds vectors with a chance that grows with their distance, then a weighted greedy pass picks k."""
    chosen = seeds_lowest_id(vectors, 1, col)
    for r in range(rounds):
        shared = vectors.sparkSession.sparkContext.broadcast(chosen)

        @F.pandas_udf("double")
        def cost(xs):
            import pandas as pd

            return pd.Series(sq_distances(np.stack(xs.to_numpy()).astype(float), shared.value).min(axis=1))

        far = vectors.select("vec_id", col, cost(F.col(col)).alias("c"))
        total = far.agg(F.sum("c")).first()[0] or 0.0
        if not total:
            break
        u = F.pmod(F.xxhash64("vec_id", F.lit(seed + r)), F.lit(1 << 30)) / float(1 << 30)
        got = far.where(u < F.col("c") * (2.0 * k / total)).orderBy("vec_id").select(col).limit(8 * k).collect()
        if got:
            chosen = np.r_[chosen, np.array([g[0] for g in got], np.float64)]
    weight = np.zeros(len(chosen))
    for row in lloyd_round(vectors, chosen, col).select("shard_id", "n").collect():
        weight[row.shard_id] = row.n
    picked = [int(weight.argmax())]
    near = sq_distances(chosen, chosen[picked])[:, 0]
    while len(picked) < min(k, len(chosen)):
        nxt = int((near * weight).argmax())
        if near[nxt] == 0:
            nxt = next(i for i in range(len(chosen)) if i not in picked)
        picked.append(nxt)
        near = np.minimum(near, sq_distances(chosen, chosen[[nxt]])[:, 0])
    return chosen[sorted(picked)]


def fit_centroids(vectors: DataFrame, k: int, sample_rows: int = 100_000, iters: int = 15, seed: int = 0, init: str = "lowest_id", col: str = "q", held: tuple[int, int] = (HELD_CELLS, HELD_WORK)) -> np.ndarray:
    """k centroids of a bounded sample; an emptied cluster keeps its centroid.

    A sample within ``held`` (components, multiplications a round) is fetched once and its rounds run
    on the driver, where they cost no jobs; beyond it every round is a job. Integer vectors give the
    same centroids either way, others the same up to the order of a sum.
    """
    ws = Workspace(vectors.sparkSession, "kmeans")
    sample = ws.write(bounded_sample(vectors.select("vec_id", col), sample_rows, seed), "sample")
    c = seeds_lowest_id(sample, k, col) if init == "lowest_id" else seeds_parallel(sample, k, col, seed=seed)
    rows = sample.count()
    x = matrix(sample.select(col).toArrow().column(0)) if rows and rows * c.shape[1] <= held[0] and rows * c.size <= held[1] else None
    for _ in range(iters):
        new = c.copy()
        if x is not None:
            n, sums = _gathered(x, c)
            new[n > 0] = sums[n > 0] / n[n > 0][:, None]
        else:
            for r in lloyd_round(sample, c, col).collect():
                new[r.shard_id] = np.asarray(r.sums) / r.n
        if np.array_equal(new, c):
            break
        c = new
    ws.drop("sample")
    return c


def fit_centroids_tree(vectors: DataFrame, k_coarse: int, k_fine: int, sample_rows: int = 100_000, iters: int = 10, seed: int = 0, col: str = "q") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Two levels for very many shards: coarse centroids, then fine ones inside each coarse cell, one group per task.

    Returns (coarse, fine, coarse cell of each fine centroid).
    """
    coarse = fit_centroids(vectors, k_coarse, sample_rows, iters, seed, col=col)
    shared = vectors.sparkSession.sparkContext.broadcast(coarse)

    @F.pandas_udf("int")
    def cell(xs):
        import pandas as pd

        return pd.Series(sq_distances(np.stack(xs.to_numpy()).astype(float), shared.value).argmin(axis=1).astype("int32"))

    def fine(t: pa.Table) -> pa.Table:
        order = np.argsort(t.column("vec_id").to_numpy(), kind="stable")
        x = matrix(t.column(col))[order]
        c = x[:k_fine].copy()
        for _ in range(iters):
            near = sq_distances(x, c).argmin(axis=1)
            for j in np.unique(near):
                c[j] = x[near == j].mean(axis=0)
        return pa.table({"cell": pa.array(np.full(len(c), t.column("cell")[0].as_py(), np.int32)), "centroid": lists(pa.array(c.ravel()), np.full(len(c), c.shape[1]))})

    sample = bounded_sample(vectors.select("vec_id", col), sample_rows, seed).withColumn("cell", cell(F.col(col)))
    rows = sample.groupBy("cell").applyInArrow(fine, "cell int, centroid array<double>").orderBy("cell", "centroid").collect()
    return coarse, np.array([r.centroid for r in rows]), np.array([r.cell for r in rows])


def _nearest(d: np.ndarray, ids: np.ndarray | None, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and distances of the m smallest entries of each row, ties to the lower id; the rest of a row is never sorted."""
    ids = np.broadcast_to(np.arange(d.shape[1]), d.shape) if ids is None else ids
    if m < d.shape[1]:
        at = np.argpartition(d, m - 1, axis=1)[:, :m]
        worst = np.take_along_axis(d, at, axis=1).max(axis=1, keepdims=True)
        for i in np.flatnonzero((d <= worst).sum(axis=1) > m).tolist():  # a tie at the cut, which a partition settles at random
            near = np.flatnonzero(d[i] <= worst[i])
            at[i] = near[np.lexsort((ids[i, near], d[i, near]))[:m]]
        d, ids = np.take_along_axis(d, at, axis=1), np.take_along_axis(ids, at, axis=1)
    order = np.lexsort((ids, d), axis=1)
    return np.take_along_axis(ids, order, axis=1), np.take_along_axis(d, order, axis=1)


def preferences(vectors: DataFrame, centroids: np.ndarray, top_m: int | None = None, metric: str = "l2", col: str = "q", keep: tuple[str, ...] = (), tree: tuple[np.ndarray, np.ndarray, int] | None = None) -> DataFrame:
    """Rows (vec_id, keep..., prefs): shards by rising distance (squared for ``l2``), ties to the lower shard.

    One pass, no shuffle: the centroids are broadcast and a batch is one matrix product. ``tree`` =
    (coarse, cell of each fine centroid, probes) compares a vector with the nearest coarse cells'
    centroids alone; no matrix of all shards is made then.
    """
    k = len(centroids)
    m = min(top_m or k, k)
    cells = None if tree is None else [np.flatnonzero(tree[1] == c) for c in range(len(tree[0]))]
    probes = 0 if tree is None else min(tree[2], len(tree[0]))
    wide = k if cells is None else probes * max((len(c) for c in cells), default=0)
    shared = vectors.sparkSession.sparkContext.broadcast((centroids, None if tree is None else tree[0], cells))
    rows_at_once = max(1, MATRIX_CELLS // max(wide, 1))

    def probed(x: np.ndarray, c: np.ndarray, coarse: np.ndarray, cells: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        near, _ = _nearest(sq_distances(x, coarse), None, probes)
        d, ids = np.full((len(x), wide), np.inf), np.zeros((len(x), wide), np.int64)
        width = wide // max(probes, 1)
        for one in np.unique(near).tolist():  # each probed cell against the rows that probe it
            rows, turn = np.nonzero(near == one)
            at = turn[:, None] * width + np.arange(len(cells[one]))[None, :]
            d[rows[:, None], at], ids[rows[:, None], at] = sq_distances(x[rows], c[cells[one]]), cells[one][None, :]
        return _nearest(d, ids, min(m, wide))

    def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
        if metric == "l2":
            return sq_distances(x, c)
        if metric == "ip":
            return -(x @ c.T)
        y, z = (v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300) for v in (x, c))
        return 1.0 - y @ z.T

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c, coarse, cells = shared.value
        for whole in batches:
            for a in range(0, whole.num_rows, rows_at_once):
                b = whole.slice(a, rows_at_once)
                x = matrix(b.column("_x"))
                order, dist = probed(x, c, coarse, cells) if cells is not None else _nearest(distances(x, c), None, m)
                fine = np.isfinite(dist)
                prefs = pa.StructArray.from_arrays([pa.array(dist[fine]), pa.array(order[fine].astype(np.int32))], names=["dist", "shard_id"])
                yield pa.RecordBatch.from_arrays([b.column("vec_id"), *(b.column(c_) for c_ in keep), lists(prefs, fine.sum(axis=1))], names=["vec_id", *keep, "prefs"])

    kinds = "".join(f", {c_} {vectors.schema[c_].dataType.simpleString()}" for c_ in keep)
    return vectors.select("vec_id", *keep, F.col(col).alias("_x")).mapInArrow(run, f"vec_id bigint{kinds}, prefs array<struct<dist:double,shard_id:int>>")
