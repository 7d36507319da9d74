"""Embedding near-duplicates by a forest of random-projection trees with spill."""

from __future__ import annotations

import math
from collections.abc import Iterator
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import Workspace, components, tidy


def unit(vectors: np.ndarray) -> np.ndarray:
    """Rows scaled to length one in double precision, without overflow."""
    x = np.asarray(vectors, np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]


#: Random directions that all nodes of a forest draw from, so that one product gives a batch's projections for every tree and level.
POOL = 512
#: Copies of a vector that one pass over the table sends to leaves; a forest of more takes several passes.
COPIES = 24
#: Levels that one fit adds; deeper ones are fitted node by node in tasks.
LEVELS = 10
#: Sample rows behind the two thresholds of a node.
NODE_ROWS = 16


def directions(dim: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((POOL, dim)).astype(np.float32)


def direction_of(node: np.ndarray, tree: int) -> np.ndarray:
    """Which direction of the pool a node splits by."""
    with np.errstate(over="ignore"):
        h = (np.asarray(node, np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(tree + 1) * np.uint64(0xC2B2AE3D27D4EB4F)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((h >> np.uint64(32)) % np.uint64(POOL)).astype(np.int64)


def fit_nodes(proj: np.ndarray, tree: int, root: int, levels: int, spill: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(node, lo, hi) of the ``levels`` below ``root``: the spill thresholds around the median of the rows that reach a node."""
    nodes, lo, hi = [], [], []
    rows = {root: np.arange(len(proj))}
    for _ in range(levels):
        below: dict[int, np.ndarray] = {}
        for node, at in rows.items():
            p = proj[at, direction_of(node, tree)]
            a, b = np.quantile(p, [0.5 - spill / 2, 0.5 + spill / 2]) if len(p) else (0.0, 0.0)
            nodes.append(node), lo.append(a), hi.append(b)
            left = p <= (a + b) / 2
            below[2 * node + 1], below[2 * node + 2] = at[left], at[~left]
        rows = below
    return np.array(nodes, np.int64), np.array(lo, np.float32), np.array(hi, np.float32)


def leaves(proj: np.ndarray, tree: int, lo: np.ndarray, hi: np.ndarray, depth: int, spilling: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(row, node) at ``depth`` of every row; with ``spilling`` rows near a split go down both sides."""
    row, node = np.arange(len(proj)), np.zeros(len(proj), np.int64)
    for _ in range(depth):
        p = proj[row, direction_of(node, tree)]
        if spilling:
            left, right = p <= hi[node], p > lo[node]
        else:
            left = p <= (lo[node] + hi[node]) / 2
            right = ~left
        row, node = np.r_[row[left], row[right]], np.r_[2 * node[left] + 1, 2 * node[right] + 2]
    return row, node


def tree_count(depth: int, least: float, spill: float, miss: float) -> int:
    """Trees after which a pair at the link angle shares no leaf with a chance of ``miss``.

    A unit step of the projections is their deviation; a pair is cut where it stands on both sides
    of the spill band, by the normal law of its difference.
    """
    if depth == 0:
        return 1
    law = NormalDist()
    gap = math.sqrt(2 * (1 - min(least, 1 - 1e-6)))
    band = 2 * law.inv_cdf(0.5 + spill / 2)
    z = band / gap
    cut = min(0.5, 2 * law.pdf(0) * gap * (law.pdf(z) - z * (1 - law.cdf(z))))
    return max(1, math.ceil(math.log(miss) / math.log1p(-((1 - cut) ** depth))))


def hot_pivots(sample: np.ndarray, least: float, members: int = 16, candidates: int = 4096) -> np.ndarray:
    """Sample points that link with at least ``members`` sample points no earlier pivot links with, most first."""
    near = np.empty((min(candidates, len(sample)), len(sample)), bool)
    for i in range(0, len(near), 512):
        near[i : i + 512] = sample[i : min(i + 512, len(near))] @ sample.T >= least
    counts, free, out = near.sum(axis=1), np.ones(len(sample), bool), []
    while len(counts) and counts.max() >= members:
        best = int(counts.argmax())
        out.append(best)
        new = near[best] & free
        free &= ~new
        counts = counts - near[:, new].sum(axis=1)
    return sample[out]


def _matrix(col: pa.Array, dim: int) -> np.ndarray:
    flat = col.combine_chunks().flatten() if isinstance(col, pa.ChunkedArray) else col.flatten()
    return flat.to_numpy(zero_copy_only=False).reshape(-1, dim)


def sketch(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Components of unit vectors as 8-bit codes, and the step of each row."""
    step = np.abs(x).max(axis=1) / 127
    return np.rint(x / step[:, None]).astype(np.int8), step.astype(np.float32)


def sketch_error(step: np.ndarray, dim: int) -> np.ndarray:
    """Bound of a row's share in the error of a cosine of two sketches: half a step in every component, and the product of two errors."""
    return step * (0.505 * math.sqrt(dim) + 0.01)


def _leaf_links(x: np.ndarray, err: np.ndarray, side: np.ndarray, least: float, block: int = 512) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row, row, sure) of pairs whose sketches may link: of all rows, or of side 0 with side 1."""
    same = not (side == 1).any()
    left, right = (np.arange(len(x)),) * 2 if same else (np.flatnonzero(side == 0), np.flatnonzero(side == 1))
    for i in range(0, len(left), block):
        a = left[i : i + block]
        for j in range(i if same else 0, len(right), 4 * block):
            b = right[j : j + 4 * block]
            s = x[a] @ x[b].T
            may = s >= np.float32(least - 1e-5) - err[a][:, None] - err[b][None, :]
            if same:
                may &= a[:, None] < b[None, :]
            ia, ib = np.nonzero(may)
            ra, rb = a[ia], b[ib]
            yield ra, rb, s[ia, ib] >= np.float32(least + 1e-5) + err[ra] + err[rb]


def _spanning(hit: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Few edges with the connected components of the links between ``a`` and ``b``."""
    rows, cols = hit.any(axis=1), hit.any(axis=0)
    h, a, b = hit[rows][:, cols], a[rows], b[cols]
    if h.sum() <= 4 * (len(a) + len(b)):
        i, j = np.nonzero(h)
        return a[i], b[j]
    la, lb, most = a, b, np.iinfo(np.int64).max
    while True:
        nb = np.minimum(lb, np.where(h, la[:, None], most).min(axis=0))
        na = np.minimum(la, np.where(h, nb[None, :], most).min(axis=1))
        if (na == la).all() and (nb == lb).all():
            return np.r_[a, b], np.r_[la, lb]
        la, lb = na, nb


#: Roles of a row in a cell: within half the link angle of its pivot, at home otherwise, guest without a home, guest with one.
TIGHT, HOME, COLD, GUEST = range(4)


def _unit_sample(reps: DataFrame, n: int, rows: int, dim: int, seed: int) -> np.ndarray:
    u = F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    got = (reps.where(u < rows / n) if n > rows else reps).select("embedding").toArrow().column(0)
    return unit(_matrix(got, dim)) if len(got) else np.zeros((0, dim))


def _fit_forest(reps: DataFrame, n: int, sample: np.ndarray, dim: int, trees: list[int], depth: int, spill: float, seed: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Tree -> thresholds (lo, hi) of its 2^depth - 1 nodes.

    The driver fits the levels that its bounded sample allows. Deeper ones are fitted in tasks,
    ``LEVELS`` at a time: a sample of ``NODE_ROWS`` rows a node goes down the levels there are, and
    every node reached fits its own subtree; only thresholds come back, 8 bytes a node and tree.
    """
    pool = directions(dim, seed)
    done = max(0, min(depth, LEVELS, int(math.log2(max(len(sample), 1) / NODE_ROWS + 1))))
    proj = sample.astype(np.float32) @ pool.T
    out = {t: (np.zeros(2**depth - 1, np.float32), np.zeros(2**depth - 1, np.float32)) for t in trees}
    for t in trees:
        node, lo, hi = fit_nodes(proj, t, 0, done, spill)
        out[t][0][node], out[t][1][node] = lo, hi
    del proj
    kind = reps.schema["embedding"].dataType.simpleString()
    while done < depth:
        have, levels = done, min(LEVELS, depth - done)
        share = min(1.0, NODE_ROWS * 2 ** (have + levels) / max(n, 1))
        some = reps.where(F.pmod(F.xxhash64("id", F.lit(seed + 1 + have)), F.lit(1 << 30)) < int(share * (1 << 30)))
        known = reps.sparkSession.sparkContext.broadcast((pool, {t: (lo[: 2**have - 1], hi[: 2**have - 1]) for t, (lo, hi) in out.items()}))

        def down(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            pool, forest = known.value
            for b in batches:
                if b.num_rows:
                    proj = unit(_matrix(b.column("embedding"), dim)).astype(np.float32) @ pool.T
                    for t, (lo, hi) in forest.items():
                        row, node = leaves(proj, t, lo, hi, have, spilling=False)
                        yield pa.RecordBatch.from_pydict({"tree": pa.array(np.full(len(row), t)), "node": pa.array(node), "embedding": b.column("embedding").take(pa.array(row))})

        def fit(t: pa.Table) -> pa.Table:
            tree, root = t.column("tree")[0].as_py(), t.column("node")[0].as_py()
            proj = unit(_matrix(t.column("embedding"), dim)).astype(np.float32) @ known.value[0].T
            node, lo, hi = fit_nodes(proj, tree, root, levels, spill)
            return pa.table({"tree": np.full(len(node), tree), "node": node, "lo": lo, "hi": hi})

        got = some.select("embedding").mapInArrow(tidy(down), f"tree bigint, node bigint, embedding {kind}").groupBy("tree", "node").applyInArrow(fit, "tree bigint, node bigint, lo float, hi float").toArrow()
        tree, node, lo, hi = (got.column(c).to_numpy() for c in ("tree", "node", "lo", "hi"))
        for t in trees:
            m = tree == t
            out[t][0][node[m]], out[t][1][node[m]] = lo[m], hi[m]
        known.destroy()
        done += levels
    return out


def _one_dimension(reps: DataFrame, ws: Workspace, dim: int, least: float, leaf_rows: int, spill: float, sample_rows: int, miss: float, seed: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links (a, b, wa, wb) of rows without a cell, tight groups (id, core, w), and edges (a, b) or counts (a, a, k) of the cells, for one dimension."""
    spark = reps.sparkSession
    n = reps.count()
    sample = _unit_sample(reps, n, sample_rows, dim, seed)
    angle = math.acos(least)
    cos_half, cos_reach = math.cos(angle / 2) + 1e-9, math.cos(min(math.pi, 2 * angle)) - 1e-9
    pivots = hot_pivots(sample, least)
    if len(pivots):
        sample = sample[(sample @ pivots.T).max(axis=1) < least]
    depth = max(0, math.ceil(math.log2(max(n, 1) / leaf_rows)))
    trees, copies = tree_count(depth, least, spill, miss), (1 + spill) ** depth
    most = math.ceil(4 * leaf_rows * copies)
    kind = reps.schema["embedding"].dataType.simpleString()
    hot_shared = spark.sparkContext.broadcast(pivots)

    def homes(x: np.ndarray, pv: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Cosines with the pivots, and the home cell (-1: none) and role of each row."""
        s = x @ pv.T
        if not len(pv):
            return s, np.full(len(x), -1), np.full(len(x), COLD)
        top = s.max(axis=1)
        return s, np.where(top >= least, s.argmax(axis=1), -1), np.where(top >= cos_half, TIGHT, np.where(top >= least, HOME, COLD))

    def forest_links(forest: dict[int, tuple[np.ndarray, np.ndarray]], name: str) -> DataFrame:
        shared = spark.sparkContext.broadcast((directions(dim, seed), forest))

        def cold_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray, Iterator[tuple[int, np.ndarray, np.ndarray]]]]:
            pool, forest = shared.value
            for whole in batches:
                for start in range(0, whole.num_rows, 2000):
                    b = whole.slice(start, 2000)
                    x = unit(_matrix(b.column("embedding"), dim))
                    cold = np.flatnonzero(homes(x, hot_shared.value)[1] < 0)
                    proj = x[cold].astype(np.float32) @ pool.T
                    yield b, x, cold, ((t, *leaves(proj, t, lo, hi, depth)) for t, (lo, hi) in forest.items())

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for _, _, _, found in cold_rows(batches):
                keys = [leaf + (t << 40) for t, _, leaf in found]
                leaf, m = np.unique(np.concatenate(keys), return_counts=True)
                yield pa.RecordBatch.from_pydict({"leaf": pa.array(leaf), "m": pa.array(m)})

        def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b, x, cold, found in cold_rows(batches):
                code, step = sketch(x[cold])
                ids, w = b.column("id").to_numpy()[cold], b.column("w").to_numpy()[cold]
                for t, row, leaf in found:
                    codes = pa.FixedSizeBinaryArray.from_buffers(pa.binary(dim), len(row), [None, pa.py_buffer(np.ascontiguousarray(code[row]).tobytes())])
                    yield pa.RecordBatch.from_pydict({"leaf": pa.array(leaf + (t << 40)), "id": pa.array(ids[row]), "w": pa.array(w[row]), "step": pa.array(step[row]), "code": codes.cast(pa.binary())})

        rows = reps.select("id", "w", "embedding")
        large = ws.write(rows.mapInArrow(tidy(count), "leaf bigint, m bigint").groupBy("leaf").agg(F.ceil(F.sum("m") / most).alias("m")).where("m > 1"), f"{name}-large")
        n_large = large.count()
        routed = rows.mapInArrow(tidy(route), "leaf bigint, id bigint, w bigint, step float, code binary")
        key, side = F.col("leaf"), F.lit(2)
        if n_large:
            m = F.coalesce("m", F.lit(1))
            routed = routed.join(F.broadcast(large) if n_large <= 1_000_000 else large, "leaf", "left").withColumn("blk", F.pmod(F.xxhash64("id", F.lit(seed)), m)).withColumn("other", F.explode(F.sequence(F.lit(0).cast("bigint"), m - 1)))
            key = F.when(F.col("m").isNull(), F.col("leaf")).otherwise(F.xxhash64("leaf", F.least("blk", "other"), F.greatest("blk", "other")))
            side = F.when(F.col("blk") == F.col("other"), 2).otherwise((F.col("blk") > F.col("other")).cast("int"))
        dealt = routed.select(key.alias("key"), "id", (F.col("w") * 4 + side).alias("ws"), "step", "code")

        def within(t: pa.Table) -> pa.Table:
            ids, ws_, step = (t.column(c).to_numpy() for c in ("id", "ws", "step"))
            w, code = ws_ >> 2, t.column("code").combine_chunks()
            start = code.offset * dim
            x = np.frombuffer(code.buffers()[2], np.int8)[start : start + len(ids) * dim].reshape(-1, dim).astype(np.float32) * step[:, None]
            out = [np.empty((5, 0), np.int64)]
            for a, b, sure in _leaf_links(x, sketch_error(step, dim).astype(np.float32), ws_ & 3, least):
                a, b = np.where(ids[a] > ids[b], a, b), np.where(ids[a] > ids[b], b, a)
                out.append(np.stack([ids[a], ids[b], w[a], w[b], sure.astype(np.int64)]))
            a, b, wa, wb, sure = np.concatenate(out, axis=1)
            return pa.table({"a": a, "b": b, "wa": wa, "wb": wb, "sure": sure})

        found = dealt.groupBy("key").applyInArrow(within, "a bigint, b bigint, wa bigint, wb bigint, sure bigint").where("a <> b").distinct()
        found = ws.write(found, name)
        shared.destroy()
        return found

    found, at_once = None, max(1, int(COPIES / copies))
    for first in range(0, trees, at_once):
        some = list(range(first, min(trees, first + at_once)))
        got = forest_links(_fit_forest(reps, n, sample, dim, some, depth, spill, seed), f"found-{dim}-{first}")
        found = got if found is None else found.unionByName(got)
    found = found.distinct() if trees > at_once else found

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                s = np.einsum("ij,ij->i", unit(_matrix(b.column("xa"), dim)), unit(_matrix(b.column("xb"), dim)))
                yield b.select(["a", "b", "wa", "wb"]).filter(pa.array(s >= least))

    ends = [reps.select(F.col("id").alias(c), F.col("embedding").alias(f"x{c}")) for c in "ab"]
    unsure = found.where("sure = 0").select("a", "b", "wa", "wb").join(ends[0], "a").join(ends[1], "b").select("a", "b", "wa", "wb", "xa", "xb")
    schema = "a bigint, b bigint, wa bigint, wb bigint"
    pairs = found.where("sure = 1").select("a", "b", "wa", "wb").unionByName(unsure.mapInArrow(tidy(exact), schema))

    def enter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pv = hot_shared.value
        for b in batches:
            if b.num_rows and len(pv):
                s, home, role = homes(unit(_matrix(b.column("embedding"), dim)), pv)
                row, cell = np.nonzero(s >= cos_reach)
                roles = np.where(home[row] == cell, role[row], np.where(home[row] < 0, COLD, GUEST))
                for i in range(0, len(row), 10_000):
                    take = pa.array(row[i : i + 10_000])
                    yield pa.RecordBatch.from_pydict({"cell": pa.array(cell[i : i + 10_000]), "role": pa.array(roles[i : i + 10_000]), "id": b.column("id").take(take), "w": b.column("w").take(take), "embedding": b.column("embedding").take(take)})

    members = reps.select("id", "w", "embedding").mapInArrow(tidy(enter), f"cell bigint, role bigint, id bigint, w bigint, embedding {kind}")
    left, right = F.col("role") <= HOME, F.col("role") >= HOME
    sizes = members.groupBy("cell").agg(F.ceil(F.count_if(left) / (2 * most)).alias("nl"), F.ceil(F.count_if(right) / (2 * most)).alias("nr")).where("nl > 0 and nr > 0")
    both = members.join(F.broadcast(sizes), "cell")
    salt, zero = F.xxhash64("id", F.lit(seed)), F.lit(0).cast("bigint")
    side = lambda rows, n, own, others, part: rows.withColumn("own", F.pmod(salt, F.col(own))).withColumn("o", F.explode(F.sequence(zero, F.col(others) - 1))).select("cell", F.expr(part).alias("part"), F.lit(n).cast("bigint").alias("side"), "role", "id", "w", "embedding")
    both = side(both.where(left), 0, "nl", "nr", "own * nr + o").unionByName(side(both.where(right), 1, "nr", "nl", "o * nr + own"))

    def cell_links(t: pa.Table) -> pa.Table:
        ids, w, role, sides = (t.column(c).to_numpy() for c in ("id", "w", "role", "side"))
        x = unit(_matrix(t.column("embedding"), dim))
        a, b = np.flatnonzero(sides == 0), np.flatnonzero(sides == 1)
        ka, kb = np.zeros(len(a), np.int64), np.zeros(len(b), np.int64)
        ends = [np.empty((2, 0), np.int64)]
        for i in range(0, len(a) if len(b) else 0, 512):
            at = a[i : i + 512]
            hit = (x[at] @ x[b].T >= least) & (ids[at][:, None] != ids[b][None, :])
            ka[i : i + 512] = np.where(hit, w[b][None, :], 0).sum(axis=1)
            from_tight = np.where(hit & (role[at] == TIGHT)[:, None], w[at][:, None], 0).sum(axis=0)
            # the links of a row at home with its like are counted from its own side, those of a guest with a home in its own cell
            kb += np.where(role[b] == COLD, np.where(hit, w[at][:, None], 0).sum(axis=0), np.where(role[b] == HOME, from_tight, 0))
            ends.append(np.stack(_spanning(hit, ids[at], ids[b])))
        u, v = np.unique(np.concatenate(ends, axis=1), axis=1)
        n = np.r_[ka, kb]
        return pa.table({"a": np.r_[u, ids[np.r_[a, b]][n > 0]], "b": np.r_[v, ids[np.r_[a, b]][n > 0]], "k": np.r_[np.zeros(len(u), np.int64), n[n > 0]]})

    hot = both.groupBy("cell", "part").applyInArrow(cell_links, "a bigint, b bigint, k bigint")
    tight = members.where(F.col("role") == TIGHT).select("id", (F.col("cell") + dim * 1_000_000).alias("core"), "w")
    return pairs, tight, hot


def near_duplicates(
    vectors: DataFrame,
    least: float = 0.9,
    leaf_rows: int = 1024,
    spill: float = 0.12,
    sample_rows: int = 16_384,
    miss: float = 1e-4,
    seed: int = 11,
) -> DataFrame:
    """Rows (vec_id, n_links, component_id, kept) of the links with cosine >= ``least``.

    1. Equal vectors become one weighted representative.
    2. Sample points that link with 16 or more others become pivots, as many as there are. A vector
       that links with a pivot is at home in the cell of the nearest one; by the triangle inequality
       all its links lie within two link angles of that pivot. These are the cell's guests, and all
       pairs of home and guest are verified in double precision, dealt to tasks as pairs of salted
       row blocks; counts and spanning edges leave a task, no pairs. Vectors within half the link
       angle of one pivot are all linked; they are counted and joined in closed form.
    3. The other vectors, all of them in all trees, go through a forest whose depth follows their
       number, so that a leaf is planned for ``leaf_rows`` vectors times their copies at any table size: each
       tree splits at random directions, at medians; vectors near a split go down both sides. The
       number of trees follows from depth, ``spill`` and link angle so that a link at the threshold
       shares no leaf with a chance of ``miss``. Only 8-bit sketches travel, at most ``COPIES`` of a
       vector in one pass; deeper forests take several. Inside a leaf a blocked product finds the
       pairs that may link within the sketches' error bound; those that the bound leaves open are
       verified in double precision by joins. A leaf that outgrew its plan fourfold is verified whole, dealt
       to tasks as pairs of salted row blocks. Links found in several trees count once.

    The driver holds the sample and a pass's thresholds, 8 bytes a node; the broadcast is these and
    ``POOL`` directions. Links with a vector in a cell are exact; recall of the others is that of
    the forest; the tests measure it against brute force. A cell costs homes times guests, so a hot
    group that is not tight costs the square of its size in products, spread over all tasks; groups
    too small for a pivot (under about a thousandth of the table) list their links as pairs.
    Null, zero, empty vectors and those with null or non-finite components link with nothing.
    Vectors of different dimension never link. Rows that repeat a vec_id are one vector (the
    smallest content hash counts); a null vec_id stays, unlinked, with a null component.
    """
    spark = vectors.sparkSession
    ws = Workspace(spark, "neardup")
    e = F.col("embedding")
    fine = F.coalesce(
        e.isNotNull() & (F.size(e) > 0) & ~F.exists(e, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(e, lambda x: x != 0), F.lit(False)
    )
    rows = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), e, fine.alias("fine")).withColumn("h", F.when(F.col("fine"), F.xxhash64("embedding")))
    ids = ws.write(rows.groupBy("vec_id").agg(F.min("h").alias("h")), "ids")
    live = ids.where("h is not null and vec_id is not null")
    weight = live.groupBy("h").agg(F.min("vec_id").alias("id"), F.count("*").alias("w"))
    reps = ws.write(rows.where("fine").select("h", "embedding").join(weight, "h").groupBy("h").agg(F.first("id").alias("id"), F.first("w").alias("w"), F.first("embedding").alias("embedding")).withColumn("dim", F.size("embedding")), "reps")
    dims = [r.dim for r in reps.groupBy("dim").count().orderBy(F.col("count").desc()).collect()]
    pairs = grouped = hot = None
    for d in dims:
        p, g, h = _one_dimension(reps.where(F.col("dim") == d), ws, d, least, leaf_rows, spill, sample_rows, miss, seed)
        pairs, grouped, hot = (p, g, h) if pairs is None else (pairs.unionByName(p), grouped.unionByName(g), hot.unionByName(h))
    if pairs is None:
        pairs = spark.createDataFrame([], "a bigint, b bigint, wa bigint, wb bigint")
        grouped = spark.createDataFrame([], "id bigint, core bigint, w bigint")
        hot = spark.createDataFrame([], "a bigint, b bigint, k bigint")
    pairs, grouped, hot = ws.write(pairs, "pairs"), ws.write(grouped, "cores"), ws.write(hot, "hot")
    sums = grouped.groupBy("core").agg(F.sum("w").alias("total"), F.min("id").alias("head"))
    dense = grouped.join(F.broadcast(sums), "core")
    counts = (
        pairs.select(F.col("a").alias("id"), F.col("wb").alias("k"))
        .unionByName(pairs.select(F.col("b").alias("id"), F.col("wa").alias("k")))
        .unionByName(dense.select("id", (F.col("total") - F.col("w")).alias("k")))
        .unionByName(hot.select(F.col("a").alias("id"), "k"))
        .groupBy("id").agg(F.sum("k").alias("k"))
    )
    comp = components(pairs.select("a", "b").unionByName(hot.select("a", "b")).unionByName(dense.select(F.col("id").alias("a"), F.col("head").alias("b"))), ws)
    reps_out = weight.join(counts, "id", "left").join(comp, "id", "left").select(
        F.col("h").alias("rh"), (F.coalesce("k", F.lit(0)) + F.col("w") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id")
    )
    out = ids.join(reps_out, F.expr("h = rh and vec_id is not null"), "left")
    return out.select(
        "vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"),
    ).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


ORACLE = """
with recursive v as (
  select vec_id, embedding::double[] as e from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0
), l as (select a.vec_id as a, b.vec_id as b from v a join v b on a.vec_id <> b.vec_id where list_cosine_similarity(a.e, b.e) >= 0.9),
reach(a, b) as (select vec_id, vec_id from v union select reach.a, l.b from reach join l on reach.b = l.a),
c as (select a, min(b) as c from reach group by a)
select e.vec_id, (select count(*) from l where l.a = e.vec_id)::bigint as n_links, coalesce(c.c, e.vec_id) as component_id, e.vec_id = coalesce(c.c, e.vec_id) as kept
from embeddings e left join c on c.a = e.vec_id
"""
