"""Blockwise-adaptive assignment of vectors to shards, with selective replicas."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from fractions import Fraction
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardgraph.operators.centroids import preferences
from shardgraph.operators.state import LOG_SCHEMA, ClusterState, radius_boost
from shardgraph.workspace import Workspace


class ShardPlan(NamedTuple):
    k: int
    capacity: int


def plan_shards(n: int, dim: int, bytes_per_component: int, degree: int, budget_bytes: int, expected_share: float, fill: float = 0.7, edge_bytes: int = 12) -> ShardPlan:
    """Fewest shards whose vectors and working graphs fit ``budget_bytes``, replicas included."""
    capacity = int(budget_bytes * fill) // (dim * bytes_per_component + degree * edge_bytes)
    if capacity < 1:
        raise ValueError("one vector does not fit the memory budget")
    return ShardPlan(max(1, math.ceil(n * (1 + expected_share) / capacity)), capacity)


@dataclass(frozen=True)
class PartitionConfig:
    eps: Fraction | None = Fraction(6, 5)  # None: no pruning
    max_homes: int = 2
    blocks: int = 4
    quota: str = "adaptive"
    lo: float = 0.0
    hi: float = 0.5
    margin: float = 1.1
    fixed_share: float = 0.3
    boost: str = "power"
    b0: float = 4.0
    p: float = 2.0
    radius_test: bool = True
    order: str = "id"
    refresh: bool = True
    mode: str = "ranked"  # "strict" walks the vectors in id order in one task, for fixtures


def is_needed(d2_home: Column, d2_alt: Column, radius2: Column | None, eps: Fraction, boost: Fraction | float = 1) -> Column:
    """Replica test on squared distances: nearer than eps times the home's, and than eps times the boosted radius."""
    num, den = float(eps.numerator**2), float(eps.denominator**2)
    near = d2_alt * den < d2_home * num
    if radius2 is None:
        return near
    return near & (radius2.isNull() | (d2_alt * den < radius2 * (num * float(boost) ** 2)))


def numbers(values, kind: str) -> Column:
    """A driver array as one foldable literal, nan as null."""
    text = ",".join("" if isinstance(v, float) and np.isnan(v) else repr(v) for v in np.asarray(values).tolist())
    return F.expr(f"transform(split('{text}', ','), x -> try_cast(x as {kind}))")


#: Keys between an approximate quantile and the cut that one job orders; a sketch gets finer with the table, so more are rare.
CUT_KEYS = 50_000


def exact_cuts(keys: DataFrame, parts: int) -> list[int]:
    """The last key of each slice but the last, as ``ntile(parts)`` over the distinct keys of column ``key`` cuts them.

    A sketch comes near each cut, one pass counts the keys up to there, and only the keys between
    the two are ordered: no task sees a sorted table.
    """
    n = keys.count()
    ranks = [i * (n // parts) + min(i, n % parts) for i in range(1, parts)]
    ranks = [r for r in ranks if r > 0]
    if not n or not ranks:
        return []
    at = keys.agg(F.percentile_approx("key", [r / n for r in ranks], max(10_000, n // CUT_KEYS))).first()[0]
    upto = keys.agg(*[F.count_if(F.col("key") <= a) for a in at]).first()
    out = []
    for rank, a, seen in zip(ranks, at, upto, strict=True):
        if seen < rank:
            a = keys.where(F.col("key") > a).orderBy("key").limit(rank - seen).agg(F.max("key")).first()[0]
        elif seen > rank:
            a = keys.where(F.col("key") <= a).orderBy(F.desc("key")).limit(seen - rank + 1).agg(F.min("key")).first()[0]
        out.append(a)
    return out


def with_blocks(vectors: DataFrame, blocks: int, order: str = "id") -> DataFrame:
    """Adds ``block_id``: even slices in arrival order, cut at exact ranks of the order key, so nothing is sorted globally."""
    if order == "shuffled":
        key = F.conv(F.substring(F.md5(F.col("vec_id").cast("string")), 1, 12), 16, 10).cast("bigint")
    else:
        key = F.col("vec_id") if order == "id" else -F.col("vec_id")
    if blocks == 1:
        return vectors.withColumn("block_id", F.lit(0))
    cuts = exact_cuts(vectors.select(key.alias("key")), blocks)
    rank = F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < key)) if cuts else F.lit(0)
    return vectors.withColumn("block_id", rank.cast("int"))


def admit_closest(proposals: DataFrame, room: np.ndarray, bins: int = 16) -> DataFrame:
    """Adds ``ok``: the ``room[shard_id]`` proposals of each shard that are closest by (dist, vec_id).

    Distance quantiles of each shard split its proposals into bins. Bins before the cut are taken
    whole, so only the bin that holds the cut is ranked: no window sees a whole hot shard.
    """
    at = [i / bins for i in range(1, bins)]
    cuts = F.broadcast(proposals.groupBy("shard_id").agg(F.percentile_approx("dist", at, 1000).alias("cuts")))
    binned = proposals.join(cuts, "shard_id").withColumn("bin", F.size(F.filter("cuts", lambda c: c < F.col("dist")))).drop("cuts")
    upto = F.sum("m").over(Window.partitionBy("shard_id").orderBy("bin"))
    sums = binned.groupBy("shard_id", "bin").agg(F.count("*").alias("m")).withColumn("upto", upto).withColumn("left", F.get(numbers(room, "bigint"), F.col("shard_id")) - (F.col("upto") - F.col("m")))
    dealt = binned.join(F.broadcast(sums), ["shard_id", "bin"])
    whole = dealt.where("left >= m or left <= 0").withColumn("ok", F.col("left") > 0)
    rank = F.row_number().over(Window.partitionBy("shard_id", "bin").orderBy("dist", "vec_id"))
    cut = dealt.where("left < m and left > 0").withColumn("ok", rank <= F.col("left"))
    return whole.unionByName(cut).drop("bin", "m", "upto", "left")


def _counts(df: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Rows and farthest distance by shard, and the rows without a shard."""
    n, far, none = np.zeros(k, np.int64), np.full(k, np.nan), 0
    for r in df.groupBy("shard_id").agg(F.count("*").alias("n"), F.max("dist").alias("far")).collect():
        if r.shard_id is None:
            none = r.n
        else:
            n[r.shard_id], far[r.shard_id] = r.n, r.far
    return n, far, none


def assign_homes(block: DataFrame, room: np.ndarray, ws: Workspace, tag: str, size: int | None = None, first: tuple[np.ndarray, np.ndarray] | None = None, full: Callable[[DataFrame], DataFrame] | None = None) -> tuple[DataFrame, np.ndarray, np.ndarray]:
    """Nearest shard with room for every vector of ``block(vec_id, prefs)``; (homes, counts, farthest).

    Everyone proposes to the first preference with room; a shard that would overflow admits the
    closest, and only the rejected go on. Without overflow it is one aggregate of k rows, or no job
    at all if the caller knows the counts of the ``first`` preferences. Vectors whose cut lists
    hold no open shard get whole ones from ``full``.
    """
    room, k = room.copy(), len(room)
    if room.sum() < (block.count() if size is None else size):
        raise ValueError("the shards have less room than there are vectors")
    total, far, done, pending = np.zeros(k, np.int64), np.full(k, np.nan), [], block
    for r in range(2 * k + 2):
        is_open = numbers((room > 0).astype(int), "int")
        pick = F.get(F.filter("prefs", lambda p: F.get(is_open, p["shard_id"]) == 1), F.lit(0))
        proposed = pending.withColumn("p", pick).select("vec_id", "prefs", F.col("p.shard_id").alias("shard_id"), F.col("p.dist").alias("dist"))
        n, d, none = (*first, 0) if first is not None and r == 0 and (room > 0).all() else _counts(proposed, k)
        if none:
            if full is None:
                raise ValueError("the preference lists hold no shard with room")
            short = proposed.where("shard_id is null").select("vec_id")
            pending = ws.write(proposed.where("shard_id is not null").select("vec_id", "prefs").unionByName(full(short)), f"{tag}-full{r}")
            continue
        over = np.flatnonzero(n > room)
        if not len(over):
            done.append(proposed)
            total, far = total + n, np.fmax(far, d)
            break
        tight = F.col("shard_id").isin([int(s) for s in over])
        done.append(proposed.where(~tight))
        decided = ws.write(admit_closest(proposed.where(tight), room), f"{tag}-round{r}")
        done.append(decided.where("ok").drop("ok").select("vec_id", "prefs", "shard_id", "dist"))
        n2, d2, _ = _counts(decided.where("ok"), k)
        fits = n <= room
        n, d = np.where(fits, n, n2), np.where(fits, d, d2)
        total, far, room = total + n, np.fmax(far, d), room - n
        pending = decided.where("not ok").select("vec_id", "prefs")
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out, total, far


def assign_replicas(homes: DataFrame, state: ClusterState, cfg: PartitionConfig, boost: float, ws: Workspace, tag: str) -> DataFrame:
    """Replica rows (vec_id, shard_id, dist) of a block's ``homes(vec_id, prefs, shard_id, dist)``.

    Pruning comes before any ranking: alternatives that fail the tests never leave their row.
    Every vector has ``max_homes - 1`` tickets and spends them on its nearest open alternatives; a
    shard over its quota admits the closest, and losers try the next, until all are settled.
    ``state.n_repl`` is advanced.
    """
    k = len(state.capacity)
    if cfg.mode == "strict":
        out = ws.write(_strict_replicas(homes, state, cfg, boost), f"{tag}-strict")
        state.n_repl = state.n_repl + _counts(out, k)[0]
        return out
    radius2 = numbers(state.radius2, "double") if cfg.radius_test else None

    def wanted(p: Column) -> Column:
        other = p["shard_id"] != F.col("shard_id")
        if cfg.eps is None:
            return other
        return other & is_needed(F.col("dist"), p["dist"], None if radius2 is None else F.get(radius2, p["shard_id"]), cfg.eps, boost)

    todo = homes.select("vec_id", F.filter("prefs", wanted).alias("alts"), F.lit(cfg.max_homes - 1).alias("tickets")).where("size(alts) > 0 and tickets > 0")
    out: DataFrame | None = None
    for r in range(k + 1):
        quota = state.quota_left
        if cfg.max_homes < 2 or not quota.any():
            break
        is_open = numbers((quota > 0).astype(int), "int")
        todo = todo.withColumn("alts", F.filter("alts", lambda p: F.get(is_open, p["shard_id"]) == 1)).where("size(alts) > 0")
        asks = todo.select("vec_id", F.posexplode(F.slice("alts", F.lit(1), F.col("tickets"))).alias("i", "p")).select("vec_id", "p.shard_id", "p.dist")
        n, _, _ = _counts(asks, k)
        if not n.any():
            break
        over = np.flatnonzero(n > quota)
        if len(over):
            tight = F.col("shard_id").isin([int(s) for s in over])
            decided = ws.write(asks.where(~tight).withColumn("ok", F.lit(True)).unionByName(admit_closest(asks.where(tight), quota)), f"{tag}-asks{r}")
            n, _, _ = _counts(decided.where("ok"), k)
            won = decided.where("ok").select("vec_id", "shard_id", "dist")
        else:
            won = asks
        out = won if out is None else out.unionByName(won)
        state.n_repl = state.n_repl + n
        if not len(over):
            break
        told = decided.groupBy("vec_id").agg(F.sum(F.col("ok").cast("int")).alias("got"), F.count("*").alias("tried"))
        todo = todo.join(told, "vec_id").select("vec_id", F.slice("alts", F.col("tried").cast("int") + 1, F.size("alts")).alias("alts"), (F.col("tickets") - F.col("got")).cast("int").alias("tickets")).where("tickets > 0")
        todo = ws.write(todo, f"{tag}-todo{r}")
    if out is None:
        return homes.select("vec_id", "shard_id", "dist").where("false")
    return out


def _strict_replicas(homes: DataFrame, state: ClusterState, cfg: PartitionConfig, boost: float) -> DataFrame:
    """The sequential form of the replica pass: live counters, vectors in id order, one task."""
    quota, radius2 = state.quota_left.tolist(), [None if np.isnan(r) or not cfg.radius_test else float(r) for r in state.radius2]
    num, den = (cfg.eps.numerator**2, cfg.eps.denominator**2) if cfg.eps else (math.inf, 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, out = list(quota), []
        for b in batches:
            for i, prefs, home, d_home in zip(*(b.column(c).to_pylist() for c in range(4)), strict=True):
                tickets = cfg.max_homes - 1
                for p in prefs:
                    s, d = p["shard_id"], p["dist"]
                    near = cfg.eps is None or (d * den < num * d_home and (radius2[s] is None or d * den < num * boost**2 * radius2[s]))
                    if tickets and s != home and left[s] > 0 and near:
                        left[s], tickets = left[s] - 1, tickets - 1
                        out.append((i, s, d))
        cols = list(zip(*out, strict=True)) if out else [[]] * 3
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.float64()), strict=True)], names=["vec_id", "shard_id", "dist"])

    one = homes.select("vec_id", "prefs", "shard_id", "dist").coalesce(1).sortWithinPartitions("vec_id")
    return one.mapInArrow(run, "vec_id bigint, shard_id int, dist double")


class Partitioned(NamedTuple):
    assignment: DataFrame
    log: DataFrame
    state: ClusterState


def sample_state(sample_prefs: DataFrame, capacity: np.ndarray) -> ClusterState:
    """Start of the state: shares and radii of the sample's nearest centroids."""
    n, far, _ = _counts(sample_prefs.select(F.get("prefs", F.lit(0)).alias("p")).select("p.shard_id", "p.dist"), len(capacity))
    return ClusterState(capacity, n / max(n.sum(), 1), far, float(max(n.sum(), 1)))


#: Rows of a block up to which its rounds run on the driver, over lists of ``KEPT_PREFS`` entries: 20 MB at most.
FEW_ROWS = 50_000


class SmallBlock:
    """The rounds of ``assign_homes`` and ``assign_replicas`` over a block's lists in memory, step by step the same."""

    def __init__(self, block: pa.Table):
        lists = block.column("prefs").combine_chunks()
        size = np.diff(lists.offsets.to_numpy())
        flat = lists.flatten()
        at = np.arange(size.max(initial=0))[None, :] < size[:, None]
        self.ids = block.column("vec_id").to_numpy()
        self.shard, self.dist = np.full(at.shape, -1), np.full(at.shape, np.inf)
        self.shard[at], self.dist[at] = flat.field("shard_id").to_numpy(), flat.field("dist").to_numpy()

    def _closest(self, rows: np.ndarray, cols: np.ndarray, room: np.ndarray) -> np.ndarray:
        """Which of the asks (row, col) are admitted: of each shard the closest by (dist, vec_id) as far as its room goes."""
        s, ok = self.shard[rows, cols], np.ones(len(rows), bool)
        for one in np.flatnonzero(np.bincount(s, minlength=len(room)) > room):
            asks = np.flatnonzero(s == one)
            order = np.lexsort((self.ids[rows[asks]], self.dist[rows[asks], cols[asks]]))
            ok[asks[order[room[one] :]]] = False
        return ok

    def homes(self, room: np.ndarray) -> np.ndarray | None:
        """Column of each vector's home; none if a cut list holds no shard with room."""
        room, home = room.copy(), np.full(len(self.ids), -1)
        todo = np.arange(len(self.ids))
        while len(todo):
            is_open = np.r_[room > 0, False][self.shard[todo]]  # the last entry stands for padding
            if not is_open.any(axis=1).all():
                return None
            first = is_open.argmax(axis=1)
            ok = self._closest(todo, first, room)
            home[todo[ok]] = first[ok]
            room -= np.bincount(self.shard[todo[ok], first[ok]], minlength=len(room))
            todo = todo[~ok]
        return home

    def replicas(self, home: np.ndarray, state: ClusterState, cfg: PartitionConfig, boost: float) -> tuple[np.ndarray, np.ndarray]:
        """(row, column) of the replicas; ``state.n_repl`` is advanced."""
        rows = np.arange(len(self.ids))
        wanted = self.shard >= 0
        wanted[rows, home] = False
        if cfg.eps is not None:
            num, den = float(cfg.eps.numerator**2), float(cfg.eps.denominator**2)
            wanted &= self.dist * den < self.dist[rows, home][:, None] * num
            if cfg.radius_test:
                radius2 = np.r_[state.radius2, np.nan][self.shard]
                wanted &= np.isnan(radius2) | (self.dist * den < radius2 * (num * float(boost) ** 2))
        tickets, out = np.full(len(rows), cfg.max_homes - 1), [np.empty((2, 0), np.int64)]
        while cfg.max_homes > 1 and state.quota_left.any():
            quota = state.quota_left
            wanted &= np.r_[quota > 0, False][self.shard]
            asks = wanted & (np.cumsum(wanted, axis=1) <= tickets[:, None])
            at = np.stack(np.nonzero(asks))
            if not at.shape[1]:
                break
            ok = self._closest(*at, quota)
            won = at[:, ok]
            out.append(won)
            state.n_repl = state.n_repl + np.bincount(self.shard[won[0], won[1]], minlength=len(quota))
            tickets = tickets - np.bincount(won[0], minlength=len(rows))
            wanted &= ~asks
            if ok.all():
                break
        return tuple(np.concatenate(out, axis=1))

    def rows(self, home: np.ndarray, row: np.ndarray, col: np.ndarray, block: int) -> pa.Table:
        order = np.lexsort((self.shard[row, col], self.dist[row, col], row))
        row, col = row[order], col[order]
        n = np.bincount(row, minlength=len(self.ids))
        rank = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n) + 2
        r, c = np.r_[np.arange(len(self.ids)), row], np.r_[home, col]
        return pa.table({
            "vec_id": self.ids[r], "shard_id": self.shard[r, c].astype(np.int32), "is_home": np.arange(len(r)) < len(self.ids), "dist": self.dist[r, c],
            "rank": np.r_[np.ones(len(self.ids), np.int32), rank.astype(np.int32)], "n_homes": (n[r] + 1).astype(np.int32), "block_id": np.full(len(r), block, np.int32),
        })


#: Entries of a preference list that ``partition_vectors`` keeps; whole lists are made only for vectors that find all of them full.
KEPT_PREFS = 16


def listed_by_block(vectors: DataFrame, centroids: np.ndarray, cfg: PartitionConfig, ws: Workspace, col: str = "q", top_m: int | None = KEPT_PREFS) -> DataFrame:
    """Preference lists (vec_id, block_id, prefs) in one scan of the vectors, written by block."""
    top_m = None if top_m is None else max(top_m, 4 * cfg.max_homes)
    return ws.write(preferences(with_blocks(vectors, cfg.blocks, cfg.order), centroids, top_m, col=col, keep=("block_id",)), "prefs", by="block_id")


def partition_vectors(vectors: DataFrame, centroids: np.ndarray, plan: ShardPlan, cfg: PartitionConfig, col: str = "q", sample_rows: int = 20_000, top_m: int | None = KEPT_PREFS, start: ClusterState | None = None, prefs: DataFrame | None = None, few_rows: int = FEW_ROWS) -> Partitioned:
    """One pass over the vectors, block by block.

    Preference lists, cut to ``top_m`` entries, are computed in one scan and written by block, or
    handed over in ``prefs`` as ``listed_by_block`` writes them; from there on only slim rows move.
    One aggregate gives every block's first proposals, so a block whose shards have room needs no
    job for its homes. Per block: homes, then counts, radii and quotas, then replicas under the new
    quotas, looked for among the listed shards. A block of up to ``few_rows`` cut lists takes its rounds
    on the driver, where they cost no jobs; the result is the same. The assignment is (vec_id, shard_id, is_home, dist,
    rank, n_homes, block_id), dist squared.
    """
    spark = vectors.sparkSession
    ws = Workspace(spark, "partition")
    k = plan.k
    if len(centroids) != k:
        raise ValueError("one centroid per shard is needed")
    if prefs is None:
        prefs = listed_by_block(vectors, centroids, cfg, ws, col, top_m)
    n = prefs.count()
    if k * plan.capacity < n:
        raise ValueError("the shards have less room than there are vectors")
    # the seed of radii and shares is the caller's, or that of a bounded sample
    sampled = F.pmod(F.xxhash64("vec_id"), F.lit(1 << 20)) < int((1 << 20) * min(1.0, sample_rows / max(n, 1)))
    near = prefs.select("block_id", sampled.alias("sampled"), F.get("prefs", F.lit(0)).alias("p")).select("block_id", "sampled", "p.shard_id", "p.dist")
    stats = near.groupBy("block_id", "shard_id").agg(F.count("*").alias("n"), F.max("dist").alias("far"), F.count_if("sampled").alias("m"), F.max(F.when(F.col("sampled"), F.col("dist"))).alias("seed")).collect()
    if start is None:
        counts, far = np.zeros(k), np.full(k, np.nan)
        for r in stats:
            counts[r.shard_id] += r.m
            far[r.shard_id] = np.fmax(far[r.shard_id], np.nan if r.seed is None else r.seed)
        start = ClusterState(np.full(k, plan.capacity, np.int64), counts / max(counts.sum(), 1), far, float(max(counts.sum(), 1)))
    state, sizes, firsts = start, {}, {}
    for r in stats:
        sizes[r.block_id] = sizes.get(r.block_id, 0) + r.n
        of = firsts.setdefault(r.block_id, (np.zeros(k, np.int64), np.full(k, np.nan)))
        of[0][r.shard_id], of[1][r.shard_id] = r.n, r.far

    def full(ids: DataFrame) -> DataFrame:
        return preferences(vectors.join(ids, "vec_id", "left_semi"), centroids, None, col=col)

    log, parts, left = [], [], n
    for b in sorted(sizes):
        block = prefs.where(F.col("block_id") == b).drop("block_id")
        small = small_home = None
        if sizes[b] <= few_rows and top_m is not None and cfg.mode != "strict":
            small = SmallBlock(block.select("vec_id", "prefs").toArrow())
            small_home = small.homes(state.room)
        if small_home is None:
            homes, counts, far = assign_homes(block, state.room, ws, f"homes{b}", sizes[b], firsts[b], full)
        else:
            own = small.shard[np.arange(len(small_home)), small_home]
            counts, far = np.bincount(own, minlength=k), np.full(k, np.nan)
            np.fmax.at(far, own, small.dist[np.arange(len(small_home)), small_home])
        state.update(counts, far)
        left -= sizes[b]
        state.n_left = left
        if cfg.refresh or b == min(sizes):
            state.refresh_quota(left, cfg.quota, cfg.lo, cfg.hi, cfg.margin, cfg.fixed_share)
        boost = radius_boost(b + 1, cfg.blocks, cfg.boost, cfg.b0, cfg.p)
        log += state.rows(b, boost)
        if small_home is not None:
            parts.append(spark.createDataFrame(small.rows(small_home, *small.replicas(small_home, state, cfg, boost), b)))
            continue
        more = assign_replicas(homes, state, cfg, boost, ws, f"repl{b}")
        w = Window.partitionBy("vec_id")
        more = more.withColumn("rank", F.row_number().over(w.orderBy("dist", "shard_id")) + 1).withColumn("n_homes", (F.count("*").over(w) + 1).cast("int"))
        more = ws.write(more, f"replicas{b}")
        per = more.where("rank = 2").select("vec_id", "n_homes")
        own = homes.select("vec_id", "shard_id", "dist").join(per, "vec_id", "left").select("vec_id", "shard_id", F.lit(True).alias("is_home"), "dist", F.lit(1).alias("rank"), F.coalesce("n_homes", F.lit(1)).alias("n_homes"))
        parts.append(own.unionByName(more.withColumn("is_home", F.lit(False))).withColumn("block_id", F.lit(b)))
    out = parts[0] if parts else spark.createDataFrame([], "vec_id bigint, shard_id int, is_home boolean, dist double, rank int, n_homes int, block_id int")
    for x in parts[1:]:
        out = out.unionByName(x)
    return Partitioned(out, spark.createDataFrame(log, LOG_SCHEMA), state)


def replay(rows: Iterator[tuple[int, list[tuple[float, int]]]], capacity: list[int], max_homes: int, eps: Fraction | None = None, boost: float = 1.0, radius2: list[float | None] | None = None, homes_first: bool = False, quota: list[int] | None = None) -> Iterator[tuple[int, int, bool, float, int]]:
    """Strict order: each vector in turn takes its nearest shards with room, one after the other.

    Without ``eps`` this is uniform replication in arrival order. It keeps live counters and so is
    one task's work; it exists for fixtures and to show what order does to fairness.
    """
    size, repl = [0] * len(capacity), [0] * len(capacity)
    num, den = (eps.numerator**2, eps.denominator**2) if eps else (1, 1)
    for vec_id, prefs in rows:
        got, home = 0, None
        for d, s in prefs:
            if got == max_homes:
                break
            if size[s] >= capacity[s]:
                continue
            if home is not None:
                if eps is not None and not d * den < home * num:
                    break
                if eps is not None and radius2 is not None and radius2[s] is not None and not d * den < radius2[s] * num * boost**2:
                    continue
                if quota is not None and repl[s] >= quota[s]:
                    continue
                repl[s] += 1
            size[s] += 1
            got += 1
            yield vec_id, s, home is None, d, got
            home = d if home is None else home


def assign_uniform(prefs: DataFrame, capacity: list[int], max_homes: int = 2, descending: bool = False) -> DataFrame:
    """Uniform replication, strictly in arrival order: compact rows stream through one task.

    The order dependence is the method's own; only lists of a few numbers pass, not vectors.
    """
    one = prefs.coalesce(1).sortWithinPartitions(F.col("vec_id").desc() if descending else F.col("vec_id"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def stream():
            for b in batches:
                for i, p in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    yield i, [(x["dist"], x["shard_id"]) for x in p]

        rows = list(replay(stream(), capacity, max_homes))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
        kinds = (pa.int64(), pa.int32(), pa.bool_(), pa.float64(), pa.int32())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["vec_id", "shard_id", "is_home", "dist", "rank"])

    return one.select("vec_id", "prefs").mapInArrow(run, "vec_id bigint, shard_id int, is_home boolean, dist double, rank int")


def contiguous_split(vectors: DataFrame, k: int) -> DataFrame:
    """Split-only assignment: even slices in id order, one copy each."""
    cut = with_blocks(vectors, k)
    return cut.select("vec_id", F.col("block_id").alias("shard_id"), F.lit(True).alias("is_home"), F.lit(0.0).alias("dist"), F.lit(1).alias("rank"), F.lit(1).alias("n_homes"), F.lit(0).alias("block_id"))


def unsplit(vectors: DataFrame) -> DataFrame:
    return contiguous_split(vectors, 1)


def literal_prefs(spark: SparkSession, rows: list[tuple[int, list[tuple[float, int]]]]) -> DataFrame:
    return spark.createDataFrame(rows, "vec_id bigint, prefs array<struct<dist:double,shard_id:int>>")
