"""Exact, merged-graph and split-only k-nearest-neighbour search."""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardgraph.operators.arrays import lists, matrix, sq_distances
from shardgraph.operators.beams import batch_size, compact, distinct, padded, pair_distances, search_beams
from shardgraph.operators.builders.robust import medoid
from shardgraph.workspace import Workspace

RESIDENT_BYTES = 2 << 30
QUERY_BYTES = 256 << 20
#: Distances that a task of an exact search holds at once: 16 MB.
EXACT_CELLS = 2_000_000
RESULT = "query_id bigint, vec_id bigint, dist double"
LOGGED = "query_id bigint, vec_id bigint, dist double, hops bigint, dist_count bigint, reads bigint, seconds double"

COUNTERS = ("hops", "dist_count", "reads", "seconds")


class Queries(NamedTuple):
    ids: np.ndarray
    x: np.ndarray


def load_queries(queries: DataFrame, col: str = "q", id_col: str = "query_id") -> Queries:
    """Query vectors on the driver for a broadcast, after a check of their size."""
    n = queries.count()
    dim = queries.select(F.size(col)).first()
    if n and n * dim[0] * 8 > QUERY_BYTES:
        raise ValueError("too many queries to broadcast; search them in blocks")
    t = queries.select(id_col, col).orderBy(id_col).toArrow()
    return Queries(t.column(0).to_numpy(), matrix(t.column(1)))


def query_blocks(queries: DataFrame, blocks: int, id_col: str = "query_id") -> list[DataFrame]:
    """Splits a query set that is over the broadcast bound; each block is searched against all rows."""
    return [queries.where(F.pmod(F.xxhash64(id_col), F.lit(blocks)) == b) for b in range(blocks)]


def _top(rows: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def k_nearest(d: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distances and ids of the k smallest entries of each row by (distance, id); the rest of a row is never sorted."""
    if k < d.shape[1]:
        at = np.argpartition(d, k - 1, axis=1)[:, :k]
        worst = np.take_along_axis(d, at, axis=1).max(axis=1, keepdims=True)
        for i in np.flatnonzero((d <= worst).sum(axis=1) > k).tolist():  # a tie at the cut
            near = np.flatnonzero(d[i] <= worst[i])
            at[i] = near[np.lexsort((ids[i, near], d[i, near]))[:k]]
        d, ids = np.take_along_axis(d, at, axis=1), np.take_along_axis(ids, at, axis=1)
    order = np.lexsort((ids, d), axis=1)
    return np.take_along_axis(d, order, axis=1), np.take_along_axis(ids, order, axis=1)


def search_exact(vectors: DataFrame, queries: DataFrame, k: int, col: str = "q") -> DataFrame:
    """Rows (query_id, rank, vec_id, dist): k nearest by (squared distance, id).

    One pass: each task keeps k rows per query over all its batches, so the shuffle is k x queries
    per task; the queries are broadcast after a check of their size, and a task holds ``EXACT_CELLS``
    distances at once, whatever the number of queries.
    """
    shared = vectors.sparkSession.sparkContext.broadcast(tuple(load_queries(queries, col)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = Queries(*shared.value)
        best_d, best_i = np.full((len(q.ids), k), np.inf), np.full((len(q.ids), k), np.iinfo(np.int64).max)
        for b in batches:
            if b.num_rows and len(q.ids):
                ids, x = b.column(0).to_numpy(), matrix(b.column(1))
                rows = max(1, EXACT_CELLS // len(ids))
                for a in range(0, len(q.ids), rows):
                    d = sq_distances(q.x[a : a + rows], x)
                    near_d, near_i = k_nearest(d, np.broadcast_to(ids, d.shape), k)
                    best_d[a : a + rows], best_i[a : a + rows] = k_nearest(np.c_[best_d[a : a + rows], near_d], np.c_[best_i[a : a + rows], near_i], k)
        real = np.isfinite(best_d)
        yield pa.RecordBatch.from_pydict({"query_id": pa.array(np.repeat(q.ids, real.sum(axis=1))), "vec_id": pa.array(best_i[real]), "dist": pa.array(best_d[real])})

    return _top(vectors.select("vec_id", col).mapInArrow(run, RESULT), k).select("query_id", "rank", "vec_id", "dist")


class Found(NamedTuple):
    at: np.ndarray
    dist: np.ndarray
    hops: int
    dist_count: int
    reads: int


def beam_search(x: np.ndarray, graph: list[np.ndarray], entries: np.ndarray, q: np.ndarray, beam: int, width: int = 1) -> Found:
    """``search_beams`` for one query, in plain steps: expand the ``width`` nearest unexpanded nodes of the beam until none is left; ties by position."""
    entries = np.unique(entries)
    seen = np.zeros(len(x), bool)
    seen[entries] = True
    node = entries
    dist = np.einsum("ij,ij->i", x[node] - q, x[node] - q)
    order = np.lexsort((node, dist))[:beam]
    node, dist, done = node[order], dist[order], np.zeros(len(order), bool)
    hops, count, reads = 0, len(entries), 0
    while not done.all():
        now = np.flatnonzero(~done)[:width]
        done[now] = True
        hops, reads = hops + 1, reads + len(now)
        new = np.unique(np.concatenate([graph[i] for i in node[now].tolist()]))
        new = new[~seen[new]]
        if len(new):
            seen[new] = True
            count += len(new)
            diff = x[new] - q
            node, dist = np.r_[node, new], np.r_[dist, np.einsum("ij,ij->i", diff, diff)]
            done = np.r_[done, np.zeros(len(new), bool)]
            order = np.lexsort((node, dist))[:beam]
            node, dist, done = node[order], dist[order], done[order]
    return Found(node, dist, hops, count, reads)


def search_range(vectors: DataFrame, queries: DataFrame, most: float, col: str = "q") -> DataFrame:
    """Rows (query_id, vec_id, dist): all vectors up to a squared distance of ``most``, by blocks of matrix products."""
    shared = vectors.sparkSession.sparkContext.broadcast(tuple(load_queries(queries, col)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = Queries(*shared.value)
        for b in batches:
            ids, x = b.column(0).to_numpy(), matrix(b.column(1))
            rows = max(1, EXACT_CELLS // max(1, len(ids)))
            for a in range(0, len(q.ids) if len(ids) else 0, rows):
                d = sq_distances(q.x[a : a + rows], x)
                i, j = np.nonzero(d <= most)
                yield pa.RecordBatch.from_pydict({"query_id": pa.array(q.ids[a + i]), "vec_id": pa.array(ids[j]), "dist": pa.array(d[i, j])})

    return vectors.select("vec_id", col).mapInArrow(run, RESULT)


def reachable(graph: np.ndarray, entries: np.ndarray) -> np.ndarray:
    """Nodes that paths from the entries reach."""
    seen = np.zeros(len(graph), bool)
    seen[entries] = True
    now = np.flatnonzero(seen)
    while len(now):
        near = np.unique(graph[now])
        now = near[(near >= 0) & ~seen[near]]
        seen[now] = True
    return np.flatnonzero(seen)


def _positions(ids: np.ndarray, nbrs: pa.Array) -> np.ndarray:
    """Neighbour lists as positions in ``ids`` (sorted), -1 behind the last; edges to unknown ids are dropped, repeated ones count once."""
    if isinstance(nbrs, pa.ChunkedArray):
        nbrs = nbrs.combine_chunks()
    flat = nbrs.flatten().field("id").to_numpy(zero_copy_only=False)
    at = np.searchsorted(ids, flat)
    known = (at < len(ids)) & (ids[np.minimum(at, len(ids) - 1)] == flat)
    offsets = nbrs.offsets.to_numpy()
    offsets = offsets - offsets[0]
    return distinct(padded([at[a:b][known[a:b]] for a, b in zip(offsets, offsets[1:], strict=False)]))


def _search_rows(ids, x, graph, entries, q: Queries, beam, width, k) -> pa.RecordBatch:
    """The k nearest of each query's beam; a batch of queries is timed as a whole, its seconds dealt by distances.

    A beam that holds all nodes drops none, so it ends with all that the entries reach: these are
    compared by a matrix product then, with the counters that the search would have.
    """
    import time

    beam, entries = max(beam, k), np.unique(entries)
    whole = reachable(graph, entries) if width == 1 and beam >= len(ids) else None
    out: dict[str, list] = {c.split()[0]: [] for c in LOGGED.split(", ")}
    step = batch_size(len(ids))
    for a in range(0, len(q.ids), step):
        some, began = q.x[a : a + step], time.perf_counter()
        if whole is not None:
            dist, node = k_nearest(sq_distances(some, x[whole]), np.broadcast_to(whole, (len(some), len(whole))), min(k, len(whole)))
            hops = count = reads = np.full(len(some), len(whole), np.int64)
        else:
            f = search_beams(x, graph, np.broadcast_to(entries, (len(some), len(entries))), some, beam, width)
            node, dist, hops, count, reads = f.node[:, :k], f.dist[:, :k], f.hops, f.dist_count, f.reads
        took = (time.perf_counter() - began) * count / max(1, count.sum())
        real = node >= 0
        of = np.nonzero(real)[0]
        for name, v in (("query_id", q.ids[a : a + step][of]), ("vec_id", ids[node[real]]), ("dist", dist[real]), ("hops", hops[of]), ("dist_count", count[of]), ("reads", reads[of]), ("seconds", took[of])):
            out[name].append(v)
    kinds = {"query_id": pa.int64(), "vec_id": pa.int64(), "dist": pa.float64(), "hops": pa.int64(), "dist_count": pa.int64(), "reads": pa.int64(), "seconds": pa.float64()}
    return pa.RecordBatch.from_pydict({c: pa.array(np.concatenate(v) if v else [], kinds[c]) for c, v in out.items()})


def hold_resident(graph: DataFrame, vectors: DataFrame, entry: str = "medoid", centroids: np.ndarray | None = None, col: str = "q", max_bytes: int = RESIDENT_BYTES) -> Broadcast:
    """A merged graph with its vectors and entries as a broadcast, for any number of searches; refuses one over ``max_bytes``."""
    spark = graph.sparkSession
    nodes = graph.join(vectors.select("vec_id", F.col(col).alias("x")), "vec_id").select("vec_id", "nbrs", "x")
    size = nodes.agg(F.coalesce(F.sum(F.size("nbrs") * 8 + F.size("x") * 8 + 8), F.lit(0))).first()[0]
    if size > max_bytes:
        raise ValueError(f"the graph takes {size} bytes; search it by frontier or routed")
    t = nodes.orderBy("vec_id").toArrow()
    ids, x = t.column("vec_id").to_numpy(), matrix(t.column("x"))
    graph_at = _positions(ids, t.column("nbrs"))
    entries = np.array([medoid(x)]) if len(x) else np.empty(0, np.int64)
    if entry == "centroids" and centroids is not None:
        entries = np.r_[entries, sq_distances(centroids, x).argmin(axis=1)]
    return spark.sparkContext.broadcast((ids, compact(x), graph_at, entries))


def search_resident(graph: DataFrame, vectors: DataFrame, queries: DataFrame, k: int, beam: int, width: int = 1, entry: str = "medoid", centroids: np.ndarray | None = None, slices: int = 8, col: str = "q", max_bytes: int = RESIDENT_BYTES, held: Broadcast | None = None) -> DataFrame:
    """Merged-graph search with the graph in each executor's memory; queries are split over tasks.

    Rows (query_id, rank, vec_id, dist, hops, dist_count, reads, seconds). Refuses a graph over
    ``max_bytes``, where ``search_frontier`` and ``search_routed`` apply. ``held`` is the graph as
    ``hold_resident`` gave it, so that further searches do not gather it again.
    """
    shared = held or hold_resident(graph, vectors, entry, centroids, col, max_bytes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x, graph_at, entries = shared.value
        for b in batches:
            if b.num_rows and len(ids):
                yield _search_rows(ids, x, graph_at, entries, Queries(b.column(0).to_numpy(), matrix(b.column(1))), beam, width, k)

    found = queries.select("query_id", F.col(col)).repartition(slices, "query_id").mapInArrow(run, LOGGED)
    return _top(found, k)


def search_split(graphs: DataFrame, vectors: DataFrame, queries: DataFrame, k: int, beam: int, shards: int, width: int = 1, col: str = "q", probes: DataFrame | None = None) -> DataFrame:
    """Split-only search: local top k in the graph of every shard, then pooled and ranked again.

    ``dist_count``, ``hops`` and ``seconds`` of a query are sums over the shards it visits. With
    ``probes(query_id, shard_id)`` only those shards are searched (routed serving of a merged
    graph's shards). An id found in two shards counts once.
    """
    shared = graphs.sparkSession.sparkContext.broadcast(tuple(load_queries(queries, col)))
    nodes = graphs.join(vectors.select("vec_id", F.col(col).alias("x")), "vec_id").select("shard_id", "vec_id", "nbrs", "x")
    routes = None
    if probes is not None:
        routes = {}
        for r in probes.select("query_id", "shard_id").collect():
            routes.setdefault(r.shard_id, set()).add(r.query_id)
        routes = graphs.sparkSession.sparkContext.broadcast(routes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        shard = t.column("shard_id").to_numpy()
        for s in np.unique(shard).tolist():
            part = t.filter(pa.array(shard == s))
            part = part.take(pa.array(np.argsort(part.column("vec_id").to_numpy(), kind="stable")))
            ids, x, q = part.column("vec_id").to_numpy(), matrix(part.column("x")), Queries(*shared.value)
            if routes is not None:
                m = np.isin(q.ids, list(routes.value.get(s, ())))
                q = Queries(q.ids[m], q.x[m])
            if len(q.ids):
                rows = _search_rows(ids, x, _positions(ids, part.column("nbrs")), np.array([medoid(x)]), q, beam, width, k)
                yield rows.append_column("shard_id", pa.array(np.full(rows.num_rows, s, np.int32)))

    local = nodes.repartitionById(shards, "shard_id").mapInArrow(run, LOGGED + ", shard_id int")
    # a shard's counters stand on each of its rows
    once = local.groupBy("query_id", "shard_id").agg(*[F.first(c).alias(c) for c in COUNTERS])
    sums = once.groupBy("query_id").agg(*[F.sum(c).alias(c) for c in COUNTERS])
    pooled = local.groupBy("query_id", "vec_id").agg(F.min("dist").alias("dist"))
    return _top(pooled, k).join(sums, "query_id")


def search_routed(graphs: DataFrame, vectors: DataFrame, queries: DataFrame, prefs: DataFrame, k: int, beam: int, shards: int, probes: int, col: str = "q") -> DataFrame:
    """Serving over sharded executors: a query visits the shards of its ``probes`` nearest centroids; ``prefs`` are its preference lists."""
    picked = prefs.select(F.col("vec_id").alias("query_id"), F.explode(F.slice("prefs", 1, probes)).alias("p")).select("query_id", "p.shard_id")
    return search_split(graphs, vectors, queries, k, beam, shards, col=col, probes=picked)


def frontier_hop(graph: DataFrame, vectors: DataFrame, queries: DataFrame, beam_rows: DataFrame, visited: DataFrame, beam: int, width: int = 1, col: str = "q", pushed: int = 0) -> DataFrame:
    """One hop of all queries as a plan: (query_id, vec_id, dist, expanded, fresh) of the next beam.

    Expands the ``width`` nearest unexpanded nodes per query, joins their edges by id, drops what
    was visited, computes distances in the JVM and keeps the ``beam`` nearest.
    """
    from shardgraph.functions.vectors import l2sq

    w = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    now = beam_rows.where("not expanded").withColumn("r", F.row_number().over(w)).where(F.col("r") <= width).select("query_id", "vec_id")
    new = now.join(_only(graph.select("vec_id", "nbrs"), now, pushed), "vec_id").select("query_id", F.explode("nbrs.id").alias("vec_id")).distinct()
    new = new.join(visited, ["query_id", "vec_id"], "left_anti")
    kind = "double" if "float" in vectors.schema[col].dataType.simpleString() or "double" in vectors.schema[col].dataType.simpleString() else "bigint"
    far = new.join(_only(vectors.select("vec_id", F.col(col).alias("x")), new, pushed), "vec_id").join(queries.select("query_id", F.col(col).alias("y")), "query_id")
    far = far.select("query_id", "vec_id", l2sq(F.col("x"), F.col("y"), kind).cast("double").alias("dist"), F.lit(False).alias("expanded"), F.lit(True).alias("fresh"))
    old = beam_rows.join(now.withColumn("just", F.lit(True)), ["query_id", "vec_id"], "left")
    old = old.select("query_id", "vec_id", "dist", (F.col("expanded") | F.col("just").isNotNull()).alias("expanded"), F.lit(False).alias("fresh"))
    ranked = old.unionByName(far).withColumn("r", F.row_number().over(w))
    return ranked.withColumn("kept", F.col("r") <= beam).drop("r")


def search_frontier(graph: DataFrame, vectors: DataFrame, queries: DataFrame, k: int, beam: int, entry_ids: list[int], width: int = 4, max_hops: int = 500, col: str = "q", pushed: int = 0) -> DataFrame:
    """Merged-graph search for large offline batches: a hop is a distributed plan, its result a written table.

    Rows (query_id, rank, vec_id, dist, hops, dist_count, reads). ``reads`` counts node records
    fetched, the measure of a graph on disk; files ranged by id let each fetch prune.
    """
    spark = graph.sparkSession
    ws = Workspace(spark, "frontier")
    start = spark.createDataFrame([(int(i),) for i in entry_ids], "vec_id bigint")
    from shardgraph.functions.vectors import l2sq

    kind = "double" if vectors.schema[col].dataType.simpleString() in ("array<float>", "array<double>") else "bigint"
    first = start.join(vectors.select("vec_id", F.col(col).alias("x")), "vec_id").join(F.broadcast(queries.select("query_id", F.col(col).alias("y"))))
    rows = first.select("query_id", "vec_id", l2sq(F.col("x"), F.col("y"), kind).cast("double").alias("dist"), F.lit(False).alias("expanded"))
    beam_rows = ws.write(rows, "beam0")
    visited = ws.write(beam_rows.select("query_id", "vec_id"), "visited0")
    log = ws.write(beam_rows.groupBy("query_id").agg(F.lit(0).cast("bigint").alias("hops"), F.count("*").alias("dist_count"), F.lit(0).cast("bigint").alias("reads")), "log0")
    for h in range(1, max_hops + 1):
        todo = beam_rows.where("not expanded").groupBy("query_id").agg(F.least(F.count("*"), F.lit(width)).alias("r"))
        if todo.isEmpty():
            break
        nxt = ws.write(frontier_hop(graph, vectors, queries, beam_rows, visited, beam, width, col, pushed), f"hop{h}")
        grown = nxt.groupBy("query_id").agg(F.sum(F.col("fresh").cast("bigint")).alias("d"))
        log = ws.write(
            log.join(todo, "query_id", "left").join(grown, "query_id", "left").select(
                "query_id", (F.col("hops") + F.col("r").isNotNull().cast("bigint")).alias("hops"), (F.col("dist_count") + F.coalesce("d", F.lit(0))).alias("dist_count"), (F.col("reads") + F.coalesce("r", F.lit(0))).alias("reads")
            ),
            f"log{h}",
        )
        visited = ws.write(visited.unionByName(nxt.where("fresh").select("query_id", "vec_id")), f"visited{h}")
        beam_rows = nxt.where("kept").select("query_id", "vec_id", "dist", "expanded")
    return _top(beam_rows.select("query_id", "vec_id", "dist"), k).join(log, "query_id")


def entry_nodes(vectors: DataFrame, centroids: np.ndarray, col: str = "q") -> list[int]:
    """Ids nearest to the centroids, one scan; ties to the lower id."""
    queries = vectors.sparkSession.createDataFrame([(i, [float(v) for v in c]) for i, c in enumerate(centroids)], f"query_id bigint, {col} array<double>")
    return sorted({r.vec_id for r in search_exact(vectors, queries, 1, col).collect()})


#: Record ids that a hop pushes to the scan of node files as a list; more of them are picked by the tasks.
PUSHED_IDS = 10_000
#: Queries whose beams and visited ids the driver holds at once.
HELD_QUERIES = 2_000


def search_nodes(spark: SparkSession, path: str, queries: DataFrame, k: int, beam: int, entry_ids: list[int], width: int = 4, max_hops: int = 500, col: str = "q") -> DataFrame:
    """``search_frontier`` over the node files that ``write_nodes`` left: no table of graph or vectors is kept elsewhere.

    A hop is one job: it reads the records that the queries meet now, and a record gives its distances
    and its edges, which the driver keeps for when it is expanded. Beams of ``HELD_QUERIES`` queries
    are held at a time. The files are ranged and sorted by id, so a list of ids prunes files and row groups.
    """
    nodes = spark.read.parquet(path).select("vec_id", F.col("nbrs.id").alias("nbrs"), F.col("embedding").alias("x"))
    q, out = load_queries(queries, col), []
    for a in range(0, len(q.ids), HELD_QUERIES):
        out += _search_held(nodes, Queries(q.ids[a : a + HELD_QUERIES], q.x[a : a + HELD_QUERIES]), k, beam, entry_ids, width, max_hops)
    return spark.createDataFrame(out, "query_id bigint, vec_id bigint, dist double, rank int, hops bigint, dist_count bigint, reads bigint")


def _search_held(nodes: DataFrame, q: Queries, k: int, beam: int, entry_ids: list[int], width: int, max_hops: int) -> list[tuple]:
    sc, edges = nodes.sparkSession.sparkContext, {}
    shared = sc.broadcast(q.x)

    def met(new: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray]]:
        """Ids and distances of each query's new records, as far as they are there; their edges are kept."""
        of, ids = np.repeat(np.arange(len(new)), [len(n) for n in new]), np.concatenate(new)
        if not len(ids):
            return [(n, np.empty(0)) for n in new]
        by = np.lexsort((of, ids))
        of, ids = of[by], ids[by]
        wanted, at = np.unique(ids, return_index=True)
        asked = sc.broadcast((wanted, np.r_[at, len(ids)], of))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            (want, ends, who), queried = asked.value, shared.value
            for b in batches:
                own = b.column(0).to_numpy()
                place = np.minimum(np.searchsorted(want, own), len(want) - 1)
                real = want[place] == own
                b, place = b.filter(pa.array(real)), place[real]
                if not b.num_rows:
                    continue
                n = ends[place + 1] - ends[place]
                row, x = np.repeat(np.arange(len(place)), n), matrix(b.column(2))
                asking = who[np.repeat(ends[place], n) + np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)]
                d = pair_distances(x, row, queried, asking)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), lists(pa.array(asking.astype(np.int64)), n), lists(pa.array(d), n)], names=["vec_id", "nbrs", "of", "d"])

        some = nodes.where("vec_id in (%s)" % ",".join(map(str, wanted.tolist()))) if len(wanted) <= PUSHED_IDS else nodes
        t = some.mapInArrow(run, "vec_id bigint, nbrs array<bigint>, of array<bigint>, d array<double>").toArrow()
        found = t.column("vec_id").to_numpy()
        edges.update(zip(found.tolist(), (np.array(e, np.int64) for e in t.column("nbrs").to_pylist()), strict=True))
        n = pc.list_value_length(t.column("of")).to_numpy()
        of, ids, d = pc.list_flatten(t.column("of")).to_numpy(), np.repeat(found, n), pc.list_flatten(t.column("d")).to_numpy()
        by = np.lexsort((ids, of))
        of, ids, d = of[by], ids[by], d[by]
        cut = np.searchsorted(of, np.arange(len(new) + 1))
        return [(ids[i:j], d[i:j]) for i, j in zip(cut, cut[1:], strict=False)]

    n = len(q.ids)
    first = met([np.unique(np.array(entry_ids, np.int64))] * n)
    node, dist = [f[0] for f in first], [f[1] for f in first]
    done, seen = [np.zeros(len(i), bool) for i in node], [set(i.tolist()) for i in node]
    hops, count, reads = np.zeros(n, np.int64), np.array([len(i) for i in node], np.int64), np.zeros(n, np.int64)
    for _ in range(max_hops):
        new = []
        for i in range(n):
            todo = np.flatnonzero(~done[i])
            now = todo[np.lexsort((node[i][todo], dist[i][todo]))[:width]]
            done[i][now] = True
            hops[i] += len(now) > 0
            reads[i] += len(now)
            new.append(np.array(sorted({e for v in node[i][now].tolist() for e in edges[v].tolist()} - seen[i]), np.int64))
        if all(d.all() for d in done) and not any(map(len, new)):
            break
        for i, (ids, d) in enumerate(met(new)):
            seen[i].update(ids.tolist())
            count[i] += len(ids)
            ids, d, old = np.r_[node[i], ids], np.r_[dist[i], d], np.r_[done[i], np.zeros(len(ids), bool)]
            by = np.lexsort((ids, d))[:beam]
            node[i], dist[i], done[i] = ids[by], d[by], old[by]
    rows = []
    for i in range(n):
        by = np.lexsort((node[i], dist[i]))[:k]
        rows += [(int(q.ids[i]), int(node[i][j]), float(dist[i][j]), r + 1, int(hops[i]), int(count[i]), int(reads[i])) for r, j in enumerate(by)]
    return rows


def _only(rows: DataFrame, ids: DataFrame, pushed: int) -> DataFrame:
    """``rows`` of the ids, as a pushed-down list while that is short."""
    got = [r.vec_id for r in ids.select("vec_id").distinct().limit(pushed + 1).collect()] if pushed else []
    return rows.where(F.col("vec_id").isin(got)) if pushed and len(got) <= pushed else rows


def entry_node(vectors: DataFrame, col: str = "q") -> int:
    """Id nearest to the mean: two aggregates, nothing collected but the mean."""
    from shardgraph.functions.vectors import l2sq

    parts = vectors.select(F.posexplode(col).alias("pos", "v")).groupBy("pos").agg(F.avg(F.col("v").cast("double")).alias("m")).orderBy("pos").collect()
    mean = F.array(*[F.lit(float(r.m)) for r in parts])
    return vectors.select("vec_id", l2sq(F.col(col), mean, "double").alias("d")).agg(F.min_by("vec_id", F.struct("d", "vec_id"))).first()[0]
