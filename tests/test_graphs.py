import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from shardgraph.operators import beams, metrics, search
from shardgraph.operators.build import build_shards, edges_of
from shardgraph.operators.builders import BUILDERS, knn_exact
from shardgraph.operators.builders.detour import detours
from shardgraph.operators.builders.robust import prune
from shardgraph.operators.merge import POLICIES, merge_graphs
from shardgraph.operators.partition import contiguous_split, unsplit
from shardgraph.plans.pipelines import METHODS, RunConfig, run


def cloud(n, d=8, seed=0):
    return np.random.default_rng(seed).integers(-100, 100, (n, d)).astype(float)


def frame(spark, x):
    return spark.createDataFrame([(i, [int(v) for v in row]) for i, row in enumerate(x)], "vec_id bigint, q array<int>")


@pytest.mark.parametrize("name", list(BUILDERS))
@pytest.mark.parametrize("n", [1, 2, 9, 150])
def test_degrees(name, n):
    g = BUILDERS[name](np.arange(n), cloud(n), 8, 16)
    assert g.shape == (n, min(8, n - 1))
    for u, row in enumerate(g):
        row = row[row >= 0].tolist()
        assert u not in row and len(set(row)) == len(row)
        assert n == 1 or row
        if name in ("knn_exact", "knn_detour", "knn_descent"):
            assert len(row) == min(8, n - 1)


def test_exact_lists_and_ties():
    x = np.array([[0.0], [1], [1], [2]])
    assert knn_exact(np.arange(4), x, 2).tolist() == [[1, 2], [2, 0], [1, 0], [1, 2]]
    assert knn_exact(np.arange(5), np.zeros((5, 2)), 2).tolist() == [[1, 2], [0, 2], [0, 1], [0, 1], [0, 1]]


def test_descent_recall():
    x = cloud(600, 6)
    truth, got = knn_exact(np.arange(600), x, 10), BUILDERS["knn_descent"](np.arange(600), x, 10, 20)
    assert np.mean([len(set(a) & set(b)) / 10 for a, b in zip(truth, got, strict=True)]) > 0.9


def test_detours_by_definition():
    lists = knn_exact(np.arange(40), cloud(40, 3), 6)
    want = np.zeros_like(lists)
    for u in range(40):
        for j, v in enumerate(lists[u]):
            want[u, j] = sum(v in lists[w][:j].tolist() for w in lists[u][:j])
    assert (detours(lists) == want).all()


@pytest.mark.parametrize("name", list(BUILDERS))
def test_search_finds_neighbours(name):
    x = cloud(400, 6, 2)
    g = BUILDERS[name](np.arange(400), x, 16, 32)
    graph = [r[r >= 0] for r in g]
    truth = knn_exact(np.arange(400), x, 10)
    hit = []
    for q in range(0, 400, 10):
        f = search.beam_search(x, graph, np.array([0]), x[q], 60)
        hit.append(len(set(f.at[:11].tolist()) & set(truth[q].tolist())) / 10)
    assert np.mean(hit) > (0.6 if name == "knn_exact" else 0.8)


def test_merge_policies_ignore_order(spark):
    rows = [(0, 1, [(2, 4.0), (3, 1.0)]), (1, 1, [(3, 1.0), (5, 2.0)]), (0, 2, [(1, 4.0)])]
    schema = "shard_id int, vec_id bigint, nbrs array<struct<id:bigint,d:double>>"
    for policy in POLICIES[:3]:
        got = [{r.vec_id: [e.id for e in r.nbrs] for r in merge_graphs(spark.createDataFrame(x, schema), 2, policy).collect()} for x in (rows, rows[::-1])]
        assert got[0] == got[1]
    assert got[0][2] == [1]
    union = {r.vec_id: [e.id for e in r.nbrs] for r in merge_graphs(spark.createDataFrame(rows, schema), 2, "union").collect()}
    assert union[1] == [3, 5, 2]
    near = {r.vec_id: [e.id for e in r.nbrs] for r in merge_graphs(spark.createDataFrame(rows, schema), 2).collect()}
    assert near[1] == [3, 5]


def test_wide_beam_is_exact_and_frontier_agrees(spark):
    x = cloud(120, 5, 3)
    v = frame(spark, x)
    graph = build_shards(unsplit(v), v, "robust", 12, 24, 1).select("vec_id", "nbrs").cache()
    q = v.where("vec_id % 12 = 0").select(F.col("vec_id").alias("query_id"), "q")
    truth = {(r.query_id, r.rank): r.vec_id for r in search.search_exact(v, q, 10).collect()}
    wide = {(r.query_id, r.rank): r.vec_id for r in search.search_resident(graph, v, q, 10, 120).collect()}
    assert wide == truth
    entry = search.entry_node(v)
    front = search.search_frontier(graph, v, q, 10, 120, [entry], 16)
    assert {(r.query_id, r.rank): r.vec_id for r in front.collect()} == truth


def test_split_search_pools_all_shards(spark):
    x = cloud(90, 4, 5)
    v = frame(spark, x)
    g = build_shards(contiguous_split(v, 3), v, "knn_exact", 100, 0, 3)
    q = v.where("vec_id % 9 = 0").select(F.col("vec_id").alias("query_id"), "q")
    a = {(r.query_id, r.rank): r.vec_id for r in search.search_split(g, v, q, 5, 200, 3).collect()}
    b = {(r.query_id, r.rank): r.vec_id for r in search.search_exact(v, q, 5).collect()}
    assert a == b


def test_resident_refuses_large_graphs(spark):
    v = frame(spark, cloud(30))
    g = build_shards(unsplit(v), v, "knn_exact", 4, 4, 1).select("vec_id", "nbrs")
    with pytest.raises(ValueError):
        search.search_resident(g, v, v.select(F.col("vec_id").alias("query_id"), "q"), 3, 8, max_bytes=10)


@pytest.mark.parametrize("method", METHODS)
def test_pipelines(spark, method):
    v = frame(spark, cloud(160, 6, 7))
    h = run(method, v, RunConfig(k=3, degree=10, working=20, blocks=2, iters=3))
    q = v.where("vec_id % 16 = 0").select(F.col("vec_id").alias("query_id"), "q")
    found = h.search(q, 5, 60)
    r = metrics.recall_at_k(found, search.search_exact(v, q, 5), 5).first()
    assert r.n_queries == 10
    assert r.recall >= (0.3 if method == "no_replica" else 0.8)
    share = metrics.replicated_share(h.assignment).first()
    assert share.n_vectors == 160
    assert (share.share == 0) == (method.startswith(("split", "unsplit")) or method == "no_replica")
    if method in ("uniform_merge", "replicate_all"):
        assert share.share == 1


def test_merged_beats_split_in_work(spark):
    """At like recall a merged graph takes fewer distances than visiting every shard."""
    v = frame(spark, cloud(500, 6, 9))
    q = v.where("vec_id % 25 = 0").select(F.col("vec_id").alias("query_id"), "q")
    truth = search.search_exact(v, q, 10)
    work = {}
    for method in ("selective_merge", "split_knn"):
        h = run(method, v, RunConfig(k=5, degree=16, working=32, blocks=2, iters=4))
        found = h.search(q, 10, 40 if method == "selective_merge" else 20).cache()
        assert metrics.recall_at_k(found, truth).first().recall > 0.9
        work[method] = metrics.search_work(found).first().mean_dist_count
    assert work["selective_merge"] < work["split_knn"]


def test_shape_on_hashed_documents(spark):
    """The published shape on whole documents: like recall with far fewer distances than split search, builds under twice a split's."""
    from fractions import Fraction

    from compare import SF
    from shardgraph.plans.workloads import dataset, split_queries

    base, queries = split_queries(dataset(spark, SF, "d768"), 50)
    truth = search.search_exact(base, queries, 10)
    cfg, got = RunConfig(k=8, degree=16, working=32, eps=Fraction(12, 10), blocks=3, iters=6), {}
    for method, beam in (("selective_merge", 64), ("split_knn", 16)):
        h = run(method, base, cfg)
        found = h.search(queries, 10, beam).cache()
        got[method] = (metrics.recall_at_k(found, truth).first().recall, metrics.search_work(found).first().mean_dist_count)
    assert got["selective_merge"][0] >= 0.95
    assert got["selective_merge"][1] < 0.7 * got["split_knn"][1]


def test_split_query_searches_every_query(spark, monkeypatch):
    from shardgraph.plans import methods

    asked = []
    monkeypatch.setattr(methods.search, "search_split", lambda g, base, queries, *a: asked.append(queries.count()) or methods.search.search_exact(base, queries, 10))
    methods.q_search_split_exact(spark, "/root/testdata/sf0.001")
    assert asked == [methods.held_out(spark, "/root/testdata/sf0.001")[1].count()]


def test_split_search_sums_equal_shards(spark):
    """Two shards of equal shape have equal counters; each counts."""
    from shardgraph.operators.build import build_shards, edges_of
    from shardgraph.operators.search import search_split

    x = [(i, [i % 10, 7 * (i % 10) % 11]) for i in range(20)]
    v = spark.createDataFrame(x, "vec_id bigint, q array<int>")
    a = v.select("vec_id", (F.col("vec_id") / 10).cast("int").alias("shard_id"))
    q = spark.createDataFrame([(0, [3, 3])], "query_id bigint, q array<int>")
    g = build_shards(a, v, "knn_exact", 4, 8, 2)
    one = search_split(g.where("shard_id = 0"), v, q, 5, 10, 2).first()
    both = search_split(g, v, q, 5, 10, 2).first()
    assert (both.hops, both.dist_count, both.reads) == (2 * one.hops, 2 * one.dist_count, 2 * one.reads)


def test_an_interrupted_build_goes_on(spark, tmp_path):
    from shardgraph.operators.build import build_in_waves, build_shards

    rng = np.random.default_rng(0)
    v = spark.createDataFrame([(i, [int(z) for z in rng.integers(0, 50, 3)]) for i in range(120)], "vec_id bigint, q array<int>")
    a = v.select("vec_id", (F.col("vec_id") % 4).cast("int").alias("shard_id"))
    path = str(tmp_path / "graphs")
    build_in_waves(a.where("shard_id < 3"), v, "knn_exact", 5, 8, 4, path, wave=2)
    before = {p: p.stat().st_mtime_ns for p in (tmp_path / "graphs").rglob("*.parquet")}
    got = build_in_waves(a, v, "knn_exact", 5, 8, 4, path, wave=2)
    want = build_shards(a, v, "knn_exact", 5, 8, 4)
    assert sorted(map(str, got.collect())) == sorted(map(str, want.collect()))
    assert all(p.stat().st_mtime_ns == t for p, t in before.items()) and len(before) >= 3


def test_faults_show_in_graph_checks(spark):
    from shardgraph.plans.methods import _misses_nearest

    first = spark.createDataFrame([(i, i + 1) for i in range(10)], "vec_id bigint, first bigint")
    good = first.select("vec_id", F.array("first").alias("ids"))
    assert _misses_nearest(good, first, ["vec_id"], 0.9).first()[0] == 0
    assert _misses_nearest(good.withColumn("ids", F.array().cast("array<bigint>")), first, ["vec_id"], 0.9).first()[0] == 10


def test_exact_search_in_blocks_keeps_ties_by_id(spark, monkeypatch):
    monkeypatch.setattr(search, "EXACT_CELLS", 50)
    x = cloud(120, 2).astype(int) // 40
    v = frame(spark, x)
    got = {}
    for r in search.search_exact(v, v.where("vec_id < 40").withColumnRenamed("vec_id", "query_id"), 7).collect():
        got.setdefault(r.query_id, {})[r["rank"]] = (r.dist, r.vec_id)
    assert {q: [got[q][i + 1] for i in range(7)] for q in got} == {q: sorted((float(((a - x[q]) ** 2).sum()), i) for i, a in enumerate(x))[:7] for q in range(40)}


@pytest.mark.parametrize("beam,width", [(5, 1), (30, 1), (12, 3)])
def test_searches_of_many_queries_equal_single_ones(beam, width):
    x = cloud(300, 3, 5) // 40
    graph = [np.unique(r[r >= 0]) for r in BUILDERS["robust"](np.arange(300), x, 6, 12)]
    q = cloud(40, 3, 6) // 40
    got = beams.search_beams(x, beams.padded(graph), np.tile([0, 7], (40, 1)), q, beam, width)
    for i, v in enumerate(q):
        f = search.beam_search(x, graph, np.array([0, 7]), v, beam, width)
        n = len(f.at)
        assert (got.node[i, :n].tolist(), got.dist[i, :n].tolist()) == (f.at.tolist(), f.dist.tolist()) and (got.node[i, n:] == -1).all()
        assert (got.hops[i], got.dist_count[i], got.reads[i]) == (f.hops, f.dist_count, f.reads)


def test_prune_by_definition():
    x, ids, rng = cloud(60, 4, 8) // 30, np.arange(60)[::-1].copy(), np.random.default_rng(3)
    cand = np.where(rng.random((20, 30)) < 0.2, -1, rng.integers(0, 60, (20, 30)))
    got = prune(np.arange(20), cand, x, 5, 1.2, ids)
    for u in range(20):
        far, kept = lambda a, b: float(((x[a] - x[b]) ** 2).sum()), []
        for v in sorted(set(cand[u].tolist()) - {-1, u}, key=lambda v: (far(u, v), ids[v])):
            if len(kept) < 5 and all(1.2 * 1.2 * far(w, v) > far(u, v) for w in kept):
                kept.append(v)
        assert got[u][got[u] >= 0].tolist() == kept


def test_a_beam_that_holds_all_nodes_counts_what_the_search_does():
    x = cloud(50, 3, 9)
    graph = [np.array([j for j in (i - 1, i + 1) if 0 <= j < 50 and {i, j} != {39, 40}]) for i in range(50)]
    rows = search._search_rows(np.arange(50) * 3, x, beams.padded(graph), np.array([5]), search.Queries(np.array([1, 2]), x[:2] + 1), 50, 1, 10).to_pylist()
    for i, v in enumerate(x[:2] + 1):
        f = search.beam_search(x, graph, np.array([5]), v, 50)
        assert [(r["vec_id"], r["dist"], r["hops"], r["dist_count"], r["reads"]) for r in rows if r["query_id"] == i + 1] == [(a * 3, d, f.hops, f.dist_count, f.reads) for a, d in zip(f.at[:10].tolist(), f.dist.tolist(), strict=False)]


def test_range_search_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(search, "EXACT_CELLS", 50)
    x = cloud(90, 3).astype(int) // 20
    v = frame(spark, x)
    got = search.search_range(v.where("vec_id % 3 <> 0"), v.where("vec_id % 3 = 0").withColumnRenamed("vec_id", "query_id"), 20).collect()
    far = ((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2)
    assert sorted((r.query_id, r.vec_id, r.dist) for r in got) == [(q, i, far[q, i]) for q in range(0, 90, 3) for i in range(90) if i % 3 and far[q, i] <= 20]


def test_searches_of_an_index_gather_its_graph_once(spark, monkeypatch):
    calls = []
    gather = search.hold_resident
    monkeypatch.setattr("shardgraph.plans.pipelines.hold_resident", lambda *a: calls.append(1) or gather(*a))
    v = frame(spark, cloud(200))
    h = run("selective_merge", v, RunConfig(k=3, degree=8, working=16, blocks=1, iters=2))
    q = v.where("vec_id < 5").withColumnRenamed("vec_id", "query_id")
    for beam in (20, 200):
        got = h.search(q, 3, beam).collect()
        assert len(got) == 15 and all(r.vec_id == r.query_id and r.dist == 0 for r in got if r["rank"] == 1)
    assert len(calls) == 1


def test_refinement_gathers_in_blocks():
    x = cloud(600, 768)
    tracemalloc.start()
    g = BUILDERS["knn_descent"](np.arange(600), x, 12, 24)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 150e6  # 3 GB before
    assert np.mean([len(set(a) & set(b)) / 12 for a, b in zip(g.tolist(), knn_exact(np.arange(600), x, 12).tolist(), strict=True)]) > 0.9


def test_edges_are_measured_in_blocks():
    x, near = cloud(4000, 768), np.tile(np.arange(1, 17), (4000, 1))
    tracemalloc.start()
    got = edges_of(x, np.arange(4000), near)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 120e6  # 788 MB before
    assert got[5].as_py()[2] == {"id": 3, "d": float(((x[5] - x[3]) ** 2).sum())}


def test_exact_lists_of_tiles():
    rng = np.random.default_rng(4)
    for x in (cloud(500, 6), rng.integers(0, 3, (500, 3)).astype(float), cloud(500, 6) + rng.random((500, 6))):
        ids = rng.permutation(9_000)[:500]
        d = ((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2)
        np.fill_diagonal(d, np.inf)
        want = np.stack([np.lexsort((ids, row))[:7] for row in d])
        for tile in (8, 64, 500):
            assert (knn_exact(ids, x, 7, tile=tile) == want).all()


def test_detour_starts_from_exact_lists(monkeypatch):
    from shardgraph.operators.builders import detour

    monkeypatch.setattr(detour, "knn_descent", None)
    x = cloud(21_000, 2, 3)
    g = BUILDERS["knn_detour"](np.arange(21_000), x, 2, 2)
    d = ((x[:50, None, :] - x[None, :, :]) ** 2).sum(axis=2)
    d[np.arange(50), np.arange(50)] = np.inf
    assert (g[:50, 0] == d.argmin(axis=1)).all()


def test_search_of_node_files_takes_a_job_a_hop(spark, tmp_path):
    from shardgraph.operators.merge import write_nodes

    x = cloud(300, 6, 5)
    near, v = knn_exact(np.arange(300), x, 6), frame(spark, x)
    g = spark.createDataFrame([(i, [(int(j), 0.0) for j in row]) for i, row in enumerate(near)], "vec_id bigint, nbrs array<struct<id:bigint,d:double>>")
    write_nodes(g, v, str(tmp_path / "n"), 2)
    queries = spark.createDataFrame([(i, [int(c) for c in x[i] + 3]) for i in range(0, 300, 30)], "query_id bigint, q array<int>")
    spark.sparkContext.setJobGroup("nodes", "nodes")
    found = search.search_nodes(spark, str(tmp_path / "n"), queries, 5, 12, [7, 200], 3)
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("nodes"))
    spark.sparkContext.setJobGroup("after", "after")
    got, hops = {}, 0
    for r in found.orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.dist, r.hops, r.dist_count, r.reads))
        hops = max(hops, r.hops)
    for i in range(0, 300, 30):
        f = search.beam_search(x, list(near), np.array([7, 200]), x[i] + 3, 12, 3)
        assert got[i] == [(n, d, f.hops, f.dist_count, f.reads) for n, d in zip(f.at[:5].tolist(), f.dist[:5].tolist(), strict=True)]
    assert len(got) == 10 and jobs <= hops + 10
