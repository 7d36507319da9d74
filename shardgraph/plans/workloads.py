"""The experiments on the given tables: stage times, ladders, searches, workers, cost."""

from __future__ import annotations

import itertools
import time
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph.operators import cost, metrics, scheduler, search
from shardgraph.operators.build import build_shards
from shardgraph.operators.centroids import fit_centroids, preferences
from shardgraph.operators.merge import write_nodes
from shardgraph.operators.partition import PartitionConfig, ShardPlan, assign_uniform, partition_vectors
from shardgraph.plans.pipelines import RunConfig, run
from shardgraph.registry import CORE, read
from shardgraph.sources import tables
from shardgraph.workspace import Workspace

#: Stand-ins of the published data sets: loader and the eps that suits how isotropic they are.
DATASETS = {
    "e64q": (tables.e64q, Fraction(103, 100)),
    "e64": (lambda spark, sf_dir: tables.e64(spark, sf_dir).withColumnRenamed("embedding", "q"), Fraction(103, 100)),
    "d96": (tables.documents_96, Fraction(12, 10)),
    "d768": (tables.documents_768, Fraction(12, 10)),
    "l4": (tables.lineitem_4, Fraction(12, 10)),
}
BUILT = ("e64q", "e64", "d96", "d768", "l4")
METHODS = ("split_knn", "split_hier", "uniform_merge", "selective_merge")
#: Shards of a stand-in, 4 unless it is named here.
SHARDS = {"l4": 16}
#: Beams of the recall sweeps, and the recall at which methods are compared.
BEAMS, EQUAL_RECALL = (10, 20, 40, 80, 160), 0.95
LADDER = {"l4": (Fraction(11, 10), Fraction(12, 10), Fraction(15, 10), None), "d768": (Fraction(11, 10), Fraction(12, 10), Fraction(15, 10), None), "e64q": (Fraction(101, 100), Fraction(102, 100), Fraction(103, 100), Fraction(105, 100), None)}
METRIC = "experiment string, dataset string, method string, params string, metric string, value double"
SMALL = RunConfig(k=4, degree=12, working=24, blocks=3, iters=5)


def dataset(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A stand-in, whole, as a written table."""
    return Workspace(spark, "data").write(DATASETS[name][0](spark, sf_dir).select("vec_id", "q"), name)


def split_queries(vecs: DataFrame, every: int = 20) -> tuple[DataFrame, DataFrame]:
    held = F.pmod(F.xxhash64("vec_id", F.lit(9)), F.lit(every)) == 0
    return vecs.where(~held), vecs.where(held).select(F.col("vec_id").alias("query_id"), "q")


def frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(*map(str, r[:5]), float(r[5])) for r in rows], METRIC)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Partition, build, merge and search held-out vectors: share, recall and work as rows."""
    base, queries = split_queries(dataset(spark, sf_dir, "e64q"), 10)
    h = run("selective_merge", base, RunConfig(k=4, degree=16, working=32, eps=Fraction(103, 100), blocks=4))
    return frame(spark, _quality("flagship", "e64q", h, base, queries, 64))


def _quality(exp: str, name: str, h, base: DataFrame, queries: DataFrame, beam: int, truth: DataFrame | None = None) -> list[tuple]:
    found = Workspace(base.sparkSession, "found").write(h.search(queries, 10, beam), "f")
    truth = truth if truth is not None else search.search_exact(base, queries, 10)
    r, w, s = metrics.recall_at_k(found, truth).first(), metrics.search_work(found).first(), metrics.replicated_share(h.assignment).first()
    p = f"beam={beam}"
    return [(exp, name, h.method, p, m, v) for m, v in (("recall", r.recall), ("dist_count", w.mean_dist_count), ("mean_ms", w.mean_ms), ("qps", w.qps), ("hops", w.mean_hops), ("reads", w.mean_reads), ("replicated_share", s.share))]


@CORE.query("exp_stage_breakdown")
def exp_stage_breakdown(spark, sf_dir):
    """Stages of uniform replication at two degrees."""
    rows = []
    sets = {n: dataset(spark, sf_dir, n) for n in ("e64q", "d768")}
    for name, (r, l) in itertools.product(sets, ((8, 16), (16, 32))):
        h = run("uniform_merge", sets[name], RunConfig(k=4, degree=r, working=l, iters=4))
        rows += [("stages", name, h.method, f"R={r} L={l}", s, v) for s, v in h.seconds.items()]
    return frame(spark, rows)


@CORE.query("exp_builder_compare")
def exp_builder_compare(spark, sf_dir):
    """Two builders on a low-dimensional integer set and a high-dimensional one of equal size."""
    rows = []
    sets = {n: dataset(spark, sf_dir, n) for n in ("e64q", "d768")}
    for name, method in itertools.product(sets, ("unsplit_detour", "unsplit_robust")):
        h = run(method, sets[name], SMALL)
        rows.append(("builders", name, method, "", "build_s", h.seconds["shard_build_sum"]))
    return frame(spark, rows)


@CORE.query(
    "exp_datasets",
    """select 'e64q' as dataset, count(*)::bigint as n, 64 as dim, 'int' as kind from embeddings union all select 'd96', count(*)::bigint, 96, 'int' from documents where length(text) >= 3
union all select 'd768', count(*)::bigint, 768, 'int' from documents where regexp_matches(lower(text), '[a-z0-9]') union all select 'l4', count(*)::bigint, 4, 'int' from (select distinct * from lineitem)""",
)
def exp_datasets(spark, sf_dir):
    out = None
    for name, dim in (("e64q", 64), ("d96", 96), ("d768", 768), ("l4", 4)):
        row = DATASETS[name][0](spark, sf_dir).agg(F.lit(name).alias("dataset"), F.count("*").alias("n"), F.lit(dim).alias("dim"), F.lit("int").alias("kind"))
        out = row if out is None else out.unionByName(row)
    return out


def ladder_rows(spark, sf_dir, name: str, build: bool = True) -> list[tuple]:
    out, vecs = [], dataset(spark, sf_dir, name)
    n = vecs.count()
    c = fit_centroids(vecs, 8, iters=8)
    for eps in LADDER[name]:
        began = time.perf_counter()
        cfg = PartitionConfig(eps=eps, blocks=2, lo=1.0, hi=1.0, radius_test=eps is not None)
        a = Workspace(spark, "ladder").write(partition_vectors(vecs, c, ShardPlan(8, 2 * n), cfg).assignment, "a")
        parted = time.perf_counter() - began
        share, label = metrics.replicated_share(a).first(), f"eps={'off' if eps is None else float(eps)}"
        out += [("eps", name, "selective_merge", label, "replicated_share", share.share), ("eps", name, "selective_merge", label, "partition_s", parted)]
        if build:
            g = build_shards(a, vecs, "knn_detour", 12, 24, 8, timed=True)
            s = g.groupBy("shard_id").agg(F.first("seconds").alias("s")).agg(F.sum("s")).first()[0]
            out += [("eps", name, "selective_merge", label, "build_s", s), ("eps", name, "selective_merge", label, "build_s_per_copy", s / share.n_copies)]
    return out


@CORE.query("exp_eps_ladder")
def exp_eps_ladder(spark, sf_dir):
    return frame(spark, ladder_rows(spark, sf_dir, "e64q") + ladder_rows(spark, sf_dir, "d768") + ladder_rows(spark, sf_dir, "l4", build=False))


@CORE.query("exp_eps_search")
def exp_eps_search(spark, sf_dir):
    """Recall against distance count along eps and beam, for both builders."""
    base, queries = split_queries(dataset(spark, sf_dir, "d768"))
    truth = Workspace(spark, "truth").write(search.search_exact(base, queries, 10), "t")
    rows = []
    for method, eps in itertools.product(("selective_merge", "uniform_selective"), (Fraction(11, 10), Fraction(12, 10), Fraction(15, 10), None)):
        cfg = RunConfig(k=4, degree=12, working=24, eps=eps, blocks=2, iters=4, partition=PartitionConfig(eps=eps, blocks=2, lo=1.0, hi=1.0, radius_test=eps is not None))
        h, label = run(method, base, cfg), "off" if eps is None else float(eps)
        for beam in (10, 30, 80):
            rows += [(e, f"{d} eps={label}", *r) for e, d, *r in _quality("eps_search", "d768", h, base, queries, beam, truth)]
    return frame(spark, rows)


@CORE.query("exp_build_matrix")
def exp_build_matrix(spark, sf_dir):
    """Overall and build seconds of four methods on the stand-ins."""
    rows = []
    sets = {n: dataset(spark, sf_dir, n) for n in BUILT}
    for name, method in itertools.product(sets, METHODS):
        h = run(method, sets[name], RunConfig(k=SHARDS.get(name, 4), degree=12, working=24, eps=DATASETS[name][1], blocks=2, iters=4))
        rows += [("build", name, method, "", m, h.seconds[m]) for m in ("overall", "shard_build_sum")]
    return frame(spark, rows)


def search_rows(spark, sf_dir, name: str, beams: tuple[int, ...]) -> list[tuple]:
    base, queries = split_queries(dataset(spark, sf_dir, name))
    truth = Workspace(spark, "truth").write(search.search_exact(base, queries, 10), "t")
    out = []
    for method in METHODS:
        h = run(method, base, RunConfig(k=SHARDS.get(name, 4), degree=12, working=24, eps=DATASETS[name][1], blocks=2, iters=4))
        done = False
        for beam in beams:
            rows = _quality("search", name, h, base, queries, beam, truth)
            out += rows
            if not done and rows[0][5] >= EQUAL_RECALL:  # the first beam that reaches it
                out += [("search", name, method, f"recall>={EQUAL_RECALL}", m, v) for *_, m, v in rows]
                done = True
    return out


@CORE.query("exp_search_lowdim")
def exp_search_lowdim(spark, sf_dir):
    return frame(spark, search_rows(spark, sf_dir, "e64q", BEAMS) + search_rows(spark, sf_dir, "e64", BEAMS) + search_rows(spark, sf_dir, "d96", BEAMS) + search_rows(spark, sf_dir, "l4", BEAMS))


@CORE.query("exp_search_highdim")
def exp_search_highdim(spark, sf_dir):
    """High dimension: the mean distance count stands for speed, reads for the disk."""
    return frame(spark, search_rows(spark, sf_dir, "d768", BEAMS))


@CORE.query("exp_search_disk")
def exp_search_disk(spark, sf_dir):
    """Search over node files with the benchmark items as queries: recall, distances and records read."""
    ws = Workspace(spark, "nodes")
    queries = ws.write(tables.benchmark_768(spark, sf_dir).withColumnRenamed("vec_id", "query_id"), "queries")
    h = run("selective_merge", DATASETS["d768"][0](spark, sf_dir), RunConfig(k=4, degree=16, working=32, blocks=2, iters=4))
    vecs = h.vectors
    truth = ws.write(search.search_exact(vecs, queries, 10), "truth")
    write_nodes(h.graph, vecs, f"{ws.root}/files", 8)
    entries = search.entry_nodes(vecs, h.centroids)
    rows = []
    for beam in (16, 48):
        found = ws.write(search.search_nodes(spark, f"{ws.root}/files", queries, 10, beam, entries, 8), f"found{beam}")
        r, w = metrics.recall_at_k(found, truth).first(), found.groupBy("query_id").agg(F.max("dist_count").alias("d"), F.max("reads").alias("r")).agg(F.avg("d"), F.avg("r")).first()
        rows += [("search_disk", "d768", "selective_merge", f"beam={beam}", m, v) for m, v in (("recall", r.recall), ("dist_count", w[0]), ("reads", w[1]))]
    return frame(spark, rows)


@CORE.query("planted_hits")
def planted_hits(spark, sf_dir):
    """Benchmark passages as queries: share whose containing document is among the ten nearest."""
    docs, bench = read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")
    vecs = Workspace(spark, "d768").write(tables.documents_768(spark, sf_dir), "v")
    q = tables.benchmark_768(spark, sf_dir).withColumnRenamed("vec_id", "query_id")
    held = docs.select("doc_id", "text").join(F.broadcast(bench.select("item_id", F.col("text").alias("needle"))), F.contains("text", "needle")).select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("vec_id"))
    got = search.search_exact(vecs, q, 10).join(held, ["query_id", "vec_id"], "left_semi").select("query_id").distinct().count()
    total = held.select("query_id").distinct().count()
    return spark.createDataFrame([(total, got)], "n_planted bigint, n_found bigint")


@CORE.query("exp_degree")
def exp_degree(spark, sf_dir):
    rows, vecs = [], dataset(spark, sf_dir, "d768")
    for method, (r, l) in itertools.product(("split_knn", "split_hier", "uniform_merge", "selective_merge"), ((8, 16), (16, 32), (32, 64))):
        h = run(method, vecs, RunConfig(k=4, degree=r, working=l, blocks=2, iters=4))
        rows += [("degree", "d768", method, f"R={r} L={l}", m, h.seconds[m]) for m in ("overall", "shard_build_sum")]
    return frame(spark, rows)


@CORE.query("exp_workers")
def exp_workers(spark, sf_dir):
    """Measured shard times on 1, 2 and 4 workers."""
    h = run("selective_merge", DATASETS["d768"][0](spark, sf_dir), RunConfig(k=8, degree=12, working=24, blocks=2, iters=4))
    times = [r.s for r in h.shard_graphs.groupBy("shard_id").agg(F.first("seconds").alias("s")).orderBy("shard_id").collect()]
    one, rows = scheduler.makespan(times, 1), []
    for g in (1, 2, 4):
        span = scheduler.makespan(times, g)
        rows += [("workers", "d768", "selective_merge", f"g={g}", "makespan_s", span), ("workers", "d768", "selective_merge", f"g={g}", "speedup", one / span), ("workers", "d768", "selective_merge", f"g={g}", "efficiency", one / span / g)]
    return frame(spark, rows)


@CORE.query("exp_cost", "select * from (values ('uniform_merge', 67.3::decimal(12,1)), ('selective_merge', 11.1::decimal(12,1))) t(method, usd)")
def exp_cost(spark, sf_dir):
    rows = [("uniform_merge", cost.index_cost(17.25, 0, [], 3.9, 0)), ("selective_merge", cost.index_cost(1.88, 0.045, [0.56], 4.6, 3.67))]
    return spark.createDataFrame([(m, c.quantize(type(c)("0.1"))) for m, c in rows], "method string, usd decimal(12,1)")


@CORE.query("exp_cost_own")
def exp_cost_own(spark, sf_dir):
    """The published formula with this library's own measured hours: uniform replication on an own machine, selective on a spot one."""
    rows, vecs = [], dataset(spark, sf_dir, "d768")
    for method, price in (("uniform_merge", 3.9), ("selective_merge", 4.6)):
        s = run(method, vecs, RunConfig(k=4, degree=12, working=24, blocks=2, iters=4)).seconds
        spot = [s["shard_build_sum"] / 3600] if method == "selective_merge" else []
        own = s["overall"] - (s["build"] if spot else 0.0)
        usd = cost.index_cost(own / 3600, 0.0, spot, price, 3.67)
        rows += [("cost_own", "d768", method, "", "overall_s", s["overall"]), ("cost_own", "d768", method, "", "build_s", s["shard_build_sum"]), ("cost_own", "d768", method, "", "usd", float(usd))]
    return frame(spark, rows)


@CORE.query("exp_hier_degree")
def exp_hier_degree(spark, sf_dir):
    rows, vecs = [], dataset(spark, sf_dir, "e64q")
    base, queries = split_queries(vecs)
    for r in (20, 64):
        h = run("split_hier", base, RunConfig(k=4, degree=12, working=24, hier_degree=r))
        rows += [("hier_degree", "e64q", "split_hier", f"R={r}", "build_s", h.seconds["shard_build_sum"])] + _quality(f"hier_degree R={r}", "e64q", h, base, queries, 20)
    return frame(spark, rows)


@CORE.query("exp_order_fairness")
def exp_order_fairness(spark, sf_dir):
    """Homes that are the nearest shard, by arrival order: strict uniform replication against blockwise selective."""
    vecs, rows = dataset(spark, sf_dir, "d768"), []
    n, c = vecs.count(), fit_centroids(vecs, 8, iters=6)
    prefs = Workspace(spark, "fair").write(preferences(vecs, c), "p")
    biggest = prefs.groupBy(F.get("prefs", F.lit(0))["shard_id"]).count().agg(F.max("count")).first()[0]
    cap = max(-(-2 * n // 8), biggest)
    for order in ("id", "reverse", "shuffled"):
        uniform = assign_uniform(prefs.withColumn("vec_id", F.when(F.lit(order == "reverse"), -F.col("vec_id")).otherwise(F.col("vec_id"))), [cap] * 8).withColumn("vec_id", F.abs("vec_id"))
        if order == "shuffled":
            uniform = assign_uniform(prefs.withColumn("vec_id", F.xxhash64("vec_id")), [cap] * 8).join(vecs.select(F.xxhash64("vec_id").alias("h"), F.col("vec_id").alias("v")), F.col("vec_id") == F.col("h")).select(F.col("v").alias("vec_id"), "shard_id", "is_home", "dist", "rank")
        mine = partition_vectors(vecs, c, ShardPlan(8, cap), PartitionConfig(blocks=4, order=order)).assignment
        for method, a in (("uniform_merge", uniform), ("selective_merge", mine)):
            m = metrics.locality(a, prefs).first()
            rows += [("fairness", "d768", method, order, "nearest_share", m.n_nearest / n), ("fairness", "d768", method, order, "mean_rank", m.mean_rank), ("fairness", "d768", method, order, "homes", m.n_vectors)]
    return frame(spark, rows)


@CORE.query("exp_arrivals", "select date_trunc('hour', ts) as hour, event_type, count(*)::bigint as n, count(distinct user_id)::bigint as users from events group by all")
def exp_arrivals(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour"), "event_type").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))


@CORE.query("exp_ablation")
def exp_ablation(spark, sf_dir):
    """Quota modes, boost kinds and the radius test."""
    vecs, rows = dataset(spark, sf_dir, "d768"), []
    n, c = vecs.count(), fit_centroids(vecs, 8, iters=6)
    cap = -(-2 * n // 8)
    cap = max(cap, preferences(vecs, c, 1).groupBy(F.get("prefs", F.lit(0))["shard_id"]).count().agg(F.max("count")).first()[0])
    variants = {f"quota={q}": PartitionConfig(quota=q, refresh=q != "density") for q in ("fixed", "density", "adaptive")}
    variants |= {f"boost={b}": PartitionConfig(boost=b, b0=1.0 if b == "constant" else 4.0) for b in ("constant", "exp")}
    variants["radius=off"] = PartitionConfig(radius_test=False)
    for label, cfg in variants.items():
        p = partition_vectors(vecs, c, ShardPlan(8, cap), cfg)
        a = Workspace(spark, "ablate").write(p.assignment, "a")
        s, b = metrics.replicated_share(a).first(), metrics.balance(a).first()
        rows += [("ablation", "d768", "selective_merge", label, "replicated_share", s.share), ("ablation", "d768", "selective_merge", label, "max_over_mean", b.max_over_mean)]
    return frame(spark, rows)


def scale_rows(spark: SparkSession, sf_dirs: list[str], name: str, build: bool) -> list[tuple]:
    """Partition and build seconds of one stand-in along table sizes: both should grow in proportion."""
    rows = []
    for sf_dir in sf_dirs:
        vecs = dataset(spark, sf_dir, name)
        n, c = vecs.count(), fit_centroids(vecs, 8, iters=4)
        began = time.perf_counter()
        a = Workspace(spark, "scale").write(partition_vectors(vecs, c, ShardPlan(8, 2 * n), PartitionConfig(eps=Fraction(12, 10), blocks=2, lo=1.0, hi=1.0)).assignment, "a")
        rows.append(("scale", name, "selective_merge", f"n={n}", "partition_s", time.perf_counter() - began))
        if build:
            g = build_shards(a, vecs, "knn_detour", 12, 24, 8, timed=True)
            rows.append(("scale", name, "selective_merge", f"n={n}", "build_s", g.groupBy("shard_id").agg(F.first("seconds").alias("s")).agg(F.sum("s")).first()[0]))
    return rows


@CORE.query("baseline_split_hier")
def baseline_split_hier(spark, sf_dir):
    base, queries = split_queries(dataset(spark, sf_dir, "e64q"))
    return frame(spark, _quality("baseline", "e64q", run("split_hier", base, SMALL), base, queries, 20))


@CORE.query("baseline_split_knn")
def baseline_split_knn(spark, sf_dir):
    base, queries = split_queries(dataset(spark, sf_dir, "e64q"))
    return frame(spark, _quality("baseline", "e64q", run("split_knn", base, SMALL), base, queries, 20))


@CORE.query("baseline_unsplit")
def baseline_unsplit(spark, sf_dir):
    base, queries = split_queries(dataset(spark, sf_dir, "e64q"))
    rows = []
    for method in ("unsplit_robust", "unsplit_detour"):
        rows += _quality("baseline", "e64q", run(method, base, SMALL), base, queries, 40)
    return frame(spark, rows)
