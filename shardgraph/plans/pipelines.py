"""Methods end to end: assignment, shard graphs, merged graph and stage times under one handle."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from fractions import Fraction

import numpy as np
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.operators import metrics
from shardgraph.operators.build import build_shards
from shardgraph.operators.centroids import fit_centroids, preferences
from shardgraph.operators.merge import merge_graphs
from shardgraph.operators.partition import PartitionConfig, ShardPlan, assign_uniform, contiguous_split, listed_by_block, partition_vectors, unsplit
from shardgraph.operators.search import hold_resident, search_resident, search_split
from shardgraph.workspace import Workspace

METHODS = ("selective_merge", "uniform_merge", "uniform_selective", "split_hier", "split_knn", "unsplit_robust", "unsplit_detour", "replicate_all", "no_replica", "static_quota")


@dataclass(frozen=True)
class RunConfig:
    k: int = 8
    degree: int = 16
    working: int = 32
    eps: Fraction | None = Fraction(6, 5)
    max_homes: int = 2
    blocks: int = 4
    slack: float = 2.2  # room of all shards together over the number of vectors
    policy: str = "nearest"
    hier_degree: int | None = None
    sample_rows: int = 20_000
    iters: int = 8
    partition: PartitionConfig | None = None
    strict_uniform: bool = False


@dataclass
class IndexHandle:
    method: str
    vectors: DataFrame
    assignment: DataFrame
    shard_graphs: DataFrame
    graph: DataFrame | None
    shards: int
    seconds: dict[str, float] = field(default_factory=dict)
    prefs: DataFrame | None = None
    centroids: np.ndarray | None = None
    held: Broadcast | None = field(default=None, repr=False)  # the graph as its first search gathered it

    def search(self, queries: DataFrame, k: int = 10, beam: int = 40, width: int = 1) -> DataFrame:
        """Merged graphs are searched once, split graphs shard by shard.

        A merged search starts from the medoid and the node nearest to each centroid: far clusters
        may be joined by few edges or none, whatever the replicas, and the entries cost k distances.
        """
        if self.graph is not None:
            entry = "medoid" if self.centroids is None else "centroids"
            self.held = self.held or hold_resident(self.graph, self.vectors, entry, self.centroids)
            return search_resident(self.graph, self.vectors, queries, k, beam, width, held=self.held)
        return search_split(self.shard_graphs, self.vectors, queries, k, beam, self.shards, width)


def run(method: str, vectors: DataFrame, cfg: RunConfig = RunConfig()) -> IndexHandle:
    """Builds an index over ``vectors(vec_id, q)``; every stage's result is a written table, so its time is its own."""
    if method not in METHODS:
        raise ValueError(method)
    ws, timer = Workspace(vectors.sparkSession, method), metrics.StageTimer()
    vectors = ws.write(vectors.select("vec_id", "q"), "vectors")
    n = vectors.count()
    split = method.startswith(("split", "unsplit"))
    k = 1 if method.startswith("unsplit") else min(cfg.k, max(n, 1))
    prefs = centroids = None
    with timer.stage("partition"):
        if split:
            assignment = ws.write(unsplit(vectors) if k == 1 else contiguous_split(vectors, k), "assignment")
        else:
            centroids = fit_centroids(vectors, k, cfg.sample_rows, cfg.iters)
            capacity = max(1, int(np.ceil(n * cfg.slack / k)))
            base = cfg.partition or PartitionConfig(eps=cfg.eps, max_homes=cfg.max_homes, blocks=cfg.blocks)
            if method == "uniform_merge":
                prefs = ws.write(preferences(vectors, centroids, None if cfg.strict_uniform else cfg.max_homes), "prefs")
                if cfg.strict_uniform:
                    rows = assign_uniform(prefs, [capacity] * k, cfg.max_homes)
                else:
                    rows = prefs.select("vec_id", F.posexplode(F.slice("prefs", 1, cfg.max_homes)).alias("i", "p")).select(
                        "vec_id", "p.shard_id", (F.col("i") == 0).alias("is_home"), "p.dist", (F.col("i") + 1).alias("rank")
                    )
                per = rows.groupBy("vec_id").agg(F.count("*").cast("int").alias("n_homes"))
                assignment = rows.join(per, "vec_id").withColumn("block_id", F.lit(0))
            else:
                if method == "replicate_all":
                    base = replace(base, eps=None, radius_test=False, lo=1.0, hi=1.0)
                    capacity = 2 * n
                elif method == "no_replica":
                    base = replace(base, max_homes=1)
                elif method == "static_quota":
                    base = replace(base, quota="density", refresh=False)
                prefs = listed_by_block(vectors, centroids, base, ws)
                assignment = partition_vectors(vectors, centroids, ShardPlan(k, capacity), base, prefs=prefs).assignment
            assignment = ws.write(assignment, "assignment")
    builder = {"uniform_merge": "robust", "uniform_selective": "robust", "split_hier": "knn_hier", "unsplit_robust": "robust"}.get(method, "knn_detour")
    degree = cfg.hier_degree or cfg.degree if builder == "knn_hier" else cfg.degree
    with timer.stage("build"):
        graphs = ws.write(build_shards(assignment, vectors, builder, degree, cfg.working, k, timed=True), "graphs")
    graph = None
    if not split:
        with timer.stage("merge"):
            graph = ws.write(merge_graphs(graphs.select("shard_id", "vec_id", "nbrs"), degree, cfg.policy, assignment, vectors), "graph")
    elif k == 1:
        graph = graphs.select("vec_id", "nbrs", F.lit(1).alias("n_homes"))
    timer.seconds["shard_build_sum"] = graphs.groupBy("shard_id").agg(F.first("seconds").alias("s")).agg(F.coalesce(F.sum("s"), F.lit(0.0))).first()[0]
    timer.seconds["overall"] = sum(timer.seconds.get(s, 0.0) for s in ("partition", "build", "merge"))
    return IndexHandle(method, vectors, assignment, graphs, graph, k, timer.seconds, prefs, centroids)
