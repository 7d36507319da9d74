"""Accuracy, work, balance, connectivity and footprint of a run."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardgraph.workspace import Workspace


def recall_at_k(found: DataFrame, truth: DataFrame, k: int = 10) -> DataFrame:
    """Rows (n_queries, hits, recall): found among the true k, ties by distance counted as hits."""
    worst = truth.where(F.col("rank") <= k).groupBy("query_id").agg(F.max("dist").alias("worst"), F.count("*").alias("k"))
    hits = found.where(F.col("rank") <= k).select("query_id", "vec_id", "dist").join(worst, "query_id").where(F.col("dist") <= F.col("worst") * (1 + 1e-12)).groupBy("query_id").agg(F.count("*").alias("h"))
    per = worst.join(hits, "query_id", "left").select("query_id", F.least(F.coalesce("h", F.lit(0)), F.col("k")).alias("h"), "k")
    return per.agg(F.count("*").alias("n_queries"), F.coalesce(F.sum("h"), F.lit(0)).alias("hits"), F.avg(F.col("h") / F.col("k")).alias("recall"))


def search_work(found: DataFrame) -> DataFrame:
    """Rows (n_queries, mean_dist_count, mean_hops, mean_reads, mean_ms, p50_ms, p95_ms, p99_ms, qps) of a logged search."""
    per = found.groupBy("query_id").agg(*[F.max(c).alias(c) for c in ("dist_count", "hops", "reads", "seconds")])
    ms = F.col("seconds") * 1000
    return per.agg(
        F.count("*").alias("n_queries"), F.avg("dist_count").alias("mean_dist_count"), F.avg("hops").alias("mean_hops"), F.avg("reads").alias("mean_reads"), F.avg(ms).alias("mean_ms"),
        *[F.percentile(ms, p / 100).alias(f"p{p}_ms") for p in (50, 95, 99)], (F.count("*") / F.sum("seconds")).alias("qps"),
    )


def replicated_share(assignment: DataFrame) -> DataFrame:
    """Rows (n_vectors, n_copies, n_replicated, share)."""
    homes = assignment.where("is_home")
    return homes.agg(F.count("*").alias("n_vectors"), F.sum("n_homes").cast("bigint").alias("n_copies"), F.count_if(F.col("n_homes") > 1).alias("n_replicated"), F.avg((F.col("n_homes") > 1).cast("double")).alias("share"))


def balance(assignment: DataFrame) -> DataFrame:
    """Rows (k, smallest, largest, max_over_mean, cv, gini) of the shard sizes."""
    sizes = assignment.groupBy("shard_id").agg(F.count("*").alias("n"))
    ranked = sizes.withColumn("i", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("n", "shard_id")))
    return ranked.agg(
        F.count("*").alias("k"), F.min("n").alias("smallest"), F.max("n").alias("largest"), (F.max("n") / F.avg("n")).alias("max_over_mean"), (F.stddev_pop("n") / F.avg("n")).alias("cv"),
        (2 * F.sum(F.col("i") * F.col("n")) / (F.count("*") * F.sum("n")) - (F.count("*") + 1) / F.count("*")).alias("gini"),
    )


def locality(assignment: DataFrame, prefs: DataFrame) -> DataFrame:
    """Rows (n_vectors, n_nearest, mean_rank): homes that are the nearest shard, and the home's mean place in the preference list."""
    place = F.array_position(F.transform("prefs", lambda p: p["shard_id"]), F.col("shard_id"))
    homes = assignment.where("is_home").select("vec_id", "shard_id").join(prefs.select("vec_id", "prefs"), "vec_id").withColumn("place", place)
    return homes.agg(F.count("*").alias("n_vectors"), F.count_if(F.col("place") == 1).alias("n_nearest"), F.avg("place").alias("mean_rank"))


def shard_links(assignment: DataFrame) -> DataFrame:
    """Rows (a, b, n): vectors that two shards share; a self-join on the id over replicated vectors only."""
    multi = assignment.where("n_homes > 1").select("vec_id", "shard_id")
    return multi.withColumnRenamed("shard_id", "a").join(multi.withColumnRenamed("shard_id", "b"), "vec_id").where("a < b").groupBy("a", "b").agg(F.count("*").alias("n"))


def reachability(graph: DataFrame, entry: int, max_hops: int = 200) -> tuple[int, int]:
    """(reached, nodes) from the entry, one hop of all new nodes per round."""
    spark = graph.sparkSession
    ws = Workspace(spark, "reach")
    edges = ws.write(graph.select("vec_id", F.explode("nbrs.id").alias("to")), "edges")
    seen = ws.write(spark.createDataFrame([(entry,)], "vec_id bigint"), "seen0")
    new = seen
    for h in range(1, max_hops + 1):
        new = ws.write(new.join(edges, "vec_id").select(F.col("to").alias("vec_id")).distinct().join(seen, "vec_id", "left_anti"), f"new{h}")
        if new.isEmpty():
            break
        seen = ws.write(seen.unionByName(new), f"seen{h}")
    return seen.count(), graph.count()


def footprint(assignment: DataFrame, dim: int, bytes_per_component: int, degree: int, edge_bytes: int = 12) -> DataFrame:
    """Rows (shard_id, n, vector_bytes, edge_bytes, total_bytes)."""
    n = F.count("*")
    return assignment.groupBy("shard_id").agg(
        n.alias("n"), (n * dim * bytes_per_component).cast("bigint").alias("vector_bytes"), (n * degree * edge_bytes).cast("bigint").alias("edge_bytes"), (n * (dim * bytes_per_component + degree * edge_bytes)).cast("bigint").alias("total_bytes")
    )


def degree_hist(graph: DataFrame) -> DataFrame:
    return graph.groupBy(F.size("nbrs").alias("degree")).agg(F.count("*").alias("n"))


def edge_recall(graph: DataFrame, truth: DataFrame) -> DataFrame:
    """Rows (n_true, n_kept, share): true neighbour edges (query_id -> vec_id) that the graph has."""
    edges = graph.select(F.col("vec_id").alias("query_id"), F.explode("nbrs.id").alias("vec_id")).distinct()
    t = truth.where("query_id <> vec_id").select("query_id", "vec_id")
    kept = t.join(edges.withColumn("k", F.lit(1)), ["query_id", "vec_id"], "left")
    return kept.agg(F.count("*").alias("n_true"), F.count("k").alias("n_kept"), (F.count("k") / F.count("*")).alias("share"))


def ratio_table(runs: DataFrame, base: str) -> DataFrame:
    """Rows (dataset, metric, method, value, ratio): every method against ``base``."""
    b = runs.where(F.col("method") == base).select("dataset", "metric", F.col("value").alias("b"))
    return runs.join(b, ["dataset", "metric"]).select("dataset", "metric", "method", "value", (F.col("value") / F.col("b")).alias("ratio"))


class StageTimer:
    """Wall seconds of named stages."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def stage(self, name: str):
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began
