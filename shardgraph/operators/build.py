"""Builds every shard's graph as an independent task."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.operators.arrays import lists, matrix
from shardgraph.operators.beams import pair_distances
from shardgraph.operators.builders import BUILDERS

GRAPH = "shard_id int, vec_id bigint, nbrs array<struct<id:bigint,d:double>>"


def edges_of(x: np.ndarray, ids: np.ndarray, near: np.ndarray) -> pa.ListArray:
    """Neighbour lists with squared distances kept beside the ids, so later caps need no vectors."""
    real = near >= 0
    row = np.repeat(np.arange(len(x)), real.sum(axis=1))
    col = near[real]
    d = pair_distances(x, col, x, row)
    return lists(pa.StructArray.from_arrays([pa.array(ids[col]), pa.array(d)], names=["id", "d"]), real.sum(axis=1))


def place(assignment: DataFrame, vectors: DataFrame, k: int, col: str = "q") -> DataFrame:
    """Vectors at their shards: the one full shuffle of stored copies, shard s in partition s."""
    rows = assignment.select("vec_id", "shard_id").join(vectors.select("vec_id", F.col(col).alias("x")), "vec_id")
    return rows.repartitionById(k, "shard_id")


def build_shards(assignment: DataFrame, vectors: DataFrame, builder: str, degree: int, working: int, k: int, col: str = "q", timed: bool = False, **options) -> DataFrame:
    """Rows (shard_id, vec_id, nbrs); with ``timed`` also (n_vectors, seconds) of the shard.

    A partition is one shard and one task that talks to no other; Spark retries a lost task, which
    is the re-queue of an interrupted worker. Memory: the shard's matrix and graph, bounded by the
    capacity of the plan. Vectors are ordered by id before building, so arrival order is immaterial.
    """
    make = BUILDERS[builder]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        shard = t.column("shard_id").to_numpy()
        for s in np.unique(shard).tolist():
            part = t.filter(pa.array(shard == s))
            ids = part.column("vec_id").to_numpy()
            order = np.argsort(ids, kind="stable")
            ids, x = ids[order], matrix(part.column("x"))[order]
            began = time.perf_counter()
            near = make(ids, x, degree, working, **options)
            took = time.perf_counter() - began
            cols = {"shard_id": pa.array(np.full(len(ids), s, np.int32)), "vec_id": pa.array(ids), "nbrs": edges_of(x, ids, near)}
            if timed:
                cols |= {"n_vectors": pa.array(np.full(len(ids), len(ids), np.int64)), "seconds": pa.array(np.full(len(ids), took))}
            yield pa.RecordBatch.from_pydict(cols)

    schema = GRAPH + (", n_vectors bigint, seconds double" if timed else "")
    return place(assignment, vectors, k, col).mapInArrow(run, schema)


def build_in_waves(assignment: DataFrame, vectors: DataFrame, builder: str, degree: int, working: int, k: int, path: str, wave: int = 64, col: str = "q", **options) -> DataFrame:
    """``build_shards`` that goes on where an interrupted run stopped.

    A job builds ``wave`` shards and commits them to ``path``, one folder a shard; a run that finds
    shards there builds only the others. What an interruption costs is the wave in work. Shards
    count as done once their folder is committed, so the assignment must not change between runs.
    """
    spark = assignment.sparkSession
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    there = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    schema = GRAPH.replace("shard_id int, ", "") + ", shard_id int"

    def committed() -> DataFrame:
        return spark.read.schema(schema).parquet(path)

    todo = pending(assignment, committed()) if there.exists(folder) else assignment
    shards = sorted(r.shard_id for r in todo.select("shard_id").distinct().collect())
    for i in range(0, len(shards), wave):
        some = todo.where(F.col("shard_id").isin(shards[i : i + wave]))
        build_shards(some, vectors, builder, degree, working, k, col, **options).write.mode("append").partitionBy("shard_id").parquet(path)
    if not shards and not there.exists(folder):
        return spark.createDataFrame([], GRAPH)
    return committed().select("shard_id", "vec_id", "nbrs")


def pending(assignment: DataFrame, committed: DataFrame) -> DataFrame:
    """Rows of shards without a committed graph: what a resumed build still has to do."""
    return assignment.join(committed.select("shard_id").distinct(), "shard_id", "left_anti")
