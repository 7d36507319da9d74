"""Shared pieces: connected components, words, tables."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph.workspace import Workspace, shared_dir

__all__ = ["WORD_BYTES", "Workspace", "components", "free_name", "letter_case", "shared_dir", "slices", "table", "tidy"]

#: Turns A-Z into a-z and every ASCII byte that is neither a letter nor a digit into a space.
WORD_BYTES = bytes(
    b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32
    for b in range(256)
)

FEW_EDGES = 400_000


def _with_least(edges: DataFrame, low: DataFrame, few: bool, hub: int) -> DataFrame:
    """``edges(a, b)`` with the label ``m`` that ``low(a, m, n)`` has for each ``a``.

    Few edges: the labels are broadcast, at most 16 bytes a node. Many: a shuffled join in which a
    node of more than ``hub`` edges is dealt over that many salts, so no task sees a whole hub. The
    list of hubs, at most edges / hub rows, is what is broadcast then.
    """
    if few:
        return edges.join(F.broadcast(low.select("a", "m")), "a")
    salts = F.ceil(F.col("n") / hub).cast("int")
    hubs = low.where(F.col("n") > hub).select("a", salts.alias("salts"))
    left = edges.join(F.broadcast(hubs), "a", "left").withColumn("salt", F.coalesce(F.pmod(F.xxhash64("b"), F.col("salts")), F.lit(0)).cast("int"))
    right = low.select("a", "m", F.explode(F.sequence(F.lit(0), F.greatest(salts, F.lit(1)) - 1)).alias("salt"))
    return left.join(right, ["a", "salt"]).select("a", "b", "m")


def components(edges: DataFrame, ws: Workspace, name: str = "cc", max_rounds: int = 60, few: int = FEW_EDGES, hub: int = 20_000) -> DataFrame:
    """Smallest id reachable from each id of ``edges(a, b)``: rows ``(id, component)``.

    Alternates the two star contractions: every node hands its larger neighbours to the smallest
    id in its neighbourhood, then its smaller ones. Each half is a partially aggregated minimum
    and an equi-join that salts hubs. Edges never outgrow the input, and the labels stay in the
    cluster, but for tables of under ``few`` edges, whose labels are broadcast between tasks.
    """
    cur = ws.write(
        edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(),
        f"{name}-0",
    )
    seen, n_edges = None, cur.count()
    for i in range(1, max_rounds + 1):
        is_few = n_edges <= few
        both = cur.unionByName(cur.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count("*").alias("n"))
        large = _with_least(both, low, is_few, hub).where("b > a and b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n"))
        small = _with_least(large, low, is_few, hub).select(
            F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")
        )
        nxt = ws.write(small.select("e.a", "e.b").where("a <> b").distinct(), f"{name}-{i}")
        now = nxt.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        ws.drop(f"{name}-{i - 1}")
        cur, n_edges = nxt, now[0]
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = cur.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct()
    return cur.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(roots)


def slices(batches: Iterator[pa.RecordBatch], chars: int = 1_000_000, col: str = "text") -> Iterator[pa.RecordBatch]:
    """Batches cut so that a slice holds few bytes of text besides one long text."""
    for b in batches:
        size = np.cumsum(pc.fill_null(pc.binary_length(b.column(col)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        start = 0
        while start < len(size):
            base = size[start - 1] if start else 0
            end = max(start + 1, int(np.searchsorted(size, base + chars, "right")))
            yield b.slice(start, end - start)
            start = end


def tidy(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The kernel, which hands its memory back when its task ends: workers are reused, and allocators keep what they once had."""

    def kernel(batches: Iterator) -> Iterator:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL(None).malloc_trim(0)
        except (AttributeError, OSError):  # another C library than glibc
            return

    return kernel


def free_name(df: DataFrame, name: str) -> str:
    """``name``, with underscores added until no column of ``df`` has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def letter_case(col):
    """Lower-cases A-Z alone, as the contracts ask; other letters stay."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
