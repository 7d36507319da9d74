"""Functions for SQL users: scalar, aggregate and table functions over vectors."""

from __future__ import annotations


import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType



@F.pandas_udf(LongType())
def vec_dist(a: pd.Series, b: pd.Series) -> pd.Series:
    """Squared distance, one Arrow batch at a time."""
    x, y = np.stack(a.to_numpy()).astype(np.int64), np.stack(b.to_numpy()).astype(np.int64)
    return pd.Series(((x - y) ** 2).sum(axis=1))


@F.arrow_udf(LongType())
def vec_dist_arrow(a: pa.Array, b: pa.Array) -> pa.Array:
    x, y = (np.asarray(c.flatten().to_numpy(zero_copy_only=False), np.int64).reshape(len(c), -1) for c in (a, b))
    return pa.array(((x - y) ** 2).sum(axis=1))


@F.pandas_udf(ArrayType(LongType()))
def centroid(xs: pd.Series) -> np.ndarray:
    """Rounded mean vector of a group that fits one worker; large groups use the partial sums of ``mean_by``."""
    m = np.stack(xs.to_numpy()).astype(np.int64)
    return np.floor(m.sum(axis=0) / len(m) + 0.5).astype(np.int64).tolist()


@F.udtf(returnType=StructType([StructField(c, LongType()) for c in ("vec_id", "nbr", "d2")]))
class ExpandNeighbors:
    """Graph row to edge rows; ``inline`` is the built-in twin."""

    def eval(self, vec_id, nbrs):
        for e in nbrs or ():
            yield vec_id, e["id"], int(e["d"])


@F.udtf
class Preference:
    """Vector and centroids to (shard_id, d2, rank) rows."""

    @staticmethod
    def analyze(q, centroids):
        from pyspark.sql.udtf import AnalyzeResult

        return AnalyzeResult(StructType([StructField("shard_id", IntegerType()), StructField("d2", LongType()), StructField("rank", IntegerType())]))

    def eval(self, q, centroids):
        d = ((np.asarray(centroids, np.int64) - np.asarray(q, np.int64)) ** 2).sum(axis=1)
        for r, s in enumerate(np.argsort(d, kind="stable").tolist()):
            yield s, int(d[s]), r + 1


def register(spark: SparkSession) -> None:
    """Puts all of them in the session under ``vec_dist``, ``vec_centroid``, ``expand_neighbors``, ``preference`` and ``is_needed``."""
    spark.udf.register("vec_dist", vec_dist)
    spark.udf.register("vec_centroid", centroid)
    spark.udtf.register("expand_neighbors", ExpandNeighbors)
    spark.udtf.register("preference", Preference)
    # inlined by the optimizer: no call remains in the plan
    spark.sql("create or replace temporary function is_needed(d2_home double, d2_alt double, num double, den double) returns boolean return d2_alt * den * den < d2_home * num * num")
