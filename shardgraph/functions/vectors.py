"""Vector arithmetic as Columns; everything stays in the JVM."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _fold(values: Column, kind: str) -> Column:
    return F.aggregate(values, F.lit(0).cast(kind), lambda s, x: s + x)


def l2sq(a: Column, b: Column, kind: str = "bigint") -> Column:
    """Squared Euclidean distance; ``bigint`` is exact for quantised vectors, ``double`` for others."""
    return _fold(F.zip_with(a, b, lambda x, y: ((x - y) * (x - y)).cast(kind)), kind)


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b, "double"))


def ip(a: Column, b: Column, kind: str = "bigint") -> Column:
    return _fold(F.zip_with(a, b, lambda x, y: (x * y).cast(kind)), kind)


def norm(a: Column) -> Column:
    return F.sqrt(_fold(F.transform(a, lambda x: (x * x).cast("double")), "double"))


def cosine(a: Column, b: Column) -> Column:
    """Cosine similarity, null where a vector is zero."""
    return ip(a, b, "double") / F.nullif(norm(a) * norm(b), F.lit(0.0))


def l1(a: Column, b: Column, kind: str = "bigint") -> Column:
    return _fold(F.zip_with(a, b, lambda x, y: F.abs(x - y).cast(kind)), kind)


def linf(a: Column, b: Column) -> Column:
    return F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y)))


def normalize(a: Column) -> Column:
    return F.transform(a, lambda x: x.cast("double") / F.nullif(norm(a), F.lit(0.0)))


def quantize(a: Column, scale: int = 1000) -> Column:
    """Integers floor(x * scale + 1/2), the exact form for checks against other engines."""
    return F.transform(a, lambda x: F.floor(x.cast("double") * scale + 0.5).cast("int"))


def quantize_u8(a: Column) -> Column:
    """One byte a component for values in [-1, 1]."""
    return F.transform(a, lambda x: F.greatest(F.lit(0), F.least(F.lit(255), F.floor((x.cast("double") + 1) * 127.5 + 0.5))).cast("smallint"))


def dequantize(a: Column, scale: int = 1000) -> Column:
    return F.transform(a, lambda x: x.cast("double") / scale)


def add_scaled(a: Column, b: Column, s: float) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y * s)


def is_valid(a: Column, dim: int) -> Column:
    fine = F.forall(a, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) != float("inf")))
    return F.coalesce(a.isNotNull() & (F.size(a) == dim) & fine, F.lit(False))


def validated(vectors: DataFrame, dim: int, col: str = "embedding") -> DataFrame:
    """``vectors``; reading a row that is null, ragged or not finite raises an error."""
    c = F.col(col)
    return vectors.withColumn(col, F.when(is_valid(c, dim), c).otherwise(F.raise_error(F.lit(f"{col} is not a finite vector of {dim} components")).cast(vectors.schema[col].dataType)))


def sum_by(vectors: DataFrame, key: str, col: str = "q") -> DataFrame:
    """Component sums per key, partially aggregated per (key, position): no group is collected."""
    parts = vectors.select(key, F.posexplode(col).alias("pos", "x")).groupBy(key, "pos").agg(F.sum("x").alias("s"), F.count("*").alias("n"))
    return parts.groupBy(key).agg(F.max("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("pos", "s"))), lambda t: t["s"]).alias("sums"))


def mean_by(vectors: DataFrame, key: str, col: str = "q") -> DataFrame:
    """Rounded component means per key: the centroid set that needs no iteration."""
    return sum_by(vectors, key, col).select(key, "n", F.transform("sums", lambda s: F.floor(s / F.col("n") + 0.5).cast("int")).alias("centroid"))
