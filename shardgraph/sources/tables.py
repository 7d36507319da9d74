"""Vector collections over the given tables; ids are stable and ties always end in the id."""

from __future__ import annotations

import hashlib
import itertools
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph.functions import vectors as v
from shardgraph.operators.arrays import lists
from shardgraph.registry import read


def e64(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "embeddings").select("vec_id", "embedding")


def e64q(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantised embeddings: exact integers in every engine."""
    return read(spark, sf_dir, "embeddings").select("vec_id", v.quantize(F.col("embedding")).alias("q"), "label")


def _bucketed(tokens: DataFrame, dims: int) -> DataFrame:
    """(id, bucket, s): signed sums of the token hashes; 28 bits of md5 give bucket and sign in any engine.

    Equal tokens of a text are counted first, so each is hashed once.
    """
    counted = tokens.groupBy("vec_id", "tok").agg(F.count("*").alias("n"))
    h = F.conv(F.substring(F.md5("tok"), 1, 7), 16, 10).cast("bigint")
    signed = counted.withColumn("h", h).select("vec_id", (F.col("h") % dims).cast("int").alias("bucket"), (F.col("n") * (1 - 2 * (F.floor(F.col("h") / dims) % 2))).cast("bigint").alias("s"))
    return signed.groupBy("vec_id", "bucket").agg(F.sum("s").alias("s")).where("s <> 0")


def hashed_words(texts: DataFrame, dims: int = 768) -> DataFrame:
    """Sparse signed word hashing of (vec_id, text): words of ASCII letters and digits of the whole text."""
    words = F.filter(F.split(F.lower("text"), "[^a-z0-9]+"), lambda w: w != "")
    return _bucketed(texts.select("vec_id", F.explode(words).alias("tok")), dims)


def hashed_trigrams(texts: DataFrame, dims: int = 96) -> DataFrame:
    """The same over character tri-grams."""
    # characters first: substr would walk the text anew for every position
    grams = F.when(F.size("c") >= 3, F.transform(F.sequence(F.lit(1), F.size("c") - 2), lambda i: F.concat(F.get("c", i - 1), F.get("c", i), F.get("c", i + 1))))
    chars = texts.select("vec_id", F.regexp_extract_all(F.lower("text"), F.lit("(?s)."), F.lit(0)).alias("c"))
    return _bucketed(chars.select("vec_id", F.explode(grams).alias("tok")), dims)


def _units(x: np.ndarray) -> pa.ListArray:
    """Rows as unit vectors times 1000, rounded."""
    norm = np.sqrt((x * x).sum(axis=1, keepdims=True))
    q = np.floor(x * 1000 / norm + 0.5).astype(np.int32)
    return lists(pa.array(q.ravel()), np.full(len(x), x.shape[1]))


def densify(sparse: DataFrame, dims: int) -> DataFrame:
    """Unit vectors times 1000, rounded: rows (vec_id, q). Scatter in numpy, as a map lookup per component is linear in the entries."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, 2048):
                b = whole.slice(a, 2048)
                entries = b.column("e")
                row = np.repeat(np.arange(b.num_rows), np.diff(entries.offsets.to_numpy()))
                flat = entries.flatten()
                x = np.zeros((b.num_rows, dims))
                x[row, flat.field("bucket").to_numpy()] = flat.field("s").to_numpy()
                yield pa.RecordBatch.from_arrays([b.column("vec_id"), _units(x)], names=["vec_id", "q"])

    one = sparse.groupBy("vec_id").agg(F.collect_list(F.struct("bucket", "s")).alias("e"))
    return one.mapInArrow(run, "vec_id bigint, q array<int>")


class _Codes(dict):
    """Word -> 2 * bucket + (1 for a negative sign), hashed when it is first asked for."""

    def __init__(self, dims: int):
        super().__init__()
        self.dims = dims

    def __missing__(self, word: bytes) -> int:
        h = int(hashlib.md5(word, usedforsecurity=False).hexdigest()[:7], 16)
        if len(self) >= KEPT_WORDS:
            self.clear()
        self[word] = code = 2 * (h % self.dims) + h // self.dims % 2
        return code


#: Words whose hash a task keeps, and bytes of text that it takes apart at once.
KEPT_WORDS, TEXT_BYTES = 500_000, 4 << 20


def hashed_units(texts: DataFrame, dims: int = 768) -> DataFrame:
    """``densify(hashed_words(texts, dims), dims)`` without a row per word: sums of a text are made where it is read, and only these meet by id."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes, words = _Codes(dims), re.compile(rb"[a-z0-9]+")
        for whole in batches:
            size = np.cumsum(pc.binary_length(whole.column(1)).to_numpy(zero_copy_only=False)) if whole.num_rows else np.zeros(0)
            cuts = np.flatnonzero(np.diff(size // TEXT_BYTES, prepend=0)).tolist() if len(size) else []
            for a, z in zip([0, *cuts], [*cuts, whole.num_rows], strict=True):
                for c in range(a, z, 1024):
                    b = whole.slice(c, min(1024, z - c))
                    found = [words.findall(t) for t in b.column(1).to_pylist()]
                    n = np.array([len(w) for w in found])
                    code = np.fromiter(map(codes.__getitem__, itertools.chain.from_iterable(found)), np.int64, n.sum())
                    x = np.bincount(np.repeat(np.arange(len(found)), n) * dims + code // 2, 1.0 - 2 * (code % 2), len(found) * dims)
                    real = np.flatnonzero(x != 0)
                    row, col = np.divmod(real, dims)
                    pairs = np.c_[col, x[real]].astype(np.int32)
                    ends = np.searchsorted(row, np.arange(len(found) + 1))
                    yield pa.RecordBatch.from_arrays([b.column(0), pa.array([pairs[i:j].tobytes() for i, j in zip(ends, ends[1:], strict=False)], pa.binary())], names=["vec_id", "e"])

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, 2048):
                b = whole.slice(a, 2048)
                parts = b.column(1).flatten().to_pylist()
                of = np.repeat(np.arange(b.num_rows), np.diff(b.column(1).offsets.to_numpy()))
                pairs = np.frombuffer(b"".join(parts), np.int32).reshape(-1, 2)
                row = np.repeat(of, [len(p) // 8 for p in parts])
                x = np.bincount(row * dims + pairs[:, 0], pairs[:, 1], b.num_rows * dims).reshape(-1, dims)
                real = x.any(axis=1)
                yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(real)), _units(x[real])], names=["vec_id", "q"])

    low = texts.where("text is not null").select(F.col("vec_id").cast("bigint").alias("vec_id"), F.lower("text").cast("binary").alias("t"))
    one = low.mapInArrow(sums, "vec_id bigint, e binary").where("length(e) > 0").groupBy("vec_id").agg(F.collect_list("e").alias("e"))
    return one.mapInArrow(dense, "vec_id bigint, q array<int>")


def documents_768(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed_units(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text"))


def documents_96(spark: SparkSession, sf_dir: str) -> DataFrame:
    return densify(hashed_trigrams(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text")), 96)


def benchmark_768(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed_units(read(spark, sf_dir, "benchmark").select(F.col("item_id").alias("vec_id"), "text"))


#: Means and deviations that standardise the four numeric columns of lineitem.
L4_STATS = {"l_quantity": (25.5, 14.4), "l_extendedprice": (38000.0, 23000.0), "l_discount": (0.05, 0.03), "l_tax": (0.04, 0.026)}


def lineitem_4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four standardised columns as integers; the id is a hash of the row, as no key is unique."""
    t = read(spark, sf_dir, "lineitem")
    z: list[Column] = [F.floor((F.col(c) - m) / s * 1000 + 0.5).cast("int") for c, (m, s) in L4_STATS.items()]
    return t.select(F.xxhash64(*t.columns).alias("vec_id"), F.array(*z).alias("q")).dropDuplicates(["vec_id"])


def page_text(html: Column) -> Column:
    """Page without scripts, styles, tags and the five basic entities, blanks folded."""
    t = F.regexp_replace(html, r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    t = F.regexp_replace(t, r"(?s)<[^>]*>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        t = F.replace(t, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(t, r"[ \t\r\n]+", " "))


def conversation_text(turns: DataFrame) -> DataFrame:
    """One text per conversation, turns in order."""
    lists = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("t"), F.count("*").alias("n_turns"))
    return lists.select("conv_id", "n_turns", F.array_join(F.transform("t", lambda x: F.concat(x["role"], F.lit(": "), x["text"])), "\n").alias("text"))
