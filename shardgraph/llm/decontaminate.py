"""Benchmark decontamination by greedy string tiling over shared-token seeds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import WORD_BYTES, Workspace, free_name, slices, tidy

MULT = 0x9E3779B97F4A7C15
INVERSE = pow(MULT, -1, 1 << 64)
#: Filter bits a seed, least and most bits: 32 MB to every executor at most, whatever the benchmark's size.
SEED_BITS, LEAST_BITS, MOST_BITS = 64, 1 << 22, 1 << 28
#: Rows up to which seeds, items and results are broadcast, 50 MB or less; beyond, the joins shuffle.
FEW_ROWS = 500_000
#: Between the stretches of a document that hold seeds; no word hashes to it but by a chance of 2^-64.
GAP = -1


def tokens(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(WORD_BYTES).split()


def window_hashes(ids: np.ndarray, n: int) -> np.ndarray:
    """Karp-Rabin hashes of all windows of n ids, from the prefix hashes modulo 2^64."""
    if len(ids) < n:
        return np.empty(0, np.uint64)
    with np.errstate(over="ignore"):
        up, down = (np.multiply.accumulate(np.r_[np.uint64(1), np.full(len(ids) - 1, m, np.uint64)]) for m in (MULT, INVERSE))
        prefix = np.zeros(len(ids) + 1, np.uint64)
        prefix[1:] = np.add.accumulate((ids + 2).astype(np.uint64) * up)
        out = (prefix[n:] - prefix[:-n]) * down[: len(ids) - n + 1]
    return out ^ (out >> np.uint64(29))


def _tiles_of(doc: np.ndarray, item: np.ndarray, used_d: np.ndarray, used_i: np.ndarray, n: int) -> list[tuple[int, int]]:
    """Places (doc, item) of equal unmarked windows of length n, in document order."""
    hd, hi = window_hashes(doc, n), window_hashes(item, n)
    if not len(hd) or not len(hi):
        return []

    def free(used: np.ndarray) -> np.ndarray:
        upto = np.r_[0, np.cumsum(used)]
        return upto[n:] == upto[:-n]

    fi = np.flatnonzero(free(used_i))
    if not len(fi):
        return []
    order = fi[np.argsort(hi[fi], kind="stable")]
    keys = hi[order]
    fd = np.flatnonzero(free(used_d) & np.isin(hd, keys))
    out = []
    for d in fd.tolist():
        a, b = np.searchsorted(keys, hd[d], "left"), np.searchsorted(keys, hd[d], "right")
        out += [(d, i) for i in order[a:b].tolist() if np.array_equal(doc[d : d + n], item[i : i + n])]
    return out


def tile(doc: np.ndarray, item: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """Greedy string tiling: (doc start, item start, length), longest matches marked first.

    The longest unmarked match is found by bisection on the window length, as a match of length n
    holds one of n - 1; all its places that do not overlap are marked, and the search goes on
    below that length until it is under ``least``.
    """
    used_d, used_i, out = np.zeros(len(doc), np.int64), np.zeros(len(item), np.int64), []
    top = min(len(doc), len(item))
    while top >= least and not used_i.all():
        lo, hi = least - 1, top
        found: list[tuple[int, int]] = []
        while lo < hi:
            mid = (lo + hi + 1) // 2
            got = _tiles_of(doc, item, used_d, used_i, mid)
            if got:
                lo, found = mid, got
            else:
                hi = mid - 1
        if lo < least:
            break
        for d, i in found:
            if not used_d[d : d + lo].any() and not used_i[i : i + lo].any():
                used_d[d : d + lo], used_i[i : i + lo] = 1, 1
                out.append((d, i, lo))
        top = lo
    return out


def word_hashes(texts: list[str | None]) -> list[np.ndarray]:
    """64-bit hashes of each text's words, for a whole slice at once."""
    words = [tokens(t) for t in texts]
    flat = [x for w in words for x in w]
    if not flat:
        return [np.empty(0, np.int64) for _ in words]
    ids, uniq = pd.factorize(np.array(flat, dtype=object))
    h = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in uniq), np.uint64, len(uniq)).view(np.int64)[ids]
    return np.split(h, np.cumsum([len(w) for w in words])[:-1])


def seed_hashes(ids: np.ndarray, n: int) -> np.ndarray:
    """Hash of every window of n words; windows of other lengths differ."""
    return (window_hashes(ids, n) * np.uint64(0xD6E8FEB86659FD93) + np.uint64(n)).view(np.int64)


def item_seeds(ids: np.ndarray, seed: int) -> np.ndarray:
    """Distinct seeds of an item: its windows of ``seed`` words, or all of it where it is shorter."""
    return np.unique(seed_hashes(ids, min(seed, len(ids)))) if len(ids) else np.empty(0, np.int64)


def stretches(ids: np.ndarray, starts: np.ndarray, n: int) -> np.ndarray:
    """Marks the words that windows of length n from ``starts`` cover."""
    edge = np.zeros(len(ids) + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + n, -1)
    return np.cumsum(edge[:-1]) > 0


def cut_out(ids: np.ndarray, inside: np.ndarray) -> np.ndarray:
    """The marked words in order, with ``GAP`` between stretches."""
    at = np.flatnonzero(inside)
    return np.insert(ids[at], np.flatnonzero(np.diff(at) > 1) + 1, GAP)


def coverage(doc: np.ndarray, item: np.ndarray, seed: int) -> tuple[float, int, int]:
    """(share of the item's words in tiles, tiles, words covered)."""
    least = min(seed, len(item))
    starts = np.flatnonzero(np.isin(seed_hashes(doc, least), item_seeds(item, seed)))
    if not len(starts):
        return 0.0, 0, 0
    tiles = tile(cut_out(doc, stretches(doc, starts, least)), item, least)  # only the seeds' stretches can hold tiles
    covered = sum(t[2] for t in tiles)
    return covered / len(item), len(tiles), covered


def _ragged(arrays: list[np.ndarray]) -> pa.Array:
    offsets = np.zeros(len(arrays) + 1, np.int32)
    np.cumsum([len(a) for a in arrays], out=offsets[1:])
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(arrays) if arrays else np.empty(0, np.int64), pa.int64()))


def _items_kernel(seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            ids = word_hashes(b.column("text").to_pylist())
            yield pa.RecordBatch.from_pydict({"item_id": b.column("item_id"), "words": _ragged(ids), "seeds": _ragged([item_seeds(x, seed) for x in ids])})

    return run


def _bit(bits: np.ndarray, h: np.ndarray) -> np.ndarray:
    at = h.view(np.uint64) & np.uint64(len(bits) * 64 - 1)
    return ((bits[at >> np.uint64(6)] >> (at & np.uint64(63))) & np.uint64(1)).astype(bool)


def _candidates_kernel(shared):
    """Texts with a window that the filter knows: their key, those windows' hashes and the words under them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits, lengths = shared.value
        for b in slices(batches):
            rows, seeds, parts = [], [], []
            for i, ids in enumerate(word_hashes(b.column("text").to_pylist())):
                inside, found = np.zeros(len(ids), bool), []
                for n in lengths:
                    h = seed_hashes(ids, n)
                    starts = np.flatnonzero(_bit(bits, h))
                    starts = starts[_bit(bits, h[starts] >> 32)]
                    if len(starts):
                        found.append(h[starts])
                        inside |= stretches(ids, starts, n)
                if found:
                    rows.append(i), seeds.append(np.unique(np.concatenate(found))), parts.append(cut_out(ids, inside))
            take = pa.array(rows, pa.int64())
            yield pa.RecordBatch.from_pydict({"k1": b.column("k1").take(take), "k2": b.column("k2").take(take), "seeds": _ragged(seeds), "words": _ragged(parts)})

    return run


def _tile_kernel(seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc, item = b.column("words"), b.column("item_words")
            got = [coverage(doc[i].values.to_numpy(), item[i].values.to_numpy(), seed) for i in range(b.num_rows)]
            cols = list(zip(*got, strict=True)) or [[]] * 3
            numbers = {"coverage": pa.array(cols[0], pa.float64()), "n_tiles": pa.array(cols[1], pa.int32()), "n_covered": pa.array(cols[2], pa.int64())}
            yield pa.RecordBatch.from_pydict({**{c: b.column(c) for c in ("k1", "k2", "item_id")}, **numbers})

    return run


def _seed_filter(seeds: DataFrame) -> np.ndarray:
    """Bitmap of seed hashes in 64-bit words, two bits a seed; what reaches the driver is one number a word that has bits."""
    n = max(1, seeds.count())
    bits = min(MOST_BITS, max(LEAST_BITS, 1 << (SEED_BITS * n - 1).bit_length()))
    at = F.col("p").bitwiseAND(bits - 1)  # bits is a power of two, so this is the unsigned remainder
    words = seeds.select(F.explode(F.array("h", F.shiftright("h", 32))).alias("p")).select(F.shiftright(at, 6).alias("word"), F.call_function("shiftleft", F.lit(1).cast("bigint"), at.bitwiseAND(63).cast("int")).alias("bit"))
    got = words.groupBy("word").agg(F.bit_or("bit").alias("bits")).toArrow()
    out = np.zeros(bits // 64, np.uint64)
    out[got.column("word").to_numpy()] = got.column("bits").to_numpy().view(np.uint64)
    return out


def covered_by(docs: DataFrame, benchmark: DataFrame, seed: int = 5, text_col: str = "text", name: str = "_overlap", threshold: float = 0.5, few_rows: int = FEW_ROWS) -> DataFrame:
    """``docs`` with a struct column ``name`` of (item_id, coverage, n_tiles, n_covered, leaks).

    The item covered most (the smallest id of equals) and its numbers; ``leaks`` lists every item
    with a coverage of ``threshold`` or more. Coverage is the share of an item's words in tiles of
    at least ``seed`` words (items shorter than that must occur whole), whatever their order, so
    shuffled passages count.

    One pass over the documents hashes their windows of ``seed`` words against a bitmap of the
    benchmark's; only texts that pass leave it, once per distinct text, as the hashes found and the
    words under them. These seeds are joined with those of the items, and every (text, item) that
    shares one is tiled: repeatedly the longest unmarked match, by running Karp-Rabin hashes. The
    bitmap is bounded; the benchmark itself may be of any size, as seeds, items and results are
    broadcast while they have at most ``few_rows`` rows and shuffled beyond. Equal texts are told
    by 128 bits of hash.

    A null or empty text, an empty benchmark and null items give coverage 0. All rows and columns
    of ``docs`` stay, repeated rows and null ids too; where ``docs`` has a column ``name``, the new
    one has underscores added (``free_name``).
    """
    spark = docs.sparkSession
    ws = Workspace(spark, "leaks")
    source = benchmark.where("text is not null and item_id is not null").select(F.col("item_id").cast("bigint").alias("item_id"), F.col("text").cast("string").alias("text")).distinct()
    items = source.mapInArrow(tidy(_items_kernel(seed)), "item_id bigint, words array<bigint>, seeds array<bigint>").where("size(words) > 0")
    items = ws.write(items.withColumn("item", F.xxhash64("item_id", "words")), "items")
    seeds = ws.write(items.select("item", F.explode("seeds").alias("h")), "seeds")
    lengths = sorted(r.n for r in items.select(F.least(F.size("words"), F.lit(seed)).alias("n")).distinct().collect())
    shared = spark.sparkContext.broadcast((_seed_filter(seeds), lengths))

    def small(df: DataFrame, rows: int | None = None) -> DataFrame:
        return F.broadcast(df) if (df.count() if rows is None else rows) <= few_rows else df

    k1, k2 = free_name(docs, "_k1"), free_name(docs, "_k2")
    text = F.col(text_col).cast("string")
    keys = F.xxhash64(text), F.xxhash64(F.lit(7), text)
    passing = docs.select(keys[0].alias("k1"), keys[1].alias("k2"), text.alias("text")).where("text <> ''").mapInArrow(tidy(_candidates_kernel(shared)), "k1 bigint, k2 bigint, seeds array<bigint>, words array<bigint>")
    texts = ws.write(passing.groupBy("k1", "k2").agg(F.first("seeds").alias("seeds"), F.first("words").alias("words")), "texts")
    shared.destroy()
    pairs = texts.select("k1", "k2", F.explode("seeds").alias("h")).join(small(seeds), "h").select("k1", "k2", "item").distinct()
    n_words = items.agg(F.coalesce(F.sum(F.size("words")), F.lit(0))).first()[0]
    whole = items.select("item", "item_id", F.col("words").alias("item_words"))
    tried = pairs.join(texts.select("k1", "k2", "words"), ["k1", "k2"]).join(F.broadcast(whole) if n_words <= 10 * few_rows else whole, "item")
    tasks = 2 * spark.sparkContext.defaultParallelism  # few bytes, much work: not to be coalesced by size
    tiled = tried.select("k1", "k2", "item_id", "words", "item_words").repartition(tasks).mapInArrow(tidy(_tile_kernel(seed)), "k1 bigint, k2 bigint, item_id bigint, coverage double, n_tiles int, n_covered bigint")
    best = F.max_by(F.struct("item_id", "coverage", "n_tiles", "n_covered"), F.struct("coverage", -F.col("item_id")))
    leaks = F.sort_array(F.collect_set(F.when(F.col("coverage") >= threshold, F.col("item_id"))))
    found = ws.write(tiled.where("n_covered > 0").groupBy(F.col("k1").alias(k1), F.col("k2").alias(k2)).agg(best.alias("_b"), leaks.alias("_l")), "found")
    ws.drop("seeds", "items", "texts")
    extra = free_name(docs, "_f")
    got, found_leaks = F.col(f"{extra}._b"), F.col(f"{extra}._l")
    out = F.struct(
        got["item_id"].alias("item_id"),
        F.coalesce(got["coverage"], F.lit(0.0)).alias("coverage"),
        F.coalesce(got["n_tiles"], F.lit(0)).alias("n_tiles"),
        F.coalesce(got["n_covered"], F.lit(0).cast("bigint")).alias("n_covered"),
        F.coalesce(found_leaks, F.array().cast("array<bigint>")).alias("leaks"),
    )
    both = docs.withColumns({k1: keys[0], k2: keys[1]}).join(small(found.select(k1, k2, F.struct("_b", "_l").alias(extra))), [k1, k2], "left")
    return both.select(*[F.col(f"`{c}`") for c in docs.columns], out.alias(free_name(docs, name)))


def contaminated(threshold: float = 0.5, name: str = "_overlap"):
    return F.col(name)["coverage"] >= threshold
