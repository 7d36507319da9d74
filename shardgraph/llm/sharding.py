"""Sharding by sampled splitters: near-equal bytes, built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from shardgraph.llm.common import Workspace

LOWEST = -(2**63)
#: Parts that a round cuts an overfull range into at most; the next round cuts further.
MOST_PARTS = 256


def _key_hash(text: Column) -> Column:
    """60 bits of md5: equal texts are neighbours in the key order, other texts are spread."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")


def _below(splitters: list[tuple[int, int]]) -> Column:
    """How many splitters are <= (h, tie): a binary search, one lambda step per bit."""
    if not splitters:
        return F.lit(0)
    hs, ts = (F.expr(f"cast(split('{','.join(str(s[i]) for s in splitters)}', ',') as array<bigint>)") for i in (0, 1))
    steps = [2**b for b in range(len(splitters).bit_length() - 1, -1, -1)]

    def step(at: Column, by: Column) -> Column:
        h, t = F.get(hs, at + by - 1), F.get(ts, at + by - 1)
        return F.when((h < F.col("h")) | ((h == F.col("h")) & (t <= F.col("tie"))), at + by).otherwise(at)

    return F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), step)


def _splitters(sample: DataFrame, of: list[str], parts: int) -> dict[tuple, list[tuple[int, int]]]:
    """Group -> boundaries at the sample's quantiles. A key stands for all its copies, unless it is so heavy that it holds several quantiles; those cut its copies by id.

    Quantiles come from a sketch that is aggregated in parts, so only boundaries reach the driver.
    """
    share = [i / parts for i in range(1, parts)]
    accuracy = F.lit(max(10_000, 8 * parts))
    out: dict[tuple, list[tuple[int, int]]] = {}
    heavy: dict[tuple, int] = {}
    for row in sample.groupBy(*of).agg(F.percentile_approx("h", share, accuracy).alias("hs")).collect():
        group = tuple(row[c] for c in of)
        out[group] = [(h, LOWEST) for h in sorted(set(row.hs or []))]
        heavy |= {(*group, h): m - 1 for h in set(row.hs or []) if (m := row.hs.count(h)) > 1}
    if heavy:
        most = max(heavy.values())
        within = sample.where(F.col("h").isin(sorted({k[-1] for k in heavy}))).groupBy(*of, "h").agg(F.percentile_approx("tie", [i / (most + 1) for i in range(1, most + 1)], accuracy).alias("ts"))
        for row in within.collect():
            key = tuple(row[c] for c in (*of, "h"))
            if key in heavy:
                out[key[:-1]] += [(row.h, t) for t in sorted(set(row.ts)) if t > LOWEST]
    return {g: sorted(set(s)) for g, s in out.items()}


def _prefix(values: list[int]) -> list[int]:
    out = [0]
    for v in values[:-1]:
        out.append(out[-1] + v)
    return out


def assign_shards(
    docs: DataFrame,
    n_shards: int = 8,
    id_col: str = "doc_id",
    text_col: str = "text",
    range_bytes: int = 1 << 30,
    range_rows: int = 500_000,
    samples_per_range: int = 64,
    group_share: float = 0.01,
    max_rounds: int = 8,
) -> DataFrame:
    """Contiguous key ranges of near-equal bytes.

    The key is (hash of the text, id). A sample in which each record's chance grows with its size
    gives the quantile boundaries of many small ranges; each range's exact bytes and rows are then
    counted, ranges over twice their share are sampled again and subdivided, and the exact offsets
    of the ranges turn a window inside each range into the global position of every record. A
    shard is the slice of the total bytes that the position falls in, so sizes differ by one
    record or one kept group, not by the error of the sample. Equal texts share a shard while
    their group is under ``group_share`` of a shard; a larger group is cut between records.

    Only the slim (id, size, checksum, hash) rows are shuffled; a hot text is subdivided by id.
    The driver sees the boundaries and sums of the ranges, one a ``range_bytes`` or ``range_rows``; the
    sample stays in the cluster.
    A null text counts as empty (size 1, checksum 0); a null id sorts first; repeated rows each
    get a slot; an empty table gives no rows; other columns of ``docs`` are ignored.
    """
    spark = docs.sparkSession
    ws = Workspace(spark, "shards")
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = ws.write(
        docs.select(
            F.col(id_col).alias("id"),
            (F.octet_length(text).cast("bigint") + 1).alias("size"),
            F.crc32(text.cast("binary")).alias("crc"),
            _key_hash(text).alias("h"),
        ).withColumn("tie", F.coalesce("id", F.lit(LOWEST)).cast("bigint")),
        "base",
    )
    total, rows = base.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count("*")).first()
    n_ranges = max(n_shards * 8, -(-total // range_bytes), -(-rows // range_rows))

    def draw(df: DataFrame, weight: int, want: int, seed: int) -> DataFrame:
        u = F.pmod(F.xxhash64("h", "tie", F.lit(seed)), F.lit(1 << 40)) / float(1 << 40)
        return df.where(u < F.col("size") * (want / max(weight, 1)))

    splits = _splitters(draw(base, total, n_ranges * samples_per_range, 0), [], n_ranges).get((), []) if rows else []
    for i in range(1, max_rounds + 1):
        ranged = base.withColumn("r", _below(splits))
        sums = {x.r: (x.b, x.c) for x in ranged.groupBy("r").agg(F.sum("size").alias("b"), F.count("*").alias("c")).collect()}
        over = {r: max(b * n_ranges // max(total, 1), c * n_ranges // max(rows, 1)) for r, (b, c) in sums.items() if b > 2 * total / n_ranges + 1 or c > 4 * rows / n_ranges + 1000}
        if not over or i == max_rounds:
            break
        again = draw(ranged.where(F.col("r").isin(list(over))), sum(sums[r][0] for r in over), sum(over.values()) * samples_per_range, i)
        more = {*splits, *(k for got in _splitters(again, ["r"], min(MOST_PARTS, max(over.values()) + 1)).values() for k in got)}
        if more == set(splits):
            break
        splits = sorted(more)
    ids = list(range(len(splits) + 1))
    at_bytes, at_rows = (_prefix([sums.get(r, (0, 0))[k] for r in ids]) for k in (0, 1))
    offset = lambda xs: F.get(F.expr(f"cast(split('{','.join(map(str, xs))}', ',') as array<bigint>)"), F.col("r"))

    order = Window.partitionBy("r").orderBy("h", "tie", "size")
    group = Window.partitionBy("r", "h")
    placed = (
        ranged.withColumn("end", F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)) + offset(at_bytes))
        .withColumn("pos", F.row_number().over(order) - 1 + offset(at_rows))
        .withColumn("first", F.min(F.col("end") - F.col("size")).over(group))
        .withColumn("whole", F.sum("size").over(group) <= int(group_share * total / n_shards))
    )
    start = F.when(F.col("whole"), F.col("first")).otherwise(F.col("end") - F.col("size"))
    shard = F.least(F.floor(start.cast("double") * n_shards / float(max(total, 1))), F.lit(n_shards - 1)).cast("int")
    placed = ws.write(placed.select("id", "size", "crc", "pos", shard.alias("shard")), "placed")
    ws.drop("base")
    firsts = {x.shard: x.p for x in placed.groupBy("shard").agg(F.min("pos").alias("p")).collect()}
    begin = F.get(F.array(*[F.lit(firsts.get(s, 0)).cast("bigint") for s in range(n_shards)]), F.col("shard"))
    return placed.select(
        F.col("id").alias("doc_id"),
        "size",
        F.col("crc").alias("text_crc32"),
        F.lit("bytes").alias("law"),
        "shard",
        (F.col("pos") - begin).alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )
