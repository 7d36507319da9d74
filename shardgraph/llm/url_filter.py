"""URL rules behind a blocked Bloom filter, built-in functions only."""

from __future__ import annotations

import hashlib
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import Workspace, letter_case

#: The rules of the contract as (host, path, verdict).
RULES = [
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
]
BLOCK_BITS = 32
PROBES = 4
#: Keys of one filter, whose blocks are a literal of the plan; longer lists take several.
FILTER_KEYS = 100_000
#: Distinct urls with a hit up to which their verdicts are broadcast; beyond, the join back is salted.
FEW_URLS, SALTS = 100_000, 16


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host in lower case (A-Z) and path, both empty without ``://`` or without a url."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.lit(2**31 - 1).cast("int"))).otherwise("")
    rest = F.coalesce(rest, F.lit(""))
    return letter_case(F.regexp_extract(rest, r"^([^/?#]*)", 1)), F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)", 1)


def _digits(key: str) -> tuple[int, int]:
    d = hashlib.md5(key.encode()).hexdigest()
    return int(d[:7], 16), int(d[7:14], 16)


def bloom_words(keys: list[str], bits_per_key: int = 16) -> list[int]:
    """Blocked filter: a key sets PROBES bits of one 32-bit block."""
    n = max(1, -(-len(keys) * bits_per_key // BLOCK_BITS))
    blocks = [0] * n
    for k in keys:
        a, b = _digits(k)
        for i in range(PROBES):
            blocks[a % n] |= 1 << ((b >> (5 * i)) & 31)
    return blocks


def bloom_test(key: Column, blocks: list[int]) -> Column:
    d = F.md5(key)
    a = F.conv(F.substring(d, 1, 7), 16, 10).cast("bigint")
    b = F.conv(F.substring(d, 8, 7), 16, 10).cast("bigint")
    words = F.expr(f"cast(split('{','.join(map(str, blocks))}', ',') as array<bigint>)")
    word = F.get(words, (a % len(blocks)).cast("int"))
    mask = F.lit(0).cast("bigint")
    for i in range(PROBES):
        mask = mask.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.shiftright(b, 5 * i).bitwiseAND(31).cast("int")))
    return word.bitwiseAND(mask) == mask


def filter_urls(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES, default: str = "allow", id_col: str = "page_id", url_col: str = "url", filter_keys: int = FILTER_KEYS, few_urls: int = FEW_URLS) -> DataFrame:
    """Longest rule of each url.

    A url's keys are its host's suffixes at the dots times its path's prefixes of the lengths that
    rules have. The filter passes the keys that may be listed; only these are joined exactly, which
    removes the false positives, and the longest rule by characters wins. One scan of the pages
    writes host, path and possible keys; the join is done once per distinct (host, path). Urls without a possible hit are never shuffled; the others get the
    verdict of their (host, path) by a broadcast while those with a rule are at most ``few_urls``,
    beyond by a join in which every url is dealt over ``SALTS`` salts, so no task sees all rows of a
    hot one. Rules are the list given by the caller; a list over ``filter_keys`` takes several filters.

    A null url, or one without ``://``, has empty host and path, no rule and the default verdict.
    Repeated rows each get their verdict; null ids are kept; other columns are ignored.
    """
    spark = pages.sparkSession
    host, path = host_and_path(F.col(url_col))
    lengths = sorted({len(p) for _, p, _ in rules})
    keys = [f"{h}{p}" for h, p, _ in rules]
    dots = F.split("host", r"\.")
    n = F.size(dots)
    tails = F.transform(F.sequence(F.lit(1), n), lambda i: F.array_join(F.slice(dots, i, n), "."))
    heads = F.array(*[F.when(F.length("path") >= k, F.substring("path", 1, k)) for k in lengths]) if lengths else F.array().cast("array<string>")
    every = F.flatten(F.transform(tails, lambda t: F.transform(F.array_compact(heads), lambda p: F.concat(t, p))))
    filters = [bloom_words(keys[i : i + filter_keys]) for i in range(0, len(keys), filter_keys)]
    may = lambda k: reduce(Column.__or__, [bloom_test(k, blocks) for blocks in filters], F.lit(False))
    urls = pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path"))
    urls = urls.withColumn("probes", F.when(F.col("host") == "", F.array().cast("array<string>")).otherwise(F.filter(every, may)))
    ws = Workspace(spark, "urls")
    urls = ws.write(urls, "urls")
    listed = spark.createDataFrame([(f"{h}{p}", v, len(h) + len(p)) for h, p, v in rules], "key string, verdict string, len int")
    hits = ws.write(
        urls.where("size(probes) > 0").groupBy("host", "path").agg(F.first("probes").alias("probes"))
        .select("host", "path", F.explode("probes").alias("key"))
        .join(listed, "key")
        .groupBy("host", "path")
        .agg(F.max_by(F.struct("key", "verdict"), F.struct("len", "key")).alias("best")),
        "hits",
    )
    some, on = urls.where("size(probes) > 0").drop("probes"), ["host", "path"]
    if hits.count() <= few_urls:
        hits = F.broadcast(hits)
    else:
        some = some.withColumn("salt", F.pmod(F.xxhash64("page_id", F.monotonically_increasing_id()), F.lit(SALTS)).cast("int"))
        hits = hits.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        on = [*on, "salt"]
    judged = some.join(hits, on, "left").select("page_id", "host", "path", F.col("best.key").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))
    return urls.where("size(probes) = 0").select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict")).unionByName(judged)


ORACLE = """
with u as (
  select page_id, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages
), s as (
  select page_id, translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
         regexp_extract(coalesce(rest, ''), '^[^/?#]*(/[^?#]*)', 1) as path from u
), r(h, p, v) as (values ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block'))
select page_id, host, path,
  (select h || p from r where (s.host = h or s.host like '%.' || h) and starts_with(s.path, p) order by length(h) + length(p) desc, h || p desc limit 1) as rule,
  coalesce((select v from r where (s.host = h or s.host like '%.' || h) and starts_with(s.path, p) order by length(h) + length(p) desc, h || p desc limit 1), 'allow') as verdict
from s
"""
