"""Exact 5-word-shingle Jaccard join over token-combination prefixes."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph.llm.common import Workspace, components, slices, tidy

#: From this size on frequent tokens are indexed in pairs, below SINGLE_UNDER one by one; sizes between do both, so that any two linked sets meet.
PAIR_FROM, SINGLE_UNDER = 16, 20
#: Of two linked sets without a rare token in common, two shared tokens stand at most so many ranks apart in both extended prefixes.
GAP = 4
#: Bins of tokens in which documents are counted: least and most, and those that share a row.
BINS, CELL = (1 << 18, 1 << 24), 1 << 15
#: Slices of sets outside a group's largest component up to which they meet all of the group; it bounds the copies of a set.
MOST_CHUNKS = 16
ODD = [np.uint64(x | 1) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)]


def mix64(h: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return h ^ (h >> np.uint64(33))


def shingle_sets(texts: list[str | None], width: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of each text, for a whole batch at once.

    Words are what ``bytes.split`` gives: maximal runs without blank, tab, newline, vertical tab,
    form feed and carriage return, after A-Z is lower-cased. A text of fewer than ``width`` words
    is one shingle; null, empty and blank texts have none.
    """
    words = [(t or "").encode("utf-8", "surrogatepass").lower().split() for t in texts]
    ends = np.cumsum([len(w) for w in words], dtype=np.int64)
    flat = [x for w in words for x in w]
    if not flat:
        return [np.empty(0, np.int64) for _ in words]
    ids, uniq = pd.factorize(np.array(flat, dtype=object))
    h = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in uniq), np.uint64, len(uniq))[ids]
    n = max(0, len(h) - width + 1)
    with np.errstate(over="ignore"):
        rolled = np.zeros(n, np.uint64)
        for k in range(width):
            rolled += mix64(h[k : k + n] * ODD[k % 5] + np.uint64(k))
    rolled = mix64(rolled)
    out, start = [], 0
    for w, end in zip(words, ends.tolist(), strict=True):
        if len(w) >= width:
            s = np.unique(rolled[start : end - width + 1])
        elif w:
            s = np.array([xxhash.xxh3_64_intdigest(b" ".join(w))], np.uint64)
        else:
            s = np.empty(0, np.uint64)
        out.append(s.view(np.int64))
        start = end
    return out


def _lists(arrays: list[np.ndarray]) -> pa.Array:
    offsets = np.zeros(len(arrays) + 1, np.int64)
    np.cumsum([len(a) for a in arrays], out=offsets[1:])
    flat = np.concatenate(arrays) if arrays else np.empty(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(flat, pa.int64()))


def _batch(sets: list[np.ndarray], doc_ids: pa.Array, n_hot: np.ndarray, hot: list[np.ndarray]) -> pa.RecordBatch:
    ent = np.array([xxhash.xxh3_64_intdigest(s.tobytes()) for s in sets], np.uint64).view(np.int64)
    n = np.array([len(s) for s in sets], np.int64)
    return pa.RecordBatch.from_pydict({"doc_id": doc_ids, "ent": pa.array(ent), "n": pa.array(n), "n_hot": pa.array(n_hot), "tokens": _lists(hot)})


DOC = "doc_id bigint, ent bigint, n bigint, n_hot bigint, tokens array<bigint>"


def _sets_kernel(width: int):
    """Each text with all its tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            sets = shingle_sets(b.column("text").to_pylist(), width)
            yield _batch(sets, b.column("doc_id"), np.zeros(len(sets), np.int64), sets)

    return run


PACKED = f"bucket int, ents binary, rows binary, toks binary, docs array<struct<{DOC.replace(' bigint', ':bigint').replace(' array', ':array')}>>"


def _pack_kernel(width: int, share: int, parts: int, frequent: bytes):
    """One row per slice and hash bucket with the slice's rare tokens there, packed; and rows of document data.

    Frequent tokens (``frequent`` has a bit for each bin) stay with documents that are frequent for at least ``share`` percent.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        flags = np.unpackbits(np.frombuffer(frequent, np.uint8)).astype(bool)
        for turn, b in enumerate(slices(batches, 2_000_000)):
            sets = shingle_sets(b.column("text").to_pylist(), width)
            size = np.array([len(s) for s in sets], np.int64)
            flat = np.concatenate(sets) if sets else np.empty(0, np.int64)
            row = np.repeat(np.arange(len(sets), dtype=np.uint32), size)
            is_hot = flags[_bin(flat, len(flags))] if len(flags) else np.zeros(len(flat), bool)
            n_hot = np.bincount(row, is_hot, len(sets)).astype(np.int64)
            keep = (n_hot >= -(-size * share // 100)) & (n_hot > 0)
            at = np.r_[0, np.cumsum(size)]
            hot = [s[is_hot[i:j]] if k else s[:0] for s, i, j, k in zip(sets, at, at[1:], keep.tolist(), strict=False)]
            docs = _batch(sets, b.column("doc_id"), n_hot, hot)
            ents = docs.column("ent").to_numpy()
            live = ~is_hot & ~np.asarray(b.column("doc_id").is_null())[row]
            tok, row = flat[live], row[live]
            bucket = ((tok.view(np.uint64) >> np.uint64(20)) % np.uint64(parts)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            cut = np.searchsorted(bucket[order], np.arange(parts + 1))
            out: dict[str, list] = {"bucket": [], "ents": [], "rows": [], "toks": [], "docs": []}
            for k in range(parts):
                o = order[cut[k] : cut[k + 1]]
                if len(o):
                    who, r = np.unique(row[o], return_inverse=True)
                    for name, x in (("bucket", k), ("ents", ents[who].tobytes()), ("rows", r.astype(np.uint32 if len(who) > 65535 else np.uint16).tobytes()), ("toks", tok[o].tobytes()), ("docs", None)):
                        out[name].append(x)
            kinds = {"bucket": pa.int32(), "ents": pa.binary(), "rows": pa.binary(), "toks": pa.binary(), "docs": pa.list_(pa.struct(docs.schema))}
            yield pa.RecordBatch.from_pydict({k: pa.array(x, kinds[k]) for k, x in out.items()})
            one = pa.ListArray.from_arrays(pa.array([0, docs.num_rows], pa.int32()), docs.to_struct_array())
            none = {k: pa.nulls(1, kinds[k]) for k in ("ents", "rows", "toks")}
            yield pa.RecordBatch.from_pydict({"bucket": pa.array([(turn + len(flat)) % parts], pa.int32()), **none, "docs": one})

    return run


HELD = "ent bigint, tok bigint, df bigint, docs array<struct<" + DOC.replace(" bigint", ":bigint").replace(" array", ":array") + ">>"


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Tokens that two or more sets hold, with the number of those sets, bucket by bucket; document data passes.

    A task's rows come sorted by bucket, so one bucket at a time is in memory.
    """
    now, toks, ents = None, [], []
    for b in batches:
        docs = b.filter(b.column("docs").is_valid()).column("docs")
        if len(docs):
            yield pa.RecordBatch.from_pydict({**{k: pa.nulls(len(docs), pa.int64()) for k in ("ent", "tok", "df")}, "docs": docs})
        for k, e, r, t in zip(*(b.column(c).to_pylist() for c in ("bucket", "ents", "rows", "toks")), strict=True):
            if t is None:
                continue
            if k != now:
                yield from _held_by_many(toks, ents)
                now, toks, ents = k, [], []
            who = np.frombuffer(e, np.int64)
            toks.append(np.frombuffer(t, np.int64))
            ents.append(who[np.frombuffer(r, np.uint16 if len(who) <= 65535 else np.uint32)])
    yield from _held_by_many(toks, ents)


def _held_by_many(toks: list[np.ndarray], ents: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    if not toks:
        return
    tok, ent = np.concatenate(toks), np.concatenate(ents)
    toks.clear(), ents.clear()
    order = np.argsort(tok, kind="stable")
    tok, ent = tok[order], ent[order]
    again = np.zeros(len(tok), bool)
    again[1:] = tok[1:] == tok[:-1]
    again[:-1] |= again[1:]
    tok, ent = tok[again], ent[again]
    order = np.lexsort((ent, tok))
    tok, ent = tok[order], ent[order]
    keep = np.ones(len(tok), bool)
    keep[1:] = (tok[1:] != tok[:-1]) | (ent[1:] != ent[:-1])  # equal texts count once
    tok, ent = tok[keep], ent[keep]
    if not len(tok):
        return
    first = np.flatnonzero(np.r_[True, tok[1:] != tok[:-1]])
    df = np.diff(np.r_[first, len(tok)])
    df = np.repeat(df, df)
    m = df > 1
    tok, ent, df = tok[m], ent[m], df[m]
    kind = pa.list_(pa.struct([("doc_id", pa.int64()), ("ent", pa.int64()), ("n", pa.int64()), ("n_hot", pa.int64()), ("tokens", pa.list_(pa.int64()))]))
    for i in range(0, len(tok), 100_000):
        part = slice(i, i + 100_000)
        yield pa.RecordBatch.from_pydict({"ent": pa.array(ent[part]), "tok": pa.array(tok[part]), "df": pa.array(df[part]), "docs": pa.nulls(len(tok[part]), kind)})


def linked_heads(sets: list[np.ndarray], share: int) -> np.ndarray:
    """For each set the position of the first set of its component under the exact join.

    A search from each set not yet reached compares the frontier with the sets left alone, so in
    a dense group few sets are ever compared with many.
    """
    size = np.array([len(s) for s in sets], np.int64)
    flat, tok = np.unique(np.concatenate(sets), return_inverse=True) if sets else (np.empty(0), np.empty(0, np.int64))
    row = np.repeat(np.arange(len(sets)), size)
    order = np.argsort(tok, kind="stable")
    holders, at = row[order], np.r_[0, np.cumsum(np.bincount(tok, minlength=len(flat)))]
    start = np.r_[0, np.cumsum(size)]
    head, todo = np.full(len(sets), -1), np.ones(len(sets), bool)
    for i in range(len(sets)):
        if not todo[i]:
            continue
        head[i], todo[i], frontier = i, False, [i]
        while frontier and todo.any():
            x = frontier.pop()
            mine = tok[start[x] : start[x + 1]]
            spans = [holders[at[t] : at[t + 1]] for t in mine.tolist()]
            inter = np.bincount(np.concatenate(spans), minlength=len(sets)) if spans else np.zeros(len(sets), np.int64)
            hit = np.flatnonzero(todo & (inter > 0) & (inter * 100 >= (size + size[x] - inter) * share))
            head[hit], todo[hit] = i, False
            frontier += hit.tolist()
    return head


def _bin(tokens: np.ndarray, bins: int) -> np.ndarray:
    return tokens & np.int64(bins - 1)


def _count_kernel(width: int, bins: int):
    """Documents of a task by bin of their tokens, compressed; one row for each cell of bins."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(bins, np.uint32)
        for b in slices(batches):
            sets = shingle_sets(b.column("text").to_pylist(), width)
            np.add.at(n, _bin(np.concatenate(sets), bins), np.uint32(1))
        for k, x in enumerate(n.reshape(-1, CELL)):
            if most := x.max():
                packed = zlib.compress(x.astype(np.min_scalar_type(most)).tobytes(), 1)
                yield pa.RecordBatch.from_pydict({"cell": pa.array([k], pa.int32()), "packed": pa.array([packed], pa.binary())})

    return run


def _frequent_kernel(floor: int):
    """The cells' counts added up over all tasks, as a bit for each bin: whether it has ``floor`` documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for b in batches:
            for k, packed in zip(b.column("cell").to_pylist(), b.column("packed").to_pylist(), strict=True):
                raw = zlib.decompress(packed)
                sums.setdefault(k, np.zeros(CELL, np.int64))
                sums[k] += np.frombuffer(raw, f"u{len(raw) // CELL}")
        bits = [np.packbits(x >= floor).tobytes() for x in sums.values()]
        yield pa.RecordBatch.from_pydict({"cell": pa.array(list(sums), pa.int32()), "packed": pa.array(bits, pa.binary())})

    return run


def frequent_tokens(docs: DataFrame, width: int, total: int, chars: int, share: float, least: int) -> bytes:
    """A bit for each bin of tokens, set where the bin's tokens are frequent; empty if none can be.

    A bin is frequent if its tokens stand in ``share`` of all documents (those of several of its
    tokens count for each). These are counts over the whole table, so every token of so many
    documents is frequent, and a rare one has fewer. There are so many bins that the mean one has
    about an eighth of that or less, up to 20,000 shingles a document; a rare token in a frequent
    bin is treated like a frequent one, which costs work and no link: any split gives all links.
    """
    floor = max(1, least, int(share * total))
    if total < floor:
        return b""
    bins = min(max(BINS[0], 1 << int(8 * chars / (6 * floor)).bit_length()), BINS[1])
    counts = docs.where("doc_id is not null").mapInArrow(tidy(_count_kernel(width, bins)), "cell int, packed binary")
    found = counts.repartitionById(bins // CELL, "cell").mapInArrow(tidy(_frequent_kernel(floor)), "cell int, packed binary").collect()
    bits = dict(found)
    return b"".join(bits.get(k, bytes(CELL // 8)) for k in range(bins // CELL))


def _hot_keys(hot: DataFrame, share: int) -> DataFrame:
    """Keys of sets that are frequent for the most part: single tokens for small sets, pairs of near ranks for the others."""
    c = F.col("n") - F.ceil(F.col("n") * share / 100)
    d = F.greatest(F.lit(0), F.size("tokens") - F.ceil(F.col("n") * share / 100))
    one = hot.where(F.col("n") < SINGLE_UNDER).select("ent", "n", F.explode(F.slice("tokens", F.lit(1), (d + 1).cast("int"))).alias("tok"))
    long = hot.where(F.col("n") >= PAIR_FROM).select("ent", "n", F.slice("tokens", F.lit(1), (d + c + 1).cast("int")).alias("p"))
    near = long.select("ent", "n", F.posexplode("p").alias("i", "x"), "p").select("ent", "n", "x", F.explode(F.slice("p", F.col("i") + 2, F.lit(GAP))).alias("y"))
    return one.select("ent", "n", F.xxhash64("tok", F.lit(1)).alias("key")).unionByName(near.select("ent", "n", F.xxhash64("x", "y", F.lit(2)).alias("key")))


def similar_components(
    docs: DataFrame,
    width: int = 5,
    share: int = 80,
    frequent_share: float = 0.01,
    frequent_least: int = 64,
    rows_per_partition: int = 3_000_000,
    rows_per_bucket: int = 500_000,
    group_tokens: int = 500_000,
    group_rows: int = 256,
    rounds: int = 8,
) -> DataFrame:
    """Rows (doc_id, n_shingles, component_id): components of the exact join ``jaccard >= share / 100``.

    1. Every text becomes its set of hashed shingles; equal sets are one entity from here on.
    2. Tokens in the order rare before frequent, by document frequency within the rare ones, give
       the prefix filter. One shuffle of the packed rare tokens counts them; those of one set
       vanish there; a task sorts its packed rows by bucket and holds one bucket of about
       ``rows_per_bucket`` tokens at a time. Frequent tokens, which a pass over all texts counts
       before, never enter that shuffle. If the first shared token of a linked pair is frequent,
       all its shared tokens are; only sets that are frequent for 80 % can be in such a pair, and
       these index two-token combinations of an extended prefix.
    3. Entities that share keys form candidate groups. A group of up to ``group_tokens`` shingles
       and ``group_rows`` sets is verified exactly in one task, each set sent once and no pair
       listed. Larger ones are cut: rounds of random slices of that size fuse near copies; then the
       sets outside of a group's largest component are verified with all that may link with them.

    A null or blank text has an empty set and links with nothing; a null id is in the result with
    a null component; rows that repeat an id are one document (its smallest set hash counts); an
    empty table gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    ws = Workspace(spark, "jaccard")
    src = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    total, chars = src.agg(F.count("*"), F.coalesce(F.sum(F.length("text")), F.lit(0))).first()
    frequent = frequent_tokens(src, width, total, chars, frequent_share, frequent_least)
    parts = max(8, -(-chars // (6 * rows_per_partition)))
    subs = -(-rows_per_partition // rows_per_bucket)
    packed = src.mapInArrow(tidy(_pack_kernel(width, share, parts * subs, frequent)), PACKED)
    dealt = packed.repartitionById(parts, F.floor(F.col("bucket") / subs).cast("int")).sortWithinPartitions("bucket")
    held = ws.write(dealt.mapInArrow(tidy(_shared), HELD), "held")
    meta = held.where("docs is not null").select(F.inline("docs"))
    by_id = meta.groupBy("doc_id").agg(F.min_by(F.struct("ent", "n"), "ent").alias("e")).select("doc_id", "e.ent", "e.n")
    members = ws.write(by_id, "members")
    live = members.where("n > 0 and doc_id is not null")
    reps = ws.write(live.groupBy("ent").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n")), "reps")

    lists = held.where("docs is null").groupBy("ent").agg(F.sort_array(F.collect_list(F.struct("df", "tok"))).alias("ts"))
    n_hot = meta.where("n > 0").groupBy("ent").agg(F.first("n_hot").alias("n_hot"))
    prefix = F.col("n") - F.ceil(F.col("n") * share / 100) + 1
    alone = F.col("n") - F.col("n_hot") - F.size("ts")
    rare_keys = (
        lists.join(n_hot, "ent").join(reps, "ent")
        .withColumn("p", (prefix - alone).cast("int"))
        .where("p > 0")
        .select("ent", "n", F.explode(F.slice("ts", F.lit(1), F.col("p"))).alias("x"))
        .select("ent", "n", F.xxhash64("x.tok", F.lit(0)).alias("key"))
    )
    hot_sets = meta.where(F.size("tokens") > 0).dropDuplicates(["ent"])
    keys = ws.write(rare_keys.unionByName(_hot_keys(hot_sets, share)), "keys")
    ws.drop("held")
    heads = keys.groupBy("key").agg(F.min("ent").alias("b"), F.max("ent").alias("top")).where("b <> top")
    posts = ws.write(keys.join(heads.select("key", "b"), "key").select("key", "ent", "n", "b"), "posts")
    ws.drop("keys")
    near = ws.write(components(posts.select(F.col("ent").alias("a"), "b").distinct(), ws, "near"), "near")
    wanted = near.join(reps, F.col("id") == F.col("ent")).select(F.col("rep").alias("doc_id"), F.col("ent").alias("want"), F.col("component").alias("grp"), "n")
    parts_of = F.greatest(F.ceil(F.sum("n") / group_tokens), F.ceil(F.count("*") / group_rows))
    big = ws.write(wanted.groupBy("grp").agg(parts_of.alias("m")).where("m > 1").select("grp"), "big")
    wanted = ws.write(wanted.join(big.withColumn("big", F.lit(True)), "grp", "left").withColumn("big", F.col("big").isNotNull()), "wanted")
    ids = wanted.select("doc_id").distinct()
    texts = src.join(F.broadcast(ids) if wanted.count() <= 500_000 else ids, "doc_id", "left_semi")
    sets = texts.mapInArrow(tidy(_sets_kernel(width)), DOC).select(F.col("ent").alias("want"), "tokens")
    sets = sets.join(wanted.select("want", "grp", "n", "big"), "want").select(F.col("want").alias("ent"), "grp", "n", "big", "tokens")
    links = ws.write(_links_within(sets.where("not big"), ["grp"], share), "links")
    if not big.isEmpty():
        large = ws.write(sets.where("big").drop("big").dropDuplicates(["ent"]), "sets")
        links = links.unionByName(_large_group_links(posts.drop("b"), large, share, group_tokens, group_rows, rounds, ws))
    comp = ws.write(components(links, ws, "cc"), "comp")
    ents = reps.join(comp.withColumnRenamed("id", "ent"), "ent", "left").select("ent", "rep", F.coalesce("component", "ent").alias("c"))
    ids = ents.join(ents.groupBy("c").agg(F.min("rep").alias("component_id")), "c").select("ent", "component_id")
    out = members.join(ids.withColumnRenamed("ent", "e2"), F.expr("ent = e2 and n > 0 and doc_id is not null"), "left")
    out = ws.write(out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id")), "out")
    ws.drop("posts", "reps", "members", "links", "comp", "near", "wanted", "big", "sets")
    return out


def _links_within(sets: DataFrame, by: list[str], share: int) -> DataFrame:
    """Edges (a, b) from each set to the first of its component among the sets of its group; one task holds a group."""

    def group_links(t: pa.Table) -> pa.Table:
        ents, first = np.unique(t.column("ent").to_numpy(), return_index=True)
        lists = t.column("tokens").combine_chunks()
        head = linked_heads([lists[i].values.to_numpy(zero_copy_only=False) for i in first.tolist()], share)
        m = head != np.arange(len(ents))
        return pa.table({"a": ents[m], "b": ents[head[m]]})

    return sets.select(*by, "ent", "tokens").groupBy(*by).applyInArrow(group_links, "a bigint, b bigint")


def _large_group_links(posts: DataFrame, sets: DataFrame, share: int, group_tokens: int, group_rows: int, rounds: int, ws: Workspace) -> DataFrame:
    """Links enough for the components of groups that one task does not take.

    Rounds of random slices of a group, one a task, fuse near copies, until that hardly helps. What
    is left are the sets outside of their group's largest component. While those of a group are
    few slices, they meet every slice of the group in a task, which costs each set some copies;
    otherwise the group is a chain of unlike sets, and they are verified by joins with every set
    of another component that shares a key with them. Both ways are exact.
    """
    links, before = None, None
    label = sets.select("ent", "grp", "n", F.col("ent").alias("c"))
    slices_of = F.greatest(F.ceil(F.sum("n") / group_tokens), F.ceil(F.count("*") / group_rows))
    for i in range(rounds):
        sizes = label.groupBy("grp", "c").agg(F.count("*").alias("k"), F.sum("n").alias("n"))
        tops = sizes.groupBy("grp").agg(F.max_by("c", F.struct("k", "c")).alias("top"), F.count("*").alias("parts"), F.sum("k").alias("all"), F.max("k").alias("most"), F.greatest(F.ceil(F.sum("n") / group_tokens), F.ceil(F.sum("k") / group_rows)).alias("m"))
        plan = ws.write(tops.where("parts > 1"), f"plan-{i}")
        outside = plan.agg(F.coalesce(F.sum(F.col("all") - F.col("most")), F.lit(0))).first()[0]
        if not outside or (before is not None and outside > 0.8 * before):
            break
        before = outside
        salted = label.join(plan.select("grp", "m"), "grp").select("ent", F.pmod(F.xxhash64("ent", F.lit(i)), F.col("m")).alias("slice"))
        new = ws.write(_links_within(sets.join(salted, "ent"), ["grp", "slice"], share), f"links-{i}")
        links = new if links is None else links.unionByName(new)
        comp = ws.write(components(links, ws, f"cc{i}"), f"comp-{i}")
        label = ws.write(sets.select("ent", "grp", "n").join(comp.withColumnRenamed("id", "ent"), "ent", "left").select("ent", "grp", "n", F.coalesce("component", "ent").alias("c")), f"label-{i}")
    sizes = label.groupBy("grp", "c").agg(F.count("*").alias("k"))
    tops = sizes.groupBy("grp").agg(F.max_by("c", F.struct("k", "c")).alias("top"))
    left = ws.write(label.join(tops, "grp").where("c <> top").drop("top"), "left")
    if left.isEmpty():
        return links
    chunks = left.groupBy("grp").agg(slices_of.alias("chunks"))
    grid = ws.write(label.groupBy("grp").agg(slices_of.alias("m")).join(chunks, "grp").withColumn("few", F.col("chunks") <= MOST_CHUNKS), "grid")

    def dealt(rows: DataFrame, own: str, by: str, others: str, over: str) -> DataFrame:
        mine = rows.select("ent", "grp").join(grid.where("few"), "grp")
        return mine.select("ent", F.pmod(F.xxhash64("ent", F.lit(-1)), F.col(by)).alias(own), F.explode(F.sequence(F.lit(0).cast("bigint"), F.col(over) - 1)).alias(others))

    cells = dealt(left, "chunk", "chunks", "slice", "m").unionByName(dealt(label, "slice", "m", "chunk", "chunks"))
    last = ws.write(_links_within(sets.join(cells, "ent"), ["grp", "chunk", "slice"], share), "links-grid")
    links = last if links is None else links.unionByName(last)
    chained = grid.where("not few").select("grp")
    if chained.isEmpty():
        return links
    mine = ws.write(posts.drop("n").join(left.join(chained, "grp").select("ent", "n", "c"), "ent").select("key", F.col("ent").alias("a"), F.col("n").alias("na"), F.col("c").alias("ca")), "left-posts")
    others = posts.drop("n").join(mine.select("key").distinct(), "key", "left_semi").join(label, "ent").select("key", F.col("ent").alias("b"), F.col("n").alias("nb"), F.col("c").alias("cb"))
    fits = F.least("na", "nb") * 100 >= F.greatest("na", "nb") * share
    pairs = mine.join(others, "key").where(fits & (F.col("ca") != F.col("cb"))).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    tokens = [sets.select(F.col("ent").alias(c), F.col("tokens").alias(f"t{c}")) for c in "ab"]
    inter = F.size(F.array_intersect("ta", "tb"))
    last = pairs.join(tokens[0], "a").join(tokens[1], "b").where(inter * 100 >= (F.size("ta") + F.size("tb") - inter) * share).select("a", "b")
    return links.unionByName(ws.write(last, "links-last"))


ORACLE = r"""
with recursive w as (
  select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws from documents
), s as (
  select distinct doc_id, unnest(case when len(ws) >= 5 then list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' ')) when len(ws) > 0 then [array_to_string(ws, ' ')] else [] end) as t from w
), n as (select doc_id, count(*) as n from s group by doc_id),
i as (select a.doc_id as a, b.doc_id as b, count(*) as k from s a join s b on a.t = b.t and a.doc_id <> b.doc_id group by all),
l as (select i.a, i.b from i join n x on x.doc_id = i.a join n y on y.doc_id = i.b where 100 * k >= 80 * (x.n + y.n - k)),
reach(a, b) as (select doc_id, doc_id from n union select reach.a, l.b from reach join l on reach.b = l.a)
select w.doc_id, coalesce(n.n, 0)::bigint as n_shingles, coalesce(c.c, w.doc_id) as component_id
from w left join n using (doc_id) left join (select a, min(b) as c from reach group by a) c on c.a = w.doc_id
"""
