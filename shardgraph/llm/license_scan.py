"""License scans: exact phrases, and short notices with bounded edits."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import WORD_BYTES, slices, tidy

#: Phrases and labels of the contract.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Short notices as normalised words, with the label each stands for.
NOTICES = {
    "licensed under the apache license version 2": "apache-2.0",
    "released under the mit license": "mit",
    "permission is hereby granted free of charge to any person obtaining a copy": "mit",
    "licensed under the gnu general public license version": "gpl",
    "gnu lesser general public license": "lgpl",
    "gnu affero general public license": "agpl",
    "redistribution and use in source and binary forms": "bsd",
    "mozilla public license version 2": "mpl-2.0",
    "licensed under cc by": "cc-by",
    "licensed under cc by nc": "cc-by-nc",
    "creative commons attribution sharealike": "cc-by-sa",
    "this is free and unencumbered software released into the public domain": "unlicense",
    "all rights reserved": "reserved",
}
EDIT_SHARE = 0.12


def _bigrams(text: str) -> set[str]:
    return {text[i : i + 2] for i in range(len(text) - 1)}


@lru_cache(maxsize=8)
def _plans(notices: tuple[tuple[str, str], ...]):
    """One automaton over the pieces of all notices, and per notice its label, edits, bigrams and pattern."""
    plans, pieces = [], {}
    for n, (text, label) in enumerate(notices):
        k = max(1, int(len(text) * EDIT_SHARE))
        cut = [round(i * len(text) / (k + 1)) for i in range(k + 2)]
        for a, b in zip(cut, cut[1:], strict=False):
            pieces.setdefault(text[a:b], []).append((n, b))
        plans.append((text, label, k, _bigrams(text), regex.compile(f"(?:{regex.escape(text)}){{e<={k}}}", regex.BESTMATCH)))
    find = ahocorasick.Automaton()
    for piece, uses in pieces.items():
        find.add_word(piece, uses)
    find.make_automaton()
    return plans, find


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(WORD_BYTES).split()


def phrase_places(flat: bytes, phrase: str) -> list[int]:
    """Start words of a phrase in ``flat``: the words with one blank before each and one at the end."""
    needle, out, at = f" {phrase} ".encode(), [], flat.find(f" {phrase} ".encode())
    word = last = 0
    while at >= 0:
        word, last = word + flat.count(b" ", last, at), at
        out.append(word)
        at = flat.find(needle, at + 1)
    return out


def notice_spans(flat: bytes, notices: dict[str, str] = NOTICES) -> list[tuple[str, str, int, int, int]]:
    """Matches (notice, label, start, end, edits) with at most ``EDIT_SHARE`` edits a character.

    A match with k edits holds one of k + 1 pieces unchanged, so the pieces' exact places give all
    windows that can hold one; the regex engine verifies the edits there, after a bound by bigrams. Offsets are bytes.
    """
    plans, find = _plans(tuple(notices.items()))
    text = flat.decode("latin-1")
    windows: dict[int, list[list[int]]] = {}
    for end, uses in find.iter(text):
        for n, upto in uses:
            size, k = len(plans[n][0]), plans[n][2]
            a = max(0, end + 1 - upto - k)
            got = windows.setdefault(n, [])
            if got and a <= got[-1][1]:
                got[-1][0], got[-1][1] = min(got[-1][0], a), max(got[-1][1], a + size + 2 * k)
            else:
                got.append([a, a + size + 2 * k])
    out = []
    for n, spans in sorted(windows.items()):
        notice, label, k, bigrams, pattern = plans[n]
        while spans:
            a, b = spans.pop()
            part = text[a:b]
            # an edit takes two bigrams at most, so a part that lacks more holds no match
            m = pattern.search(part) if len(bigrams - _bigrams(part)) <= 2 * k else None
            if m:
                # the best match comes first; copies with more edits stand on both sides of it
                out.append((notice, label, a + m.start(), a + m.end(), sum(m.fuzzy_counts)))
                spans += [[a, a + m.start()], [a + m.end(), b]]
    return sorted(out)


def scan_text(text: str | None, notices: dict[str, str] = NOTICES) -> tuple:
    words = words_of(text)
    flat = b" " + b" ".join(words) + b" "
    places = {p: phrase_places(flat, p) for p in PHRASES}
    starts = [x for xs in places.values() for x in xs]
    base = sorted({PHRASES[p] for p, xs in places.items() if xs})
    spans = notice_spans(flat, notices) if words else []
    labels = sorted({*base, *(s[1] for s in spans)})
    score = max([1.0 * bool(starts), *(1 - s[4] / len(s[0]) for s in spans)])
    return len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(base), ",".join(labels), score, spans


def scan(docs: DataFrame, notices: dict[str, str] = NOTICES) -> DataFrame:
    """Rows (doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans), one pass.

    ``spans`` are the fuzzy matches as (notice, label, start, end, edits) over the normalised
    bytes. A null or empty text has no words, no labels (empty strings) and score 0. Null ids and
    repeated rows pass through; other columns are ignored. Memory is a few copies of one text.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            got = [scan_text(t, notices) for t in b.column("text").to_pylist()]
            cols = list(zip(*got, strict=True)) if got else [[]] * 8
            spans = [[dict(zip(("notice", "label", "start", "end", "edits"), s, strict=True)) for s in ss] for ss in cols[7]]
            yield pa.RecordBatch.from_pydict(
                {
                    "doc_id": b.column("doc_id"),
                    **{k: pa.array(cols[i], pa.int64()) for i, k in enumerate(("n_words", "n_base", "first_word", "last_word"))},
                    "base_labels": pa.array(cols[4], pa.string()),
                    "labels": pa.array(cols[5], pa.string()),
                    "score": pa.array(cols[6], pa.float64()),
                    "spans": pa.array(spans, pa.list_(pa.struct([("notice", pa.string()), ("label", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("edits", pa.int64())]))),
                }
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(
        tidy(run),
        f"doc_id {kind}, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string, score double, "
        "spans array<struct<notice:string,label:string,start:bigint,end:bigint,edits:bigint>>",
    )
