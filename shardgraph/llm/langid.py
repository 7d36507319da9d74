"""Language identification: multinomial naive Bayes over hashed character n-grams."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import slices, tidy

BUCKETS = 1 << 15
ORDERS = (1, 2, 3)
SLICE_CHARS = 400_000


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)


def gram_buckets(codes: np.ndarray) -> list[np.ndarray]:
    """Bucket of every n-gram that starts at each position, one array per order."""
    out = []
    with np.errstate(over="ignore"):
        h = np.zeros(len(codes), np.uint64)
        for n in ORDERS:
            m = len(codes) - n + 1
            if m <= 0:
                out.append(np.empty(0, np.int64))
                continue
            h = h[:m] * np.uint64(0x100000001B3) + codes[n - 1 :] + np.uint64(n)
            out.append((((h * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - 15))).astype(np.int64))
    return out


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[str | None]]]:
    for b in slices(batches):
        yield b, b.column("text").to_pylist()


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sums: dict[str, np.ndarray] = {}
    rows: dict[str, int] = {}
    for b, texts in _texts(batches):
        for text, lang in zip(texts, b.column("lang").to_pylist(), strict=True):
            got = sums.setdefault(lang, np.zeros(BUCKETS, np.int64))
            rows[lang] = rows.get(lang, 0) + 1
            for g in gram_buckets(_codes(text)):
                got += np.bincount(g, minlength=BUCKETS)
    for lang, c in sums.items():
        at = np.flatnonzero(c)
        yield pa.RecordBatch.from_pydict({"lang": pa.array([lang] * (len(at) + 1), pa.string()), "bucket": pa.array(np.r_[at, BUCKETS]), "n": pa.array(np.r_[c[at], rows[lang]])})


class Model:
    """Class names, the matrix of log-probabilities, buckets by classes, and the log-priors; its size is fixed by the first two."""

    def __init__(self, langs: list[str], logp: np.ndarray, prior: np.ndarray):
        self.langs, self.logp, self.prior = langs, logp, prior

    @classmethod
    def of_counts(cls, langs: list[str], counts: np.ndarray, rows: np.ndarray) -> Model:
        """From n-gram counts, half a count added to each, and the classes' numbers of rows."""
        c = counts + 0.5
        return cls(langs, np.log(c / c.sum(axis=0, keepdims=True)), np.log(np.maximum(rows, 1) / max(np.sum(rows), 1)))

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """Most probable class of each whole text, and its share of the posterior.

        Evidence is the mean over n-grams times their number up to 200, so that long texts do not
        saturate; ties go to the first name.
        """
        has = np.array([t is not None and any(map(str.isalpha, t)) for t in texts], bool)
        total, grams = np.zeros((len(texts), len(self.langs))), np.zeros(len(texts))
        todo = np.flatnonzero(has).tolist()
        while todo:
            take, size = [], 0
            while todo and (not take or size + len(texts[todo[0]]) <= SLICE_CHARS):
                take.append(todo.pop(0))
                size += len(texts[take[-1]])
            self._add(take, [texts[i] for i in take], total, grams)
        score, pick = np.zeros(len(texts)), np.zeros(len(texts), int)
        if len(self.langs) and has.any():
            z = total[has] / grams[has, None] * np.minimum(grams[has, None], 200) + self.prior
            z = np.exp(z - z.max(axis=1, keepdims=True))
            pick[has], score[has] = z.argmax(axis=1), z.max(axis=1) / z.sum(axis=1)
        names = [self.langs[p] if h and self.langs else "und" for h, p in zip(has.tolist(), pick.tolist(), strict=True)]
        return names, score

    def _add(self, rows: list[int], texts: list[str], total: np.ndarray, grams: np.ndarray) -> None:
        if len(rows) == 1 and len(texts[0]) > BUCKETS:
            for g in gram_buckets(_codes(texts[0])):
                total[rows[0]] += np.bincount(g, minlength=BUCKETS) @ self.logp
                grams[rows[0]] += len(g)
            return
        codes = [_codes(t) for t in texts]
        size = np.array([len(c) for c in codes])
        flat, start = np.concatenate(codes), np.r_[0, np.cumsum(size)[:-1]]
        for n, g in zip(ORDERS, gram_buckets(flat), strict=True):
            m = size >= n
            if not m.any():
                continue
            own = np.repeat(size, size) - (np.arange(len(flat)) - np.repeat(start, size)) >= n  # grams that stay in their text
            own = own[: len(g)]
            g = g[own]
            per = np.maximum(size - n + 1, 0)
            at = np.r_[0, np.cumsum(per)[:-1]][m]
            for k in range(len(self.langs)):
                total[np.array(rows)[m], k] += np.add.reduceat(self.logp[:, k][g], at)
            grams[np.array(rows)[m]] += per[m]


def held_out(doc_id):
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def train(docs: DataFrame, max_rows: int = 20_000) -> Model:
    """Counts over a hash sample of at most about ``max_rows`` labelled training documents, whole texts."""
    rows = docs.where(~held_out(F.col("doc_id")) & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "lang", "text")
    n = rows.count()
    if n > max_rows:
        rows = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int((1 << 30) * max_rows / n))
    got = rows.select("lang", "text").mapInArrow(tidy(_count), "lang string, bucket bigint, n bigint").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(got["lang"].unique())
    counts = np.zeros((BUCKETS + 1, len(langs)))  # the last row counts rows
    counts[got["bucket"], [langs.index(x) for x in got["lang"]]] = got["n"]
    return Model.of_counts(langs, counts[:BUCKETS], counts[BUCKETS])


def identify(docs: DataFrame, max_rows: int = 20_000) -> DataFrame:
    """Rows (doc_id, held_out, lang_pred, score).

    The model is learned from text and lang of rows outside the held-out fifth and broadcast (2 MB
    for eight languages). Scoring is one pass in batches; it sees the text alone. A null text or
    one without a letter is ``und`` with score 0, and so is everything if no row has a lang. Null
    ids count as the empty string and are held out or not by its checksum; repeated rows each get
    their prediction; other columns are ignored.
    """
    src = docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    trained = train(src, max_rows)
    shared = docs.sparkSession.sparkContext.broadcast((trained.langs, trained.logp, trained.prior))  # plain data: executors need no copy of the package

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = Model(*shared.value)
        for b, texts in _texts(batches):
            names, score = model.predict(texts)
            yield pa.RecordBatch.from_pydict({"doc_id": b.column("doc_id"), "held_out": b.column("held_out"), "lang_pred": pa.array(names, pa.string()), "score": pa.array(score)})

    kind = src.schema["doc_id"].dataType.simpleString()
    return src.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(tidy(run), f"doc_id {kind}, held_out boolean, lang_pred string, score double")
