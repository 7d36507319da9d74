"""Toxicity grades by cumulative-link ordinal regression over sparse features of words."""

from __future__ import annotations

from collections.abc import Iterator
from math import fsum

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import WORD_BYTES, Workspace, free_name, slices, tidy


#: Length of the character n-grams of a word, its ends marked.
GRAM = 5
#: Words whose sums a task remembers before it starts anew.
REMEMBERED = 100_000


def word_set(text: str | None) -> set[bytes]:
    return set((text or "").encode("utf-8", "surrogatepass").translate(WORD_BYTES).split())


def features_of(word: bytes) -> set[bytes]:
    """The word itself and its character n-grams, which inflected and joined forms share."""
    if word.isascii():
        b = b"^%b$" % word
        return {word, *[b[i : i + GRAM] for i in range(len(b) - GRAM + 1)]}
    w = "^" + word.decode("utf-8", "replace") + "$"
    return {word, *(w[i : i + GRAM].encode("utf-8", "replace") for i in range(len(w) - GRAM + 1))}


class WordSums(dict):
    """Word -> sum of the weights of its features; starts anew after ``REMEMBERED`` words."""

    def __init__(self, vocabulary: dict[bytes, int], weights: np.ndarray):
        super().__init__()
        self.known = {f: w for f, w in zip(vocabulary, weights[list(vocabulary.values())].tolist(), strict=True)}

    def __missing__(self, word: bytes) -> float:
        if len(self) >= REMEMBERED:
            self.clear()
        known = self.known
        got = self[word] = fsum([known[f] for f in features_of(word) if f in known])
        return got


class OrdinalModel:
    """P(grade <= j) = sigmoid(theta_j - w.x) over the grades seen; one weight vector, ordered thresholds."""

    def __init__(self, grades: list[int], vocabulary: dict[bytes, int], weights: np.ndarray, theta: np.ndarray):
        self.grades, self.vocabulary, self.weights, self.theta = grades, vocabulary, weights, theta
        self.sums: WordSums | None = None

    def probabilities(self, texts: list[str | None]) -> np.ndarray:
        if self.sums is None:
            self.sums = WordSums(self.vocabulary, self.weights)
        x = np.array([fsum(map(self.sums.__getitem__, word_set(t))) for t in texts])
        below = 1 / (1 + np.exp(np.clip(x[:, None] - self.theta[None, :], -60, 60)))
        return np.diff(np.c_[np.zeros(len(texts)), below, np.ones(len(texts))], axis=1)

    @classmethod
    def fit(cls, rows: list[list[int]], y: np.ndarray, vocabulary: dict[bytes, int], steps: int = 250, rate: float = 0.1, l2: float = 3e-4) -> OrdinalModel:
        """Full-batch Adam on the likelihood; thresholds stay ordered as a start and exponential gaps."""
        grades = sorted(set(y.tolist())) or [0]
        k, n = len(grades), len(rows)
        w, gaps = np.zeros(len(vocabulary)), np.zeros(max(k - 1, 0))
        if k == 1:
            return cls(grades, vocabulary, w, gaps)
        at = np.repeat(np.arange(n), [len(r) for r in rows])
        ix = np.concatenate([np.asarray(r, np.int64) for r in rows]) if n else np.empty(0, np.int64)  # a feature stands once per word that has it
        label = np.searchsorted(grades, y)
        share = np.clip(np.cumsum(np.bincount(label, minlength=k))[:-1] / n, 1e-3, 1 - 1e-3)
        theta0 = np.log(share / (1 - share))
        gaps[0], gaps[1:] = theta0[0], np.log(np.maximum(np.diff(theta0), 1e-2))
        params, m, v = np.r_[w, gaps], 0.0, 0.0
        sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -60, 60)))
        for t in range(1, steps + 1):
            w, gaps = params[: len(vocabulary)], params[len(vocabulary) :]
            theta = np.cumsum(np.r_[gaps[0], np.exp(gaps[1:])])
            x = np.bincount(at, w[ix], n)
            edge = np.r_[-np.inf, theta, np.inf]
            hi, lo = sig(edge[label + 1] - x), sig(edge[label] - x)
            p = np.maximum(hi - lo, 1e-12)
            dhi, dlo = hi * (1 - hi) / p, lo * (1 - lo) / p
            gx = (dhi - dlo) / n  # derivative of the loss by x
            gtheta = np.array([(dlo[label == j + 1].sum() - dhi[label == j].sum()) / n for j in range(k - 1)])
            ggap = np.cumsum(gtheta[::-1])[::-1].copy()
            ggap[1:] *= np.exp(gaps[1:])
            g = np.r_[np.bincount(ix, gx[at], len(vocabulary)) + l2 * w, ggap]
            m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
            params = params - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
        w, gaps = params[: len(vocabulary)], params[len(vocabulary) :]
        return cls(grades, vocabulary, w, np.cumsum(np.r_[gaps[0], np.exp(gaps[1:])]))


def _features(vocabulary: dict[bytes, int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            rows = [sorted(vocabulary[f] for w in word_set(t) for f in features_of(w) if f in vocabulary) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_pydict({"grade": b.column("grade"), "x": pa.array(rows, pa.list_(pa.int32()))})

    return run


def _words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in slices(batches):
        sets = [set().union(*map(features_of, word_set(t))) for t in b.column("text").to_pylist()]
        grade = np.repeat(b.column("grade").to_numpy(), [len(s) for s in sets])
        yield pa.RecordBatch.from_pydict({"grade": pa.array(grade, pa.int32()), "word": pa.array([w for s in sets for w in s], pa.binary())})


def train(docs: DataFrame, labels: DataFrame, max_rows: int = 8_000, max_features: int = 20_000, min_rows: int = 4, slack: float = -3.0) -> OrdinalModel:
    """Model of the labelled documents, from a hash sample of at most about ``max_rows`` of them.

    The label ``toxic`` is the grade, 0 and up; grades without a row are left out. Several labels of
    a document count as the highest.
    Features are the words and n-grams of at least ``min_rows`` sampled documents whose share of toxic ones is
    off by more than the number of features tested would give by chance (n times the divergence over
    the logarithm of that number plus ``slack``, which halves of the labelled rows of 10,000
    documents chose: -2 to -4 find the same toxic ones to a hundredth), the ``max_features`` strongest. What reaches the driver is
    bounded by both parameters.
    """
    marked = labels.where("toxic is not null and doc_id is not null").select("doc_id", F.col("toxic").cast("int").alias("grade")).groupBy("doc_id").agg(F.max("grade").alias("grade"))
    n = marked.count()
    if n > max_rows:
        marked = marked.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int((1 << 30) * max_rows / n))
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(marked), "doc_id").select("grade", "text")
    ws = Workspace(docs.sparkSession, "toxicity")
    rows = ws.write(rows, "rows")
    total, toxic = rows.agg(F.count("*"), F.count_if(F.col("grade") > 0)).first()
    p0 = min(max(toxic / max(total, 1), 1e-6), 1 - 1e-6)
    counts = rows.mapInArrow(tidy(_words), "grade int, word binary").groupBy("word").agg(F.count("*").alias("n"), F.count_if(F.col("grade") > 0).alias("pos")).where(F.col("n") >= min_rows)
    p = F.col("pos") / F.col("n")
    part = lambda x, y: F.when(x > 0, x * F.log(x / y)).otherwise(0.0)
    scored = ws.write(counts.select("word", (F.col("n") * (part(p, p0) + part(1 - p, 1 - p0))).alias("score")), "scored")
    chance = float(np.log(max(scored.count(), 1)) + slack)
    top = scored.where(F.col("score") >= chance).orderBy(F.col("score").desc(), "word").limit(max_features).collect()
    vocabulary = {bytes(r.word): i for i, r in enumerate(top)}
    got = rows.mapInArrow(tidy(_features(vocabulary)), "grade int, x array<int>").collect()
    ws.drop("rows", "scored")
    return OrdinalModel.fit([r.x for r in got], np.array([r.grade for r in got], int), vocabulary)


def severity(docs: DataFrame, model: OrdinalModel, text_col: str = "text", out: str = "_toxicity") -> DataFrame:
    """``docs`` with a struct column ``out`` of (severity, grade, p_toxic), one pass over whole texts.

    Expected severity is the grades' mean under the model; grade the most probable one, the lower
    of equals; p_toxic the chance of a grade over 0. A null or empty text has no features and gets
    the thresholds' own probabilities. All columns and rows stay, repeated or null ids too; where
    ``docs`` has a column ``out``, the new one has underscores added (``free_name``).
    """
    shared = docs.sparkSession.sparkContext.broadcast((model.grades, model.vocabulary, model.weights, model.theta))
    kinds = (("severity", pa.float64()), ("grade", pa.int32()), ("p_toxic", pa.float64()))

    def score(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        model = OrdinalModel(*shared.value)
        g = np.array(model.grades)
        for whole in arrays:
            batch = pa.RecordBatch.from_arrays([whole], names=["text"])
            p = np.concatenate([np.empty((0, len(g))), *(model.probabilities(t.column(0).to_pylist()) for t in slices(iter([batch])))])
            cols = (p @ g, g[p.argmax(axis=1)], p[:, g > 0].sum(axis=1))
            yield pa.StructArray.from_arrays([pa.array(c, kind) for c, (_, kind) in zip(cols, kinds, strict=True)], fields=[pa.field(*x) for x in kinds])

    @F.arrow_udf("severity double, grade int, p_toxic double")
    def grade(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        yield from tidy(score)(texts)

    return docs.withColumn(free_name(docs, out), grade(F.col(text_col).cast("string")))


def rejects(threshold: float = 0.5, out: str = "_toxicity"):
    return F.col(out)["p_toxic"] >= threshold
