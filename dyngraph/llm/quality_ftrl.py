"""Quality classifier: logistic regression on hashed word n-grams, trained by follow-the-regularised-leader.

A word gives two features bases: itself (lower case) and its shape (runs of upper, lower, digit, then the marks as
they are). The n-grams are word unigrams and bigrams, and shape unigrams to trigrams with a mark for a repeated word.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BITS = 20
MAX_TRAIN = 8192
EPOCHS = 3
CACHE_WORDS = 300_000
_runs = re.compile(r"([^\W\d_])+|\d+")
_words: dict[str, tuple[int, int]] = {}


def _shape(word: str) -> str:
    def kind(m):
        s = m[0]
        return "0" if s[0].isdigit() else "A" if len(s) > 1 and s.isupper() else "Aa" if s[0].isupper() else "a" if s.islower() else "aA"

    return _runs.sub(kind, word)[:12]


def _base(word: str) -> tuple[int, int]:
    got = _words.get(word)
    if got is None:
        if len(_words) >= CACHE_WORDS:
            _words.clear()
        got = _words[word] = (zlib.crc32(word.lower().encode("utf-8", "replace")), zlib.crc32(_shape(word).encode("utf-8", "replace"), 7))
    return got


def slots(text: str | None, bits: int = BITS) -> np.ndarray:
    """Hash slots of all n-grams of the whole text, repeats included."""
    words = (text or "").split()
    if not words:
        return np.zeros(0, np.int64)
    w, s = np.array([_base(x) for x in words], np.uint64).T
    m = np.uint64(0x9E3779B97F4A7C15)
    with np.errstate(over="ignore"):
        mix = lambda x, seed: ((x + np.uint64(seed)) * m) >> np.uint64(64 - bits)
        same = (w[1:] == w[:-1]).astype(np.uint64)
        parts = [mix(w, 1 << 33), mix(w[:-1] * m + w[1:], 2 << 33), mix(s, 3 << 33), mix((s[:-1] * m + s[1:]) * np.uint64(3) + same, 4 << 33), mix((s[:-2] * m + s[1:-1]) * m + s[2:], 5 << 33)]
    return np.concatenate(parts).astype(np.int64)


def features(text: str | None, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Sparse row: slots and square roots of their shares (unit length)."""
    at, n = np.unique(slots(text, bits), return_counts=True)
    return at, np.sqrt(n / max(n.sum(), 1))


def sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


class Ftrl:
    """Per-coordinate follow-the-regularised-leader state for the logistic loss; the last slot is the bias."""

    def __init__(self, size: int, alpha=0.5, beta=1.0, l1=0.02, l2=0.1):
        self.z, self.n = np.zeros(size + 1), np.zeros(size + 1)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, at):
        z, n = self.z[at], self.n[at]
        w = -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) > self.l1, w, 0.0)

    def learn(self, at, x, y):
        at, x = np.append(at, len(self.z) - 1), np.append(x, 1.0)
        w = self.weights(at)
        g = (sigmoid(w @ x) - y) * x
        step = (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha
        self.z[at] += g - step * w
        self.n[at] += g * g


def _trainer(bits: int, epochs: int):
    def train(batches):
        rows = []
        for b in batches:
            for doc, text, y in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text", "quality"))):
                at, x = features(text, bits)
                rows.append((doc, at.astype(np.int32), x.astype(np.float32), y))
        model = Ftrl(1 << bits)
        rows.sort(key=lambda r: zlib.crc32(str(r[0]).encode()))
        for _ in range(epochs):
            for _, at, x, y in rows:
                model.learn(at.astype(np.int64), x.astype(float), y)
        w = model.weights(np.arange(len(model.z))).astype("<f4")
        yield pa.RecordBatch.from_pydict({"n": pa.array([len(rows)], pa.int64()), "w": [w.tobytes()]})

    return train


def fit(labelled: DataFrame, bits: int = BITS, max_train: int = MAX_TRAIN, epochs: int = EPOCHS) -> np.ndarray:
    """Weights from (doc_id, text, quality). At most about max_train rows are learnt from: those with the smallest hash of doc_id."""
    total = labelled.select("doc_id").count()
    share = min(1.0, max_train / max(total, 1))
    kept = labelled.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(share * (1 << 30)))
    row = kept.repartition(1).mapInArrow(_trainer(bits, epochs), "n long, w binary").first()
    return np.frombuffer(row["w"], "<f4") if row else np.zeros((1 << bits) + 1, "<f4")


def _scorer(weights, bits: int):
    def score(batches):
        w = weights.value.astype(np.float64)
        for b in batches:
            out = [float(sigmoid(w[at] @ x + w[-1])) for at, x in (features(t, bits) for t in b.column("text").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(out, pa.float64())], names=["doc_id", "score"])

    return score


def score(docs: DataFrame, weights: np.ndarray, bits: int = BITS) -> DataFrame:
    """doc_id and the probability of quality 1; a null or empty text has the score of the bias alone."""
    shipped = docs.sparkSession.sparkContext.broadcast(weights)  # 4 MB, fixed by bits
    return docs.select("doc_id", "text").mapInArrow(_scorer(shipped, bits), "doc_id long, score double")


def held_out(fold: int, remainder: int):
    """True for the documents of the fold that is never learnt from."""
    return F.coalesce(F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")) % fold == remainder, F.lit(False))


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, **fitting) -> DataFrame:
    """Learns from the labelled documents outside the held-out fold (a null label or doc_id is not learnt from) and scores all."""
    known = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(5, 0)).select("doc_id", F.col("quality").cast("double").alias("quality"))
    weights = fit(docs.select("doc_id", "text").join(known.dropDuplicates(["doc_id"]), "doc_id"), **fitting)
    return score(docs, weights).select("doc_id", held_out(5, 0).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
