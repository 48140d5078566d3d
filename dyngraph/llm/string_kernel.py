"""Language identification with a blended-spectrum string kernel.

Two texts are compared by the character n-grams (n = 1..3, letters in lower case, words apart) that occur in both,
by presence, over the geometric mean of how many each has. Nyström landmarks give the feature map, one-versus-rest
kernel ridge regression the weights; scoring is two matrix products a batch.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dyngraph.llm.quality_ftrl import held_out

SPACE = 1 << 16
LONGEST = 3
MAX_TRAIN = 4096
LANDMARKS = 128
RIDGE = 1e-2
UNKNOWN = "und"
_letters: list[np.ndarray] = []


def _folding() -> np.ndarray:
    """For each code unit: its lower-case letter, or 0 where it is no letter."""
    if not _letters:
        t = np.zeros(1 << 16, np.uint32)
        for i in range(1 << 16):
            c = chr(i)
            if c.isalpha():
                t[i] = ord(c.lower()[0])
        _letters.append(t)
    return _letters[0]


def presence(text: str | None) -> np.ndarray | None:
    """Flags of the hashed n-grams that occur in the whole text; None where no letter does."""
    fold = _folding()
    u = np.frombuffer((text or "").encode("utf-32-le", "replace"), np.uint32)
    c = fold[np.minimum(u, 0xFFFF)]
    if len(u) and u.max() >= 1 << 16:  # beyond the table: letters only
        for x in np.unique(u[u >= 1 << 16]).tolist():
            c = np.where(u == x, x if chr(x).isalpha() else 0, c)
    c = c[(c != 0) | np.append(True, c[:-1] != 0)] if len(c) else c
    if not c.any():
        return None
    c = np.concatenate([[0], c, [0]]).astype(np.uint64)
    flags = np.zeros(SPACE, np.uint8)
    h, m = c, np.uint64(0x9E3779B97F4A7C15)
    with np.errstate(over="ignore"):
        for n in range(1, LONGEST + 1):
            flags[(((h + np.uint64(n)) * m) >> np.uint64(48)).astype(np.int64)] = 1
            h = h[:-1] * np.uint64(0x1F0F0F0F) + c[n:] + np.uint64(1)
    return flags


def _fitter(landmarks: int, ridge: float):
    def fit(batches):
        rows, names, keys = [], [], []
        for b in batches:
            for doc, text, lang in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text", "lang"))):
                flags = presence(text)
                if flags is not None:
                    rows.append(np.packbits(flags))
                    names.append(lang)
                    keys.append(zlib.crc32(str(doc).encode()))
        if not rows:
            return
        order = np.argsort(keys, kind="stable")
        names = np.array(names, object)[order]
        x = np.array(rows)[order]
        langs = sorted(set(names))
        places = {g: np.flatnonzero(names == g) for g in langs}
        marks = np.concatenate([places[g][: max(1, landmarks // len(langs))] for g in langs])
        dense = np.unpackbits(x[marks], axis=1).astype(np.float32)
        cols = np.flatnonzero(dense.any(0))
        norm_l = np.sqrt(dense.sum(1))
        base = dense[:, cols] / norm_l[:, None]
        k_ll = (base @ base.T).astype(float)
        val, vec = np.linalg.eigh(k_ll)
        root = vec / np.sqrt(np.maximum(val, 1e-8))  # Nyström map
        phi = []
        for lo in range(0, len(x), 256):
            part = np.unpackbits(x[lo : lo + 256], axis=1).astype(np.float32)
            phi.append((part[:, cols] @ base.T) / np.sqrt(part.sum(1))[:, None] @ root)
        phi = np.concatenate(phi)
        phi = np.hstack([phi, np.ones((len(phi), 1))])
        y = np.where(names[:, None] == np.array(langs, object), 1.0, -1.0)
        # every language weighs the same
        wt = np.array([1 / len(places[g]) for g in names])[:, None] * len(names) / len(langs)
        w = np.linalg.solve(phi.T @ (wt * phi) + ridge * np.eye(phi.shape[1]), phi.T @ (wt * y))
        yield pa.RecordBatch.from_pydict({"langs": ["\n".join(langs)], "cols": [cols.astype("<i4").tobytes()], "base": [base.astype("<f4").tobytes()], "weights": [np.vstack([root @ w[:-1], w[-1:]]).astype("<f4").tobytes()]})

    return fit


def fit(labelled: DataFrame, max_train: int = MAX_TRAIN, landmarks: int = LANDMARKS, ridge: float = RIDGE) -> dict | None:
    """Model from (doc_id, text, lang). About max_train rows are learnt from, an equal number of each language where
    there are enough, those with the smallest hash of doc_id."""
    sizes = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        return None
    limit = F.lit(0)
    for lang, n in sizes.items():
        share = min(1.0, max_train / len(sizes) / n)
        limit = F.when(F.col("lang") == lang, int(share * (1 << 30))).otherwise(limit)
    kept = labelled.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < limit)
    row = kept.repartition(1).mapInArrow(_fitter(landmarks, ridge), "langs string, cols binary, base binary, weights binary").first()
    if row is None:
        return None
    langs, cols = row["langs"].split("\n"), np.frombuffer(row["cols"], "<i4")
    return {"langs": langs, "cols": cols, "base": np.frombuffer(row["base"], "<f4").reshape(-1, len(cols)), "weights": np.frombuffer(row["weights"], "<f4").reshape(-1, len(langs))}


def _scorer(shipped, size: int = 128):
    def score(batches):
        m = shipped.value
        for b in batches:
            docs, texts = b.column("doc_id"), b.column("text").to_pylist()
            names: list = [UNKNOWN] * len(texts)
            scores = np.zeros(len(texts))
            for lo in range(0, len(texts) if m else 0, size):
                rows, at, total = [], [], []
                for i, t in enumerate(texts[lo : lo + size], lo):
                    flags = presence(t)
                    if flags is not None:
                        rows.append(flags[m["cols"]])
                        at.append(i)
                        total.append(int(flags.sum()))
                if not rows:
                    continue
                k = (np.array(rows, np.float32) @ m["base"].T) / np.sqrt(np.array(total, np.float32))[:, None]
                out = k @ m["weights"][:-1] + m["weights"][-1]
                e = np.exp(3 * (out - out.max(1, keepdims=True)))
                for i, g, s in zip(at, out.argmax(1), e.max(1) / e.sum(1)):
                    names[i], scores[i] = m["langs"][g], s
            yield pa.RecordBatch.from_arrays([docs, pa.array(names, pa.string()), pa.array(scores)], names=["doc_id", "lang_pred", "score"])

    return score


def learn(docs: DataFrame, **fitting) -> dict | None:
    """The model from the rows outside the held-out fold (null text, lang or doc_id: not learnt from)."""
    known = docs.where(F.col("text").isNotNull() & F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(4, 2))
    return fit(known.select("doc_id", "text", "lang"), **fitting)


def identify(docs: DataFrame, model: dict | None) -> DataFrame:
    """doc_id, lang_pred, score (softmax of the regressions); "und" with score 0 for a null text, one without letters, or no model."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)  # at most landmarks x SPACE floats
    return docs.select("doc_id", "text").mapInArrow(_scorer(shipped), "doc_id long, lang_pred string, score double")


def predict(docs: DataFrame, **fitting) -> DataFrame:
    return identify(docs, learn(docs, **fitting)).select("doc_id", held_out(4, 2).alias("held_out"), "lang_pred", "score")
