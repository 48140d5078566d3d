"""Exact top-k by inner product, term at a time over blocks.

Rows are packed into blocks of bounded size. Each block of candidates meets each block of the stated queries;
there, every term scatters query weight times posting weight into a dense array of integer scores, a partition
selects the best k of the block for each query, and a last merge keeps the best k of all blocks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.llm.common import written

SCALE = 256
CANDIDATES = 4096
QUERIES = 512
_BLOCK = "block string, n int, width int, ids binary, weights binary"


def quantised(vectors: DataFrame, scale: int = SCALE) -> DataFrame:
    """(vec_id, terms array<long>): floor(scale * x) of each component; rows with null vectors or components that are null or not finite go."""
    bad = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    kept = vectors.where(F.col("embedding").isNotNull() & F.col("vec_id").isNotNull()).where(~F.exists("embedding", bad))
    return kept.select("vec_id", F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("long")).alias("terms"))


def _packer(size: int):
    def pack(batches):
        import uuid

        ids, rows = [], []

        def block():
            width = max(map(len, rows), default=0)
            m = np.zeros((len(rows), width), "<i8")
            for i, r in enumerate(rows):
                m[i, : len(r)] = r
            order = np.argsort(np.array(ids, "<i8"), kind="stable")
            at = np.array(ids, "<i8")[order]
            return pa.RecordBatch.from_pydict({"block": [uuid.uuid4().hex], "n": pa.array([len(rows)], pa.int32()), "width": pa.array([width], pa.int32()), "ids": [at.tobytes()], "weights": [m[order].T.tobytes()]})

        for b in batches:
            ids += b.column("vec_id").to_pylist()
            rows += b.column("terms").to_pylist()
            while len(ids) >= size:
                rest = ids[size:], rows[size:]
                del ids[size:], rows[size:]
                yield block()
                ids, rows = rest
        if ids:
            yield block()

    return pack


def accumulate(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Scores (queries x candidates) of q (terms x queries) and c (terms x candidates), one term's postings after the other."""
    scores = np.zeros((q.shape[1], c.shape[1]), np.int64)
    for t in range(min(len(q), len(c))):
        rows, postings = np.flatnonzero(q[t]), np.flatnonzero(c[t])
        if len(rows) == q.shape[1] and len(postings) == c.shape[1]:
            scores += q[t][:, None] * c[t]
        elif len(rows) and len(postings):
            scores[np.ix_(rows, postings)] += q[t][rows][:, None] * c[t][postings]
    return scores


def best(scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Row and column numbers of the k best columns of each row; ties to the smaller column. Scores below the barrier are none."""
    none = np.iinfo(np.int64).min
    if scores.shape[1] > k:
        cut = np.partition(scores, scores.shape[1] - k, axis=1)[:, -k][:, None]
        over = scores > cut
        ties = (scores == cut) & ((np.cumsum(scores == cut, axis=1)) <= k - over.sum(1, keepdims=True))
        keep = (over | ties) & (scores != none)
    else:
        keep = scores != none
    return np.nonzero(keep)


def _match(k: int):
    def match(batches):
        for b in batches:
            cols = {n: b.column(n).to_pylist() for n in b.schema.names}
            for i in range(b.num_rows):
                qid, cid = np.frombuffer(cols["q_ids"][i], "<i8"), np.frombuffer(cols["ids"][i], "<i8")
                q = np.frombuffer(cols["q_weights"][i], "<i8").reshape(cols["q_width"][i], len(qid))
                c = np.frombuffer(cols["weights"][i], "<i8").reshape(cols["width"][i], len(cid))
                for lo in range(0, len(qid), 128):
                    part = qid[lo : lo + 128]
                    scores = accumulate(np.ascontiguousarray(q[:, lo : lo + 128]), c)
                    scores[part[:, None] == cid] = np.iinfo(np.int64).min
                    r, at = best(scores, k)
                    yield pa.RecordBatch.from_arrays([pa.array(part[r]), pa.array(cid[at]), pa.array(scores[r, at])], names=["query_id", "vec_id", "score"])

    return match


def top_k(vectors: DataFrame, every: int = 50, k: int = 5, candidates: int = CANDIDATES, queries: int = QUERIES) -> DataFrame:
    """The k best other rows of every row whose vec_id is divisible by `every`: query_id, rank, vec_id, score.

    A shorter vector has zeros for the terms it lacks. Rows with a query's own vec_id are not its candidates.
    A repeated candidate row is listed once for each time it occurs; a repeated query row is answered once.
    Only the names of the query blocks (one for `queries` stated queries) pass through the driver.
    """
    rows = quantised(vectors)
    asked = rows.where(F.pmod("vec_id", F.lit(every)) == 0).dropDuplicates(["vec_id"])
    q = written(asked.mapInArrow(_packer(queries), _BLOCK), "topk-queries")
    names = [r["block"] for r in q.select("block").collect()]
    c = rows.mapInArrow(_packer(candidates), _BLOCK)
    c = c.withColumn("q_block", F.explode(F.array([F.lit(n) for n in names]).cast("array<string>"))).drop("block", "n")
    q = q.select(F.col("block").alias("q_block"), F.col("width").alias("q_width"), F.col("ids").alias("q_ids"), F.col("weights").alias("q_weights"))
    found = c.join(q, "q_block").mapInArrow(_match(k), "query_id long, vec_id long, score long")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


ORACLE = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS t FROM embeddings
           WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
             CAST(list_sum(list_transform(range(1, len(q.t) + 1), lambda i: q.t[i] * c.t[i])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
