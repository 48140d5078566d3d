"""Removal of repeated passages with collection suffix arrays, built column by column.

A passage is a string of `length` bytes. Its anchor is the position of the smallest hash among its 24-byte grams, a
function of its bytes alone, so equal passages have equal anchors; the passages of a text that share an anchor form
one span. Spans are dealt out by the hash of their anchor, so that each bucket is a collection of its own:

* equal spans: all their passages start first in the smallest document that has the span;
* an anchor with different spans in different documents: the spans' strings (bounded by 2 * length) form a collection
  whose Burrows-Wheeler transform is built by inserting one symbol of each string a round, from the last to the
  first. It gives the order of all suffixes; neighbours with a common prefix of `length` bytes are equal passages.

Nothing is sampled: every passage has exactly one anchor. Before anything moves, a task settles what it can: of the
spans that it sees more than once, only those of the smallest document leave it.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dyngraph.llm.common import written

LENGTH = 50
GRAM = 24
CHUNK = 1 << 18
FLUSH = 700_000
BUCKET_ANCHORS = 400_000
BUCKET_PIECES = 12_000
_M1, _M2, _M3 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB))
_span = np.dtype([("key", "<u8"), ("span", "<u8"), ("doc", "<i8"), ("text", "<i8"), ("at", "<i8"), ("n", "<i4")])
_run = np.dtype([("doc", "<i8"), ("text", "<i8"), ("at", "<i8"), ("n", "<i4")])


def _mix(x):
    x = (x ^ (x >> np.uint64(30))) * _M2
    x = (x ^ (x >> np.uint64(27))) * _M3
    return x ^ (x >> np.uint64(31))


def _sliding_min(v: np.ndarray, width: int) -> np.ndarray:
    step = 1
    while step * 2 <= width:
        v = np.minimum(v[:-step], v[step:])
        step *= 2
    return np.minimum(v[: len(v) - (width - step)], v[width - step :]) if width > step else v


def spans(data: bytes, length: int = LENGTH, gram: int = GRAM):
    """(key, span, start, passages) of the spans of one text, in order; they cover each passage once."""
    assert gram % 8 == 0 and 2 * gram >= length - gram and length >= gram
    parts = []
    width = length - gram + 1
    with np.errstate(over="ignore"):
        for lo in range(0, max(len(data) - length + 1, 0), CHUNK):
            x = np.frombuffer(data[lo : lo + CHUNK + length - 1], np.uint8).astype(np.uint64) + np.uint64(1)
            h, step = _mix(x * _M1), 1
            while step < 8:
                h = h[:-step] * _M1 + _mix(h[step:])
                step *= 2
            g = h[: len(x) - gram + 1].copy()
            for o in range(8, gram, 8):
                g = _mix(g) * _M1 + h[o : o + len(g)]
            g = _mix(g)
            where = np.uint64((1 << 21) - 1)
            low = _sliding_min((g & ~where) | np.arange(len(g), dtype=np.uint64), width)
            anchor = (low & where).astype(np.int64)
            first = np.flatnonzero(np.append(True, anchor[1:] != anchor[:-1]))
            n = np.diff(np.append(first, len(anchor)))
            end = first + n - 1 + length  # the span's bytes end here
            s = g[first]
            for o in (first + gram, end - 2 * gram, end - gram):
                s = _mix(s) * _M1 + g[o]
            parts.append((g[anchor[first]], _mix(s + n.astype(np.uint64)), first + lo, n))
    if not parts:
        return tuple(np.zeros(0, t) for t in (np.uint64, np.uint64, np.int64, np.int64))
    return tuple(map(np.concatenate, zip(*parts)))


#: Column, its bytes, and those that are sent; as planes of single bytes, which compress well.
_PLANES = (("key", 8, 5), ("span", 8, 8), ("doc", 8, 8), ("text", 8, 4), ("at", 8, 5), ("n", 4, 1))


def _pack(rows: np.ndarray) -> bytes:
    """Spans of one bucket. 40 bits of the key tell anchors of a bucket apart; two that fall together are compared like any others.

    Of the text's key 32 bits go along: they tell texts of one doc_id apart.
    """
    out = []
    for c, size, sent in _PLANES:
        x = np.ascontiguousarray(rows[c] >> np.uint64(24) if c == "key" else rows[c])
        out.append(x.view(np.uint8).reshape(-1, size)[:, :sent].T.tobytes())
    return b"".join(out)


def _unpack(blob: bytes) -> np.ndarray:
    n = len(blob) // sum(p[2] for p in _PLANES)
    rows, at = np.zeros(n, _span), 0
    for c, size, sent in _PLANES:
        x = np.zeros((n, size), np.uint8)
        x[:, :sent] = np.frombuffer(blob, np.uint8, n * sent, at).reshape(sent, n).T
        rows[c] = x.view(_span[c])[:, 0]
        at += n * sent
    return rows


def _least(rows: np.ndarray):
    """Rows sorted by (key, span, doc), and for each the smallest doc of its span."""
    rows = rows[np.lexsort((rows["doc"], rows["span"], rows["key"]))]
    new = np.append(True, (rows["key"][1:] != rows["key"][:-1]) | (rows["span"][1:] != rows["span"][:-1])) if len(rows) else np.zeros(0, bool)
    return rows, rows["doc"][np.maximum.accumulate(np.where(new, np.arange(len(rows)), 0))] if len(rows) else rows["doc"], new


def _joined(runs: np.ndarray) -> np.ndarray:
    """Runs of passages of one text that follow on each other, as one."""
    if not len(runs):
        return runs
    runs = runs[np.lexsort((runs["at"], runs["text"], runs["doc"]))]
    follows = (runs["doc"][1:] == runs["doc"][:-1]) & (runs["text"][1:] == runs["text"][:-1]) & (runs["at"][1:] == runs["at"][:-1] + runs["n"][:-1])
    start = np.flatnonzero(np.append(True, ~follows))
    total = np.add.reduceat(runs["n"], start)
    out = runs[start].copy()
    out["n"] = total
    return out


def _runs_of(rows: np.ndarray) -> np.ndarray:
    out = np.zeros(len(rows), _run)
    for c in _run.names:
        out[c] = rows[c]
    return out


def _mapper(length: int, buckets: int):
    def deal(batches):
        held, size = [], 0

        def flush():
            rows, least, _ = _least(np.concatenate(held))
            runs = _joined(_runs_of(rows[rows["doc"] > least]))
            rows = rows[rows["doc"] == least]
            for data, bucket, name in ((rows, rows["key"] % np.uint64(buckets), "spans"), (runs, _mix(runs["text"].view(np.uint64)) % np.uint64(buckets), "runs")):
                order = np.argsort(bucket, kind="stable")
                data, bucket = data[order], bucket[order]
                cuts = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])) if len(data) else np.zeros(0, int)
                ends = np.append(cuts[1:], len(data))
                for lo in range(0, len(cuts), 64):
                    ids = [int(bucket[c]) for c in cuts[lo : lo + 64]]
                    blobs = [_pack(data[a:b]) if name == "spans" else data[a:b].tobytes() for a, b in zip(cuts[lo : lo + 64], ends[lo : lo + 64])]
                    none = [None] * len(ids)
                    yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array(blobs if name == "spans" else none, pa.binary()), pa.array(blobs if name == "runs" else none, pa.binary())], names=["bucket", "spans", "runs"])

        for b in batches:
            for doc, key, text in zip(b.column("doc_id").to_pylist(), b.column("text_key").to_pylist(), b.column("text").to_pylist()):
                k, s, at, n = spans(text.encode("utf-8", "replace"), length)
                rows = np.zeros(len(k), _span)
                rows["key"], rows["span"], rows["doc"], rows["text"], rows["at"], rows["n"] = k, s, doc, key, at, n
                held.append(rows)
                size += len(rows)
                if size > FLUSH:
                    yield from flush()
                    held, size = [], 0
        if size:
            yield from flush()

    return deal


_FOUND = "ask boolean, key long, doc_id long, text_key long, at long, n int"


def _rows(ask: bool, key, rows) -> pa.Table:
    return pa.table({"ask": pa.array(np.full(len(rows), ask)), "key": pa.array(key), "doc_id": pa.array(rows["doc"].copy()), "text_key": pa.array(rows["text"].copy()), "at": pa.array(rows["at"].copy()), "n": pa.array(rows["n"].copy())})


def _settle(table: pa.Table) -> pa.Table:
    """One bucket: runs of settled passages, and the spans whose strings have to be compared (ask)."""
    blobs = lambda c: [x for x in table.column(c).to_pylist() if x]
    rows, least, _ = _least(np.concatenate([np.zeros(0, _span), *map(_unpack, blobs("spans"))]))
    runs = np.concatenate([np.frombuffer(b"".join(blobs("runs")), _run), _runs_of(rows[rows["doc"] > least])])
    rows = rows[rows["doc"] == least]
    ask = rows[:0]
    if len(rows):
        key = np.flatnonzero(np.append(True, rows["key"][1:] != rows["key"][:-1]))
        size = np.diff(np.append(key, len(rows)))
        low, high = np.minimum.reduceat(rows["doc"], key), np.maximum.reduceat(rows["doc"], key)
        ask = rows[np.repeat(low != high, size)]
    runs = _joined(runs)
    return pa.concat_tables([_rows(False, np.zeros(len(runs), np.int64), runs), _rows(True, ask["key"].view(np.int64) if not len(ask) else ask["key"].copy().view(np.int64), ask)])


def _cut(length: int, buckets: int):
    def cut(batches):
        for b in batches:
            cols: list[list] = [[] for _ in range(7)]
            for doc, key, text, asks in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text_key", "text", "asks"))):
                data = text.encode("utf-8", "replace")
                for a in asks:
                    for c, v in zip(cols, ((a["key"] & (1 << 62) - 1) % buckets, a["key"], doc, key, a["at"], a["n"], data[a["at"] : a["at"] + a["n"] + length - 1])):
                        c.append(v)
            kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=["bucket", "key", "doc_id", "text_key", "at", "n", "piece"])

    return cut


def suffix_order(pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Collection suffix array (piece, start) of all non-empty suffixes, by column-wise Burrows-Wheeler construction.

    Each round puts one more symbol of every piece in front of the suffix that the piece has reached. Where the new
    suffix goes follows from the transform alone: behind all suffixes with smaller first symbols, and behind as many
    with the same one as that symbol has occurred before. Equal suffixes are ordered by piece.
    """
    m = len(pieces)
    size = np.fromiter(map(len, pieces), np.int64, m)
    flat = np.frombuffer(b"".join(pieces), np.uint8)
    begin = np.concatenate([[0], np.cumsum(size)[:-1]]) if m else np.zeros(0, np.int64)
    # the empty suffixes come first, in the order of the pieces; a symbol is 1 + byte, 0 where the piece has ended
    piece, left = np.arange(m), size.copy()
    bwt = np.where(left > 0, flat[np.maximum(begin + left - 1, 0)].astype(np.int16) + 1, 0).astype(np.int16) if len(flat) else np.zeros(m, np.int16)
    fresh = np.arange(m)  # places of the suffixes of the last round
    for _ in range(int(size.max(initial=0))):
        order = np.argsort(bwt, kind="stable")  # symbols in order of occurrence: the last-to-first mapping
        order = order[np.searchsorted(bwt[order], 1) :]
        rank = np.full(len(bwt), -1)
        rank[order] = m + np.arange(len(order))
        grow = fresh[bwt[fresh] > 0]
        at = rank[grow]
        owner, start = piece[grow], left[grow] - 1
        total = len(bwt) + len(grow)
        old = np.ones(total, bool)
        old[at] = False
        merged = [np.zeros(total, a.dtype) for a in (bwt, piece, left)]
        for new, a in zip(merged, (bwt, piece, left)):
            new[old] = a
        merged[0][at] = np.where(start > 0, flat[np.maximum(begin[owner] + start - 1, 0)].astype(np.int16) + 1, 0)
        merged[1][at], merged[2][at] = owner, start
        bwt, piece, left = merged
        fresh = np.sort(at)
    return piece[m:], left[m:]


def equal_passages(pieces: list[bytes], length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(piece, start, class) of all passages; equal strings have equal classes."""
    piece, start = suffix_order(pieces)
    size = np.fromiter(map(len, pieces), np.int64, len(pieces))
    full = size[piece] - start >= length
    piece, start = piece[full], start[full]
    flat = np.frombuffer(b"".join(pieces), np.uint8)
    begin = np.concatenate([[0], np.cumsum(size)[:-1]])
    at = begin[piece] + start
    new = np.ones(len(at), bool)
    for lo in range(1, len(at), 20_000):  # neighbours' common prefixes
        a, b = at[lo - 1 : lo + 19_999][: len(at) - lo], at[lo : lo + 20_000]
        new[lo : lo + 20_000] = (flat[a[:, None] + np.arange(length)] != flat[b[:, None] + np.arange(length)]).any(1)
    return piece, start, np.cumsum(new) - 1


def _compare(length: int):
    def compare(table: pa.Table) -> pa.Table:
        cols = {c: table.column(c).to_numpy() for c in ("doc_id", "text_key", "at", "n")}
        raw = table.column("piece").to_pylist()
        # equal strings are one piece of the collection, that of the smallest document
        names: dict[bytes, int] = {}
        of = np.fromiter((names.setdefault(x, len(names)) for x in raw), np.int64, len(raw))
        owner = np.full(len(names), np.iinfo(np.int64).max)
        np.minimum.at(owner, of, cols["doc_id"])
        piece, start, cls = equal_passages(list(names), length)
        least = np.full(int(cls.max(initial=-1)) + 1, np.iinfo(np.int64).max)
        np.minimum.at(least, cls, owner[piece])
        order = np.lexsort((start, piece))
        piece, start, least = piece[order], start[order], least[cls[order]]
        first = np.searchsorted(piece, np.arange(len(names) + 1))
        size = (first[1:] - first[:-1])[of]
        row = np.repeat(np.arange(len(raw)), size)
        at = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size) + first[of][row]
        hit = least[at] < cols["doc_id"][row]
        row, at = row[hit], at[hit]
        out = np.zeros(len(row), _run)
        out["doc"], out["text"], out["at"], out["n"] = cols["doc_id"][row], cols["text_key"][row], cols["at"][row] + start[at], 1
        out = _joined(out)
        return _rows(False, np.zeros(len(out), np.int64), out)

    return compare


def _cleaner(length: int):
    def clean(batches):
        for b in batches:
            cols: list[list] = [[] for _ in range(6)]
            for doc, text, runs in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text", "runs"))):
                data = (text or "").encode("utf-8", "replace")
                cover = sorted((r["at"], r["at"] + r["n"] + length - 1) for r in runs or ())
                removed = []
                for lo, hi in cover:
                    if removed and lo <= removed[-1][1]:
                        removed[-1][1] = max(hi, removed[-1][1])
                    else:
                        removed.append([lo, hi])
                kept, at = [], 0
                for lo, hi in removed:
                    kept.append(data[at:lo])
                    at = hi
                rest = b"".join([*kept, data[at:]])
                for c, v in zip(cols, (doc, len(data), len(data) - len(rest), len(removed), hashlib.sha256(rest).hexdigest(), rest)):
                    c.append(v)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    return clean


def text_key(text: str):
    return F.xxhash64(text).bitwiseAND(F.lit(0xFFFFFFFF))


def removal_runs(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, text_key, at, n): runs of n passage starts that also start in a document with a smaller doc_id."""
    texts = docs.where(F.col("doc_id").isNotNull() & (F.octet_length("text") >= length)).select("doc_id", text_key("text").alias("text_key"), "text")
    total = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    anchors = 2 * total / (length - GRAM + 2)
    buckets = max(8, int(anchors / BUCKET_ANCHORS) + 1)
    dealt = texts.mapInArrow(_mapper(length, buckets), "bucket int, spans binary, runs binary")
    found = written(dealt.groupBy("bucket").applyInArrow(_settle, _FOUND), "passages")
    asked = found.where("ask")
    pieces_n = max(8, asked.count() // BUCKET_PIECES + 1)
    asks = asked.groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("key", "at", "n")).alias("asks"))
    strings = texts.join(asks, ["doc_id", "text_key"]).dropDuplicates(["doc_id", "text_key"]).mapInArrow(_cut(length, pieces_n), "bucket int, key long, doc_id long, text_key long, at long, n int, piece binary")
    compared = written(strings.groupBy("bucket").applyInArrow(_compare(length), _FOUND), "compared")
    return found.where("not ask").unionByName(compared).select("doc_id", "text_key", "at", "n")


def remove_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept (the bytes that stay) of each row.

    Null texts are empty. Rows that share a doc_id take nothing from each other; a row with a null doc_id neither
    loses bytes nor takes any.
    """
    runs = removal_runs(docs, length).groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("at", "n")).alias("runs"))
    rows = docs.select("doc_id", text_key("text").alias("text_key"), "text").join(runs, ["doc_id", "text_key"], "left")
    return rows.mapInArrow(_cleaner(length), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def report(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    return remove_repeats(docs, length).drop("kept")
