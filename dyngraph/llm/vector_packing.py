"""Vector best-fit packing of token sequences.

Each piece of a document needs tokens, one document place and an attention cost (its length squared); each bin
has a capacity for all three. Pieces of one length have the same needs, so the choice of bins is made on the
histogram of lengths (at most max_tokens rows, whatever the input), largest first, for whole ranges of equal bins
at a time; every piece then finds its bin by its rank among the pieces of its length.
"""

from __future__ import annotations

import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dyngraph.llm.common import ranked, written

MAX_TOKENS = 4096
MAX_DOCS = 4096
CACHE_WORDS = 1_000_000
_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
_state: dict = {}


def _encoder(path: str):
    """Words (bytes between ASCII white space, which the vocabulary drops) to their ids as little-endian bytes."""
    if _state.get("path") != path:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        _state.update(path=path, model=Tokenizer.from_file(path), words={})
    return _state["model"], _state["words"]


def _plain(text: bytes) -> bytes:
    """A-Z in lower case, as the vocabulary's normaliser has it, so that fewer words differ; a special token's string stays as it is."""
    return text if b"<|" in text else text.lower()


def token_bytes(texts: list[str], path: str) -> list[bytes]:
    """The ids of each text, 4 bytes each; equal to encoding the whole text, as no token spans white space."""
    model, words = _encoder(path)
    split = [_plain(t.encode("utf-8", "replace")).split() for t in texts]
    new = list(set().union(*split).difference(words))
    if len(words) + len(new) > CACHE_WORDS:
        words.clear()
        new = list(set().union(*split))
    many = getattr(model, "encode_batch_fast", model.encode_batch)
    for lo in range(0, len(new), 4096):
        part = new[lo : lo + 4096]
        for w, e in zip(part, many([w.decode() for w in part], add_special_tokens=False)):
            words[w] = array("I", e.ids).tobytes()
    out = [b"".join(map(words.__getitem__, ws)) for ws in split]
    if len(words) > CACHE_WORDS:
        words.clear()
    return out


def _cutter(path: str, end_id: int, size: int):
    end = np.array([end_id], "<u4").tobytes()

    def cut(batches):
        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                b = whole.slice(lo, 256)
                cols: list[list] = [[], [], [], [], []]
                texts = [t or "" for t in b.column("text").to_pylist()]
                for doc, ids in zip(b.column("doc_id").to_pylist(), token_bytes(texts, path)):
                    ids += end
                    for piece, at in enumerate(range(0, len(ids), 4 * size)):
                        part = ids[at : at + 4 * size]
                        for c, v in zip(cols, (doc, piece, at // 4, len(part) // 4, zlib.crc32(part))):
                            c.append(v)
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return cut


def pieces(docs: DataFrame, path: str, end_id: int = 1, size: int = MAX_TOKENS) -> DataFrame:
    """Every document's ids with end_id behind them (null text: only end_id), cut after each `size` ids."""
    return docs.select("doc_id", "text").mapInArrow(_cutter(path, end_id, size), _PIECES)


def choose(histogram: dict[int, int], max_tokens: int = MAX_TOKENS, max_docs: int = MAX_DOCS, max_attention: int | None = None, rule: str = "norm", weights=(1.0, 0.3, 0.3)) -> list[tuple]:
    """Bins for a histogram length -> pieces: rows (length, first rank, last rank + 1, first bin, pieces a bin, offset).

    rule "norm" takes the bins whose weighted residual, in shares of the capacities, has the least norm once the
    piece is in; a bin just filled is then the closest again, so it takes as many equal pieces as fit. Rule "dot"
    takes the largest weighted dot product of need and residual, and each of a range of equal bins takes one.
    All three capacities hold under either rule.
    """
    cap = np.array([max_tokens, max_docs, max_attention or max_tokens**2], float)
    wts = np.array(weights, float)
    residual = np.zeros((1024, 3))
    count = np.zeros(1024, np.int64)
    first = np.zeros(1024, np.int64)
    used, bins, out = 0, 0, []

    def add(r, n, at):
        nonlocal used, residual, count, first
        if used == len(count):
            live = count[:used] > 0
            k = int(live.sum())
            residual[:k], count[:k], first[:k] = residual[:used][live], count[:used][live], first[:used][live]
            count[k:] = 0
            used = k
            if k > len(count) // 2:
                residual, count, first = (np.concatenate([x, np.zeros_like(x)]) for x in (residual, count, first))
        residual[used], count[used], first[used] = r, n, at
        used += 1

    for length in sorted(histogram, reverse=True):
        need = np.array([length, 1, length**2], float)
        if (need > cap).any():
            raise ValueError(f"a piece of {length} tokens exceeds a capacity")
        left, rank = histogram[length], 0
        while left:
            fits = np.flatnonzero((count[:used] > 0) & (residual[:used] >= need).all(1))
            if len(fits):
                r = residual[fits]
                if rule == "norm":
                    g = fits[np.argmin((wts * ((r - need) / cap) ** 2).sum(1))]
                else:
                    g = fits[np.argmax((wts * (r / cap) * (need / cap)).sum(1))]
                space, open_bins, at = residual[g].copy(), int(count[g]), int(first[g])
            else:
                g, space, open_bins, at = None, cap.copy(), left, bins
            each = int((space // need).min()) if rule == "norm" else 1
            full = min(open_bins, left // each)
            take, n = (each, full) if full else (left, 1)
            out.append((length, rank, rank + take * n, at, take, int(max_tokens - space[0])))
            if g is None:
                bins += n
            else:
                count[g] -= n
                first[g] += n
            rest = space - take * need
            if (rest >= 1).all():
                add(rest, n, at)
            left, rank = left - take * n, rank + take * n
    return out


def pack(cut: DataFrame, **limits) -> DataFrame:
    """Pieces (written, as they are read three times) with sequence_id and offset."""
    histogram = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    rows = choose(histogram, **limits)
    schema = "length long, _from long, _to long, _bin long, _each long, _offset long"
    plan = F.broadcast(cut.sparkSession.createDataFrame(rows or [], schema))  # rows follow the number of lengths, not of pieces
    at = F.col("rank") - F.col("_from")
    placed = ranked(cut, ["length"], ["doc_id", "piece", "ids_crc32"]).join(plan, "length").where("rank >= _from and rank < _to")
    return placed.select(*cut.columns, (F.col("_bin") + F.floor(at / F.col("_each"))).cast("long").alias("sequence_id"), (F.col("_offset") + at % F.col("_each") * F.col("length")).cast("long").alias("offset"))


def pack_documents(docs: DataFrame, path: str | None = None, piece_tokens: int | None = None, **limits) -> DataFrame:
    """All documents as pieces with their places; an empty table gives an empty result.

    Documents are cut after piece_tokens ids (max_tokens, if none are given), so that with shorter pieces an attention
    capacity below that of one full sequence can be kept.
    """
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    return pack(written(pieces(docs, path, size=piece_tokens or limits.get("max_tokens", MAX_TOKENS)), "pieces"), **limits)
