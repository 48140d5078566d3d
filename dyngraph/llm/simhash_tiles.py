"""SimHash near-duplicates by tiled exact comparison.

Distinct fingerprints are laid out in buckets by each of some masked values (two fingerprints within the radius agree
in one of them at least), sorted by population count and cut into tiles of bounded size. Tile pairs of a bucket whose
population counts lie further apart than the radius are never formed; the others are compared in full with
exclusive-or and bit counts, and hand on a spanning forest of the links they find.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.llm.common import block_masks, checked, components, masked, scope, written

SHINGLE = 3
RADIUS = 3
TILE = 1024
BROADCAST_ROWS = 200_000
_LANES = np.uint64(0x0101010101010101)


def _hashes(text: str | None, words: int) -> np.ndarray:
    """Hashes of the word shingles of the whole text, repeats included; of all words if there are fewer, none if there is no word."""
    parts = (text or "").encode("utf-8", "replace").lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    line = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = max(len(parts) - words + 1, 1)
    stops = ends[words - 1 :] if len(parts) >= words else ends[-1:]
    digest = xxhash.xxh64_intdigest
    return np.array([digest(line[a:b], 42) for a, b in zip(starts[:n].tolist(), stops.tolist())], np.uint64)


def _majority(h: np.ndarray) -> int:
    """The bits set in more than half of the hashes."""
    counts = np.zeros(64, np.int64)
    for lo in range(0, len(h), 255):  # bytes of a lane can't overflow
        part = h[lo : lo + 255]
        for j in range(8):
            lanes = ((part >> np.uint64(j)) & _LANES).sum(dtype=np.uint64)
            counts[j::8] += np.array([lanes], "<u8").view(np.uint8)
    bits = np.flatnonzero(2 * counts > len(h))
    return sum(1 << int(b) for b in bits)


def fingerprint(text: str | None, words: int = SHINGLE) -> int:
    """64-bit SimHash of the word shingles of the whole text, repeats included; zero where there is no word."""
    return _majority(_hashes(text, words))


def _printer(words: int):
    def prints(batches):
        for b in batches:
            out = np.array([fingerprint(t, words) for t in b.column("text").to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(out.view(np.int64))], names=["doc_id", "fp"])

    return prints


def fingerprints(docs: DataFrame, words: int = SHINGLE) -> DataFrame:
    """doc_id and the fingerprint's bits as a signed long."""
    return docs.select("doc_id", "text").mapInArrow(_printer(words), "doc_id long, fp long")


def forest(a: np.ndarray, b: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links (at most len(a) + len(b)) of the pairs of a and b at `radius` bits or fewer."""
    both = np.unique(np.concatenate([a, b]))
    root = np.arange(len(both))
    ia, ib = np.searchsorted(both, a), np.searchsorted(both, b)
    pa_, pb = [], []
    for lo in range(0, len(a), 256):
        i, j = np.nonzero(np.bitwise_count(a[lo : lo + 256, None] ^ b) <= radius)
        pa_.append(ia[i + lo])
        pb.append(ib[j])
    x, y = np.concatenate(pa_), np.concatenate(pb)
    while True:  # minimum label over links, with shortcuts
        low = root.copy()
        np.minimum.at(low, x, root[y])
        np.minimum.at(low, y, root[x])
        low = low[low]
        if (low == root).all():
            break
        root = low
    at = np.flatnonzero(root != np.arange(len(both)))
    return both[at], both[root[at]]


def _compare(radius: int):
    def compare(batches):
        for batch in batches:
            u, v = [], []
            for a, b in zip(batch.column("left").to_pylist(), batch.column("right").to_pylist()):
                x, y = forest(np.array(a, np.int64).view(np.uint64), np.array(b, np.int64).view(np.uint64), radius)
                u.append(x)
                v.append(y)
            cat = lambda parts: pa.array(np.concatenate(parts).view(np.int64) if parts else np.zeros(0, np.int64))
            yield pa.RecordBatch.from_arrays([cat(u), cat(v)], names=["u", "v"])

    return compare


def links(prints: DataFrame, radius: int = RADIUS, tile: int = TILE) -> DataFrame:
    """Links (u, v) that connect all fingerprints (column fp, distinct) as the full set of pairs within the radius does."""
    masks = block_masks(prints.count(), radius)
    rows = prints.select("fp", F.bit_count("fp").alias("ones"), F.explode(masked("fp", masks)).alias("k")).select("fp", "ones", "k.*")
    place = Window.partitionBy("band", "value").orderBy("ones", "fp")
    rows = rows.withColumn("tile", F.floor((F.row_number().over(place) - 1) / tile).cast("long"))
    tiles = rows.groupBy("band", "value", "tile").agg(F.collect_list("fp").alias("fps"), F.min("ones").alias("low"), F.max("ones").alias("high"))
    tiles = written(tiles.where("size(fps) > 1 or tile > 0"), "tiles")  # each holds `tile` fingerprints at most
    a = tiles.select("band", "value", "tile", F.col("fps").alias("left"), F.col("high").alias("top"))
    b = tiles.select("band", "value", F.col("tile").alias("other"), F.col("fps").alias("right"), F.col("low").alias("bottom"))
    own = a.select("left", F.col("left").alias("right"))
    more = a.join(b, ["band", "value"]).where(f"other > tile and bottom - top <= {radius}").select("left", "right")
    return own.unionByName(more).mapInArrow(_compare(radius), "u long, v long").distinct()


def near_duplicates(docs: DataFrame, words: int = SHINGLE, radius: int = RADIUS, tile: int = TILE) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable).

    Equal fingerprints are compared once. Null and wordless texts have fingerprint zero, which links like any
    other. Repeated rows keep their rows; a null doc_id is never a component's id unless all of its are null.
    """
    rows = written(fingerprints(docs, words), "fingerprints")
    least = written(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    roots = components(links(least.select("fp"), radius, tile), "simhash")
    joined = least.join(roots, least["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    ids = joined.groupBy("root").agg(F.min("least").alias("component_id"))
    named = joined.join(ids, "root").select("fp", "component_id")
    return rows.join(named, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


#: MinHash bands of similar_documents: 24 of five find 0.9999 of the pairs at Jaccard 0.8 (each minimum taken as independent).
BANDS, BAND_ROWS = 24, 5
_FACTORS = np.random.default_rng(5).integers(0, 1 << 63, BANDS * BAND_ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingles(text: str | None, words: int) -> np.ndarray:
    """Sorted distinct hashes of the word shingles; of the whole text if it has fewer words, none if it has no word."""
    return np.unique(_hashes(text, words))


def _bands(h: np.ndarray) -> list[int]:
    if not len(h):
        return []
    least = np.array([(h * f).min() for f in _FACTORS], np.uint64).reshape(BANDS, BAND_ROWS)
    return [xxhash.xxh64_intdigest(row.tobytes(), i) for i, row in enumerate(least)]


def _longs(rows: list) -> pa.Array:
    return pa.array([np.array(r, np.uint64).view(np.int64) for r in rows], pa.list_(pa.int64()))


def _same(parts: np.ndarray) -> bytes:
    return xxhash.xxh128_digest(parts.tobytes())


def _shingler(words: int):
    def shingle(batches):
        for b in batches:
            same, fp, size, keys = [], [], [], []
            for text in b.column("text").to_pylist():
                h = _hashes(text, words)
                parts = np.unique(h)
                same.append(_same(parts))
                fp.append(_majority(h))
                size.append(len(parts))
                keys.append(_bands(parts))
            columns = [b.column("doc_id"), pa.array(same, pa.binary()), pa.array(np.array(fp, np.uint64).view(np.int64)), pa.array(size, pa.int32()), _longs(keys)]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "same", "fp", "size", "keys"])

    return shingle


def _parted(words: int):
    def parted(batches):
        for b in batches:
            found = [(i, parts) for i, same, text in zip(*(b.column(c).to_pylist() for c in ("id", "same", "text"))) if _same(parts := shingles(text, words)) == same]
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in found], pa.int64()), _longs([p for _, p in found])], names=["id", "parts"])

    return parted


def printed_pairs(sets: DataFrame) -> DataFrame:
    """Pairs (u, v) of sets (id, fp) that the tiles link: each with the first set of its fingerprint, and the first sets of linked fingerprints."""
    first = written(sets.groupBy("fp").agg(F.min("id").alias("first")), "first-sets")
    side = lambda fp, i: first.select(F.col("fp").alias(fp), F.col("first").alias(i))
    found = links(first.select("fp")).withColumnsRenamed({"u": "a", "v": "b"}).join(side("a", "x"), "a").join(side("b", "y"), "b").select("x", "y")
    found = found.unionByName(sets.join(first, "fp").where("id <> first").select(F.col("id").alias("x"), F.col("first").alias("y")))
    return found.select(F.greatest("x", "y").alias("u"), F.least("x", "y").alias("v"))


def similar_documents(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """(doc_id, component_id) for each row: components of the documents whose sets of word shingles have that Jaccard similarity.

    Candidates are those whose SimHashes the tiles link at RADIUS bits, and those that share a MinHash band, as the
    SimHashes of most pairs at the similarity differ in more bits; the sets decide. Each bucket's rows are compared with one of them, another in each
    band, and then all pairs that these links leave in different groups. Texts without words are alike.

    Of a set only its size, its SimHash and its keys are stored; the sets of candidates are made from their texts once more.
    """
    with scope(docs.sparkSession) as inner:
        rows = written(docs.select("doc_id", "text").mapInArrow(_shingler(words), "doc_id long, same binary, fp long, size int, keys array<long>"), "shingles")
        sets = rows.groupBy("same").agg(F.min("doc_id").alias("least"), F.min("fp").alias("fp"), F.first("size").alias("size"), F.first("keys").alias("keys"))
        sets = written(sets.select(F.monotonically_increasing_id().alias("id"), "*"), "shingle-sets")
        spread = sets.select("id", "size", F.explode("keys").alias("key"))

        def verified(pairs: DataFrame, tag: str) -> DataFrame:
            with scope(docs.sparkSession) as checking:
                pairs = written(pairs.distinct(), "document-pairs")
                ids = pairs.select(F.col("u").alias("id")).union(pairs.select("v")).distinct()
                wanted = checked(written(sets.select("id", "same", "least").join(ids, "id"), "wanted-sets"), BROADCAST_ROWS)
                texts = docs.join(wanted, docs["doc_id"] == wanted["least"]).select("id", "same", "text")
                # rows may share a doc_id
                parts = written(texts.mapInArrow(_parted(words), "id long, parts array<long>").groupBy("id").agg(F.first("parts").alias("parts")), "wanted-parts")
                side = lambda i, a: parts.select(F.col("id").alias(i), F.col("parts").alias(a))
                both = pairs.join(side("u", "a"), "u").join(side("v", "b"), "v").withColumn("common", F.size(F.array_intersect("a", "b")))
                return checking.keep(both.where(F.col("common") + 1e-9 >= similarity * (F.size("a") + F.size("b") - F.col("common"))).select("u", "v"), tag)

        close = lambda a, b: F.least(a, b) + 1e-9 >= similarity * F.greatest(a, b)
        lead = spread.groupBy("key").agg(F.min_by(F.struct("id", "size"), F.xxhash64("id", "key")).alias("l"), F.count(F.lit(1)).alias("n")).where("n > 1")
        lead = lead.select("key", F.col("l.id").alias("v"), F.col("l.size").alias("other"))
        stars = spread.withColumnRenamed("id", "u").join(lead, "key").where((F.col("u") != F.col("v")) & close(F.col("size"), F.col("other")))
        stars = stars.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).unionByName(printed_pairs(sets.select("id", "fp")))
        stars = verified(stars, "document-stars")
        rooted = spread.join(components(stars, "documents").withColumnRenamed("node", "id"), "id", "left").withColumn("root", F.coalesce("root", "id"))
        mixed = rooted.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low < high").select("key")
        rooted = written(rooted.join(mixed, "key", "left_semi"), "document-buckets")
        other = rooted.select("key", F.col("id").alias("v"), F.col("size").alias("other"), F.col("root").alias("o_root"))
        more = rooted.withColumnRenamed("id", "u").join(other, "key").where((F.col("root") != F.col("o_root")) & (F.col("u") > F.col("v")) & close(F.col("size"), F.col("other")))
        roots = components(stars.unionByName(verified(more.select("u", "v"), "document-links")), "documents")
        joined = sets.select("id", "same", "least").join(roots.withColumnRenamed("node", "id"), "id", "left").withColumn("root", F.coalesce("root", "id"))
        ids = joined.groupBy("root").agg(F.min("least").alias("component_id"))
        return inner.keep(rows.select("doc_id", "same").join(joined.join(ids, "root").select("same", "component_id"), "same").select("doc_id", "component_id"), "document-components")
