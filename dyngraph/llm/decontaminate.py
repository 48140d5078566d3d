"""Benchmark decontamination by size-partitioned MinHash containment search, with DataFrame operations only.

Benchmark items are put into classes by the size of their shingle set. An item's MinHash sketch is its smallest
shingle hashes; the sketch length of a class follows from its largest size and the threshold, so that a text which
holds the asked share of any item of the class holds at least one hash of its sketch. The search therefore loses no
pair, however long the text is. Candidate pairs are verified with the shingles themselves.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dyngraph.llm.common import checked, written

SHINGLE = 5
CONTAINMENT = 0.8
CLASS_GROWTH = 1.25
BROADCAST_ROWS = 500_000


def words(text):
    """Runs of letters and digits in lower case; the empty array for null or wordless texts."""
    flat = F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " "))
    return F.when(flat == "", F.array().cast("array<string>")).otherwise(F.split(flat, " "))


def hashed_shingles(ws, n: int):
    """64-bit hashes of all n-word shingles of the array ws."""
    last = F.size(ws) - n
    each = lambda i: F.xxhash64(F.lit(n), *[F.get(ws, i + k) for k in range(n)])
    return F.when(last >= 0, F.transform(F.sequence(F.lit(0), last), each)).otherwise(F.array().cast("array<long>"))


def shingles(ws, n):
    """The n-word shingles themselves, distinct."""
    last = F.size(ws) - n
    return F.when(last >= 0, F.array_distinct(F.transform(F.sequence(F.lit(0), last), lambda i: F.concat_ws(" ", F.slice(ws, i + 1, n))))).otherwise(F.array().cast("array<string>"))


def sketches(items: DataFrame, n: int = SHINGLE, threshold: float = CONTAINMENT) -> DataFrame:
    """(item_id, size, len, hash): the sketch of each item. Items of fewer than n words have one shingle of all their words."""
    rows = items.where(F.col("item_id").isNotNull()).select("item_id", words(F.col("text")).alias("w")).where(F.size("w") > 0)
    rows = rows.withColumn("len", F.least(F.size("w"), F.lit(n)))
    by_len = F.coalesce(*[F.when(F.col("len") == k, F.array_distinct(hashed_shingles(F.col("w"), k))) for k in range(1, n + 1)])
    rows = rows.select("item_id", "len", by_len.alias("h")).withColumn("size", F.size("h"))
    # the class of sizes (g^(c-1), g^c]; its largest size decides the sketch length of all its items
    step = math.log(CLASS_GROWTH)
    largest = F.floor(F.pow(F.lit(CLASS_GROWTH), F.ceil(F.log("size") / step - 1e-9)) + 1e-9)
    length = F.least(F.col("size"), (F.greatest(largest, F.col("size")) - F.ceil(F.greatest(largest, F.col("size")) * threshold - 1e-9) + 1).cast("int"))
    rows = rows.select("item_id", "size", "len", F.slice(F.array_sort("h"), F.lit(1), length).alias("s"))
    return rows.select("item_id", "size", "len", F.explode("s").alias("hash"))


def contaminated(docs: DataFrame, items: DataFrame, n: int = SHINGLE, threshold: float = CONTAINMENT) -> DataFrame:
    """(doc_id, item_id, containment): every document and item where the item's share of shingles in the whole text
    is at least the threshold.

    Words are compared in lower case without marks. An item without words is in no document; null texts hold
    nothing. Rows that share a doc_id are judged each, and the largest share is reported; a null doc_id can't be
    named and is left out, as is a null item_id. The sketch table is broadcast while it has at most
    BROADCAST_ROWS rows and joined by shuffle beyond.
    """
    sketch = sketches(items, n, threshold).select("item_id", "len", "hash")
    head = sketch.groupBy("len").agg(F.count(F.lit(1)).alias("c")).collect()  # n rows at most
    small = sum(r["c"] for r in head) <= BROADCAST_ROWS
    sizes = sorted(r["len"] for r in head) or [n]
    texts = docs.where(F.col("doc_id").isNotNull()).select("doc_id", "text")
    ws = texts.select("doc_id", words(F.col("text")).alias("w"))
    held = ws.select("doc_id", F.explode(F.array_distinct(F.concat(*[hashed_shingles(F.col("w"), k) for k in sizes]))).alias("hash"))
    keys = sketch.select("hash", "item_id")
    pairs = written(held.join(F.broadcast(keys) if small else keys, "hash").select("doc_id", "item_id").distinct(), "candidates")
    asked = items.where(F.col("item_id").isNotNull()).select("item_id", words(F.col("text")).alias("iw"))
    asked = asked.select("item_id", F.least(F.size("iw"), F.lit(n)).alias("len"), "iw").where("len > 0")
    asked = asked.select("item_id", "len", shingles(F.col("iw"), F.col("len")).alias("parts"))
    wanted = pairs.join(F.broadcast(asked) if small else asked, "item_id").groupBy("doc_id").agg(F.collect_list(F.struct("item_id", "len", "parts")).alias("wanted"))
    named = checked(pairs.select("doc_id").distinct(), BROADCAST_ROWS)
    both = texts.join(named, "doc_id", "left_semi").join(wanted, "doc_id").select("doc_id", words(F.col("text")).alias("w"), "wanted")
    # the text's shingles are made once for each length and row, not once for each candidate
    for k in sizes:
        both = both.withColumn(f"held_{k}", shingles(F.col("w"), k))
    pick = lambda x: F.coalesce(*[F.when(x["len"] == k, F.size(F.array_intersect(x["parts"], F.col(f"held_{k}")))) for k in sizes])
    found = both.select("doc_id", F.explode(F.transform("wanted", lambda x: F.struct(x["item_id"].alias("item_id"), (pick(x) / F.size(x["parts"])).alias("containment")))).alias("r"))
    found = found.select("doc_id", "r.*").where(F.col("containment") >= threshold - 1e-12)
    return found.groupBy("doc_id", "item_id").agg(F.max("containment").alias("containment"))


def clean(docs: DataFrame, items: DataFrame, n: int = SHINGLE, threshold: float = CONTAINMENT) -> DataFrame:
    """The documents that hold no item. Rows with a null doc_id are kept."""
    bad = contaminated(docs, items, n, threshold).select("doc_id").distinct()
    return docs.join(bad, "doc_id", "left_anti")


_WORDS = r"string_split(nullif(trim(regexp_replace(lower(coalesce(text, '')), '[^\p{L}\p{N}]+', ' ', 'g')), ''), ' ')"
ORACLE = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents WHERE doc_id IS NOT NULL),
b AS (SELECT item_id, {_WORDS} AS w FROM benchmark WHERE item_id IS NOT NULL),
i AS (SELECT DISTINCT item_id, least(len(w), 5) AS n, unnest(list_transform(range(0, len(w) - least(len(w), 5) + 1), lambda k: array_to_string(w[k + 1 : k + least(len(w), 5)], ' '))) AS s FROM b WHERE w IS NOT NULL),
t AS (SELECT item_id, count(*) AS c FROM i GROUP BY item_id),
h AS (SELECT DISTINCT doc_id, n, unnest(list_transform(range(0, len(w) - n + 1), lambda k: array_to_string(w[k + 1 : k + n], ' '))) AS s FROM d, (SELECT DISTINCT n FROM i) WHERE len(w) >= n)
SELECT doc_id, item_id, count(*) / any_value(c)::DOUBLE AS containment FROM h JOIN i USING (n, s) JOIN t USING (item_id)
GROUP BY doc_id, item_id HAVING count(*) >= 0.8 * any_value(c)
"""
