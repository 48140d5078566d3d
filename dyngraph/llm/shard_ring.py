"""Sharding by a consistent-hash ring with virtual nodes and bounded loads.

The ring has a fixed number of positions. Keys hash to a position and go to the shard of the next virtual
node clockwise; once that shard is full, its further keys continue clockwise to the next shard with room.
Keys of one position share their whole way round the ring, so the walk is decided on the counts by position
(at most `positions` numbers, whatever the input) and rows only learn their rank inside their position.
"""

from __future__ import annotations

import bisect
import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.llm.common import written

POSITIONS = 1 << 15
VNODES = 128


def ring(shards: int, vnodes: int = VNODES, positions: int = POSITIONS) -> list[tuple[int, int]]:
    """Sorted (position, shard) of all virtual nodes."""
    at = lambda s, v: int.from_bytes(hashlib.blake2b(b"%d/%d" % (s, v), digest_size=8).digest(), "big") % positions
    return sorted((at(s, v), s) for s in range(shards) for v in range(vnodes))


def capacities(total: int, shards: int, slack: float) -> list[int]:
    """Rows that each shard may hold. slack 0: the shares of an even split, which differ by one at most."""
    if slack == 0:
        return [total // shards + (s < total % shards) for s in range(shards)]
    return [-int(-(1 + slack) * total // shards)] * shards


def walk(counts: dict[int, int], nodes: list[tuple[int, int]], room: list[int]) -> list[tuple[int, int, int, int, int, int]]:
    """Runs (position, first rank, last rank + 1, shard, first slot, home shard); positions are served in ring order."""
    room, filled, runs = list(room), [0] * len(room), []
    spots = [p for p, _ in nodes]
    for position in sorted(counts):
        left, rank = counts[position], 0
        i = bisect.bisect_left(spots, position) % len(nodes)
        home = nodes[i][1]
        while left:
            shard = nodes[i][1]
            if take := min(left, room[shard]):
                runs.append((position, rank, rank + take, shard, filled[shard], home))
                room[shard] -= take
                filled[shard] += take
                rank, left = rank + take, left - take
            i = (i + 1) % len(nodes)
    return runs


def assign(df: DataFrame, key: str, shards: int = 16, slack: float = 0.0, vnodes: int = VNODES, positions: int = POSITIONS, salts: int = 16) -> DataFrame:
    """df (key and further small columns) with shard, slot (gapless from 0 in each shard) and home_shard.

    Equal rows are counted before they are moved and dealt out again at the end; rows of one key are ranked in
    `salts` cells. A null key hashes like any other key. An empty df gives an empty result. slack is the share
    by which a shard may exceed the mean; with 0 the shards' counts differ by one at most.
    """
    spark, cols = df.sparkSession, df.columns
    at = F.pmod(F.xxhash64(key), F.lit(positions)).cast("int")
    equal = df.groupBy(*cols).agg(F.count(F.lit(1)).alias("_n"))
    equal = written(equal.select(*cols, "_n", at.alias("_at"), F.pmod(F.xxhash64(*cols), F.lit(salts)).cast("int").alias("_salt")), "ring")
    cells = equal.groupBy("_at", "_salt").agg(F.sum("_n").alias("_c"))
    counts = {r["_at"]: r["_c"] for r in cells.groupBy("_at").agg(F.sum("_c").alias("_c")).collect()}
    runs = walk(counts, ring(shards, vnodes, positions), capacities(sum(counts.values()), shards, slack))
    schema = "_at int, _from long, _to long, shard int, _slot long, home_shard int"
    before = Window.partitionBy("_at").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    shifts = cells.select("_at", "_salt", F.coalesce(F.sum("_c").over(before), F.lit(0)).alias("_shift"))
    within = Window.partitionBy("_at", "_salt").orderBy(*cols).rowsBetween(Window.unboundedPreceding, -1)
    rows = equal.withColumn("_first", F.coalesce(F.sum("_n").over(within), F.lit(0))).join(shifts, ["_at", "_salt"])
    rows = rows.withColumn("_first", F.col("_first") + F.col("_shift"))
    rows = rows.withColumn("_rank", F.explode(F.sequence(F.col("_first"), F.col("_first") + F.col("_n") - 1)))
    runs = spark.createDataFrame(runs or [], schema)
    placed = rows.join(F.broadcast(runs), "_at").where("_rank >= _from and _rank < _to")  # at most positions + shards * vnodes runs
    return placed.select(*cols, "shard", (F.col("_slot") + F.col("_rank") - F.col("_from")).alias("slot"), "home_shard")


def shard_documents(docs: DataFrame, shards: int = 16) -> DataFrame:
    """One row per document with its size in bytes plus one, the CRC of its text (null: empty), shard and slot."""
    text = F.coalesce(F.col("text"), F.lit(""))
    slim = docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"))
    placed = assign(slim, "doc_id", shards)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "home_shard")
