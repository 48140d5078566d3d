"""Shared pieces of the corpus operators: table access, written intermediates, ranks, components."""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.storage import release, scope, shared_dir, written  # noqa: F401  the operators take them from here


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ranked(df: DataFrame, keys: list[str], order: list[str], salts: int = 64, out: str = "rank") -> DataFrame:
    """Adds a gapless 0-based rank within keys.

    Rows are ranked inside (keys, salt) cells and shifted by the sizes of the cells before, so that a key
    which holds a third of all rows is spread over `salts` tasks. The cell sizes are at most `salts` rows a key.
    """
    salted = df.withColumn("_salt", F.pmod(F.xxhash64(*order), F.lit(salts)))
    cells = salted.groupBy(*keys, "_salt").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*keys).orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    cells = cells.withColumn("_shift", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    within = Window.partitionBy(*keys, "_salt").orderBy(*order)
    return (
        salted.withColumn("_row", F.row_number().over(within) - 1)
        .join(cells, [*keys, "_salt"])
        .withColumn(out, F.col("_row") + F.col("_shift"))
        .drop("_row", "_shift", "_salt")
    )


def free_name(df: DataFrame, name: str) -> str:
    """name, with underscores behind it until df has no such column."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name += "_"
    return name


def checked(df: DataFrame, rows: int) -> DataFrame:
    """df (written, so that counting is cheap) as a broadcast side while it has at most `rows` rows, else as it is."""
    return F.broadcast(df) if df.count() <= rows else df


def block_masks(count: int, radius: int, bits: int = 64, bucket: int = 256) -> list[int]:
    """Bit masks of which at least one covers no differing bit of two words within `radius` bits (pigeonhole).

    The word is cut into radius + p blocks and each choice of p of them is a mask; p is the smallest for which
    `count` evenly spread words leave at most `bucket` to a masked value. Masks are signed longs.
    """
    for pick in range(1, 5):
        blocks = radius + pick
        cuts = [bits * i // blocks for i in range(blocks + 1)]
        if count <= bucket << (bits * pick // blocks):
            break
    parts = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in itertools.pairwise(cuts)]
    masks = [sum(chosen) for chosen in itertools.combinations(parts, pick)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def masked(fp: str, masks: list[int]):
    """Array of the (mask number, masked value) of column fp."""
    return F.array(*[F.struct(F.lit(i).alias("band"), F.col(fp).bitwiseAND(F.lit(m)).alias("value")) for i, m in enumerate(masks)])


def _digest(edges: DataFrame):
    row = edges.agg(
        F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))
    ).first()
    return row[0], row[1]


def components(edges: DataFrame, tag: str = "components", max_rounds: int = 60) -> DataFrame:
    """Connected components of edges (u, v) of longs: (node, root) for each node of an edge, root the smallest node.

    Alternates the two star contractions of the MapReduce connectivity literature; each round is two
    map-side combined minima and two joins, and is written to the shared folder. No group is collected.
    """
    e = edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    e = written(e, tag)
    seen = _digest(e)
    if seen[0] == 0:
        return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    for _ in range(max_rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        small = small.select("u", "m").unionByName(small.select(F.col("v").alias("u"), "m"))
        e = written(small.where("u <> m").select("u", F.col("m").alias("v")).distinct(), tag)
        now = _digest(e)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not converge")
    stars = e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return stars.unionByName(stars.select(F.col("root").alias("node"), "root").distinct())
