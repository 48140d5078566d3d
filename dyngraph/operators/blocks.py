"""Blocks of the timeline, the memory that they need, and the choice of their number."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def ranges(steps: int, blocks: int) -> list[tuple[int, int, int]]:
    """(block, first, last), balanced: step i (from 0) is in block floor(i * blocks / steps)."""
    cut = [-(-b * steps // blocks) for b in range(blocks + 1)]
    return [(b, cut[b] + 1, cut[b + 1]) for b in range(blocks)]


def block_plan(spark: SparkSession, steps: int, blocks: int) -> DataFrame:
    """(block, first, last, size)."""
    b = F.col("id")
    lo, hi = F.ceil(b * steps / blocks), F.ceil((b + 1) * steps / blocks)
    return spark.range(blocks).select(b.alias("block"), (lo + 1).cast("long").alias("first"), hi.cast("long").alias("last"), (hi - lo).cast("long").alias("size"))


def block_owner(t, steps: int, blocks: int, processors: int):
    """Expressions (block, pid) of a step: contiguous balanced ranges of the processors inside each block."""
    i = t - 1
    b = F.floor(i * blocks / steps)
    lo, hi = F.ceil(b * steps / blocks), F.ceil((b + 1) * steps / blocks)
    return b.cast("long"), F.floor((i - lo) * processors / (hi - lo)).cast("long")


def owner_in_block(spark: SparkSession, steps: int, blocks: int, processors: int) -> DataFrame:
    """(t, block, pid): every processor has a share of every block."""
    return owners_of(spark.range(1, steps + 1).select(F.col("id").alias("t")), steps, blocks, processors)


def owners_of(t: DataFrame, steps: int, blocks: int, processors: int) -> DataFrame:
    """owner_in_block for given steps (t)."""
    block, pid = block_owner(F.col("t"), steps, blocks, processors)
    return t.select("t", block.alias("block"), pid.alias("pid"))


def memory_model(spark: SparkSession, nnz: int, n: int, steps: int, widths: int, carry: int, blocks: list[int], processors: list[int], index_bytes: int = 8, value_bytes: int = 4, budget: float | None = None) -> DataFrame:
    """(nb, p, block_bytes, carry_bytes, bytes, fits): activations of one block, and the states kept between blocks.

    widths: floats of all activations of a vertex and step; carry: floats of the state of a vertex.
    """
    rows = spark.createDataFrame([(b, p) for b in blocks for p in processors], "nb long, p long")
    inner = F.lit(float(nnz * (2 * index_bytes + value_bytes) + steps * n * 8 * widths)) / F.col("nb") / F.col("p")
    kept = F.col("nb") * float(n * 8 * carry) / F.col("p")
    out = rows.select("nb", "p", F.round(inner, 3).alias("block_bytes"), F.round(kept, 3).alias("carry_bytes"), F.round(inner + kept, 3).alias("bytes"))
    return out.withColumn("fits", F.col("bytes") <= budget) if budget is not None else out


def best_blocks(nnz: int, n: int, steps: int, widths: int, carry: int, index_bytes: int = 8, value_bytes: int = 4) -> float:
    """Number of blocks where activations and states together are least."""
    inner = nnz * (2 * index_bytes + value_bytes) + steps * n * 8 * widths
    return (inner / (n * 8 * carry)) ** 0.5 if carry else float(steps)


def tune_blocks(model: DataFrame) -> DataFrame:
    """(p, nb): for each processor count the fewest blocks that fit (fewer blocks run faster); null: did not run."""
    return model.groupBy("p").agg(F.min(F.when(F.col("fits"), F.col("nb"))).alias("nb"))
