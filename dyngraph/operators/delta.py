"""Snapshots as differences: coding, decoding, sizes and their measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.schema import DynamicGraph


def step_plan(spark: SparkSession, steps: int, block: int | None = None, processors: int = 1) -> DataFrame:
    """(t, block, pid, first): blocks of `block` steps cut into `processors` chunks; first marks the first step of a chunk."""
    size = block or steps
    t = F.col("id")
    b = F.floor((t - 1) / size)
    length = F.least(F.lit(size), F.lit(steps) - b * size)
    plan = spark.range(1, steps + 1).select(t.alias("t"), b.cast("long").alias("block"), F.floor(((t - 1) % size) * processors / length).cast("long").alias("pid"))
    # a chunk's first step: another chunk, or another block, holds the step before
    before = F.floor(((F.col("t") - 2) % size) * processors / F.least(F.lit(size), F.lit(steps) - F.col("block") * size)).cast("long")
    return plan.withColumn("first", ((F.col("t") - 1) % size == 0) | (before != F.col("pid")))


def diff_sets(g: DynamicGraph) -> DataFrame:
    """(t, kind, src, dst) for each step t > 1: common, left (in t - 1 only), entered (in t only); one exchange, no self join."""
    w = Window.partitionBy("src", "dst").orderBy("t")
    e = g.edges.select("t", "src", "dst", F.coalesce(F.lag("t").over(w) == F.col("t") - 1, F.lit(False)).alias("came"), F.coalesce(F.lead("t").over(w) == F.col("t") + 1, F.lit(False)).alias("stays"))
    here = F.when(F.col("t") > 1, F.struct(F.col("t").alias("t"), F.when(F.col("came"), "common").otherwise("entered").alias("kind")))
    gone = F.when(~F.col("stays") & (F.col("t") < g.T), F.struct((F.col("t") + 1).alias("t"), F.lit("left").alias("kind")))
    return e.select("src", "dst", F.explode(F.array_compact(F.array(here, gone))).alias("r")).select("r.t", "r.kind", "src", "dst")


def step_counts(g: DynamicGraph) -> DataFrame:
    """(t, nnz, ext_prev, ext_next): size of t, pairs that left since t - 1, pairs that entered; all steps, T rows."""
    size = g.edges.groupBy("t").agg(F.count(F.lit(1)).alias("nnz"))
    parts = diff_sets(g).groupBy("t").agg(F.count_if(F.col("kind") == "left").alias("ext_prev"), F.count_if(F.col("kind") == "entered").alias("ext_next"))
    return g.spark.range(1, g.T + 1).select(F.col("id").alias("t")).join(size, "t", "left").join(parts, "t", "left").na.fill(0)


def step_costs(g: DynamicGraph, block: int | None = None, processors: int = 1, index_bytes: int = 8, value_bytes: int = 4, values: str = "all", counts: DataFrame | None = None) -> DataFrame:
    """Bytes of each step in full, as a difference (in full where a chunk starts), and the cheaper of the two.

    counts: step_counts(g), if they are at hand. values="none" leaves the value arrays out of the differences, for graphs whose weights never change.
    """
    vb = value_bytes if values == "all" else 0
    full = F.col("nnz") * (2 * index_bytes + value_bytes)
    diff = (F.col("ext_prev") + F.col("ext_next")) * (2 * index_bytes) + F.col("nnz") * vb
    rows = (step_counts(g) if counts is None else counts).join(step_plan(g.spark, g.T, block, processors), "t")
    delta = F.when(F.col("first"), full).otherwise(diff)
    return rows.select("t", "block", "pid", "first", "nnz", "ext_prev", "ext_next", full.alias("full_bytes"), delta.alias("delta_bytes"), F.least(full, delta).alias("adaptive_bytes"))


def cost_totals(g: DynamicGraph, passes: int = 2, **how) -> DataFrame:
    """One row: bytes an epoch in full, by differences, adaptively, and the ratios to full. Blocks are loaded `passes` times."""
    c = step_costs(g, **how).agg(*[(F.coalesce(F.sum(f"{m}_bytes"), F.lit(0)) * passes).alias(f"{m}_bytes") for m in ("full", "delta", "adaptive")])
    return c.select("*", *[F.round(F.col("full_bytes") / F.col(f"{m}_bytes"), 6).alias(f"{m}_ratio") for m in ("delta", "adaptive")])


def canonical_rank(edges: DataFrame, cell: int = 1024) -> DataFrame:
    """edges with pos, the 0-based place of a pair in its snapshot by (src, dst).

    Sources are ranked in cells of `cell` ids and shifted by the cells before: no task sorts a whole snapshot.
    """
    e = edges.withColumn("_c", F.floor(F.col("src") / cell).cast("long"))
    sizes = e.groupBy("t", "_c").agg(F.count(F.lit(1)).alias("_n"))
    shift = F.coalesce(F.sum("_n").over(Window.partitionBy("t").orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    own = F.row_number().over(Window.partitionBy("t", "_c").orderBy("src", "dst")) - 1
    return e.withColumn("_r", own).join(sizes.withColumn("_s", shift).drop("_n"), ["t", "_c"]).withColumn("pos", F.col("_r") + F.col("_s")).drop("_c", "_r", "_s")


def encode_full(g: DynamicGraph) -> tuple[DataFrame, DataFrame]:
    """The baseline: all pairs and values of all snapshots."""
    return g.edges.select("t", F.lit("full").alias("kind"), "src", "dst"), canonical_rank(g.edges).select("t", "pos", "w")


def encode_delta(g: DynamicGraph, block: int | None = None, processors: int = 1, adaptive: bool = False, plan: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(indices (t, kind, src, dst), values (t, pos, w)): full steps where a chunk starts, else pairs to add and to drop.

    adaptive sends a step in full wherever that is no larger. plan: (t, whole) in place of chunks of equal length.
    """
    if plan is not None:
        plan = plan.select("t", "whole")
    elif adaptive:
        c = step_costs(g, block, processors)
        plan = c.select("t", (F.col("first") | (F.col("full_bytes") <= F.col("delta_bytes"))).alias("whole"))
    else:
        plan = step_plan(g.spark, g.T, block, processors).select("t", F.col("first").alias("whole"))
    plan = F.broadcast(plan)  # T rows
    full = g.edges.join(plan, "t").where("whole").select("t", F.lit("full").alias("kind"), "src", "dst")
    parts = diff_sets(g).where("kind <> 'common'").join(plan, "t").where("not whole")
    parts = parts.select("t", F.when(F.col("kind") == "left", "del").otherwise("add").alias("kind"), "src", "dst")
    return full.unionByName(parts), canonical_rank(g.edges).select("t", "pos", "w")


def decode_delta(indices: DataFrame, values: DataFrame, plan_whole: DataFrame, steps: int) -> DataFrame:
    """Edges rebuilt from differences. plan_whole: (t) of the steps sent in full (empty ones too), T rows at most."""
    starts = plan_whole.select("t").withColumn("until", F.coalesce(F.lead("t").over(Window.orderBy("t")) - 1, F.lit(steps).cast("long"))).withColumnRenamed("t", "seg")
    ev = indices.join(F.broadcast(starts), (F.col("t") >= F.col("seg")) & (F.col("t") <= F.col("until")))
    nxt = F.lead("t").over(Window.partitionBy("seg", "src", "dst").orderBy("t"))
    alive = ev.withColumn("end", F.coalesce(nxt - 1, F.col("until"))).where("kind <> 'del'")
    pairs = alive.select(F.explode(F.sequence("t", "end")).alias("t"), "src", "dst")
    return canonical_rank(pairs).join(values, ["t", "pos"]).select("t", "src", "dst", "w")


def whole_steps(g: DynamicGraph, block: int | None = None, processors: int = 1, adaptive: bool = False) -> DataFrame:
    """(t) of the steps that encode_delta sends in full."""
    c = step_costs(g, block, processors)
    return c.where((F.col("first") | (F.col("full_bytes") <= F.col("delta_bytes"))) if adaptive else F.col("first")).select("t")


def gd_benefit(spark: SparkSession, sizes: list[int], processors: list[int]) -> DataFrame:
    """(bsize, p, share): part of a block's snapshots that go as differences."""
    rows = [(b, p) for b in sizes for p in processors]
    return spark.createDataFrame(rows, "bsize long, p long").withColumn("share", F.round(F.greatest(F.col("bsize") - F.col("p"), F.lit(0)) / F.col("bsize"), 6))
