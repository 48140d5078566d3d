"""Smoothing along time: sums and banded means of snapshots and frames."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.schema import DynamicGraph, FeatureTensor


def _reach(t: str, span: int, last: int):
    return F.sequence(F.col(t), F.least(F.col(t) + span - 1, F.lit(last).cast("long")))


def edge_life(g: DynamicGraph, span: int) -> DynamicGraph:
    """Each snapshot becomes the sum of the last `span` snapshots, itself included."""
    if span == 1:
        return g
    lived = g.edges.select(F.explode(_reach("t", span, g.T)).alias("t"), "src", "dst", "w")
    return g.with_edges(lived.groupBy("t", "src", "dst").agg(F.sum("w").alias("w")))


def m_transform_edges(g: DynamicGraph, span: int) -> DynamicGraph:
    """Banded mean: the sum of edge_life over min(span, t)."""
    e = edge_life(g, span).edges
    return g.with_edges(e.withColumn("w", F.col("w") / F.least(F.lit(span).cast("long"), F.col("t"))))


def m_transform_features(x: FeatureTensor, span: int) -> FeatureTensor:
    """Banded mean of the frames: on a dense grid the frame of the last `span` rows of a vertex."""
    w = Window.partitionBy("v").orderBy("t").rowsBetween(-(span - 1), 0)
    return FeatureTensor(x.df.select("t", "v", *[F.avg(c).over(w).alias(c) for c in x.cols]), x.width, x.name)


def band_matrix(spark: SparkSession, steps: int, span: int) -> DataFrame:
    """(t, k, m): m = 1 / min(span, t) for the last `span` steps k up to t."""
    return band_of(spark.range(1, steps + 1).select(F.col("id").alias("t")), span)


def band_of(t: DataFrame, span: int) -> DataFrame:
    """The rows of the band matrix of given steps (t)."""
    first = F.greatest(F.lit(1).cast("long"), F.col("t") - span + 1)
    return t.select("t", F.explode(F.sequence(first, F.col("t"))).alias("k"), (1.0 / F.least(F.lit(span).cast("long"), F.col("t"))).alias("m"))


def mode1_product(x: FeatureTensor, matrix: DataFrame) -> FeatureTensor:
    """Frames mixed along time by any matrix (t, k, m): row t is the sum over k of m times frame k.

    The matrix is broadcast: it has at most T * T rows, T being the number of snapshots.
    """
    mixed = x.df.withColumnRenamed("t", "k").join(F.broadcast(matrix), "k")
    return FeatureTensor(mixed.groupBy("t", "v").agg(*[F.sum(F.col("m") * F.col(c)).alias(c) for c in x.cols]), x.width, x.name)


def smoothing_growth(g: DynamicGraph, span: int) -> DataFrame:
    """One row: non-zeros before, after the banded mean and after edge life, and the growth factor (the two have one pattern)."""
    raw = g.edges.agg(F.count(F.lit(1)).alias("nnz"))
    grown = edge_life(g, span).edges.agg(F.count(F.lit(1)).alias("nnz_smoothed"))
    return raw.crossJoin(grown).select(F.lit(span).cast("long").alias("span"), "nnz", "nnz_smoothed", F.round(F.col("nnz_smoothed") / F.col("nnz"), 6).alias("growth"))


def compress_runs(edges: DataFrame) -> DataFrame:
    """Edges as runs (src, dst, t_from, t_to, w) of consecutive steps with one weight: rows follow changes, not spans."""
    w = Window.partitionBy("src", "dst", "w").orderBy("t")
    island = edges.withColumn("i", F.col("t") - F.row_number().over(w))
    return island.groupBy("src", "dst", "w", "i").agg(F.min("t").alias("t_from"), F.max("t").alias("t_to")).select("src", "dst", "t_from", "t_to", "w")


def expand_runs(runs: DataFrame, first: int | None = None, last: int | None = None) -> DataFrame:
    """Edges of runs, for the steps first..last where given (one block at a time at scale)."""
    lo = F.greatest("t_from", F.lit(first).cast("long")) if first else F.col("t_from")
    hi = F.least("t_to", F.lit(last).cast("long")) if last else F.col("t_to")
    return runs.where(lo <= hi).select(F.explode(F.sequence(lo, hi)).alias("t"), "src", "dst", "w")
