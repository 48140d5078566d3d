"""Readers of edge lists, and stores of snapshots, differences, layouts, parameters and histories."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dyngraph.operators.delta import decode_delta, encode_delta, step_plan, whole_steps
from dyngraph.schema import EDGES, DynamicGraph

FORMATS = ("parquet", "csv", "json", "orc", "text")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", header: bool = True) -> tuple[DataFrame, DataFrame]:
    """(edges, rejects) of an edge list in any of FORMATS; text lines are "t src dst [w]". A missing weight is 1.

    The schema is fixed; malformed rows and rows with a null step or endpoint come out as rejects, to be counted.
    """
    if fmt == "text":
        p = F.split(F.trim("value"), r"\s+")
        rows = spark.read.text(path).select(*[F.try_element_at(p, F.lit(i + 1)).try_cast(EDGES[c].dataType).alias(c) for i, c in enumerate(("t", "src", "dst", "w"))])
    elif fmt in ("csv", "json"):
        reader = spark.read.schema(EDGES).option("mode", "PERMISSIVE")
        rows = reader.option("header", header).csv(path) if fmt == "csv" else reader.json(path)
    else:
        rows = spark.read.format(fmt).load(path)
        rows = rows.select(*[(F.col(c) if c in rows.columns else F.lit(1.0)).cast(EDGES[c].dataType).alias(c) for c in ("t", "src", "dst", "w")])
    bad = F.col("t").isNull() | F.col("src").isNull() | F.col("dst").isNull()
    return rows.where(~bad).withColumn("w", F.coalesce("w", F.lit(1.0))), rows.where(bad)


def write_snapshots(g: DynamicGraph, path: str, per_range: int = 10) -> None:
    """Edges as Parquet by ranges of steps, sorted by pair inside, so that reading a block opens its ranges only."""
    rows = g.edges.withColumn("range", F.floor((F.col("t") - 1) / per_range).cast("int"))
    rows.repartition("range", "t").sortWithinPartitions("t", "src", "dst").write.mode("overwrite").partitionBy("range").parquet(path)


def read_snapshots(spark: SparkSession, path: str, first: int, last: int, per_range: int = 10) -> DataFrame:
    rows = spark.read.parquet(path).where(F.col("range").between((first - 1) // per_range, (last - 1) // per_range))
    return rows.where(F.col("t").between(first, last)).select("t", "src", "dst", "w")


def write_delta(g: DynamicGraph, path: str, block: int, processors: int = 1, adaptive: bool = False) -> None:
    """The difference form: indices and values by block, and the steps sent in full."""
    indices, values = encode_delta(g, block, processors, adaptive)
    blocks = F.broadcast(step_plan(g.spark, g.T, block, processors).select("t", "block"))
    indices.join(blocks, "t").write.mode("overwrite").partitionBy("block").parquet(f"{path}/indices")
    values.join(blocks, "t").write.mode("overwrite").partitionBy("block").parquet(f"{path}/values")
    whole_steps(g, block, processors, adaptive).write.mode("overwrite").parquet(f"{path}/whole")


def read_delta(spark: SparkSession, path: str, steps: int, block: int | None = None) -> DataFrame:
    """Edges of one block, or of all; only the block's folders are read."""
    pick = (lambda df: df.where(F.col("block") == block)) if block is not None else (lambda df: df)
    indices, values = (pick(spark.read.parquet(f"{path}/{n}")).drop("block") for n in ("indices", "values"))
    return decode_delta(indices, values, spark.read.parquet(f"{path}/whole"), steps)


def save_layout(df: DataFrame, name: str, buckets: int, key: str = "t") -> None:
    """A bucketed table: joins and groupings by the key then move no row."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def save_params(spark: SparkSession, params: dict[str, np.ndarray], path: str) -> None:
    """Parameters as rows (name, i, j, val)."""
    rows = [(n, i, j, float(v)) for n, m in params.items() for i, r in enumerate(np.atleast_2d(m)) for j, v in enumerate(r)]
    spark.createDataFrame(rows, "name string, i int, j int, val double").coalesce(1).write.mode("overwrite").parquet(path)


def load_params(spark: SparkSession, path: str) -> dict[str, np.ndarray]:
    out: dict[str, dict] = {}
    for r in spark.read.parquet(path).collect():
        out.setdefault(r["name"], {})[r["i"], r["j"]] = r["val"]
    shape = lambda c: (max(i for i, _ in c) + 1, max(j for _, j in c) + 1)
    return {n: np.array([[c[i, j] for j in range(shape(c)[1])] for i in range(shape(c)[0])]) for n, c in out.items()}


def append_history(spark: SparkSession, rows: list[dict], path: str) -> None:
    spark.createDataFrame([(json.dumps(r),) for r in rows], "value string").coalesce(1).write.mode("append").text(path)
