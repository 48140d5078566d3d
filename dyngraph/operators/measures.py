"""Measures of experiments: speedup, throughput, gains, phases of an epoch, exchanges of a plan."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window


def speedup_table(timings: DataFrame, keys: list[str]) -> DataFrame:
    """timings (keys, p, ms) with ref_p and speedup: the smallest p that ran counts as p times faster than one."""
    w = Window.partitionBy(*keys)
    ran = timings.where("ms is not null")
    ref = ran.withColumn("ref_p", F.min("p").over(w)).withColumn("ref_ms", F.min_by("ms", "p").over(w))
    return ref.select(*keys, "p", "ms", "ref_p", F.round(F.col("ref_p") * F.col("ref_ms") / F.col("ms"), 6).alias("speedup"))


def throughput_table(timings: DataFrame, keys: list[str]) -> DataFrame:
    """timings (keys, p, nnz, ms) with non-zeros a second and its ratio to that of the smallest p."""
    w = Window.partitionBy(*keys).orderBy("p")
    rate = timings.where("ms is not null").withColumn("per_s", F.col("nnz") * 1000.0 / F.col("ms"))
    return rate.select(*keys, "p", "nnz", "ms", F.round("per_s", 6).alias("per_s"), F.round(F.col("per_s") / F.first("per_s").over(w), 6).alias("scaled"))


def gd_gain(timings: DataFrame) -> DataFrame:
    """(..., base_ms, gd_ms, rest_ms) with the transfer speedup and the share of the whole time saved."""
    return timings.select("*", F.round(F.col("base_ms") / F.col("gd_ms"), 6).alias("transfer_speedup"), F.round(100 * (F.col("base_ms") - F.col("gd_ms")) / (F.col("base_ms") + F.col("rest_ms")), 6).alias("overall_gain"))


def curve_gap(history: DataFrame, a: str, b: str) -> DataFrame:
    """One row: largest difference of loss and accuracy between two layouts' histories (layout, epoch, loss, accuracy)."""
    x, y = history.where(F.col("layout") == a), history.where(F.col("layout") == b)
    j = x.alias("x").join(y.alias("y"), "epoch")
    return j.agg(F.max(F.abs(F.col("x.loss") - F.col("y.loss"))).alias("loss_gap"), F.max(F.abs(F.col("x.accuracy") - F.col("y.accuracy"))).alias("accuracy_gap"))


class PhaseTimer:
    """Wall-clock milliseconds by phase: prepare, transfer, compute, communicate."""

    def __init__(self):
        self.ms: dict[str, float] = {}

    @contextmanager
    def phase(self, name: str):
        began = time.perf_counter()
        try:
            yield
        finally:
            self.ms[name] = self.ms.get(name, 0.0) + (time.perf_counter() - began) * 1000


def run(df: DataFrame) -> None:
    """Executes a plan and drops its rows."""
    df.write.format("noop").mode("overwrite").save()


def plan_text(df: DataFrame) -> str:
    """The physical plan; of an adaptive one, the part before the initial plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return text.split("== Initial Plan ==")[0]


def plan_exchanges(df: DataFrame) -> int:
    """Shuffles in the physical plan; broadcasts don't count."""
    import re

    return len(re.findall(r"(?<!Broadcast)Exchange (?:hash|range|Round|Single|ShufflePartitionId|direct)", plan_text(df)))
