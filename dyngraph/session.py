"""Session for local work; on a cluster the session as given is used."""

from __future__ import annotations

from pyspark.sql import SparkSession


def get_spark(cores: int | str = "*", shuffle: int = 8, memory: str = "6g") -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("dyngraph")
        .config("spark.sql.shuffle.partitions", shuffle)
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .getOrCreate()
    )


def co_located(spark: SparkSession) -> None:
    """Lets joins and groupings reuse a layout by t alone, so that a convolution over a layout by t moves no row."""
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")
