"""Written intermediates in the folder that driver and executors share, and their release."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_OWN: dict[str, list[str]] = {}
_TABLES: dict[str, str] = {}
_BYTES: dict[str, int] = {}
_PEAK = [0]


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where that is unset, a folder in the warehouse, which executors share too, or of a one-process master its temporary folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not base and spark.sparkContext.master.split("[")[0] == "local":
        base = os.environ.setdefault("DYNGRAPH_TEST_SHARED", tempfile.mkdtemp(prefix="dyngraph-"))
    return (base or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/written").rstrip("/")


def _paths(spark: SparkSession) -> list[str]:
    return _OWN.setdefault(spark.sparkContext.applicationId, [])


def fresh_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    _paths(spark).append(path)
    return path


def written(df: DataFrame, tag: str, partition_by: list[str] | None = None, codec: str | None = None) -> DataFrame:
    """df written as Parquet and read again: cuts lineage, fixes the rows, survives lost executors. codec: the session's if none."""
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    was = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")  # the shuffle files of this write serve nothing later
    try:
        (df.write.partitionBy(*partition_by) if partition_by else df.write).parquet(path, compression=codec)
    finally:
        spark.conf.set(_CLEANUP, was)
    _weigh(spark, path)
    return spark.read.schema(df.schema).parquet(path)


def laid_out(df: DataFrame, tag: str, key: str, parts: int, partition_by: list[str] | None = None) -> DataFrame:
    """Like written, in `parts` buckets by key: joins and groupings by the key and more columns need no exchange when it is read."""
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    name = path.rsplit("/", 1)[-1].replace("-", "_")
    writer = df.repartition(parts, key).write.format("parquet").option("path", path).bucketBy(parts, key)
    (writer.partitionBy(*partition_by) if partition_by else writer).saveAsTable(name)
    _TABLES[path] = name
    _weigh(spark, path)
    return spark.table(name)


def stored_bytes(df: DataFrame) -> int:
    """Size of the files that a stored DataFrame reads."""
    jvm, conf = df.sparkSession.sparkContext._jvm, df.sparkSession.sparkContext._jsc.hadoopConfiguration()
    paths = [jvm.org.apache.hadoop.fs.Path(f) for f in df.inputFiles()]
    return sum(p.getFileSystem(conf).getFileStatus(p).getLen() for p in paths)


def _weigh(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    _BYTES[path] = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength()
    _PEAK[0] = max(_PEAK[0], sum(_BYTES.values()))


@contextmanager
def peak() -> Iterator[dict]:
    """Measures the most bytes of intermediates that stood at once inside, beyond those that stood before (key "bytes")."""
    base = _PEAK[0] = sum(_BYTES.values())
    out: dict = {}
    try:
        yield out
    finally:
        out["bytes"] = _PEAK[0] - base


def _delete(spark: SparkSession, paths: list[str]) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for path in paths:
        _BYTES.pop(path, None)
        if path in _TABLES:
            spark.sql(f"DROP TABLE IF EXISTS {_TABLES.pop(path)}")
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(conf).delete(p, True)


class Scope:
    """What was written since a scope began."""

    def __init__(self) -> None:
        self.kept: set[str] = set()

    def keep(self, df: DataFrame, tag: str | None = None) -> DataFrame:
        """df for use after the scope: the files that it reads stay; with a tag, it is written first, so that nothing else has to."""
        df = df if tag is None else written(df, tag)
        self.kept |= {part for f in df.inputFiles() for part in f.split("/")}
        return df


@contextmanager
def scope(spark: SparkSession) -> Iterator[Scope]:
    """Deletes at its end what was written inside and isn't kept; an outer scope takes over what is.

    Results that leave the scope must be kept or collected before.
    """
    own, inside = _paths(spark), Scope()
    before = set(own)
    try:
        yield inside
    finally:
        gone = [path for path in own if path not in before and path.rsplit("/", 1)[-1] not in inside.kept]
        _delete(spark, gone)
        dropped = set(gone)
        own[:] = [path for path in own if path not in dropped]


def release(spark: SparkSession) -> None:
    """Deletes what written() has left; call once results have been consumed."""
    own = _paths(spark)
    _delete(spark, own)
    own.clear()
