"""The methods over streams of timestamped links: snapshots, smoothing, differences and recurrences as steps close."""

from __future__ import annotations

from typing import Any, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from dyngraph.storage import fresh_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
FLOW = "t long, src long, dst long"


def stream_events(spark: SparkSession, folder: str, name: str = "events.parquet", per_trigger: int = 1) -> DataFrame:
    """The events as a stream of files; ts becomes an instant, as watermarks ask for one."""
    rows = spark.readStream.schema(EVENTS).option("pathGlobFilter", name).option("maxFilesPerTrigger", per_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(df: DataFrame, tag: str, mode: str = "append", checkpoint: str | None = None, out: str | None = None) -> DataFrame:
    """Runs a streaming query over all that is there, into Parquet in the shared folder, and reads its rows.

    With the checkpoint and folder of an earlier run it goes on where that one ended.
    """
    spark = df.sparkSession
    out = out or fresh_path(spark, tag)
    q = df.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", checkpoint or fresh_path(spark, f"{tag}-log")).trigger(availableNow=True).start(out)
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def day_of(ts):
    return (F.datediff(ts.cast("date"), F.lit("2024-01-01").cast("date")) + 1).cast("long")


def tumbling_snapshots(events: DataFrame, src, dst) -> DataFrame:
    """(t, src, dst) distinct in each day, as the watermark passes it."""
    w = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), src.alias("src"), dst.alias("dst")).agg(F.count(F.lit(1)).alias("n"))
    return w.select(day_of(F.col("window.start")).alias("t"), "src", "dst", "n")


def sliding_edge_life(events: DataFrame, src, dst, span: int, steps: int) -> DataFrame:
    """Edge life online: distinct pairs by day, then counted over windows of `span` days that slide by one; t is the window's last day."""
    daily = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), src.alias("src"), dst.alias("dst")).agg(F.count(F.lit(1)).alias("n"))
    slid = daily.groupBy(F.window(F.window_time("window"), f"{span} days", "1 day").alias("w"), "src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w_sum"))
    t = day_of(F.col("w.end")) - 1
    return slid.select(t.alias("t"), "src", "dst", F.col("w_sum").alias("w")).where(F.col("t") <= steps)


def sliding_banded_mean(events: DataFrame, src, dst, span: int, steps: int) -> DataFrame:
    """Banded mean online: edge life over min(span, t), emitted as the watermark passes a window's last day."""
    life = sliding_edge_life(events, src, dst, span, steps)
    return life.withColumn("w", F.col("w") / F.least(F.lit(span).cast("long"), F.col("t")))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n): sessions of a user, closed by the watermark."""
    s = events.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.unix_micros("session_window.start").alias("start_us"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def interval_pairs(events: DataFrame, other: DataFrame, minutes: int = 10) -> DataFrame:
    """Stream-stream join: pairs of events of one user that lie at most some minutes apart."""
    a = events.withWatermark("ts", "1 hour").select(F.col("user_id").alias("u"), F.col("ts").alias("ts_a"), F.col("event_id").alias("a"))
    b = other.withWatermark("ts", "1 hour").select("user_id", F.col("ts").alias("ts_b"), F.col("event_id").alias("b"))
    return a.join(b, F.expr(f"u = user_id AND ts_b > ts_a AND ts_b <= ts_a + INTERVAL {minutes} MINUTES")).select("u", "a", "b")


class OnlineDifference(StatefulProcessor):
    """Per bucket of pairs: the last step seen of each pair, packed in one value, so that a bucket costs two calls of the state store.

    Emits (t, kind): an addition where a step has no forerunner, and the removal that follows a gap.
    """

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "pairs binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer) -> Iterator[pd.DataFrame]:
        known = np.frombuffer(self.last.get()[0], np.int64).reshape(-1, 3) if self.last.exists() else np.zeros((0, 3), np.int64)
        new = np.concatenate([pdf[["src", "dst", "t"]].to_numpy(np.int64) for pdf in rows])
        added, removed, known = differences(known, new)
        self.last.update((known.tobytes(),))
        if len(added) or len(removed):
            both = np.concatenate([added, removed])
            yield pd.DataFrame({"src": both[:, 0], "dst": both[:, 1], "t": both[:, 2], "kind": ["add"] * len(added) + ["del"] * len(removed)})

    def close(self) -> None:
        pass


def differences(known: np.ndarray, new: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(additions, removals, last steps) as rows (src, dst, t), from the last steps known before, one a pair, and new rows.

    A row whose step is not behind its pair's last one is late: the step is closed.
    """
    both = np.concatenate([known, new])
    old = np.arange(len(both)) < len(known)
    order = np.lexsort((~old, both[:, 2], both[:, 1], both[:, 0]))
    both, old = both[order], old[order]
    follows = np.zeros(len(both), bool)  # of the same pair as the row before
    follows[1:] = (both[1:, :2] == both[:-1, :2]).all(1)
    pair = np.cumsum(~follows) - 1
    closed = np.full(len(both), np.iinfo(np.int64).min)  # by pair
    closed[pair[old]] = both[old, 2]
    stay = old | (both[:, 2] > closed[pair])
    both, old, pair = both[stay], old[stay], pair[stay]
    follows = np.zeros(len(both), bool)
    follows[1:] = pair[1:] == pair[:-1]
    before = np.concatenate([both[:1, 2], both[:-1, 2]])
    gap = follows & (both[:, 2] > before + 1)
    removed = both[gap].copy()
    removed[:, 2] = before[gap] + 1
    return both[gap | ~(follows | old)], removed, both[np.append(~follows[1:], True)[: len(both)]]


def online_difference(flow: DataFrame, buckets: int = 1024) -> DataFrame:
    """(src, dst, t, kind) of a stream of (t, src, dst); needs the RocksDB state store."""
    keyed = flow.withColumn("bucket", F.pmod(F.xxhash64("src", "dst"), F.lit(buckets)))
    return keyed.groupBy("bucket").transformWithStateInPandas(OnlineDifference(), "src long, dst long, t long, kind string", "append", "None")


class OnlineLstm(StatefulProcessor):
    """Per vertex: the state after the last step; emits the state of each new step."""

    def __init__(self, params: dict, cols: list[str]):
        self.params, self.cols = params, cols
        self.hidden = len(params["wh"])

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("state", "t long, s array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer) -> Iterator[pd.DataFrame]:
        from dyngraph.operators.recur import lstm_forward

        pdf = pd.concat(list(rows)).sort_values("t")
        last, s = (self.state.get() if self.state.exists() else (0, [0.0] * (2 * self.hidden)))
        pdf = pdf[pdf["t"] > last]
        if not len(pdf):
            return
        s = np.array([s])
        out = lstm_forward(pdf[self.cols].to_numpy(float)[:, None], self.params, s[:, : self.hidden], s[:, self.hidden :])
        after = np.concatenate([out["h"], out["c"]], axis=2)[:, 0]
        self.state.update((int(pdf["t"].iloc[-1]), [float(x) for x in after[-1]]))
        frame = pd.DataFrame(after, columns=[f"h{i}" for i in range(self.hidden)] + [f"c{i}" for i in range(self.hidden)])
        frame.insert(0, "v", key[0])
        frame.insert(0, "t", pdf["t"].to_numpy())
        yield frame

    def close(self) -> None:
        pass


def online_lstm(frames: DataFrame, params: dict, cols: list[str]) -> DataFrame:
    """(t, v, h*, c*) of a stream of frames (t, v, x*), each step's frames not before those of the step before."""
    hidden = len(params["wh"])
    schema = "t long, v long, " + ", ".join(f"{s}{i} double" for s in "hc" for i in range(hidden))
    return frames.groupBy("v").transformWithStateInPandas(OnlineLstm(params, cols), schema, "append", "None")


def with_rocksdb(spark: SparkSession) -> Any:
    """The state store that arbitrary state needs; a setting of the session, not of its start."""
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    return spark


def score_batches(frames: DataFrame, score, tag: str) -> DataFrame:
    """foreachBatch: each micro-batch goes through the batch function `score` and is appended to the result."""
    spark = frames.sparkSession
    out = fresh_path(spark, tag)

    def run(batch: DataFrame, epoch: int) -> None:
        score(batch).write.mode("append").parquet(out)

    frames.writeStream.foreachBatch(run).option("checkpointLocation", fresh_path(spark, f"{tag}-log")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)
