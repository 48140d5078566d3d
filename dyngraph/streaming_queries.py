"""Streaming queries run over the events with AvailableNow; their twins are the batch forms, on the steps that close."""

from __future__ import annotations

from pyspark.sql import functions as F

from dyngraph import oracles as O
from dyngraph.catalog import N, _scaled, query, r6
from dyngraph.operators import recur, snapshots
from dyngraph.sources import tables
from dyngraph.storage import fresh_path
from dyngraph.streaming import online



def pair():
    """User and a small bucket of the value: pairs that come back."""
    return F.col("user_id"), F.col("value").cast("long") % 10


_E = f"ev AS (SELECT {O.DAY} AS t, user_id AS src, CAST(trunc(value) AS BIGINT) % 10 AS dst, ts, event_id FROM events)"


def _closed(rows: str, extra: str = "") -> str:
    # the watermark ends an hour before the newest event: days whose end lies behind it are out
    return f"WITH {_E} {extra} SELECT * FROM ({rows}) WHERE t <= (SELECT date_diff('day', DATE '2024-01-01', CAST(max(ts) - INTERVAL 1 HOUR AS DATE)) FROM events)"


@query("st_tumbling_snapshot", _closed("SELECT t, src, dst, count(*) AS n FROM ev GROUP BY ALL"))
def st_tumbling_snapshot(spark, sf):
    return online.drain(online.tumbling_snapshots(online.stream_events(spark, sf), *pair()), "tumbling")


@query("st_sliding_edge_life", _closed("SELECT CAST(t + k AS BIGINT) AS t, src, dst, CAST(count(*) AS DOUBLE) AS w FROM (SELECT DISTINCT t, src, dst FROM ev), range(0, 3) r(k) WHERE t + k <= 30 GROUP BY ALL"))
def st_sliding_edge_life(spark, sf):
    return online.drain(online.sliding_edge_life(online.stream_events(spark, sf), *pair(), 3, 30), "sliding")


@query("st_banded_mean", _closed("SELECT CAST(t + k AS BIGINT) AS t, src, dst, round(count(*) / least(3, CAST(t + k AS BIGINT)), 6) AS w FROM (SELECT DISTINCT t, src, dst FROM ev), range(0, 3) r(k) WHERE t + k <= 30 GROUP BY CAST(t + k AS BIGINT), t + k, src, dst"))
def st_banded_mean(spark, sf):
    return r6(online.drain(online.sliding_banded_mean(online.stream_events(spark, sf), *pair(), 3, 30), "banded"), ["w"], ("t", "src", "dst"))


@query("st_session", "SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM (SELECT *, sum(CASE WHEN gap IS NULL OR gap > 1800000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT user_id, ts, event_id, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap FROM events)) GROUP BY user_id, s HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def st_session(spark, sf):
    return online.drain(online.sessions(online.stream_events(spark, sf)), "sessions")


@query("st_dedupe", "SELECT DISTINCT event_id, user_id FROM events")
def st_dedupe(spark, sf):
    ev = online.stream_events(spark, sf)
    return online.drain(online.deduplicated(ev.unionByName(online.stream_events(spark, sf))), "dedupe")


@query("st_stream_static", "SELECT event_id, CAST(user_id % 25 AS INTEGER) AS n_nationkey, n_name FROM events JOIN nation ON n_nationkey = user_id % 25")
def st_stream_static(spark, sf):
    nation = tables.load(spark, sf, "nation").select("n_nationkey", "n_name")
    ev = online.stream_events(spark, sf).select("event_id", (F.col("user_id") % 25).cast("int").alias("n_nationkey"))
    return online.drain(ev.join(F.broadcast(nation), "n_nationkey"), "static").select("event_id", "n_nationkey", "n_name")


@query("st_interval_join", "SELECT a.user_id AS u, a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def st_interval_join(spark, sf):
    return online.drain(online.interval_pairs(online.stream_events(spark, sf), online.stream_events(spark, sf)), "interval")


@query("st_online_diff", O.sql(O.graph("user_flow")[0], final="SELECT src, dst, t, 'add' AS kind FROM e a WHERE NOT EXISTS (SELECT 1 FROM e b WHERE b.t = a.t - 1 AND b.src = a.src AND b.dst = a.dst) UNION ALL SELECT src, dst, t + 1, 'del' FROM e a WHERE NOT EXISTS (SELECT 1 FROM e b WHERE b.t = a.t + 1 AND b.src = a.src AND b.dst = a.dst) AND EXISTS (SELECT 1 FROM e b WHERE b.t > a.t AND b.src = a.src AND b.dst = a.dst)"))
def st_online_diff(spark, sf):
    """Differences of the user graph from a stream of its links; the last removal of a pair is not known to a stream yet."""
    online.with_rocksdb(spark)
    folder = fresh_path(spark, "flow")
    tables.graph(spark, sf, "user_flow").edges.select("t", "src", "dst").write.parquet(folder)
    flow = spark.readStream.schema(online.FLOW).parquet(folder)
    return online.drain(online.online_difference(flow), "difference")


_ST = ["h0", "h1", "c0", "c1"]


@query("st_online_lstm", O.sql(*O.graph(N), "xs AS (SELECT t, v, x0 / 10.0::DOUBLE AS x0, x1 / 10.0::DOUBLE AS x1 FROM x)", O.lstm("xs", recur.lstm_params(2, 2), "r"), final=O.rounded(_ST) + " FROM r WHERE t > 0"))
def st_online_lstm(spark, sf):
    """States of every vertex from frames that arrive in two parts; the second run goes on from the first one's checkpoint."""
    online.with_rocksdb(spark)
    folder, log, out = (fresh_path(spark, tag) for tag in ("frames", "lstm-log", "lstm"))
    x = _scaled(snapshots.degree_features(tables.graph(spark, sf, N)))
    for lo, hi in ((1, 40), (41, 80)):
        x.df.where(F.col("t").between(lo, hi)).write.mode("append").parquet(folder)
        frames = spark.readStream.schema("t long, v long, x0 double, x1 double").parquet(folder)
        states = online.drain(online.online_lstm(frames, recur.lstm_params(2, 2), x.cols), "lstm", checkpoint=log, out=out)
    return r6(states, _ST)


@query("st_foreach_batch", "SELECT event_id, round(value * 2, 6) AS twice FROM events")
def st_foreach_batch(spark, sf):
    return online.score_batches(online.stream_events(spark, sf), lambda b: b.select("event_id", F.round(F.col("value") * 2, 6).alias("twice")), "scored")
