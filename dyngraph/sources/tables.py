"""The given tables, and the dynamic graphs that they hold."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.operators.snapshots import build_snapshots, vertex_index
from dyngraph.schema import DynamicGraph

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
OFFSET = 1_000_000  # right-hand ids of two-sided graphs
MONTHS, SHIP_MONTHS, DAYS = 80, 83, 30


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str) -> None:
    """Each given table as a temporary view, for the SQL route."""
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def month(ts):
    """1-based month since January 1995."""
    return ((F.year(ts) - 1995) * 12 + F.month(ts)).cast("long")


def day(ts):
    """1-based day since 1 January 2024."""
    return (F.datediff(ts.cast("date"), F.lit("2024-01-01").cast("date")) + 1).cast("long")


def trades(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with the month of the order and of shipping."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", month(F.col("o_orderdate")).alias("t"))
    line = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_extendedprice", month(F.col("l_shipdate")).alias("ship_t"))
    return line.join(o, line["l_orderkey"] == o["o_orderkey"])


def events_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(t, src, dst): user of an event, user of the next one in (ts, event_id) order, by the day of the first.

    The next event is looked up inside its day; the last event of a day meets the first of the next day that has any,
    so that no window spans the whole stream (the table of days has one row a day).
    """
    ev = load(spark, sf_dir, "events").select(day(F.col("ts")).alias("t"), "ts", "event_id", "user_id")
    inside = Window.partitionBy("t").orderBy("ts", "event_id")
    ev = ev.withColumn("next", F.lead("user_id").over(inside)).withColumn("last", F.lead("event_id").over(inside).isNull())
    days = ev.groupBy("t").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    days = days.withColumn("follow", F.lead("first").over(Window.orderBy("t"))).select("t", "follow")
    ev = ev.join(F.broadcast(days), "t").withColumn("next", F.when(F.col("last"), F.col("follow")).otherwise(F.col("next")))
    return ev.where("next is not null and next <> user_id").select("t", F.col("user_id").alias("src"), F.col("next").alias("dst"))


def links(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, int]:
    """Timestamped links (t, src, dst, w) of a graph, before bucketing, and its number of steps."""
    one = F.lit(1.0).alias("w")
    if name == "user_flow":
        return events_flow(spark, sf_dir).withColumn("w", F.lit(1.0)), DAYS
    base = trades(spark, sf_dir)
    if name == "nation_trade":
        c = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("src"))
        s = load(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("dst"))
        return base.join(c, base["o_custkey"] == c["c_custkey"]).join(s, base["l_suppkey"] == s["s_suppkey"]).select("t", "src", "dst", one), MONTHS
    if name == "cust_supp":
        return base.select("t", F.col("o_custkey").alias("src"), (F.col("l_suppkey") + OFFSET).alias("dst"), one), MONTHS
    if name == "cust_part":
        return base.select("t", F.col("o_custkey").alias("src"), (F.col("l_partkey") + OFFSET).alias("dst"), one), MONTHS
    if name == "supp_part":
        line = load(spark, sf_dir, "lineitem")
        return line.select(month(F.col("l_shipdate")).alias("t"), F.col("l_suppkey").alias("src"), (F.col("l_partkey") + OFFSET).alias("dst"), one), SHIP_MONTHS
    if name == "cust_supp_amount":
        return base.select("t", F.col("o_custkey").alias("src"), (F.col("l_suppkey") + OFFSET).alias("dst"), F.col("l_extendedprice").alias("w")), MONTHS
    raise KeyError(name)


def graph(spark: SparkSession, sf_dir: str, name: str, agg: str = "distinct") -> DynamicGraph:
    """One of the graphs nation_trade, cust_supp, cust_part, supp_part, user_flow; rows with a null endpoint or step go."""
    rows, steps = links(spark, sf_dir, name)
    edges = build_snapshots(rows, agg=agg).where(F.col("t").between(1, steps))
    return DynamicGraph(edges, vertex_index(edges), steps)
