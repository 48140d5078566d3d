"""Building snapshots, vertex sets and degree features."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.schema import DynamicGraph, FeatureTensor
from dyngraph.storage import written


def build_snapshots(links: DataFrame, agg: str = "distinct") -> DataFrame:
    """Edges (t, src, dst, w), one a step and pair. agg: distinct (weight 1), sum of w, or count."""
    value = {"distinct": F.lit(1.0), "sum": F.sum("w"), "count": F.count(F.lit(1)).cast("double")}[agg]
    rows = links.where("t is not null and src is not null and dst is not null").select(*[F.col(c).cast("long") for c in ("t", "src", "dst")], *(["w"] if agg == "sum" else []))
    if agg == "distinct":
        return rows.select("t", "src", "dst").distinct().withColumn("w", value)
    return rows.groupBy("t", "src", "dst").agg(value.alias("w"))


def snapshots_from_changes(changes: DataFrame, steps: int) -> DataFrame:
    """Edges as the graph stood at the end of each step, from changes (t, src, dst, op), op in ins, del.

    A pair with both in one step counts as inserted there; an edge stays from its insertion to the step before its
    deletion.
    """
    last = changes.groupBy("t", "src", "dst").agg(F.max("op").alias("op"))
    w = Window.partitionBy("src", "dst").orderBy("t")
    spans = last.withColumn("until", F.coalesce(F.lead("t").over(w) - 1, F.lit(steps).cast("long"))).where("op = 'ins' and until >= t")
    return spans.select(F.explode(F.sequence("t", "until")).alias("t"), "src", "dst", F.lit(1.0).alias("w"))


def vertex_index(edges: DataFrame) -> DataFrame:
    """(v) of all endpoints over all steps."""
    return edges.select(F.col("src").alias("v")).union(edges.select("dst")).distinct()


def dense_rank(vertices: DataFrame, parts: int = 64) -> DataFrame:
    """(v, vid): 0-based rank in id order. Ranges are ranked apart and shifted by the sizes of the ranges before.

    The ranges are written before they are counted and ranked: planned twice, they could get different bounds.
    """
    ranged = written(vertices.repartitionByRange(parts, "v").withColumn("_p", F.spark_partition_id()), "ranges")
    bounds = ranged.groupBy("_p").agg(F.min("v").alias("lo"), F.count(F.lit(1)).alias("n"))
    shift = bounds.withColumn("shift", F.coalesce(F.sum("n").over(Window.orderBy("lo").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("_p", "shift")
    own = Window.partitionBy("_p").orderBy("v")
    return ranged.withColumn("r", F.row_number().over(own) - 1).join(F.broadcast(shift), "_p").select("v", (F.col("r") + F.col("shift")).alias("vid"))


def symmetrize(g: DynamicGraph, how: str = "union") -> DynamicGraph:
    """how="union": each edge both ways with the larger weight; "none": as it is."""
    if how == "none":
        return g
    e = g.edges
    both = e.unionByName(e.select("t", F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return g.with_edges(both.groupBy("t", "src", "dst").agg(F.max("w").alias("w")))


def degrees(g: DynamicGraph, kind: str = "all") -> DataFrame:
    """(t, v, deg) of vertices with an edge. in, out: distinct neighbours that way; all: distinct neighbours either way."""
    e = g.edges
    if kind == "in":
        return e.groupBy("t", F.col("dst").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    if kind == "out":
        return e.groupBy("t", F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    return degrees(symmetrize(g), "out")


def grid(g: DynamicGraph) -> DataFrame:
    """(t, v) of every vertex in every snapshot: the steps are unrolled from an array, so nothing is joined."""
    return g.vertices.select(F.explode(F.sequence(F.lit(1).cast("long"), F.lit(g.T).cast("long"))).alias("t"), "v")


def degree_features(g: DynamicGraph) -> FeatureTensor:
    """Frames [in-degree, out-degree]; zeros for vertices without edges in a snapshot."""
    ends = g.edges.select("t", F.explode(F.array(F.struct(F.col("dst").alias("v"), F.lit(1).alias("i"), F.lit(0).alias("o")), F.struct(F.col("src").alias("v"), F.lit(0).alias("i"), F.lit(1).alias("o")))).alias("r")).select("t", "r.*")
    both = ends.unionByName(grid(g).select("t", "v", F.lit(0).alias("i"), F.lit(0).alias("o")))
    return FeatureTensor(both.groupBy("t", "v").agg(F.sum("i").cast("double").alias("x0"), F.sum("o").cast("double").alias("x1")), 2)


def static_features(g: DynamicGraph, table: DataFrame, key: str, vector: str, width: int) -> FeatureTensor:
    """The vectors of a table in every frame; zeros for vertices without one."""
    cols = [F.coalesce(F.get(F.col(vector), i).cast("double"), F.lit(0.0)).alias(f"x{i}") for i in range(width)]
    by_v = g.vertices.join(table.select(F.col(key).alias("v"), vector), "v", "left").select("v", *cols)
    return FeatureTensor(by_v.select(F.explode(F.sequence(F.lit(1).cast("long"), F.lit(g.T).cast("long"))).alias("t"), "v", *[f"x{i}" for i in range(width)]), width)


def hash32(text):
    """The first 32 bits of the MD5 of a string: the same numbers in other engines."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def random_gnm(spark: SparkSession, steps: int, n: int, f: int, seed: int = 1) -> DynamicGraph:
    """Independent snapshots of n * f random pairs over n vertices (repeats fall together), from hashes of the counter."""
    rows = spark.range(steps * n * f).select((F.floor(F.col("id") / (n * f)) + 1).cast("long").alias("t"), "id")
    return DynamicGraph(random_pairs(rows, n, seed), spark.range(n).select(F.col("id").alias("v")), steps)


def random_pairs(rows: DataFrame, n: int, seed: int = 1) -> DataFrame:
    """Edges between n vertices, one for each row (t, id), from hashes of the id; repeats fall together."""
    end = lambda s: hash32(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"), F.lit(s))) % n
    return rows.select("t", end("s").alias("src"), end("d").alias("dst")).distinct().withColumn("w", F.lit(1.0))


def planted_communities(spark: SparkSession, steps: int = 20, n: int = 60, f: int = 4, seed: int = 5) -> DynamicGraph:
    """Two communities (even and odd ids): nine of ten links stay inside; shows that training learns."""
    g = random_gnm(spark, steps, n, f, seed)
    inside = hash32(F.concat_ws("-", F.lit(f"c{seed}"), F.col("t").cast("string"), F.col("src").cast("string"), F.col("dst").cast("string"))) % 10 < 9
    moved = F.when(inside & ((F.col("src") + F.col("dst")) % 2 == 1), (F.col("dst") + 1) % n).otherwise(F.col("dst"))
    return g.with_edges(g.edges.select("t", "src", moved.alias("dst")).where("src <> dst").distinct().withColumn("w", F.lit(1.0)))


def graph_stats(g: DynamicGraph) -> DataFrame:
    """One row: vertices, steps, non-zeros."""
    nnz = g.edges.agg(F.count(F.lit(1)).alias("nnz"))
    return g.vertices.agg(F.count(F.lit(1)).alias("n")).crossJoin(nnz).select("n", F.lit(g.T).cast("long").alias("steps"), "nnz")


def overlap(g: DynamicGraph) -> DataFrame:
    """For consecutive snapshots t, t + 1: pairs in both, leaving and entering ones, and their Jaccard index."""
    w = Window.partitionBy("src", "dst").orderBy("t")
    e = g.edges.select("t", F.coalesce(F.lead("t").over(w) == F.col("t") + 1, F.lit(False)).alias("stays"), F.coalesce(F.lag("t").over(w) == F.col("t") - 1, F.lit(False)).alias("came"))
    per = e.groupBy("t").agg(F.count(F.lit(1)).alias("nnz"), F.sum(F.col("stays").cast("long")).alias("stay"), F.sum((~F.col("came")).cast("long")).alias("enter"))
    steps = g.spark.range(1, g.T).select(F.col("id").alias("t"))
    nxt = per.select((F.col("t") - 1).alias("t"), F.col("enter").alias("ext_next"))
    out = steps.join(per, "t", "left").join(nxt, "t", "left").na.fill(0)
    ext_prev = F.col("nnz") - F.col("stay")
    total = F.col("stay") + ext_prev + F.col("ext_next")
    return out.select("t", F.col("stay").alias("common"), ext_prev.alias("ext_prev"), "ext_next", F.when(total > 0, F.round(F.col("stay") / total, 6)).alias("jaccard"))
