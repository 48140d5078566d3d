"""Heads, losses, link samples and their measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.operators.convolve import times
from dyngraph.operators.snapshots import dense_rank, hash32
from dyngraph.schema import DynamicGraph, FeatureTensor


def argmax(cols: list[str]):
    """0-based number of the first largest column."""
    a = F.array(*cols)
    return (F.array_position(a, F.array_max(a)) - 1).cast("long")


def vertex_scores(z: FeatureTensor, u: np.ndarray) -> DataFrame:
    """(t, v, r0.., pred)."""
    r = [f"r{k}" for k in range(u.shape[1])]
    scored = z.df.select("t", "v", *[e.alias(n) for n, e in zip(r, times(z.cols, u))])
    return scored.withColumn("pred", argmax(r))


def edge_embedding(z: FeatureTensor, pairs: DataFrame) -> FeatureTensor:
    """pairs (t, u, v, ...) with both ends' frames side by side as e0.. - the pair's columns stay."""
    a = z.df.select("t", F.col("v").alias("u"), *[F.col(c).alias(f"e{i}") for i, c in enumerate(z.cols)])
    b = z.df.select("t", "v", *[F.col(c).alias(f"e{z.width + i}") for i, c in enumerate(z.cols)])
    return FeatureTensor(pairs.join(a, ["t", "u"]).join(b, ["t", "v"]), 2 * z.width, "e")


def link_scores(z: FeatureTensor, pairs: DataFrame, u: np.ndarray, bias: np.ndarray | None = None) -> DataFrame:
    """pairs with scores r0.. and pred."""
    e = edge_embedding(z, pairs)
    b = np.zeros(u.shape[1]) if bias is None else bias
    r = [f"r{k}" for k in range(u.shape[1])]
    scored = e.df.select(*pairs.columns, *e.cols, *[(x + float(b[k])).alias(r[k]) for k, x in enumerate(times(e.cols, u))])
    return scored.withColumn("pred", argmax(r))


def log_loss(r: list[str], y: str = "y"):
    """Cross-entropy of a row, with the largest score taken out first."""
    top = F.greatest(*r)
    return F.log(sum((F.exp(F.col(c) - top) for c in r), F.lit(0.0))) + top - F.get(F.array(*r), F.col(y).cast("int"))


def cross_entropy(scored: DataFrame, classes: int = 2) -> DataFrame:
    return scored.agg(F.avg(log_loss([f"r{k}" for k in range(classes)])).alias("loss"))


def accuracy(scored: DataFrame) -> DataFrame:
    """Per cent of right predictions."""
    return scored.agg((F.avg((F.col("pred") == F.col("y")).cast("double")) * 100).alias("accuracy"))


def confusion(scored: DataFrame) -> DataFrame:
    return scored.groupBy(F.col("y").cast("long").alias("y"), "pred").agg(F.count(F.lit(1)).alias("n"))


def classification_report(scored: DataFrame) -> DataFrame:
    """One row for class 1: precision, recall, F1, and the area under the ranking by score difference.

    The ranking works on counts by distinct score, cut into ranges, so that no task sorts all rows. The ranges are
    written before they are summed and ranked: planned twice, they could get different bounds.
    """
    from dyngraph.storage import written

    p = written(scored.select(F.col("y").cast("long").alias("y"), "pred", (F.col("r1") - F.col("r0")).alias("s")), "scored")  # read three times
    tp, fp, fn = (F.count_if(c) for c in ((F.col("y") == 1) & (F.col("pred") == 1), (F.col("y") == 0) & (F.col("pred") == 1), (F.col("y") == 1) & (F.col("pred") == 0)))
    base = p.agg(tp.alias("tp"), fp.alias("fp"), fn.alias("fn"), F.count_if(F.col("y") == 1).alias("pos"), F.count_if(F.col("y") == 0).alias("neg"))
    by = p.groupBy("s").agg(F.count_if(F.col("y") == 1).alias("p"), F.count_if(F.col("y") == 0).alias("n"))
    by = written(by.repartitionByRange(32, "s").withColumn("part", F.spark_partition_id()), "score-ranges")
    parts = by.groupBy("part").agg(F.min("s").alias("lo"), F.sum("n").alias("pn"))
    before = F.coalesce(F.sum("pn").over(Window.orderBy("lo").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    own = F.coalesce(F.sum("n").over(Window.partitionBy("part").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    wins = by.withColumn("own", own).join(F.broadcast(parts.select("part", before.alias("before"))), "part")
    wins = wins.agg(F.sum(F.col("p") * (F.col("own") + F.col("before") + F.col("n") / 2)).alias("wins"))
    precision, recall = F.col("tp") / F.nullif(F.col("tp") + F.col("fp"), F.lit(0)), F.col("tp") / F.nullif(F.col("tp") + F.col("fn"), F.lit(0))
    f1 = 2 * F.col("tp") / F.nullif(2 * F.col("tp") + F.col("fp") + F.col("fn"), F.lit(0))
    return base.crossJoin(wins).select(*[F.round(e, 6).alias(n) for e, n in ((precision, "precision"), (recall, "recall"), (f1, "f1"), (F.col("wins") / F.nullif(F.col("pos") * F.col("neg"), F.lit(0)), "auc"))])


def _pair_key(tag: str, seed: int, *cols: str):
    return F.concat_ws(":", F.lit(f"{tag}{seed}"), *[F.col(c).cast("string") for c in cols])


def sample_links(g: DynamicGraph, theta: float = 0.1, seed: int = 7, mode: str = "exact", reject_existing: bool = False) -> DataFrame:
    """(t, u, v, y): a share theta of each snapshot's pairs (y = 1) and as many random ones (y = 0), self pairs aside.

    exact: the ceil(theta * size) pairs of a step with the smallest hash, ranked by the hash in cells of its first
    digit. bernoulli: every pair by its own hash, without any rank: the mode for large snapshots. A random pair may be
    a true one, unless reject_existing. Random ends are drawn by vertex rank, from a table of vertices.
    """
    e = g.edges.where("src <> dst").select("t", F.col("src").alias("u"), F.col("dst").alias("v"), hash32(_pair_key("pos", seed, "t", "src", "dst")).alias("h"))
    if mode == "bernoulli":
        pos = e.where(F.col("h") < int(theta * (1 << 32)))
    else:
        cell = F.floor(F.col("h") / (1 << 28)).cast("int")
        e = e.withColumn("c", cell)
        sizes = e.groupBy("t", "c").agg(F.count(F.lit(1)).alias("n"))
        before = Window.partitionBy("t").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)
        sizes = sizes.select("t", "c", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"), F.sum("n").over(Window.partitionBy("t")).alias("all"))
        rank = F.row_number().over(Window.partitionBy("t", "c").orderBy("h", "u", "v")) + F.col("before")
        pos = e.join(sizes, ["t", "c"]).withColumn("rank", rank).where(F.col("rank") <= F.ceil(F.col("all") * theta))
    pos = pos.select("t", "u", "v", F.lit(1).cast("long").alias("y"))
    ids = dense_rank(g.vertices)
    n = g.vertices.count()
    want = pos.groupBy("t").agg(F.count(F.lit(1)).alias("m")).select("t", F.explode(F.sequence(F.lit(1).cast("long"), "m")).alias("k"))
    a = hash32(_pair_key("neg-u", seed, "t", "k")) % n
    # the other end is any of the n - 1 others
    b = (F.col("a") + 1 + hash32(_pair_key("neg-v", seed, "t", "k")) % max(n - 1, 1)) % n
    drawn = want.withColumn("a", a).withColumn("b", b)
    neg = drawn.join(ids.select(F.col("vid").alias("a"), F.col("v").alias("u")), "a").join(ids.select(F.col("vid").alias("b"), "v"), "b").select("t", "u", "v", F.lit(0).cast("long").alias("y"))
    if reject_existing:
        neg = neg.join(g.edges.select("t", F.col("src").alias("u"), F.col("dst").alias("v")), ["t", "u", "v"], "left_anti")
    return pos.unionByName(neg)


def link_dataset(g: DynamicGraph, theta: float = 0.1, seed: int = 7, **how) -> DataFrame:
    """(t, u, v, y, split): the last step is the test; its pairs are scored with the frames of the step before, so they carry that t."""
    rows = sample_links(g, theta, seed, **how)
    last = F.col("t") == g.T
    return rows.select(F.when(last, F.col("t") - 1).otherwise(F.col("t")).alias("t"), "u", "v", "y", F.when(last, "test").otherwise("train").alias("split"))


def next_step_active(g: DynamicGraph) -> DataFrame:
    """(t, v, y): whether a vertex has an edge in the next step, for t < T."""
    from dyngraph.operators.snapshots import degrees, grid

    busy = degrees(g).select((F.col("t") - 1).alias("t"), "v", F.lit(1).cast("long").alias("y"))
    return grid(g).where(F.col("t") < g.T).join(busy, ["t", "v"], "left").na.fill(0, ["y"])
