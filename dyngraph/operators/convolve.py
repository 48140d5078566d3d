"""Normalised Laplacians and graph convolution inside each snapshot."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dyngraph.operators.snapshots import grid, symmetrize
from dyngraph.schema import DynamicGraph, FeatureTensor


def laplacian(g: DynamicGraph, degree: str = "count", how: str = "union") -> DataFrame:
    """(t, src, dst, a): a = w / sqrt((1 + d_src)(1 + d_dst)) with the identity added, for every vertex of every snapshot.

    Degrees count neighbours other than the vertex itself, or sum their weights with degree="weight". They are
    gathered once and meet the edges twice by (t, vertex), so that a layout by t serves both.
    """
    s = symmetrize(g, how)
    e = s.edges.where("src <> dst")
    d = F.count(F.lit(1)).cast("double") if degree == "count" else F.sum("w")
    deg = e.groupBy("t", F.col("src").alias("v")).agg(d.alias("d"))
    deg = grid(g).join(deg, ["t", "v"], "left").select("t", "v", (1 + F.coalesce("d", F.lit(0.0))).alias("d"))
    own = s.edges.where("src = dst").select("t", F.col("src").alias("v"), "w")
    diagonal = deg.join(own, ["t", "v"], "left").select("t", F.col("v").alias("src"), F.col("v").alias("dst"), ((1 + F.coalesce("w", F.lit(0.0))) / F.col("d")).alias("a"))
    a, b = deg.select("t", F.col("v").alias("src"), F.col("d").alias("ds")), deg.select("t", F.col("v").alias("dst"), F.col("d").alias("dd"))
    off = e.join(a, ["t", "src"]).join(b, ["t", "dst"]).select("t", "src", "dst", (F.col("w") / F.sqrt(F.col("ds") * F.col("dd"))).alias("a"))
    return off.unionByName(diagonal)


def transposed(lap: DataFrame) -> DataFrame:
    return lap.select(*[c for c in lap.columns if c == "home"], "t", F.col("dst").alias("src"), F.col("src").alias("dst"), "a")


def aggregate_neighbors(lap: DataFrame, x: FeatureTensor, salts: int = 1) -> FeatureTensor:
    """Weighted sums of neighbour frames, the vertex itself included.

    salts > 1 adds up hub rows in two steps, so that a vertex with a large part of a snapshot's edges is spread. If both
    sides are laid out by home, which follows from t, the join and the sum stay inside it.
    """
    place = ["home", "t"] if "home" in lap.columns and "home" in x.df.columns else ["t"]
    lap = lap.select(*place, "src", "dst", "a")
    joined = lap.join(x.df.select(*place, F.col("v").alias("dst"), *x.cols), [*place, "dst"])
    sums = [F.sum(F.col("a") * F.col(c)).alias(c) for c in x.cols]
    if salts > 1:
        part = joined.groupBy(*place, "src", F.pmod("dst", F.lit(salts)).alias("_s")).agg(*sums)
        out = part.groupBy(*place, "src").agg(*[F.sum(c).alias(c) for c in x.cols])
    else:
        out = joined.groupBy(*place, "src").agg(*sums)
    return FeatureTensor(out.withColumnRenamed("src", "v"), x.width, x.name)


def times(cols: list[str], w: np.ndarray) -> list[Column]:
    """The row vector of cols times w, as expressions."""
    return [sum((F.col(c) * float(w[i, j]) for i, c in enumerate(cols)), F.lit(0.0)) for j in range(w.shape[1])]


def project(x: FeatureTensor, w: np.ndarray | dict[int, np.ndarray], out: str = "x") -> FeatureTensor:
    """Frames times a dense matrix; with a dict, times the matrix of the frame's own step.

    Small matrices are literals of the expression. Per-step ones come as one row a step, broadcast (T rows).
    """
    if not isinstance(w, dict):
        return FeatureTensor(x.df.select(*x.keys, *[e.alias(f"{out}{j}") for j, e in enumerate(times(x.cols, w))]), w.shape[1], out)
    wide = next(iter(w.values())).shape[1]
    rows = [(int(t), [float(z) for z in m.ravel()]) for t, m in w.items()]
    table = x.df.sparkSession.createDataFrame(rows, "t long, w array<double>")
    dot = [sum((F.col(c) * F.get("w", F.lit(i * wide + j)) for i, c in enumerate(x.cols)), F.lit(0.0)) for j in range(wide)]
    return FeatureTensor(x.df.join(F.broadcast(table), "t").select(*x.keys, *[e.alias(f"{out}{j}") for j, e in enumerate(dot)]), wide, out)


def activation(name: str):
    """Expression of an activation function."""
    return {
        "relu": lambda c: F.greatest(c, F.lit(0.0)),
        "sigmoid": lambda c: 1 / (1 + F.exp(-c)),
        "tanh": F.tanh,
        "identity": lambda c: c,
    }[name]


def activate(x: FeatureTensor, name: str) -> FeatureTensor:
    f = activation(name)
    return FeatureTensor(x.df.select(*x.keys, *[f(F.col(c)).alias(c) for c in x.cols]), x.width, x.name)


def gcn_layer(lap: DataFrame, x: FeatureTensor, w, act: str = "relu", precomputed: FeatureTensor | None = None) -> FeatureTensor:
    """activation(A X W). Projects first where that makes the frames narrower, unless A X is at hand."""
    if precomputed is not None:
        return activate(project(precomputed, w), act)
    narrow = not isinstance(w, dict) and w.shape[1] < w.shape[0]
    y = aggregate_neighbors(lap, project(x, w)) if narrow else project(aggregate_neighbors(lap, x), w)
    return activate(y, act)


def gcn_concat_layer(lap: DataFrame, x: FeatureTensor, w: np.ndarray, act: str = "relu", precomputed: FeatureTensor | None = None) -> FeatureTensor:
    """activation of A X and A X W side by side: the width grows by that of the input."""
    s = precomputed if precomputed is not None else aggregate_neighbors(lap, x)
    f = activation(act)
    cols = [F.col(c) for c in s.cols] + times(s.cols, w)
    return FeatureTensor(s.df.select("t", "v", *[f(c).alias(f"x{i}") for i, c in enumerate(cols)]), len(cols))


def precompute_first(lap: DataFrame, x: FeatureTensor) -> FeatureTensor:
    """A X of the first layer, which no parameter enters, written once for all epochs."""
    from dyngraph.storage import written

    s = aggregate_neighbors(lap, x)
    return FeatureTensor(written(s.df, "first-layer"), s.width, s.name)
