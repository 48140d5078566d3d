"""Scalar functions on arrays and sparse rows, and the functions that SQL users get."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_scale(a: Column, s) -> Column:
    return F.transform(a, lambda x: x * s)


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def vec_concat(a: Column, b: Column) -> Column:
    return F.concat(a, b)


def vec_relu(a: Column) -> Column:
    return F.transform(a, lambda x: F.greatest(x, F.lit(0.0)))


def vec_sigmoid(a: Column) -> Column:
    return F.transform(a, lambda x: 1 / (1 + F.exp(-x)))


def l2_norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double") * x))


def softmax(a: Column) -> Column:
    top = F.array_max(a)
    e = F.transform(a, lambda x: F.exp(x - top))
    total = F.aggregate(e, F.lit(0.0), lambda s, x: s + x)
    return F.transform(e, lambda x: x / total)


def argmax(a: Column) -> Column:
    return (F.array_position(a, F.array_max(a)) - 1).cast("long")


def mat_vec(a: Column, w: np.ndarray) -> Column:
    """The row vector a times w."""
    return F.array(*[sum((F.get(a, F.lit(i)) * float(w[i, j]) for i in range(w.shape[0])), F.lit(0.0)) for j in range(w.shape[1])])


def sparse_row(key: Column, value: Column) -> Column:
    """Aggregate: a map from neighbour to weight."""
    return F.map_from_entries(F.array_sort(F.collect_list(F.struct(key, value))))


def vec_sum(col: str, width: int) -> Column:
    """Aggregate: the sum of vectors, slot by slot, without exploding them."""
    return F.array(*[F.sum(F.get(col, F.lit(i)).cast("double")) for i in range(width)])


def outer_sum(a: list[str], b: list[str]) -> list[Column]:
    """Aggregates: the cells of the sum of outer products."""
    return [F.sum(F.col(x) * F.col(y)).alias(f"{x}_{y}") for x in a for y in b]


def vec_project(w: np.ndarray):
    """Arrow-batched function x -> x W for wide matrices."""

    @F.pandas_udf("array<double>")
    def run(x: pd.Series) -> pd.Series:
        return pd.Series(list(np.stack(x.to_numpy()) @ w)) if len(x) else x

    return run


def register(spark: SparkSession) -> None:
    """The SQL surface: functions vec_dot and softmax as SQL functions, table functions band and unroll_lstm."""
    from pyspark.sql.functions import udtf

    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_softmax(a ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> exp(x - array_max(a)) / aggregate(transform(a, y -> exp(y - array_max(a))), 0D, (s, y) -> s + y))")

    @udtf(returnType="k bigint, m double")
    class Band:
        def eval(self, t: int, w: int):
            for k in range(max(1, t - w + 1), t + 1):
                yield k, 1.0 / min(w, t)

    @udtf(returnType="t bigint, i int, j int, val double")
    class UnrollLstm:
        def eval(self, width: int, items: int, k: int, steps: int):
            from dyngraph.operators.recur import evolve_weights, weight_cell
            from dyngraph.schema import fixed_weights

            ws, _ = evolve_weights(fixed_weights(width, items, k), weight_cell(width), steps)
            for t, m in enumerate(ws, 1):
                for i in range(width):
                    for j in range(items):
                        yield t, i, j, float(m[i, j])

    spark.udtf.register("band", Band)
    spark.udtf.register("unroll_lstm", UnrollLstm)
    # table-valued smoothing for a view named edges
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION smooth_reach(t BIGINT, l INT, steps INT) RETURNS ARRAY<BIGINT> RETURN sequence(t, least(t + l - 1, CAST(steps AS BIGINT)))")
