"""Registry of the queries of the graph engine, each with its DuckDB twin where SQL can express it."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph import oracles as O
from dyngraph.operators import blocks, convolve, delta, measures, partition, recur, smooth, snapshots, tasks, training
from dyngraph.schema import Config, DynamicGraph, FeatureTensor, fixed_weights
from dyngraph.sources import tables
from dyngraph.storage import written

_QUERIES: dict = {}
_SQL: dict[str, str] = {}
N, T = "nation_trade", 80
HIDDEN, SPAN = 2, 3


def query(name: str, sql: str | None = None):
    def add(fn):
        _QUERIES[name] = fn
        if sql is not None:
            _SQL[name] = sql
        return fn

    return add


def queries():
    from dyngraph import relational, streaming_queries, workloads  # noqa: F401  they register themselves

    return dict(_QUERIES)


def oracle_sql():
    queries()
    return dict(_SQL)


def r6(df, cols, keys=("t", "v")):
    return df.select(*keys, *[(F.round(c, 6) + 0.0).alias(c) for c in cols])


def graph_of(name):
    return lambda spark, sf: tables.graph(spark, sf, name)


def months(spark, sf):
    """(t) of each month with orders."""
    return tables.load(spark, sf, "orders").select(tables.month(F.col("o_orderdate")).alias("t")).where("t is not null").distinct()


def last_month(spark, sf) -> int:
    """Number of steps of the timeline of the orders."""
    return months(spark, sf).agg(F.max("t")).first()[0] or 0


_MONTHS = f"(SELECT DISTINCT t FROM (SELECT {O.month('o_orderdate')} AS t FROM orders) WHERE t IS NOT NULL)"
_LAST = f"(SELECT max({O.month('o_orderdate')}) AS n FROM orders)"


# ---- snapshots ------------------------------------------------------------------------------------------------------

for _g in O.STEPS:
    query(f"snap_{_g}", O.sql(*O.graph(_g)[:1], final="SELECT t, src, dst, w FROM e"))(lambda spark, sf, g=_g: tables.graph(spark, sf, g).edges)
    query(f"graph_stats_{_g}", O.sql(*O.graph(_g)[:2], final=f"SELECT (SELECT count(*) FROM v) AS n, CAST({O.STEPS[_g]} AS BIGINT) AS steps, (SELECT count(*) FROM e) AS nnz"))(lambda spark, sf, g=_g: snapshots.graph_stats(tables.graph(spark, sf, g)))
    _overlap = """
, d AS (SELECT t, src, dst, lead(t) OVER (PARTITION BY src, dst ORDER BY t) = t + 1 AS stays, lag(t) OVER (PARTITION BY src, dst ORDER BY t) = t - 1 AS came FROM e),
p AS (SELECT t, count(*) AS nnz, count(*) FILTER (stays) AS stay, count(*) FILTER (coalesce(NOT came, true)) AS enter FROM d GROUP BY t),
q AS (SELECT CAST(r.t AS BIGINT) AS t, coalesce(a.stay, 0) AS common, coalesce(a.nnz - a.stay, 0) AS ext_prev, coalesce(b.enter, 0) AS ext_next FROM range(1, {steps}) r(t) LEFT JOIN p a ON a.t = r.t LEFT JOIN p b ON b.t = r.t + 1)
SELECT *, CASE WHEN common + ext_prev + ext_next > 0 THEN round(common / (common + ext_prev + ext_next), 6) END AS jaccard FROM q"""
    query(f"overlap_{_g}", "WITH " + O.graph(_g)[0] + _overlap.replace("{steps}", str(O.STEPS[_g])))(lambda spark, sf, g=_g: snapshots.overlap(tables.graph(spark, sf, g)))


@query("snap_weighted_amount", f"SELECT {O.month('o_orderdate')} AS t, o_custkey AS src, l_suppkey + 1000000 AS dst, round(sum(l_extendedprice), 4) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
def snap_weighted_amount(spark, sf):
    rows, _ = tables.links(spark, sf, "cust_supp_amount")
    return snapshots.build_snapshots(rows, "sum").withColumn("w", F.round("w", 4))


@query("snap_counted", f"SELECT {O.month('o_orderdate')} AS t, o_custkey AS src, l_suppkey + 1000000 AS dst, CAST(count(*) AS DOUBLE) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
def snap_counted(spark, sf):
    return snapshots.build_snapshots(tables.links(spark, sf, "cust_supp")[0], "count")


def changes(spark, sf):
    """A change log from events: a pair of users is inserted by an event of even id and deleted by one of odd id."""
    ev = tables.load(spark, sf, "events")
    return ev.select(tables.day(F.col("ts")).alias("t"), (F.col("user_id") % 15).alias("src"), (F.col("event_id") % 7).alias("dst"), F.when(F.col("event_id") % 2 == 0, "ins").otherwise("del").alias("op"))


@query(
    "snap_from_changes",
    f"""WITH c AS (SELECT {O.DAY} AS t, user_id % 15 AS src, event_id % 7 AS dst, max(CASE WHEN event_id % 2 = 0 THEN 'ins' ELSE 'del' END) AS op FROM events GROUP BY ALL),
n AS (SELECT *, coalesce(lead(t) OVER (PARTITION BY src, dst ORDER BY t) - 1, 30) AS until FROM c)
SELECT CAST(unnest(range(t, until + 1)) AS BIGINT) AS t, src, dst, CAST(1 AS DOUBLE) AS w FROM n WHERE op = 'ins' AND until >= t""",
)
def snap_from_changes(spark, sf):
    return snapshots.snapshots_from_changes(changes(spark, sf), 30)


@query("vertex_index", O.sql(*O.graph("cust_supp")[:2], final="SELECT v, row_number() OVER (ORDER BY v) - 1 AS vid FROM v"))
def vertex_index(spark, sf):
    return snapshots.dense_rank(tables.graph(spark, sf, "cust_supp").vertices)


@query("symmetrized_edges", O.sql(*O.graph(N)[:1], final="SELECT t, src, dst, max(w) AS w FROM (SELECT t, src, dst, w FROM e UNION ALL SELECT t, dst, src, w FROM e) GROUP BY ALL"))
def symmetrized_edges(spark, sf):
    return snapshots.symmetrize(tables.graph(spark, sf, N)).edges


for _k, _s in (("in", "SELECT t, dst AS v, count(*) AS deg FROM e GROUP BY ALL"), ("out", "SELECT t, src AS v, count(*) AS deg FROM e GROUP BY ALL"), ("all", "SELECT t, v, count(DISTINCT u) AS deg FROM (SELECT t, src AS v, dst AS u FROM e UNION ALL SELECT t, dst, src FROM e) GROUP BY ALL")):
    query(f"degrees_{_k}", O.sql(*O.graph("cust_supp")[:1], final=_s))(lambda spark, sf, k=_k: snapshots.degrees(tables.graph(spark, sf, "cust_supp"), k))


@query("degree_features_grid", O.sql(*O.graph("user_flow"), final="SELECT * FROM x"))
def degree_features_grid(spark, sf):
    return snapshots.degree_features(tables.graph(spark, sf, "user_flow")).df


@query("static_features", O.sql(*O.graph("user_flow")[:3], final="SELECT g.t, g.v, round(coalesce(CAST(embedding[1] AS DOUBLE), 0), 6) + 0.0 AS x0, round(coalesce(CAST(embedding[2] AS DOUBLE), 0), 6) + 0.0 AS x1 FROM g LEFT JOIN embeddings ON vec_id = v"))
def static_features(spark, sf):
    g = tables.graph(spark, sf, "user_flow")
    x = snapshots.static_features(g, tables.load(spark, sf, "embeddings"), "vec_id", "embedding", 2)
    return r6(x.df, x.cols)


_GNM = f"""SELECT DISTINCT CAST(i // 300 + 1 AS BIGINT) AS t, {O.hash32("'1:' || CAST(i AS VARCHAR) || ':s'")} % 100 AS src, {O.hash32("'1:' || CAST(i AS VARCHAR) || ':d'")} % 100 AS dst, CAST(1 AS DOUBLE) AS w FROM range(6000) r(i)"""
_GNM_ORDERS = f"""SELECT DISTINCT {O.month('o_orderdate')} AS t, {O.hash32("'1:' || CAST(o_orderkey AS VARCHAR) || ':s'")} % 100 AS src, {O.hash32("'1:' || CAST(o_orderkey AS VARCHAR) || ':d'")} % 100 AS dst, CAST(1 AS DOUBLE) AS w FROM orders WHERE o_orderdate IS NOT NULL AND o_orderkey IS NOT NULL"""


@query("random_gnm_small", _GNM_ORDERS)
def random_gnm_small(spark, sf):
    """As many random pairs a month as it has orders, from hashes of their keys."""
    o = tables.load(spark, sf, "orders").select(tables.month(F.col("o_orderdate")).alias("t"), F.col("o_orderkey").alias("id")).dropna()
    return snapshots.random_pairs(o, 100)



query("random_gnm_stats", f"SELECT t, count(*) AS nnz, count(DISTINCT src) AS sources FROM ({_GNM}) GROUP BY t")(lambda spark, sf: snapshots.random_gnm(spark, 20, 100, 3).edges.groupBy("t").agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("src").alias("sources")))


@query("random_gnm_source", _GNM)
def random_gnm_source(spark, sf):
    from dyngraph.sources.random_source import RandomGraphSource

    spark.dataSource.register(RandomGraphSource)
    return spark.read.format("random_gnm").options(steps=20, n=100, f=3, seed=1, parts=4).load().distinct()


# ---- smoothing ------------------------------------------------------------------------------------------------------

for _l in (1, 3, 6):
    query(f"edge_life_{_l}", O.sql(O.graph(N)[0], O.life(_l, T), final="SELECT t, src, dst, w FROM el"))(lambda spark, sf, n=_l: smooth.edge_life(tables.graph(spark, sf, N), n).edges)
for _l in (3, 6):
    query(f"m_edges_{_l}", O.sql(O.graph(N)[0], O.life(_l, T, mean=True), final="SELECT t, src, dst, round(w, 6) AS w FROM el"))(lambda spark, sf, n=_l: smooth.m_transform_edges(tables.graph(spark, sf, N), n).edges.withColumn("w", F.round("w", 6)))


@query("m_features_3", O.sql(*O.graph(N), O.mean(3, 2, "x", "m"), final=O.rounded(["x0", "x1"]) + " FROM m"))
def m_features_3(spark, sf):
    return r6(smooth.m_transform_features(snapshots.degree_features(tables.graph(spark, sf, N)), 3).df, ["x0", "x1"])


_BAND = f"SELECT t, CAST(unnest(range(greatest(1, t - 3), t + 1)) AS BIGINT) AS k, CAST(1 AS DOUBLE) / least(4, t) AS m FROM {_MONTHS}"
query("band_matrix", _BAND)(lambda spark, sf: smooth.band_of(months(spark, sf), 4))


@query("mode1_product", O.sql(*O.graph(N), O.mean(4, 2, "x", "m"), final=O.rounded(["x0", "x1"]) + " FROM m"))
def mode1_product(spark, sf):
    """The banded mean as a product with the band matrix; its twin is the window form."""
    x = smooth.mode1_product(snapshots.degree_features(tables.graph(spark, sf, N)), smooth.band_matrix(spark, T, 4))
    return r6(x.df, x.cols)


for _g in O.STEPS:
    query(f"smoothing_growth_{_g}", O.sql(O.graph(_g)[0], O.life(3, O.STEPS[_g]), final="SELECT CAST(3 AS BIGINT) AS span, (SELECT count(*) FROM e) AS nnz, (SELECT count(*) FROM el) AS nnz_smoothed, round((SELECT count(*) FROM el) / (SELECT count(*) FROM e), 6) AS growth"))(lambda spark, sf, g=_g: smooth.smoothing_growth(tables.graph(spark, sf, g), 3))


@query("smooth_runs_roundtrip", O.sql(O.graph(N)[0], O.life(3, T), final="SELECT t, src, dst, w FROM el"))
def smooth_runs_roundtrip(spark, sf):
    return smooth.expand_runs(smooth.compress_runs(smooth.edge_life(tables.graph(spark, sf, N), 3).edges)).select("t", "src", "dst", "w")


# ---- convolution ----------------------------------------------------------------------------------------------------

for _d in ("count", "weight"):
    query(f"laplacian_{_d}", O.sql(*O.graph(N), O.life(3, T), *O.laplacian("el", _d), final="SELECT t, src, dst, round(a, 6) AS a FROM la"))(lambda spark, sf, d=_d: convolve.laplacian(smooth.edge_life(tables.graph(spark, sf, N), 3), d).withColumn("a", F.round("a", 6)))


@query("laplacian_rowsum", O.sql(*O.graph(N), *O.laplacian(), final="SELECT t, src AS v, round(sum(a), 6) AS s FROM la GROUP BY ALL"))
def laplacian_rowsum(spark, sf):
    return convolve.laplacian(tables.graph(spark, sf, N)).groupBy("t", F.col("src").alias("v")).agg(F.round(F.sum("a"), 6).alias("s"))


def _base(spark, sf, name=N):
    g = tables.graph(spark, sf, name)
    return g, convolve.laplacian(g), snapshots.degree_features(g)


@query("gcn_aggregate", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), final=O.rounded(["x0", "x1"]) + " FROM s"))
def gcn_aggregate(spark, sf):
    _, lap, x = _base(spark, sf)
    return r6(convolve.aggregate_neighbors(lap, x).df, ["x0", "x1"])


@query("gcn_aggregate_salted", O.sql(*O.graph("cust_supp"), *O.laplacian(), O.aggregate("x", 2, "s"), final=O.rounded(["x0", "x1"]) + " FROM s"))
def gcn_aggregate_salted(spark, sf):
    _, lap, x = _base(spark, sf, "cust_supp")
    return r6(convolve.aggregate_neighbors(lap, x, salts=8).df, ["x0", "x1"])


for _a in ("relu", "sigmoid", "tanh"):
    query(f"gcn_layer_{_a}", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), O.project("s", fixed_weights(2, 3), "y", _a), final=O.rounded(O.cols(3)) + " FROM y"))(
        lambda spark, sf, a=_a: (lambda b: r6(convolve.gcn_layer(b[1], b[2], fixed_weights(2, 3), a).df, O.cols(3)))(_base(spark, sf))
    )


@query("gcn_project_first", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), O.project("s", fixed_weights(2, 1, 4), "y"), final=O.rounded(["x0"]) + " FROM y"))
def gcn_project_first(spark, sf):
    """One output column: frames are projected before the join; the twin aggregates first."""
    _, lap, x = _base(spark, sf)
    return r6(convolve.gcn_layer(lap, x, fixed_weights(2, 1, 4)).df, ["x0"])


@query("gcn_precomputed", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), O.project("s", fixed_weights(2, 3), "y"), final=O.rounded(O.cols(3)) + " FROM y"))
def gcn_precomputed(spark, sf):
    _, lap, x = _base(spark, sf)
    return r6(convolve.gcn_layer(lap, x, fixed_weights(2, 3), precomputed=convolve.precompute_first(lap, x)).df, O.cols(3))


@query("gcn_concat", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), O.project("s", fixed_weights(2, 2), "y", "relu", True), final=O.rounded(O.cols(4)) + " FROM y"))
def gcn_concat(spark, sf):
    _, lap, x = _base(spark, sf)
    return r6(convolve.gcn_concat_layer(lap, x, fixed_weights(2, 2)).df, O.cols(4))


def _step_weights(t):
    return fixed_weights(2, 2, t % 7)


_PER_STEP = "yw AS (SELECT t, v, " + ", ".join("greatest(" + " + ".join(f"x{i} * ((3 * {i} + 5 * {j} + t % 7) % 7 - 3) / 10.0::DOUBLE" for i in range(2)) + f", 0) AS x{j}" for j in range(2)) + " FROM s)"


@query("gcn_per_step_weights", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), _PER_STEP, final=O.rounded(["x0", "x1"]) + " FROM yw"))
def gcn_per_step_weights(spark, sf):
    _, lap, x = _base(spark, sf)
    return r6(convolve.gcn_layer(lap, x, {t: _step_weights(t) for t in range(1, T + 1)}).df, ["x0", "x1"])


_TWO = [*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s1"), O.project("s1", fixed_weights(2, 2), "y1"), O.aggregate("y1", 2, "s2"), O.project("s2", fixed_weights(2, 2, 1), "y2")]


@query("gcn_two_layer", O.sql(*_TWO, final=O.rounded(["x0", "x1"]) + " FROM y2"))
def gcn_two_layer(spark, sf):
    _, lap, x = _base(spark, sf)
    y = convolve.gcn_layer(lap, x, fixed_weights(2, 2))
    return r6(convolve.gcn_layer(lap, y, fixed_weights(2, 2, 1)).df, ["x0", "x1"])


def fixed_params(model: str, hidden: int = HIDDEN) -> dict:
    p = {"w0": fixed_weights(2, hidden, 0), "w1": fixed_weights(hidden, hidden, 1), "u": fixed_weights(2 * hidden, 2, 2), "b": np.zeros(2)}
    for k, width in ((0, 2), (1, hidden)):
        cell = recur.lstm_params(width + hidden, hidden) if model == "skip_lstm" else recur.weight_cell(width)
        p |= {f"{n}{k}": v for n, v in cell.items()}
    return p


def model_of(spark, sf, model: str, name: str = N, **cfg) -> training.DynamicModel:
    return training.DynamicModel(tables.graph(spark, sf, name), model, Config(hidden=HIDDEN, window=SPAN, life=SPAN, **cfg), fixed_params(model))


@query("static_gcn_embedding", O.sql(*_TWO, final=O.rounded(["x0", "x1"]) + " FROM y2"))
def static_gcn_embedding(spark, sf):
    return r6(model_of(spark, sf, "static_gcn").forward().df, ["x0", "x1"])


# ---- differences ----------------------------------------------------------------------------------------------------

_LIFE3 = lambda spark, sf: smooth.edge_life(tables.graph(spark, sf, N), 3)
_DIFF = "df AS (SELECT t, 'common' AS kind, src, dst FROM el a WHERE EXISTS (SELECT 1 FROM el b WHERE b.t = a.t - 1 AND b.src = a.src AND b.dst = a.dst) UNION ALL SELECT t, 'entered', src, dst FROM el a WHERE t > 1 AND NOT EXISTS (SELECT 1 FROM el b WHERE b.t = a.t - 1 AND b.src = a.src AND b.dst = a.dst) UNION ALL SELECT t + 1, 'left', src, dst FROM el a WHERE t < 80 AND NOT EXISTS (SELECT 1 FROM el b WHERE b.t = a.t + 1 AND b.src = a.src AND b.dst = a.dst))"
query("gd_split", O.sql(O.graph(N)[0], O.life(3, T), _DIFF, final="SELECT t, kind, src, dst FROM df"))(lambda spark, sf: delta.diff_sets(_LIFE3(spark, sf)))


def _cost_parts(span: int, block: int, processors: int = 1, name: str = N) -> list[str]:
    steps = O.STEPS[name]
    size = f"least({block}, {steps} - ((t - 1) // {block}) * {block})"
    return [
        O.graph(name)[0], O.life(span, steps), _DIFF.replace("t < 80", f"t < {steps}"),
        f"pl AS (SELECT CAST(t AS BIGINT) AS t, CAST((t - 1) // {block} AS BIGINT) AS block, CAST((((t - 1) % {block}) * {processors}) // {size} AS BIGINT) AS pid FROM range(1, {steps + 1}) r(t))",
        "fi AS (SELECT *, coalesce(lag(block) OVER (ORDER BY t) <> block OR lag(pid) OVER (ORDER BY t) <> pid, true) AS first FROM pl)",
        "sc AS (SELECT fi.*, coalesce(z.n, 0) AS nnz, coalesce(d.l, 0) AS ext_prev, coalesce(d.r, 0) AS ext_next FROM fi LEFT JOIN (SELECT t, count(*) AS n FROM el GROUP BY t) z USING (t) LEFT JOIN (SELECT t, count(*) FILTER (kind = 'left') AS l, count(*) FILTER (kind = 'entered') AS r FROM df GROUP BY t) d USING (t))",
        "co AS (SELECT *, nnz * 20 AS full_bytes, CASE WHEN first THEN nnz * 20 ELSE (ext_prev + ext_next) * 16 + nnz * 4 END AS delta_bytes FROM sc)",
    ]


_COST = "SELECT t, block, pid, first, nnz, ext_prev, ext_next, full_bytes, delta_bytes, least(full_bytes, delta_bytes) AS adaptive_bytes FROM co"
for _name, _block, _p in (("gd_cost_block5", 5, 1), ("gd_cost_block10", 10, 1), ("gd_cost_all", 80, 1), ("gd_cost_chunked_P4", 20, 4)):
    query(_name, O.sql(*_cost_parts(3, _block, _p), final=_COST))(lambda spark, sf, b=_block, p=_p: delta.step_costs(_LIFE3(spark, sf), b, p))
query("gd_cost_full", O.sql(O.graph(N)[0], O.life(3, T), final="SELECT t, count(*) * 20 AS full_bytes FROM el GROUP BY t"))(lambda spark, sf: delta.step_costs(_LIFE3(spark, sf), 10).where("nnz > 0").select("t", "full_bytes"))
_TOTALS = "SELECT CAST(2 * sum(full_bytes) AS BIGINT) AS full_bytes, CAST(2 * sum(delta_bytes) AS BIGINT) AS delta_bytes, CAST(2 * sum(least(full_bytes, delta_bytes)) AS BIGINT) AS adaptive_bytes, round(sum(full_bytes) / sum(delta_bytes), 6) AS delta_ratio, round(sum(full_bytes) / sum(least(full_bytes, delta_bytes)), 6) AS adaptive_ratio FROM co"
for _name, _span, _g in (("gd_ratio_raw", 1, N), ("gd_ratio_l3", 3, N), ("gd_ratio_l12", 12, N), ("gd_ratio_raw_cust_supp", 1, "cust_supp"), ("gd_ratio_l6_user_flow", 6, "user_flow")):
    query(_name, O.sql(*_cost_parts(_span, 10, 1, _g), final=_TOTALS))(lambda spark, sf, n=_span, g=_g: delta.cost_totals(smooth.edge_life(tables.graph(spark, sf, g), n), block=10))


def _roundtrip(spark, sf, adaptive, name=N, span=3, block=10, processors=2):
    g = smooth.edge_life(tables.graph(spark, sf, name), span)
    indices, values = delta.encode_delta(g, block, processors, adaptive)
    whole = delta.whole_steps(g, block, processors, adaptive)
    return delta.decode_delta(indices, values, whole, g.T)


_EL = O.sql(O.graph(N)[0], O.life(3, T), final="SELECT t, src, dst, w FROM el")
query("gd_roundtrip", _EL)(lambda spark, sf: _roundtrip(spark, sf, False))
query("gd_adaptive", _EL)(lambda spark, sf: _roundtrip(spark, sf, True))
query("gd_benefit_table", f"SELECT b AS bsize, p, round(greatest(b - p, 0) / b, 6) AS share FROM (SELECT DISTINCT CAST(ceil(n / nb) AS BIGINT) AS b FROM {_LAST}, (VALUES (2), (4), (8), (20)) z(nb)), (VALUES (1::BIGINT), (2), (8), (32), (128)) y(p)")(lambda spark, sf: delta.gd_benefit(spark, sorted({-(-last_month(spark, sf) // nb) for nb in (2, 4, 8, 20)}), [1, 2, 8, 32, 128]))


# ---- recurrences and models ------------------------------------------------------------------------------------------

@query("window_mean_layer", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), O.project("s", fixed_weights(2, 2), "y"), O.mean(3, 2, "y", "z"), final=O.rounded(["x0", "x1"]) + " FROM z"))
def window_mean_layer(spark, sf):
    _, lap, x = _base(spark, sf)
    return r6(recur.window_mean(convolve.gcn_layer(lap, x, fixed_weights(2, 2)), 3).df, ["x0", "x1"])


query("window_mean_embedding", O.sql(*O.model_parts(N), final=O.rounded(["x0", "x1"]) + " FROM z2"))(lambda spark, sf: r6(model_of(spark, sf, "window_mean").forward().df, ["x0", "x1"]))


@query("window_mean_carry_blocks", O.sql(*O.graph(N), O.mean(4, 2, "x", "m"), final=O.rounded(["x0", "x1"]) + " FROM m"))
def window_mean_carry_blocks(spark, sf):
    """Seven blocks with carried frames; the twin is the unblocked mean."""
    x = snapshots.degree_features(tables.graph(spark, sf, N))
    out, carry = None, None
    for _, lo, hi in blocks.ranges(T, 7):
        part = x.keep(F.col("t").between(lo, hi))
        y = recur.window_mean(part, 4, carry, lo).df
        both = FeatureTensor(part.df if carry is None else part.df.unionByName(carry), 2)
        carry = recur.tail(both, 4, hi)
        out = y if out is None else out.unionByName(y)
    return r6(out, ["x0", "x1"])


def _scaled(x, by=10.0):
    return FeatureTensor(x.df.select("t", "v", *[(F.col(c) / by).alias(c) for c in x.cols]), x.width)


_SCALED = "xs AS (SELECT t, v, x0 / 10.0::DOUBLE AS x0, x1 / 10.0::DOUBLE AS x1 FROM x)"
for _name, _h, _backend, _g in (("lstm_scalar_H1", 1, "catalyst", "user_flow"), ("lstm_H2", 2, "arrow", N), ("lstm_H2_catalyst", 2, "catalyst", N)):
    _st = [f"{s}{i}" for s in "hc" for i in range(_h)]
    query(_name, O.sql(*O.graph(_g), _SCALED, O.lstm("xs", recur.lstm_params(2, _h), "r"), final=O.rounded(_st) + " FROM r WHERE t > 0"))(
        lambda spark, sf, h=_h, b=_backend, g=_g, st=tuple(_st): r6(recur.lstm(_scaled(snapshots.degree_features(tables.graph(spark, sf, g))), recur.lstm_params(2, h), backend=b), list(st))
    )


@query("lstm_carry_blocks", O.sql(*O.graph(N), _SCALED, O.lstm("xs", recur.lstm_params(2, 2), "r"), final=O.rounded(["h0", "h1", "c0", "c1"]) + " FROM r WHERE t > 0"))
def lstm_carry_blocks(spark, sf):
    x = _scaled(snapshots.degree_features(tables.graph(spark, sf, N)))
    out, carry = None, None
    for _, lo, hi in blocks.ranges(T, 3):
        s = written(recur.lstm(x.keep(F.col("t").between(lo, hi)), recur.lstm_params(2, 2), carry), "block")
        carry = s.where(F.col("t") == hi).drop("t")
        out = s if out is None else out.unionByName(s)
    return r6(out, ["h0", "h1", "c0", "c1"])


_SKIP = [
    *O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s1"), O.project("s1", fixed_weights(2, 2, 0), "y1", "relu", True), O.lstm("y1", recur.lstm_params(4, 2), "r1"), O.frames_of("r1", 2, "z1"),
    O.aggregate("z1", 2, "s2"), O.project("s2", fixed_weights(2, 2, 1), "y2", "relu", True), O.lstm("y2", recur.lstm_params(4, 2), "r2"), O.frames_of("r2", 2, "z2"),
]
query("skip_lstm_embedding", O.sql(*_SKIP, final=O.rounded(["x0", "x1"]) + " FROM z2"))(lambda spark, sf: r6(model_of(spark, sf, "skip_lstm").forward().df, ["x0", "x1"]))
query("skip_lstm_one_layer", O.sql(*_SKIP[:-4], final=O.rounded(["x0", "x1"]) + " FROM z1"))(lambda spark, sf: r6(model_of(spark, sf, "skip_lstm", layers=1).forward().df, ["x0", "x1"]))

_W = [f"m{i}_{j}" for i in range(2) for j in range(2)]
_EVOLVE = lambda k, name: O.evolve(fixed_weights(2, 2, k), recur.weight_cell(2), T, name)
#: First weights from the order lines: their mean quantity, discount, tax and price, brought into the range of the weights.
_FIRST = ("avg(l_quantity) / 50", "avg(l_discount)", "avg(l_tax)", "avg(l_extendedprice) / 100000")
_FROM_LINES = "WITH RECURSIVE w0 AS (SELECT " + ", ".join(f"{e} AS {m}" for e, m in zip(_FIRST, _W)) + " FROM lineitem),\n" + O.evolve(None, recur.weight_cell(2), T, "ew", "w0") + "\nSELECT t, "


@query("evolve_weights_T", _FROM_LINES + ", ".join(f"round({c}, 6) + 0.0 AS {c}" for c in _W) + " FROM ew WHERE t > 0")
def evolve_weights_T(spark, sf):
    first = tables.load(spark, sf, "lineitem").agg(*[F.expr(e) for e in _FIRST]).first()
    ws, _ = recur.evolve_weights(np.array(first, float).reshape(2, 2), recur.weight_cell(2), T)
    rows = [(t + 1, *[float(x) for x in w.ravel()]) for t, w in enumerate(ws)]
    return r6(spark.createDataFrame(rows, "t long, " + ", ".join(f"{c} double" for c in _W)), _W, ("t",))


@query("evolve_weights_sql", _FROM_LINES + ", ".join(f"round({c}, 6) + 0.0 AS {c}" for c in _W) + " FROM ew WHERE t > 0")
def evolve_weights_sql(spark, sf):
    """The recurrence of the weights as a recursive query of Spark SQL."""
    tables.load(spark, sf, "lineitem").createOrReplaceTempView("lineitem")
    text = _FROM_LINES + ", ".join(f"round({c}, 6) + 0.0D AS {c}" for c in _W) + " FROM ew WHERE t > 0"
    import re

    return spark.sql(re.sub(r"(-?\d+\.\d+)::DOUBLE", r"CAST(\1 AS DOUBLE)", text))


def _evolved(source, ev, name):
    return f"{name} AS (SELECT f.t, f.v, greatest(x0 * m0_0 + x1 * m1_0, 0) AS x0, greatest(x0 * m0_1 + x1 * m1_1, 0) AS x1 FROM {source} f JOIN {ev} e USING (t))"


_WL = [*O.graph(N), O.life(3, T), *O.laplacian("el"), _EVOLVE(0, "e0"), _EVOLVE(1, "e1"), O.aggregate("x", 2, "s1"), _evolved("s1", "e0", "y1"), O.aggregate("y1", 2, "s2"), _evolved("s2", "e1", "y2")]
query("weight_lstm_embedding", O.sql(*_WL, final=O.rounded(["x0", "x1"]) + " FROM y2"))(lambda spark, sf: r6(model_of(spark, sf, "weight_lstm").forward().df, ["x0", "x1"]))
query("weight_lstm_h_embedding")(lambda spark, sf: r6(model_of(spark, sf, "weight_lstm_h").forward().df, ["x0", "x1"]))


# ---- tasks ----------------------------------------------------------------------------------------------------------

_U = fixed_weights(4, 2, 2)


def _argmax(a="r0", b="r1"):
    return f"CAST(CASE WHEN {b} > {a} THEN 1 ELSE 0 END AS BIGINT)"


@query("vertex_scores_argmax", O.sql(*O.model_parts(N), f"sc AS (SELECT t, v, {O.dot(['x0', 'x1'], fixed_weights(2, 2, 5), 0)} AS r0, {O.dot(['x0', 'x1'], fixed_weights(2, 2, 5), 1)} AS r1 FROM z2)", final=f"SELECT t, v, round(r0, 6) + 0.0 AS r0, round(r1, 6) + 0.0 AS r1, {_argmax()} AS pred FROM sc"))
def vertex_scores_argmax(spark, sf):
    s = tasks.vertex_scores(model_of(spark, sf, "window_mean").forward(), fixed_weights(2, 2, 5))
    return r6(s, ["r0", "r1"], ("t", "v", "pred"))


def _links(spark, sf, name=N, **how):
    return tasks.link_dataset(tables.graph(spark, sf, name), **how)


_LD = [*O.graph(N), *O.link_parts(T)]
query("link_dataset", O.sql(*_LD, final="SELECT t, u, v, y, split FROM ld"))(lambda spark, sf: _links(spark, sf))
query("link_pos_sample", O.sql(*_LD, final="SELECT t, u, v FROM po"))(lambda spark, sf: tasks.sample_links(tables.graph(spark, sf, N)).where("y = 1").select("t", "u", "v"))
query("link_neg_sample", O.sql(*_LD, final="SELECT t, u, v FROM ne"))(lambda spark, sf: tasks.sample_links(tables.graph(spark, sf, N)).where("y = 0").select("t", "u", "v"))
query("link_neg_rejecting", O.sql(*_LD, final="SELECT t, u, v FROM ne WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.t = ne.t AND e.src = ne.u AND e.dst = ne.v)"))(lambda spark, sf: tasks.sample_links(tables.graph(spark, sf, N), reject_existing=True).where("y = 0").select("t", "u", "v"))
query("link_bernoulli_sample", O.sql(*_LD, final=f"SELECT t, u, v FROM pe WHERE h < {int(0.1 * (1 << 32))}"))(lambda spark, sf: tasks.sample_links(tables.graph(spark, sf, N), mode="bernoulli").where("y = 1").select("t", "u", "v"))
query("next_step_active", O.sql(*O.graph("user_flow"), final="SELECT g.t, g.v, CAST(CASE WHEN EXISTS (SELECT 1 FROM e WHERE e.t = g.t + 1 AND (e.src = g.v OR e.dst = g.v)) THEN 1 ELSE 0 END AS BIGINT) AS y FROM g WHERE g.t < 30"))(lambda spark, sf: tasks.next_step_active(tables.graph(spark, sf, "user_flow")))

_EE = "ee AS (SELECT l.*, a.x0 AS e0, a.x1 AS e1, b.x0 AS e2, b.x1 AS e3 FROM ld l JOIN z2 a ON a.t = l.t AND a.v = l.u JOIN z2 b ON b.t = l.t AND b.v = l.v)"
_SCORE = f"sr AS (SELECT *, {O.dot(['e0', 'e1', 'e2', 'e3'], _U, 0)} AS r0, {O.dot(['e0', 'e1', 'e2', 'e3'], _U, 1)} AS r1 FROM ee)"
_SOFT = "sx AS (SELECT *, greatest(r0, r1) AS top, ln(exp(r0 - greatest(r0, r1)) + exp(r1 - greatest(r0, r1))) + greatest(r0, r1) - CASE WHEN y = 1 THEN r1 ELSE r0 END AS loss, exp(r0 - greatest(r0, r1)) / (exp(r0 - greatest(r0, r1)) + exp(r1 - greatest(r0, r1))) AS p0 FROM sr)"
_LINKED = [*O.model_parts(N), *O.link_parts(T), _EE, _SCORE, _SOFT]


def _scored(spark, sf):
    return tasks.link_scores(model_of(spark, sf, "window_mean").forward(), _links(spark, sf), _U)


@query("edge_embedding", O.sql(*_LINKED, final="SELECT t, u, v, y, split, " + ", ".join(f"round(e{i}, 6) + 0.0 AS e{i}" for i in range(4)) + " FROM ee"))
def edge_embedding(spark, sf):
    e = tasks.edge_embedding(model_of(spark, sf, "window_mean").forward(), _links(spark, sf))
    return r6(e.df, e.cols, ("t", "u", "v", "y", "split"))


query("link_scores", O.sql(*_LINKED, final=f"SELECT t, u, v, y, split, {_argmax()} AS pred, round(r0, 6) + 0.0 AS r0, round(r1, 6) + 0.0 AS r1 FROM sr"))(lambda spark, sf: r6(_scored(spark, sf), ["r0", "r1"], ("t", "u", "v", "y", "split", "pred")))
query("cross_entropy", O.sql(*_LINKED, final="SELECT round(avg(loss), 6) AS loss FROM sx WHERE split = 'train'"))(lambda spark, sf: tasks.cross_entropy(_scored(spark, sf).where("split = 'train'")).select(F.round("loss", 6).alias("loss")))
query("accuracy", O.sql(*_LINKED, final=f"SELECT round(avg(CASE WHEN {_argmax()} = y THEN 1.0 ELSE 0.0 END) * 100, 6) AS accuracy FROM sr WHERE split = 'test'"))(lambda spark, sf: tasks.accuracy(_scored(spark, sf).where("split = 'test'")).select(F.round("accuracy", 6).alias("accuracy")))
query("confusion", O.sql(*_LINKED, final=f"SELECT y, {_argmax()} AS pred, count(*) AS n FROM sr GROUP BY ALL"))(lambda spark, sf: tasks.confusion(_scored(spark, sf)))
_REPORT = f"""SELECT round(tp / nullif(tp + fp, 0), 6) AS precision, round(tp / nullif(tp + fn, 0), 6) AS recall, round(2 * tp / nullif(2 * tp + fp + fn, 0), 6) AS f1, round(wins / nullif(pos * neg, 0), 6) AS auc FROM
(SELECT count(*) FILTER (y = 1 AND pred = 1) AS tp, count(*) FILTER (y = 0 AND pred = 1) AS fp, count(*) FILTER (y = 1 AND pred = 0) AS fn, count(*) FILTER (y = 1) AS pos, count(*) FILTER (y = 0) AS neg FROM (SELECT y, {_argmax()} AS pred FROM sq)),
(SELECT sum(CASE WHEN a.s > b.s THEN 1 WHEN a.s = b.s THEN 0.5 ELSE 0 END) AS wins FROM (SELECT r1 - r0 AS s FROM sq WHERE y = 1) a, (SELECT r1 - r0 AS s FROM sq WHERE y = 0) b)"""
query("classification_report", O.sql(*_LINKED, "sq AS (SELECT t, u, v, y, split, round(r0, 6) AS r0, round(r1, 6) AS r1 FROM sr)", final=_REPORT))(lambda spark, sf: tasks.classification_report(_scored(spark, sf).withColumns({"r0": F.round("r0", 6), "r1": F.round("r1", 6)}).withColumn("pred", tasks.argmax(["r0", "r1"]))))


# ---- gradients and training -------------------------------------------------------------------------------------------

@query("gcn_weight_gradient", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), final="SELECT " + ", ".join(f"round(sum(CASE WHEN {O.dot(['x0', 'x1'], fixed_weights(2, 2), k)} > 0 THEN x{i} ELSE 0 END), 4) AS w{i}_{k}" for i in range(2) for k in range(2)) + " FROM s"))
def gcn_weight_gradient(spark, sf):
    """Gradient of the sum of a layer's outputs by its weights."""
    _, lap, x = _base(spark, sf)
    s = convolve.aggregate_neighbors(lap, x)
    p = convolve.times(s.cols, fixed_weights(2, 2))
    return s.df.agg(*[F.round(F.sum(F.when(p[k] > 0, F.col(f"x{i}")).otherwise(0.0)), 4).alias(f"w{i}_{k}") for i in range(2) for k in range(2)])


query("window_mean_gradient", O.sql(*O.graph(N), "sp AS (SELECT CAST(unnest(range(greatest(t - 2, 1), t + 1)) AS BIGINT) AS k, v, x0 / least(3, t) AS x0, x1 / least(3, t) AS x1 FROM x)", final="SELECT k AS t, v, round(sum(x0), 6) + 0.0 AS x0, round(sum(x1), 6) + 0.0 AS x1 FROM sp GROUP BY ALL"))(lambda spark, sf: r6(recur.window_mean_backward(snapshots.degree_features(tables.graph(spark, sf, N)), 3).df, ["x0", "x1"]))
_CG = ", ".join(f"round(sum(e{i} * ({'p0' if k == 0 else '1 - p0'} - CASE WHEN y = {k} THEN 1 ELSE 0 END)) / count(*), 6) + 0.0 AS u{i}_{k}" for i in range(4) for k in range(2))


@query("classifier_gradient", O.sql(*_LINKED, final=f"SELECT {_CG} FROM sx WHERE split = 'train'"))
def classifier_gradient(spark, sf):
    m = model_of(spark, sf, "window_mean")
    rows = written(_links(spark, sf).where("split = 'train'").drop("split"), "pairs")
    _, du, _, _ = m._head(m.forward(), rows, rows.count())
    names = [f"u{i}_{k}" for i in range(4) for k in range(2)]
    return r6(spark.createDataFrame([tuple(float(x) for x in du.ravel())], ", ".join(f"{n} double" for n in names)), names, ())


_SGD = ", ".join(f"round({_U[i, k]:.1f}::DOUBLE - 0.1::DOUBLE * sum(e{i} * ({'p0' if k == 0 else '1 - p0'} - CASE WHEN y = {k} THEN 1 ELSE 0 END)) / count(*), 6) + 0.0 AS u{i}_{k}" for i in range(4) for k in range(2))


@query("one_sgd_step_window_mean", O.sql(*_LINKED, final=f"SELECT {_SGD} FROM sx WHERE split = 'train'"))
def one_sgd_step_window_mean(spark, sf):
    """The classifier's weights after one full-batch step of the whole model, over two re-executed blocks."""
    m = model_of(spark, sf, "window_mean", blocks=2)
    _, grads = m.gradients(written(_links(spark, sf).where("split = 'train'").drop("split"), "pairs"))
    m.step(grads)
    names = [f"u{i}_{k}" for i in range(4) for k in range(2)]
    return r6(spark.createDataFrame([tuple(float(x) for x in m.params["u"].ravel())], ", ".join(f"{n} double" for n in names)), names, ())


def _history(spark, sf, model, epochs=2, **cfg):
    g = snapshots.planted_communities(spark, 6, 24, 3)
    g = DynamicGraph(written(g.edges, "planted"), g.vertices, g.T)
    data = written(tasks.link_dataset(g, 0.3), "pairs")
    m = training.DynamicModel(g, model, Config(hidden=4, optimizer="adam", rate=0.05, **cfg))
    h = m.train(data.where("split = 'train'").drop("split"), data.where("split = 'test'").drop("split"), epochs)
    return spark.createDataFrame([(cfg.get("layout", "snapshot"), cfg.get("blocks", 2), r["epoch"], r["loss"], r["accuracy"]) for r in h], "layout string, blocks int, epoch int, loss double, accuracy double")


for _m in ("window_mean", "skip_lstm", "weight_lstm"):
    query(f"train_{_m}")(lambda spark, sf, m=_m: _history(spark, sf, m, blocks=2))
query("loss_history_blocked_vs_plain")(lambda spark, sf: _history(spark, sf, "window_mean", blocks=1).unionByName(_history(spark, sf, "window_mean", blocks=3)).unionByName(_history(spark, sf, "window_mean", blocks=2, layout="vertex")))


@query("lstm_gradient")
def lstm_gradient(spark, sf):
    x = _scaled(snapshots.degree_features(tables.graph(spark, sf, N)))
    dz = FeatureTensor(x.df.select("t", "v", F.lit(1.0).alias("x0"), F.lit(1.0).alias("x1")), 2)
    g = recur.lstm_gradients(x, dz, recur.lstm_params(2, 2))
    return g.where("kind = 0").select("t", "v", *[F.round(F.get("g", F.lit(i)), 6).alias(f"x{i}") for i in range(2)])


# ---- blocks, distribution, measures -----------------------------------------------------------------------------------

query("block_plan", f"SELECT CAST(b AS BIGINT) AS block, CAST(ceil(b * n / 7) + 1 AS BIGINT) AS first, CAST(ceil((b + 1) * n / 7) AS BIGINT) AS last, CAST(ceil((b + 1) * n / 7) - ceil(b * n / 7) AS BIGINT) AS size FROM {_LAST}, range(7) r(b)")(lambda spark, sf: blocks.block_plan(spark, last_month(spark, sf), 7))
query("owner_in_block", f"SELECT t, CAST(b AS BIGINT) AS block, CAST(floor((t - 1 - ceil(b * n / 6)) * 3 / (ceil((b + 1) * n / 6) - ceil(b * n / 6))) AS BIGINT) AS pid FROM (SELECT t, n, ((t - 1) * 6) // n AS b FROM {_MONTHS}, {_LAST})")(lambda spark, sf: blocks.owners_of(months(spark, sf), last_month(spark, sf), 6, 3))
query("owner_snapshot", O.sql(O.graph(N)[0], final="SELECT CAST(((t - 1) * 6) // 80 AS INTEGER) AS pid, count(*) AS n, min(t) AS first, max(t) AS last FROM e GROUP BY 1"))(lambda spark, sf: partition.by_snapshot(tables.graph(spark, sf, N).edges, T, 6).groupBy("pid").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("first"), F.max("t").alias("last")))
_UNIFORM = lambda p, name="cust_supp": [*O.graph(name)[:2], f"ow AS (SELECT v, CAST(((row_number() OVER (ORDER BY v) - 1) * {p}) // (SELECT count(*) FROM v) AS INTEGER) AS q FROM v)"]
query("owner_vertex_uniform", O.sql(*_UNIFORM(7), final="SELECT v, q FROM ow"))(lambda spark, sf: partition.by_vertex_uniform(tables.graph(spark, sf, "cust_supp"), 7))
query("volume_snapshot_table", "SELECT p, CAST(80 * 1600 AS BIGINT) AS per_exchange, round(80 * 1600 * (p - 1) / p, 6) AS remote, CAST(8 AS BIGINT) AS exchanges, CAST(80 * 1600 * 8 AS BIGINT) AS units, round(80 * 1600 * 8 * (p - 1) / p, 6) AS remote_units, round(80 * 1600 * 48 * (p - 1) / p, 6) AS floats FROM (VALUES (1::BIGINT), (4), (16), (64)) x(p)")(lambda spark, sf: partition.volume_snapshot(spark, 80, 1600, [1, 4, 16, 64], widths=(6, 6)))
_PINS = "pn AS (SELECT DISTINCT t, u, v FROM (SELECT t, src AS u, dst AS v FROM e UNION ALL SELECT t, dst, src FROM e) WHERE u <> v), nd AS (SELECT DISTINCT t, pn.v, a.q AS q, b.q AS p FROM pn JOIN ow a ON a.v = u JOIN ow b ON b.v = pn.v)"
for _p in (4, 16, 64):
    query(f"volume_vertex_P{_p}", O.sql(*_UNIFORM(_p), _PINS, final="SELECT count(*) AS lambda_all, count(*) FILTER (p <> q) AS lambda_remote FROM nd"))(lambda spark, sf, p=_p: (lambda g: partition.volume_vertex(g, partition.by_vertex_uniform(g, p)))(tables.graph(spark, sf, "cust_supp")))


@query("volume_compare", " UNION ALL ".join("SELECT * FROM (" + O.sql(*O.graph(N)[:1], O.life(3, T), *[c.replace("FROM e", "FROM el") if c.startswith("pn") else c for c in (O.graph(N)[1], f"ow AS (SELECT v, CAST(((row_number() OVER (ORDER BY v) - 1) * {p}) // (SELECT count(*) FROM v) AS INTEGER) AS q FROM v)", _PINS)], final=f"SELECT '{kind}' AS model, CAST({p} AS BIGINT) AS p, round(80 * (SELECT count(*) FROM v) * ({p} - 1) / {p}, 6) AS snapshot_units, (SELECT count(*) FILTER (p <> q) FROM nd) AS vertex_units").replace("FROM el", "FROM el" if kind == "smoothed" else "FROM e") + ")" for kind in ("raw", "smoothed") for p in (4, 16)))
def volume_compare(spark, sf):
    """Frames that one exchange of the snapshot layout and one convolution of the vertex layout move to another processor."""
    raw = tables.graph(spark, sf, N)
    raw = DynamicGraph(written(raw.edges, "edges"), raw.vertices, T)
    n, out = raw.vertices.count(), None
    for kind, g in (("raw", raw), ("smoothed", smooth.edge_life(raw, 3))):
        for p in (4, 16):
            v = partition.volume_vertex(g, partition.by_vertex_uniform(raw, p)).select(F.lit(kind).alias("model"), F.lit(p).cast("long").alias("p"), F.round(F.lit(float(T * n)) * (p - 1) / p, 6).alias("snapshot_units"), F.col("lambda_remote").alias("vertex_units"))
            out = v if out is None else out.unionByName(v)
    return out


query("send_matrix", O.sql(*_UNIFORM(5), _PINS, final="SELECT CAST(p AS BIGINT) AS p, CAST(q AS BIGINT) AS q, count(*) AS frames FROM nd WHERE p <> q GROUP BY ALL"))(lambda spark, sf: (lambda g: partition.send_matrix(partition.send_index(g, partition.by_vertex_uniform(g, 5))))(tables.graph(spark, sf, "cust_supp")))
query("moved_rows", O.sql(*_UNIFORM(5, N), "g AS (SELECT CAST(r.t AS BIGINT) AS t, v.v FROM range(1, 81) r(t), v)", final="SELECT count(*) AS rows, count(*) FILTER (((t - 1) * 5) // 80 <> q) AS remote FROM g JOIN ow USING (v)"))(lambda spark, sf: (lambda g: partition.moved_rows(snapshots.grid(g), partition.by_vertex_uniform(g, 5), T, 5))(tables.graph(spark, sf, N)))
query("node_split", f"SELECT t AS p, CAST(greatest(ceil(t / 8), 1) AS BIGINT) AS nodes, round(1 / greatest(ceil(t / 8), 1), 6) AS intra, round((greatest(ceil(t / 8), 1) - 1) / greatest(ceil(t / 8), 1), 6) AS inter FROM {_MONTHS}")(lambda spark, sf: partition.node_split(months(spark, sf).withColumnRenamed("t", "p")))
query("balance_snapshot", O.sql(O.graph(N)[0], final="SELECT max(n) AS largest, round(sum(n) / 6, 6) AS mean, round(max(n) / (sum(n) / 6), 6) AS ratio FROM (SELECT ((t - 1) * 6) // 80 AS pid, count(*) AS n FROM e GROUP BY 1)"))(lambda spark, sf: partition.balance(tables.graph(spark, sf, N).edges.withColumn("pid", partition.snapshot_owner(F.col("t"), T, 6)), "pid", 6))
query("balance_vertex", O.sql(*_UNIFORM(6), final="SELECT max(n) AS largest, round(sum(n) / 6, 6) AS mean, round(max(n) / (sum(n) / 6), 6) AS ratio FROM (SELECT q, count(*) AS n FROM e JOIN ow ON v = src GROUP BY q)"))(lambda spark, sf: (lambda g: partition.balance(g.edges.join(partition.by_vertex_uniform(g, 6).withColumnRenamed("v", "src"), "src"), "q", 6))(tables.graph(spark, sf, "cust_supp")))
query("gcn_vertex_layout", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), final=O.rounded(["x0", "x1"]) + " FROM s"))(lambda spark, sf: (lambda b: r6(partition.aggregate_shipped(b[1], b[2], partition.by_vertex_hash(b[0], 5)).df, ["x0", "x1"]))(_base(spark, sf)))
query("gcn_hybrid_layout", O.sql(*O.graph(N), *O.laplacian(), O.aggregate("x", 2, "s"), final=O.rounded(["x0", "x1"]) + " FROM s"))(lambda spark, sf: (lambda b: r6(partition.aggregate_shipped(b[1], b[2], partition.by_vertex_uniform(b[0], 3), partition.hybrid_tile(T, 4)).df, ["x0", "x1"]))(_base(spark, sf)))


@query("redistribution_roundtrip", O.sql(*O.graph(N), final="SELECT t, v, x0, x1 FROM x"))
def redistribution_roundtrip(spark, sf):
    g = tables.graph(spark, sf, N)
    x = snapshots.degree_features(g)
    return partition.to_snapshot_layout(partition.to_vertex_layout(x, partition.by_vertex_uniform(g, 4), 4), T, 4).drop("pid")


@query("hypergraph_partition_quality")
def hypergraph_partition_quality(spark, sf):
    """(round, lambda) of the refinement of four owners of the customer and supplier graph."""
    g = tables.graph(spark, sf, "cust_supp")
    g = DynamicGraph(written(g.edges, "edges"), written(g.vertices, "vertices"), g.T)
    _, trace = partition.by_vertex_hypergraph(g, 4, rounds=4)
    return spark.createDataFrame(trace, "round long, lambda_all long")


@query("relabelled_parts", O.sql(*O.graph(N)[:1], final="SELECT count(*) AS nnz, CAST(80 AS BIGINT) AS steps FROM e"))
def relabelled_parts(spark, sf):
    g = tables.graph(spark, sf, N)
    h, _ = partition.relabel(g, partition.by_vertex_hash(g, 4))
    return h.edges.agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("t").alias("steps"))


_MEM = "SELECT nb, p, round((30446.0::DOUBLE * 20 + 80 * 25 * 8 * 30) / nb / p, 3) AS block_bytes, round(nb * (25.0::DOUBLE * 8 * 24) / p, 3) AS carry_bytes, round((30446.0::DOUBLE * 20 + 80 * 25 * 8 * 30) / nb / p + nb * (25.0::DOUBLE * 8 * 24) / p, 3) AS bytes FROM (VALUES (1::BIGINT), (2), (4), (8), (16)) x(nb), (VALUES (1::BIGINT), (4), (8)) y(p)"
_memory = lambda spark: blocks.memory_model(spark, 30446, 25, 80, 30, 24, [1, 2, 4, 8, 16], [1, 4, 8], budget=60_000.0)
_COUNTED = _MEM.replace("30446.0::DOUBLE", "nnz::DOUBLE").replace("25.0::DOUBLE", "n::DOUBLE").replace("80 * 25 * 8 * 30", "80 * n * 8 * 30").replace("FROM (VALUES", "FROM (SELECT (SELECT count(*) FROM e) AS nnz, (SELECT count(*) FROM v) AS n), (VALUES", 1)


@query("memory_model_grid", O.sql(*O.graph(N)[:2], final=f"SELECT *, bytes <= 60000 AS fits FROM ({_COUNTED})"))
def memory_model_grid(spark, sf):
    """Memory by blocks and processors, for the size of the trade graph."""
    s = snapshots.graph_stats(tables.graph(spark, sf, N)).first()
    return blocks.memory_model(spark, s["nnz"], s["n"], s["steps"], 30, 24, [1, 2, 4, 8, 16], [1, 4, 8], budget=60_000.0)



query("tune_blocks", f"SELECT p, min(nb) FILTER (bytes <= 60000) AS nb FROM ({_MEM}) GROUP BY p")(lambda spark, sf: blocks.tune_blocks(_memory(spark)))

#: Published times of an epoch in milliseconds (model, layout, processors, ms); none where it did not run.
TIMES = [
    ("window_mean", "snapshot", 4, 3396.0), ("window_mean", "snapshot", 16, 1384.0), ("window_mean", "snapshot", 64, 593.0),
    ("window_mean", "hypergraph", 4, 6668.0), ("window_mean", "hypergraph", 16, 5254.0), ("window_mean", "hypergraph", 64, 9164.0),
    ("skip_lstm", "snapshot", 4, 3867.0), ("skip_lstm", "snapshot", 16, 2545.0), ("skip_lstm", "snapshot", 64, 1135.0),
    ("skip_lstm", "hypergraph", 4, 6252.0), ("skip_lstm", "hypergraph", 16, 4653.0), ("skip_lstm", "hypergraph", 64, 8856.0),
    ("weight_lstm", "snapshot", 4, 4185.0), ("weight_lstm", "snapshot", 16, 944.0), ("weight_lstm", "snapshot", 64, 308.0),
    ("weight_lstm", "hypergraph", 4, None), ("weight_lstm", "hypergraph", 16, 8431.0), ("weight_lstm", "hypergraph", 64, 12276.0),
]
_VALUES = "(VALUES " + ", ".join(f"('{m}', '{lay}', {p}::BIGINT, {'NULL' if ms is None else ms}::DOUBLE)" for m, lay, p, ms in TIMES) + ") x(model, layout, p, ms)"
_times = lambda spark: spark.createDataFrame(TIMES, "model string, layout string, p long, ms double")
query("speedup_table", f"SELECT model, layout, p, ms, min(p) OVER w AS ref_p, round(min(p) OVER w * arg_min(ms, p) OVER w / ms, 6) AS speedup FROM {_VALUES} WHERE ms IS NOT NULL WINDOW w AS (PARTITION BY model, layout)")(lambda spark, sf: measures.speedup_table(_times(spark), ["model", "layout"]))
query("throughput_table", f"SELECT model, layout, p, 1000 * p AS nnz, ms, round(1000 * p * 1000.0::DOUBLE / ms, 6) AS per_s, round((1000 * p * 1000.0::DOUBLE / ms) / first_value(1000 * p * 1000.0::DOUBLE / ms) OVER (PARTITION BY model, layout ORDER BY p), 6) AS scaled FROM {_VALUES} WHERE ms IS NOT NULL")(lambda spark, sf: measures.throughput_table(_times(spark).withColumn("nnz", F.col("p") * 1000), ["model", "layout"]))


@query("layout_time_ratio", f"SELECT model, p, round(vertex_units / snapshot_units, 6) AS ratio FROM ({_SQL['volume_compare']})")
def layout_time_ratio(spark, sf):
    """Time of the vertex layout's exchange over that of the snapshot layout at equal rates, from the frames that each moves on the trade graph."""
    moved = volume_compare(spark, sf).unpivot(["model", "p"], [F.col("snapshot_units").alias("snapshot"), F.col("vertex_units").cast("double").alias("hypergraph")], "layout", "ms")
    return moved.groupBy("model", "p").pivot("layout", ["snapshot", "hypergraph"]).agg(F.first("ms")).select("model", "p", F.round(F.col("hypergraph") / F.col("snapshot"), 6).alias("ratio"))


#: Bytes that go to a processor in a millisecond, and milliseconds of an epoch beside the transfer: both assumed.
_RATE, _REST = 1000.0, 390.0
_GAIN = f"SELECT sum(full_bytes) * 2 / {_RATE}::DOUBLE AS base_ms, sum(delta_bytes) * 2 / {_RATE}::DOUBLE AS gd_ms, {_REST}::DOUBLE AS rest_ms FROM co"


@query("gd_gain", O.sql(*_cost_parts(3, 10), f"ga AS ({_GAIN})", final="SELECT *, round(base_ms / gd_ms, 6) AS transfer_speedup, round(100 * (base_ms - gd_ms) / (base_ms + rest_ms), 6) AS overall_gain FROM ga"))
def gd_gain(spark, sf):
    """What differences save of an epoch on the trade graph, from the bytes of its loads."""
    cost = delta.cost_totals(_LIFE3(spark, sf), block=10)
    return measures.gd_gain(cost.select((F.col("full_bytes") / _RATE).alias("base_ms"), (F.col("delta_bytes") / _RATE).alias("gd_ms"), F.lit(_REST).alias("rest_ms")))


def flagship(spark, sf_dir):
    """Forward pass of the banded-mean model on the trade graph, with the accuracy of its link scores beside each step's size."""
    scored = _scored(spark, sf_dir)
    return scored.groupBy("split", "t").agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg((F.col("pred") == F.col("y")).cast("double")) * 100, 6).alias("accuracy"))


query("flagship", O.sql(*_LINKED, final=f"SELECT split, t, count(*) AS pairs, round(avg(CASE WHEN {_argmax()} = y THEN 1.0 ELSE 0.0 END) * 100, 6) AS accuracy FROM sr GROUP BY ALL"))(flagship)
