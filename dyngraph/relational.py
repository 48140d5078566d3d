"""Queries of the relational operators that the methods are made of, on the trade graph and the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph import oracles as O
from dyngraph.catalog import _MONTHS, N, months, query
from dyngraph.functions import vectors
from dyngraph.operators import smooth, snapshots
from dyngraph.sources import tables
from dyngraph.storage import written

E = O.graph(N)[0]
edges = lambda spark, sf, name=N: tables.graph(spark, sf, name).edges


@query("rel_filter_predicates", O.sql(E, final="SELECT t, src, dst, CASE WHEN src < dst THEN 'up' ELSE 'down' END AS way FROM e WHERE t BETWEEN 10 AND 20 AND src IN (1, 3, 5) AND src <> dst AND w IS NOT NULL"))
def rel_filter_predicates(spark, sf):
    e = edges(spark, sf).where(F.col("t").between(10, 20) & F.col("src").isin(1, 3, 5) & (F.col("src") != F.col("dst")) & F.col("w").isNotNull())
    return e.select("t", "src", "dst", F.when(F.col("src") < F.col("dst"), "up").otherwise("down").alias("way"))


@query("rel_like_null_safe", "SELECT p_partkey, p_type FROM part WHERE p_type LIKE '%ANDARD%' AND p_brand IS NOT DISTINCT FROM 'Brand#11'")
def rel_like_null_safe(spark, sf):
    return tables.load(spark, sf, "part").where(F.col("p_type").like("%ANDARD%") & F.col("p_brand").eqNullSafe("Brand#11")).select("p_partkey", "p_type")


_JOIN = "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"
for _h in ("broadcast", "shuffle_hash", "merge"):
    @query(f"rel_join_{_h}", _JOIN)
    def rel_join(spark, sf, hint=_h):
        """The same equi-join by each strategy; customer is the small side and is only broadcast for the named hint."""
        c = tables.load(spark, sf, "customer").select("c_custkey", "c_mktsegment").hint(hint)
        o = tables.load(spark, sf, "orders").select("o_custkey")
        return o.join(c, o["o_custkey"] == c["c_custkey"]).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("rel_semi_surviving_edges", O.sql(E, final="SELECT t, src, dst FROM e a WHERE EXISTS (SELECT 1 FROM e b WHERE b.t = a.t + 1 AND b.src = a.src AND b.dst = a.dst)"))
def rel_semi_surviving_edges(spark, sf):
    e = edges(spark, sf).select("t", "src", "dst")
    return e.join(e.withColumn("t", F.col("t") - 1), ["t", "src", "dst"], "left_semi")


@query("rel_anti_new_edges", O.sql(E, final="SELECT t, src, dst FROM e a WHERE NOT EXISTS (SELECT 1 FROM e b WHERE b.t = a.t - 1 AND b.src = a.src AND b.dst = a.dst)"))
def rel_anti_new_edges(spark, sf):
    e = edges(spark, sf).select("t", "src", "dst")
    return e.join(e.withColumn("t", F.col("t") + 1), ["t", "src", "dst"], "left_anti")


@query("rel_full_outer_diff", O.sql(E, final="SELECT coalesce(a.src, b.src) AS src, coalesce(a.dst, b.dst) AS dst, CASE WHEN b.src IS NULL THEN 'left' WHEN a.src IS NULL THEN 'entered' ELSE 'common' END AS kind FROM (SELECT src, dst FROM e WHERE t = 3) a FULL JOIN (SELECT src, dst FROM e WHERE t = 4) b ON a.src = b.src AND a.dst = b.dst"))
def rel_full_outer_diff(spark, sf):
    e = edges(spark, sf)
    a = e.where("t = 3").select("src", "dst", F.lit(1).alias("a"))
    b = e.where("t = 4").select("src", "dst", F.lit(1).alias("b"))
    return a.join(b, ["src", "dst"], "full").select("src", "dst", F.when(F.col("b").isNull(), "left").when(F.col("a").isNull(), "entered").otherwise("common").alias("kind"))


@query("rel_range_band_join", O.sql(E, final="SELECT a.t, a.src, a.dst, count(*) AS n FROM e a JOIN e b ON a.src = b.src AND a.dst = b.dst AND b.t BETWEEN a.t - 2 AND a.t GROUP BY ALL"))
def rel_range_band_join(spark, sf):
    """Band join through an equality on the pair and the unrolled short band of steps."""
    e = edges(spark, sf).select("t", "src", "dst")
    b = e.select(F.explode(F.sequence("t", F.col("t") + 2)).alias("t"), "src", "dst")
    return e.join(b, ["t", "src", "dst"]).groupBy("t", "src", "dst").agg(F.count(F.lit(1)).alias("n"))


@query("rel_interval_runs_join", O.sql(E, f"rn AS (SELECT src, dst, min(t) AS t_from, max(t) AS t_to FROM (SELECT t, src, dst, t - row_number() OVER (PARTITION BY src, dst ORDER BY t) AS i FROM e) GROUP BY src, dst, i)", final="SELECT CAST(k.t AS BIGINT) AS t, count(*) AS alive FROM range(5, 81, 15) k(t) JOIN rn ON k.t BETWEEN t_from AND t_to GROUP BY 1"))
def rel_interval_runs_join(spark, sf):
    """Steps inside runs: runs meet steps by buckets of ten steps, then by the interval itself."""
    runs = smooth.compress_runs(edges(spark, sf)).withColumn("b", F.explode(F.sequence(F.floor(F.col("t_from") / 10), F.floor(F.col("t_to") / 10))))
    steps = spark.range(5, 81, 15).select(F.col("id").alias("t"), F.floor(F.col("id") / 10).alias("b"))
    return runs.join(steps, "b").where("t between t_from and t_to").groupBy("t").agg(F.count(F.lit(1)).alias("alive"))


@query("rel_asof_carry", O.sql(E, "d AS (SELECT t, src AS v, count(*) AS n FROM e GROUP BY ALL)", final="SELECT CAST(q.t AS BIGINT) AS t, q.v, (SELECT arg_max(d.n, d.t) FROM d WHERE d.v = q.v AND d.t < q.t) AS last_n FROM (SELECT t, v FROM range(10, 81, 10) r(t), (SELECT DISTINCT v FROM d)) q"))
def rel_asof_carry(spark, sf):
    """Last known out-degree before each block's first step: one window over the union of states and questions."""
    e = edges(spark, sf)
    d = e.groupBy("t", F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("n"))
    ask = d.select("v").distinct().select(F.explode(F.sequence(F.lit(10).cast("long"), F.lit(80).cast("long"), F.lit(10).cast("long"))).alias("t"), "v")
    both = d.select("t", "v", "n", F.lit(1).alias("o")).unionByName(ask.select("t", "v", F.lit(None).cast("long").alias("n"), F.lit(0).alias("o")))
    w = Window.partitionBy("v").orderBy("t", "o")
    return both.withColumn("last_n", F.last("n", ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, -1))).where("o = 0").select("t", "v", "last_n")


@query("rel_two_hop", O.sql(E, final="SELECT a.t, a.src, b.dst, count(*) AS paths FROM e a JOIN e b ON a.t = b.t AND a.dst = b.src WHERE a.src <> b.dst GROUP BY ALL"))
def rel_two_hop(spark, sf):
    e = edges(spark, sf)
    a, b = e.select("t", "src", F.col("dst").alias("mid")), e.select("t", F.col("src").alias("mid"), "dst")
    return a.join(b, ["t", "mid"]).where("src <> dst").groupBy("t", "src", "dst").agg(F.count(F.lit(1)).alias("paths"))


_TRAFFIC = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _traffic(spark, sf):
    t = tables.trades(spark, sf)
    c = tables.load(spark, sf, "customer").select("c_custkey", "c_nationkey")
    n = tables.load(spark, sf, "nation")
    r = tables.load(spark, sf, "region")
    return t.join(c, t["o_custkey"] == c["c_custkey"]).join(F.broadcast(n), F.col("c_nationkey") == n["n_nationkey"]).join(F.broadcast(r), F.col("n_regionkey") == r["r_regionkey"]).withColumn("year", F.floor((F.col("t") - 1) / 12).cast("long"))


_YEAR = f"({O.month('o_orderdate')} - 1) // 12"
for _k, _group in (("cube", "CUBE (r_name, year)"), ("rollup", "ROLLUP (r_name, n_name)"), ("grouping_sets", "GROUPING SETS ((r_name), (year), ())")):
    _keys = ("r_name", "n_name") if _k == "rollup" else ("r_name", "year")
    @query(f"rel_{_k}_traffic", f"SELECT {', '.join(_keys)}, grouping({_keys[0]}, {_keys[1]}) AS gid, count(*) AS n FROM (SELECT r_name, n_name, CAST({_YEAR} AS BIGINT) AS year {_TRAFFIC}) GROUP BY {_group}")
    def rel_groups(spark, sf, kind=_k, keys=_keys):
        rows = _traffic(spark, sf)
        if kind == "cube":
            g = rows.cube(*keys)
        elif kind == "rollup":
            g = rows.rollup(*keys)
        else:
            rows.select(*keys).createOrReplaceTempView("traffic_rows")
            return spark.sql("SELECT r_name, year, grouping_id(r_name, year) AS gid, count(*) AS n FROM traffic_rows GROUP BY GROUPING SETS ((r_name), (year), ())")
        return g.agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"))


_DEG = "d AS (SELECT t, src AS v, count(*) AS n FROM e GROUP BY ALL)"
_RANKS = "row_number() OVER o AS rn, rank() OVER k AS rk, dense_rank() OVER k AS dr, CAST(ntile(4) OVER o AS INTEGER) AS nt, round(percent_rank() OVER k, 6) AS pr, round(cume_dist() OVER k, 6) AS cd, lag(n) OVER o AS lg, lead(n) OVER o AS ld, first_value(n) OVER o AS fv, nth_value(n, 2) OVER (PARTITION BY t ORDER BY n DESC, v ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS nv"


@query("rel_window_rank_suite", O.sql(E, _DEG, final=f"SELECT t, v, n, {_RANKS} FROM d WINDOW o AS (PARTITION BY t ORDER BY n DESC, v), k AS (PARTITION BY t ORDER BY n DESC)"))
def rel_window_rank_suite(spark, sf):
    d = edges(spark, sf).groupBy("t", F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("n"))
    k = Window.partitionBy("t").orderBy(F.desc("n"))
    o = Window.partitionBy("t").orderBy(F.desc("n"), "v")
    full = o.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return d.select("t", "v", "n", F.row_number().over(o).cast("long").alias("rn"), F.rank().over(k).cast("long").alias("rk"), F.dense_rank().over(k).cast("long").alias("dr"), F.ntile(4).over(o).alias("nt"), F.round(F.percent_rank().over(k), 6).alias("pr"), F.round(F.cume_dist().over(k), 6).alias("cd"), F.lag("n").over(o).alias("lg"), F.lead("n").over(o).alias("ld"), F.first("n").over(o).alias("fv"), F.nth_value("n", 2).over(full).alias("nv"))


@query("rel_range_frame", O.sql(E, "d AS (SELECT t, src AS v, count(*) AS n FROM e GROUP BY ALL)", final="SELECT t, v, CAST(sum(n) OVER (PARTITION BY v ORDER BY t RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last3, CAST(sum(n) OVER (PARTITION BY v ORDER BY t ROWS UNBOUNDED PRECEDING) AS BIGINT) AS so_far FROM d"))
def rel_range_frame(spark, sf):
    d = edges(spark, sf).groupBy("t", F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("v").orderBy("t")
    return d.select("t", "v", F.sum("n").over(w.rangeBetween(-2, 0)).alias("last3"), F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"))


@query("rel_topk_degree", O.sql(O.graph("cust_supp")[0], "d AS (SELECT t, dst AS v, count(*) AS n FROM e GROUP BY ALL)", final="SELECT t, v, n, k FROM (SELECT *, row_number() OVER (PARTITION BY t ORDER BY n DESC, v) AS k FROM d) WHERE k <= 3"))
def rel_topk_degree(spark, sf):
    d = snapshots.degrees(tables.graph(spark, sf, "cust_supp"), "in").withColumnRenamed("deg", "n")
    k = F.row_number().over(Window.partitionBy("t").orderBy(F.desc("n"), "v"))
    return d.withColumn("k", k.cast("long")).where("k <= 3").select("t", "v", "n", "k")


@query("rel_sort_limit_offset", O.sql(O.graph("cust_supp")[0], final="SELECT src, count(*) AS n FROM e GROUP BY src ORDER BY n DESC, src LIMIT 10 OFFSET 5"))
def rel_sort_limit_offset(spark, sf):
    return edges(spark, sf, "cust_supp").groupBy("src").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "src").offset(5).limit(10)


for _op, _sqlop in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
    @query(f"rel_{_op}", O.sql(E, final=f"SELECT src, dst FROM e WHERE t = 5 {_sqlop} SELECT src, dst FROM e WHERE t = 6"))
    def rel_set(spark, sf, op=_op):
        e = edges(spark, sf)
        a, b = (e.where(F.col("t") == t).select("src", "dst") for t in (5, 6))
        return {"union": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b)}[op]()


@query("rel_except_all", O.sql(E, final="SELECT src FROM e WHERE t = 5 EXCEPT ALL SELECT src FROM e WHERE t = 6"))
def rel_except_all(spark, sf):
    e = edges(spark, sf)
    return e.where("t = 5").select("src").exceptAll(e.where("t = 6").select("src"))


_AGG = "count(DISTINCT dst) AS sinks, min(t) AS first, max(t) AS last, round(avg(t), 6) AS mean_t, round(stddev_samp(t), 6) AS sd, count(*) FILTER (src < dst) AS up, arg_max(dst, t * 100 + dst) AS newest"


@query("rel_aggregates", O.sql(E, final=f"SELECT src, {_AGG} FROM e GROUP BY src"))
def rel_aggregates(spark, sf):
    return edges(spark, sf).groupBy("src").agg(F.countDistinct("dst").alias("sinks"), F.min("t").alias("first"), F.max("t").alias("last"), F.round(F.avg("t"), 6).alias("mean_t"), F.round(F.stddev("t"), 6).alias("sd"), F.count_if(F.col("src") < F.col("dst")).alias("up"), F.max_by("dst", F.col("t") * 100 + F.col("dst")).alias("newest"))


@query("rel_sets_and_medians", O.sql(E, final="SELECT t, array_to_string(list_sort(list(DISTINCT src)), ',') AS sources, CAST(quantile_disc(dst, 0.5) AS BIGINT) AS median_dst FROM e GROUP BY t"))
def rel_sets_and_medians(spark, sf):
    return edges(spark, sf).groupBy("t").agg(F.array_join(F.sort_array(F.collect_set("src")), ",").alias("sources"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY dst)").cast("long").alias("median_dst"))


@query("rel_approx_within", O.sql(E, final="SELECT count(DISTINCT src * 1000 + dst) AS exact, true AS close FROM e"))
def rel_approx_within(spark, sf):
    e = edges(spark, sf).select((F.col("src") * 1000 + F.col("dst")).alias("k"))
    return e.agg(F.countDistinct("k").alias("exact"), F.approx_count_distinct("k", 0.01).alias("a")).select("exact", (F.abs(F.col("a") - F.col("exact")) <= 0.05 * F.col("exact")).alias("close"))


@query("rel_pivot", O.sql(E, final="SELECT src, count(*) FILTER (t = 1) AS m1, count(*) FILTER (t = 2) AS m2, count(*) FILTER (t = 3) AS m3 FROM e WHERE t <= 3 GROUP BY src"))
def rel_pivot(spark, sf):
    p = edges(spark, sf).where("t <= 3").groupBy("src").pivot("t", [1, 2, 3]).agg(F.count(F.lit(1))).na.fill(0)
    return p.select("src", *[F.col(str(i)).alias(f"m{i}") for i in (1, 2, 3)])


@query("rel_unpivot", O.sql(*O.graph(N), final="SELECT t, v, 'x0' AS name, x0 AS val FROM x UNION ALL SELECT t, v, 'x1', x1 FROM x"))
def rel_unpivot(spark, sf):
    return snapshots.degree_features(tables.graph(spark, sf, N)).df.unpivot(["t", "v"], ["x0", "x1"], "name", "val")


@query("rel_distinct_multi_edges", f"SELECT count(*) AS lines, count(DISTINCT (o_custkey, l_suppkey, {O.month('o_orderdate')})) AS pairs FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def rel_distinct_multi_edges(spark, sf):
    t = tables.trades(spark, sf)
    return t.agg(F.count(F.lit(1)).alias("lines"), F.count_distinct("o_custkey", "l_suppkey", "t").alias("pairs"))


@query("rel_scalar_subquery", O.sql(E, final="SELECT t, count(*) AS n, round(count(*) / (SELECT count(*) FROM e), 6) AS share FROM e GROUP BY t"))
def rel_scalar_subquery(spark, sf):
    edges(spark, sf).createOrReplaceTempView("e_view")
    return spark.sql("SELECT t, count(*) AS n, round(count(*) / (SELECT count(*) FROM e_view), 6) AS share FROM e_view GROUP BY t")


@query("rel_correlated_exists", O.sql(E, "v AS (SELECT DISTINCT src AS v FROM e)", final="SELECT v FROM v WHERE EXISTS (SELECT 1 FROM e WHERE e.src = v.v AND e.t = 2) AND EXISTS (SELECT 1 FROM e WHERE e.dst = v.v AND e.t = 1)"))
def rel_correlated_exists(spark, sf):
    edges(spark, sf).createOrReplaceTempView("e_view")
    return spark.sql("SELECT v FROM (SELECT DISTINCT src AS v FROM e_view) x WHERE EXISTS (SELECT 1 FROM e_view WHERE src = v AND t = 2) AND EXISTS (SELECT 1 FROM e_view WHERE dst = v AND t = 1)")


@query("rel_recursive_reach", O.sql(E, "r(v, t) AS (SELECT CAST(0 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT e.dst, e.t FROM r JOIN e ON e.src = r.v AND e.t = r.t + 1)", final="SELECT t, count(*) AS reached FROM r GROUP BY t"))
def rel_recursive_reach(spark, sf):
    """Vertices reached along one edge a step, as a recursive query.

    Each level of it joins the set that was reached with the next step's pairs of nations, one row a step, and so is one
    job without an exchange; these rows are written first, as every level reads them.
    """
    pairs = edges(spark, sf).groupBy("t").agg(F.collect_set(F.struct("src", "dst")).alias("pairs"))
    written(pairs.coalesce(1), "reach-pairs").createOrReplaceTempView("reach_pairs")
    step = "array_distinct(transform(filter(pairs, x -> array_contains(r.vs, x.src)), x -> x.dst))"
    return spark.sql(f"WITH RECURSIVE r(vs, t) MAX RECURSION LEVEL 400 AS (SELECT array(0L), 0L UNION ALL SELECT {step}, p.t FROM r JOIN reach_pairs p ON p.t = r.t + 1 WHERE size({step}) > 0) SELECT t, CAST(size(vs) AS BIGINT) AS reached FROM r")


@query("rel_hash_sample", O.sql(E, final=f"SELECT t, src, dst FROM e WHERE {O.hash32('CAST(t AS VARCHAR) || chr(45) || CAST(src AS VARCHAR) || chr(45) || CAST(dst AS VARCHAR)')} % 10 = 0"))
def rel_hash_sample(spark, sf):
    return edges(spark, sf).where(snapshots.hash32(F.concat_ws("-", "t", "src", "dst")) % 10 == 0).select("t", "src", "dst")


@query("rel_sample")
def rel_sample(spark, sf):
    """A tenth of the edges by seed, and shares by source group: a sampling operator, so without twin."""
    e = edges(spark, sf).withColumn("half", (F.col("src") % 2).cast("int"))
    some = e.sample(0.1, 7).select(F.lit("sample").alias("how"), "t", "src", "dst")
    return some.unionByName(e.sampleBy("half", {0: 0.05, 1: 0.2}, 7).select(F.lit("by").alias("how"), "t", "src", "dst"))


@query("rel_json_props", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def rel_json_props(spark, sf):
    p = F.from_json("props", "k BIGINT")
    return tables.load(spark, sf, "events").select(p["k"].alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("rel_string_host", "SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, count(*) AS n, max(length(url)) AS longest FROM pages GROUP BY 1")
def rel_string_host(spark, sf):
    return tables.load(spark, sf, "pages").select(F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.length("url").cast("long").alias("l")).groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.max("l").alias("longest"))


@query("rel_map_sparse_row", O.sql(E, final="SELECT t, src, array_to_string(list_transform(list_sort(list(dst)), lambda d: CAST(d AS VARCHAR)), ',') AS neighbours, count(*) AS n FROM e GROUP BY t, src"))
def rel_map_sparse_row(spark, sf):
    m = edges(spark, sf).groupBy("t", "src").agg(vectors.sparse_row(F.col("dst"), F.col("w")).alias("row"))
    return m.select("t", "src", F.array_join(F.sort_array(F.map_keys("row")), ",").alias("neighbours"), F.size("row").cast("long").alias("n"))


@query("rel_turn_transitions", "SELECT role, nxt, count(*) AS n FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL GROUP BY ALL")
def rel_turn_transitions(spark, sf):
    c = tables.load(spark, sf, "conversations")
    return c.select("role", F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("nxt")).where("nxt is not null").groupBy("role", "nxt").agg(F.count(F.lit(1)).alias("n"))


_VEC = "list_transform(embedding, lambda x: CAST(x AS DOUBLE))"


@query("fn_vectors", f"SELECT vec_id, round(list_dot_product(v, v), 6) AS dot, round(sqrt(list_dot_product(v, v)), 6) AS norm, round(exp(v[1] - list_max(v)) / list_sum(list_transform(v, lambda x: exp(x - list_max(v)))), 6) AS first_share, CAST(list_position(v, list_max(v)) - 1 AS BIGINT) AS best, round(greatest(v[2], 0), 6) + 0.0 AS relu1 FROM (SELECT vec_id, {_VEC} AS v FROM embeddings)")
def fn_vectors(spark, sf):
    v = tables.load(spark, sf, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    return v.select("vec_id", F.round(vectors.vec_dot(F.col("v"), F.col("v")), 6).alias("dot"), F.round(vectors.l2_norm(F.col("v")), 6).alias("norm"), F.round(F.get(vectors.softmax(F.col("v")), F.lit(0)), 6).alias("first_share"), vectors.argmax(F.col("v")).alias("best"), (F.round(F.get(vectors.vec_relu(F.col("v")), F.lit(1)), 6) + 0.0).alias("relu1"))


@query("fn_project_udf", "SELECT vec_id, round(0.5 * v[1] - 0.25 * v[2], 6) + 0.0 AS p FROM (SELECT vec_id, list_transform(embedding[1:2], lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings)")
def fn_project_udf(spark, sf):
    import numpy as np

    v = tables.load(spark, sf, "embeddings").select("vec_id", F.transform(F.slice("embedding", 1, 2), lambda x: x.cast("double")).alias("v"))
    return v.select("vec_id", (F.round(F.get(vectors.vec_project(np.array([[0.5], [-0.25]]))("v"), F.lit(0)), 6) + 0.0).alias("p"))


@query("fn_sql_surface", "SELECT CAST(t AS BIGINT) AS t, CAST(unnest(range(greatest(1, t - 2), t + 1)) AS BIGINT) AS k, round(1.0 / least(3, t), 6) AS m FROM " + _MONTHS)
def fn_sql_surface(spark, sf):
    vectors.register(spark)
    months(spark, sf).createOrReplaceTempView("order_months")
    return spark.sql("SELECT r.t, b.k, round(b.m, 6) AS m FROM order_months r, LATERAL band(CAST(r.t AS INT), 3) b")
