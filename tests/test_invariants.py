"""Invariants of the methods, and the cases that every graph function must take."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from dyngraph.operators import blocks, convolve, delta, measures, partition, recur, smooth, snapshots, tasks, training
from dyngraph.schema import EDGES, Config, DynamicGraph, FeatureTensor, assert_schema, fixed_weights
from dyngraph.sources import edge_files
from dyngraph.storage import written


def made(spark, rows, n, steps):
    return DynamicGraph(spark.createDataFrame(rows, "t long, src long, dst long, w double"), spark.range(n).select(F.col("id").alias("v")), steps)


@pytest.fixture(scope="module")
def odd(spark):
    """An empty snapshot in the middle, an isolated vertex, a self edge, equal and disjoint neighbours."""
    e = {1: [(0, 1), (1, 2)], 2: [(0, 1), (1, 2)], 4: [(3, 3), (4, 0)], 5: [(0, 1)], 6: [(2, 3), (4, 1), (0, 4)]}
    return made(spark, [(t, a, b, float(1 + (a + b) % 3)) for t, p in e.items() for a, b in p], 7, 6)


@pytest.fixture(scope="module")
def rnd(spark):
    g = snapshots.random_gnm(spark, 8, 24, 3)
    return DynamicGraph(written(g.edges, "edges"), g.vertices, g.T)


def rows(df):
    return sorted(map(tuple, df.select("t", "src", "dst", "w").collect()))


@pytest.mark.parametrize("block,p,adaptive", [(None, 1, False), (2, 1, False), (4, 3, False), (3, 9, True), (6, 2, True)])
def test_differences_are_lossless(odd, block, p, adaptive):
    indices, values = delta.encode_delta(odd, block, p, adaptive)
    back = delta.decode_delta(indices, values, delta.whole_steps(odd, block, p, adaptive), odd.T)
    assert rows(back) == rows(odd.edges)


def test_adaptive_is_never_dearer(odd, rnd):
    for g in (odd, rnd):
        for r in delta.step_costs(g, 3, 2).collect():
            assert r["adaptive_bytes"] <= min(r["full_bytes"], r["delta_bytes"])
            if not r["first"]:
                assert (r["delta_bytes"] < r["full_bytes"]) == (r["ext_prev"] + r["ext_next"] < r["nnz"])


def test_smoothing_laws(odd):
    assert rows(smooth.edge_life(odd, 1).edges) == rows(odd.edges) == rows(smooth.m_transform_edges(odd, 1).edges)
    total = sum(r["w"] * min(3, odd.T - r["t"] + 1) for r in odd.edges.collect())
    assert smooth.edge_life(odd, 3).edges.agg(F.sum("w")).first()[0] == pytest.approx(total)
    runs = smooth.compress_runs(smooth.edge_life(odd, 3).edges)
    assert rows(smooth.expand_runs(runs)) == rows(smooth.edge_life(odd, 3).edges)
    assert rows(smooth.expand_runs(runs, 2, 4)) == [r for r in rows(smooth.edge_life(odd, 3).edges) if 2 <= r[0] <= 4]


def test_laplacian_laws(odd, rnd):
    for g in (odd, rnd):
        lap = {(r["t"], r["src"], r["dst"]): r["a"] for r in convolve.laplacian(g).collect()}
        for (t, a, b), x in lap.items():
            assert lap[t, b, a] == pytest.approx(x)
    lap = convolve.laplacian(DynamicGraph(rnd.edges.where("src <> dst").withColumn("w", F.lit(1.0)), rnd.vertices, rnd.T))
    d = snapshots.degrees(DynamicGraph(rnd.edges.where("src <> dst"), rnd.vertices, rnd.T))
    x = snapshots.grid(rnd).join(d, ["t", "v"], "left").select("t", "v", F.sqrt(1 + F.coalesce("deg", F.lit(0))).alias("x0"))
    y = convolve.aggregate_neighbors(lap, FeatureTensor(x, 1)).df.withColumnRenamed("x0", "y")
    assert x.join(y, ["t", "v"]).where("abs(x0 - y) > 1e-9").count() == 0


def test_single_step_and_vertex(spark):
    g = made(spark, [(1, 0, 0, 1.0)], 1, 1)
    m = training.DynamicModel(g, "window_mean", Config(blocks=1))
    assert m.forward().df.count() == 1
    assert delta.cost_totals(g).first()["delta_ratio"] == 1
    assert snapshots.overlap(g).count() == 0


def test_null_endpoints_go(spark):
    df = spark.createDataFrame([(1, 2, 3, 1.0), (1, None, 3, 1.0), (None, 2, 3, 1.0), (1, 2, 3, 2.0)], "t long, src long, dst long, w double")
    assert rows(snapshots.build_snapshots(df, "sum")) == [(1, 2, 3, 3.0)]
    assert_schema(snapshots.build_snapshots(df), EDGES)
    with pytest.raises(TypeError):
        assert_schema(df.drop("w"), EDGES)


def test_blocks_cover_the_timeline(spark):
    for steps, nb in ((12, 3), (7, 3), (5, 5), (4, 9)):
        plan = blocks.ranges(steps, nb)
        assert [t for _, lo, hi in plan for t in range(lo, hi + 1)] == list(range(1, steps + 1))
        assert [tuple(r)[:3] for r in blocks.block_plan(spark, steps, nb).orderBy("block").collect()] == plan
    assert {r["pid"] for r in blocks.owner_in_block(spark, 12, 2, 3).collect()} == {0, 1, 2}


def test_redistribution_volume(rnd):
    for p in (2, 4, 8):
        n, moved = partition.moved_rows(snapshots.grid(rnd), partition.by_vertex_uniform(rnd, p), rnd.T, p).first()
        assert n == rnd.T * 24 and moved == n * (p - 1) // p


def test_refinement_lowers_the_volume(spark):
    g = snapshots.planted_communities(spark, 4, 40, 3)
    g = DynamicGraph(written(g.edges, "edges"), g.vertices, g.T)
    owner, trace = partition.by_vertex_hypergraph(g, 2, eps=0.1, rounds=4)
    assert trace[-1][1] <= trace[0][1] and trace[-1][1] == partition.volume_vertex(g, owner).first()["lambda_all"]
    assert max(r["count"] for r in owner.groupBy("q").count().collect()) <= int(1.1 * 40 / 2) + 1
    all_, remote = partition.volume_vertex(g, owner).first()
    assert remote <= all_


def test_relabelled_parts_are_ranges(rnd):
    owner = partition.by_vertex_hash(rnd, 3)
    g, names = partition.relabel(rnd, owner)
    assert g.edges.count() == rnd.edges.count()
    by = names.join(owner, "v").groupBy("q").agg(F.min("new_v").alias("a"), F.max("new_v").alias("b"), F.count(F.lit(1)).alias("n")).collect()
    assert all(r["b"] - r["a"] + 1 == r["n"] for r in by)


def test_lstm_backends_and_carry(rnd):
    x = snapshots.degree_features(rnd)
    p = recur.lstm_params(2, 3)
    cols = [f"{s}{i}" for s in "hc" for i in range(3)]
    take = lambda df: {(r["t"], r["v"]): [r[c] for c in cols] for r in df.collect()}
    a, b = take(recur.lstm(x, p)), take(recur.lstm(x, p, backend="catalyst"))
    assert all(np.allclose(a[k], b[k], atol=1e-12) for k in a) and len(a) == len(b) == 8 * 24


@pytest.mark.parametrize("model", ["window_mean", "skip_lstm", "weight_lstm"])
def test_gradients(spark, model):
    """Equal over blocks and layouts, and to central differences of a dense version of the whole model."""
    g = snapshots.planted_communities(spark, 4, 8, 3)
    g = DynamicGraph(written(g.edges, "edges"), g.vertices, g.T)
    pairs = written(tasks.link_dataset(g, 0.3).where("split = 'train'").drop("split"), "pairs")
    found = []
    for nb, layout in ((1, "snapshot"), (3, "vertex")):
        m = training.DynamicModel(g, model, Config(hidden=3, blocks=nb, layout=layout, window=2, life=2))
        found.append(m.gradients(pairs))
    (loss, grads), (other, others) = found
    assert loss == pytest.approx(other, rel=1e-9)
    for k in grads:
        assert np.allclose(grads[k], others[k], rtol=1e-9, atol=1e-12)
    cfg = Config(hidden=3, window=2, life=2)
    pg, px = training.prepare(g, model, cfg)
    ids = sorted(r["v"] for r in g.vertices.collect())
    edges = [tuple(r) for r in pg.edges.select("t", "src", "dst", "w").collect()]
    x = np.zeros((g.T, len(ids), 2))
    for r in px.df.collect():
        x[r["t"] - 1, ids.index(r["v"])] = [r["x0"], r["x1"]]
    labelled, params = pairs.collect(), training.init_params(model, cfg)

    def dense(p):
        z = training.dense_reference(model, edges, ids, g.T, x, p, cfg)
        out = 0.0
        for r in labelled:
            s = np.concatenate([z[r["t"] - 1, ids.index(r["u"])], z[r["t"] - 1, ids.index(r["v"])]]) @ p["u"] + p["b"]
            out += np.log(np.exp(s - s.max()).sum()) + s.max() - s[r["y"]]
        return out / len(labelled)

    assert loss == pytest.approx(dense(params), rel=1e-9)
    for name, value in params.items():
        for at in list(np.ndindex(value.shape))[:4]:
            up, down = training.clone(params), training.clone(params)
            up[name][at] += 1e-6
            down[name][at] -= 1e-6
            assert grads[name][at] == pytest.approx((dense(up) - dense(down)) / 2e-6, rel=1e-4, abs=1e-7)


def test_training_learns(spark):
    g = snapshots.planted_communities(spark, 4, 16, 4)
    g = DynamicGraph(written(g.edges, "edges"), g.vertices, g.T)
    data = written(tasks.link_dataset(g, 0.5), "pairs")
    x = FeatureTensor(written(snapshots.grid(g).select("t", "v", (F.col("v") % 2).cast("double").alias("x0"), F.lit(1.0).alias("x1")), "x"), 2)
    m = training.DynamicModel(g, "static_gcn", Config(hidden=4, blocks=1, layers=1, optimizer="adam", rate=0.1), prepared=(g, x))
    h = m.train(data.where("split = 'train'").drop("split"), data.where("split = 'test'").drop("split"), 4)
    assert h[-1]["loss"] < h[0]["loss"]


def test_negatives(rnd):
    s = tasks.sample_links(rnd, 0.2)
    n = {(r["t"], r["y"]): r["count"] for r in s.groupBy("t", "y").count().collect()}
    assert all(n[t, 0] == n[t, 1] for t, _ in n) and s.where("u = v").count() == 0
    clean = tasks.sample_links(rnd, 0.2, reject_existing=True).where("y = 0")
    assert clean.join(rnd.edges.select("t", F.col("src").alias("u"), F.col("dst").alias("v")), ["t", "u", "v"], "left_semi").count() == 0


def test_convolution_moves_nothing_in_its_layout(spark, rnd):
    """With both inputs laid out by the owner of their step, the join and the sum add no exchange."""
    was = {k: spark.conf.get(k) for k in ("spark.sql.adaptive.enabled", "spark.sql.autoBroadcastJoinThreshold")}
    try:
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        lap = partition.by_snapshot(written(convolve.laplacian(rnd), "lap"), rnd.T, 4)
        x = partition.by_snapshot(written(snapshots.degree_features(rnd).df, "x"), rnd.T, 4)
        y = lap.join(x.withColumnRenamed("v", "dst"), ["pid", "t", "dst"]).groupBy("pid", "t", "src").agg(F.sum(F.col("a") * F.col("x0")).alias("x0"))
        assert measures.plan_text(y).count("Exchange") == 2
    finally:
        for k, v in was.items():
            spark.conf.set(k, v)


def test_stores(spark, odd, tmp_path):
    edge_files.write_snapshots(odd, str(tmp_path / "s"), 2)
    assert rows(edge_files.read_snapshots(spark, str(tmp_path / "s"), 2, 5, 2)) == [r for r in rows(odd.edges) if 2 <= r[0] <= 5]
    edge_files.write_delta(odd, str(tmp_path / "d"), 3, 2)
    assert rows(edge_files.read_delta(spark, str(tmp_path / "d"), odd.T)) == rows(odd.edges)
    assert rows(edge_files.read_delta(spark, str(tmp_path / "d"), odd.T, 1)) == [r for r in rows(odd.edges) if r[0] >= 4]
    p = {"w": fixed_weights(2, 3), "b": np.zeros((1, 2))}
    edge_files.save_params(spark, p, str(tmp_path / "p"))
    assert all(np.array_equal(p[k], v) for k, v in edge_files.load_params(spark, str(tmp_path / "p")).items())


@pytest.mark.parametrize("fmt", edge_files.FORMATS)
def test_readers(spark, odd, tmp_path, fmt):
    path = str(tmp_path / fmt)
    e = odd.edges.select("t", "src", "dst", "w")
    if fmt == "text":
        e.selectExpr("concat_ws(' ', t, src, dst, w) AS value").union(spark.createDataFrame([("x y",)], "value string")).write.text(path)
    elif fmt == "csv":
        e.write.option("header", True).csv(path)
    else:
        e.write.format(fmt).save(path)
    good, bad = edge_files.read_edges(spark, path, fmt)
    assert rows(good) == rows(odd.edges) and bad.count() == (fmt == "text")


def test_planner(rnd):
    from dyngraph.plans import planner

    layers = [fixed_weights(2, 3), fixed_weights(3, 2, 1)]
    plan = planner.window_mean_plan(layers, 3)
    assert [n.args.get("order") for n in planner.optimize(plan, epochs=5).chain() if n.kind == "convolve"] == ["stored", "project"]
    take = lambda p: {(r["t"], r["v"]): (r["x0"], r["x1"]) for r in planner.execute(p, rnd, 3).df.collect()}
    a, b = take(plan), take(planner.optimize(plan, 5))
    assert all(np.allclose(a[k], b[k]) for k in a)
    assert "exchanges:" in planner.explain(plan, rnd)


def test_weight_summaries_extension(rnd):
    m = training.DynamicModel(rnd, "weight_lstm_h", Config(hidden=2, layers=1))
    assert m.forward().df.count() == rnd.T * 24


def test_core_does_not_need_the_corpus_operators():
    import os
    import re

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    for folder, _, names in os.walk(os.path.join(root, "dyngraph")):
        if os.path.basename(folder) != "llm":
            for n in names:
                if n.endswith(".py"):
                    assert not re.search(r"dyngraph\.llm|from dyngraph import llm", open(os.path.join(folder, n)).read()), n


def test_online_differences_in_buckets():
    """Runs with repeats, gaps and late rows in any order equal the steps of each pair, one pair after the other."""
    from dyngraph.streaming.online import differences

    rng = np.random.default_rng(4)
    known, last = np.zeros((0, 3), np.int64), {}
    for lo, hi in ((1, 8), (5, 15), (15, 15), (14, 30)):  # later runs bring late rows too
        new = np.stack([rng.integers(0, 4, 40), rng.integers(-2, 2, 40), rng.integers(lo, hi + 1, 40)], 1)
        expect = set()
        for src, dst, t in sorted(map(tuple, new.tolist())):
            before = last.get((src, dst))
            if before is not None and t <= before:
                continue
            if before is None or t > before + 1:
                expect |= {(src, dst, t, "add")} | ({(src, dst, before + 1, "del")} if before is not None else set())
            last[src, dst] = t
        added, removed, known = differences(known, new)
        got = [(*r, "add") for r in added.tolist()] + [(*r, "del") for r in removed.tolist()]
        assert len(got) == len(set(got)) and set(got) == expect
        assert {(s, d): t for s, d, t in known.tolist()} == last and len(known) == len(last)
    assert [len(x) for x in differences(known[:0], known[:0])] == [0, 0, 0]


def test_volumes_of_smoothed_snapshots(odd, rnd):
    """Counting the steps of a need equals shipping over the unrolled snapshots, for both kinds of smoothing."""
    for g in (odd, rnd):
        kinds = [partition.by_vertex_uniform(g, 3), partition.by_vertex_hash(g, 130)]  # the second ones take three longs
        got = {(r["k"], r["span"]): (r["lambda_all"], r["lambda_remote"]) for r in partition.volumes_smoothed(g, kinds, [3, 130], (1, 3)).collect()}
        for k, owner in enumerate(kinds):
            for span in (1, 3):
                for how in (smooth.edge_life, smooth.m_transform_edges):
                    assert got[k, span] == tuple(partition.volume_vertex(how(g, span), owner).first())
