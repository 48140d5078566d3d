"""The model's own plans and what it keeps on disk; ranks at a size where ranges are sampled."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from dyngraph import storage
from dyngraph.operators import measures, snapshots, tasks, training
from dyngraph.schema import Config, DynamicGraph
from dyngraph.storage import written


@pytest.fixture(scope="module")
def planted(spark):
    g = snapshots.planted_communities(spark, 6, 16, 3)
    g = DynamicGraph(written(g.edges, "edges"), written(g.vertices, "vertices"), g.T)
    return g, written(tasks.link_dataset(g, 0.3).where("split = 'train'").drop("split"), "pairs")


@pytest.fixture
def planned(spark):
    """Plans without adaptive changes and broadcasts of small tables."""
    was = {k: spark.conf.get(k) for k in ("spark.sql.adaptive.enabled", "spark.sql.autoBroadcastJoinThreshold")}
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    for k, v in was.items():
        spark.conf.set(k, v)


@pytest.mark.parametrize("model,exchanges", [("window_mean", 3), ("skip_lstm", 3), ("weight_lstm", 0), ("static_gcn", 0)])
def test_exchanges_of_the_models_own_plan(planted, planned, model, exchanges):
    """Two exchanges of frames a layer, but for the last layer's way back; none with evolving weights, none in a convolution."""
    m = training.DynamicModel(planted[0], model, Config(hidden=3, blocks=2)).store()
    assert measures.plan_exchanges(m.forward().df) == exchanges
    lap, x = m._lap(1, m.T), m.x
    assert measures.plan_exchanges(m.aggregate(lap, training.FeatureTensor(x.df.drop("block"), x.width)).df) == 0


def test_exchanges_of_the_way_back(planted, planned):
    """The convolution's adjoint meets frames that were sent to their steps' places once."""
    m = training.DynamicModel(planted[0], "window_mean", Config(hidden=3, blocks=2)).store()
    frames = training.FeatureTensor(written(m.forward().df, "frames"), 3)
    assert measures.plan_exchanges(m.aggregate(training.transposed(m._lap(1, m.T)), frames).df) == 1


@pytest.mark.parametrize("transfer", ["delta", "adaptive"])
def test_transfer_changes_nothing_but_bytes(planted, transfer):
    g, pairs = planted
    a = training.DynamicModel(g, "weight_lstm", Config(hidden=3, blocks=2, life=3))
    b = training.DynamicModel(g, "weight_lstm", Config(hidden=3, blocks=2, life=3, transfer=transfer))
    (x, dx), (y, dy) = a.gradients(pairs), b.gradients(pairs)
    assert x == pytest.approx(y, rel=1e-9) and all(np.allclose(dx[k], dy[k], rtol=1e-8, atol=1e-12) for k in dx)
    assert a.loaded_bytes() > 0 and b.loaded_bytes() > 0


def test_epochs_leave_nothing(spark, planted):
    g, pairs = planted
    m = training.DynamicModel(g, "window_mean", Config(hidden=3, blocks=3)).store()
    held = lambda: sorted(os.listdir(storage.shared_dir(spark).removeprefix("file://")))
    before = held()
    for _ in range(2):
        m.gradients(pairs)
        assert held() == before
    assert {"prepare", "forward", "head", "backward"} <= set(m.timer.ms)


def test_owner_places_fill_every_bucket(spark):
    from dyngraph.operators.partition import homes

    for p in (1, 3, 8, 50):
        keys = homes(spark, p)
        rows = spark.createDataFrame([(k,) for k in keys], "k long").select(F.pmod(F.hash("k"), F.lit(p)).alias("p")).collect()
        assert [r["p"] for r in rows] == list(range(p))


def test_no_gradients_of_the_extension(planted):
    with pytest.raises(NotImplementedError):
        training.DynamicModel(planted[0], "weight_lstm_h", Config(hidden=2)).gradients(planted[1])


def test_area_under_the_ranking_at_size(spark):
    """Five million distinct scores, against ranks of one sort."""
    n = 5_000_000
    score = F.pmod(F.col("id") * 7_368_787 + F.floor(F.col("id") / 3), F.lit(2_147_483_647)) / 1e9
    y = ((F.col("id") % 3 == 0) | (F.xxhash64("id") % 11 == 0)).cast("int")
    rows = spark.range(n).select(y.alias("y"), (score + y * 0.2).alias("r1"), F.lit(0.0).alias("r0"), F.lit(1).alias("pred"))
    rows = written(rows, "scores")
    got = tasks.classification_report(rows).first()["auc"]
    p = rows.select("y", "r1").toPandas()
    rank = p["r1"].rank()
    pos = int(p["y"].sum())
    exact = (rank[p["y"] == 1].sum() - pos * (pos + 1) / 2) / (pos * (n - pos))
    assert got == pytest.approx(exact, abs=2e-6)


def test_dense_rank_without_reuse(spark):
    was = spark.conf.get("spark.sql.exchange.reuse")
    try:
        spark.conf.set("spark.sql.exchange.reuse", "false")
        n = 2_000_000
        ranks = snapshots.dense_rank(spark.range(n).select((F.col("id") * 3 + 5).alias("v")))
        assert ranks.where(F.col("v") != F.col("vid") * 3 + 5).count() == 0 and ranks.count() == n
    finally:
        spark.conf.set("spark.sql.exchange.reuse", was)
