"""A worked example: four vertices, three steps, seven undirected edges."""

import pytest
from pyspark.sql import functions as F

from dyngraph.operators import convolve, delta, partition, smooth, snapshots
from dyngraph.schema import DynamicGraph, FeatureTensor

SNAPS = {1: [(1, 2), (2, 3)], 2: [(1, 2), (2, 3), (3, 4)], 3: [(2, 3), (3, 4), (1, 4)]}


@pytest.fixture(scope="module")
def toy(spark):
    rows = [(t, a, b, 1.0) for t, e in SNAPS.items() for x, y in e for a, b in ((x, y), (y, x))]
    return DynamicGraph(spark.createDataFrame(rows, "t long, src long, dst long, w double"), spark.createDataFrame([(i,) for i in range(1, 5)], "v long"), 3)


def test_convolution(toy):
    d = snapshots.degrees(toy)
    x = snapshots.grid(toy).join(d, ["t", "v"], "left").select("t", "v", F.coalesce("deg", F.lit(0)).cast("double").alias("x0"))
    got = {(r["t"], r["v"]): r["x0"] for r in convolve.aggregate_neighbors(convolve.laplacian(toy), FeatureTensor(x, 1)).df.collect()}
    want = {1: (1.316497, 1.483163, 1.316497, 0), 2: (1.316497, 1.741582, 1.741582, 1.316497), 3: (1.316497, 1.316497, 1.741582, 1.741582)}
    assert got == pytest.approx({(t, v + 1): a for t, row in want.items() for v, a in enumerate(row)}, abs=1e-6)
    lap = {(r["t"], r["src"], r["dst"]): r["a"] for r in convolve.laplacian(toy).collect()}
    assert lap[1, 1, 2] == pytest.approx(0.408248, abs=1e-6) and lap[1, 4, 4] == 1


def test_smoothing(toy):
    def pairs(g):
        return {(r["t"], r["src"], r["dst"]): r["w"] for r in g.edges.collect() if r["src"] < r["dst"]}

    life, mean = pairs(smooth.edge_life(toy, 2)), pairs(smooth.m_transform_edges(toy, 2))
    assert {k[1:]: w for k, w in life.items() if k[0] == 3} == {(1, 2): 1, (2, 3): 2, (3, 4): 2, (1, 4): 1}
    assert {k[1:]: w for k, w in mean.items() if k[0] == 2} == {(1, 2): 1, (2, 3): 1, (3, 4): 0.5}
    assert {k[1:]: w for k, w in mean.items() if k[0] == 3} == {(1, 2): 0.5, (2, 3): 1, (3, 4): 1, (1, 4): 0.5}


def test_costs_and_volumes(toy, spark):
    c = delta.cost_totals(toy, passes=1).first()
    assert (c["full_bytes"], c["delta_bytes"]) == (320, 224)
    owner = spark.createDataFrame([(1, 0), (2, 0), (3, 1), (4, 1)], "v long, q int")
    assert tuple(partition.volume_vertex(toy, owner).first()) == (16, 8)
    assert tuple(partition.moved_rows(snapshots.grid(toy), owner, 2, 2).first())[0] == 12
