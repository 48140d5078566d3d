"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.shuffle.partitions", CPUS).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from dyngraph.operators import convolve, delta, measures, smooth, snapshots, tasks, training
    from dyngraph.schema import Config, DynamicGraph
    from dyngraph.session import co_located
    from dyngraph.sources import tables
    from dyngraph.storage import release, written

    co_located(spark)
    seconds: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name, fn, repeat=1):
        began = time.perf_counter()
        for _ in range(repeat):
            out = fn()
        seconds[name] = round((time.perf_counter() - began) / repeat, 3)
        return out

    graph = timed("snapshots_cust_supp", lambda: (lambda g: DynamicGraph(written(g.edges, "edges"), written(g.vertices, "vertices"), g.T))(tables.graph(spark, SF_DIR, "cust_supp")))
    small = (lambda g: DynamicGraph(written(g.edges, "edges"), written(g.vertices, "vertices"), g.T))(tables.graph(spark, SF_DIR, "nation_trade"))
    facts["nnz"] = graph.edges.count()
    timed("overlap", lambda: measures.run(snapshots.overlap(graph)))
    grown = timed("edge_life_3", lambda: written(smooth.edge_life(graph, 3).edges, "life"))
    facts["nnz_life_3"] = grown.count()
    timed("m_transform_3", lambda: measures.run(smooth.m_transform_edges(graph, 3).edges))
    costs = timed("transfer_costs", lambda: delta.cost_totals(graph.with_edges(grown), block=10).first())
    facts |= {"base_bytes": costs["full_bytes"], "gd_bytes": costs["delta_bytes"], "adaptive_bytes": costs["adaptive_bytes"], "gd_ratio": costs["delta_ratio"]}
    timed("laplacian", lambda: measures.run(convolve.laplacian(graph)))
    for name in ("window_mean", "skip_lstm", "weight_lstm"):
        m = training.DynamicModel(graph, name, Config())
        timed(f"embedding_{name}", lambda m=m: measures.run(m.forward().df))
    facts["edges_per_s"] = round(facts["nnz_life_3"] / seconds["embedding_window_mean"])
    pairs = written(tasks.link_dataset(small).where("split = 'train'").drop("split"), "pairs")
    for nb in (1, 4):
        m = training.DynamicModel(small, "window_mean", Config(blocks=nb)).store()
        loss, _ = timed(f"epoch_window_mean_blocks{nb}", lambda m=m: m.gradients(pairs))
        facts[f"loss_blocks{nb}"] = round(loss, 9)
    rows = written(snapshots.degree_features(graph).df, "frames")
    timed("exchange_frames", lambda: measures.run(rows.repartition(8, F.col("v"))))
    release(spark)
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "facts": facts, "sf": SF_DIR.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
