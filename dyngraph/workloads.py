"""The experiments, re-expressed on the given tables: one result table each, with the axes of the published one."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dyngraph import oracles as O
from dyngraph import storage
from dyngraph.catalog import N, T, query
from dyngraph.operators import blocks, convolve, delta, measures, partition, smooth, snapshots, tasks, training
from dyngraph.schema import Config, DynamicGraph
from dyngraph.sources import tables
from dyngraph.storage import written

PROCESSORS = [1, 2, 4, 8, 16, 32, 64, 128]
#: Which input each model is meant for: its graph and the floats of its recurrent state and exchanged frames.
INPUTS = {"skip_lstm": "raw", "weight_lstm": "life", "window_mean": "mean"}


def fixed(g: DynamicGraph) -> DynamicGraph:
    return DynamicGraph(written(g.edges, "edges"), written(g.vertices, "vertices"), g.T)


def smoothed(g: DynamicGraph, how: str, span: int) -> DynamicGraph:
    return g if how == "raw" else fixed(smooth.edge_life(g, span) if how == "life" else smooth.m_transform_edges(g, span))


def dataset_table(spark: SparkSession, sf: str, spans: tuple[int, ...] = (3, 6, 12)) -> DataFrame:
    """(graph, n, steps, nnz, span, nnz_smoothed, growth) of the five graphs."""
    out = None
    for name in O.STEPS:
        g = fixed(tables.graph(spark, sf, name))
        for span in spans:
            row = snapshots.graph_stats(g).crossJoin(smooth.smoothing_growth(g, span).drop("nnz")).select(F.lit(name).alias("graph"), "n", "steps", "nnz", "span", "nnz_smoothed", "growth")
            out = row if out is None else out.unionByName(row)
    return out


def transfer_table(spark: SparkSession, sf: str, names=tuple(O.STEPS), span: int = 6, nb: int = 8, processors=PROCESSORS) -> DataFrame:
    """(graph, model, p, full_bytes, delta_bytes, adaptive_bytes, delta_ratio, adaptive_ratio, share) of an epoch's two loads."""
    out = None
    for name in names:
        with storage.scope(spark) as inner:
            raw = fixed(tables.graph(spark, sf, name))
            size = -(-raw.T // nb)
            for model, how in INPUTS.items():
                g = smoothed(raw, how, span)
                counts = inner.keep(delta.step_counts(g), "step-counts")  # T rows, the same for all p
                for p in processors:
                    t = delta.cost_totals(g, block=size, processors=p, counts=counts)
                    row = t.select(F.lit(name).alias("graph"), F.lit(model).alias("model"), F.lit(p).cast("long").alias("p"), "full_bytes", "delta_bytes", "adaptive_bytes", "delta_ratio", "adaptive_ratio", F.lit(max(size - p, 0) / size).alias("share"))
                    out = row if out is None else out.unionByName(row)
    return out


def transfer_times(spark: SparkSession, sf: str, names=("nation_trade", "cust_supp"), nb: int = 8) -> DataFrame:
    """(graph, model, transfer, bytes, ms): size of the stored Laplacian and time to load all blocks of it once, whole and as differences."""
    rows = []
    for name in names:
        g = fixed(tables.graph(spark, sf, name))
        for model in INPUTS:
            for transfer in ("full", "delta", "adaptive"):
                with storage.scope(spark):
                    m = training.DynamicModel(g, model, Config(blocks=nb, transfer=transfer, precompute=False)).store()
                    began = time.perf_counter()
                    for _, lo, hi in blocks.ranges(m.T, nb):
                        measures.run(m._lap(lo, hi))
                    rows.append((name, model, transfer, m.loaded_bytes(), (time.perf_counter() - began) * 1000))
    return spark.createDataFrame(rows, "graph string, model string, transfer string, bytes long, ms double")


def plain_and_blocked(spark: SparkSession, sf: str, name: str = N, blocks_of=(1, 4), budget: int | None = None) -> DataFrame:
    """(model, blocks, loss, ms, peak_bytes, fits): real epochs; most bytes of activations that stood at once, and whether they fit a budget.

    The budget is, if none is given, three quarters of what one block needs.
    """
    g = fixed(tables.graph(spark, sf, name))
    pairs = written(tasks.link_dataset(g, 0.1).where("split = 'train'").drop("split"), "pairs")
    rows = []
    for model in INPUTS:
        found = []
        for nb in blocks_of:
            with storage.scope(spark):
                m = training.DynamicModel(g, model, Config(blocks=nb)).store()
                began = time.perf_counter()
                with storage.peak() as most:
                    loss, _ = m.gradients(pairs)
                found.append((model, nb, float(loss), (time.perf_counter() - began) * 1000, most["bytes"]))
        limit = budget if budget is not None else found[0][4] * 3 // 4
        rows += [(*r, r[4] <= limit) for r in found]
    return spark.createDataFrame(rows, "model string, blocks int, loss double, ms double, peak_bytes long, fits boolean")


def epoch_phases(spark: SparkSession, sf: str, name: str = N, epochs: int = 5, nb: int = 2) -> DataFrame:
    """(model, layout, epoch_ms, transfer_ms, communicate_ms, compute_ms): means of epochs; loads and exchanges are timed on their own, the rest is computing.

    transfer: an epoch's two loads of all blocks; communicate: its exchanges of T * N frames, four a layer but for the
    last one's way back, none with evolving weights.
    """
    g = fixed(tables.graph(spark, sf, name))
    pairs = written(tasks.link_dataset(g, 0.1).where("split = 'train'").drop("split"), "pairs")
    frames = written(snapshots.degree_features(g).df, "frames")
    rows = []
    timed = lambda f: (lambda t: (f(), (time.perf_counter() - t) * 1000)[1])(time.perf_counter())
    for model in INPUTS:
        with storage.scope(spark):
            cfg = Config(blocks=nb)
            m = training.DynamicModel(g, model, cfg).store()
            load = lambda m=m: [measures.run(m._lap(lo, hi)) for _, lo, hi in blocks.ranges(m.T, nb)]
            m.gradients(pairs)  # compiled code
            epoch = sum(timed(lambda m=m: m.gradients(pairs)) for _ in range(epochs)) / epochs
            transfer = sum(timed(load) for _ in range(epochs)) / epochs * 2
            moves = 0 if model == "weight_lstm" else 4 * cfg.layers - 2
            communicate = moves * sum(timed(lambda: measures.run(frames.repartition(cfg.processors, "v"))) for _ in range(epochs)) / epochs
            rows.append((model, cfg.layout, epoch, transfer, communicate, max(epoch - transfer - communicate, 0.0)))
    return spark.createDataFrame(rows, "model string, layout string, epoch_ms double, transfer_ms double, communicate_ms double, compute_ms double")


def feasibility(spark: SparkSession, sf: str, name: str = "cust_supp", budget: float = 5e7) -> DataFrame:
    """(p, nb_least, plain_runs): the fewest blocks that fit a budget of memory, and whether one block would."""
    s = snapshots.graph_stats(tables.graph(spark, sf, name)).first()
    m = blocks.memory_model(spark, s["nnz"], s["n"], s["steps"], 30, 24, [1, 2, 4, 8, 16, 20], PROCESSORS, budget=budget)
    return m.groupBy("p").agg(F.min(F.when(F.col("fits"), F.col("nb"))).alias("nb_least"), F.bool_or(F.col("fits") & (F.col("nb") == 1)).alias("plain_runs"))


def strong_scaling(spark: SparkSession, sf: str, name: str = "cust_supp") -> DataFrame:
    """(p, largest, remote_units, compute_speedup): rows on the busiest processor and frames moved, for logical processors."""
    g = fixed(tables.graph(spark, sf, name))
    n, nnz = g.vertices.count(), g.edges.count()
    out = None
    for p in PROCESSORS:
        placed = g.edges.withColumn("pid", partition.snapshot_owner(F.col("t"), g.T, p))
        row = partition.balance(placed, "pid", p).select(F.lit(p).cast("long").alias("p"), "largest", F.round(F.lit(8.0 * g.T * n) * (p - 1) / p, 6).alias("remote_units"), F.round(nnz / F.col("largest"), 6).alias("compute_speedup"))
        out = row if out is None else out.unionByName(row)
    return out


def weak_scaling(spark: SparkSession, n0: int = 32, steps: int = 256, f: int = 3, sizes=(1, 2, 4), models=tuple(INPUTS)) -> DataFrame:
    """(model, p, nnz, ms, per_s, scaled): one forward pass on random graphs that grow with p."""
    rows = []
    for p in sizes:
        with storage.scope(spark):
            g = fixed(snapshots.random_gnm(spark, steps, n0 * p, f))
            for model in models:
                m = training.DynamicModel(g, model, Config(window=3)).store()
                nnz = m.g.edges.count()
                began = time.perf_counter()
                measures.run(m.forward().df)
                rows.append((model, p, nnz, (time.perf_counter() - began) * 1000))
    return measures.throughput_table(spark.createDataFrame(rows, "model string, p long, nnz long, ms double"), ["model"])


def exchanged_width(model: str, hidden: int = 6, layers: int = 2, features: int = 2) -> int:
    """Floats of a frame in the exchanges of one pass: out from the convolution, back from the recurrence, layer by layer."""
    if model == "weight_lstm":
        return 0
    into = [features if k == 0 else hidden for k in range(layers)]
    return sum((hidden + w if model == "skip_lstm" else hidden) + hidden for w in into)


def layout_volumes(spark: SparkSession, sf: str, name: str = "cust_supp", processors=(4, 16, 64), span: int = 6, rounds: int = 2) -> DataFrame:
    """(model, p, snapshot_floats, vertex_floats) an epoch: redistributed frames against frames shipped for the convolutions of refined owners."""
    edges = written(tables.graph(spark, sf, name).edges, "edges")
    raw = DynamicGraph(edges, written(snapshots.vertex_index(edges), "vertices"), O.STEPS[name])
    n, spans = raw.vertices.count(), {model: 1 if how == "raw" else span for model, how in INPUTS.items()}
    kinds = [(model, p) for model in INPUTS for p in processors] if rounds else [(None, p) for p in processors]  # uniform owners are the same for all models
    with storage.scope(spark):
        owners = [partition.by_vertex_hypergraph(smoothed(raw, INPUTS[model], span), p, rounds=rounds)[0] if rounds else partition.by_vertex_uniform(raw, p) for model, p in kinds]
        found = partition.volumes_smoothed(raw, owners, [p for _, p in kinds], tuple(sorted(set(spans.values())))).collect()  # a row a kind and span
    shipped = {(*kinds[r["k"]], r["span"]): r["lambda_remote"] for r in found}
    # the first convolution's product is stored, the second one ships the hidden frames there and their gradients back
    rows = [(model, p, 2.0 * exchanged_width(model) * raw.T * n * (p - 1) / p, float(shipped[model if rounds else None, p, spans[model]] * 6 * 2)) for model in INPUTS for p in processors]
    return spark.createDataFrame(rows, "model string, p long, snapshot_floats double, vertex_floats double")


def layout_times(spark: SparkSession, sf: str, name: str = N, processors=(4, 16), epochs: int = 1) -> DataFrame:
    """(model, p, layout, ms): time of an epoch in the snapshot layout and in that of refined vertex owners."""
    g = fixed(tables.graph(spark, sf, name))
    pairs = written(tasks.link_dataset(g, 0.1).where("split = 'train'").drop("split"), "pairs")
    rows = []
    for model in INPUTS:
        for p in processors:
            for layout in ("snapshot", "hypergraph"):
                with storage.scope(spark):
                    m = training.DynamicModel(g, model, Config(layout=layout, processors=p, blocks=1)).store()
                    began = time.perf_counter()
                    for _ in range(epochs):
                        m.gradients(pairs)
                    rows.append((model, p, layout, (time.perf_counter() - began) * 1000 / epochs))
    return spark.createDataFrame(rows, "model string, p long, layout string, ms double")


def convergence(spark: SparkSession, g: DynamicGraph, models=tuple(INPUTS), epochs: int = 5, theta: float = 0.1, settings=(("snapshot", 1), ("hypergraph", 1), ("snapshot", 4)), **cfg) -> DataFrame:
    """(model, layout, blocks, epoch, loss, accuracy) of link prediction: train on all steps but the last, test on that."""
    rows = []
    with storage.scope(spark):
        g = fixed(g)
        data = written(tasks.link_dataset(g, theta), "pairs")
        for model in models:
            for layout, nb in settings:
                with storage.scope(spark):
                    m = training.DynamicModel(g, model, Config(layout=layout, blocks=nb, **cfg))
                    h = m.train(data.where("split = 'train'").drop("split"), data.where("split = 'test'").drop("split"), epochs)
                rows += [(model, layout, nb, r["epoch"], r["loss"], r["accuracy"]) for r in h]
    return spark.createDataFrame(rows, "model string, layout string, blocks int, epoch int, loss double, accuracy double")


def convergence_gaps(history: DataFrame) -> DataFrame:
    """(model, loss_gap, accuracy_gap) between the curves of the two layouts."""
    one = history.where("blocks = 1")
    parts = [measures.curve_gap(one.where(F.col("model") == m), "snapshot", "hypergraph").select(F.lit(m).alias("model"), "*") for m in INPUTS]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def vertex_labels(spark: SparkSession, sf: str, kind: str) -> tuple[DynamicGraph, DataFrame, int]:
    """(graph, rows (t, v, y), classes): the region of a nation, the market segment of a customer, or whether a vertex has an edge in the next step."""
    if kind == "region":
        g = fixed(tables.graph(spark, sf, N))
        y = tables.load(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("v"), F.col("n_regionkey").cast("long").alias("y"))
        return g, snapshots.grid(g).join(F.broadcast(y), "v").select("t", "v", "y"), 5
    if kind == "segment":
        g = fixed(tables.graph(spark, sf, "cust_supp"))
        c = tables.load(spark, sf, "customer")
        names = [r[0] for r in c.select("c_mktsegment").distinct().orderBy("c_mktsegment").collect()]  # the classes
        y = c.select(F.col("c_custkey").cast("long").alias("v"), (F.array_position(F.array(*[F.lit(n) for n in names]), F.col("c_mktsegment")) - 1).alias("y"))
        return g, snapshots.grid(g).join(y, "v").select("t", "v", "y"), len(names)
    g = fixed(tables.graph(spark, sf, N))
    seen = g.edges.select("t", F.col("src").alias("v")).union(g.edges.select("t", "dst")).distinct().select((F.col("t") - 1).alias("t"), "v", F.lit(1).cast("long").alias("y"))
    return g, snapshots.grid(g).where(F.col("t") < g.T).join(seen, ["t", "v"], "left").na.fill(0, ["y"]), 2


def vertex_classification(spark: SparkSession, sf: str, kind: str = "region", epochs: int = 2) -> DataFrame:
    """(epoch, loss) of vertex labels over all steps."""
    with storage.scope(spark):
        g, rows, classes = vertex_labels(spark, sf, kind)
        m = training.DynamicModel(g, "window_mean", Config(classes=classes, blocks=2, optimizer="adam", rate=0.05, extra={"task": "vertex"}))
        history = m.train(rows, None, epochs)
    return spark.createDataFrame([(r["epoch"], r["loss"]) for r in history], "epoch int, loss double")


def precompute_ablation(spark: SparkSession, sf: str, epochs: int = 2) -> DataFrame:
    """(precompute, loss, ms): the same gradients with and without the stored product of the first layer, over all steps."""
    g = fixed(tables.graph(spark, sf, N))
    rows = written(tasks.link_dataset(g).where("split = 'train'").drop("split"), "pairs")
    out = []
    for on in (True, False):
        with storage.scope(spark):
            m = training.DynamicModel(g, "window_mean", Config(blocks=2, precompute=on)).store()
            began = time.perf_counter()
            loss = sum(m.gradients(rows)[0] for _ in range(epochs)) / epochs
            out.append((on, float(loss), (time.perf_counter() - began) * 1000 / epochs))
    return spark.createDataFrame(out, "precompute boolean, loss double, ms double")


# ---- registered: those whose result doesn't depend on the clock have a twin ------------------------------------------

_ROW = "SELECT '{g}' AS graph, (SELECT count(*) FROM v) AS n, CAST({steps} AS BIGINT) AS steps, (SELECT count(*) FROM e) AS nnz, CAST({span} AS BIGINT) AS span, (SELECT count(*) FROM el) AS nnz_smoothed, round((SELECT count(*) FROM el) / (SELECT count(*) FROM e), 6) AS growth"
query("wl_dataset_table", " UNION ALL ".join("SELECT * FROM (" + O.sql(*O.graph(g)[:2], O.life(s, O.STEPS[g]), final=_ROW.format(g=g, steps=O.STEPS[g], span=s)) + ")" for g in O.STEPS for s in (3, 12)))(lambda spark, sf: dataset_table(spark, sf, (3, 12)))
query("wl_transfer")(lambda spark, sf: transfer_table(spark, sf, ("nation_trade",)))
query("wl_feasibility")(lambda spark, sf: feasibility(spark, sf))
query("wl_strong_scaling", O.sql(*O.graph("cust_supp")[:2], "p AS (SELECT * FROM (VALUES (1::BIGINT), (2), (4), (8), (16), (32), (64), (128)) x(p))", "b AS (SELECT p, max(n) AS largest FROM (SELECT p, ((t - 1) * p) // 80 AS pid, count(*) AS n FROM e, p GROUP BY ALL) GROUP BY p)", final="SELECT p, largest, round(8.0::DOUBLE * 80 * (SELECT count(*) FROM v) * (p - 1) / p, 6) AS remote_units, round((SELECT count(*) FROM e) / largest, 6) AS compute_speedup FROM b"))(lambda spark, sf: strong_scaling(spark, sf))
query("wl_weak_scaling")(lambda spark, sf: weak_scaling(spark, steps=16, sizes=(1, 2)))
query("wl_layout_volumes")(lambda spark, sf: layout_volumes(spark, sf, processors=(4, 16), rounds=0))
query("wl_precompute_ablation")(lambda spark, sf: precompute_ablation(spark, sf, 1))
query("wl_vertex_classification")(lambda spark, sf: vertex_classification(spark, sf, epochs=1))
query("wl_convergence")(lambda spark, sf: convergence(spark, snapshots.planted_communities(spark, 5, 20, 3), ("window_mean",), 2, 0.3, (("snapshot", 1), ("hypergraph", 1)), optimizer="adam", rate=0.05))
