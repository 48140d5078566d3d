"""Data distribution: owners of snapshots and vertices, redistribution, and the volumes that they cost."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from dyngraph.operators.snapshots import dense_rank, symmetrize
from dyngraph.schema import DynamicGraph, FeatureTensor
from dyngraph.storage import written


def snapshot_owner(t, steps: int, processors: int):
    """Owner of a step: contiguous balanced ranges."""
    return F.floor((t - 1) * processors / steps).cast("int")


def by_vertex_uniform(g: DynamicGraph, processors: int) -> DataFrame:
    """(v, q): contiguous balanced ranges of the sorted ids. The number of vertices is counted first (action)."""
    n = g.vertices.count()
    return dense_rank(g.vertices).select("v", F.floor(F.col("vid") * processors / max(n, 1)).cast("int").alias("q"))


def by_vertex_hash(g: DynamicGraph, processors: int) -> DataFrame:
    """(v, q) by hash: the control."""
    return g.vertices.select("v", F.pmod(F.xxhash64("v"), F.lit(processors)).cast("int").alias("q"))


def by_snapshot(df: DataFrame, steps: int, processors: int) -> DataFrame:
    """Rows laid out by the owner of their step, one partition an owner; pid stays in the rows and belongs in later keys."""
    return df.withColumn("pid", snapshot_owner(F.col("t"), steps, processors)).repartitionById(processors, F.col("pid"))


def homes(spark: SparkSession, processors: int) -> list[int]:
    """For each processor the smallest key that hash partitioning into so many parts sends to its part."""
    n = 16 * processors
    while True:
        part = F.pmod(F.hash("id"), F.lit(processors))
        found = dict(spark.range(n).groupBy(part.alias("p")).agg(F.min("id")).collect())
        if len(found) == processors:
            return [found[p] for p in range(processors)]
        n *= 2


def home(pid, keys: list[int]):
    """Key of a processor: rows hash-partitioned by it lie with the processor's other rows, in stored buckets as after an exchange."""
    return F.element_at(F.array(*[F.lit(k).cast("long") for k in keys]), (pid + 1).cast("int"))


def to_vertex_layout(y: FeatureTensor, owner: DataFrame, processors: int) -> DataFrame:
    """Frames split into vertex chunks, chunk q to processor q: one exchange of T * N rows."""
    return y.df.join(owner, "v").repartitionById(processors, F.col("q"))


def to_snapshot_layout(z: DataFrame, steps: int, processors: int) -> DataFrame:
    """Frames back to the owners of their steps: the mirrored exchange."""
    return by_snapshot(z.drop("q"), steps, processors)


def pins(g: DynamicGraph) -> DataFrame:
    """(t, u, v): the row of u needs frame (t, v), over both directions of the edges, u itself aside."""
    return symmetrize(g).edges.where("src <> dst").select("t", F.col("src").alias("u"), F.col("dst").alias("v"))


def send_index(g: DynamicGraph, owner: DataFrame, include_self: bool = False) -> DataFrame:
    """(t, v, p, q): frames (t, v) of owner p that processor q needs, each once; without q = p unless asked."""
    need = pins(g).join(owner.select(F.col("v").alias("u"), "q"), "u").select("t", "v", "q").distinct()
    rows = need.join(owner.select("v", F.col("q").alias("p")), "v").select("t", "v", "p", "q")
    return rows if include_self else rows.where("p <> q")


def volume_vertex(g: DynamicGraph, owner: DataFrame) -> DataFrame:
    """One row (lambda_all, lambda_remote): frames that a convolution ships, over all snapshots, with and without the owner itself."""
    rows = send_index(g, owner, include_self=True)
    return rows.agg(F.count(F.lit(1)).alias("lambda_all"), F.count_if(F.col("p") != F.col("q")).alias("lambda_remote"))


def volumes_smoothed(g: DynamicGraph, owners: list[DataFrame], processors: list[int], spans: tuple[int, ...]) -> DataFrame:
    """(k, span, lambda_all, lambda_remote): volume_vertex of g after edge life (or banded mean) of each span, for the k-th of several owners (v, q).

    The processors that need a frame are bits of longs, one row a step and vertex. A frame that is needed at some step is
    needed for the next span - 1 steps too: the row counts at each of them the bits that no later row has set by then,
    so no edge is unrolled.
    """
    wide = owners[0].select("v", F.col("q").alias("q0"))
    for k, owner in enumerate(owners[1:], 1):
        wide = wide.join(owner.select("v", F.col("q").alias(f"q{k}")), "v")
    wide = written(wide, "owners")
    words = [(k, w) for k, p in enumerate(processors) for w in range((p + 63) // 64)]
    bit = {(k, w): F.expr(f"IF(q{k} DIV 64 = {w}, shiftleft(1L, q{k} % 64), 0L)") for k, w in words}
    e = g.edges.where("src <> dst")
    both = e.select("t", F.col("src").alias("u"), F.col("dst").alias("v")).unionByName(e.select("t", F.col("dst").alias("u"), F.col("src").alias("v")))
    need = both.join(wide.withColumnRenamed("v", "u"), "u").groupBy("t", "v").agg(*[F.bit_or(bit[x]).alias(f"m{x[0]}_{x[1]}") for x in words])
    own = Window.partitionBy("v").orderBy("t")
    set_by = lambda x, d: F.coalesce(F.bit_or(f"m{x[0]}_{x[1]}").over(own.rangeBetween(1, d - 1)), F.lit(0).cast("long")) if d > 1 else F.lit(0).cast("long")
    need = need.select("t", "v", *[f"m{k}_{w}" for k, w in words], *[set_by(x, d).alias(f"s{x[0]}_{x[1]}_{d}") for x in words for d in range(1, max(spans) + 1)])
    rows = need.join(wide, "v")

    def total(k: int, span: int, bits):
        left = [F.when(F.col("t") + (d - 1) <= g.T, F.bit_count(bits(x).bitwiseAND(F.bitwise_not(F.col(f"s{x[0]}_{x[1]}_{d}"))))).otherwise(0) for x in words if x[0] == k for d in range(1, span + 1)]
        return F.coalesce(F.sum(sum(left[1:], left[0])), F.lit(0))

    held = lambda x: F.col(f"m{x[0]}_{x[1]}")
    away = lambda x: held(x).bitwiseAND(F.bitwise_not(bit[x]))
    kinds = [F.struct(F.lit(k).alias("k"), F.lit(s).alias("span"), total(k, s, held).alias("lambda_all"), total(k, s, away).alias("lambda_remote")) for k in range(len(owners)) for s in spans]
    return rows.agg(F.array(*kinds).alias("x")).select(F.inline("x"))


def volume_snapshot(spark: SparkSession, steps: int, n: int, processors: list[int], layers: int = 2, widths: tuple[int, int] | None = None, skip_last: bool = False) -> DataFrame:
    """(p, per_exchange, remote, exchanges, units, remote_units, floats): an exchange moves T * N frames whatever P is.

    Two exchanges a layer forward and two backward; skip_last saves the last layer's way back and its mirror. widths:
    of the convolution's and the recurrence's output, which go out and come back.
    """
    k = 4 * layers - 2 * skip_last
    f = (sum(widths) * 2 * layers - 2 * widths[1] * skip_last) if widths else k
    rows = spark.createDataFrame([(p,) for p in processors], "p long")
    units = F.lit(steps * n).cast("long")
    part = (F.col("p") - 1) / F.col("p")
    return rows.select("p", units.alias("per_exchange"), F.round(units * part, 6).alias("remote"), F.lit(k).cast("long").alias("exchanges"), (units * k).alias("units"), F.round(units * k * part, 6).alias("remote_units"), F.round(units * f * part, 6).alias("floats"))


def volume_weight(spark: SparkSession, processors: list[int], params: int) -> DataFrame:
    """Weights that evolve apart from the vertices: no frame moves, only the sum of the gradients."""
    return spark.createDataFrame([(p,) for p in processors], "p long").select("p", F.lit(0).cast("long").alias("units"), (F.col("p") * params).alias("reduced_floats"))


def moved_rows(df: DataFrame, owner: DataFrame, steps: int, processors: int) -> DataFrame:
    """One row: rows, and rows whose snapshot owner is not their vertex owner - counted, not derived."""
    both = df.select("t", "v").join(owner, "v").select(snapshot_owner(F.col("t"), steps, processors).alias("pid"), "q")
    return both.agg(F.count(F.lit(1)).alias("rows"), F.count_if(F.col("pid") != F.col("q")).alias("remote"))


def node_split(processors: DataFrame, per_node: int = 8) -> DataFrame:
    """(p, nodes, intra, inter) for processor counts (p): shares of an all-to-all inside a node and between nodes."""
    k = F.greatest(F.ceil(F.col("p") / per_node), F.lit(1))
    return processors.select("p", k.cast("long").alias("nodes"), F.round(1 / k, 6).alias("intra"), F.round((k - 1) / k, 6).alias("inter"))


def send_matrix(sent: DataFrame) -> DataFrame:
    """(p, q, frames) of a send list."""
    return sent.groupBy(F.col("p").cast("long").alias("p"), F.col("q").cast("long").alias("q")).agg(F.count(F.lit(1)).alias("frames"))


def balance(placed: DataFrame, key: str, processors: int) -> DataFrame:
    """One row: largest and mean number of rows an owner has, and their ratio; owners without rows count."""
    n = placed.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    mean = F.sum("n") / processors
    return n.agg(F.max("n").alias("largest"), F.round(mean, 6).alias("mean"), F.round(F.max("n") / mean, 6).alias("ratio"))


def _in_cells(df: DataFrame, keys: list[str], cells: int = 256) -> DataFrame:
    """df with place, a gapless 0-based rank of v within keys: ranked in cells of hashes, shifted by the cells before."""
    cut = df.withColumn("_c", F.pmod(F.xxhash64("v"), F.lit(cells)))
    sizes = cut.groupBy(*keys, "_c").agg(F.count(F.lit(1)).alias("_n"))
    shift = F.coalesce(F.sum("_n").over(Window.partitionBy(*keys).orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    own = F.row_number().over(Window.partitionBy(*keys, "_c").orderBy("v")) - 1
    return cut.withColumn("_r", own).join(sizes.withColumn("_s", shift).drop("_n"), [*keys, "_c"]).withColumn("place", F.col("_r") + F.col("_s")).drop("_c", "_r", "_s")


def by_vertex_hypergraph(g: DynamicGraph, processors: int, eps: float = 0.05, rounds: int = 6, start: DataFrame | None = None) -> tuple[DataFrame, list[tuple[int, int]]]:
    """(owner (v, q), trace of (round, lambda)): balanced refinement of the owners, which lowers the frames shipped.

    A net is a frame (t, v), its pins the rows that need it. In each round half of the vertices (by parity of their
    hash and the round) may move to the part with the largest gain; a part takes the best movers that it has room
    for. A round that doesn't lower the volume is taken back. Owners stay a table.
    """
    p = written(pins(g), "pins")
    owner = written(start if start is not None else by_vertex_uniform(g, processors), "owner")
    n = g.vertices.count()
    room = int((1 + eps) * n / processors) + 1
    total = lambda o: p.join(o.withColumnRenamed("v", "u"), "u").select("t", "v", "q").distinct().count()
    best = total(owner)
    trace = [(0, best)]
    misses = 0
    for r in range(1, rounds + 1):
        owned = p.join(owner.withColumnRenamed("v", "u"), "u")
        held = owned.groupBy("t", "v", "q").agg(F.count(F.lit(1)).alias("n"))
        alone = owned.join(held, ["t", "v", "q"]).groupBy("u").agg(F.count_if(F.col("n") == 1).alias("frees"), F.count(F.lit(1)).alias("nets"), F.first("q").alias("own"))
        present = p.join(held.select("t", "v", "q"), ["t", "v"]).groupBy("u", "q").agg(F.count(F.lit(1)).alias("present"))
        gain = present.join(alone, "u").where("q <> own").withColumn("gain", F.col("frees") - F.col("nets") + F.col("present"))
        movers = gain.where((F.col("gain") > 0) & (F.pmod(F.xxhash64("u"), F.lit(2)) == r % 2))
        choice = movers.groupBy("u").agg(F.max_by(F.struct("q", "gain"), F.struct("gain", -F.col("q"))).alias("m")).select(F.col("u").alias("v"), "m.q", "m.gain")
        sizes = owner.groupBy("q").agg(F.count(F.lit(1)).alias("size"))
        # movers are counted by gain and part; only the gain at which a part fills up is ranked, in cells of hashes
        choice = written(choice, "movers")
        counts = choice.groupBy("q", "gain").agg(F.count(F.lit(1)).alias("n"))
        free = F.lit(room) - F.coalesce("size", F.lit(0)) - (F.sum("n").over(Window.partitionBy("q").orderBy(F.desc("gain"))) - F.col("n"))
        counts = counts.join(sizes, "q", "left").select("q", "gain", "n", free.alias("free")).where("free > 0")
        ranked = _in_cells(choice.join(counts, ["q", "gain"]), ["q", "gain"])
        moved = ranked.where("place < free").select("v", F.col("q").alias("to"))
        new = written(owner.join(moved, "v", "left").select("v", F.coalesce("to", "q").alias("q")), "owner")
        now = total(new)
        if now < best:
            owner, best, misses = new, now, 0
        else:
            misses += 1
        trace.append((r, best))
        if misses == 2:
            break
    return owner, trace


def relabel(g: DynamicGraph, owner: DataFrame) -> tuple[DynamicGraph, DataFrame]:
    """The graph with ids that make each part one range, and the table (v, new_v)."""
    sizes = owner.groupBy("q").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.withColumn("shift", F.coalesce(F.sum("n").over(Window.orderBy("q").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("q", "shift")
    names = _in_cells(owner, ["q"]).join(F.broadcast(before), "q").select("v", (F.col("place") + F.col("shift")).cast("long").alias("new_v"))
    a, b = names.select(F.col("v").alias("src"), F.col("new_v").alias("s")), names.select(F.col("v").alias("dst"), F.col("new_v").alias("d"))
    edges = g.edges.join(a, "src").join(b, "dst").select("t", F.col("s").alias("src"), F.col("d").alias("dst"), "w")
    return DynamicGraph(edges, names.select(F.col("new_v").alias("v")), g.T), names


def aggregate_shipped(lap: DataFrame, x: FeatureTensor, owner: DataFrame, tile=None) -> FeatureTensor:
    """Convolution in a vertex layout: needed frames are shipped to each processor by the send list, then met locally.

    tile: expression of further tile keys over t (time ranges of a hybrid time x vertex layout), or none. The result
    equals that of the snapshot layout.
    """
    z = tile if tile is not None else F.lit(0)
    rows = lap.join(owner.withColumnRenamed("v", "src"), "src").withColumn("z", z)
    need = rows.select("z", "q", "t", F.col("dst").alias("v")).distinct()
    shipped = need.join(x.df, ["t", "v"]).withColumnRenamed("v", "dst")
    out = rows.join(shipped, ["z", "q", "t", "dst"]).groupBy("z", "q", "t", "src").agg(*[F.sum(F.col("a") * F.col(c)).alias(c) for c in x.cols])
    return FeatureTensor(out.select("t", F.col("src").alias("v"), *x.cols), x.width, x.name)


def hybrid_tile(steps: int, ranges: int):
    """Time range of a step, for aggregate_shipped: processors form a grid of ranges x vertex parts."""
    return F.floor((F.col("t") - 1) * ranges / steps)
