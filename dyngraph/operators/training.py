"""Models and full-batch training with re-executed blocks of the timeline.

A model is a stack of layers: convolution in each snapshot, then a recurrence along time. Training goes forward over
all blocks in order, keeping only the small carry at each block's end; then backward over the blocks, each run forward
again from its carry. Gradients are sums over rows, reduced by partial aggregation; only arrays of the parameters'
size (for evolving weights, of T times it) reach the driver.
"""

from __future__ import annotations

import copy

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dyngraph.operators import recur, tasks
from dyngraph.operators.blocks import block_owner, ranges
from dyngraph.operators.convolve import aggregate_neighbors, laplacian, project, times, transposed
from dyngraph.operators.delta import decode_delta, encode_delta, step_counts
from dyngraph.operators.measures import PhaseTimer
from dyngraph.operators.partition import aggregate_shipped, by_vertex_hash, by_vertex_hypergraph, by_vertex_uniform, home, homes, hybrid_tile
from dyngraph.operators.smooth import edge_life, m_transform_edges, m_transform_features
from dyngraph.operators.snapshots import degree_features
from dyngraph.schema import Config, DynamicGraph, FeatureTensor
from dyngraph.session import co_located
from dyngraph.storage import laid_out, scope, stored_bytes, written

#: Frames that a chunk of the LSTM holds at most, on average.
CHUNK_FRAMES = 200_000
MODELS = ("window_mean", "skip_lstm", "weight_lstm", "weight_lstm_h", "static_gcn")


def prepare(g: DynamicGraph, model: str, cfg: Config) -> tuple[DynamicGraph, FeatureTensor]:
    """The input a model is meant for: raw, edge-life or banded-mean graph; features always from the raw directed graph."""
    x = degree_features(g)
    if model == "window_mean":
        return m_transform_edges(g, cfg.window), m_transform_features(x, cfg.window)
    if model.startswith("weight_lstm"):
        return edge_life(g, cfg.life), x
    return g, x


def init_params(model: str, cfg: Config, features: int = 2, seed: int | None = None) -> dict[str, np.ndarray]:
    """Parameters by name; seed None draws from the configuration's."""
    rng = np.random.default_rng(cfg.seed if seed is None else seed)
    draw = lambda a, b: rng.uniform(-1, 1, (a, b)) * np.sqrt(1.5 / a)
    p, width = {}, features
    for k in range(cfg.layers):
        p[f"w{k}"] = draw(width, cfg.hidden)
        if model == "skip_lstm":
            p |= {f"{n}{k}": v for n, v in recur.lstm_params(width + cfg.hidden, cfg.hidden, rng).items()}
        elif model.startswith("weight_lstm"):
            p |= {f"{n}{k}": v for n, v in recur.weight_cell(width, rng).items()}
        width = cfg.hidden
    p["u"] = draw(2 * width if cfg.extra.get("task", "link") == "link" else width, cfg.classes)
    p["b"] = np.zeros(cfg.classes)
    return p


def cell_of(p: dict, k: int, names=("wx", "wh", "b")) -> dict:
    return {n: p[f"{n}{k}"] for n in names}


class DynamicModel:
    """One model on one prepared graph: forward passes, and training by epochs."""

    def __init__(self, g: DynamicGraph, model: str, cfg: Config | None = None, params: dict | None = None, prepared: tuple | None = None):
        if model not in MODELS:
            raise ValueError(model)
        self.cfg = cfg or Config()
        self.model, self.raw = model, g
        self.g, self.x = prepared or prepare(g, model, self.cfg)
        self.params = params or init_params(model, self.cfg, self.x.width)
        self.T = g.T
        self.lap = laplacian(self.g)
        self.first = None
        self.state: dict = {}
        self.stored = False
        self.owner = None
        self.keys: list[int] = []
        self.differences: tuple | None = None
        self.vertices: int | None = None
        self.timer = PhaseTimer()

    def store(self) -> DynamicModel:
        """Writes what every epoch reads: the Laplacian by block, and (with cfg.precompute) the first layer's A X.

        In the snapshot layout both lie in buckets by the processor that owns a step inside its block, and frames are
        sent to the same places, so that a convolution moves no row. With cfg.transfer "delta" or "adaptive" the
        Laplacian is kept as differences instead, and each block is decoded when it is loaded.
        """
        cfg, spark = self.cfg, self.g.spark
        with self.timer.phase("prepare"):
            block, pid = block_owner(F.col("t"), self.T, cfg.blocks, cfg.processors)
            cut = lambda df: df.withColumn("block", block.cast("int"))
            if cfg.layout == "snapshot":
                co_located(spark)
                self.keys = homes(spark, cfg.processors)
                put = lambda df, tag: laid_out(cut(self._home(df)), tag, "home", cfg.processors, ["block"])
            else:
                put = lambda df, tag: written(cut(df), tag, ["block"])
                refined = lambda g, p: by_vertex_hypergraph(g, p, rounds=cfg.extra.get("rounds", 2))[0]
                make = {"vertex": by_vertex_uniform, "hash": by_vertex_hash, "hybrid": by_vertex_uniform, "hypergraph": refined}[cfg.layout]
                with scope(spark) as inner:
                    self.owner = inner.keep(make(self.g, cfg.processors), "owner")
            if cfg.transfer == "full":
                self.lap = put(self.lap, "laplacian")
            else:
                self._store_differences(cut, block, pid)
            self.x = FeatureTensor(put(self.x.df, "features"), self.x.width, self.x.name)
            if cfg.precompute:
                s = self.aggregate(self._lap(1, self.T), FeatureTensor(self.x.df.drop("block"), self.x.width))
                self.first = FeatureTensor(put(s.df.drop("home"), "first-layer"), s.width)
        self.stored = True
        return self

    def _home(self, df: DataFrame) -> DataFrame:
        return df.withColumn("home", home(block_owner(F.col("t"), self.T, self.cfg.blocks, self.cfg.processors)[1], self.keys))

    def _store_differences(self, cut, block, pid) -> None:
        """Differences inside each processor's share of each block; adaptive keeps a step in full where that is no larger."""
        g = DynamicGraph(written(self.lap.select("t", "src", "dst", F.col("a").alias("w")), "laplacian"), self.g.vertices, self.T)
        at = g.spark.range(1, self.T + 1).select(F.col("id").alias("t")).withColumns({"b": block, "p": pid})
        plan = at.groupBy("b", "p").agg(F.min("t").alias("t")).select("t", F.lit(True).alias("whole"))
        plan = at.select("t").join(plan, "t", "left").na.fill(False, ["whole"])
        if self.cfg.transfer == "adaptive":
            dearer = F.col("nnz") <= F.col("ext_prev") + F.col("ext_next")
            plan = plan.join(step_counts(g), "t").select("t", (F.col("whole") | dearer).alias("whole"))
        plan = written(plan, "difference-plan")
        indices, values = encode_delta(g, plan=plan)
        self.differences = (written(cut(indices), "indices", ["block"]), written(cut(values), "values", ["block"]), plan.where("whole").select("t"))

    def loaded_bytes(self) -> int:
        """Size of the stored Laplacian, which an epoch loads twice."""
        return sum(stored_bytes(d) for d in self.differences[:2]) if self.differences else stored_bytes(self.lap)

    def _lap(self, lo: int, hi: int) -> DataFrame:
        """The Laplacian of some steps: read, or decoded from the differences of their blocks."""
        if self.differences is None:
            return self._part(self.lap, lo, hi)
        indices, values, whole = self.differences
        lap = decode_delta(self._part(indices, lo, hi), self._part(values, lo, hi), whole.where(F.col("t").between(lo, hi)), hi).withColumnRenamed("w", "a")
        return self._home(lap).repartition(self.cfg.processors, "home") if self.keys else lap

    def _chunks(self, lo: int, hi: int) -> int:
        """Chunks of vertices for the LSTM: as many as processors, more if a chunk would hold too many frames."""
        if self.vertices is None:
            self.vertices = self.g.vertices.count()
        return max(self.cfg.processors, -(-self.vertices * (hi - lo + 1) // CHUNK_FRAMES))

    def aggregate(self, lap: DataFrame, x: FeatureTensor) -> FeatureTensor:
        if self.owner is None:
            if self.keys and "home" not in x.df.columns:
                x = FeatureTensor(self._home(x.df).repartition(self.cfg.processors, "home"), x.width, x.name)
            return aggregate_neighbors(lap, x)
        tile = hybrid_tile(self.T, 2) if self.cfg.layout == "hybrid" else None
        return aggregate_shipped(lap, x, self.owner, tile)

    def _part(self, df: DataFrame, lo: int, hi: int) -> DataFrame:
        if "block" in df.columns:
            b = lambda t: (t - 1) * self.cfg.blocks // self.T
            df = df.where(F.col("block").between(b(lo), b(hi))).drop("block")
        return df.where(F.col("t").between(lo, hi))

    def _cut(self, x: FeatureTensor, lo: int, hi: int) -> FeatureTensor:
        return FeatureTensor(self._part(x.df, lo, hi), x.width, x.name)

    def weights(self, frames: FeatureTensor | None = None) -> list[tuple]:
        """For each layer with evolving weights: (W_1..W_T, states)."""
        if self.model != "weight_lstm":
            return [(None, None)] * self.cfg.layers
        return [recur.evolve_weights(self.params[f"w{k}"], cell_of(self.params, k), self.T) for k in range(self.cfg.layers)]

    def _summaries(self, x: FeatureTensor, k: int) -> list[np.ndarray]:
        """For each step the highest scoring frames as columns (T * F' * F numbers)."""
        w = self.params[f"w{k}"]
        out = [np.zeros(w.shape) for _ in range(self.T)]
        for r in recur.top_summary(x, w[:, 0], w.shape[1]).collect():
            out[r["t"] - 1][:, r["r"] - 1] = [r[c] for c in x.cols]
        return out

    def _pre(self, s: FeatureTensor, k: int, ws) -> FeatureTensor:
        """The layer's pre-activations from A X."""
        if self.model == "skip_lstm":
            cols = [F.col(c) for c in s.cols] + times(s.cols, self.params[f"w{k}"])
            return FeatureTensor(s.df.select(*s.keys, *[c.alias(f"p{i}") for i, c in enumerate(cols)]), len(cols), "p")
        w = self.params[f"w{k}"] if ws is None else {t + 1: m for t, m in enumerate(ws)}
        return project(s, w, "p")

    def _layer(self, k: int, lap: DataFrame, x: FeatureTensor, lo: int, hi: int, carry, ws, keep: bool) -> tuple:
        s = self._cut(self.first, lo, hi) if k == 0 and self.first is not None else self.aggregate(lap, x)
        if keep and not (k == 0 and self.first is not None):
            s = FeatureTensor(written(s.df, "layer"), s.width, s.name)
        pre = self._pre(s, k, ws)
        y = FeatureTensor(pre.df.select(*pre.keys, *[F.greatest(c, F.lit(0.0)).alias(f"x{i}") for i, c in enumerate(pre.cols)]), pre.width)
        if self.model in ("skip_lstm", "window_mean"):  # to the vertices' places; the next convolution sends frames back to their steps'
            y = FeatureTensor(y.df.drop("home"), y.width)
            if self.keys and self.model == "window_mean" and carry is None:
                y = FeatureTensor(y.df.repartition(self.cfg.processors, "v"), y.width)
        if self.model == "skip_lstm":
            states = recur.lstm(y, cell_of(self.params, k), carry, self._chunks(lo, hi))
            if keep:
                states = written(states, "states")
            z = FeatureTensor(states.select("t", "v", *[F.col(f"h{i}").alias(f"x{i}") for i in range(self.cfg.hidden)]), self.cfg.hidden)
            after = states.where(F.col("t") == hi).drop("t")
        elif self.model == "window_mean":
            z = recur.window_mean(y, self.cfg.window, carry, lo)
            both = y if carry is None else FeatureTensor(y.df.unionByName(carry), y.width)
            after = recur.tail(both, self.cfg.window, hi)
        else:
            z, after = y, None
        return s, y, z, after

    def forward(self, keep: bool = False) -> FeatureTensor:
        """Frames of the last layer for all steps, in one block."""
        x = FeatureTensor(self.x.df.drop("block"), self.x.width)
        lap = self._lap(1, self.T)
        evolved = self.weights()
        for k in range(self.cfg.layers):
            ws = evolved[k][0]
            if self.model == "weight_lstm_h":
                x = FeatureTensor(written(x.df, "summary-input"), x.width)
                ws, _ = recur.evolve_weights(self.params[f"w{k}"], cell_of(self.params, k), self.T, self._summaries(x, k))
            _, _, x, _ = self._layer(k, lap, x, 1, self.T, None, ws, keep)
        return x

    # ---- training -------------------------------------------------------------------------------------------------

    def _head(self, z: FeatureTensor, rows: DataFrame, m: int) -> tuple:
        """(loss share, gradients of u and b, gradients of the frames) of labelled pairs or vertices."""
        u, b = self.params["u"], self.params["b"]
        link = self.cfg.extra.get("task", "link") == "link"
        if link:
            e = tasks.edge_embedding(z, rows)
        else:
            e = FeatureTensor(z.renamed("e").df.join(rows, ["t", "v"]), z.width, "e")
        c = self.cfg.classes
        r = [f"r{k}" for k in range(c)]
        scored = e.df.select("*", *[(q + float(b[k])).alias(r[k]) for k, q in enumerate(times(e.cols, u))])
        top = F.greatest(*r)
        total = sum((F.exp(F.col(k) - top) for k in r), F.lit(0.0))
        scored = scored.withColumn("_loss", tasks.log_loss(r)).withColumns({f"g{k}": (F.exp(F.col(r[k]) - top) / total - (F.col("y") == k).cast("double")) / m for k in range(c)})
        scored = written(scored, "head")
        sums = scored.agg(F.coalesce(F.sum("_loss"), F.lit(0.0)).alias("loss"), *[F.coalesce(F.sum(F.col(a) * F.col(f"g{k}")), F.lit(0.0)).alias(f"u{i}_{k}") for i, a in enumerate(e.cols) for k in range(c)], *[F.coalesce(F.sum(f"g{k}"), F.lit(0.0)).alias(f"b{k}") for k in range(c)]).first()
        du = np.array([[sums[f"u{i}_{k}"] for k in range(c)] for i in range(e.width)])
        db = np.array([sums[f"b{k}"] for k in range(c)])
        g = [f"g{k}" for k in range(c)]
        ends = [("v", u)] if not link else [("u", u[: z.width]), ("v", u[z.width :])]
        part = [scored.select("t", F.col(end).alias("v"), *[q.alias(f"x{i}") for i, q in enumerate(times(g, w.T))]) for end, w in ends]
        dz = part[0] if len(part) == 1 else part[0].unionByName(part[1])
        dz = dz.groupBy("t", "v").agg(*[F.sum(f"x{i}").alias(f"x{i}") for i in range(z.width)])
        return sums["loss"] / m, du, db, FeatureTensor(dz, z.width)

    def _forward_block(self, lo: int, hi: int, carries: list, evolved: list, keep: bool) -> tuple:
        lap = self._lap(lo, hi)
        x = self._cut(self.x, lo, hi)
        kept, after = [], []
        for k in range(self.cfg.layers):
            s, y, z, out = self._layer(k, lap, x, lo, hi, carries[k], evolved[k][0], keep)
            kept.append((s, y, z))
            after.append(out)
            x = z
        return x, kept, after, lap

    def _outer(self, s: FeatureTensor, g: FeatureTensor, by_step: bool):
        """Sums over rows of the outer products of frames and gradients; by step for evolving weights."""
        j = s.renamed("s").df.drop("home").join(g.renamed("g").df.drop("home"), ["t", "v"])
        cells = [F.sum(F.col(f"s{i}") * F.col(f"g{k}")).alias(f"c{i}_{k}") for i in range(s.width) for k in range(g.width)]
        rows = (j.groupBy("t") if by_step else j.groupBy()).agg(*cells).collect()
        take = lambda r: np.array([[r[f"c{i}_{k}"] or 0.0 for k in range(g.width)] for i in range(s.width)])
        return {r["t"]: take(r) for r in rows} if by_step else take(rows[0])

    def _backward_block(self, dz: FeatureTensor, kept: list, carries: list, back: list, lap: DataFrame, lo: int, grads: dict, evolved: list) -> list:
        handed: list = [None] * self.cfg.layers
        for k in range(self.cfg.layers - 1, -1, -1):
            s, y, _ = kept[k]
            if self.model == "skip_lstm":
                out = written(recur.lstm_gradients(y, dz, cell_of(self.params, k), carries[k], back[k], self._chunks(lo, lo + self.T // self.cfg.blocks)), "lstm-grad")
                dy = FeatureTensor(out.where("kind = 0").select("t", "v", *[F.get("g", F.lit(i)).alias(f"x{i}") for i in range(y.width)]), y.width)
                size = len(self.params[f"wx{k}"]) * 4 * self.cfg.hidden + self.cfg.hidden * 4 * self.cfg.hidden + 4 * self.cfg.hidden
                flat = out.where("kind = 1").agg(F.array(*[F.sum(F.get("g", F.lit(i))) for i in range(size)]).alias("g")).first()["g"]
                flat = np.array(flat, float)
                a, b = self.params[f"wx{k}"].size, self.params[f"wh{k}"].size
                for n, v in (("wx", flat[:a]), ("wh", flat[a : a + b]), ("b", flat[a + b :])):
                    grads[f"{n}{k}"] += v.reshape(self.params[f"{n}{k}"].shape)
                names = [f"h{i}" for i in range(self.cfg.hidden)] + [f"c{i}" for i in range(self.cfg.hidden)]
                handed[k] = out.where("kind = 2").select("v", *[F.get("g", F.lit(i)).alias(n) for i, n in enumerate(names)])
            elif self.model == "window_mean":
                spread = recur.window_mean_backward(dz, self.cfg.window)
                df = spread.df if back[k] is None else spread.df.unionByName(back[k])
                df = written(df.groupBy("t", "v").agg(*[F.sum(c).alias(c) for c in spread.cols]), "mean-grad")
                dy = FeatureTensor(df.where(F.col("t") >= lo), spread.width)
                handed[k] = df.where(F.col("t") < lo)
            else:
                dy = dz
            on = y.renamed("y").df.drop("home").join(dy.df.drop("home"), ["t", "v"])
            g = FeatureTensor(on.select("t", "v", *[F.when(F.col(f"y{i}") > 0, F.col(f"x{i}")).otherwise(F.lit(0.0)).alias(f"x{i}") for i in range(y.width)]), y.width)
            g = FeatureTensor(written(g.df, "pre-grad"), g.width)
            w = self.params[f"w{k}"]
            own = g if self.model != "skip_lstm" else FeatureTensor(g.df.select("t", "v", *[F.col(f"x{s.width + i}").alias(f"x{i}") for i in range(w.shape[1])]), w.shape[1])
            dw = self._outer(s, own, evolved[k][0] is not None)
            if evolved[k][0] is None:
                grads[f"w{k}"] += dw
            else:
                for t, m in dw.items():
                    grads["steps"][k][t - 1] += m
            if k:
                if self.model == "skip_lstm":
                    cols = [F.col(f"x{i}") + e for i, e in enumerate(times([f"x{s.width + j}" for j in range(w.shape[1])], w.T))]
                    ds = FeatureTensor(g.df.select("t", "v", *[c.alias(f"x{i}") for i, c in enumerate(cols)]), s.width)
                elif evolved[k][0] is None:
                    ds = project(g, w.T)
                else:
                    ds = project(g, {t + 1: m.T for t, m in enumerate(evolved[k][0])})
                dz = self.aggregate(transposed(lap), ds)
                dz = FeatureTensor(written(dz.df, "down-grad"), dz.width)
        return handed

    def gradients(self, rows: DataFrame, m: int | None = None) -> tuple[float, dict]:
        """Loss and full-batch gradients over cfg.blocks blocks. rows: (t, u, v, y) or (t, v, y).

        weight_lstm_h, an extension, has a forward pass only: its summaries are picked by rank, which has no derivative here.
        """
        if self.model == "weight_lstm_h":
            raise NotImplementedError("weight_lstm_h has no backward pass")
        if not self.stored:
            self.store()
        m = m or rows.count()
        cfg, evolved = self.cfg, self.weights()
        grads: dict = {n: np.zeros_like(v) for n, v in self.params.items()}
        if self.model == "weight_lstm":
            grads["steps"] = [[np.zeros_like(self.params[f"w{k}"]) for _ in range(self.T)] for k in range(cfg.layers)]
        plan = [b for b in ranges(self.T, cfg.blocks) if b[1] <= b[2]]
        spark, loss = self.g.spark, 0.0
        with scope(spark):  # the carries, for the way back
            carries: list[list] = [[None] * cfg.layers]
            for _, lo, hi in plan[:-1]:  # forward: only the carries are kept
                with self.timer.phase("forward"), scope(spark) as block:
                    _, _, after, _ = self._forward_block(lo, hi, carries[-1], evolved, False)
                    carries.append([None if a is None else block.keep(a, "carry") for a in after])
            back: list = [None] * cfg.layers
            for n in range(len(plan) - 1, -1, -1):  # the last block's first run is its only one
                _, lo, hi = plan[n]
                with scope(spark) as block:
                    with self.timer.phase("forward"):
                        z, kept, _, lap = self._forward_block(lo, hi, carries[n], evolved, True)
                    with self.timer.phase("head"):
                        part, du, db, dz = self._head(z, rows.where(F.col("t").between(lo, hi)), m)
                    loss += part
                    grads["u"] += du
                    grads["b"] += db
                    with self.timer.phase("backward"):
                        back = self._backward_block(dz, kept, carries[n], back, lap, lo, grads, evolved)
                        back = [None if h is None or n == 0 else block.keep(h, "back") for h in back]
        if self.model == "weight_lstm":
            for k, steps in enumerate(grads.pop("steps")):
                dw0, cell = recur.evolve_backward(steps, cell_of(self.params, k), evolved[k][1])
                grads[f"w{k}"] += dw0
                for n, v in cell.items():
                    grads[f"{n}{k}"] += v
        return loss, grads

    def step(self, grads: dict) -> None:
        """One update: sgd, momentum or adam."""
        kind, rate = self.cfg.optimizer, self.cfg.rate
        n = self.state["n"] = self.state.get("n", 0) + 1
        for k, g in grads.items():
            if kind == "sgd":
                self.params[k] = self.params[k] - rate * g
                continue
            m = self.state[f"m{k}"] = 0.9 * self.state.get(f"m{k}", 0) + (g if kind == "momentum" else 0.1 * g)
            if kind == "momentum":
                self.params[k] = self.params[k] - rate * m
            else:
                v = self.state[f"v{k}"] = 0.999 * self.state.get(f"v{k}", 0) + 0.001 * g * g
                self.params[k] = self.params[k] - rate * (m / (1 - 0.9**n)) / (np.sqrt(v / (1 - 0.999**n)) + 1e-8)

    def score(self, rows: DataFrame) -> DataFrame:
        z = self.forward()
        if self.cfg.extra.get("task", "link") == "link":
            return tasks.link_scores(z, rows, self.params["u"], self.params["b"])
        r = [f"r{k}" for k in range(self.cfg.classes)]
        e = FeatureTensor(z.df.join(rows, ["t", "v"]), z.width)
        scored = e.df.select("t", "v", "y", *[(q + float(self.params["b"][k])).alias(r[k]) for k, q in enumerate(times(e.cols, self.params["u"]))])
        return scored.withColumn("pred", tasks.argmax(r))

    def train(self, train: DataFrame, test: DataFrame | None = None, epochs: int = 5, patience: int | None = None) -> list[dict]:
        """History of (epoch, loss, accuracy on test); patience stops after so many epochs without a lower loss."""
        train = written(train, "train-rows")
        m, history, best, worse = train.count(), [], float("inf"), 0
        for epoch in range(1, epochs + 1):
            loss, grads = self.gradients(train, m)
            self.step(grads)
            with self.timer.phase("test"), scope(self.g.spark):
                right = tasks.accuracy(self.score(test)).first()["accuracy"] if test is not None else None
            history.append({"epoch": epoch, "loss": float(loss), "accuracy": right})
            worse = 0 if loss < best else worse + 1
            best = min(best, loss)
            if patience and worse >= patience:
                break
        return history


def dense_reference(model: str, edges: list[tuple], ids: list[int], steps: int, x: np.ndarray, params: dict, cfg: Config) -> np.ndarray:
    """Frames (T, N, H) of the last layer with dense matrices on one machine: the sequential run, for tests."""
    at = {v: i for i, v in enumerate(ids)}
    n = len(ids)
    a = np.zeros((steps, n, n))
    for t, s, d, w in edges:
        i, j = at[s], at[d]
        a[t - 1, i, j] = max(a[t - 1, i, j], w)
        a[t - 1, j, i] = max(a[t - 1, j, i], w)
    lap = np.zeros_like(a)
    for t in range(steps):
        off = a[t] * (1 - np.eye(n))
        d = 1 + (off > 0).sum(1)
        lap[t] = off / np.sqrt(np.outer(d, d)) + np.diag((1 + np.diag(a[t])) / d)
    for k in range(cfg.layers):
        w = params[f"w{k}"]
        s = lap @ x
        if model == "skip_lstm":
            y = np.maximum(np.concatenate([s, s @ w], axis=2), 0)
            zero = np.zeros((n, cfg.hidden))
            x = recur.lstm_forward(y, cell_of(params, k), zero, zero)["h"]
        elif model == "weight_lstm":
            ws, _ = recur.evolve_weights(w, cell_of(params, k), steps)
            x = np.maximum(np.stack([s[t] @ ws[t] for t in range(steps)]), 0)
        else:
            y = np.maximum(s @ w, 0)
            x = np.stack([y[max(0, t - cfg.window + 1) : t + 1].mean(0) for t in range(steps)]) if model == "window_mean" else y
    return x


def clone(params: dict) -> dict:
    return copy.deepcopy(params)
