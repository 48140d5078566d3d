"""Recurrent components along the time of each vertex, and along the evolution of weights."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dyngraph.operators.smooth import m_transform_features
from dyngraph.schema import FeatureTensor

GATES = 4  # in, forget, candidate, out


def lstm_params(width: int, hidden: int, rng: np.random.Generator | None = None) -> dict[str, np.ndarray]:
    """wx (width x 4 hidden), wh (hidden x 4 hidden), b; by formula without a generator, so that SQL can follow."""
    if rng is None:
        from dyngraph.schema import fixed_weights

        return {"wx": fixed_weights(width, GATES * hidden, 1), "wh": fixed_weights(hidden, GATES * hidden, 2), "b": fixed_weights(1, GATES * hidden, 3)[0]}
    scale = 1 / np.sqrt(hidden)
    return {"wx": rng.uniform(-scale, scale, (width, GATES * hidden)), "wh": rng.uniform(-scale, scale, (hidden, GATES * hidden)), "b": rng.uniform(-scale, scale, GATES * hidden)}


def _sig(x):
    return 1 / (1 + np.exp(-x))


def lstm_forward(x: np.ndarray, p: dict, h: np.ndarray, c: np.ndarray) -> dict:
    """All steps of x (T, n, width) from state (h, c), every vertex at once; keeps what the way back needs."""
    steps, n, _ = x.shape
    hidden = h.shape[1]
    out = {k: np.zeros((steps, n, hidden)) for k in ("i", "f", "g", "o", "h", "c", "tc")}
    h0, c0 = h, c
    for t in range(steps):
        z = x[t] @ p["wx"] + h @ p["wh"] + p["b"]
        i, f, g, o = _sig(z[:, :hidden]), _sig(z[:, hidden : 2 * hidden]), np.tanh(z[:, 2 * hidden : 3 * hidden]), _sig(z[:, 3 * hidden :])
        c = f * c + i * g
        tc = np.tanh(c)
        h = o * tc
        for k, v in zip(("i", "f", "g", "o", "h", "c", "tc"), (i, f, g, o, h, c, tc)):
            out[k][t] = v
    return out | {"h0": h0, "c0": c0}


def lstm_backward(x: np.ndarray, p: dict, s: dict, dz: np.ndarray, dh: np.ndarray, dc: np.ndarray) -> tuple:
    """Through time: gradients of the inputs, of the parameters, and of the state before the first step."""
    dx, g = np.zeros_like(x), {k: np.zeros_like(v) for k, v in p.items()}
    for t in range(len(x) - 1, -1, -1):
        before_h, before_c = (s["h"][t - 1], s["c"][t - 1]) if t else (s["h0"], s["c0"])
        i, f, cand, o, tc = (s[k][t] for k in ("i", "f", "g", "o", "tc"))
        dh = dh + dz[t]
        dc = dc + dh * o * (1 - tc * tc)
        d = np.concatenate([dc * cand * i * (1 - i), dc * before_c * f * (1 - f), dc * i * (1 - cand * cand), dh * tc * o * (1 - o)], axis=1)
        g["wx"] += x[t].T @ d
        g["wh"] += before_h.T @ d
        g["b"] += d.sum(0)
        dx[t] = d @ p["wx"].T
        dh, dc = d @ p["wh"].T, dc * f
    return dx, g, dh, dc


def tensor(pdf: pd.DataFrame, cols: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Steps, vertices and the (T, n, width) array of a chunk's dense rows."""
    pdf = pdf.sort_values(["t", "v"], kind="stable")
    ts, vs = np.unique(pdf["t"]), np.unique(pdf["v"])
    return ts, vs, pdf[cols].to_numpy(float).reshape(len(ts), len(vs), len(cols))


def chunk(chunks: int):
    """Chunk of a vertex. A chunk's frames must fit a task: chunks grows with the number of vertices."""
    return F.pmod(F.xxhash64("v"), F.lit(chunks)).cast("int")


def _state_cols(hidden: int) -> list[str]:
    return [f"h{i}" for i in range(hidden)] + [f"c{i}" for i in range(hidden)]


def with_carry(df: DataFrame, carry: DataFrame | None, names: list[str]) -> DataFrame:
    """df with the vertex's carry columns, zeros where there is none."""
    if carry is None:
        return df.withColumns({f"in_{c}": F.lit(0.0) for c in names})
    c = carry.select("v", *[F.col(n).alias(f"in_{n}") for n in names])
    return df.join(c, "v", "left").na.fill(0.0, [f"in_{n}" for n in names])


def lstm(x: FeatureTensor, p: dict, carry: DataFrame | None = None, chunks: int = 8, backend: str = "arrow") -> DataFrame:
    """(t, v, h*, c*): state after each step, from the carry (v, h*, c*) or zeros."""
    hidden = len(p["wh"])
    states = _state_cols(hidden)
    if backend == "catalyst":
        return _lstm_expressions(x, p, carry)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ts, vs, a = tensor(pdf, x_cols)
        first = pdf[pdf["t"] == ts[0]].sort_values("v")[[f"in_{s}" for s in states]].to_numpy(float)
        s = lstm_forward(a, p, first[:, :hidden], first[:, hidden:])
        flat = np.concatenate([s["h"], s["c"]], axis=2).reshape(-1, 2 * hidden)
        out = pd.DataFrame(flat, columns=states)
        out.insert(0, "v", np.tile(vs, len(ts)))
        out.insert(0, "t", np.repeat(ts, len(vs)))
        return out

    x_cols = x.cols
    schema = "t long, v long, " + ", ".join(f"{c} double" for c in states)
    return with_carry(x.df, carry, states).groupBy(chunk(chunks).alias("q")).applyInPandas(run, schema)


def _lstm_expressions(x: FeatureTensor, p: dict, carry: DataFrame | None) -> DataFrame:
    """The same in expressions only: a fold over each vertex's sorted frames."""
    hidden = len(p["wh"])
    states = _state_cols(hidden)
    rows = with_carry(x.df, carry, states)
    frames = F.array_sort(F.collect_list(F.struct("t", *x.cols)))
    by_v = rows.groupBy("v").agg(frames.alias("s"), *[F.first(f"in_{c}").alias(f"in_{c}") for c in states])
    doubles = "array<double>"

    def step(acc, e):
        state = acc["state"]
        z = []
        for k in range(GATES * hidden):
            z.append(sum((e[c] * float(p["wx"][i, k]) for i, c in enumerate(x.cols)), F.lit(float(p["b"][k]))) + sum((F.get(state, F.lit(i)) * float(p["wh"][i, k]) for i in range(hidden)), F.lit(0.0)))
        sig = lambda c: 1 / (1 + F.exp(-c))
        c = [sig(z[hidden + k]) * F.get(state, F.lit(hidden + k)) + sig(z[k]) * F.tanh(z[2 * hidden + k]) for k in range(hidden)]
        h = [sig(z[3 * hidden + k]) * F.tanh(c[k]) for k in range(hidden)]
        new = F.array(*h, *c)
        return F.struct(new.alias("state"), F.concat(acc["out"], F.array(F.struct(e["t"].alias("t"), new.alias("s")))).alias("out"))

    zero = F.struct(F.array(*[F.col(f"in_{c}") for c in states]).cast(doubles).alias("state"), F.array().cast(f"array<struct<t:bigint,s:{doubles}>>").alias("out"))
    out = by_v.select("v", F.explode(F.aggregate("s", zero, step)["out"]).alias("r"))
    return out.select("r.t", "v", *[F.get("r.s", F.lit(i)).alias(c) for i, c in enumerate(states)])


def lstm_gradients(x: FeatureTensor, dz: FeatureTensor, p: dict, carry: DataFrame | None = None, grad_carry: DataFrame | None = None, chunks: int = 8) -> DataFrame:
    """(kind, t, v, g): kind 0 input gradients of (t, v); 1 one row of parameter gradients a chunk; 2 gradients of the carry of v."""
    hidden = len(p["wh"])
    states, x_cols = _state_cols(hidden), x.cols
    d_cols = [f"d{i}" for i in range(hidden)]
    up = dz.renamed("d").df
    rows = x.df.join(up, ["t", "v"], "left").na.fill(0.0, d_cols)
    rows = with_carry(rows, carry, states)
    back = grad_carry.select("v", *[F.col(c).alias(f"b_{c}") for c in states]) if grad_carry is not None else None
    rows = rows.join(back, "v", "left").na.fill(0.0, [f"b_{c}" for c in states]) if back is not None else rows.withColumns({f"b_{c}": F.lit(0.0) for c in states})

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ts, vs, a = tensor(pdf, x_cols)
        _, _, d = tensor(pdf, d_cols)
        first = pdf[pdf["t"] == ts[0]].sort_values("v")
        start, end = first[[f"in_{s}" for s in states]].to_numpy(float), first[[f"b_{s}" for s in states]].to_numpy(float)
        s = lstm_forward(a, p, start[:, :hidden], start[:, hidden:])
        dx, g, dh, dc = lstm_backward(a, p, s, d, end[:, :hidden], end[:, hidden:])
        flat = np.concatenate([g["wx"].ravel(), g["wh"].ravel(), g["b"]])
        return pd.concat(
            [
                pd.DataFrame({"kind": 0, "t": np.repeat(ts, len(vs)), "v": np.tile(vs, len(ts)), "g": list(dx.reshape(-1, dx.shape[2]))}),
                pd.DataFrame({"kind": [1], "t": [0], "v": [0], "g": [flat]}),
                pd.DataFrame({"kind": 2, "t": 0, "v": vs, "g": list(np.concatenate([dh, dc], axis=1))}),
            ]
        )

    return rows.groupBy(chunk(chunks).alias("q")).applyInPandas(run, "kind int, t long, v long, g array<double>")


def window_mean(x: FeatureTensor, span: int, carry: DataFrame | None = None, first: int = 1) -> FeatureTensor:
    """Banded mean of frames from step `first` on; carry: the span - 1 frames before it."""
    if carry is None:
        return m_transform_features(x, span)
    both = FeatureTensor(x.df.unionByName(carry.select("t", "v", *x.cols)), x.width, x.name)
    return m_transform_features(both, span).keep(F.col("t") >= first)


def tail(x: FeatureTensor, span: int, last: int) -> DataFrame:
    """The span - 1 frames up to step `last`: the carry of the banded mean."""
    return x.df.where((F.col("t") > last - (span - 1)) & (F.col("t") <= last))


def window_mean_backward(dy: FeatureTensor, span: int) -> FeatureTensor:
    """Adjoint of the banded mean: frame k gets the gradients of t = k .. k + span - 1, each over min(span, t). Frames before the block appear too."""
    k = F.explode(F.sequence(F.greatest(F.col("t") - span + 1, F.lit(1).cast("long")), F.col("t")))
    n = F.least(F.lit(span).cast("long"), F.col("t"))
    spread = dy.df.select(k.alias("k"), "v", *[(F.col(c) / n).alias(c) for c in dy.cols])
    return FeatureTensor(spread.groupBy(F.col("k").alias("t"), "v").agg(*[F.sum(c).alias(c) for c in dy.cols]), dy.width, dy.name)


def weight_cell(width: int, rng: np.random.Generator | None = None) -> dict[str, np.ndarray]:
    """Cell of a recurrence over the columns of a width x F' matrix: one column is one item, its rows are features."""
    return lstm_params(width, width, rng)


def evolve_weights(w0: np.ndarray, cell: dict, steps: int, summaries: list[np.ndarray] | None = None) -> tuple[list[np.ndarray], list[dict]]:
    """W_1 .. W_T from W_0, and the states kept for the way back.

    The input of each step is the matrix before, or with summaries (an extension: one matrix of the same shape a
    step, made of the vertices that score highest) that summary.
    """
    h, c, out, states = w0.T, np.zeros_like(w0.T), [], []
    for t in range(steps):
        x = h if summaries is None else summaries[t].T
        s = lstm_forward(x[None], cell, h, c)
        s["x"] = x[None]
        h, c = s["h"][0], s["c"][0]
        out.append(h.T)
        states.append(s)
    return out, states


def evolve_backward(dw: list[np.ndarray], cell: dict, states: list[dict], own_input: bool = True) -> tuple[np.ndarray, dict]:
    """Gradients of W_0 and the cell from those of every W_t; a step's matrix is both state and, with own_input, input of the next."""
    g = {k: np.zeros_like(v) for k, v in cell.items()}
    dh, dc = np.zeros_like(dw[0].T), np.zeros_like(dw[0].T)
    for t in range(len(dw) - 1, -1, -1):
        dx, part, dh, dc = lstm_backward(states[t]["x"], cell, states[t], dw[t].T[None], dh, dc)
        for k in g:
            g[k] += part[k]
        if own_input:
            dh = dh + dx[0]
    return dh.T, g


def top_summary(x: FeatureTensor, score: np.ndarray, k: int) -> DataFrame:
    """(t, r, x*): for each step the k frames that score highest along a direction, scaled by tanh of the score; ties to the smaller id."""
    from pyspark.sql import Window

    norm = float(np.linalg.norm(score)) or 1.0
    s = sum((F.col(c) * float(a) / norm for c, a in zip(x.cols, score)), F.lit(0.0))
    rows = x.df.withColumn("_s", s).withColumn("r", F.row_number().over(Window.partitionBy("t").orderBy(F.desc("_s"), "v")))
    return rows.where(F.col("r") <= k).select("t", F.col("r").cast("long").alias("r"), *[(F.col(c) * F.tanh("_s")).alias(c) for c in x.cols])
