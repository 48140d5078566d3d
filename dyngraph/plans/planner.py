"""A small planner over method nodes: rewrites that Catalyst can't make, then DataFrames that Catalyst optimises."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np

from dyngraph.operators import convolve, recur, smooth
from dyngraph.operators.measures import plan_exchanges
from dyngraph.operators.snapshots import degree_features
from dyngraph.schema import DynamicGraph, FeatureTensor


@dataclass(frozen=True)
class Node:
    """One step of a method. kind: features, smooth, laplacian, convolve, mean, lstm, stored."""

    kind: str
    args: dict = field(default_factory=dict, hash=False)
    child: Node | None = None

    def chain(self) -> list[Node]:
        return (self.child.chain() if self.child else []) + [self]


def window_mean_plan(layers: list[np.ndarray], span: int) -> Node:
    n = Node("smooth_features", {"span": span}, Node("features"))
    for w in layers:
        n = Node("mean", {"span": span}, Node("convolve", {"w": w, "order": "aggregate"}, n))
    return n


def skip_lstm_plan(layers: list[np.ndarray], cells: list[dict]) -> Node:
    n = Node("features")
    for w, cell in zip(layers, cells):
        n = Node("lstm", {"cell": cell}, Node("convolve", {"w": w, "concat": True, "order": "aggregate"}, n))
    return n


def optimize(plan: Node, epochs: int = 1) -> Node:
    """Stores A X of the first layer when it is used in several epochs; else projects first where that narrows the frames."""
    if plan.child is None:
        return plan
    child = optimize(plan.child, epochs)
    out = replace(plan, child=child)
    if plan.kind == "convolve":
        first = all(n.kind in ("features", "smooth_features") for n in child.chain())
        w = plan.args["w"]
        if first and epochs > 1:
            out = replace(out, args={**plan.args, "order": "stored"})
        elif not plan.args.get("concat") and w.shape[1] < w.shape[0]:
            out = replace(out, args={**plan.args, "order": "project"})
    return out


def execute(plan: Node, g: DynamicGraph, span: int | None = None) -> FeatureTensor:
    """The frames of a plan on a graph; span smooths the graph by the banded mean first."""
    lap = convolve.laplacian(smooth.m_transform_edges(g, span) if span else g)
    x: FeatureTensor | None = None
    for n in plan.chain():
        if n.kind == "features":
            x = degree_features(g)
        elif n.kind == "smooth_features":
            x = smooth.m_transform_features(x, n.args["span"])
        elif n.kind == "convolve":
            pre = convolve.precompute_first(lap, x) if n.args["order"] == "stored" else None
            layer = convolve.gcn_concat_layer if n.args.get("concat") else convolve.gcn_layer
            x = layer(lap, x, n.args["w"], precomputed=pre)
        elif n.kind == "mean":
            x = recur.window_mean(x, n.args["span"])
        elif n.kind == "lstm":
            h = len(n.args["cell"]["wh"])
            s = recur.lstm(x, n.args["cell"])
            x = FeatureTensor(s.selectExpr("t", "v", *[f"h{i} AS x{i}" for i in range(h)]), h)
        else:
            raise ValueError(n.kind)
    return x


def explain(plan: Node, g: DynamicGraph, span: int | None = None) -> str:
    """The nodes in order of execution, and the number of exchanges of the physical plan."""
    lines = [n.kind + (f" ({n.args['order']})" if "order" in n.args else "") for n in plan.chain()]
    return " -> ".join(lines) + f"; exchanges: {plan_exchanges(execute(plan, g, span).df)}"
