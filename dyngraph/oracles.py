"""Building blocks of the DuckDB twins: common table expressions for graphs, smoothing, convolution and recurrences."""

from __future__ import annotations

import numpy as np

from dyngraph.schema import fixed_weights

STEPS = {"nation_trade": 80, "cust_supp": 80, "cust_part": 80, "supp_part": 83, "user_flow": 30}


def month(c: str) -> str:
    return f"CAST((year({c}) - 1995) * 12 + month({c}) AS BIGINT)"


_LINES = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
DAY = "CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) + 1 AS BIGINT)"
EDGES = {
    "nation_trade": f"SELECT DISTINCT {month('o_orderdate')} AS t, CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, CAST(1 AS DOUBLE) AS w {_LINES} JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey",
    "cust_supp": f"SELECT DISTINCT {month('o_orderdate')} AS t, o_custkey AS src, l_suppkey + 1000000 AS dst, CAST(1 AS DOUBLE) AS w {_LINES}",
    "cust_part": f"SELECT DISTINCT {month('o_orderdate')} AS t, o_custkey AS src, l_partkey + 1000000 AS dst, CAST(1 AS DOUBLE) AS w {_LINES}",
    "supp_part": f"SELECT DISTINCT {month('l_shipdate')} AS t, l_suppkey AS src, l_partkey + 1000000 AS dst, CAST(1 AS DOUBLE) AS w FROM lineitem",
    "user_flow": f"SELECT DISTINCT t, src, dst, CAST(1 AS DOUBLE) AS w FROM (SELECT {DAY} AS t, user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst <> src",
}


def sql(*parts: str, final: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + final


def graph(name: str) -> list[str]:
    """e (edges), v (vertices), g (grid), x (in- and out-degree)."""
    steps = STEPS[name]
    return [
        f"e AS (SELECT * FROM ({EDGES[name]}) WHERE t BETWEEN 1 AND {steps})",
        "v AS (SELECT src AS v FROM e UNION SELECT dst FROM e)",
        f"g AS (SELECT CAST(r.t AS BIGINT) AS t, v.v FROM range(1, {steps + 1}) r(t), v)",
        "x AS (SELECT g.t, g.v, CAST(coalesce(i.n, 0) AS DOUBLE) AS x0, CAST(coalesce(o.n, 0) AS DOUBLE) AS x1 FROM g LEFT JOIN (SELECT t, dst AS v, count(*) AS n FROM e GROUP BY ALL) i USING (t, v) LEFT JOIN (SELECT t, src AS v, count(*) AS n FROM e GROUP BY ALL) o USING (t, v))",
    ]


def life(span: int, steps: int, name: str = "el", edges: str = "e", mean: bool = False) -> str:
    over = f" / least({span}, t)" if mean else ""
    return f"{name} AS (SELECT t, src, dst, sum(w){over} AS w FROM (SELECT CAST(unnest(range(t, least(t + {span - 1}, {steps}) + 1)) AS BIGINT) AS t, src, dst, w FROM {edges}) GROUP BY t, src, dst)"


def cols(width: int, prefix: str = "x") -> list[str]:
    return [f"{prefix}{i}" for i in range(width)]


def mean(span: int, width: int, source: str, name: str) -> str:
    avg = ", ".join(f"avg({c}) OVER (PARTITION BY v ORDER BY t ROWS BETWEEN {span - 1} PRECEDING AND CURRENT ROW) AS {c}" for c in cols(width))
    return f"{name} AS (SELECT t, v, {avg} FROM {source})"


def laplacian(edges: str = "e", degree: str = "count", tag: str = "") -> list[str]:
    d = "CAST(count(*) AS DOUBLE)" if degree == "count" else "sum(w)"
    sy, dg, d1, la = (n + tag for n in ("sy", "dg", "d1", "la"))
    return [
        f"{sy} AS (SELECT t, src, dst, max(w) AS w FROM (SELECT t, src, dst, w FROM {edges} UNION ALL SELECT t, dst, src, w FROM {edges}) GROUP BY ALL)",
        f"{dg} AS (SELECT t, src AS v, {d} AS d FROM {sy} WHERE src <> dst GROUP BY ALL)",
        f"{d1} AS (SELECT g.t, g.v, 1 + coalesce(d, 0) AS d FROM g LEFT JOIN {dg} USING (t, v))",
        f"{la} AS (SELECT s.t, s.src, s.dst, w / sqrt(a.d * b.d) AS a FROM {sy} s JOIN {d1} a ON s.t = a.t AND s.src = a.v JOIN {d1} b ON s.t = b.t AND s.dst = b.v WHERE s.src <> s.dst UNION ALL SELECT a.t, a.v, a.v, (1 + coalesce(s.w, 0)) / a.d FROM {d1} a LEFT JOIN {sy} s ON s.t = a.t AND s.src = a.v AND s.dst = a.v)",
    ]


def aggregate(source: str, width: int, name: str, lap: str = "la") -> str:
    sums = ", ".join(f"sum(a * {c}) AS {c}" for c in cols(width))
    return f"{name} AS (SELECT l.t, l.src AS v, {sums} FROM {lap} l JOIN {source} f ON l.t = f.t AND l.dst = f.v GROUP BY l.t, l.src)"


def dot(names: list[str], w: np.ndarray, j: int) -> str:
    return " + ".join(f"{c} * CAST({w[i, j]:.1f} AS DOUBLE)" for i, c in enumerate(names))


def act(e: str, kind: str) -> str:
    return {"relu": f"greatest({e}, 0)", "sigmoid": f"1 / (1 + exp(-({e})))", "tanh": f"tanh({e})", "identity": f"({e})"}[kind]


def project(source: str, w: np.ndarray, name: str, kind: str = "relu", concat: bool = False) -> str:
    names = cols(w.shape[0])
    parts = [act(c, kind) for c in names] if concat else []
    parts += [act(dot(names, w, j), kind) for j in range(w.shape[1])]
    return f"{name} AS (SELECT t, v, " + ", ".join(f"{p} AS x{i}" for i, p in enumerate(parts)) + f" FROM {source})"


def lstm(source: str, p: dict, name: str, vertices: str = "v") -> str:
    """Recursive: one step of all vertices at a time."""
    width, hidden = len(p["wx"]), len(p["wh"])
    zeros = ", ".join("CAST(0 AS DOUBLE)" for _ in range(2 * hidden))
    state = [f"h{k}" for k in range(hidden)] + [f"c{k}" for k in range(hidden)]
    z = []
    for k in range(4 * hidden):
        e = " + ".join([f"{p['b'][k]:.1f}::DOUBLE"] + [f"f.x{i} * {p['wx'][i, k]:.1f}::DOUBLE" for i in range(width)] + [f"s.h{i} * {p['wh'][i, k]:.1f}::DOUBLE" for i in range(hidden)])
        z.append(f"tanh({e}) AS z{k}" if 2 * hidden <= k < 3 * hidden else f"1 / (1 + exp(-({e}))) AS z{k}")
    inner = f"SELECT f.t, f.v, {', '.join(z)}, {', '.join(f's.c{k}' for k in range(hidden))} FROM {name} s JOIN {source} f ON f.v = s.v AND f.t = s.t + 1"
    new_c = ", ".join(f"z{hidden + k} * c{k} + z{k} * z{2 * hidden + k} AS n{k}" for k in range(hidden))
    mid = f"SELECT t, v, {', '.join(f'z{3 * hidden + k}' for k in range(hidden))}, {new_c} FROM ({inner})"
    last = ", ".join([f"z{3 * hidden + k} * tanh(n{k})" for k in range(hidden)] + [f"n{k}" for k in range(hidden)])
    return f"{name}(t, v, {', '.join(state)}) AS (SELECT CAST(0 AS BIGINT), v, {zeros} FROM {vertices} UNION ALL SELECT t, v, {last} FROM ({mid}))"


def frames_of(source: str, hidden: int, name: str) -> str:
    return f"{name} AS (SELECT t, v, {', '.join(f'h{k} AS x{k}' for k in range(hidden))} FROM {source} WHERE t > 0)"


def evolve(w0: np.ndarray | None, cell: dict, steps: int, name: str, source: str = "") -> str:
    """Recursive over the steps: all entries of the matrix, m{i}_{j}, and of the memory, c{i}_{j}, in one row; without w0, two by two ones start from the row of `source`."""
    f, items = w0.shape if w0 is not None else (2, 2)
    cells = [(i, j) for i in range(f) for j in range(items)]
    start = ", ".join([f"{w0[i, j]:.1f}::DOUBLE" if w0 is not None else f"m{i}_{j}" for i, j in cells] + ["CAST(0 AS DOUBLE)"] * len(cells))
    both = cell["wx"] + cell["wh"]
    z = []
    for j in range(items):
        for k in range(4 * f):
            e = " + ".join([f"{cell['b'][k]:.1f}::DOUBLE"] + [f"m{i}_{j} * {both[i, k]:.1f}::DOUBLE" for i in range(f)])
            z.append(f"tanh({e}) AS z{k}_{j}" if 2 * f <= k < 3 * f else f"1 / (1 + exp(-({e}))) AS z{k}_{j}")
    inner = f"SELECT t + 1 AS t, {', '.join(z)}, {', '.join(f'c{i}_{j}' for i, j in cells)} FROM {name} WHERE t < {steps}"
    mid = "SELECT t, " + ", ".join(f"z{3 * f + i}_{j} AS o{i}_{j}, z{f + i}_{j} * c{i}_{j} + z{i}_{j} * z{2 * f + i}_{j} AS n{i}_{j}" for i, j in cells) + f" FROM ({inner})"
    out = ", ".join([f"o{i}_{j} * tanh(n{i}_{j})" for i, j in cells] + [f"n{i}_{j}" for i, j in cells])
    names = ", ".join([f"m{i}_{j}" for i, j in cells] + [f"c{i}_{j}" for i, j in cells])
    return f"{name}(t, {names}) AS (SELECT CAST(0 AS BIGINT), {start}{f' FROM {source}' if source else ''} UNION ALL SELECT t, {out} FROM ({mid}))"


def rounded(names: list[str], keys: str = "t, v") -> str:
    return f"SELECT {keys}, " + ", ".join(f"round({c}, 6) + 0.0 AS {c}" for c in names)


def model_parts(name: str, span: int = 3, hidden: int = 2, edges: str = "e", features: str = "x") -> list[str]:
    """Two layers of window_mean with fixed weights: z2 holds the frames."""
    steps = STEPS[name]
    return [
        *graph(name), life(span, steps, "me", mean=True), *laplacian("me"), mean(span, 2, "x", "mx"),
        aggregate("mx", 2, "s1"), project("s1", fixed_weights(2, hidden, 0), "y1"), mean(span, hidden, "y1", "z1"),
        aggregate("z1", hidden, "s2"), project("s2", fixed_weights(hidden, hidden, 1), "y2"), mean(span, hidden, "y2", "z2"),
    ]


def hash32(text: str) -> str:
    return f"CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT)"


def link_parts(steps: int, theta: float = 0.1, seed: int = 7) -> list[str]:
    """ld: (t, u, v, y, split) on e and v."""
    key = lambda tag, *c: " || ':' || ".join([f"'{tag}{seed}'", *[f"CAST({x} AS VARCHAR)" for x in c]])
    return [
        f"pe AS (SELECT t, src AS u, dst AS v, {hash32(key('pos', 't', 'src', 'dst'))} AS h FROM e WHERE src <> dst)",
        "pr AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY h, u, v) AS k, count(*) OVER (PARTITION BY t) AS n FROM pe)",
        f"po AS (SELECT t, u, v FROM pr WHERE k <= ceil(n * {theta}::DOUBLE))",
        "ids AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS i FROM v)",
        "nn AS (SELECT count(*) AS n FROM v)",
        "wt AS (SELECT t, unnest(range(1, m + 1)) AS k FROM (SELECT t, count(*) AS m FROM po GROUP BY t))",
        f"dr AS (SELECT t, k, {hash32(key('neg-u', 't', 'k'))} % n AS a, {hash32(key('neg-v', 't', 'k'))} % greatest(n - 1, 1) AS b0, n FROM wt, nn)",
        "ne AS (SELECT t, p.v AS u, q.v AS v FROM (SELECT t, a, (a + 1 + b0) % n AS b FROM dr) JOIN ids p ON p.i = a JOIN ids q ON q.i = b)",
        f"ld AS (SELECT CASE WHEN t = {steps} THEN t - 1 ELSE t END AS t, u, v, y, CASE WHEN t = {steps} THEN 'test' ELSE 'train' END AS split FROM (SELECT *, CAST(1 AS BIGINT) AS y FROM po UNION ALL SELECT *, CAST(0 AS BIGINT) FROM ne))",
    ]
