"""Pieces of DuckDB SQL that say the same as the operators, for the queries' oracles."""

from __future__ import annotations

E_BASE = "exp(1.0::DOUBLE)"


def with_(*ctes: str, recursive: bool = False) -> str:
    return ("WITH RECURSIVE " if recursive or any("(step, t, sample_index" in c for c in ctes) else "WITH ") + ",\n".join(ctes) + "\n"


def histogram(name: str, keys: str, rows: str) -> str:
    """CTEs ``name``_f (keys, n, features, cloud_fraction) and ``name``_v (valid ones with sample_index); ``rows`` gives keys and bin (NULL: not counted)."""
    using = f"USING ({keys})"
    return f"""{name}_b AS ({rows}),
{name}_n AS (SELECT {keys}, count(*) AS n FROM {name}_b GROUP BY {keys}),
{name}_c AS (SELECT {keys}, bin, count(*) AS c FROM {name}_b WHERE bin IS NOT NULL GROUP BY {keys}, bin),
{name}_g AS (SELECT {name}_n.*, k.range AS bin FROM {name}_n, range(42) k),
{name}_f AS (SELECT {keys}, n, list(coalesce(c, 0)::DOUBLE / n ORDER BY g.bin) AS features, sum(coalesce(c, 0))::DOUBLE / n AS cloud_fraction
  FROM {name}_g g LEFT JOIN {name}_c USING ({keys}, bin) GROUP BY {keys}, n),
{name}_v AS (SELECT *, row_number() OVER (ORDER BY {keys}) - 1 AS sample_index FROM {name}_f WHERE cloud_fraction > 0)"""


_LINE_BIN = "CASE WHEN l_returnflag <> 'N' THEN least(5, floor((l_quantity - 1) * 6 / 50))::INT * 7 + floor(round(l_discount * 100) * 7 / 11)::INT END AS bin"
CELLS = histogram("cells", "l_suppkey, period", f"SELECT l_suppkey, date_trunc('month', l_shipdate)::DATE AS period, {_LINE_BIN} FROM lineitem")
NATIONS = histogram("nations", "n_nationkey, period", f"SELECT s_nationkey AS n_nationkey, date_trunc('month', l_shipdate)::DATE AS period, {_LINE_BIN} FROM lineitem JOIN supplier ON s_suppkey = l_suppkey")
DOCS = histogram(
    "docs",
    "doc_id",
    r"""SELECT doc_id, CASE WHEN regexp_matches(w, '^\p{L}+[.,]?$') THEN least(5, (length(w) - 1) // 2)::INT * 7
    + least(6, floor(12.0::DOUBLE * (length(w) - length(regexp_replace(lower(w), '[aeiou]', '', 'g'))) / length(w)))::INT END AS bin
  FROM (SELECT doc_id, unnest(regexp_split_to_array(text, '\s+')) AS w FROM documents) WHERE w <> ''""",
)
EVENTS = histogram(
    "events",
    "user_id, day",
    """SELECT user_id, ts::DATE AS day, CASE WHEN event_type <> 'error' THEN (hour(ts) // 4) * 7
    + (value >= 8)::INT + (value >= 17)::INT + (value >= 28)::INT + (value >= 42)::INT + (value >= 63)::INT + (value >= 96)::INT END AS bin FROM events""",
)


def scaled(name: str, source: str, keys: str, dim: int, order: str | None = None) -> str:
    """CTE ``name``_v (keys, sample_index, features) of ``source`` (keys, x list), scaled per component."""
    return f"""{name}_r AS ({source}),
{name}_e AS (SELECT list(lo ORDER BY i) AS lo, list(hi ORDER BY i) AS hi FROM (SELECT i.range AS i, min(x[i.range]) AS lo, max(x[i.range]) AS hi FROM {name}_r, range(1, {dim + 1}) i GROUP BY 1)),
{name}_v AS (SELECT {keys}, row_number() OVER (ORDER BY {order or keys}) - 1 AS sample_index,
  list_transform(range(1, {dim + 1}), lambda i: CASE WHEN hi[i] > lo[i] THEN (x[i] - lo[i]) / (hi[i] - lo[i]) ELSE 0 END) AS features FROM {name}_r, {name}_e)"""


VECTORS = scaled("vectors", "SELECT vec_id, list_transform(embedding, lambda v: v::DOUBLE) AS x FROM embeddings", "vec_id", 64)
LINE_KEY = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
LINES = scaled("lines", f"SELECT {LINE_KEY}, [l_quantity, l_extendedprice, l_discount, l_tax]::DOUBLE[] AS x FROM lineitem", LINE_KEY, 4)


def gradient(dim: int, rows: int = 4, cols: int = 3, name: str = "protos") -> str:
    far = f"sqrt(({rows} - 1) * ({rows} - 1) + ({cols} - 1) * ({cols} - 1))"
    value = f"sqrt((k.range // {cols}) * (k.range // {cols}) + (k.range % {cols}) * (k.range % {cols})) / {far}"
    return f"{name} AS (SELECT k.range AS node, list_transform(range({dim}), lambda i: {value}) AS prototype FROM range({rows * cols}) k)"


def distance(dim: int, a: str = "features", b: str = "prototype") -> str:
    return f"list_sum(list_transform(range(1, {dim + 1}), lambda i: ({a}[i] - {b}[i]) * ({a}[i] - {b}[i])))"


def winners(name: str, source: str, dim: int, protos: str = "protos", key: str = "sample_index") -> str:
    """CTE ``name``: source's rows with node, distance, second."""
    return f"""{name}_d AS (SELECT s.*, p.node, {distance(dim)} AS d2 FROM {source} s, {protos} p),
{name}_k AS (SELECT *, row_number() OVER (PARTITION BY {key} ORDER BY d2, node) AS place, lead(node) OVER (PARTITION BY {key} ORDER BY d2, node) AS second FROM {name}_d),
{name} AS (SELECT * EXCLUDE (place, d2), sqrt(d2) AS distance FROM {name}_k WHERE place = 1)"""


def grid_gap(a: str, b: str, cols: int = 3) -> str:
    return f"sqrt(({a} // {cols} - {b} // {cols}) * ({a} // {cols} - {b} // {cols}) + ({a} % {cols} - {b} % {cols}) * ({a} % {cols} - {b} % {cols}))"


def weight(t: str, horizon: str, d: str, rows: int = 4, cols: int = 3, l0: str = "0.1::DOUBLE") -> str:
    radius = f"pow({min(rows, cols) / 2}::DOUBLE, 1 - {t}::DOUBLE / {horizon})"
    return f"CASE WHEN {d} <= {radius} THEN round({l0} * pow({E_BASE}, -{t}::DOUBLE / {horizon}) * pow({E_BASE}, -{d} / (2 * {radius})), 12) ELSE 0 END"


def fold(source: str, dim: int, passes: int, rows: int = 4, cols: int = 3, horizon: str | None = None) -> str:
    """CTEs of a serial training in staggered order from gradient start: fold (step, t, sample_index, winner, v). Needs WITH RECURSIVE."""
    k = rows * cols
    horizon = horizon or "(SELECT fold_rows FROM fold_n)"
    d2 = f"list_transform(range(1, {k + 1}), lambda k: list_sum(list_transform(range(1, {dim + 1}), lambda i: (s.features[i] - f.v[k][i]) * (s.features[i] - f.v[k][i]))))"
    return f"""fold_n AS (SELECT count(*) AS fold_rows FROM {source}),
{gradient(dim, rows, cols, "fold_start")},
fold_w AS (SELECT t, list(row ORDER BY a) AS w FROM (SELECT t.range AS t, a.range AS a, list({weight("t.range", horizon, grid_gap("a.range", "b.range", cols), rows, cols)} ORDER BY b.range) AS row
  FROM range({passes}) t, range({k}) a, range({k}) b GROUP BY 1, 2) GROUP BY t),
fold_s AS MATERIALIZED (SELECT t.range * fold_rows + CASE WHEN t.range % 2 = 0 THEN (s.sample_index - t.range // 2 + fold_rows) % fold_rows ELSE (fold_rows - 1 - (t.range - 1) // 2 - s.sample_index + fold_rows) % fold_rows END AS step,
  t.range AS t, s.sample_index, s.features, w.w FROM {source} s, fold_n, range({passes}) t JOIN fold_w w ON w.t = t.range),
fold(step, t, sample_index, winner, v) AS (
  SELECT -1::BIGINT, -1::BIGINT, -1::BIGINT, -1::BIGINT, (SELECT list(prototype ORDER BY node) FROM fold_start)
  UNION ALL
  SELECT step, t, sample_index, win - 1, list_transform(range(1, {k + 1}), lambda k: list_transform(range(1, {dim + 1}), lambda i: v[k][i] + w[win][k] * (features[i] - v[k][i])))
  FROM (SELECT s.step, s.t, s.sample_index, s.features, s.w, f.v, list_position({d2}, list_min({d2})) AS win FROM fold f JOIN fold_s s ON s.step = f.step + 1))"""


def random_start(dim: int, seed: int, rows: int = 4, cols: int = 3, name: str = "protos") -> str:
    value = f"('0x' || substr(md5('{seed}:' || k.range || ':' || i), 1, 13))::UBIGINT / 4503599627370496.0::DOUBLE"
    return f"{name} AS (SELECT k.range AS node, list_transform(range({dim}), lambda i: {value}) AS prototype FROM range({rows * cols}) k)"


def position(selection: str, seed: int = 1) -> str:
    """Place of sample s.sample_index among fold_rows in pass t.range."""
    if selection == "staggered":
        return "CASE WHEN t.range % 2 = 0 THEN (s.sample_index - t.range // 2 + fold_rows) % fold_rows ELSE (fold_rows - 1 - (t.range - 1) // 2 - s.sample_index + fold_rows) % fold_rows END"
    return "s.sample_index" if selection == "sequential" else f"row_number() OVER (PARTITION BY t.range ORDER BY md5('{seed}:' || t.range || ':' || s.sample_index)) - 1"


def run(p: str, source: str, dim: int, passes: int, *, init: str = "gradient", selection: str = "staggered", seed: int = 1, rows: int = 4, cols: int = 3, horizon: str | None = None, rate: float = 0.1, stop: str = "no_moves") -> str:
    """CTEs of one serial training under the prefix ``p``: {p}_h (pass, radius, rate, moves, stop_reason) up to its stop, {p}_p (node, prototype) there."""
    k = rows * cols
    horizon = horizon or f"(SELECT fold_rows FROM {p}_n)"
    d2 = f"list_transform(range(1, {k + 1}), lambda k: list_sum(list_transform(range(1, {dim + 1}), lambda i: (s.features[i] - f.v[k][i]) * (s.features[i] - f.v[k][i]))))"
    start = gradient(dim, rows, cols, f"{p}_start") if init == "gradient" else random_start(dim, seed, rows, cols, f"{p}_start")
    shown = f"{source} s" if selection != "random_replace" else f"(SELECT j.sample_index AS place, t0.range AS pass, s.* FROM {source} j, range({passes}) t0, (SELECT count(*) AS m FROM {source}) JOIN {source} s ON s.sample_index = ('0x' || substr(md5('{seed}:' || t0.range || ':' || j.sample_index), 1, 12))::UBIGINT % m) s"
    at = position(selection, seed) if selection != "random_replace" else "s.place"
    only = "" if selection != "random_replace" else "WHERE s.pass = t.range"
    return f"""{p}_n AS (SELECT count(*) AS fold_rows FROM {source}),
{start},
{p}_w AS (SELECT t, list(row ORDER BY a) AS w FROM (SELECT t.range AS t, a.range AS a, list({weight("t.range", horizon, grid_gap("a.range", "b.range", cols), rows, cols, f"{rate!r}::DOUBLE")} ORDER BY b.range) AS row
  FROM range({passes}) t, range({k}) a, range({k}) b GROUP BY 1, 2) GROUP BY t),
{p}_s AS MATERIALIZED (SELECT t.range * fold_rows + {at} AS step, t.range AS t, s.sample_index, s.features, w.w FROM {shown}, {p}_n, range({passes}) t JOIN {p}_w w ON w.t = t.range {only}),
{p}(step, t, sample_index, winner, v) AS (
  SELECT -1::BIGINT, -1::BIGINT, -1::BIGINT, -1::BIGINT, (SELECT list(prototype ORDER BY node) FROM {p}_start)
  UNION ALL
  SELECT step, t, sample_index, win - 1, list_transform(range(1, {k + 1}), lambda k: list_transform(range(1, {dim + 1}), lambda i: v[k][i] + w[win][k] * (features[i] - v[k][i])))
  FROM (SELECT s.step, s.t, s.sample_index, s.features, s.w, f.v, list_position({d2}, list_min({d2})) AS win FROM {p} f JOIN {p}_s s ON s.step = f.step + 1)),
{p}_m AS (SELECT t, count(*) FILTER (moved) AS moves FROM (SELECT t, winner IS DISTINCT FROM lag(winner) OVER (PARTITION BY sample_index ORDER BY step) AS moved FROM {p} WHERE step >= 0) GROUP BY t),
{p}_z AS (SELECT {"coalesce(min(t) FILTER (t > 0 AND moves = 0), max(t))" if stop == "no_moves" else "max(t)"} AS last, {"count(*) FILTER (t > 0 AND moves = 0) > 0" if stop == "no_moves" else "false"} AS still FROM {p}_m),
{p}_h AS (SELECT t AS pass, pow({min(rows, cols) / 2}::DOUBLE, 1 - t::DOUBLE / {horizon}) AS radius, {rate!r}::DOUBLE * pow({E_BASE}, -t::DOUBLE / {horizon}) AS rate, moves,
  CASE WHEN still THEN 'no_moves' WHEN {passes} = {horizon} THEN 'horizon' ELSE 'max_passes' END AS stop_reason FROM {p}_m, {p}_z WHERE t <= last),
{p}_p AS (SELECT k.range - 1 AS node, v[k.range] AS prototype FROM (SELECT v FROM {p}, {p}_z WHERE t <= last ORDER BY step DESC LIMIT 1), range(1, {k + 1}) k)"""


def run_groups(p: str, source: str, dim: int, passes: int, rows: int, cols: int, horizon: str = "n") -> str:
    """As ``run`` for many lists side by side: ``source`` has g and a sample_index within it; {p}_p (g, node, prototype), {p}_l (g, t, winner, c): last winners counted by the passes run."""
    k = rows * cols
    d2 = f"list_transform(range(1, {k + 1}), lambda k: list_sum(list_transform(range(1, {dim + 1}), lambda i: (s.features[i] - f.v[k][i]) * (s.features[i] - f.v[k][i]))))"
    return f"""{p}_n AS (SELECT g, count(*) AS n, least({passes}, {horizon.replace("n", "count(*)")}) AS passes FROM {source} GROUP BY g),
{gradient(dim, rows, cols, f"{p}_start")},
{p}_w AS (SELECT g, t, list(row ORDER BY a) AS w FROM (SELECT g, t.range AS t, a.range AS a, list({weight("t.range", horizon, grid_gap("a.range", "b.range", cols), rows, cols)} ORDER BY b.range) AS row
  FROM {p}_n, range({passes}) t, range({k}) a, range({k}) b WHERE t.range < passes GROUP BY 1, 2, 3) GROUP BY g, t),
{p}_s AS MATERIALIZED (SELECT s.g, t * n + CASE WHEN t % 2 = 0 THEN (s.sample_index - t // 2 + n) % n ELSE (n - 1 - (t - 1) // 2 - s.sample_index + n) % n END AS step, t, s.sample_index, s.features, w.w
  FROM {source} s JOIN {p}_n USING (g) JOIN {p}_w w USING (g)),
{p}(step, t, sample_index, winner, v, g) AS (
  SELECT -1::BIGINT, -1::BIGINT, -1::BIGINT, -1::BIGINT, (SELECT list(prototype ORDER BY node) FROM {p}_start), g FROM {p}_n
  UNION ALL
  SELECT step, t, sample_index, win - 1, list_transform(range(1, {k + 1}), lambda k: list_transform(range(1, {dim + 1}), lambda i: v[k][i] + w[win][k] * (features[i] - v[k][i]))), g
  FROM (SELECT s.g, s.step, s.t, s.sample_index, s.features, s.w, f.v, list_position({d2}, list_min({d2})) AS win FROM {p} f JOIN {p}_s s ON s.g = f.g AND s.step = f.step + 1)),
{p}_m AS (SELECT g, t, count(*) FILTER (moved) AS moves FROM (SELECT g, t, winner IS DISTINCT FROM lag(winner) OVER (PARTITION BY g, sample_index ORDER BY step) AS moved FROM {p} WHERE step >= 0) GROUP BY g, t),
{p}_z AS (SELECT g, coalesce(min(t) FILTER (t > 0 AND moves = 0), max(t)) AS last FROM {p}_m GROUP BY g),
{p}_e AS (SELECT g, max_by(v, step) AS v FROM {p} JOIN {p}_z USING (g) WHERE t <= last GROUP BY g),
{p}_p AS (SELECT g, k.range - 1 AS node, v[k.range] AS prototype FROM {p}_e, range(1, {k + 1}) k),
{p}_l AS (SELECT g, winner, count(*) AS c FROM {p} JOIN {p}_z USING (g) WHERE t = last GROUP BY 1, 2)"""


def history(p: str, name: str, source: str, dim: int) -> str:
    """A SELECT of the run's passes with its name and its quantization error at the end."""
    error = f"(SELECT avg(sqrt(d2)) FROM (SELECT min({distance(dim)}) AS d2 FROM {source} s, {p}_p p GROUP BY s.sample_index))"
    return f"SELECT '{name}' AS run, pass, round(radius, 6) AS radius, round(rate, 6) AS rate, moves, stop_reason, round({error}, 6) AS quantization_error FROM {p}_h"


def trained(source: str, dim: int, passes: int, rows: int = 4, cols: int = 3) -> str:
    """CTEs up to ``protos`` (node, prototype) of the map that ``fold`` trains."""
    return f"""{fold(source, dim, passes, rows, cols)},
protos AS (SELECT k.range - 1 AS node, v[k.range] AS prototype FROM fold, range(1, {rows * cols + 1}) k WHERE step = (SELECT max(step) FROM fold))"""


def pearson(x: str, y: str) -> str:
    n, sx, sy = "count(*)::DOUBLE", f"sum({x})", f"sum({y})"
    vx, vy = f"({n} * sum({x} * {x}) - {sx} * {sx})", f"({n} * sum({y} * {y}) - {sy} * {sy})"
    return f"CASE WHEN {vx} > 1e-15 AND {vy} > 1e-15 THEN ({n} * sum({x} * {y}) - {sx} * {sy}) / (sqrt({vx}) * sqrt({vy})) END"


#: Correlation of two lists.
LIST_PEARSON = (
    "CASE WHEN len({x}) * list_sum(list_transform({x}, lambda v: v * v)) - list_sum({x}) * list_sum({x}) > 1e-15 AND len({y}) * list_sum(list_transform({y}, lambda v: v * v)) - list_sum({y}) * list_sum({y}) > 1e-15 "
    "THEN (len({x}) * list_sum(list_transform(range(1, len({x}) + 1), lambda i: {x}[i] * {y}[i])) - list_sum({x}) * list_sum({y})) "
    "/ (sqrt(len({x}) * list_sum(list_transform({x}, lambda v: v * v)) - list_sum({x}) * list_sum({x})) * sqrt(len({y}) * list_sum(list_transform({y}, lambda v: v * v)) - list_sum({y}) * list_sum({y}))) END"
)


def exact_mean(value: str) -> str:
    return f"sum(round({value} * 16777216)::BIGINT)::DOUBLE / 16777216.0::DOUBLE / count(*)"


def centroids(name: str, assigned: str, dim: int) -> str:
    """CTE ``name`` (regime, n, cloud_fraction, rfo, centroid)."""
    return f"""{name}_l AS (SELECT node, i.range AS i, {exact_mean("features[i.range]")} AS m, count(*) AS n FROM {assigned}, range(1, {dim + 1}) i GROUP BY 1, 2),
{name}_a AS (SELECT node AS regime, any_value(n) AS n, list(m ORDER BY i) AS centroid FROM {name}_l GROUP BY node),
{name} AS (SELECT regime, n, list_sum(centroid) AS cloud_fraction, n / sum(n) OVER () AS rfo, centroid FROM {name}_a)"""


def rounded(values: str, digits: int = 6) -> str:
    return f"list_transform({values}, lambda x: round(x, {digits}))"
