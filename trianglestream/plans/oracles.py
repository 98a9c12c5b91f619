"""DuckDB texts of the estimators: the same windows and coins, as one chain of named queries."""

from __future__ import annotations

from ..functions.hashing import coin_sql, colour_sql
from ..sources.graphs import stream_sql

END = str(1 << 62)


def worker_sql(node: str, mapping: str, k: int, seed: int) -> str:
    return f"CAST({node} % {k} AS INTEGER)" if mapping == "modulo" else colour_sql(node, k, seed)


def chain(parts: list[tuple[str, str]], final: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(f"{name} AS MATERIALIZED ({body})" for name, body in parts) + "\n" + final


def stream_parts(graph: str, order: str = "random", fraction: float | None = None) -> list[tuple[str, str]]:
    """Edges ``e``."""
    return [("e", stream_sql(graph, order))]


def assigned_parts(k: int, mapping: str, seed: int = 0, nodemap: bool = False) -> list[tuple[str, str]]:
    """``ew`` with workers of the ends, ``a`` assigned rows with their rank."""
    if nodemap:
        both = "SELECT e.*, x.worker AS fu, y.worker AS fv FROM e JOIN nodemap x ON e.u = x.node JOIN nodemap y ON e.v = y.node"
    else:
        both = f"SELECT *, {worker_sql('u', mapping, k, seed)} AS fu, {worker_sql('v', mapping, k, seed)} AS fv FROM e"
    return [
        ("ew", both),
        ("a", "SELECT worker, t, u, v, row_number() OVER (PARTITION BY worker ORDER BY t) AS rank FROM (SELECT fu AS worker, t, u, v FROM ew UNION ALL SELECT fv, t, u, v FROM ew WHERE fu <> fv)"),
    ]


def broadcast_parts(k: int) -> list[tuple[str, str]]:
    return [("a", f"SELECT CAST(w.range AS INTEGER) AS worker, t, u, v, t AS rank FROM e, range({k}) w")]


def residency_parts(budget: int, seed: int, trials: int) -> list[tuple[str, str]]:
    coin = coin_sql(str(seed), "trial", "worker", "rank")
    return [
        ("s", f"SELECT * FROM (SELECT a.*, trial, CASE WHEN rank <= {budget} THEN rank ELSE CAST(floor({coin} * rank) AS BIGINT) + 1 END AS slot FROM a, (SELECT CAST(range AS INTEGER) AS trial FROM range({trials}))) WHERE slot <= {budget}"),
        ("r", "SELECT trial, worker, u, v, rank, slot, t AS t_in, lead(t) OVER (PARTITION BY trial, worker, slot ORDER BY t) AS t_out FROM s"),
    ]


def closure_parts(routed: bool) -> list[tuple[str, str]]:
    parts = [
        ("d", f"SELECT trial, worker, u AS apex, v AS o, t_in, coalesce(t_out, {END}) AS t_out FROM r UNION ALL SELECT trial, worker, v, u, t_in, coalesce(t_out, {END}) FROM r"),
        ("w", "SELECT x.trial, x.worker, x.apex, x.o AS a, y.o AS b, greatest(x.t_in, y.t_in) AS lo, least(x.t_out, y.t_out) AS hi FROM d x JOIN d y ON x.trial = y.trial AND x.worker = y.worker AND x.apex = y.apex AND x.o < y.o"),
    ]
    if routed:
        parts.append(("c", "SELECT trial, w.worker, u, v, apex, t FROM w JOIN ew ON w.a = ew.u AND w.b = ew.v WHERE lo < t AND t <= hi AND (fu <> fv OR w.worker = fu)"))
        parts.append(("l", "SELECT c.*, coalesce(a.rank, 0) AS load_before FROM c ASOF LEFT JOIN a ON c.worker = a.worker AND c.t > a.t"))
    else:
        parts.append(("l", "SELECT trial, w.worker, e.u, e.v, apex, t, t - 1 AS load_before FROM w JOIN e ON w.a = e.u AND w.b = e.v WHERE lo < t AND t <= hi"))
    return parts


def weigh_parts(budget: int) -> list[tuple[str, str]]:
    return [
        ("x", f"SELECT *, CASE WHEN load_before <= {budget} THEN 1 ELSE 0 END AS hit, CAST(CASE WHEN load_before <= {budget} THEN 0 ELSE load_before * (load_before - 1) END AS HUGEINT) AS num FROM l"),
        ("k", "SELECT trial, worker, CAST(NULL AS BIGINT) AS node, t, hit, num FROM x UNION ALL SELECT trial, worker, u, t, hit, num FROM x UNION ALL SELECT trial, worker, v, t, hit, num FROM x UNION ALL SELECT trial, worker, apex, t, hit, num FROM x"),
    ]


def est(budget: int | str, divisor: int, hits: str = "hits", num: str = "num") -> str:
    room = f"(CAST({budget} AS DOUBLE) * ({budget} - 1))" if isinstance(budget, str) else repr(float(budget) * (budget - 1))
    return f"(CAST({hits} AS DOUBLE) + CAST({num} AS DOUBLE) / {room}) / {float(divisor)!r}"


def estimate_parts(graph: str, k: int, budget: int, mapping: str | None, seed: int, trials: int, map_seed: int | None = None) -> list[tuple[str, str]]:
    """All steps up to ``x`` and ``k``; mapping None is the broadcast policy."""
    parts = stream_parts(graph)
    parts += broadcast_parts(k) if mapping is None else assigned_parts(k, mapping, seed if map_seed is None else map_seed)
    return parts + residency_parts(budget, seed, trials) + closure_parts(mapping is not None) + weigh_parts(budget)


def global_sql(parts, budget: int, divisor: int, trials: int) -> str:
    return chain(parts, f"""SELECT trial, hits, num, {est(budget, divisor)} AS est FROM (SELECT trial, CAST(coalesce(sum(hit), 0) AS BIGINT) AS hits, CAST(coalesce(sum(num), 0) AS BIGINT) AS num
      FROM (SELECT CAST(range AS INTEGER) AS trial FROM range({trials})) LEFT JOIN x USING (trial) GROUP BY trial)""")


def local_sql(parts, budget: int, divisor: int) -> str:
    return chain(parts, f"SELECT trial, node, {est(budget, divisor)} AS est FROM (SELECT trial, node, sum(hit) AS hits, sum(num) AS num FROM k WHERE node IS NOT NULL GROUP BY trial, node)")


def snapshot_sql(parts, budget: int, divisor: int, times: list[int], trials: int = 1) -> str:
    """Every trial at every time, zero before anything is found."""
    grid = ", ".join(f"({t})" for t in times)
    return chain(parts, f"""SELECT trial, as_of, hits, num, {est(budget, divisor)} AS est FROM (
      SELECT g.trial, g.as_of, CAST(coalesce(sum(hit), 0) AS BIGINT) AS hits, CAST(coalesce(sum(num), 0) AS BIGINT) AS num
      FROM (SELECT CAST(range AS INTEGER) AS trial, CAST(as_of AS BIGINT) AS as_of FROM range({trials}), (VALUES {grid}) v(as_of)) g
      LEFT JOIN x ON x.trial = g.trial AND x.t <= g.as_of GROUP BY ALL)""")


def local_snapshot_sql(parts, budget: int, divisor: int, times: list[int]) -> str:
    grid = ", ".join(f"({t})" for t in times)
    return chain(parts, f"""SELECT trial, as_of, node, {est(budget, divisor)} AS est FROM (
      SELECT trial, CAST(as_of AS BIGINT) AS as_of, node, sum(hit) AS hits, sum(num) AS num
      FROM k JOIN (VALUES {grid}) v(as_of) ON k.t <= as_of WHERE node IS NOT NULL GROUP BY ALL)""")


TRIANGLES = [
    ("tri0", "SELECT p.u AS x, p.v AS y, q.v AS z, p.t AS txy, q.t AS tyz, r.t AS txz FROM e p JOIN e q ON p.v = q.u JOIN e r ON r.u = p.u AND r.v = q.v"),
    ("tri", """SELECT CASE greatest(txy, tyz, txz) WHEN txy THEN x WHEN tyz THEN y ELSE x END AS u, CASE greatest(txy, tyz, txz) WHEN txy THEN y WHEN tyz THEN z ELSE z END AS v,
      CASE greatest(txy, tyz, txz) WHEN txy THEN z WHEN tyz THEN x ELSE y END AS apex, greatest(txy, tyz, txz) AS t, least(txy, tyz, txz) AS t1, txy + tyz + txz - greatest(txy, tyz, txz) - least(txy, tyz, txz) AS t2 FROM tri0"""),
]


def triangle_parts(graph: str) -> list[tuple[str, str]]:
    """``tri``: (u, v, apex, t, t1, t2)."""
    return stream_parts(graph) + TRIANGLES


def placed_parts(graph: str, k: int, mapping: str, seed: int = 0) -> list[tuple[str, str]]:
    """``p``: triangles with their counting worker."""
    f = lambda c: worker_sql(c, mapping, k, seed)
    return triangle_parts(graph) + assigned_parts(k, mapping, seed) + [("p", f"SELECT *, CASE WHEN {f('u')} = {f('v')} THEN {f('u')} ELSE {f('apex')} END AS worker FROM tri")]


def adaptive_parts(k: int, theta: float) -> list[tuple[str, str]]:
    """``nodemap`` by a recursive query over a small stream: loads and colours as lists and maps."""
    spare = "list_position(loads, list_min(loads))"
    slack = f"{1 + theta!r}"
    step = f"""SELECT e.t, e.u, e.v, n.cu, n.cv, list_transform(loads, lambda x, i: x + CASE WHEN i = n.cu OR i = n.cv THEN 1 ELSE 0 END) AS loads,
      map_concat(colours, MAP {{e.u: n.cu, e.v: n.cv}}) AS colours FROM g JOIN e ON e.t = g.t + 1, LATERAL (SELECT
        CASE WHEN hu IS NOT NULL THEN hu WHEN hv IS NULL THEN spare WHEN loads[hv] <= {slack} * loads[spare] THEN hv ELSE spare END AS cu,
        CASE WHEN hv IS NOT NULL THEN hv WHEN hu IS NULL THEN spare WHEN loads[hu] <= {slack} * loads[spare] THEN hu ELSE spare END AS cv
        FROM (SELECT colours[e.u] AS hu, colours[e.v] AS hv, {spare} AS spare)) n"""
    start = f"SELECT CAST(0 AS BIGINT) AS t, CAST(NULL AS BIGINT) AS u, CAST(NULL AS BIGINT) AS v, CAST(NULL AS INTEGER) AS cu, CAST(NULL AS INTEGER) AS cv, [CAST(0 AS BIGINT) FOR i IN range({k})] AS loads, MAP {{CAST(-1 AS BIGINT): CAST(0 AS INTEGER)}} AS colours"
    return [
        ("g", f"{start} UNION ALL {step}"),
        ("nodemap", "SELECT node, CAST(any_value(worker) AS INTEGER) AS worker FROM (SELECT u AS node, cu - 1 AS worker FROM g WHERE t > 0 UNION ALL SELECT v, cv - 1 FROM g WHERE t > 0) GROUP BY node"),
    ]


def epoch_parts(k: int, theta: float, epochs: int = 8) -> list[tuple[str, str]]:
    """``nodemap`` of the epoch engine, epochs unrolled: loads stand still within one."""
    last = "(SELECT max(t) FROM e)"
    bounds = ["0", *[f"({last} >> {i})" for i in range(epochs - 2, 0, -1)], last]
    parts = [
        ("known0", "SELECT CAST(NULL AS BIGINT) AS node, CAST(NULL AS INTEGER) AS worker WHERE false"),
        ("loads0", f"SELECT CAST(range AS INTEGER) AS worker, CAST(0 AS BIGINT) AS load FROM range({k})"),
    ]
    half = max(1, (k + 1) // 2)
    for i, (low, high) in enumerate(zip(bounds, bounds[1:])):
        coin = coin_sql("'p'", "least(f.node, f.partner)")
        parts += [
            (f"part{i}", f"SELECT * FROM e WHERE t > {low} AND t <= {high}"),
            (f"first{i}", f"SELECT node, arg_min(partner, t) AS partner FROM (SELECT u AS node, v AS partner, t FROM part{i} UNION ALL SELECT v, u, t FROM part{i}) WHERE node NOT IN (SELECT node FROM known{i}) GROUP BY node"),
            (f"light{i}", f"SELECT list(worker ORDER BY load, worker)[1:{half}] AS light, min(load) AS least FROM loads{i}"),
            (f"known{i + 1}", f"""SELECT node, worker FROM known{i} UNION ALL SELECT f.node,
              CASE WHEN n.worker IS NOT NULL AND CAST(l.load AS DOUBLE) <= CAST({1 + theta!r} AS DOUBLE) * least THEN n.worker ELSE light[CAST(floor({coin} * {half}) AS BIGINT) + 1] END
              FROM first{i} f LEFT JOIN known{i} n ON f.partner = n.node LEFT JOIN loads{i} l ON l.worker = n.worker, light{i}"""),
            (f"loads{i + 1}", f"""SELECT o.worker, o.load + coalesce(c.n, 0) AS load FROM loads{i} o LEFT JOIN (
              SELECT worker, count(*) AS n FROM (SELECT unnest(list_distinct([x.worker, y.worker])) AS worker FROM part{i} p JOIN known{i + 1} x ON p.u = x.node JOIN known{i + 1} y ON p.v = y.node) GROUP BY worker) c USING (worker)"""),
        ]
    return [*parts, ("nodemap", f"SELECT * FROM known{len(bounds) - 1}")]


def hold_sql(graph: str, p: float, q: float, seed: int, trials: int, sure: bool, nodes: int) -> str:
    """The hold sampler over a small graph of node ids below ``nodes``, edge by edge: the sample as a map of pairs to weights."""
    key = lambda a, b: f"(least({a}, {b}) * 1000 + greatest({a}, {b}))"
    common = f"[w FOR w IN range({nodes}) IF w <> e.u AND w <> e.v AND map_contains(held, {key('e.u', 'w')}) AND map_contains(held, {key('e.v', 'w')})]"
    touch = "len([x FOR x IN map_keys(held) IF x // 1000 = e.u OR x % 1000 = e.u OR x // 1000 = e.v OR x % 1000 = e.v]) > 0"
    closes = "len(common) > 0" if sure else "false"
    gain = f"list_sum([held[{key('e.u', 'w')}] * held[{key('e.v', 'w')}] / chance FOR w IN common])"
    start = f"SELECT CAST(range AS INTEGER) AS trial, CAST(0 AS BIGINT) AS t, MAP {{CAST(-1 AS BIGINT): CAST(0 AS DOUBLE)}} AS held, CAST(0 AS DOUBLE) AS est, CAST(0 AS BIGINT) AS n FROM range({trials})"
    step = f"""SELECT g.trial, e.t, CASE WHEN kept THEN map_concat(held, MAP {{CAST({key('e.u', 'e.v')} AS BIGINT): 1 / chance}}) ELSE held END,
      est + CASE WHEN kept AND len(common) > 0 THEN {gain} ELSE 0 END, n + CASE WHEN kept THEN 1 ELSE 0 END
      FROM g JOIN e ON e.t = g.t + 1, LATERAL (SELECT *, {coin_sql("'h'", str(seed), "g.trial", "e.t")} < chance AS kept FROM (
        SELECT common, CAST(CASE WHEN {closes} THEN 1.0 WHEN touch THEN {q} ELSE {p} END AS DOUBLE) AS chance FROM (SELECT {common} AS common, {touch} AS touch)))"""
    parts = stream_parts(graph) + [("g", f"{start} UNION ALL {step}")]
    return chain(parts, "SELECT trial, round(est, 6) AS est, n AS held FROM g WHERE t = (SELECT max(t) FROM e)")


def fraction_budget(fraction: float) -> str:
    """A share of the stream, two at least, as an expression."""
    return f"(SELECT greatest(2, CAST(floor(count(*) * CAST({fraction!r} AS DOUBLE)) AS BIGINT)) FROM e)"


def mapped_parts(graph: str, k: int, mapping: str, seed: int, theta: float = 0.2) -> list[tuple[str, str]]:
    """Stream, node map where the mapping needs one, and assigned rows."""
    if mapping == "adaptive":
        return stream_parts(graph) + adaptive_parts(k, theta) + assigned_parts(k, "", nodemap=True)
    return stream_parts(graph) + (broadcast_parts(k) if mapping == "broadcast" else assigned_parts(k, mapping, seed))


def measured_sql(labels: dict, graph: str, k: int, budget: int | str, mapping: str, seed: int, trials: int, theta: float = 0.2) -> str:
    """One row: labels, trials, mean, stderr, error, variance of an estimator, rounded as the workloads do."""
    parts = mapped_parts(graph, k, mapping, seed, theta) + residency_parts(budget, seed, trials) + closure_parts(mapping != "broadcast") + weigh_parts(budget) + TRIANGLES
    divisor = k if mapping == "broadcast" else 1
    parts += [
        ("gl", f"SELECT trial, {est(budget, divisor)} AS est FROM (SELECT trial, coalesce(sum(hit), 0) AS hits, coalesce(sum(num), 0) AS num FROM (SELECT CAST(range AS INTEGER) AS trial FROM range({trials})) LEFT JOIN x USING (trial) GROUP BY trial)"),
        ("tt", "SELECT CAST(count(*) AS DOUBLE) AS truth FROM tri"),
    ]
    said = ", ".join(f"{v!r} AS {name}" if isinstance(v, str) else f"CAST({v!r} AS {'DOUBLE' if isinstance(v, float) else 'INTEGER'}) AS {name}" for name, v in labels.items())
    return "(" + chain(parts, f"SELECT {said}, count(*) AS trials, round(avg(est), 7) AS mean, round(stddev_samp(est) / sqrt(count(*)), 7) AS stderr, round(avg(abs(est - truth) / (truth + 1)), 9) AS error, round(avg((est - truth) * (est - truth)), 5) AS variance, max(truth) AS truth FROM gl, tt") + ")"


def rows_sql(rows: list[str], columns: str) -> str:
    return f"SELECT {columns} FROM (" + " UNION ALL ".join(f"SELECT * FROM {r}" for r in rows) + ")"
