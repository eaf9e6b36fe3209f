"""DuckDB fragments of the balancing loop: one recursive step for each event, lists for bounds and loads."""

from __future__ import annotations

from ..operators.scenarios import PRIME, portable_hash


def lists(trace: str, m: int, steps: int, ranks: int, noise: float, seed: int = 0) -> str:
    """pre: step, load and its running sums c by slice, and the measurement noise j by rank; after CTEs that end in tr."""
    factor = repr(noise * 0.0017)
    return f"""{trace}, dense AS (SELECT s.i::INTEGER AS step, list(coalesce(work, 0)::BIGINT ORDER BY q.i) AS load
  FROM range({steps}) s(i) CROSS JOIN range({m}) q(i) LEFT JOIN tr ON tr.step = s.i AND tr.slice_id = q.i GROUP BY 1),
pre AS (SELECT step, load, list_concat([0::BIGINT], list_transform(range(1, {m + 1}), lambda i: list_sum(load[1:i])::BIGINT)) AS c,
  list_transform(range(0, {ranks}), lambda k: 1.0::DOUBLE + ((((({portable_hash(seed)} * 48271::BIGINT + step + 11) % {PRIME}) * 48271::BIGINT + k + 11) % {PRIME}) % 2001 - 1000) * {factor}::DOUBLE) AS j FROM dense)"""


def recut(source: str, ranks: int, m: int, least: int, keep: str = "step") -> str:
    """Bounds b of the midpoint cut of the loads x (a list of doubles) of each row of source, none narrower than least."""
    forward = ", ".join(f"greatest(b0[{k}], {f'f{k - 1}' if k > 1 else 0} + {least}) AS f{k}" for k in range(1, ranks))
    back = ", ".join(f"least(f{k}, {f'g{k + 1}' if k + 1 < ranks else m} - {least}) AS g{k}" for k in range(ranks - 1, 0, -1))
    bounds = ", ".join(f"g{k}" for k in range(1, ranks))
    return f"""(SELECT {keep}, [0, {bounds}, {m}]::BIGINT[] AS b FROM (SELECT *, {forward}, {back} FROM (
  SELECT *, list_transform(range(1, {ranks}), lambda k: CASE WHEN cum[{m}] = 0 THEN ({m} * k + {ranks - 1}) // {ranks}
    ELSE len(list_filter(range(1, {m + 1}), lambda i: (2 * cum[i] - w[i]) * {ranks} < 2 * cum[{m}] * k)) END) AS b0
  FROM (SELECT *, list_transform(range(1, {m + 1}), lambda i: list_sum(w[1:i])::BIGINT) AS cum
    FROM (SELECT *, list_transform(x, lambda v: floor(v / CASE WHEN list_sum(x) = 0 THEN 1 ELSE list_sum(x) END * 1e6 + 0.5)::BIGINT) AS w FROM {source})))))"""


def seen(ranks: int) -> str:
    """step, b, true times t and seen times s of the rows of r."""
    return f"""(SELECT r.*, load, t, list_transform(range(1, {ranks + 1}), lambda i: t[i] * j[i]) AS s
  FROM (SELECT r.*, load, j, list_transform(range(1, {ranks + 1}), lambda i: c[b[i + 1] + 1] - c[b[i] + 1]) AS t FROM r JOIN pre USING (step)) r)"""


def first(ranks: int, m: int, least: int) -> str:
    return recut("(SELECT 0 AS step, list_transform(load, lambda v: v::DOUBLE) AS x FROM pre WHERE step = 0)", ranks, m, least)


def reactive(ranks: int, m: int, least: int, most: float, tau: float = 0.02, alpha: float = 0.5) -> str:
    edge = repr(most * (1 - 1e-6))
    step = f"""CASE WHEN abs((s[i + 1] - s[i]) / ((s[i + 1] + s[i]) / 2)) > {tau} THEN sign(s[i + 1] - s[i]) * ({alpha}
      * (CASE WHEN s[i + 1] > s[i] THEN b[i + 2] - b[i + 1] ELSE b[i + 1] - b[i] END) * (abs(s[i + 1] - s[i]) / (2 * greatest(s[i], s[i + 1])))) ELSE 0 END"""
    moves = ", ".join(f"least(greatest(b[{k + 1}] + d[{k}], {f'n{k - 1}' if k > 1 else 0} + {least}), b[{k + 2}] - {least}) AS n{k}" for k in range(1, ranks))
    return f"""r(step, b) AS (SELECT step, b FROM {first(ranks, m, least)} UNION ALL
  SELECT (step + 1)::INTEGER, [0, {', '.join(f'n{k}' for k in range(1, ranks))}, {m}]::BIGINT[] FROM (SELECT *, {moves} FROM (
    SELECT *, list_transform(q, lambda v: (sign(v) * floor(abs(v) + 0.5))::BIGINT) AS d FROM (
      SELECT *, list_transform(range(1, {ranks}), lambda i: round(least(greatest({step}, -{edge}::DOUBLE), {edge}::DOUBLE), 9)) AS q FROM {seen(ranks)}))))"""


def spread_times(ranks: int, m: int) -> str:
    """x: rank times spread evenly over their slices."""
    return f"list_transform(range(0, {m}), lambda z: (s[len(list_filter(b[2:{ranks}], lambda e: e <= z)) + 1] / (b[len(list_filter(b[2:{ranks}], lambda e: e <= z)) + 2] - b[len(list_filter(b[2:{ranks}], lambda e: e <= z)) + 1]))::DOUBLE)"


def persistence(ranks: int, m: int, least: int, histogram: bool = False) -> str:
    x = "list_transform(load, lambda v: v::DOUBLE)" if histogram else spread_times(ranks, m)
    source = f"(SELECT (step + 1)::INTEGER AS step, {x} AS x FROM {seen(ranks)})"
    return f"r(step, b) AS (SELECT step, b FROM {first(ranks, m, least)} UNION ALL SELECT step, b FROM {recut(source, ranks, m, least)})"


def holt(ranks: int, m: int, least: int, histogram: bool = False, a: float = 0.5, b: float = 0.3) -> str:
    x = "list_transform(load, lambda v: v::DOUBLE)" if histogram else spread_times(ranks, m)
    every = f"range(1, {m + 1})"
    level = f"CASE WHEN step = 0 THEN y ELSE list_transform({every}, lambda i: {a}::DOUBLE * y[i] + {1 - a!r}::DOUBLE * (l[i] + d[i])) END"
    trend = f"CASE WHEN step = 0 THEN list_transform(y, lambda v: 0::DOUBLE) ELSE list_transform({every}, lambda i: {b}::DOUBLE * (nl[i] - l[i]) + {1 - b!r}::DOUBLE * d[i]) END"
    source = f"""(SELECT (step + 1)::INTEGER AS step, nl, nd, list_transform({every}, lambda i: greatest(nl[i] + nd[i], 0)) AS x FROM (
    SELECT *, {trend} AS nd FROM (SELECT *, {level} AS nl FROM (SELECT *, {x} AS y FROM {seen(ranks)}))))"""
    return f"""r(step, b, l, d) AS (SELECT step, b, NULL::DOUBLE[], NULL::DOUBLE[] FROM {first(ranks, m, least)}
  UNION ALL SELECT step, b, nl, nd FROM {recut(source, ranks, m, least, 'step, nl, nd')})"""


def static(ranks: int, m: int, least: int) -> str:
    return f"r(step, b) AS (SELECT step, b FROM {first(ranks, m, least)} UNION ALL SELECT (step + 1)::INTEGER, b FROM {seen(ranks)})"


def log(ranks: int) -> str:
    """log: each event's bounds, the next ones, true times and running loads."""
    return f"""log AS (SELECT r.step, r.b, n.b AS nb, c, list_transform(range(1, {ranks + 1}), lambda i: c[r.b[i + 1] + 1] - c[r.b[i] + 1]) AS t
  FROM r JOIN r n ON n.step = r.step + 1 JOIN pre ON pre.step = r.step)"""


def shown(ranks: int) -> str:
    return f"""SELECT step, array_to_string(b, ',') AS bounds, list_sum(list_transform(range(1, {ranks + 2}), lambda i: abs(nb[i] - b[i])))::BIGINT AS moved,
  round((list_max(t) - list_min(t)) / list_avg(t), 6) AS i_global, list_max(t)::BIGINT AS t_max FROM log"""
