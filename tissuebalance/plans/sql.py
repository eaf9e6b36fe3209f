"""DuckDB fragments from which the catalogue's SQL is put together."""

from __future__ import annotations

ELEMENTS = {
    "order": """SELECT l_orderkey AS cell_id,
  row_number() OVER (PARTITION BY l_orderkey ORDER BY l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate)::INTEGER AS element_no,
  (date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) * 1000 + (2 * CAST(l_quantity AS BIGINT) - 51) * 10)::BIGINT AS x,
  (CAST(round(o_totalprice * 100) AS BIGINT) // 500 + CAST(round(l_discount * 100) AS BIGINT) * 100 - 500)::BIGINT AS y,
  (c_nationkey::BIGINT * 2000 + CAST(round(l_tax * 100) AS BIGINT) * 100 - 400)::BIGINT AS z,
  c_mktsegment AS cell_type, CAST(l_shipdate AS DATE) AS born
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey""",
    "event": """SELECT (user_id * 100 + extract('day' FROM ts))::BIGINT AS cell_id, event_id AS element_no,
  (CAST(round(value * 100) AS BIGINT) * 200)::BIGINT AS x, (user_id * 1000)::BIGINT AS y,
  ((epoch_us(ts) - 1704067200000000) // 3600000)::BIGINT AS z, event_type AS cell_type, CAST(ts AS DATE) AS born,
  (epoch_us(ts) - 1704067200000000)::BIGINT AS micros, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k
FROM events""",
    "vector": """SELECT vec_id AS cell_id, 1 AS element_no, floor(embedding[1]::DOUBLE * 100000 + 0.5)::BIGINT AS x,
  floor(embedding[2]::DOUBLE * 100000 + 0.5)::BIGINT AS y, floor(embedding[3]::DOUBLE * 100000 + 0.5)::BIGINT AS z,
  label::VARCHAR AS cell_type, NULL::DATE AS born
FROM embeddings""",
}


def elements(tissue: str, name: str = "e") -> str:
    return f"{name} AS ({ELEMENTS[tissue]})"


def bin_of(position: str, edge: int) -> str:
    return f"floor({position} / {edge}::DOUBLE)::BIGINT"


def binned(edge: int, source: str = "e", name: str = "p") -> str:
    return f"{name} AS (SELECT *, {bin_of('x', edge)} AS bx, {bin_of('y', edge)} AS by_, {bin_of('z', edge)} AS bz FROM {source})"


def bins(source: str = "p", name: str = "b") -> str:
    return f"{name} AS (SELECT bx, by_, bz, count(*) AS n FROM {source} GROUP BY ALL)"


NEAR = """near AS (
  SELECT b.bx, b.by_, b.bz, b.n, sum(o.n)::BIGINT AS n_near FROM b JOIN b o
  ON o.bx BETWEEN b.bx - 1 AND b.bx + 1 AND o.by_ BETWEEN b.by_ - 1 AND b.by_ + 1 AND o.bz BETWEEN b.bz - 1 AND b.bz + 1 GROUP BY ALL)"""

SHIFTS = "shifts AS (SELECT a, b, c FROM range(-1, 2) t(a), range(-1, 2) u(b), range(-1, 2) v(c))"
#: Bins around every occupied bin, joined by equality.
AROUND = "around AS (SELECT bx + a AS bx, by_ + s.b AS by_, bz + c AS bz, sum(n)::BIGINT AS n_near FROM b, shifts s GROUP BY ALL)"


def pair_counts(cutoff: int) -> str:
    """n_pairs of each element that has any, by testing all pairs."""
    return f"""pairs AS (SELECT a.cell_id, a.element_no, count(*)::BIGINT AS n_pairs FROM e a JOIN e b
  ON (a.cell_id <> b.cell_id OR a.element_no <> b.element_no)
  WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) + (a.z - b.z) * (a.z - b.z) <= {cutoff}::BIGINT * {cutoff} GROUP BY ALL)"""


def binned_pair_counts(cutoff: int) -> str:
    return f"""pairs AS (SELECT a.cell_id, a.element_no, count(*)::BIGINT AS n_pairs
  FROM (SELECT p.cell_id, p.element_no, p.x, p.y, p.z, p.bx + s.a AS bx, p.by_ + s.b AS by_, p.bz + s.c AS bz FROM p, shifts s) a
  JOIN p o ON a.bx = o.bx AND a.by_ = o.by_ AND a.bz = o.bz
  WHERE (a.cell_id <> o.cell_id OR a.element_no <> o.element_no)
    AND (a.x - o.x) * (a.x - o.x) + (a.y - o.y) * (a.y - o.y) + (a.z - o.z) * (a.z - o.z) <= {cutoff}::BIGINT * {cutoff} GROUP BY ALL)"""


def forces(tissue: str, cutoff: int) -> str:
    """v: velocity of each element, from binned pairs and the membrane."""
    return f"""{elements(tissue)}, {binned(cutoff)}, {SHIFTS}, near AS (
  SELECT a.cell_id, a.element_no, a.x - o.x AS dx, a.y - o.y AS dy, a.z - o.z AS dz, a.cell_id = o.cell_id AS own, a.cell_type IS NOT DISTINCT FROM o.cell_type AS same
  FROM (SELECT p.cell_id, p.element_no, p.cell_type, p.x, p.y, p.z, p.bx + s.a AS bx, p.by_ + s.b AS by_, p.bz + s.c AS bz FROM p, shifts s) a
  JOIN p o ON a.bx = o.bx AND a.by_ = o.by_ AND a.bz = o.bz WHERE a.cell_id <> o.cell_id OR a.element_no <> o.element_no),
far AS (SELECT *, sqrt((dx * dx + dy * dy + dz * dz)::DOUBLE) AS r FROM near WHERE dx * dx + dy * dy + dz * dz <= {cutoff}::BIGINT * {cutoff}),
pulls AS (SELECT *, CASE WHEN r > 0 THEN (0.3 / 0.2 * exp(-(r / {cutoff}) / 0.2) - CASE WHEN own THEN 0.1 WHEN same THEN 0.04 ELSE 0.02 END / 0.4 * exp(-(r / {cutoff}) / 0.4)) / r ELSE 0 END AS f FROM far),
sums AS (SELECT cell_id, element_no, sum(f * dx) AS vx, sum(f * dy) AS vy, sum(f * dz) AS vz FROM pulls GROUP BY ALL),
v AS (SELECT e.cell_id, e.element_no, coalesce(vx, 0) AS vx, coalesce(vy, 0) AS vy, coalesce(vz, 0) - 0.05 * exp(-(e.z - (SELECT min(z) FROM e)) / {cutoff}::DOUBLE) AS vz FROM e LEFT JOIN sums USING (cell_id, element_no))"""


def cells(cutoff: int) -> str:
    centre = ", ".join(f"floor(sum({a})::DOUBLE / count(*))::BIGINT AS c{a}" for a in "xyz")
    own = ", ".join(f"{bin_of(f'c{a}', cutoff)} AS {n}" for a, n in zip("xyz", ("bx", "by_", "bz"), strict=True))
    return f"centres AS (SELECT cell_id, count(*) AS n_elements, {centre} FROM e GROUP BY cell_id), cells AS (SELECT *, {own} FROM centres)"


def work(tissue: str, cutoff: int) -> str:
    """cells with their centroid score, as CTEs ending in w."""
    return f"""{elements(tissue)}, {binned(cutoff)}, {bins()}, {SHIFTS}, {AROUND}, {cells(cutoff)},
w AS (SELECT cell_id, cx, n_elements::BIGINT AS n_elements, (n_elements * coalesce(n_near, 0))::BIGINT AS work FROM cells LEFT JOIN around USING (bx, by_, bz))"""


def histogram(tissue: str, cutoff: int, m: int) -> str:
    return f"""{work(tissue, cutoff)}, ext AS (SELECT min(x) - {cutoff} AS lo, max(x) + {cutoff} AS hi FROM e),
h0 AS (SELECT floor((cx - lo) * {m} / (hi - lo)::DOUBLE)::INTEGER AS slice_id, sum(work)::BIGINT AS work, count(*)::BIGINT AS n_cells FROM w, ext GROUP BY 1),
h AS (SELECT r.i::INTEGER AS slice_id, coalesce(work, 0)::BIGINT AS work, coalesce(n_cells, 0)::BIGINT AS n_cells FROM range({m}) r(i) LEFT JOIN h0 ON slice_id = r.i)"""


def ranked(rule: str, ranks: int, m: int, weight: str = "work", source: str = "h", name: str = "g") -> str:
    if rule == "uniform":
        return f"{name} AS (SELECT *, floor(slice_id * {ranks} / {m}::DOUBLE)::INTEGER AS rank FROM {source})"
    if rule == "nearest":  # an edge for each cut, at the least distance from the cut's share
        return f"""{name}e AS (SELECT 0 AS edge, 0 AS upto UNION ALL SELECT slice_id + 1, sum({weight}) OVER (ORDER BY slice_id) FROM {source}),
{name}c AS (SELECT k, first(edge ORDER BY abs(upto * {ranks} - t * k), upto, CASE WHEN upto * {ranks} < t * k THEN -edge ELSE edge END) AS edge FROM {name}e, range(1, {ranks}) q(k), (SELECT max(upto) AS t FROM {name}e) GROUP BY k),
{name} AS (SELECT slice_id, work, n_cells, (SELECT count(*) FROM {name}c WHERE edge <= slice_id)::INTEGER AS rank FROM {source})"""
    twice = {"midpoint": f"2 * upto - {weight}", "ceil": "2 * upto - 1", "floor": f"2 * (upto - {weight})"}[rule]
    return f"""{name}0 AS (SELECT *, sum({weight}) OVER (ORDER BY slice_id)::BIGINT AS upto, sum({weight}) OVER ()::BIGINT AS total FROM {source}),
{name} AS (SELECT slice_id, work, n_cells, greatest(0, least({ranks - 1}, ({twice}) * {ranks} // (2 * total)))::INTEGER AS rank FROM {name}0)"""


def shares(source: str = "g") -> str:
    return f"""SELECT rank, sum(work)::BIGINT AS work, count(*)::BIGINT AS n_slices, min(slice_id) AS first_slice, max(slice_id) AS last_slice,
  floor(sum(work) * 1000000.0::DOUBLE / sum(sum(work)) OVER ())::BIGINT AS share_ppm FROM {source} GROUP BY rank"""
