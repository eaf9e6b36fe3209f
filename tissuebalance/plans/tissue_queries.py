"""Queries on tissues: elements, bins, pairs, forces, work, partitions and ghosts."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..operators import ghosts, grid, interactions, mechanics, measures, partitioner, runtime, score
from ..sources.scratch import release, scratch, settled
from ..sources.tissues import DEFAULT_CUTOFF, TISSUES
from . import sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
M = {"order": 256, "event": 1024, "vector": 256}
RANKS = 8


def add(name: str, query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def long_key(df: DataFrame) -> DataFrame:
    return df.withColumn("element_no", F.col("element_no").cast("bigint"))



for _kind in TISSUES:
    add(
        f"tissue_elements_{_kind}",
        lambda s, d, k=_kind: long_key(TISSUES[k](s, d)).select("cell_id", "element_no", "x", "y", "z", "cell_type"),
        f"WITH {sql.elements(_kind)} SELECT cell_id, element_no::BIGINT AS element_no, x, y, z, cell_type FROM e",
    )


def bins_order(spark: SparkSession, folder: str) -> DataFrame:
    return grid.bins(TISSUES["order"](spark, folder), DEFAULT_CUTOFF["order"])


add("bins_order", bins_order, f"WITH {sql.elements('order')}, {sql.binned(5000)}, {sql.bins()} SELECT bx, by_ AS by, bz, n::BIGINT AS n FROM b")
add(
    "bin_neighbourhood_order",
    lambda s, d: grid.neighbourhood_counts(bins_order(s, d)),
    f"WITH {sql.elements('order')}, {sql.binned(5000)}, {sql.bins()}, {sql.SHIFTS}, {sql.AROUND} SELECT bx, by_ AS by, bz, n::BIGINT AS n, n_near FROM b JOIN around USING (bx, by_, bz)",
)

_VECTOR_PAIRS = f"WITH {sql.elements('vector')}, {sql.pair_counts(10000)} SELECT cell_id, element_no::BIGINT AS element_no, n_pairs FROM pairs"


def vector_counts(spark: SparkSession, folder: str, how) -> DataFrame:
    return long_key(how(TISSUES["vector"](spark, folder), 10000)).where("n_pairs > 0").select("cell_id", "element_no", "n_pairs")


def even_bounds(elements: DataFrame, cutoff: int, ranks: int) -> list[float]:
    """Cuts uniform on x, as many as stay a cutoff apart."""
    low, high = elements.agg(F.min("x"), F.max("x")).first()
    ranks = max(1, min(ranks, int((high - low) // max(cutoff, 1)))) if low is not None else 1
    return [low + (high - low) * r / ranks for r in range(1, ranks)]


def placed_only(elements: DataFrame) -> DataFrame:
    """Keys and positions of elements, in a table of their own."""
    return settled(elements.select(*interactions.ID, *grid.AXES))


def slabs(elements: DataFrame, cutoff: int, ranks: int = 4) -> DataFrame:
    """Counts by rank-local sweeps."""
    held = placed_only(elements)
    return interactions.slab_counts(held, cutoff, even_bounds(held, cutoff, ranks))


for _name, _how in {
    "serial": interactions.all_pairs_serial,
    "allpairs": lambda e, c: interactions.pair_counts(interactions.all_pairs(e, c)),
    "binned": lambda e, c: interactions.pair_counts(interactions.binned(e, c)),
    "half": lambda e, c: interactions.pair_counts(interactions.binned(e, c, stencil="half")),
    "fine": lambda e, c: interactions.pair_counts(interactions.binned(e, c, per_cutoff=2)),
    "auto": lambda e, c: interactions.pair_counts(interactions.evaluate(e, c)),
    "slab": slabs,
    "tiled": interactions.all_pairs_tiled,
}.items():
    add(f"pairs_{_name}_vector", lambda s, d, h=_how: vector_counts(s, d, h), _VECTOR_PAIRS)

add(
    "pairs_binned_order",
    lambda s, d: long_key(interactions.binned_counts(placed_only(TISSUES["order"](s, d)), 5000)),
    f"WITH {sql.elements('order')}, {sql.binned(5000)}, {sql.SHIFTS}, {sql.binned_pair_counts(5000)} SELECT cell_id, element_no::BIGINT AS element_no, n_pairs FROM pairs",
)
add(
    "pairs_slab_order",
    lambda s, d: long_key(slabs(TISSUES["order"](s, d), 5000, 8)).where("n_pairs > 0").select("cell_id", "element_no", "n_pairs"),
    ORACLES["pairs_binned_order"],
)


def candidates_by_tissue(spark: SparkSession, folder: str) -> DataFrame:
    parts = [interactions.candidate_counts(make(spark, folder), DEFAULT_CUTOFF[k]).withColumn("tissue", F.lit(k)) for k, make in TISSUES.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).select("tissue", "elements", "bins", "candidates")


add("candidates_by_tissue", candidates_by_tissue, " UNION ALL ".join(f"(WITH {sql.elements(k)}, {sql.binned(DEFAULT_CUTOFF[k])}, {sql.bins()}, {sql.SHIFTS}, {sql.AROUND} SELECT '{k}' AS tissue, sum(n)::BIGINT AS elements, count(*)::BIGINT AS bins, sum(n * n_near)::BIGINT AS candidates FROM b JOIN around USING (bx, by_, bz))" for k in TISSUES))

SIZES = (64, 16, 4, 1)


def nested_parts(elements: DataFrame, sizes: tuple[int, ...] = SIZES) -> DataFrame:
    """Each element once for every part of the extent that holds it: the first 1/q of the range of x, marked one_in = q.

    Parts grow by their extent, so the density is the tissue's own in all of them.
    """
    return elements.withColumn("one_in", F.explode(F.array_compact(F.array(*held_by(elements, sizes)))))


def held_by(elements: DataFrame, sizes: tuple[int, ...] = SIZES) -> list[Column]:
    """The q of each part of nested_parts where it holds the element, in the order of sizes."""
    low, high = elements.agg(F.min("x"), F.max("x")).first()
    return [F.when(F.col("x") < low + -(-(high + 1 - low) // q), q) for q in sizes]


def evaluator_work_by_size(spark: SparkSession, folder: str) -> DataFrame:
    """Tests of the quadratic and the binned evaluator on growing parts of a tissue (W1), with log-log slopes."""
    rows = interactions.candidate_counts(nested_parts(TISSUES["order"](spark, folder)), 5000, ("one_in",))
    rows = rows.select("one_in", "elements", "candidates", (F.col("elements") * F.col("elements")).alias("all_pairs"))
    slope = [F.expr(f"round(regr_slope(ln({c}), ln(elements)) over (), 6)").alias(f"slope_{n}") for c, n in (("candidates", "binned"), ("all_pairs", "all_pairs"))]
    return rows.select("*", *slope)  # a window over one row for each size


add(
    "evaluator_work_by_size",
    evaluator_work_by_size,
    f"""WITH {sql.elements('order', 'e0')}, ext AS (SELECT min(x) AS lo, max(x) + 1 - min(x) AS n FROM e0), e AS (SELECT * FROM e0, ext, (VALUES {', '.join(f'({q})' for q in SIZES)}) t(one_in) WHERE x < lo + (n + one_in - 1) // one_in),
{sql.binned(5000)}, b AS (SELECT one_in, bx, by_, bz, count(*) AS n FROM p GROUP BY ALL), {sql.SHIFTS},
around AS (SELECT one_in, bx + a AS bx, by_ + s.b AS by_, bz + c AS bz, sum(n)::BIGINT AS n_near FROM b, shifts s GROUP BY ALL),
rows AS (SELECT one_in, sum(n)::BIGINT AS elements, sum(n * n_near)::BIGINT AS candidates FROM b JOIN around USING (one_in, bx, by_, bz) GROUP BY one_in)
SELECT one_in, elements, candidates, elements * elements AS all_pairs, (SELECT round(regr_slope(ln(candidates), ln(elements)), 6) FROM rows) AS slope_binned, (SELECT round(regr_slope(ln(elements * elements), ln(elements)), 6) FROM rows) AS slope_all_pairs FROM rows""",
)


def evaluator_seconds(spark: SparkSession, folder: str, serial: int = 10_000, quadratic: int = 40_000, cutoff: int = 5000) -> DataFrame:
    """Seconds of every evaluator on growing parts of a tissue (W1); the quadratic ones only on parts up to a size. Rows are timings."""
    tissue = TISSUES["order"](spark, folder).select(*interactions.ID, *grid.AXES)
    smallest = F.coalesce(*held_by(tissue, tuple(sorted(SIZES, reverse=True))))  # larger parts hold it too
    held, out = settled(tissue.withColumn("one_in", smallest), by=("one_in",)), []
    for q in SIZES:
        part = held.where(F.col("one_in") >= q).drop("one_in")
        n = part.count()
        ways = {"binned": lambda e: interactions.binned_counts(e, cutoff), "slab": lambda e: interactions.slab_counts(e, cutoff, even_bounds(e, cutoff, 8))}
        if n <= quadratic:
            ways |= {"all_pairs": lambda e: interactions.pair_counts(interactions.all_pairs(e, cutoff)), "tiled": lambda e: interactions.all_pairs_tiled(e, cutoff)}
        if n <= serial:
            ways["serial"] = lambda e: interactions.all_pairs_serial(e, cutoff)
        for name, way in ways.items():
            begin = time.perf_counter()
            way(part).write.format("noop").mode("overwrite").save()
            out.append((name, n, time.perf_counter() - begin))
            release(spark)
    return spark.createDataFrame(out, "evaluator string, elements bigint, seconds double")


add("evaluator_seconds", evaluator_seconds)


def scaling_seconds(spark: SparkSession, folder: str) -> DataFrame:
    """Strong scaling by the seconds that ranks spend in the kernel (W2): the slowest rank, speed-up and efficiency. The sites are made once."""
    spots, out = settled(interactions.sites(TISSUES["order"](spark, folder))), []
    for p in (1, 2, 4, 8, 16):
        found = interactions.slab_sites(spots, 5000, even_bounds(spots, 5000, p))
        ranks = found.groupBy("rank").agg(F.sum("seconds").alias("s"), F.sum(F.col("n") * F.col("tests")).alias("tests")).collect()  # one row a rank
        out.append(("order", p, max(r.s for r in ranks), max(r.tests for r in ranks)))
        release(spark)
    return measures.speedup(spark.createDataFrame(out, "case string, p int, t double, tests bigint"))


add("scaling_seconds", scaling_seconds)

add(
    "pair_work_vector",
    lambda s, d: interactions.pair_work(TISSUES["vector"](s, d), 10000).withColumn("hit_rate", F.round("hit_rate", 6)),
    f"""WITH {sql.elements('vector')}, {sql.binned(10000)}, {sql.bins()}, {sql.SHIFTS}, {sql.AROUND}, {sql.pair_counts(10000)},
w AS (SELECT sum(n)::BIGINT AS elements, sum(n * n_near)::BIGINT AS candidates FROM b JOIN around USING (bx, by_, bz))
SELECT elements, candidates, (elements + (SELECT sum(n_pairs) FROM pairs))::BIGINT AS pairs, round((elements + (SELECT sum(n_pairs) FROM pairs))::DOUBLE / candidates, 6) AS hit_rate FROM w""",
)


def observed_work(spark: SparkSession, folder: str) -> DataFrame:
    """Candidate tests reported by a job that does something else with the bins: metrics on the side."""
    near, seen = grid.neighbourhood_counts(bins_order(spark, folder)), Observation("candidates")
    near.observe(seen, F.count(F.lit(1)).alias("bins"), F.sum(F.col("n") * F.col("n_near")).alias("candidates")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["bins"], seen.get["candidates"])], "bins bigint, candidates bigint")


add("observed_work", observed_work, f"WITH {sql.elements('order')}, {sql.binned(5000)}, {sql.bins()}, {sql.SHIFTS}, {sql.AROUND} SELECT count(*)::BIGINT AS bins, sum(n * n_near)::BIGINT AS candidates FROM b JOIN around USING (bx, by_, bz)")

add(
    "axis_choice",
    lambda s, d: s.createDataFrame([(k, score.choose_axis(make(s, d), DEFAULT_CUTOFF[k])) for k, make in TISSUES.items()], "tissue string, axis string"),
    " UNION ALL ".join(f"(WITH {sql.elements(k)}, w AS (SELECT max(x) - min(x) AS x, max(y) - min(y) AS y, max(z) - min(z) AS z FROM e) SELECT '{k}' AS tissue, CASE WHEN x >= y AND x >= z THEN 'x' WHEN y >= z THEN 'y' ELSE 'z' END AS axis FROM w)" for k in TISSUES),
)


def forces_vector(spark: SparkSession, folder: str) -> DataFrame:
    moved = mechanics.velocity(TISSUES["vector"](spark, folder), 10000)
    return moved.select("cell_id", *(F.round(f"v{a}", 6).alias(f"v{a}") for a in grid.AXES))


_FORCES = f"""WITH {sql.elements('vector')}, d AS (
  SELECT a.cell_id, a.x AS ax, a.y AS ay, a.z AS az, b.x AS bx, b.y AS by_, b.z AS bz, a.cell_type = b.cell_type AS same,
    sqrt(((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) + (a.z - b.z) * (a.z - b.z))::DOUBLE) AS r
  FROM e a JOIN e b ON a.cell_id <> b.cell_id),
f AS (SELECT *, CASE WHEN r > 0 THEN (1.5 * exp(-(r / 10000) / 0.2) - CASE WHEN same THEN 0.04 ELSE 0.02 END / 0.4 * exp(-(r / 10000) / 0.4)) / r ELSE 0 END AS f FROM d WHERE r <= 10000),
v AS (SELECT cell_id, sum(f * (ax - bx)) AS vx, sum(f * (ay - by_)) AS vy, sum(f * (az - bz)) AS vz FROM f GROUP BY cell_id),
m AS (SELECT e.cell_id, e.x, e.y, e.z, coalesce(vx, 0) AS vx, coalesce(vy, 0) AS vy, coalesce(vz, 0) - 0.05 * exp(-(e.z - (SELECT min(z) FROM e)) / 10000::DOUBLE) AS vz FROM e LEFT JOIN v USING (cell_id))"""
add("forces_vector", forces_vector, f"{_FORCES} SELECT cell_id, round(vx, 6) AS vx, round(vy, 6) AS vy, round(vz, 6) AS vz FROM m")
add(
    "step_vector",
    lambda s, d: mechanics.step(TISSUES["vector"](s, d), 10000, 100.0).select("cell_id", "x", "y", "z"),
    f"{_FORCES} SELECT cell_id, (x + floor(vx * 100 + 0.5))::BIGINT AS x, (y + floor(vy * 100 + 0.5))::BIGINT AS y, (z + floor(vz * 100 + 0.5))::BIGINT AS z FROM m",
)

def rounded_forces(spark: SparkSession, folder: str, kind: str, pushes=None) -> DataFrame:
    moved = mechanics.velocity(TISSUES[kind](spark, folder).select(*interactions.ID, *grid.AXES, "cell_type"), DEFAULT_CUTOFF[kind], pushes)
    return long_key(moved).select("cell_id", "element_no", *((F.round(f"v{a}", 6) + 0.0).alias(f"v{a}") for a in grid.AXES))  # no negative zeros


for _kind in ("order", "event"):
    _forces = f"WITH {sql.forces(_kind, DEFAULT_CUTOFF[_kind])} SELECT cell_id, element_no::BIGINT AS element_no, round(vx, 6) + 0.0 AS vx, round(vy, 6) + 0.0 AS vy, round(vz, 6) + 0.0 AS vz FROM v"
    add(f"forces_{_kind}", lambda s, d, k=_kind: rounded_forces(s, d, k), _forces)
    add(f"slab_forces_{_kind}", lambda s, d, k=_kind, c=DEFAULT_CUTOFF[_kind]: rounded_forces(s, d, k, lambda spots: interactions.slab_push(spots, c, even_bounds(spots, c, 8))), _forces)

#: The loop of ranks, ghosts and sweeps takes the same step as the join.
add(
    "simulated_vector",
    lambda s, d: runtime.simulate(TISSUES["vector"](s, d), 10000, runtime.Plan(1, ranks=4, slices=64, dt=100.0))[0].select("cell_id", "x", "y", "z"),
    ORACLES["step_vector"],
)


def simulation_log(spark: SparkSession, folder: str) -> DataFrame:
    """Ranks of a short run that grows, divides and rebalances at every other iteration (B8): counts, tests and slices, no timings."""
    plan = runtime.Plan(iterations=4, cadence=2, ranks=4, slices=128, dt=50.0, growth=2, divide_at=6)
    return runtime.simulate(TISSUES["order"](spark, folder), 5000, plan)[1].drop("seconds")


add("simulation_log", simulation_log)

add("cell_work_centroid", lambda s, d: score.cell_work(TISSUES["order"](s, d), 5000), f"WITH {sql.work('order', 5000)} SELECT cell_id, cx, n_elements, work FROM w")
add(
    "cell_work_per_element",
    lambda s, d: score.cell_work(TISSUES["order"](s, d), 5000, "per_element"),
    f"""WITH e AS MATERIALIZED ({sql.ELEMENTS['order']}), {sql.binned(5000)}, {sql.bins()}, {sql.SHIFTS}, around AS MATERIALIZED (SELECT bx + a AS bx, by_ + s.b AS by_, bz + c AS bz, sum(n)::BIGINT AS n_near FROM b, shifts s GROUP BY ALL),
{sql.cells(5000)}, q AS MATERIALIZED (SELECT cell_id, bx, by_, bz, count(*) AS n FROM p GROUP BY ALL), x AS (SELECT cell_id, sum(n * n_near)::BIGINT AS work FROM q JOIN around USING (bx, by_, bz) GROUP BY 1)
SELECT centres.cell_id, cx, n_elements, work FROM centres JOIN x USING (cell_id)""",
)


def histogram(spark: SparkSession, folder: str, kind: str, cutoff: int | None = None) -> DataFrame:
    elements = TISSUES[kind](spark, folder)
    cutoff = cutoff or DEFAULT_CUTOFF[kind]
    low, high = score.extent(elements, cutoff)
    return score.slice_histogram(score.cell_work(elements, cutoff), low, high, M[kind])


CUTS = {
    "uniform": (lambda h, m: partitioner.uniform(h, RANKS, m), ("uniform", "work")),
    "count": (lambda h, m: partitioner.count_balanced(h, RANKS), ("midpoint", "n_cells")),
    "shares": (lambda h, m: partitioner.balanced(h, RANKS), ("midpoint", "work")),
    "ceil": (lambda h, m: partitioner.balanced(h, RANKS, "ceil"), ("ceil", "work")),
    "floor": (lambda h, m: partitioner.balanced(h, RANKS, "floor"), ("floor", "work")),
    "nearest": (lambda h, m: partitioner.balanced(h, RANKS, "nearest"), ("nearest", "work")),
}
for _kind in TISSUES:
    _own = sql.histogram(_kind, DEFAULT_CUTOFF[_kind], M[_kind])
    add(f"slice_histogram_{_kind}", lambda s, d, k=_kind: histogram(s, d, k), f"WITH {_own} SELECT slice_id, work, n_cells FROM h")
    for _cut, (_make, (_rule, _weight)) in CUTS.items():
        add(f"partition_{_cut}_{_kind}", lambda s, d, k=_kind, f=_make: partitioner.shares(f(histogram(s, d, k), M[k]), RANKS), f"WITH {_own}, {sql.ranked(_rule, RANKS, M[_kind], _weight)} {sql.shares()}")


def partition_optimal(spark: SparkSession, folder: str, ranks: int) -> DataFrame:
    """The smallest possible largest share."""
    work = [r.work for r in histogram(spark, folder, "event").orderBy("slice_id").collect()]  # M numbers
    return spark.createDataFrame([(ranks, partitioner.optimal(work, ranks))], "ranks int, largest bigint")


_UPTO = f"WITH {sql.histogram('event', 20000, M['event'])}, c AS MATERIALIZED (SELECT 0 AS i, 0::BIGINT AS a UNION ALL SELECT slice_id + 1, sum(work) OVER (ORDER BY slice_id)::BIGINT FROM h)"
_BEST = ", ".join(f"f{k} AS MATERIALIZED (SELECT c.i, min(greatest(p.v, c.a - d.a))::BIGINT AS v FROM c JOIN c d ON d.i <= c.i JOIN f{k - 1} p ON p.i = d.i GROUP BY c.i)" for k in range(2, RANKS + 1))
for _p in (2, RANKS):
    add(f"partition_optimal_event_{_p}", lambda s, d, p=_p: partition_optimal(s, d, p), f"{_UPTO}, f1 AS (SELECT i, a AS v FROM c), {_BEST} SELECT {_p}::INTEGER AS ranks, v AS largest FROM f{_p} WHERE i = {M['event']}")

_EDGES = [600_000, 1_200_000, 1_800_000]
_RANK = " + ".join(f"CASE WHEN {{0}} >= {b} THEN 1 ELSE 0 END" for b in _EDGES)
_GHOSTS = f"""WITH {sql.elements('order')}, r AS (SELECT *, {_RANK.format('x')} AS home, {_RANK.format('(x - 5000)')} AS lo, {_RANK.format('(x + 5000)')} AS hi FROM e),
g AS (SELECT cell_id, element_no, home AS rank, false AS is_ghost FROM r UNION ALL SELECT cell_id, element_no, home - 1, true FROM r WHERE lo < home UNION ALL SELECT cell_id, element_no, home + 1, true FROM r WHERE hi > home)"""
add("ghost_rows_order", lambda s, d: long_key(ghosts.attach(TISSUES["order"](s, d), _EDGES, 5000)).where("is_ghost").select("cell_id", "element_no", "rank"), f"{_GHOSTS} SELECT cell_id, element_no::BIGINT AS element_no, rank::INTEGER AS rank FROM g WHERE is_ghost")
add("ghost_replication", lambda s, d: ghosts.attach(TISSUES["order"](s, d), _EDGES, 5000).groupBy("rank").agg(F.count_if(~F.col("is_ghost")).alias("owned"), F.count_if("is_ghost").alias("ghosts")), f"{_GHOSTS} SELECT rank::INTEGER AS rank, count(*) FILTER (NOT is_ghost)::BIGINT AS owned, count(*) FILTER (is_ghost)::BIGINT AS ghosts FROM g GROUP BY 1")


def slab_result_invariant(spark: SparkSession, folder: str) -> DataFrame:
    """Ordered pairs found with 1, 2, 4 and 8 ranks: ghosts make them equal. The sites are made once."""
    spots = settled(interactions.sites(TISSUES["order"](spark, folder)))
    found = [(p, interactions.slab_sites(spots, 5000, even_bounds(spots, 5000, p))) for p in (1, 2, 4, 8)]
    parts = [settled(f.agg(F.sum(F.col("n") * F.col("n_pairs")).cast("bigint").alias("n_pairs")).select(F.lit(p).alias("ranks"), "n_pairs")) for p, f in found]  # one row each, so that one sweep's shuffle files go before the next
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


add("slab_result_invariant", slab_result_invariant, f"WITH {sql.elements('order')}, {sql.binned(5000)}, {sql.SHIFTS}, {sql.binned_pair_counts(5000)} SELECT r.p::INTEGER AS ranks, sum(n_pairs)::BIGINT AS n_pairs FROM pairs, (VALUES (1), (2), (4), (8)) r(p) GROUP BY 1")


def growth_snapshots(spark: SparkSession, folder: str) -> DataFrame:
    return mechanics.snapshots(TISSUES["order"](spark, folder))


add(
    "growth_snapshots",
    growth_snapshots,
    f"""WITH {sql.elements('order')}, d AS (SELECT min(born) AS lo, date_diff('day', min(born), max(born)) AS n FROM e),
days AS (SELECT i AS day, (lo + CAST(n * (i + 1) // 6 AS INTEGER)) AS until FROM d, range(6) r(i))
SELECT day::INTEGER AS day, cell_type, floor(z / 2000.0::DOUBLE + 0.5)::BIGINT AS layer, count(*)::BIGINT AS n_elements, count(DISTINCT cell_id)::BIGINT AS n_cells FROM e JOIN days ON born <= until GROUP BY ALL""",
)
add(
    "division_daughters",
    lambda s, d: mechanics.divide(TISSUES["order"](s, d)).groupBy("cell_id", "parent_id").agg(F.count(F.lit(1)).alias("n_elements"), F.sum("x").cast("bigint").alias("sum_x")),
    f"""WITH {sql.elements('order')}, s AS (SELECT *, count(*) OVER w AS n, max(x) OVER w - min(x) OVER w AS dx, max(y) OVER w - min(y) OVER w AS dy, max(z) OVER w - min(z) OVER w AS dz FROM e WINDOW w AS (PARTITION BY cell_id)),
t AS (SELECT *, CASE WHEN dx >= dy AND dx >= dz THEN x WHEN dy >= dz THEN y ELSE z END AS along FROM s),
u AS (SELECT *, row_number() OVER (PARTITION BY cell_id ORDER BY along, element_no) AS place FROM t)
SELECT cell_id * 2 + CASE WHEN n >= 6 AND 2 * place > n THEN 1 ELSE 0 END AS cell_id, CASE WHEN n >= 6 THEN cell_id END AS parent_id, count(*)::BIGINT AS n_elements, sum(x)::BIGINT AS sum_x FROM u GROUP BY ALL""",
)


def lineage_closure(spark: SparkSession, folder: str) -> DataFrame:
    """Descendants of the first cells after two rounds of division, at six and at two elements (C9)."""
    tissue, edges = mechanics.generations(TISSUES["order"](spark, folder), [6, 2])
    path = scratch(spark, f"lineage-{uuid.uuid4().hex}")
    edges.write.parquet(path)
    closed = mechanics.lineage(spark.read.parquet(path)).where("since = 1")
    return closed.groupBy("ancestor", "generations").agg(F.count(F.lit(1)).alias("n_descendants"), F.sum("descendant").cast("bigint").alias("sum_ids"))


def _divided(source: str, threshold: int, name: str) -> str:
    return f"""{name}s AS (SELECT *, count(*) OVER w AS n, max(x) OVER w - min(x) OVER w AS dx, max(y) OVER w - min(y) OVER w AS dy, max(z) OVER w - min(z) OVER w AS dz FROM {source} WINDOW w AS (PARTITION BY cell_id)),
{name}u AS (SELECT *, row_number() OVER (PARTITION BY cell_id ORDER BY CASE WHEN dx >= dy AND dx >= dz THEN x WHEN dy >= dz THEN y ELSE z END, element_no) AS place FROM {name}s),
{name} AS (SELECT cell_id AS parent, cell_id * 2 + CASE WHEN n >= {threshold} AND 2 * place > n THEN 1 ELSE 0 END AS cell_id, element_no, x, y, z FROM {name}u)"""


add(
    "lineage_closure",
    lineage_closure,
    f"""WITH {sql.elements('order')}, {_divided('e', 6, 'g1')}, {_divided('g1', 2, 'g2')}, e1 AS (SELECT DISTINCT parent, cell_id AS child FROM g1), e2 AS (SELECT DISTINCT parent, cell_id AS child FROM g2),
c AS (SELECT parent AS ancestor, child AS descendant, 1 AS generations FROM e1 UNION ALL SELECT e1.parent, e2.child, 2 FROM e1 JOIN e2 ON e2.parent = e1.child)
SELECT ancestor, generations::INTEGER AS generations, count(*)::BIGINT AS n_descendants, sum(descendant)::BIGINT AS sum_ids FROM c GROUP BY ALL""",
)
add(
    "growth_by_rule",
    lambda s, d: mechanics.grow(TISSUES["order"](s, d)).groupBy("cell_id").agg(F.count(F.lit(1)).alias("n_elements"), F.sum("y").cast("bigint").alias("sum_y")),
    f"WITH {sql.elements('order')} SELECT cell_id, (count(*) + CASE WHEN count(*) < 8 THEN 1 ELSE 0 END)::BIGINT AS n_elements, (sum(y) + CASE WHEN count(*) < 8 THEN floor(sum(y)::DOUBLE / count(*)) ELSE 0 END)::BIGINT AS sum_y FROM e GROUP BY cell_id",
)
add(
    "differentiation_by_layer",
    lambda s, d: mechanics.differentiate(TISSUES["order"](s, d), [(F.col("z") < 10000, "basal"), (F.col("z") < 30000, "spinous")]).groupBy("cell_type").agg(F.count(F.lit(1)).alias("n_elements")),
    f"WITH {sql.elements('order')} SELECT CASE WHEN z < 10000 THEN 'basal' WHEN z < 30000 THEN 'spinous' ELSE cell_type END AS cell_type, count(*)::BIGINT AS n_elements FROM e GROUP BY 1",
)
add(
    "composition_cube",
    lambda s, d: TISSUES["order"](s, d).cube("cell_type", F.year("born").alias("year")).agg(F.count(F.lit(1)).alias("n_elements"), F.countDistinct("cell_id").alias("n_cells"), F.grouping_id().cast("int").alias("level")),
    f"WITH {sql.elements('order')} SELECT cell_type, year(born)::INTEGER AS year, count(*)::BIGINT AS n_elements, count(DISTINCT cell_id)::BIGINT AS n_cells, (2 * grouping(cell_type) + grouping(year(born)))::INTEGER AS level FROM e GROUP BY CUBE (cell_type, year(born))",
)
