"""Evaluators, work scores, ghosts and plans on small tissues."""

import math
import time

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F
from tissuebalance.functions.forces import INTER, INTRA, MEMBRANE, OTHER_TYPE
from tissuebalance.operators import ghosts, grid, interactions, kernels, mechanics, partitioner, runtime, score
from tissuebalance.plans import catalogue, tissue_queries
from tissuebalance.sources.scratch import settled
from tissuebalance.sources.tissues import TISSUES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SCHEMA = "cell_id bigint, element_no int, x bigint, y bigint, z bigint, cell_type string, born date"


def elements(spark, rows):
    return spark.createDataFrame([(*r, "a", None) for r in rows], SCHEMA)


def test_golden_counts(spark, tiny):
    order = TISSUES["order"](spark, tiny)
    assert interactions.candidate_counts(order, 10000).first().candidates == 94324
    vector = TISSUES["vector"](spark, tiny)
    assert interactions.candidate_counts(vector, 10000).first().candidates == 50706
    assert interactions.binned(vector, 10000).count() + 500 == 10708
    assert interactions.candidate_counts(TISSUES["event"](spark, tiny), 20000).first().candidates == 3396


def test_evaluators_agree_on_edges(spark):
    rows = [(1, 1, 0, 0, 0), (1, 2, 10, 0, 0), (2, 1, -10, 0, 0), (2, 2, -11, 0, 0), (3, 1, 10, 10, 10), (4, 1, 0, 0, 0)]
    e = elements(spark, rows)
    brute = sum(1 for a in rows for b in rows if a is not b and sum((a[k] - b[k]) ** 2 for k in (2, 3, 4)) <= 100)
    assert interactions.all_pairs(e, 10).count() == brute
    for how in ({}, {"stencil": "half"}, {"per_cutoff": 2}):
        assert interactions.binned(e, 10, **how).count() == brute
    assert interactions.slab_counts(e, 10, [0.0]).agg(F.sum("n_pairs")).first()[0] == brute
    assert interactions.all_pairs_serial(e, 10).agg(F.sum("n_pairs")).first()[0] == brute


def test_quadratic_evaluators_keep_their_size(spark, tiny):
    vector = TISSUES["vector"](spark, tiny)
    with pytest.raises(ValueError):
        interactions.all_pairs(vector, 10000, most=100)
    tiled = interactions.all_pairs_tiled(vector, 10000, tile=64).agg(F.sum("n_pairs")).first()[0]
    assert tiled == interactions.binned(vector, 10000).count()
    work = interactions.pair_work(vector, 10000).first()
    assert (work.candidates, work.pairs) == (50706, 10708)


def test_types_play_no_part_within_a_cell(spark):
    rows = [(1, 1, 0, 0, 0, "a"), (1, 2, 3, 0, 0, "a"), (2, 1, 0, 4, 0, "a")]
    mixed = [rows[0], (1, 2, 3, 0, 0, "b"), rows[2]]
    both = []
    for cells in (rows, mixed):
        e = spark.createDataFrame([(*r, None) for r in cells], SCHEMA)
        by_join = {(r.cell_id, r.element_no): (r.vx, r.vy, r.vz) for r in mechanics.velocity(e, 10).collect()}
        by_sweep = {(r.cell_id, r.element_no): (r.vx, r.vy, r.vz) for r in interactions.slab_forces(e, 10, []).collect()}
        assert by_join.keys() == by_sweep.keys() and all(by_join[k] == pytest.approx(by_sweep[k]) for k in by_join)
        both.append(by_join)
    assert both[0][1, 1] == pytest.approx(both[1][1, 1])
    assert both[0][1, 2][1] != pytest.approx(both[1][1, 2][1])  # the pull between two cells depends on both types


def test_simulation_takes_the_steps_of_the_join(spark, tiny):
    e = TISSUES["vector"](spark, tiny)
    want = mechanics.step(mechanics.step(e, 10000, 100.0), 10000, 100.0)
    want = {r.cell_id: (r.x, r.y, r.z) for r in want.collect()}
    for policy in ("static", "reactive"):
        got, log = runtime.simulate(e, 10000, runtime.Plan(2, cadence=1, ranks=3, slices=60, policy=policy))
        got = {r.cell_id: (r.x, r.y, r.z) for r in got.collect()}
        # Sums in another order may fall on the other side of a half once in a while.
        assert got.keys() == want.keys() and sum(got[k] != want[k] for k in got) <= 2
        rows = log.collect()
        assert {r.event for r in rows} == {0, 1} and all(r.elements >= 0 and r.tests >= r.elements for r in rows)
        assert sum(r.elements for r in rows) == 2 * len(got)


def test_simulation_grows_and_divides(spark):
    e = elements(spark, [(c, k, 40 * c + k, k, 0) for c in range(12) for k in range(4)])
    out, log = runtime.simulate(e, 20, runtime.Plan(2, cadence=2, ranks=2, slices=24, dt=1.0, growth=1, divide_at=5, policy="learned"))
    assert out.count() > 48 and out.select("cell_id").distinct().count() > 12 and log.count() == 2


def test_empty_tissue(spark):
    e = elements(spark, [])
    assert interactions.binned(e, 10).count() == 0
    assert score.cell_work(e, 10).count() == 0
    assert score.extent(e, 10) == (0, 1)


def test_score_by_hand(spark):
    rows = [(1, k, 1, 1, 1) for k in range(3)] + [(2, k, 11, 1, 1) for k in range(2)] + [(3, k, 31, 1, 1) for k in range(4)]
    got = {r.cell_id: r.work for r in score.cell_work(elements(spark, rows), 10).collect()}
    assert got == {1: 15, 2: 10, 3: 16}
    assert {r.cell_id: r.work for r in score.cell_work(elements(spark, rows), 10, "per_element").collect()} == got


def test_ghosts_and_assembly(spark):
    e = elements(spark, [(1, k, 5 * k, 0, 0) for k in range(20)])
    placed = ghosts.attach(e, [50.0], 10)
    assert placed.where("is_ghost").count() == 4
    assert ghosts.assemble(placed).count() == 20
    assert ghosts.min_width(10, 3) == 4


def test_ranks_narrower_than_the_cutoff_are_refused(spark):
    e = elements(spark, [(1, k, 10 * k, 0, 0) for k in range(12)])
    with pytest.raises(ValueError):
        interactions.slab_counts(e, 50, [40.0, 50.0, 60.0, 70.0])
    brute = sum(1 for a in range(12) for b in range(12) if a != b and abs(a - b) <= 5)
    assert interactions.slab_counts(e, 50, [40.0, 90.0]).agg(F.sum("n_pairs")).first()[0] == brute
    bounds = [3.0, 7.0, 7.5, 20.0]
    at = [-1.0, 3.0, 6.9, 7.2, 7.5, 19.0, 20.0, 99.0]
    got = spark.createDataFrame([(x,) for x in at], "x double").select(ghosts.rank_of(F.col("x"), bounds)).collect()
    assert [r[0] for r in got] == [sum(x >= b for b in bounds) for x in at]


def test_division_keeps_elements(spark, tiny):
    order = TISSUES["order"](spark, tiny)
    assert mechanics.divide(order).count() == order.count()


def test_plans(spark, tiny):
    plan = interactions.binned(TISSUES["order"](spark, tiny), 5000)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan
    bins = grid.bins(TISSUES["order"](spark, tiny), 5000)._jdf.queryExecution().executedPlan().toString()
    assert "l_comment" not in bins


@pytest.mark.parametrize("name", ["partition_shares_event", "ghost_replication", "reactive_proposals", "holt_forecast", "growth_snapshots", "sweep_cases", "min_width_repair", "stream_telemetry_batch_equal", "join_as_of", "forces_event", "slab_forces_order", "rollout_reactive", "rollout_holt", "moved_slices_reactive", "lineage_closure", "parity_numpy", "parity_sql", "scenario_source", "partition_nearest_event", "evaluator_work_by_size", "udtf_stencil"])
def test_catalogue_against_sql(spark, tiny, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    got = catalogue.queries()[name](spark, tiny).toPandas()
    want = con.execute(catalogue.oracle_sql()[name]).df()
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    key = lambda df: sorted(tuple("" if v is None or v != v else str(round(float(v), 5)) if isinstance(v, (int, float)) else str(v) for v in r) for r in df[columns].astype(object).itertuples(index=False))
    assert key(got) == key(want)


def test_work_aware_beats_uniform_on_a_skewed_tissue(spark, tiny):
    shares = {n: [r.work for r in catalogue.queries()[f"partition_{n}_event"](spark, tiny).collect()] for n in ("uniform", "shares")}
    assert max(shares["shares"]) < 0.4 * max(shares["uniform"])
    assert partitioner.optimal([1, 2, 3], 1) == 6


def test_lineage_has_no_row_limit(spark):
    edges = spark.createDataFrame([(g, p, c) for g in (1, 2, 3) for p in range(2 ** (g - 1), 2**g) for c in (2 * p, 2 * p + 1)], "generation int, parent bigint, child bigint")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "5")
    try:
        got = {tuple(r) for r in mechanics.lineage(edges).select("ancestor", "descendant", "since", "generations").collect()}
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")
    assert got == {(a, d, a.bit_length(), k) for a in range(1, 8) for k in range(1, 4) for d in range(a << k, (a + 1) << k) if d < 16}


def test_tiles_meet_whatever_the_partitions(spark):
    rows = [(c, 1, 3 * c, c % 7, c % 5) for c in range(60)]
    e = elements(spark, rows)
    brute = {a[0]: sum(1 for b in rows if a is not b and sum((a[k] - b[k]) ** 2 for k in (2, 3, 4)) <= 400) for a in rows}
    own = {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": "13"}
    before = {k: spark.conf.get(k) for k in own}
    try:
        for k, v in own.items():
            spark.conf.set(k, v)
        got = {r.cell_id: r.n_pairs for r in interactions.all_pairs_tiled(e, 20, tile=8).collect()}
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    assert got == brute


def test_elements_that_lie_together_are_tested_once(spark):
    """Copies of a tissue raise the counts and forces, not the pairs of sites that are made."""
    rows = [(c, k, 7 * c, 5 * k, c % 3, "ab"[c % 2]) for c in range(12) for k in range(3)]
    whole = [(100 * i + c, k, x, y, z, t, None) for i in range(5) for c, k, x, y, z, t in rows]
    e = spark.createDataFrame(whole, SCHEMA)
    want = {(r.cell_id, r.element_no): r.n_pairs for r in interactions.pair_counts(interactions.binned(e, 20)).collect()}
    assert {(r.cell_id, r.element_no): r.n_pairs for r in interactions.binned_counts(e, 20).collect()} == want
    assert {(r.cell_id, r.element_no): r.n_pairs for r in interactions.slab_counts(e, 20, [40.0]).collect()} == want
    assert interactions.sites(e).count() == len(rows)
    assert interactions.met_sites(interactions.sites(e), 20).count() == interactions.met_sites(interactions.sites(e.where("cell_id < 100")), 20).count()

    def force(r, a, b):
        (u, v, near, far) = INTRA if a[0] == b[0] else (INTER[0], INTER[1] * (1 if a[5] == b[5] else OTHER_TYPE), *INTER[2:])
        return u / near * math.exp(-r / 20 / near) - v / far * math.exp(-r / 20 / far)

    for got in (mechanics.velocity(e, 20), interactions.slab_forces(e, 20, [40.0])):
        got = {(r.cell_id, r.element_no): (r.vx, r.vy, r.vz) for r in got.collect()}
        assert len(got) == len(whole)
        for a in whole[::7]:
            v = [0.0, 0.0, -MEMBRANE[0] / MEMBRANE[1] * math.exp(-a[4] / (MEMBRANE[1] * 20))]
            for b in whole:
                r = math.dist(a[2:5], b[2:5])
                if 0 < r <= 20:
                    v = [p + force(r, a, b) / r * (a[2 + i] - b[2 + i]) for i, p in enumerate(v)]
            assert got[a[0], a[1]] == pytest.approx(tuple(v), abs=1e-9)


def test_lines_are_shuffled_once(spark, tiny):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = TISSUES["order"](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert plan.count("Exchange hashpartitioning(l_orderkey") == 1 and plan.count("Exchange hashpartitioning") == 4


def shuffle_files(spark):
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {n for n in (files.apply(i).getName() for i in range(files.size())) if n.startswith("shuffle_")}


def test_a_settled_table_leaves_no_shuffle_files_nor_side_files(spark, tiny, tmp_path, monkeypatch):
    monkeypatch.setattr("tissuebalance.sources.scratch.scratch", lambda _, name: f"file://{tmp_path}/{name}")
    before = shuffle_files(spark)
    held = settled(TISSUES["order"](spark, tiny).select("cell_id", "element_no", "x"))
    until = time.time() + 20
    while shuffle_files(spark) - before and time.time() < until:
        time.sleep(0.2)
    assert not shuffle_files(spark) - before
    assert held.count() == TISSUES["order"](spark, tiny).count()
    assert all(p.suffix == ".parquet" for p in tmp_path.rglob("*") if p.is_file())


def test_sites_go_to_the_bins_that_their_sphere_reaches(spark):
    rows = [(c, 1, (37 * c) % 101 - 50, (53 * c) % 97 - 40, (29 * c) % 89 - 30) for c in range(150)] + [(200, 1, 40, 0, 0), (201, 1, 20, 0, 0), (202, 1, -20, 0, 0), (203, 1, 0, 0, 0)]
    spots = interactions.sites(elements(spark, rows))
    for cutoff in (20, 7):
        want = sum(1 for a in rows for b in rows if sum((a[k] - b[k]) ** 2 for k in (2, 3, 4)) <= cutoff**2)
        assert interactions.met_sites(spots, cutoff).agg(F.sum("n")).first()[0] == want
        copies = grid.reached(grid.with_bins(spots, 2.0 * cutoff), 2.0 * cutoff, cutoff).count()
        assert copies < 10 * len(rows)


def test_one_rank_is_swept_by_many_tasks(spark):
    """Runs of planes, with ghosts between them, give one rank's counts."""
    rows = [(c, k, 90 * c + k, (31 * c + 7 * k) % 60 - 30, (17 * c) % 50) for c in range(-12, 12) for k in range(3)]
    rows += [(c, 1, 9 * c, 5, c % 40) for c in range(100, 160)]
    spots = interactions.sites(elements(spark, rows))
    found = interactions.slab_sites(spots, 20, [])
    assert found.select(F.spark_partition_id()).distinct().count() > 1
    want = {(x, y, z): sum(1 for b in rows if (x - b[2]) ** 2 + (y - b[3]) ** 2 + (z - b[4]) ** 2 <= 400) - 1 for _, _, x, y, z in rows}
    got = found.collect()
    assert len(got) == len(want) and {(r.x, r.y, r.z): r.n_pairs for r in got} == want and {r["rank"] for r in got} == {0}
    ranks = interactions.slab_sites(spots, 20, [-400.0, 5.0, 600.0]).collect()
    assert {(r.x, r.y, r.z): (r.n_pairs, r.tests) for r in ranks} == {(r.x, r.y, r.z): (r.n_pairs, r.tests) for r in got}
    bins = {}
    for r in rows:
        bins[tuple(p // 20 for p in r[2:])] = bins.get(tuple(p // 20 for p in r[2:]), 0) + 1
    for r in got:
        assert r.tests == sum(n for b, n in bins.items() if all(abs(p // 20 - q) <= 1 for p, q in zip((r.x, r.y, r.z), b, strict=True)))


def test_pairs_come_in_pieces(monkeypatch):
    monkeypatch.setattr(kernels, "PAIRS_AT_ONCE", 5)
    starts, sizes = np.array([4, 0, 9, 2, 2]), np.array([0, 3, 0, 11, 2])
    got = [(i, j) for a, b in kernels.expanded(starts, sizes) for i, j in zip(a.tolist(), b.tolist(), strict=True)]
    assert got == [(i, s + k) for i, (s, n) in enumerate(zip(starts.tolist(), sizes.tolist(), strict=True)) for k in range(n)]
    assert not list(kernels.expanded(starts[:0], sizes[:0])) and not list(kernels.expanded(starts[:1], sizes[:1]))


def test_forces_within_cells_take_one_pass(spark, tiny):
    """No pairs of elements are made as rows, and a cell may go over several batches."""
    rows = [(c, k, (7 * c * k) % 23, (5 * k + c) % 19, (3 * k) % 17, "ab"[k % 2]) for c, size in enumerate((1, 9, 3, 4, 25, 2)) for k in range(size)]
    e = spark.createDataFrame([(*r, None) for r in rows] + [(4, 99, None, 1, 1, "a", None), (None, 1, 0, 0, 0, None, None), (None, 2, 3, 0, 0, None, None)], SCHEMA)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "4")
    try:
        got = {(r.cell_id, r.element_no): (r.ux, r.uy, r.uz) for r in mechanics.own_cell(e, 12).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert len(got) == len(rows) + 3 and got[4, 99] == (0.0, 0.0, 0.0) and got[None, 1][0] != 0.0

    def more(r, same):
        one, two = ((u / near * math.exp(-r / 12 / near) - v / far * math.exp(-r / 12 / far)) for u, v, near, far in (INTRA, (INTER[0], INTER[1] * (1 if same else OTHER_TYPE), *INTER[2:])))
        return one - two

    for a in rows:
        want = [0.0, 0.0, 0.0]
        for b in rows:
            if a[0] == b[0] and 0 < (r := math.dist(a[2:5], b[2:5])) <= 12:
                want = [w + more(r, a[5] == b[5]) / r * (a[2 + i] - b[2 + i]) for i, w in enumerate(want)]
        assert got[a[:2]] == pytest.approx(tuple(want), abs=1e-9)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = mechanics.own_cell(TISSUES["order"](spark, tiny), 5000)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "Generate" not in plan and plan.count("Exchange hashpartitioning") == 4


def test_growing_parts_are_written_once(spark, tiny, monkeypatch):
    made = []
    monkeypatch.setattr(tissue_queries, "settled", lambda df, by=(): made.append(settled(df, by)) or made[-1])
    got = tissue_queries.evaluator_seconds(spark, tiny, serial=0, quadratic=0).collect()
    order = TISSUES["order"](spark, tiny)
    assert made[0].count() == order.count() and made[0].columns == ["cell_id", "element_no", "x", "y", "z", "one_in"]
    want = {r.one_in: r["count"] for r in tissue_queries.nested_parts(order).groupBy("one_in").count().collect()}
    assert [(r.evaluator, r.elements) for r in got] == [(e, want[q]) for q in tissue_queries.SIZES for e in ("binned", "slab")]
