"""Queries that once made their data up read a table: its bytes, and what its rows change."""

import re

import duckdb
import pytest
from pyspark.sql import functions as F
from tissuebalance.plans import catalogue

MOVED = {
    "ablation": "events", "combine_step_grid": "lineitem", "end_to_end_calm": "events", "min_width_repair": "events", "parity_numpy": "events", "parity_sql": "events",
    "policy_table_calm": "events", "policy_table_scenarios": "events", "policy_table_still": "events", "scenario_loads": "events",
}


@pytest.mark.parametrize("name", MOVED)
def test_query_reads_its_table(spark, tiny, name):
    plan = catalogue.queries()[name](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert re.search(rf"FileScan parquet.*{MOVED[name]}\.parquet", plan)


@pytest.mark.parametrize("name", ["combine_step_grid", "min_width_repair", "parity_numpy", "parity_sql", "scenario_loads"])
def test_moved_query_against_sql(spark, tiny, name):
    con = duckdb.connect()
    for t in ("events", "lineitem"):
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    got = catalogue.queries()[name](spark, tiny).toPandas()
    want = con.execute(catalogue.oracle_sql()[name]).df()[list(got.columns)]
    assert len(got) and sorted(map(tuple, got.round(5).to_numpy().tolist())) == sorted(map(tuple, want.round(5).to_numpy().tolist()))


def test_bounds_need_repair(spark, tiny):
    rows = catalogue.queries()["min_width_repair"](spark, tiny).groupBy("case").agg(F.sort_array(F.collect_list("bound")).alias("b")).collect()
    assert len(rows) == 12 and all(r.b[0] == 0 and r.b[-1] == 40 and min(y - x for x, y in zip(r.b, r.b[1:])) >= 5 for r in rows)
