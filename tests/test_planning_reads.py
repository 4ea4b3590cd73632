"""Planning queries plan for the requests of a given table."""

import duckdb
import pytest

import __spark_entry__ as driver
from vecpath.queries import ORACLES

GRIDS = [
    "access_path_matrix", "advise_grid", "choose_kernel_grid", "choose_path_grid", "cost_model_grid", "crossover_interpolated", "crossover_points",
    "fallback_reason_table", "policy_regret",
]


@pytest.mark.parametrize("name", GRIDS)
def test_plans_for_the_events(spark, sf, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM read_parquet('{sf}/events.parquet')")
    got = driver.queries()[name](spark, sf)
    assert any("events.parquet" in f for f in got.inputFiles())
    cols = sorted(got.columns)
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({ORACLES[name]})").fetchall()
    assert sorted(map(str, (tuple(r) for r in got.select(cols).collect()))) == sorted(map(str, want)) and want
    if "n_requests" in cols and name in ("choose_kernel_grid", "choose_path_grid", "advise_grid", "fallback_reason_table"):
        assert sum(r.n_requests for r in got.collect()) == spark.read.parquet(f"{sf}/events.parquet").count()
