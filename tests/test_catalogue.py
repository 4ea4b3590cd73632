import duckdb
import pytest

import __spark_entry__ as driver
from vecpath.queries import ORACLES, QUERIES
from vecpath.sources.tables import TABLES

SAMPLE = [
    "select_bound", "mixed_push", "mixed_no_push", "range_unrolled_b1", "sparse_scan", "topk_l1", "widen256_counts", "rel_probe_sum_10",
    "graph_prefilter_saturated", "post_grow", "choose_path_grid", "crossover_points", "fallback_reason_table", "adaptive_topk",
    "geo_date_topk", "match_cube", "sql_surface", "udtf_topk", "stream_tumbling_batches", "stream_answers", "union_tail",
]


def test_registry():
    assert set(ORACLES) <= set(QUERIES) and set(SAMPLE) <= set(ORACLES)
    assert set(QUERIES) <= set(driver.queries()) and set(ORACLES) <= set(driver.oracle_sql())


def test_entry(spark):
    assert driver.entry(spark).count() == 100


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_its_sql(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    got = driver.queries()[name](spark, sf)
    cols = sorted(got.columns)
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({ORACLES[name]})").fetchall()
    assert sorted(map(str, (tuple(r) for r in got.select(cols).collect()))) == sorted(map(str, want))
