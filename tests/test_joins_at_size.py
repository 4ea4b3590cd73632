"""Joins of packed tiles: what the optimizer may not broadcast, and how often a vector moves."""

import numpy as np
from pyspark.sql import functions as F

from vecpath.functions.metrics import resolve
from vecpath.operators import joins

VECTORS = "vec_id long, embedding array<float>"


def vectors(spark, n=300, seed=5):
    return spark.createDataFrame([(i, v) for i, v in enumerate(np.random.default_rng(seed).normal(size=(n, 8)).tolist())], VECTORS)


def ran(df):
    """(rows, the plan as it ran)."""
    rows = df.collect()
    return rows, df._jdf.queryExecution().executedPlan().toString()


def test_range_join_never_broadcasts_packed_rows(spark):
    df = vectors(spark)
    rows, plan = ran(joins.vector_range_join(df, df, 0.3, block_rows=7))
    x = np.array([r.embedding for r in df.orderBy("vec_id").collect()])
    x /= np.linalg.norm(x, axis=1)[:, None]
    assert {(r.l_id, r.r_id) for r in rows} == set(zip(*(i.tolist() for i in np.nonzero(x @ x.T > 0.3))))
    assert "BroadcastExchange" not in plan and "SortMergeJoin" in plan


def test_small_tiles_give_the_same_pairs(spark):
    df = vectors(spark)
    pairs = lambda tile, upper: sorted(
        (r.query_id, r.r_id) for r in joins._pairs(df, df, "vec_id", "vec_id", "embedding", resolve("cosine"), 0.3, None, None, None, 50, upper, tile).collect()
    )
    assert pairs(700, False) == pairs(1 << 20, False) and pairs(700, True) == pairs(1 << 20, True)


def test_topk_join_never_broadcasts_packed_rows(spark):
    df = vectors(spark)
    rows, plan = ran(joins.vector_topk_join(df, df, 2, block_rows=7))
    assert len(rows) == 600 and all(r.l_id == r.r_id for r in rows if r["rank"] == 1)
    assert "BroadcastExchange" not in plan and "SortMergeJoin" in plan


def test_vectors_move_once_for_each_tile_of_the_other_side(spark):
    df = vectors(spark)
    assert len(joins.self_pairs(df, 0.3, block_rows=5).collect()) == len(joins.self_pairs(df, 0.3).collect())
    packed, tiles = joins._packed(df, "vec_id", "embedding", None, joins.TILE_BYTES, "i")
    row = packed.first()
    assert tiles == 1 and len(row.i_ids) == 8 * 300 and len(row.i_x) == 4 * 8 * 300  # 60 blocks of 5 rows in one tile, floats as they are


def test_a_tile_moves_once_for_each_group_of_tiles(spark):
    df = vectors(spark)
    tile, metric = 200, resolve("cosine")
    tiles = joins._packed(df, "vec_id", "embedding", None, tile, "i")[1]
    pairs = joins._pairs(df, df, "vec_id", "vec_id", "embedding", metric, 0.3, None, None, None, 50, True, tile)
    plan = pairs._jdf.queryExecution().optimizedPlan().toString()
    ways = int(np.ceil(np.sqrt(4 * spark.sparkContext.defaultParallelism)))
    assert tiles == 48 and max(ways, 3) < tiles and f"% {max(ways, 3)}" in plan  # before: 48 times
    want = sorted((r.query_id, r.r_id) for r in joins._pairs(df, df, "vec_id", "vec_id", "embedding", metric, 0.3, None, None, None, 50, True).collect())
    got = sorted((r.query_id, r.r_id) for r in pairs.collect())
    assert got == want and len(set(got)) == len(got)
