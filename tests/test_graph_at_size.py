"""Graphs of larger shards: builds and saturated walks whose work stays bounded."""

import time

import numpy as np

from vecpath.operators.graph import Shard


def unit_rows(n, dim=16, seed=3):
    x = np.random.default_rng(seed).normal(size=(n, dim))
    return x / np.linalg.norm(x, axis=1)[:, None]


def best(x, q, k, allowed=None):
    s = x @ q
    return np.argsort(-(s if allowed is None else np.where(allowed, s, -np.inf)), kind="stable")[:k].tolist()


def test_a_build_with_many_links_considers_all_rows_in_time():
    x = unit_rows(1_500)
    began = time.process_time()
    g = Shard.build(np.arange(1_500), x, 48, 384, 1)
    assert time.process_time() - began < 30  # with a walk for every row and a cut for every link 400 rows alone took 33 s
    assert len(g.ids) == 1_500 and max(len(node[0]) for node in g.links) <= 96 and max(len(y) for node in g.links for y in node[1:]) <= 48
    for q in x[:20]:
        assert [j for _, j in g.search(q, 10, 100)[0]] == best(x, q, 10)


def test_a_saturated_walk_costs_what_it_reaches():
    x = unit_rows(6_000)
    g, allowed = Shard.build(np.arange(6_000) * 2, x, 8, 32, 1), np.arange(6_000) % 10 == 0
    began = time.process_time()
    found, cost = g.search_block(x[:100], 10, 1 << 20, allowed)
    assert time.process_time() - began < 5  # 14 s when each step was taken by itself
    assert [[j // 2 for _, j in f] for f in found] == [best(x, q, 10, allowed) for q in x[:100]]
    assert all(c["reached"] == 6_000 and c["filter_probes"] == 6_000 and c["hops"] >= 6_000 for c in cost)


def test_a_shard_answers_thousands_of_saturated_probes():
    x = unit_rows(4_000)
    g, allowed = Shard.build(np.arange(4_000), x, 8, 32, 1), np.arange(4_000) % 10 == 1
    began = time.process_time()
    found = [f for f, _ in g.search_all(x, 5, 1 << 20, allowed)]
    assert time.process_time() - began < 30
    assert all([j for _, j in f] == best(x, q, 5, allowed) for f, q in zip(found, x)) and len(found) == 4_000


def test_the_width_grows_to_the_recall(spark):
    from vecpath.measures.accuracy import widened

    exact = spark.createDataFrame([(1, i) for i in range(10)], "query_id long, vec_id long")
    search = lambda width: exact.where(f"vec_id < {width // 20}")
    assert widened(search, exact, 64, 1_000)[1] == 256 and widened(search, exact, 64, 100)[1] == 128


def test_recall_ladder_equals_its_sql(spark, sf):
    import duckdb

    from vecpath.queries import ORACLES, QUERIES

    con = duckdb.connect()
    for t in ("embeddings", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    cols = ["bound", "mode", "n_exact", "recall_ok"]
    got = QUERIES["graph_recall_ladder"](spark, sf).select(cols).collect()
    assert sorted(map(tuple, got)) == sorted(con.execute(f"SELECT {', '.join(cols)} FROM ({ORACLES['graph_recall_ladder']})").fetchall())
