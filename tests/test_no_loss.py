"""Nothing is lost without a word: vectors of several lengths, large batches, ties of other ids, late rows."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecpath.measures.reads import reads
from vecpath.operators import scan as scans
from vecpath.operators.graph import CALLBACKS, graph_build, graph_rebuild, graph_search
from vecpath.operators.joins import self_pairs, vector_probe_join, vector_range_join, vector_topk_join
from vecpath.operators.relational import relational_scan_sum, store_indexed, stored_probe_sum
from vecpath.operators.scan import QueryBlock, collect_queries, scan, select_product
from vecpath.sources.stored import shared_folder, stored
from vecpath.streaming.requests import answer_cached, late_rows, strategy_for

VECTORS = "vec_id long, embedding array<double>"


def threes(n=11, seed=2):
    rng = np.random.default_rng(seed)
    return [(i, rng.normal(size=3).tolist()) for i in range(n)]


def test_joins_keep_every_length(spark):
    rows = threes()
    alone = spark.createDataFrame(rows, VECTORS)
    mixed = spark.createDataFrame([*rows, (100, [1.0, 2.0, 3.0, 4.0]), (101, [1.0, 2.0, 3.0, 4.1]), (102, None), (103, [None, 1.0, 2.0])], VECTORS)
    for size in (2_000, 3):
        base = {(r.l_id, r.r_id) for r in vector_range_join(alone, alone, -0.5, block_rows=size).collect()}
        got = {(r.l_id, r.r_id) for r in vector_range_join(mixed, mixed, -0.5, block_rows=size).collect()}
        assert len(base) > 40 and got == base | {(a, b) for a in (100, 101) for b in (100, 101)}
        pairs = {(r.l_id, r.r_id) for r in self_pairs(mixed, -0.5, block_rows=size).collect()}
        assert pairs == {(a, b) for a, b in got if a < b}
        top = vector_topk_join(mixed, mixed, 2, block_rows=size).groupBy("l_id").count().collect()
        assert {r.l_id: r["count"] for r in top} == {i: 2 for i in [*range(11), 100, 101]}


def test_graph_takes_the_common_length_and_counts_the_rest(spark, tmp_path):
    rows = [*threes(), (100, [1.0, 2.0, 3.0, 4.0]), (102, None), (103, [float("nan"), 1.0, 2.0]), (104, [0.0, 0.0, 0.0])]
    df = spark.createDataFrame(rows, VECTORS)
    g = graph_build(df, metric="cosine", m=4, ef_build=8, shards=2, path=f"file://{tmp_path}/index")
    assert g.nodes().count() == 11 and g.rejected() == 4
    assert graph_build(df, metric="ip", m=4, ef_build=8, shards=None, dim=4).nodes().count() == 1
    more = df.unionByName(spark.createDataFrame([(i + 200, v) for i, v in threes(5, 9)], VECTORS))
    for shard in range(2):
        g = graph_rebuild(g, more, shard)
    assert g.nodes().count() == 16
    q = QueryBlock(np.arange(3), np.array([v for _, v in threes(3)]))
    ok = df.where("vec_id % 2 = 0").select("vec_id")
    found = [
        sorted((r.query_id, r["rank"], r.vec_id, round(r.score, 9)) for r in graph_search(g, q, 3, 50, ok, callback=c).collect()) for c in CALLBACKS
    ]
    assert found[0] == found[1] == found[2] and len(found[0]) == 9


def test_probe_join_without_gathering_the_left_side(spark):
    df = spark.createDataFrame(threes(40), VECTORS)
    g = graph_build(df, metric="cosine", m=8, ef_build=32, shards=2)
    one = sorted(map(tuple, vector_probe_join(df, g, 3, 64).collect()))
    two = sorted(map(tuple, vector_probe_join(df, g, 3, 64, max_bytes=100, block_rows=7).collect()))
    assert len(one) == 120 and [r[:3] for r in one] == [r[:3] for r in two]


def test_query_batches_are_measured_first(spark, monkeypatch):
    many = spark.range(1_100_000).select(F.col("id").alias("query_id"), F.array(F.lit(1.0), F.col("id").cast("double")).alias("qvec"))
    assert len(collect_queries(many)) == 1_100_000
    with pytest.raises(ValueError, match="bytes"):
        collect_queries(many, max_bytes=1 << 20)
    monkeypatch.setattr(scans, "QUERY_BYTES", 1_000)
    with pytest.raises(ValueError, match="bytes"):
        select_product(spark.createDataFrame(threes(), VECTORS), many)
    with pytest.raises(ValueError, match="dimensions"):
        collect_queries(spark.createDataFrame([(1, [1.0, 2.0]), (2, [1.0, 2.0, 3.0, 4.0])], "query_id long, qvec array<double>"))


def test_ties_of_ids_that_are_not_numbers(spark):
    rows = spark.createDataFrame([(x, [1.0, 0.0]) for x in "dbeacf"], "name string, embedding array<double>").repartition(1)
    q = QueryBlock(np.array([7]), np.array([[1.0, 0.0]]))
    got = scan(rows, q, row_id="name", k=3).orderBy("rank").collect()
    assert [r.name for r in got] == ["a", "b", "c"]


def test_stored_probe_prunes_files(spark, tmp_path, sf):
    path, price = f"file://{tmp_path}/items", F.col("l_extendedprice") < 912
    items = spark.read.parquet(f"{sf}/../sf0.01/lineitem.parquet")
    row = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice"]
    built = []
    make = lambda p: built.append(p) or store_indexed(items, p, "l_extendedprice", row, pages=32)
    assert stored(spark, "items", str(tmp_path), make) == stored(spark, "items", str(tmp_path), make) and len(built) == 1
    path = built[0]
    for one_task in (False, True):
        probe = stored_probe_sum(spark, path, "l_extendedprice", price, row, "l_extendedprice", one_task)
        plain = relational_scan_sum(items, "l_extendedprice", 912, "l_extendedprice", one_task)
        assert probe.first() == plain.first()
    probe = stored_probe_sum(spark, path, "l_extendedprice", price, row, "l_extendedprice")
    plan = probe._jdf.queryExecution().toString()
    assert "dynamicpruning" in plan and "PushedFilters: [IsNotNull(l_extendedprice), LessThan(l_extendedprice,912.0)" in plan
    assert reads(probe)["rows"] < reads(relational_scan_sum(items, "l_extendedprice", 912, "l_extendedprice"))["rows"]


def test_shared_folder_is_needed_on_a_cluster(spark):
    class Cluster:
        conf = type("C", (), {"get": staticmethod(lambda *a: None)})()
        sparkContext = type("S", (), {"master": "spark://host:7077", "applicationId": "x"})()

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        shared_folder(Cluster())
    assert shared_folder(spark)


def test_cache_answers_repeats_over_batches(spark, tmp_path):
    vectors = spark.createDataFrame(threes(30), VECTORS)
    for i, keys in enumerate(([1, 2, 2], [2, 3], [1, 3, 9])):
        spark.createDataFrame([(10 * i + j, k) for j, k in enumerate(keys)], "request long, about long").coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    stream = spark.readStream.schema("request long, about long").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")
    asked = []

    def queries_of(keys):
        asked.extend(r.about for r in keys.collect())
        return keys.join(vectors, keys.about == vectors.vec_id).select("about", F.col("embedding").alias("qvec"))

    got = answer_cached(spark, stream, vectors, "about", queries_of, 2).collect()
    assert sorted(asked) == [1, 2, 3, 9]
    exact = {(r.l_id, r["rank"]): r.r_id for r in vector_topk_join(vectors, vectors, 2).collect()}
    assert len(got) == 16 and all(exact[r.about, r["rank"]] == r.answer_id for r in got)


def test_late_rows_are_counted(spark, tmp_path):
    day = dt.datetime(2024, 1, 1)
    for i, hours in enumerate(([0, 1], [30, 31], [31], [2, 32])):
        spark.createDataFrame([(day + dt.timedelta(hours=h),) for h in hours], "ts timestamp").coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    stream = spark.readStream.schema("ts timestamp").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")
    counted = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).count()
    running = counted.writeStream.format("noop").option("checkpointLocation", f"{tmp_path}/checkpoint").trigger(availableNow=True).start()
    running.awaitTermination()
    assert late_rows(running) == 1


def test_kernel_of_a_batch_follows_the_planner():
    assert strategy_for(1, 64) == "block_rows" and strategy_for(100, 64) == "tensor" and strategy_for(10_000, 1024) == "tensor"


def test_search_takes_query_tables_of_any_size(spark, monkeypatch):
    from vecpath import api

    rows = spark.createDataFrame(threes(40), VECTORS).withColumn("price", F.col("vec_id") * 10)
    asked = rows.where("vec_id < 7").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))
    cond = F.col("price") < 300
    key = lambda df: sorted((r.query_id, r["rank"], r.vec_id, round(r.score, 9)) for r in df.collect())
    small, near = key(api.search(rows, asked, 4, cond=cond)), api.search(rows, asked, bound=0.5, cond=cond).count()
    assert len(small) == 28
    monkeypatch.setattr(api, "QUERY_BYTES", 100)
    assert key(api.search(rows, asked, 4, cond=cond)) == small
    assert api.search(rows, asked, bound=0.5, cond=cond).count() == near


def test_walks_in_blocks_find_what_single_walks_find():
    from vecpath.operators.graph import Shard

    rng = np.random.default_rng(5)
    x = rng.normal(size=(600, 12))
    x /= np.sqrt((x * x).sum(1))[:, None]
    g = Shard.build(np.arange(600) * 3, x, 8, 32, 1)
    assert g.top >= 1
    q = rng.normal(size=(40, 12))
    for allowed in (None, rng.random(600) < 0.3, rng.random(600) < 0.01, np.zeros(600, bool)):
        for ef in (10, 50, 5_000):
            block, costs = g.search_block(q, 10, ef, allowed)
            for one, found, cost in zip(q, block, costs):
                want, spent = g.search(one, 10, ef, allowed)
                assert [j for _, j in found] == [j for _, j in want] and np.allclose([s for s, _ in found], [s for s, _ in want])
                assert cost["filter_probes"] > 0 or allowed is None
                assert abs(cost["distance_evals"] - spent["distance_evals"]) <= 0.05 * spent["distance_evals"] + 20
