import numpy as np
import pytest
from pyspark.sql import functions as F

from vecpath.api import search, search_per_shard
from vecpath.functions.metrics import METRICS, cosine, literal_vector
from vecpath.measures.accuracy import mean_counters, recall_at_k
from vecpath.operators.graph import GraphIndex, Shard, graph_build, graph_post_grow, graph_search
from vecpath.operators.joins import nested_loop_join, self_pairs, vector_range_join, vector_topk_join
from vecpath.operators.relational import KeyIndex, relational_probe_sum, relational_scan_sum
from vecpath.operators.scan import STRATEGIES, collect_queries, phase_times, scan, scan_split, select_bound, select_product
from vecpath.sources.tables import LADDER, Catalog, synthetic


@pytest.fixture(scope="module")
def c(spark, sf):
    return Catalog(spark, sf)


@pytest.fixture(scope="module")
def vectors(c):
    rows = c.embeddings.orderBy("vec_id").collect()
    return np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], float)


def rows_of(df, *cols):
    return sorted((tuple(r) for r in df.select(*cols).collect()))


def exact_topk(vectors, q, k, metric, keep=None):
    ids, x = vectors
    s = METRICS[metric].block(x, q[None])[:, 0]
    s = -s if METRICS[metric].larger_is_better else s
    at = [i for i in np.lexsort((ids, s)) if keep is None or keep[i]]
    return [int(ids[i]) for i in at[:k]]


@pytest.mark.parametrize("metric", sorted(METRICS))
def test_topk_of_every_metric(c, vectors, metric):
    q = collect_queries(c.queries(5))
    got = {}
    for r in scan(c.embeddings, q, k=7, metric=metric).orderBy("rank").collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    for i, v in zip(q.ids.tolist(), q.matrix):
        if metric == "sign_hamming":
            assert len(got[i]) == 7
        else:
            assert got[i] == exact_topk(vectors, v, 7, metric)


@pytest.mark.parametrize("metric", sorted(METRICS))
def test_expression_and_kernel_agree(spark, metric):
    rng = np.random.default_rng(0)
    x, q = rng.normal(size=(30, 9)), rng.normal(size=9)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, v array<double>")
    got = df.select("vec_id", METRICS[metric].column(F.col("v"), literal_vector(q)).alias("s")).orderBy("vec_id").collect()
    assert np.allclose([r.s for r in got], METRICS[metric].block(x, q[None])[:, 0])


def test_all_strategies_and_places_of_the_predicate_agree(c):
    q, cond = collect_queries(c.queries(6)), F.col("o_totalprice") < 251000
    want = None
    for strategy in STRATEGIES:
        for pushdown in ("late", "inline", "minibatch", "none"):
            got = rows_of(scan(c.mix_orders(), q, bound=0.2, cond=cond, strategy=strategy, pushdown=pushdown, batch_rows=37), "query_id", "vec_id")
            want = want or got
            assert got == want
    attributes = c.orders.select(F.col("o_orderkey").alias("vec_id"), "o_totalprice")
    assert rows_of(scan_split(attributes, c.embeddings, q, cond, bound=0.2), "query_id", "vec_id") == want
    assert rows_of(select_product(c.mix_orders(), c.queries(6), bound=0.2, cond=cond), "query_id", "vec_id") == want
    first = q.matrix[0]
    assert rows_of(select_bound(c.mix_orders().where(cond), first, bound=0.2), "vec_id") == [(v,) for i, v in want if i == 0]


def test_golden_counts(c, sf):
    if not sf.endswith("sf0.001"):
        pytest.skip("values are for one size")
    q = collect_queries(c.queries(100))
    assert scan(c.embeddings, q, bound=0.3).count() == 497
    for bound, n in zip((6000, 51000, 251000, 450000), (12, 293, 1323, 2547)):
        assert scan(c.mix_orders(), q, bound=0.2, cond=F.col("o_totalprice") < bound).count() == n
    top = scan(c.embeddings, collect_queries(c.queries(1)), k=5).orderBy("rank").collect()
    assert [(r.vec_id, round(r.score * 1e6)) for r in top] == [(0, 1000000), (17, 334456), (225, 315127), (12, 311027), (483, 300451)]


def test_odd_vectors_are_no_candidates(spark):
    rows = [(0, [1.0, 0.0]), (1, None), (2, [1.0]), (3, [float("nan"), 1.0]), (4, [0.0, 0.0]), (5, [None, 1.0]), (6, [1.0, 0.0]), (7, [-1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    q = collect_queries(spark.createDataFrame([(0, [1.0, 0.0])], "query_id long, qvec array<double>"))
    for strategy in STRATEGIES:
        assert rows_of(scan(df, q, k=10, strategy=strategy), "rank", "vec_id") == [(1, 0), (2, 6), (3, 7)]
    none = collect_queries(spark.createDataFrame([], "query_id long, qvec array<double>"))
    assert scan(df, none, k=3).count() == 0
    assert scan(df.where("false"), q, k=3).count() == 0
    assert scan(df, q, bound=1.0).count() == 0  # the bound is strict
    with pytest.raises(ValueError):
        collect_queries(spark.createDataFrame([(0, [1.0, 0.0])], "query_id long, qvec array<double>"), max_bytes=8)


def test_predicate_and_columns_reach_the_files(c):
    q = collect_queries(c.queries(2))
    plan = scan(c.orders.withColumn("embedding", F.array(F.lit(1.0))), q, "o_orderkey", bound=0.2, cond=F.col("o_totalprice") < 6000)
    text = plan._jdf.queryExecution().executedPlan().toString()
    assert "LessThan(o_totalprice,6000" in text and "o_orderpriority" not in text


def test_phases_sum_to_a_hundred(c):
    got = phase_times(c.mix_orders(), collect_queries(c.queries(10)), F.col("o_totalprice") < 251000).collect()
    assert len(got) == 3 and abs(sum(r.share for r in got) - 100) < 0.2


# ---- joins


def test_joins_agree(c):
    a, b = c.embeddings.where("label = 0"), c.embeddings.where("label = 1")
    want = rows_of(nested_loop_join(a, b, 0.25), "l_id", "r_id")
    for block in (7, 50, 5000):
        assert rows_of(vector_range_join(a, b, 0.25, block_rows=block), "l_id", "r_id") == want
    top = vector_topk_join(a, b, 1, block_rows=30)
    assert top.count() == a.count()
    pairs = rows_of(self_pairs(c.embeddings, 0.35, block_rows=100), "l_id", "r_id")
    assert len(pairs) == 257 if c.sf_dir.endswith("sf0.001") else pairs
    assert all(x < y for x, y in pairs)


# ---- relational


def test_scan_and_probe_give_the_same_sums(c, tmp_path):
    row = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice"]
    index = KeyIndex.build(c.lineitem, "l_extendedprice", row, 4)
    index.save(str(tmp_path / "index"))
    index = KeyIndex.load(c.spark, str(tmp_path / "index"), "l_extendedprice")
    for hi in (0, 1950, 52900, 10**9):
        one = relational_scan_sum(c.lineitem, "l_extendedprice", hi, "l_extendedprice").first()
        assert one == relational_probe_sum(index, c.lineitem, F.col("l_extendedprice") < hi, row, "l_extendedprice").first()
    plan = index.probe(F.col("l_extendedprice") < 1950)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_extendedprice), LessThan(l_extendedprice,1950" in plan


# ---- graph


@pytest.fixture(scope="module")
def graph(c):
    g = graph_build(c.embeddings, metric="cosine", m=8, ef_build=32, shards=2)
    g.packed = g.packed.cache()
    return g


def test_saturated_search_is_exact(c, graph):
    q = collect_queries(c.queries(20))
    for cond in (None, "o_totalprice < 51000"):
        ok = None if cond is None else c.mix_orders().where(cond).select("vec_id")
        want = rows_of(scan(c.mix_orders(), q, k=10, cond=None if cond is None else F.expr(cond)), "query_id", "rank", "vec_id")
        assert rows_of(graph_search(graph, q, 10, 1000, ok), "query_id", "rank", "vec_id") == want


def test_prefilter_returns_only_qualifying_rows_and_costs_more_when_few_qualify(c):
    g = graph_build(c.embeddings, metric="cosine", m=8, ef_build=32, shards=1)
    g.packed = g.packed.cache()
    q = collect_queries(c.queries(50))
    evals = []
    for bound in LADDER.values():
        ok = c.mix_orders().where(F.col("o_totalprice") < bound).select("vec_id")
        found = graph_search(g, q, 10, 32, ok)
        assert found.join(ok, "vec_id", "left_anti").count() == 0
        evals.append(mean_counters(graph_search(g, q, 10, 32, ok, counters=True)).first().distance_evals)
    assert all(a >= b * 0.98 for a, b in zip(evals, evals[1:])) and evals[0] > 1.5 * evals[-1]


def test_recall_grows_with_the_width(c, graph):
    q = collect_queries(c.queries(50))
    exact = scan(c.embeddings, q, k=10)
    recall = [recall_at_k(graph_search(graph, q, 10, ef), exact).agg(F.avg("recall")).first()[0] for ef in (10, 40, 200)]
    assert recall[0] <= recall[1] + 0.01 <= recall[2] + 0.02 and recall[2] > 0.97


def test_post_filter_loses_answers_and_growing_brings_them_back(c, graph):
    q = collect_queries(c.queries(20))
    ok = c.embeddings.where("label < 1").select("vec_id")
    lost = graph_search(graph, q, 10, 1000, ok, "post")
    assert lost.count() < 20 * 10 / 3
    want = rows_of(scan(c.embeddings, q, k=10, cond=F.expr("label < 1")), "query_id", "rank", "vec_id")
    assert rows_of(graph_post_grow(graph, q, 10, ok, 1000), "query_id", "rank", "vec_id") == want


def test_growing_ends_in_an_exact_scan_when_rounds_run_out(c, graph):
    q = collect_queries(c.queries(20))
    want = rows_of(scan(c.embeddings, q, k=10, cond=F.expr("vec_id % 40 = 7")), "query_id", "rank", "vec_id")
    ok = c.embeddings.where("vec_id % 40 = 7").select("vec_id")
    assert len(want) > 0 and rows_of(graph_post_grow(graph, q, 10, ok, 16, max_rounds=2), "query_id", "rank", "vec_id") == want
    assert graph_post_grow(graph, q, 10, ok.where("false"), 16, max_rounds=2).count() == 0


def test_every_request_of_the_stream_is_answered(c, spark, sf, vectors):
    from collections import Counter

    from vecpath.queries import QUERIES
    from vecpath.streaming.requests import answer_batches, request_stream

    ids, x = vectors
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    matches = dict(zip(ids.tolist(), (x @ x.T > 0.3).sum(1).tolist()))
    events = spark.read.parquet(f"{sf}/events.parquet").collect()
    want = {e.event_id: matches[e.event_id % len(ids)] for e in events}
    assert {r.query_id: r.n_matches for r in QUERIES["stream_answers_all"](spark, sf).collect()} == want
    hours, total = Counter(), Counter()
    for e in events:
        at = e.ts.replace(minute=0, second=0, microsecond=0, tzinfo=None)
        hours[at] += 1
        total[at] += want[e.event_id]
    got = QUERIES["stream_hourly_matches"](spark, sf).collect()
    assert {r.window_start: (r.n_requests, r.n_matches) for r in got} == {t: (hours[t], total[t]) for t in hours}
    of = lambda b: b.join(c.embeddings, b.event_id == F.col("vec_id")).select(F.col("event_id").alias("query_id"), F.col("embedding").alias("qvec"))
    few = lambda most: answer_batches(spark, request_stream(spark, sf), c.embeddings, of, max_bytes=most, bound=0.3)
    assert rows_of(few(1_000), "query_id", "vec_id") == rows_of(few(64 << 20), "query_id", "vec_id")


def test_index_round_trip_and_data_source(c, graph, tmp_path):
    from vecpath.sources.index_source import register

    path = str(tmp_path / "graph")
    graph.save(path)
    back = GraphIndex.load(c.spark, path)
    assert (back.metric, back.shards, back.m, back.ef_build) == ("cosine", 2, 8, 32)
    q = collect_queries(c.queries(5))
    assert rows_of(graph_search(back, q, 5, 50), "query_id", "vec_id") == rows_of(graph_search(graph, q, 5, 50), "query_id", "vec_id")
    register(c.spark)
    nodes = c.spark.read.format("vecpath_index").option("path", path).load()
    assert nodes.count() == c.embeddings.count() == graph.nodes().count()
    one = nodes.where("shard = 1")
    assert {r.shard for r in one.select("shard").distinct().collect()} == {1}
    edges = c.spark.read.format("vecpath_index").option("path", path).option("table", "edges").load()
    assert edges.count() == graph.edges().count()


def test_build_is_repeatable():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(200, 8))
    ids = rng.permutation(200)
    one, two = Shard.build(ids, x, 6, 20, 3), Shard.build(ids[::-1], x[::-1], 6, 20, 3)
    assert one.pack(0) == two.pack(0)
    assert all(len(n[0]) <= 12 for n in one.links)
    empty = Shard.build(ids[:0], x[:0], 6, 20, 3)
    assert empty.search(x[0], 5, 10)[0] == []


def test_planned_searches_agree(c, graph):
    q, cond = collect_queries(c.queries(8)), F.col("o_totalprice") < 126000
    want = rows_of(scan(c.mix_orders(), q, k=5, cond=cond), "query_id", "rank", "vec_id")
    for hint in (None, "scan", "matrix", "graph"):
        got = search(c.mix_orders(), q, 5, cond=cond, index=graph, ef=1000, hint=hint)
        assert rows_of(got, "query_id", "rank", "vec_id") == want
    assert rows_of(search_per_shard(c.mix_orders(), q, 5, cond, graph, ef=1000), "query_id", "rank", "vec_id") == want
    with pytest.raises(ValueError):
        search(c.mix_orders(), q, 5, bound=0.2, index=graph, hint="graph")


def test_synthetic_rows_do_not_depend_on_partitions(spark):
    a, b = synthetic(spark, 500, 16), synthetic(spark, 500, 16).repartition(7)
    assert rows_of(a, "id", "attr") == rows_of(b, "id", "attr")
    assert cosine is METRICS["cosine"].column
