"""What a stream of requests keeps of its answers."""

import numpy as np
from pyspark.sql import functions as F

from vecpath.functions.metrics import METRICS
from vecpath.operators.joins import _cosine_counts
from vecpath.queries.streams import queries_of
from vecpath.sources.tables import Catalog
from vecpath.streaming import requests


def test_a_micro_batch_leaves_counts_and_large_ones_are_not_gathered(spark, sf, monkeypatch):
    c, gathered = Catalog(spark, sf), []
    whole = requests.collect_queries
    monkeypatch.setattr(requests, "collect_queries", lambda *a, **k: gathered.append(1) or whole(*a, **k))
    count = lambda found: found.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    run = lambda most, each: requests.answer_batches(
        spark, requests.request_stream(spark, sf), c.embeddings, queries_of(c), max_bytes=most, each=each, bound=0.3
    )
    few = run(1_000, count)
    assert not gathered and set(few.columns) - {"batch"} == {"query_id", "n"}
    pairs = count(run(requests.BATCH_BYTES, lambda found: found))
    assert gathered and requests.BATCH_BYTES <= 16 << 20
    assert sorted((r.query_id, r.n) for r in few.collect()) == sorted((r.query_id, r.n) for r in pairs.collect())


def test_pairs_of_large_micro_batches_are_counted_where_they_are_found(spark, sf, monkeypatch):
    c = Catalog(spark, sf)
    run = lambda **how: requests.answer_batches(
        spark, requests.request_stream(spark, sf), c.embeddings, queries_of(c), bound=0.3, **how
    )
    pairs = run().groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    expected = sorted((r.query_id, r.n) for r in pairs.collect())
    monkeypatch.setattr(requests, "vector_range_join", None)  # makes pairs
    for most in (1_000, requests.BATCH_BYTES):
        found = run(max_bytes=most, counts=True)
        assert sorted((r.query_id, r.n) for r in found.groupBy("query_id").agg(F.sum("n").alias("n")).collect()) == expected


def test_counts_near_the_bound_are_those_of_double_precision():
    rng = np.random.default_rng(5)
    x, y = rng.normal(size=(300, 64)), rng.normal(size=(2_500, 64))
    x[7], y[9] = 0, np.nan
    scores = METRICS["cosine"].block(x, y)
    for bound in (0.3, float(scores[3, 4]) - 1e-9, float(scores[3, 4]) + 1e-9):
        assert (_cosine_counts(x, y, bound) == (scores > bound).sum(1)).all()
