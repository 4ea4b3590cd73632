"""Recall, shortfall, and counted work."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall_at_k(found: DataFrame, exact: DataFrame, row_id: str = "vec_id") -> DataFrame:
    """(query_id, n_exact, n_found, recall) for each query with an exact answer."""
    hits = found.select("query_id", row_id).distinct().withColumn("hit", F.lit(1))
    joined = exact.select("query_id", row_id).join(hits, ["query_id", row_id], "left")
    return joined.groupBy("query_id").agg(
        F.count(F.lit(1)).alias("n_exact"), F.count("hit").alias("n_found"), (F.count("hit") / F.count(F.lit(1))).alias("recall")
    )


def widened(search: Callable[[int], DataFrame], exact: DataFrame, width: int, most: int, least: float = 0.9) -> tuple[DataFrame, int]:
    """(answers, width) of ``search(width)`` at the first doubling of the width whose measured recall is at least ``least``.

    A width of ``most`` rows, all there are, is the last that is tried.  The
    answers, k for each query, are kept by the session.
    """
    while True:
        found = search(width).cache()
        exactly, hits = recall_at_k(found, exact).agg(F.sum("n_exact"), F.sum("n_found")).first()
        if width >= most or (hits or 0) >= least * (exactly or 0):
            return found, width
        found.unpersist()
        width *= 2


def shortfall(found: DataFrame, queries: DataFrame, k: int, row_id: str = "vec_id") -> DataFrame:
    """(query_id, survivors, shortfall): how many of k results are left after a filter."""
    n = found.groupBy("query_id").agg(F.count(row_id).alias("survivors"))
    return queries.select("query_id").join(n, "query_id", "left").select(
        "query_id", F.coalesce("survivors", F.lit(0)).alias("survivors"), (F.lit(k) - F.coalesce("survivors", F.lit(0))).alias("shortfall")
    )


def mean_counters(counters: DataFrame) -> DataFrame:
    """Mean cost of a query over all shards: hops, distance_evals, filter_probes and the fraction of nodes reached."""
    per = counters.groupBy("query_id").agg(
        *(F.sum(c).alias(c) for c in ("hops", "distance_evals", "filter_probes", "results")),
        (F.sum("reached") / F.sum("n")).alias("reached_fraction"),
    )
    return per.agg(*(F.avg(c).alias(c) for c in ("hops", "distance_evals", "filter_probes", "results", "reached_fraction")))
