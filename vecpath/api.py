"""One call for a mixed search: the planner picks the path, the operators run it."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .operators.graph import GraphIndex, graph_search, shard_of
from .operators.joins import vector_range_join, vector_topk_join
from .operators.scan import QUERY_BYTES, QueryBlock, best, collect_queries, query_bytes, scan
from .plans.planner import CostModel, Decision, IndexInfo, Workload, choose_path, choose_per_shard, counted


def plan(
    df: DataFrame, queries: QueryBlock, k: int | None, cond: Column | None, metric: str, index: GraphIndex | None,
    min_recall: float, hint: str | None, model: CostModel | None = None,
) -> Decision:
    n, share = counted(df, cond)
    w = Workload(n, max(1, queries.dim if len(queries) else 1), max(1, len(queries)), share, k=k, metric=metric, min_recall=min_recall)
    return choose_path(w, IndexInfo(index.metric if index else None), model, hint)


def search(
    df: DataFrame, queries: QueryBlock | DataFrame, k: int | None = 10, bound: float | None = None, cond: Column | None = None,
    metric: str = "cosine", index: GraphIndex | None = None, row_id: str = "vec_id", vector: str = "embedding",
    ef: int = 64, min_recall: float = 0.9, hint: str | None = None, model: CostModel | None = None,
) -> DataFrame:
    """(query_id, <row_id>, score[, rank]) by the path that is cheapest for this predicate, batch and dimension.

    ``queries`` is a gathered batch, or a table (query_id, qvec) of any size:
    one that is too large to gather is joined in blocks.  ``hint`` forces
    "scan", "matrix" or "graph".
    """
    if isinstance(queries, DataFrame):
        if query_bytes(queries) > QUERY_BYTES:
            asked = queries.select("query_id", F.col("qvec").alias(vector))
            meet = vector_topk_join if bound is None else vector_range_join
            found = meet(asked, df, k if bound is None else bound, metric, "query_id", row_id, vector, None, cond)
            found = found.withColumnsRenamed({"l_id": "query_id", "r_id": row_id})
            return found if bound is None or k is None else best(found, k, metric, row_id)
        queries = collect_queries(queries)
    chosen = plan(df, queries, k if bound is None else None, cond, metric, index, min_recall, hint, model)
    if chosen.path == "graph":
        qualifying = None if cond is None else df.where(cond).select(row_id)
        return graph_search(index, queries, k, ef, qualifying, "pre", row_id)
    how = {"strategy": "block_rows", "pushdown": "late"} if chosen.path == "scan" else {"strategy": "tensor", "pushdown": "late"}
    return scan(df, queries, row_id, vector, metric, bound, k, cond, **how)


def search_per_shard(
    df: DataFrame, queries: QueryBlock, k: int, cond: Column, index: GraphIndex, row_id: str = "vec_id",
    vector: str = "embedding", ef: int = 64, model: CostModel | None = None,
) -> DataFrame:
    """Each shard by its own best path: few qualifying rows are scanned, many are probed; the best k are merged."""
    sharded = df.withColumn("_shard", shard_of(row_id, index.shards))
    counts = sharded.groupBy(F.col("_shard").alias("shard")).agg(
        F.count(F.lit(1)).alias("n"), F.count_if(F.coalesce(cond, F.lit(False))).alias("qualifying")
    )
    w = Workload(1, queries.dim, max(1, len(queries)), k=k, metric=index.metric)
    paths = choose_per_shard(counts, w, IndexInfo(index.metric), model)
    probed = [s for s, p in paths.items() if p == "graph"]
    found = scan(sharded.where(~F.col("_shard").isin(probed)), queries, row_id, vector, index.metric, None, k, cond)
    if probed:
        part = replace(index, packed=index.packed.where(F.col("shard").isin(probed)))
        more = graph_search(part, queries, k, ef, sharded.where(F.col("_shard").isin(probed)).where(cond).select(row_id), "pre", row_id)
        found = found.unionByName(more)
    return best(found.drop("rank"), k, index.metric, row_id)
