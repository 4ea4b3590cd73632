"""Registry of catalogue queries and pieces that they share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import Catalog

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register ``f(catalog) -> DataFrame`` under a name, with the SQL that gives the same rows."""

    def add(f: Callable[[Catalog], DataFrame]):
        QUERIES[name] = lambda spark, sf_dir: f(Catalog(spark, sf_dir))
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def u6(score: str | Column = "score") -> Column:
    """Integer micro-units, the same in any engine."""
    c = F.col(score) if isinstance(score, str) else score
    return F.round(c * 1_000_000).cast("long").alias("score_u6")


# SQL pieces
U6 = "CAST(round({} * 1000000) AS BIGINT)"
V = "CAST({} AS DOUBLE[])"


def sql_cos(a: str, b: str) -> str:
    return f"list_cosine_similarity({V.format(a)}, {V.format(b)})"


MIX = "embeddings JOIN orders ON vec_id = o_orderkey"


def sql_bound(queries: str, rows: str, bound: float, row_id: str = "vec_id", cond: str = "TRUE") -> str:
    """Pairs above a cosine bound: queries is SQL for (query_id, qvec), rows a FROM item."""
    return f"""
SELECT query_id, {row_id}, {U6.format('s')} AS score_u6
FROM (SELECT q.query_id, r.{row_id}, {sql_cos('r.embedding', 'q.qvec')} AS s
      FROM ({queries}) q CROSS JOIN (SELECT * FROM {rows} WHERE {cond}) r) WHERE s > {bound}"""


def sql_queries(b: int) -> str:
    return f"SELECT vec_id AS query_id, embedding AS qvec FROM embeddings WHERE vec_id < {b}"


def sql_topk(queries: str, rows: str, k: int, cond: str = "TRUE", score: str | None = None, desc: str = "DESC") -> str:
    s = score or sql_cos("r.embedding", "q.qvec")
    return f"""
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, {U6.format('s')} AS score_u6
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY s {desc}, vec_id) AS rank
      FROM (SELECT q.query_id, r.vec_id, {s} AS s
            FROM ({queries}) q CROSS JOIN (SELECT * FROM {rows} WHERE {cond}) r)) WHERE rank <= {k}"""


CARRIER_EVENTS = """(SELECT e.*, m.vec_id, m.embedding FROM events e JOIN embeddings m
  ON m.vec_id = e.event_id % (SELECT count(*) FROM embeddings))"""
