"""Request streams, run over what is there and compared with the same batches in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..streaming.requests import answer_batches, answer_cached, batches, first_requests, request_stream, run_once
from .registry import query, sql_bound, sql_topk


@query(
    "stream_tumbling_batches",
    "SELECT time_bucket(INTERVAL '1 day', ts) AS window_start, count(*) AS n_requests FROM events GROUP BY 1",
)
def _(c):
    found = run_once(c.spark, batches(request_stream(c.spark, c.sf_dir), "tumbling", "1 day"), "complete")
    return found.select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "n_requests")


@query(
    "stream_sliding_batches",
    """SELECT w AS window_start, count(*) AS n_requests
FROM (SELECT unnest([time_bucket(INTERVAL '6 hours', ts) - k * INTERVAL '6 hours' for k in [0, 1]]) AS w FROM events) GROUP BY 1""",
)
def _(c):
    found = run_once(c.spark, batches(request_stream(c.spark, c.sf_dir), "sliding", "12 hours", "6 hours"), "complete")
    return found.select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "n_requests")


@query(
    "stream_session_requests",
    """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL '30 minutes' THEN 0 ELSE 1 END AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(first) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g)
SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, session""",
)
def _(c):
    found = run_once(c.spark, batches(request_stream(c.spark, c.sf_dir), "session", "30 minutes", by=["user_id"]), "complete")
    return found.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), F.col("n_requests").alias("n"))


@query("stream_dedup_requests")
def _(c):
    """Requests left after repeats within the watermark go; how many depends on where the watermark stands."""
    kept = first_requests(request_stream(c.spark, c.sf_dir), ["user_id", "event_type"])
    return run_once(c.spark, kept.select("event_id", "user_id", "event_type")).groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))


PENDING = """SELECT event_id AS query_id, embedding AS qvec FROM events JOIN embeddings
  ON vec_id = event_id % (SELECT count(*) FROM embeddings)"""
SQL_MATCHES = f"SELECT query_id, count(*) AS n_matches FROM ({sql_bound(PENDING, 'embeddings', 0.3)}) GROUP BY query_id"


def queries_of(c):
    """Batch of requests -> their queries: every request carries the vector numbered by its id."""
    vectors = c.embeddings
    n = vectors.count()

    def ask(batch):
        asked = batch.select("event_id", F.pmod("event_id", F.lit(n)).alias("vec_id"))
        return asked.join(vectors, "vec_id").select(F.col("event_id").alias("query_id"), F.col("embedding").alias("qvec"))

    return ask


def match_counts(c):
    """(query_id, n): how many matches every answered request has; each micro-batch leaves its counts."""
    found = answer_batches(c.spark, request_stream(c.spark, c.sf_dir), c.embeddings, queries_of(c), counts=True, bound=0.3)
    return found.groupBy("query_id").agg(F.sum("n").alias("n"))


@query("stream_answers", SQL_MATCHES)
@query("stream_answers_all", SQL_MATCHES)
def _(c):
    """All pending requests answered batch by batch; the rows do not depend on the batches."""
    return match_counts(c).withColumnRenamed("n", "n_matches")


@query(
    "stream_hourly_matches",
    f"""SELECT date_trunc('hour', ts) AS window_start, count(*) AS n_requests, CAST(coalesce(sum(n_matches), 0) AS BIGINT) AS n_matches
FROM events LEFT JOIN ({SQL_MATCHES}) ON event_id = query_id GROUP BY 1""",
)
def _(c):
    """Requests of each hour and how many matches they have."""
    per = match_counts(c)
    asked = c.events.select("event_id", "ts")
    return (
        asked.join(per, asked.event_id == per.query_id, "left")
        .groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("window_start"))
        .agg(F.count(F.lit(1)).alias("n_requests"), F.coalesce(F.sum("n"), F.lit(0)).alias("n_matches"))
    )


@query(
    "stream_cached_answers",
    f"""SELECT event_id AS query_id, rank, t.vec_id
FROM events JOIN ({sql_topk('SELECT vec_id AS query_id, embedding AS qvec FROM embeddings', 'embeddings', 5)}) t ON t.query_id = event_id % (SELECT count(*) FROM embeddings)""",
)
def _(c):
    """Requests that repeat a question get its answer from the cache: every vector is searched for once."""
    n = c.embeddings.count()
    requests = request_stream(c.spark, c.sf_dir).select("event_id", F.pmod("event_id", F.lit(n)).alias("vec_id"))
    ask = lambda keys: keys.join(c.embeddings, "vec_id").select("vec_id", F.col("embedding").alias("qvec"))
    found = answer_cached(c.spark, requests, c.embeddings, "vec_id", ask, 5)
    return found.select(F.col("event_id").alias("query_id"), "rank", F.col("answer_id").alias("vec_id"))
