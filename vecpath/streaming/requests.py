"""Pending requests as a stream: tumbling, sliding and session batches, repeated requests, answers per micro-batch."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.joins import vector_range_counts, vector_range_join, vector_topk_join
from ..operators.scan import QUERY_BYTES, QueryBlock, collect_queries, scan
from ..plans.planner import choose_kernel
from ..sources.stored import shared_folder


BATCH_BYTES = 16 << 20  # of a micro-batch that is gathered: a stream's driver holds it beside the stream's own state


def strategy_for(batch: int, dim: int) -> str:
    """How a scan of a batch pairs queries and rows, by the planner's choice of the kernel."""
    return "tensor" if choose_kernel(max(1, batch), max(1, dim)) == "matrix" else "block_rows"


def request_stream(spark: SparkSession, sf_dir: str, watermark: str = "1 hour") -> DataFrame:
    """``events`` as a stream of requests; ts becomes a timestamp so that it can carry a watermark."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    # a stream reads folders; the file itself is named by a pattern
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parque[t]")
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def windows(kind: str, length: str, slide: str | None = None):
    if kind == "tumbling":
        return F.window("ts", length)
    if kind == "sliding":
        return F.window("ts", length, slide)
    if kind == "session":
        return F.session_window("ts", length)
    raise ValueError(f"unknown kind of batch {kind!r}")


def batches(requests: DataFrame, kind: str, length: str, slide: str | None = None, by: list[str] | None = None) -> DataFrame:
    """(window, ..., n_requests): size of each batch of requests; drives the choice of the kernel."""
    return requests.groupBy(windows(kind, length, slide), *(by or [])).agg(F.count(F.lit(1)).alias("n_requests"))


def first_requests(requests: DataFrame, by: list[str], within: str | None = None) -> DataFrame:
    """Requests that do not repeat an earlier one within the watermark."""
    return requests.dropDuplicatesWithinWatermark(by)


def run_once(spark: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    """Process what is there (``availableNow``) into Parquet in the shared folder and return it as a table."""
    place = f"{shared_folder(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    out, checkpoint = f"{place}/out", f"{place}/checkpoint"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint)
    else:  # a complete result replaces the table at every trigger
        query = stream.writeStream.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).option("checkpointLocation", checkpoint)
    running = query.outputMode(mode).trigger(availableNow=True).start()
    running.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def answer_batches(
    spark: SparkSession, requests: DataFrame, vectors: DataFrame, queries_of: Callable[[DataFrame], DataFrame],
    strategy_of: Callable[[int, int], str] = strategy_for,
    max_bytes: int = BATCH_BYTES, each: Callable[[DataFrame], DataFrame] = lambda found: found, counts: bool = False, **how,
) -> DataFrame:
    """Answer each micro-batch as one query block, with the kernel that the planner picks for its size.

    A micro-batch of more than ``max_bytes`` is not gathered but joined with the
    vectors in blocks (``how`` has bound or k, and metric).  Results do not depend on how requests fall into micro-batches: every
    request is answered against all vectors.  ``each`` is what is kept of the
    answers of a micro-batch, so that counts need not be written as pairs.
    With ``counts`` (and a bound) it gets (query_id, n), the number of answers
    of every request that has any; of a large micro-batch the pairs are
    counted in the kernel and leave no worker.
    """
    place = f"{shared_folder(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    out = f"{place}/out"

    def answer(batch: DataFrame, number: int) -> None:
        asked = queries_of(batch).where("qvec is not null").cache()
        n, dim = asked.agg(F.count(F.lit(1)), F.max(F.size("qvec"))).first()
        if n and counts and n * dim * 8 > max_bytes:
            asked_of = asked.select("query_id", F.col("qvec").alias("embedding"))
            found = vector_range_counts(asked_of, vectors, how["bound"], how.get("metric", "cosine"), "query_id").withColumnRenamed("l_id", "query_id")
        elif n and n * dim * 8 > max_bytes:
            asked_of = asked.select("query_id", F.col("qvec").alias("embedding"))
            meet, bounds = (vector_topk_join, how["k"]) if how.get("k") else (vector_range_join, how["bound"])
            found = meet(asked_of, vectors, bounds, how.get("metric", "cosine"), "query_id").withColumnsRenamed({"l_id": "query_id", "r_id": "vec_id"})
        elif n:
            block: QueryBlock = collect_queries(asked, max_bytes=max_bytes)
            found = scan(vectors, block, strategy=strategy_of(n, dim), **how)
            found = found.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")) if counts else found
        if n:
            each(found).write.mode("overwrite").parquet(f"{out}/batch={number}")
        asked.unpersist()

    running = requests.writeStream.foreachBatch(answer).option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).start()
    running.awaitTermination()
    return spark.read.parquet(out)


def answer_cached(
    spark: SparkSession, requests: DataFrame, vectors: DataFrame, key: str, queries_of: Callable[[DataFrame], DataFrame], k: int,
    metric: str = "cosine", row_id: str = "vec_id", max_bytes: int = QUERY_BYTES,
) -> DataFrame:
    """Every request with the k best rows for its key: (<columns of requests>, rank, answer_id, score).

    The answers are the stream's state, a table in the shared folder that
    grows by the keys of each micro-batch that no earlier one had; those are
    searched for together, the others are looked up.  ``queries_of`` gives
    (key, qvec) for a table of keys.
    """
    place = f"{shared_folder(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    out, cache = f"{place}/out", f"{place}/answers"
    kind = requests.schema[key].dataType.simpleString()
    answers = f"`{key}` {kind}, rank int, answer_id long, score double"

    def held(before: int) -> DataFrame:
        parts = [f"{cache}/batch={i}" for i in range(before)]
        return spark.read.schema(answers).parquet(*parts) if parts else spark.createDataFrame([], answers)

    def answer(batch: DataFrame, number: int) -> None:
        keys = batch.select(key).where(F.col(key).isNotNull()).distinct()
        asked = queries_of(keys.join(held(number).select(key).distinct(), key, "left_anti")).select(F.col(key).cast("long").alias("query_id"), "qvec")
        found = vector_topk_join(asked.withColumnRenamed("qvec", "embedding"), vectors, k, metric, "query_id", row_id)
        found = found.select(F.col("l_id").cast(kind).alias(key), "rank", F.col("r_id").alias("answer_id"), "score")
        found.write.mode("overwrite").parquet(f"{cache}/batch={number}")
        batch.join(held(number + 1), key).write.mode("overwrite").parquet(f"{out}/batch={number}")

    running = requests.writeStream.foreachBatch(answer).option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).start()
    running.awaitTermination()
    fields = [f for f in requests.schema.fields if f.name != key]
    rest = "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in fields)
    return spark.read.schema(answers + rest).option("recursiveFileLookup", "true").parquet(out)


def late_rows(running) -> int:
    """Rows that a finished or running query dropped because they came after the watermark."""
    return sum(op.numRowsDroppedByWatermark for p in running.recentProgress for op in p.stateOperators)
