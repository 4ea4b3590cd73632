"""Exhaustive scans: four ways to pair queries with rows, three kernels, several places for the predicate."""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import Metric, is_vector, literal_vector, resolve, unrolled_dot, unrolled_norm

QUERY_BYTES = 64 << 20
BLOCK_BYTES = 64 << 20
STRATEGIES = ("pairwise", "block_rows", "block_queries", "tensor")


@dataclass(frozen=True)
class QueryBlock:
    """A batch of pending queries as a dense matrix; its size is checked."""

    ids: np.ndarray
    matrix: np.ndarray

    @property
    def dim(self) -> int:
        return self.matrix.shape[1]

    def __len__(self) -> int:
        return len(self.ids)


def query_bytes(queries: DataFrame, qvec: str = "qvec") -> int:
    """Bytes of a query batch as a dense matrix with its ids."""
    n, components = queries.where(F.col(qvec).isNotNull()).agg(F.count(F.lit(1)), F.sum(F.size(qvec))).first()
    return 8 * (n + (components or 0))


def collect_queries(queries: DataFrame, query_id: str = "query_id", qvec: str = "qvec", max_bytes: int = QUERY_BYTES) -> QueryBlock:
    """Gather a query batch of at most ``max_bytes``; it raises beyond that, where the joins of blocks by blocks take over."""
    wanted = queries.select(query_id, qvec).where(F.col(qvec).isNotNull())
    if (size := query_bytes(wanted, qvec)) > max_bytes:
        raise ValueError(f"query batch of {size} bytes; use vector_range_join or vector_topk_join")
    rows = wanted.toArrow()
    ids = np.asarray(rows.column(0), np.int64)
    vectors = rows.column(1).combine_chunks()
    flat = np.asarray(vectors.flatten(), float)
    if len(ids) and len(set(vectors.value_lengths().to_pylist())) > 1:
        raise ValueError("queries of different dimensions")
    matrix = flat.reshape(len(ids), -1) if len(ids) else np.zeros((0, 0))
    order = np.argsort(ids, kind="stable")
    return QueryBlock(ids[order], np.ascontiguousarray(matrix[order]))


def densify(column: pa.Array, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions, rows x dim) of the vectors that are whole; others are no candidates."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if column.null_count == 0 and len(column):
        ends = np.asarray(column.offsets)
        values = column.flatten()
        if values.null_count == 0 and (np.diff(ends) == dim).all():
            x = np.asarray(values, float).reshape(-1, dim)
            ok = ~np.isnan(x).any(1)
            at = np.flatnonzero(ok)
            return at, x if len(at) == len(x) else x[at]
    at, rows = [], []
    for i, v in enumerate(column.to_pylist()):
        if v is not None and len(v) == dim and None not in v and not any(c != c for c in v):
            at.append(i)
            rows.append(v)
    return np.array(at, np.int64), np.array(rows, float).reshape(-1, dim)


def block_scores(x: np.ndarray, q: np.ndarray, metric: Metric, strategy: str) -> np.ndarray:
    """Scores (rows x queries); the strategy says what meets in one step."""
    if strategy == "tensor":
        return metric.block(x, q)
    out = np.empty((len(x), len(q)))
    if strategy == "block_rows":
        for j in range(len(q)):
            out[:, j] = metric.block(x, q[j : j + 1])[:, 0]
    elif strategy == "block_queries":
        for i in range(len(x)):
            out[i] = metric.block(x[i : i + 1], q)[0]
    elif strategy == "pairwise":
        for i in range(len(x)):
            for j in range(len(q)):
                out[i, j] = metric.block(x[i : i + 1], q[j : j + 1])[0, 0]
    else:
        raise ValueError(f"unknown strategy {strategy!r}; known: {STRATEGIES}")
    return out


def _pick(scores: np.ndarray, ids: np.ndarray, metric: Metric, bound: float | None, k: int | None):
    """(row, query) positions that meet the bound and are among the k best of the block."""
    good = ~np.isnan(scores) if bound is None else metric.within(scores, bound)  # NaN is within no bound
    if k is None:
        return np.nonzero(good)
    rows, cols = [], []
    sign = -1.0 if metric.larger_is_better else 1.0
    for j in range(scores.shape[1]):
        at = np.flatnonzero(good[:, j])
        if len(at) > k:
            s = sign * scores[at, j]
            limit = np.partition(s, k - 1)[k - 1]
            at = at[s <= limit]  # all ties at the limit, settled by id
            at = at[np.lexsort((ids[at], sign * scores[at, j]))[:k]]
        rows.append(at)
        cols.append(np.full(len(at), j))
    return np.concatenate(rows) if rows else np.zeros(0, int), np.concatenate(cols) if cols else np.zeros(0, int)


def scan(
    df: DataFrame, queries: QueryBlock, row_id: str = "vec_id", vector: str = "embedding", metric: str | Metric = "cosine",
    bound: float | None = None, k: int | None = None, cond: Column | None = None, strategy: str = "tensor",
    pushdown: str = "late", batch_rows: int = 2_048,
) -> DataFrame:
    """(query_id, <row_id>, score) of the pairs that qualify.

    ``cond`` is the relational predicate.  ``pushdown`` says where it is tested:
    ``late`` filters first, so only qualifying vectors are gathered; ``inline``
    tests each row in the kernel before its vector is looked at; ``minibatch``
    masks small parts of each Arrow batch, so that filter and product overlap
    without a copy of all qualifying rows; ``none`` scores all rows and filters
    the results.  A bound search has no shuffle; a top-k search keeps k per
    block and shuffles at most blocks x queries x k rows.
    """
    m = resolve(metric)
    if pushdown not in ("late", "inline", "minibatch", "none"):
        raise ValueError(f"unknown pushdown {pushdown!r}")
    theta = F.lit(True) if cond is None else F.coalesce(cond, F.lit(False))
    rows = df.where(cond) if cond is not None and pushdown == "late" else df  # bare, so that the files see it
    rows = rows.select(
        F.col(row_id).alias("_id"), F.col(vector).alias("_v"), (F.lit(True) if pushdown == "late" else theta).alias("_theta")
    )
    kind = rows.schema["_id"].dataType.simpleString()
    if not len(queries):
        return rows.where("false").select(F.lit(0).cast("long").alias("query_id"), F.col("_id").alias(row_id), F.lit(0.0).alias("score"))
    block_k = k if pushdown != "none" else None  # the best rows are only known after the filter
    step = max(1, min(batch_rows if pushdown == "minibatch" else 1 << 30, BLOCK_BYTES // (8 * len(queries))))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, step):
                part = batch.slice(lo, step)
                if pushdown in ("inline", "minibatch"):
                    part = part.filter(part.column("_theta"))
                at, x = densify(part.column("_v"), queries.dim)
                if not len(at):
                    continue
                ids, passed = part.column("_id").take(pa.array(at)), part.column("_theta").take(pa.array(at))
                s = block_scores(x, queries.matrix, m, strategy)
                numbers = np.asarray(pc.rank(ids, tiebreaker="dense"), np.int64)  # by the id, of whatever kind
                r, c = _pick(s, numbers, m, bound, block_k)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(queries.ids[c]), ids.take(pa.array(r)), pa.array(s[r, c]), passed.take(pa.array(r))],
                    ["query_id", row_id, "score", "_theta"],
                )

    out = rows.mapInArrow(work, f"query_id long, `{row_id}` {kind}, score double, _theta boolean")
    out = out.where("_theta").drop("_theta")
    return out if k is None else best(out, k, m, row_id)


def best(scored: DataFrame, k: int, metric: str | Metric = "cosine", row_id: str = "vec_id") -> DataFrame:
    """The k best rows of each query, with rank; ties to the smaller id."""
    w = Window.partitionBy("query_id").orderBy(resolve(metric).order(F.col("score")), row_id)
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


# ---- selection without Python: the per-tuple kernels


def select_bound(df: DataFrame, query, metric: str | Metric = "cosine", bound: float = 0.9, vector: str = "embedding") -> DataFrame:
    """Rows whose similarity to one query meets the bound, as a filter on an expression."""
    m = resolve(metric)
    q = literal_vector(query)
    return df.where(is_vector(F.col(vector), len(query))).withColumn("score", m.column(F.col(vector), q)).where(m.within(F.col("score"), bound))


def select_unrolled(df: DataFrame, query, bound: float, vector: str = "embedding") -> DataFrame:
    """The same for cosine with the inner product compiled as one flat sum."""
    q = np.asarray(query, float)
    norm = float(np.sqrt(q @ q))
    score = unrolled_dot(F.col(vector), q / norm) / unrolled_norm(F.col(vector), len(q))
    return df.where(is_vector(F.col(vector), len(q))).withColumn("score", score).where(F.col("score") > bound)


def select_product(
    df: DataFrame, queries: DataFrame, metric: str | Metric = "cosine", bound: float = 0.9, row_id: str = "vec_id",
    vector: str = "embedding", cond: Column | None = None,
) -> DataFrame:
    """Product of the query relation with the rows, filtered: the plain nested-loop form.

    The queries' side is broadcast, behind a check of its size; it is what the
    other forms are compared with.
    """
    m = resolve(metric)
    if (size := query_bytes(queries)) > QUERY_BYTES:
        raise ValueError(f"query batch of {size} bytes; use vector_range_join")
    rows = df if cond is None else df.where(cond)
    pairs = F.broadcast(queries.select("query_id", "qvec")).crossJoin(rows.select(F.col(row_id), F.col(vector).alias("_v")))
    return pairs.withColumn("score", m.column(F.col("_v"), F.col("qvec"))).where(m.within(F.col("score"), bound)).select("query_id", row_id, "score")


def scan_split(
    attributes: DataFrame, vectors: DataFrame, queries: QueryBlock, cond: Column, key: str = "vec_id", **how
) -> DataFrame:
    """Predicate first on a table of attributes, then a semi join to the table of vectors.

    The vector table is read once and only its qualifying rows reach the
    kernel; the shuffle, if the ids are too many to broadcast, moves ids.
    """
    ids = attributes.where(cond).select(key)
    return scan(vectors.join(ids, key, "left_semi"), queries, row_id=key, **how)


def scan_sparse(df: DataFrame, query: dict[int, float], bound: float, row_id: str = "vec_id", sparse: str = "sparse") -> DataFrame:
    """Inner products of sparse vectors above the bound; the work is that of non-zero components."""
    from ..functions.metrics import sparse_dot

    score = sparse_dot(F.col(f"{sparse}.indices"), F.col(f"{sparse}.values"), query)
    return df.select(row_id, score.alias("score")).where(F.col("score") > bound)


# ---- phases of the matrix scan


def phase_times(
    df: DataFrame, queries: QueryBlock, cond: Column, vector: str = "embedding", batch_rows: int = 10_000
) -> DataFrame:
    """(phase, seconds, n_rows, share) of filtering with copying, normalising and computing.

    Times travel as rows, not as accumulators, so a task run again is not
    counted twice.
    """
    rows = df.select(F.col(vector).alias("_v"), F.coalesce(cond, F.lit(False)).alias("_theta"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spent, n = dict.fromkeys(("filter", "normalise", "compute"), 0.0), 0
        for batch in batches:
            t0 = time.perf_counter()
            part = batch.filter(batch.column("_theta"))
            _, x = densify(part.column("_v"), queries.dim)
            x = np.ascontiguousarray(x)
            n += len(x)
            t1 = time.perf_counter()
            norm = np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]
            x = x / np.where(norm > 0, norm, 1)
            q = queries.matrix / np.sqrt(np.einsum("ij,ij->i", queries.matrix, queries.matrix))[:, None]
            t2 = time.perf_counter()
            (x @ q.T > 0.9).sum()
            t3 = time.perf_counter()
            for name, t in zip(spent, (t1 - t0, t2 - t1, t3 - t2)):
                spent[name] += t
        yield pa.RecordBatch.from_arrays(
            [pa.array(list(spent)), pa.array(list(spent.values())), pa.array([n] * len(spent))], ["phase", "seconds", "n_rows"]
        )

    timed = rows.mapInArrow(work, "phase string, seconds double, n_rows long").groupBy("phase").agg(
        F.sum("seconds").alias("seconds"), F.sum("n_rows").alias("n_rows")
    )
    whole = Window.partitionBy(F.lit(1))
    return timed.withColumn("share", 100 * F.col("seconds") / F.sum("seconds").over(whole))


