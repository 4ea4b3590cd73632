"""Vector joins: blocks of one side meet blocks of the other in matrix products."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import METRICS, Metric, _unit_rows, resolve
from .graph import GraphIndex, graph_search, graph_search_blocks, unpacked
from .scan import QUERY_BYTES, _pick, best, collect_queries, densify, query_bytes

BLOCK_ROWS = 2_000
TILE_BYTES = 2 << 20  # vectors of a side that move together
CELL_TILES = 16  # tiles of a side in a cell, at most
PRODUCT = 1 << 20  # scores of a product of few rows with many


def _packed(df: DataFrame, row_id: str, vector: str, cond: Column | None, tile_bytes: int, side: str) -> tuple[DataFrame, int]:
    """(side, dim, ids, x), one row for each tile of about ``tile_bytes`` of whole vectors of one length; and how many tiles."""
    rows = df if cond is None else df.where(cond)
    narrow = rows.schema[vector].dataType.simpleString() == "array<float>"
    rows = rows.where(F.col(row_id).isNotNull() & F.col(vector).isNotNull()).select(
        F.col(row_id).cast("long").alias("id"), F.col(vector).cast("array<float>" if narrow else "array<double>").alias("v"), F.size(vector).cast("long").alias("dim")
    )
    components = rows.agg(F.sum("dim")).first()[0] or 0
    tiles = max(1, -(-components * (4 if narrow else 8) // tile_bytes))
    rows = rows.withColumn(side, F.pmod(F.xxhash64("id"), F.lit(tiles)))

    def pack(key, table):
        at, x = densify(table.column("v"), key[1].as_py())
        ids = np.asarray(table.column("id"), np.int64)[at]
        return pa.table(
            {side: pa.array([key[0].as_py()], pa.int64()), "dim": pa.array([key[1].as_py()], pa.int64()),
             f"{side}_ids": pa.array([ids.tobytes()], pa.binary()), f"{side}_x": pa.array([x.astype(np.float32 if narrow else float).tobytes()], pa.binary())}
        )

    return rows.groupBy(side, "dim").applyInArrow(pack, f"{side} long, dim long, {side}_ids binary, {side}_x binary"), tiles


def _each(name: str, least, most) -> Column:
    """``name``: the numbers from ``least`` to ``most``, a row each."""
    whole = lambda x: x if isinstance(x, Column) else F.lit(x).cast("long")
    return F.explode(F.sequence(whole(least), whole(most))).alias(name)


def _cosine_counts(x: np.ndarray, y: np.ndarray, bound: float) -> np.ndarray:
    """How many rows of y have a cosine above the bound with each row of x.

    Products are in single precision; what is nearer to the bound than their
    error can be is worked out again in double.
    """
    x, y = _unit_rows(x.astype(float)), _unit_rows(y.astype(float))
    slack = (x.shape[1] + 8) * 2.0**-23
    low, high = np.float32(bound - slack), np.float32(bound + slack)
    few, many = x.astype(np.float32), y.astype(np.float32)
    n = np.zeros(len(x), np.int64)
    for a in range(0, len(x), 256):
        for b in range(0, len(y), BLOCK_ROWS):
            s = few[a : a + 256] @ many[b : b + BLOCK_ROWS].T
            sure, may = s > high, s > low
            for i, (p, q) in enumerate(zip(sure, may)):
                count = np.count_nonzero(p)
                if np.count_nonzero(q) != count:
                    count += np.count_nonzero(y[b + np.flatnonzero(q & ~p)] @ x[a + i] > bound)
                n[a + i] += count
    return n


def _pairs(l, r, l_id, r_id, vector, metric: Metric, bound, k, l_cond, r_cond, block_rows, upper, tile_bytes=TILE_BYTES, counts=False) -> DataFrame:
    """(query_id, r_id, score): each pair of tiles of one vector length is a row.

    With ``counts`` it is (query_id, n): how many rows of a tile each row of
    the other has within the bound; a row comes once for each tile it meets
    with any.

    Tiles are dealt into groups, and pairs of groups, the cells, to the tasks:
    a tile moves once for each group of the other side, of which there are a
    few more than the tasks that run at once need; within a pair of tiles,
    ``block_rows`` rows at a time meet the others.  The sizes of packed rows
    are unknown to the optimizer, so the sides are merged and never broadcast.
    With ``upper`` both sides are the same rows: a pair of tiles meets once,
    and a pair of rows comes with the smaller id first.
    """
    left, n_left = _packed(l, l_id, vector, l_cond, tile_bytes, "i")
    right, n_right = _packed(r, r_id, vector, r_cond, tile_bytes, "j")
    ways = int(np.ceil(np.sqrt(4 * l.sparkSession.sparkContext.defaultParallelism)))
    g_left, g_right = (min(n, max(ways, -(-n // CELL_TILES))) for n in (n_left, n_right))
    left, right = left.withColumn("gi", F.col("i") % g_left), right.withColumn("gj", F.col("j") % g_right)
    left = left.select("*", _each("gj", F.col("gi") if upper else 0, g_right - 1))
    right = right.select("*", _each("gi", 0, F.col("gj") if upper else g_left - 1))
    pairs = left.hint("merge").join(right.hint("merge"), ["gi", "gj", "dim"])
    if upper:  # in a group's cell with itself; between two groups every pair is there once
        pairs = pairs.where("gi <> gj or i <= j")
    pairs = pairs.drop("gi", "gj")
    wide = max(block_rows, PRODUCT // block_rows)

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                got = {c: batch.column(c)[row].as_py() for c in batch.schema.names}
                ids_a, ids_b = (np.frombuffer(got[f"{c}_ids"], np.int64) for c in "ij")
                x, y = (unpacked(got[f"{c}_x"], len(n), got["dim"]) for c, n in (("i", ids_a), ("j", ids_b)))
                if counts:
                    n = np.zeros(len(ids_a), np.int64)
                    if metric is METRICS["cosine"]:
                        n += _cosine_counts(x, y, bound)
                    else:
                        for a in range(0, len(ids_a), block_rows):
                            for b in range(0, len(ids_b), wide):
                                n[a : a + block_rows] += metric.within(metric.block(y[b : b + wide], x[a : a + block_rows]), bound).sum(0)
                    some = np.flatnonzero(n)
                    yield pa.RecordBatch.from_arrays([pa.array(ids_a[some]), pa.array(n[some])], ["query_id", "n"])
                    continue
                for a in range(0, len(ids_a), block_rows):
                    for b in range(0, len(ids_b), wide):
                        yield product(ids_a[a : a + block_rows], ids_b[b : b + wide], x[a : a + block_rows], y[b : b + wide], upper and got["i"] == got["j"])

    def product(ids_a, ids_b, x, y, same) -> pa.RecordBatch:
        s = metric.block(y, x)
        if same:
            s = np.where(ids_b[:, None] > ids_a[None, :], s, np.nan)
        elif upper:
            s = np.where(ids_b[:, None] != ids_a[None, :], s, np.nan)
        at_b, at_a = _pick(s, ids_b, metric, bound, k)
        one, two = ids_a[at_a], ids_b[at_b]
        if upper:
            one, two = np.minimum(one, two), np.maximum(one, two)
        return pa.RecordBatch.from_arrays([pa.array(one), pa.array(two), pa.array(s[at_b, at_a])], ["query_id", "r_id", "score"])

    return pairs.mapInArrow(meet, "query_id long, n long" if counts else "query_id long, r_id long, score double")


def vector_range_join(
    l: DataFrame, r: DataFrame, bound: float, metric: str | Metric = "cosine", l_id: str = "vec_id", r_id: str = "vec_id",
    vector: str = "embedding", l_cond: Column | None = None, r_cond: Column | None = None, block_rows: int = BLOCK_ROWS,
) -> DataFrame:
    """(l_id, r_id, score) of all pairs within the bound.

    Both sides are dealt into tiles of about ``TILE_BYTES`` by a hash of the id
    and packed to one row each; every pair of tiles meets in one task, in
    matrix products of ``block_rows`` rows at a time.  Vectors meet vectors of their own length, whatever the lengths
    of other rows.  Neither side is broadcast or collected.  Self pairs stay
    if both sides share ids.  Null ids and vectors that are null or hold null
    or NaN take no part.
    """
    out = _pairs(l, r, l_id, r_id, vector, resolve(metric), bound, None, l_cond, r_cond, block_rows, False)
    return out.select(F.col("query_id").alias("l_id"), "r_id", "score")


def vector_range_counts(
    l: DataFrame, r: DataFrame, bound: float, metric: str | Metric = "cosine", l_id: str = "vec_id", r_id: str = "vec_id",
    vector: str = "embedding", l_cond: Column | None = None, r_cond: Column | None = None, block_rows: int = BLOCK_ROWS,
) -> DataFrame:
    """(l_id, n): how many pairs ``vector_range_join`` has for each row of l that has any; they are counted where tiles meet and never made."""
    out = _pairs(l, r, l_id, r_id, vector, resolve(metric), bound, None, l_cond, r_cond, block_rows, False, counts=True)
    return out.groupBy(F.col("query_id").alias("l_id")).agg(F.sum("n").alias("n"))


def vector_topk_join(
    l: DataFrame, r: DataFrame, k: int, metric: str | Metric = "cosine", l_id: str = "vec_id", r_id: str = "vec_id",
    vector: str = "embedding", l_cond: Column | None = None, r_cond: Column | None = None, block_rows: int = BLOCK_ROWS,
) -> DataFrame:
    """(l_id, rank, r_id, score): the k best rows of r for every row of l."""
    out = _pairs(l, r, l_id, r_id, vector, resolve(metric), None, k, l_cond, r_cond, block_rows, False)
    return best(out, k, metric, "r_id").select(F.col("query_id").alias("l_id"), "rank", "r_id", "score")


def vector_probe_join(
    l: DataFrame, index: GraphIndex, k: int, ef: int = 64, l_id: str = "vec_id", vector: str = "embedding",
    qualifying: DataFrame | None = None, block_rows: int = BLOCK_ROWS, max_bytes: int = QUERY_BYTES,
) -> DataFrame:
    """The same by probing a graph.

    A left side of up to ``max_bytes`` is one query batch; beyond it, packed
    tiles of the left side, of about ``block_rows`` rows, meet the shards, and
    nothing is gathered.
    """
    asked = l.select(F.col(l_id).alias("query_id"), F.col(vector).alias("qvec")).where("query_id is not null")
    if query_bytes(asked, "qvec") <= max_bytes:
        found = graph_search(index, collect_queries(asked, max_bytes=max_bytes), k, ef, qualifying)
    else:
        tile = max(1, block_rows * query_bytes(asked, "qvec") // max(1, asked.count()))
        blocks = _packed(l, l_id, vector, None, tile, "i")[0].select("*", _each("shard", 0, index.shards - 1))
        found = graph_search_blocks(index, blocks, k, ef, qualifying)
    return found.select(F.col("query_id").alias("l_id"), "rank", F.col("vec_id").alias("r_id"), "score")


def self_pairs(df: DataFrame, bound: float, metric: str | Metric = "cosine", row_id: str = "vec_id", vector: str = "embedding", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(l_id, r_id, score) with l_id < r_id: every pair once, no self pairs."""
    out = _pairs(df, df, row_id, row_id, vector, resolve(metric), bound, None, None, None, block_rows, True)
    return out.select(F.col("query_id").alias("l_id"), "r_id", "score")


def nested_loop_join(l: DataFrame, r: DataFrame, bound: float, metric: str | Metric = "cosine", row_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Baseline: product of both sides and a filter.  For small inputs only."""
    m = resolve(metric)
    a = l.select(F.col(row_id).alias("l_id"), F.col(vector).alias("_a"))
    b = r.select(F.col(row_id).alias("r_id"), F.col(vector).alias("_b"))
    return a.crossJoin(b).withColumn("score", m.column(F.col("_a"), F.col("_b"))).where(m.within(F.col("score"), bound)).select("l_id", "r_id", "score")
