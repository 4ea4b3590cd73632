"""Exact top-k search by inner product with a bit-sliced index."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut

ROWS_PER_BLOCK = 32_768
QUERIES_PER_BLOCK = 128
EXACT = float(1 << 60)  # whole numbers below this fit a long with room for an offset
MOST = 10**38 - 1  # of a score while blocks are merged


def whole(x: np.ndarray) -> np.ndarray:
    """floor(256 * x) as integers: longs, or Python's where a component is too large for a long."""
    with np.errstate(over="ignore"):
        y = np.floor(x * 256.0)
    if np.abs(y).max(initial=0) < EXACT:
        return y.astype(np.int64)
    flat = [int(a) if np.isfinite(a) else int(b) * 256 for a, b in zip(y.ravel().tolist(), x.ravel().tolist())]
    out = np.empty(len(flat), object)
    out[:] = flat
    return out.reshape(x.shape)


def slices_of(x: np.ndarray) -> tuple[np.ndarray, int]:
    """(slices, offset): bit j of every x[row, dim] + offset, as bitmaps [dim, j, word]."""
    offset = max(-int(x.min(initial=0)), int(x.max(initial=0)) + 1, 1)
    width = max(1, (2 * offset - 1).bit_length())
    offset = 1 << (width - 1)
    rows, dims = x.shape
    words = -(-rows // 64)
    out = np.zeros((dims, width, words), np.uint64)
    up = x + offset
    for d in range(dims):
        for j in range(width):
            bits = np.packbits(((up[:, d] >> j) & 1).astype(np.uint8), bitorder="little")
            out[d, j].view(np.uint8)[: len(bits)] = bits
    return out, offset


def _full(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sum and carry bitmaps of three."""
    x = a ^ b
    return x ^ c, (a & b) | (x & c)


def _compress(columns: dict[int, list[np.ndarray]]) -> dict[int, np.ndarray]:
    """Add bitmaps: columns[p] holds those of weight 2**p; one for each p is left."""
    out, p = {}, 0
    while any(q >= p for q in columns):
        held = columns.pop(p, [])
        while len(held) > 1:
            if len(held) > 2:
                one, carry = _full(held.pop(), held.pop(), held.pop())
            else:
                a, b = held.pop(), held.pop()
                one, carry = a ^ b, a & b
            held.insert(0, one)
            columns.setdefault(p + 1, []).append(carry)
        if held:
            out[p] = held[0]
        p += 1
    return out


def scores(slices: np.ndarray, offset: int, query: np.ndarray) -> tuple[list[np.ndarray | None], int]:
    """Bit slices (least first) of the inner products with ``query``, less a constant.

    Components enter as unsigned numbers u = x + offset; where the query is
    negative the complement enters, so that only sums are needed.  For each
    bit of the query's components the slices of the dimensions that have it
    are counted by carry-save adders, all slices of a number at once; the
    counts are then added up by weight.
    """
    width = slices.shape[1]
    top = (1 << width) - 1
    size = np.abs(query)
    values = [int(q) for q in query]
    constant = -offset * sum(values) + top * sum(q for q in values if q < 0)
    # inner = sum q*(u - offset); a negative q gives q*u = |q|*(top - u) - |q|*top
    columns: dict[int, list[np.ndarray]] = {}
    for b in range(int(size.max(initial=0)).bit_length()):
        chosen = [~slices[d] if query[d] < 0 else slices[d] for d in np.flatnonzero(((size >> b) & 1).astype(bool))]
        for k, counts in _compress({0: chosen}).items():
            for j in range(width):
                columns.setdefault(b + k + j, []).append(counts[j])
    summed = _compress(columns)
    return [summed.get(p) for p in range(max(summed, default=-1) + 1)], constant


def best_rows(sliced: list[np.ndarray | None], valid: np.ndarray, k: int) -> np.ndarray:
    """Rows of the k largest numbers, ties to the first rows, from the top slice down."""
    sure, open_ = np.zeros_like(valid), valid.copy()
    for s in reversed(sliced):
        if s is None:
            continue
        more = open_ & s
        n = int(np.bitwise_count(sure | more).sum())
        if n > k:
            open_ = more
        else:
            sure = sure | more
            open_ = open_ & ~s
            if n == k:
                open_ = np.zeros_like(valid)
                break
    rows = np.flatnonzero(np.unpackbits(sure.view(np.uint8), bitorder="little"))
    missing = k - len(rows)
    if missing > 0:  # equal numbers at the boundary: the first rows
        ties = np.flatnonzero(np.unpackbits(open_.view(np.uint8), bitorder="little"))[:missing]
        rows = np.concatenate([rows, ties])
    return rows


def taking_part(df: DataFrame, vec_id: str, vector: str) -> DataFrame:
    """(vec_id, x array<double>, dim) of the rows that take part."""
    x = F.col(vector).cast("array<double>")
    bad = F.exists(x, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == F.lit(float("inf"))))
    return (
        df.where(F.col(vec_id).isNotNull() & F.col(vector).isNotNull() & ~bad)
        .select(F.col(vec_id).cast("long").alias("vec_id"), x.alias("x"))
        .withColumn("dim", F.size("x").cast("long"))
    )


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    flat = column.combine_chunks().flatten() if isinstance(column, pa.ChunkedArray) else column.flatten()
    return np.asarray(flat, float).reshape(len(column), dim)


def topk_inner(
    df: DataFrame, vec_id: str = "vec_id", vector: str = "embedding", every: int = 50, k: int = 5,
    rows_per_block: int = ROWS_PER_BLOCK,
) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best rows for each query row.

    Components become floor(256 * x); the score is their integer inner
    product.  Queries are the rows whose id is divisible by ``every``,
    candidates all rows but those with the query's id; ties go to the smaller
    id, and fewer rows than k give all.  Vectors that are null or hold null,
    NaN or infinite components take no part, and neither do null ids; any
    other component counts in full, however large.  A score beyond a long is
    given as the nearest long, and ranked by its first 38 digits at most.
    Vectors meet only vectors of their own length; empty ones score 0.  An
    empty table gives an empty result, and other columns are not looked at.
    Repeated rows are candidates each; a query id that
    occurs with several different vectors is answered for each of them
    together, keeping its k best.

    The index is cut into blocks of rows, sorted by id; the stated queries
    into blocks too.  Every pair of blocks is one small task: the slices are
    added with bitmap arithmetic, the k best rows of the block are selected
    from the most significant slice downward, and the ties at the boundary
    are settled by id.  A last window keeps the k best of all blocks.
    """
    rows = cut(taking_part(df, vec_id, vector))
    total = rows.count()
    blocks = max(1, -(-total // rows_per_block))
    groups = max(1, -(-total // (every * QUERIES_PER_BLOCK)))

    def index(key, table):
        dim = key[0].as_py()
        ids = np.asarray(table.column("vec_id"), np.int64)
        order = np.argsort(ids, kind="stable")
        s, offset = slices_of(whole(_matrix(table.column("x"), dim))[order])
        return pa.table(
            {"dim": [dim], "block": pa.array([key[1].as_py()], pa.int64()), "n": [len(ids)], "width": [s.shape[1]],
             "base": [str(offset)], "ids": [ids[order].tobytes()], "slices": [s.tobytes()]}
        )

    def packed(key, table):
        ids = np.asarray(table.column("vec_id"), np.int64)
        x = _matrix(table.column("x"), key[0].as_py())
        return pa.table(
            {"qdim": [key[0].as_py()], "part": pa.array([key[1].as_py()], pa.int64()), "qids": [ids.tobytes()], "qs": [x.tobytes()]}
        )

    dealt = rows.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)))
    built = cut(
        dealt.groupBy("dim", "block").applyInArrow(
            index, "dim long, block long, n long, width long, base string, ids binary, slices binary"
        )
    )
    asked = (
        rows.where(F.col("vec_id") % every == 0)
        .distinct()
        .withColumn("part", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(groups)))
        .groupBy("dim", "part")
        .applyInArrow(packed, "qdim long, part long, qids binary, qs binary")
        .withColumn("qblock", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    )
    pairs = asked.join(built, (F.col("qdim") == F.col("dim")) & (F.col("qblock") == F.col("block")))
    pairs = pairs.repartition(max(2, min(blocks * groups, 20_000)), "part", "block").select(
        "dim", "n", "width", "base", "ids", "slices", "qids", "qs"
    )

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                dim, n, width, base, ids, s, qids, qs = (c[i].as_py() for c in batch.columns)
                ids, qids = np.frombuffer(ids, np.int64), np.frombuffer(qids, np.int64)
                words = -(-n // 64)
                s, base = np.frombuffer(s, np.uint64).reshape(dim, width, words), int(base)
                qs = whole(np.frombuffer(qs, float).reshape(len(qids), dim))
                valid = np.zeros(words * 8, np.uint8)
                valid[: -(-n // 8)] = np.packbits(np.ones(n, np.uint8), bitorder="little")
                out = ([], [], [])
                for q, own in zip(qs, qids):
                    mask = valid.copy()
                    for r in range(*np.searchsorted(ids, [own, own + 1])):
                        mask[r >> 3] &= ~np.uint8(1 << (r & 7))
                    sliced, constant = scores(s, base, q)
                    found = best_rows(sliced, mask.view(np.uint64), k)
                    word, bit = found >> 6, (found & 63).astype(np.uint64)
                    score = [constant] * len(found)
                    for p, bits in enumerate(sliced):
                        if bits is not None:
                            score = [v + (x << p) for v, x in zip(score, ((bits[word] >> bit) & np.uint64(1)).tolist())]
                    out[0].append(np.full(len(found), own))
                    out[1].append(ids[found])
                    out[2].extend(Decimal(max(-MOST, min(MOST, v))) for v in score)
                yield pa.RecordBatch.from_arrays(
                    [*(pa.array(np.concatenate(c).astype(np.int64)) for c in out[:2]), pa.array(out[2], pa.decimal128(38, 0))],
                    ["query_id", "vec_id", "score"],
                )

    found = pairs.mapInArrow(search, "query_id long, vec_id long, score decimal(38,0)")
    best = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    least, most = F.lit(-(1 << 63)).cast("decimal(38,0)"), F.lit((1 << 63) - 1).cast("decimal(38,0)")
    score = F.least(F.greatest("score", least), most).cast("long").alias("score")
    return (
        found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", score)
    )
