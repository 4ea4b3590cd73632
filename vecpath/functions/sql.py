"""SQL surface: vector functions as SQL functions and a top-k table function."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructType

from ..operators.scan import densify

# One SQL expression over arrays a and b for each name; evaluated in the JVM.
_DOT = "aggregate(zip_with(CAST({a} AS ARRAY<DOUBLE>), CAST({b} AS ARRAY<DOUBLE>), (x, y) -> x * y), 0D, (s, x) -> s + x)"
_FUNCTIONS = {
    "vec_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", _DOT.format(a="a", b="b")),
    "vec_norm": ("a ARRAY<DOUBLE>", "DOUBLE", f"sqrt({_DOT.format(a='a', b='a')})"),
    "vec_cosine": (
        "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>",
        "DOUBLE",
        f"{_DOT.format(a='a', b='b')} / (sqrt({_DOT.format(a='a', b='a')}) * sqrt({_DOT.format(a='b', b='b')}))",
    ),
    "vec_l2": (
        "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>",
        "DOUBLE",
        "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
    ),
    "vec_unit": (
        "a ARRAY<DOUBLE>",
        "ARRAY<DOUBLE>",
        f"transform(a, x -> x / sqrt({_DOT.format(a='a', b='a')}))",
    ),
}


@F.arrow_udtf(returnType=StructType().add("query_id", LongType()).add("vec_id", LongType()).add("score", DoubleType()))
class VectorTopK:
    """``SELECT * FROM vec_topk(TABLE(v) PARTITION BY p, q, k)``: k best rows by cosine for one query.

    The table has columns vec_id and embedding.  Rows come in Arrow batches,
    each scored by one product; every partition keeps its own k best, so a
    last ORDER BY ... LIMIT gives the whole table's.  Vectors that are null,
    not whole, of another length or zero take no part.
    """

    def __init__(self):
        self.score, self.ids, self.k = np.zeros(0), np.zeros(0, np.int64), 0

    def eval(self, rows: pa.RecordBatch, query: pa.Array, k: pa.Array) -> Iterator[pa.Table]:
        if rows.num_rows:
            q, self.k = np.array(query[0].as_py(), float), k[0].as_py()
            at, x = densify(rows.column("embedding"), len(q))
            norm = np.sqrt(np.einsum("ij,ij->i", x, x))
            ok = norm > 0
            s = x[ok] @ q / norm[ok] / np.sqrt(q @ q)
            self.score = np.concatenate([self.score, s])
            self.ids = np.concatenate([self.ids, np.asarray(rows.column("vec_id"), np.int64)[at[ok]]])
            best = np.lexsort((self.ids, -self.score))[: self.k]
            self.score, self.ids = self.score[best], self.ids[best]
        return iter(())

    def terminate(self) -> Iterator[pa.Table]:
        yield pa.table({"query_id": pa.array(np.zeros(len(self.ids), np.int64)), "vec_id": pa.array(self.ids), "score": pa.array(self.score)})


def cosine_to(query) -> Callable[[Column], Column]:
    """Vectorised function of a column: cosine with a fixed query, null where there is none."""
    q = np.asarray(query, float)
    q = q / np.sqrt(q @ q)

    @F.arrow_udf(DoubleType())
    def score(v: pa.Array) -> pa.Array:
        at, x = densify(v, len(q))
        norm = np.sqrt(np.einsum("ij,ij->i", x, x))
        out, ok = np.full(len(v), np.nan), norm > 0
        out[at[ok]] = x[ok] @ q / norm[ok]
        return pa.array(out, mask=np.isnan(out))

    return score


@F.arrow_udf(ArrayType(DoubleType()))
def vec_mean(v: pa.Array) -> pa.Scalar:
    """Aggregate: mean of a group's vectors; those of another length than the group's first are left out.

    A group meets in one task.  For large groups ``aggregates.centroids`` adds up before the shuffle.
    """
    first = next((len(x) for x in v.to_pylist() if x is not None), 0)
    _, x = densify(v, first)
    return pa.scalar(x.mean(0).tolist() if len(x) else None, pa.list_(pa.float64()))


def register(spark: SparkSession) -> None:
    """Install the vec_* functions in the session."""
    for name, (args, returns, body) in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {returns} RETURN {body}")
    spark.udtf.register("vec_topk", VectorTopK)
    spark.udf.register("vec_mean", vec_mean)
