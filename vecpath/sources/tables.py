"""The given tables, the mixed relations built from them, and derivations of vectors."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.metrics import l2_norm, unit

TABLES = (
    "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"
).split()
# Bounds on o_totalprice that keep about so many percent of the rows.
LADDER = {1: 6000, 5: 26000, 10: 51000, 25: 126000, 50: 251000, 75: 375000, 90: 450000, 95: 475000, 99: 495000}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Catalog:
    """Mixed relations of one data directory, all lazy."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        if name in TABLES:
            return table(self.spark, self.sf_dir, name)
        raise AttributeError(name)

    def mix_orders(self) -> DataFrame:
        return self.embeddings.join(self.orders, F.col("vec_id") == F.col("o_orderkey"))

    def mix_geo(self) -> DataFrame:
        return (
            self.mix_orders()
            .join(self.customer, F.col("o_custkey") == F.col("c_custkey"))
            .join(F.broadcast(self.nation), F.col("c_nationkey") == F.col("n_nationkey"))
            .join(F.broadcast(self.region), F.col("n_regionkey") == F.col("r_regionkey"))
        )

    def mix_documents(self) -> DataFrame:
        docs = self.documents.select("doc_id", "lang", "source", "n_chars")
        return self.embeddings.join(docs, F.col("vec_id") == F.col("doc_id")).join(self.labels, "doc_id", "left")

    def mix_part(self) -> DataFrame:
        return self.embeddings.join(self.part, F.col("vec_id") == F.col("p_partkey"))

    def n_vectors(self) -> Column:
        """Number of vectors as a scalar subquery."""
        return self.embeddings.agg(F.count(F.lit(1)).alias("n")).scalar()

    def carrier_events(self) -> DataFrame:
        """Every event carries the vector numbered event_id modulo the number of vectors."""
        e = self.events.withColumn("vec_id", F.pmod("event_id", self.n_vectors()))
        return e.join(self.embeddings, "vec_id")

    def carrier_lineitem(self) -> DataFrame:
        li = self.lineitem.withColumn("vec_id", F.pmod("l_partkey", self.n_vectors()))
        return li.join(self.embeddings, "vec_id")

    def queries(self, b: int) -> DataFrame:
        return self.embeddings.where(F.col("vec_id") < b).select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))

    def request_queries(self, b: int) -> DataFrame:
        """A batch of any size: requests keyed by event id, repeating vectors."""
        e = self.events.where(F.col("event_id") < b).withColumn("vec_id", F.pmod("event_id", self.n_vectors()))
        return e.join(self.embeddings, "vec_id").select(F.col("event_id").alias("query_id"), F.col("embedding").alias("qvec"))


def ingest(rows: DataFrame, vector: str = "embedding", keep_norm: bool = True) -> DataFrame:
    """``rows`` with unit vectors in place of the vectors, normalised once when they come in.

    With ``keep_norm`` the lengths stay as ``norm``.  Cosine is then the inner
    product of the stored vectors, and no search normalises again.  A zero
    vector becomes null.
    """
    norm = l2_norm(F.col(vector))
    out = rows.withColumn("norm", norm) if keep_norm else rows
    return out.withColumn(vector, unit(F.col(vector)))


def first_components(vector: str, d: int) -> Column:
    return F.slice(vector, 1, d)


def tile(vector: str, r: int) -> Column:
    """The vector r times over: cosines stay, the work grows r times."""
    return F.flatten(F.array_repeat(F.col(vector), r))


def widen(embeddings: DataFrame, r: int) -> DataFrame:
    """(vec_id, embedding of r times the dimension): vectors of the next r ids, divided by sqrt(r)."""
    n = embeddings.agg(F.count(F.lit(1)).alias("n")).scalar()
    parts = embeddings.select(
        F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("j"), F.col("vec_id").alias("from"), "embedding"
    ).select(F.pmod(F.col("from") - F.col("j"), n).alias("vec_id"), "j", "embedding")
    joined = parts.groupBy("vec_id").agg(F.array_sort(F.collect_list(F.struct("j", "embedding"))).alias("x"))
    scale = math.sqrt(r)
    flat = F.flatten(F.transform("x", lambda x: x["embedding"]))
    return joined.select("vec_id", F.transform(flat, lambda v: v.cast("double") / scale).alias("embedding"))


def synthetic(spark: SparkSession, n: int, dim: int, seed: int = 42) -> DataFrame:
    """(id, attr in [0,1), embedding): seeded uniform rows for benchmarks, the same on any cluster."""

    def uniform(*cols: Column) -> Column:
        return F.shiftrightunsigned(F.xxhash64(*cols, F.lit(seed)), 11).cast("double") / float(1 << 53)

    return spark.range(n).select(
        "id",
        uniform(F.col("id"), F.lit(-1)).alias("attr"),
        F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda j: (uniform(F.col("id"), j) - 0.5).cast("float")).alias("embedding"),
    )


def sparsified(vector: str, least: float) -> Column:
    """struct(indices, values) of the components of absolute value ``least`` and more."""
    at = F.filter(
        F.transform(F.col(vector), lambda x, i: F.struct(i.alias("i"), x.cast("double").alias("x"))),
        lambda s: F.abs(s["x"]) >= least,
    )
    return F.struct(F.transform(at, lambda s: s["i"]).alias("indices"), F.transform(at, lambda s: s["x"]).alias("values"))
