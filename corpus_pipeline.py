"""Training-data pipeline over ``documents``.

Low quality goes, then exact copies, then near copies; sources are mixed to
their weights, and what is left is encoded.  Every stage takes
(spark, docs, sf_dir) and works on all that the stage before it kept.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecpath.deploy import ship_package
from vecpath.llm import bpe, quality
from vecpath.llm.common import without_ids
from vecpath.llm.exact_dedup import exact_dedup
from vecpath.llm.jaccard import jaccard_join
from vecpath.llm.mixing import mix, repeat
from vecpath.llm.queries import quality_model, tokenizer_path
from vecpath.llm.warc import new_folder


def _renamed(docs: DataFrame) -> tuple[DataFrame, Callable[[str], str], Callable[[DataFrame], DataFrame]]:
    """``docs`` with names that no operator uses, the new name of a column, and the way back to the columns of ``docs``."""
    new = [f"doc_column_{i}" for i in range(len(docs.columns))]
    names = {c.lower(): n for c, n in zip(docs.columns, new)}
    back = lambda df: df.select(*(F.col(n).alias(c) for n, c in zip(new, docs.columns)))
    return docs.toDF(*new), lambda c: names[c.lower()], back


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject.

    Null counts as the empty text, which is scored like any other.  Repeated
    rows go or stay together.  Other columns, of any name, stay as they are; an
    empty table gives an empty result.
    """
    ship_package(spark)
    rows, name, back = _renamed(docs)
    model = quality_model(spark, docs.select("doc_id", "text"), sf_dir)
    return back(quality.score(rows, model, text=name("text")).where("predicted = 1"))


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the largest doc_id.

    Null counts as the empty text.  Of several rows with the id that stays
    exactly one stays; a null id stays only where no equal text has another.
    Other columns, of any name, stay as they are; an empty table gives an
    empty result.
    """
    rows, name, back = _renamed(docs)
    return back(exact_dedup(rows, name("text"), name("doc_id")).where("kept"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest doc_id.

    Rows that share an id stay or go together.  Rows with a null id and rows
    without words stay.  Other columns, of any name, stay as they are; an
    empty table gives an empty result.
    """
    ship_package(spark)
    groups = jaccard_join(docs.select("doc_id", "text"))
    gone = groups.groupBy("doc_id").agg(F.max((F.col("component_id") == F.col("doc_id")).cast("int")).alias("first"))
    return without_ids(docs, gone.where("first = 0").select("doc_id"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it.

    Null is a source of its own; a document without words counts nothing and
    is taken by the rate of its source.  Repeated rows are rows of their own.
    Other columns, of any name, stay as they are; an empty table gives an
    empty result.
    """
    rows, name, back = _renamed(docs)
    return back(repeat(mix(rows, name("text"), name("doc_id"), name("source"))))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document that is left, as counts and digests.

    Null counts as the empty text, which has no ids; repeated rows are encoded
    each; columns other than these three are left out.
    """
    ship_package(spark)
    coded = bpe.encode_decode(docs.select("doc_id", "lang", "source", "text"), tokenizer_path())
    return coded.select("doc_id", "lang", "source", "n_tokens", "ids_sha256", "decoded_sha256")


STAGES = [
    ("quality_classifier", keep_quality),
    ("exact_dedup", drop_exact_copies),
    ("near_dedup", drop_near_copies),
    ("mix_sources", mix_sources),
    ("bpe_encode", encode),
]

# The classifier, the random offsets and the tokenizer cannot be expressed in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each one's result is written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = new_folder(spark, "pipeline")
    for number, (name, stage) in enumerate(STAGES):
        path = f"{folder}/{number}-{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
