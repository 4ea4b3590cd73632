"""Helpers shared by the training-data operators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.stored import shared_folder

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
WORD = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share (``spark.checkpoint.dir``).

    Only where the session names none and runs on one machine (tests) a
    temporary folder is made and set; on a cluster that is an error.
    """
    sc = spark.sparkContext
    held = sc._jsc.sc().getCheckpointDir()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if held.isEmpty():
        sc.setCheckpointDir(named or shared_folder(spark))
        held = sc._jsc.sc().getCheckpointDir()
    return named or str(held.get())


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared checkpoint folder and go on from there.

    What was shuffled for it is not read again, and its files go at once.
    """
    spark = df.sparkSession
    shared_dir(spark)
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        return df.select("*").checkpoint(eager=True)  # a plan made under this setting
    finally:
        spark.conf.set(CLEANUP, before) if before is not None else spark.conf.unset(CLEANUP)


def settled(value: Column) -> Column:
    """The same value, worked out once: no filter above it works it out again for each of its parts."""
    return F.explode(F.array(value))


def text_or_empty(name: str) -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z and nothing else.

    ``lower`` touches only A-Z where every character is one byte, and is many
    times faster than ``translate``, which takes the other texts.
    """
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(
        F.translate(text, UPPER, UPPER.lower())
    )


def word_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def free_name(taken: list[str], base: str) -> str:
    """A column name that no column of ``taken`` has (case-insensitive)."""
    used = {c.lower() for c in taken}
    name, k = base, 0
    while name.lower() in used:
        k += 1
        name = f"{base}_{k}"
    return name


def without_ids(docs: DataFrame, ids: DataFrame, doc_id: str = "doc_id", max_filter_bytes: int = 32 << 20) -> DataFrame:
    """Rows of ``docs`` whose id is not in ``ids`` (one column of the same name).

    Rows that a Bloom filter of ``ids`` rules out pass straight through; only
    the others are shuffled.  Rows with a null id stay.
    """
    from .bloom import blocks_for, may_hold, present_bits

    ids = cut(ids.where(F.col(doc_id).isNotNull()).distinct())
    blocks = blocks_for(ids.count(), max_filter_bytes)
    if blocks is None:
        return docs.join(ids, doc_id, "left_anti")
    maps = cut(present_bits(ids.select(F.xxhash64(doc_id).alias("h")), "h", blocks)).scalar()
    maybe = F.col(doc_id).isNotNull() & may_hold(maps, F.xxhash64(doc_id), blocks)
    return docs.where(~maybe).unionByName(docs.where(maybe).join(ids, doc_id, "left_anti").select(*docs.columns))
