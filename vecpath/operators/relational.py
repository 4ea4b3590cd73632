"""Relational scan and index probe, for comparison with the vector paths."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PAGE = "_page"


def cents(measure: str) -> Column:
    return F.sum(F.round(F.col(measure) * 100).cast("long")).alias("sum_cents")


def relational_scan_sum(df: DataFrame, key: str, hi: float, measure: str, one_task: bool = False) -> DataFrame:
    """(n, sum_cents) of rows below ``hi``: the predicate is pushed to the files, two columns are read.

    ``one_task`` reads with a single task, to compare with all of them.
    """
    rows = df.coalesce(1) if one_task else df
    return rows.where(F.col(key) < hi).agg(F.count(F.lit(1)).alias("n"), cents(measure))


def paged(df: DataFrame, row: list[str], pages: int) -> DataFrame:
    """Rows with the page that they are stored in."""
    return df.withColumn(PAGE, F.pmod(F.xxhash64(*row), F.lit(pages)).cast("int"))


class KeyIndex:
    """Secondary index: (key, page, row) sorted by key, so that file statistics prune what a probe reads."""

    def __init__(self, rows: DataFrame, key: str):
        self.rows, self.key = rows, key

    @classmethod
    def build(cls, df: DataFrame, key: str, row: list[str], partitions: int = 8, kind: str = "tree") -> KeyIndex:
        """``tree``: range partitions, sorted; for ranges and points.  ``hash``: hashed by key; for points."""
        if kind not in ("tree", "hash"):
            raise ValueError(f"unknown index kind {kind!r}")
        extra = [PAGE] if PAGE in df.columns else []
        entries = df.select(key, *extra, *[c for c in row if c != key])
        dealt = entries.repartitionByRange(partitions, key) if kind == "tree" else entries.repartition(partitions, key)
        return cls(dealt.sortWithinPartitions(key), key)

    def save(self, path: str) -> None:
        self.rows.write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str, key: str) -> KeyIndex:
        return cls(spark.read.parquet(path), key)

    def probe(self, cond: Column) -> DataFrame:
        return self.rows.where(cond)


def store_indexed(df: DataFrame, path: str, key: str, row: list[str], pages: int = 64, partitions: int = 8, kind: str = "tree") -> None:
    """Write the rows by page and the index beside them: what a database has before the first query comes."""
    rows = paged(df, row, pages)
    rows.repartition(pages, PAGE).write.mode("overwrite").partitionBy(PAGE).parquet(f"{path}/rows")
    KeyIndex.build(rows, key, row, partitions, kind).save(f"{path}/index")


def stored_probe_sum(spark: SparkSession, path: str, key: str, cond: Column, row: list[str], measure: str, one_task: bool = False) -> DataFrame:
    """(n, sum_cents) by a probe of the stored index.

    The predicate prunes the index's files; the pages that it names prune the
    rows' files at run time, and a semi join picks the rows.
    """
    names = KeyIndex.load(spark, f"{path}/index", key).probe(cond).select(PAGE, *row)
    rows = spark.read.parquet(f"{path}/rows").select(PAGE, *dict.fromkeys([*row, measure]))
    found = rows.join(names, [PAGE, *row], "left_semi")
    return (found.coalesce(1) if one_task else found).agg(F.count(F.lit(1)).alias("n"), cents(measure))


def relational_probe_sum(index: KeyIndex, df: DataFrame, cond: Column, row: list[str], measure: str) -> DataFrame:
    """(n, sum_cents): qualifying row names from the index, then a semi join back to the rows."""
    names = index.probe(cond).select(*row)
    return df.select(*dict.fromkeys([*row, measure])).join(names, row, "left_semi").agg(F.count(F.lit(1)).alias("n"), cents(measure))


def sorted_copy(df: DataFrame, key: str, columns: list[str], partitions: int = 8) -> DataFrame:
    """Clustered form: a copy of the needed columns in key order, probed by range without a join."""
    return df.select(*dict.fromkeys([key, *columns])).repartitionByRange(partitions, key).sortWithinPartitions(key)
