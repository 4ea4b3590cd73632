"""Aggregates over vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def centroid_positions(df: DataFrame, by: str, vector: str = "embedding") -> DataFrame:
    """(by, pos, mean): mean of each component, with partial aggregation before the shuffle."""
    return (
        df.select(by, F.posexplode(vector).alias("pos", "x"))
        .groupBy(by, "pos")
        .agg(F.avg(F.col("x").cast("double")).alias("mean"))
    )


def centroids(df: DataFrame, by: str, vector: str = "embedding") -> DataFrame:
    """(by, centroid array<double>)."""
    return (
        centroid_positions(df, by, vector)
        .groupBy(by)
        .agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "mean"))), lambda x: x["mean"]).alias("centroid"))
    )
