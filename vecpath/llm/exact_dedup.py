"""Exact de-duplication by two-pass Bloom filtering.  DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bloom import blocks_for, may_hold, repeated_bits
from .common import ascii_lower, cut, settled, text_or_empty

HEAVY_GROUPS = 10_000


def digest(text: str):
    """SHA-256 (lower-case hex) of the text with A-Z lower-cased; null counts as empty."""
    return F.sha2(ascii_lower(text_or_empty(text)), 256)


def mark_copies(
    df: DataFrame, key: str, doc_id: str, largest: bool = True, max_filter_bytes: int = 32 << 20
) -> DataFrame:
    """Add ``keep_id``, ``group_size`` and ``kept`` to every row of ``df``.

    Rows with equal ``key`` form a group; the row with the largest (or smallest)
    ``doc_id`` stays.  A null id counts as neither, and stays only in a group
    of nulls; of several rows with the id that stays, exactly one is kept.  A
    null key is a key like any other.  An empty table gives an empty result.
    The three names must be free in ``df``.

    Pass one builds a Bloom filter of the key hashes set by two rows or more.
    Pass two sends rows that the filter rules out straight to the result; only
    the others shuffle.  The filter is broadcast as a scalar of at most
    ``max_filter_bytes``.  Where the rows are too many for a filter of that
    size to rule anything out, all rows take the exact shuffle.

    Groups too large for one task are at most ``HEAVY_GROUPS`` (each has more
    than one in ``HEAVY_GROUPS`` of all rows), so they are broadcast, and
    their rows never meet in one task.
    """
    src = df.withColumn("__vp_h", settled(F.xxhash64(F.coalesce(F.col(key), F.lit("")), F.col(key).isNull())))
    rows = df.count()
    blocks = blocks_for(rows, max_filter_bytes)
    best = F.max if largest else F.min
    pick = F.max_by if largest else F.min_by
    if blocks is None:
        straight, maybe = None, src
    else:
        maps = cut(repeated_bits(src, "__vp_h", blocks)).scalar()
        flagged = src.withColumn("__vp_maybe", may_hold(maps, F.col("__vp_h"), blocks))
        straight = flagged.where(~F.col("__vp_maybe")).drop("__vp_maybe")
        maybe = flagged.where("__vp_maybe").drop("__vp_maybe")
    groups = cut(
        maybe.select(F.col(key).alias("__vp_key"), F.col(doc_id).alias("__vp_id"))
        .groupBy("__vp_key", "__vp_id")
        .agg(F.count(F.lit(1)).alias("__vp_n"))
        .groupBy("__vp_key")
        .agg(
            best("__vp_id").alias("__vp_keep"),
            F.sum("__vp_n").alias("__vp_size"),
            F.coalesce(pick("__vp_n", "__vp_id"), F.sum("__vp_n")).alias("__vp_same"),
        )
    )
    limit = max(32, rows // HEAVY_GROUPS)
    heavy = F.broadcast(groups.where(F.col("__vp_size") > limit))
    light = groups.where(F.col("__vp_size") <= limit)
    on = F.col(key).eqNullSafe(F.col("__vp_key"))
    large = maybe.join(heavy, on)
    small = maybe.join(F.broadcast(heavy.select("__vp_key")), on, "left_anti").join(light, on)
    joined = large.unionByName(small).drop("__vp_key")
    stays = F.col(doc_id).eqNullSafe(F.col("__vp_keep"))
    out = joined.where(~stays | (F.col("__vp_same") == 1)).withColumn("__vp_kept", stays)
    if not groups.where("__vp_same > 1").isEmpty():
        # Repeated rows with the id that stays: one of them is kept.
        one = Window.partitionBy(key, doc_id).orderBy("__vp_h")
        tied = joined.where(stays & (F.col("__vp_same") > 1)).withColumn("__vp_kept", F.row_number().over(one) == 1)
        out = out.unionByName(tied)
    out = out.drop("__vp_same")
    if straight is not None:
        out = out.unionByName(
            straight.withColumns({"__vp_keep": F.col(doc_id), "__vp_size": F.lit(1).cast("long"), "__vp_kept": F.lit(True)})
        )
    return out.drop("__vp_h").withColumnsRenamed({"__vp_keep": "keep_id", "__vp_size": "group_size", "__vp_kept": "kept"})


def exact_dedup(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """Every row of ``docs`` with keep_id, group_size, kept and text_sha256.

    Texts are equal when they are identical after lower-casing A-Z; null
    counts as the empty text.  Columns of ``docs`` with these four names are
    replaced.  See ``mark_copies`` for ties, repeated rows and empty tables.
    """
    clash = [c for c in docs.columns if c.lower() in {"keep_id", "group_size", "kept", "text_sha256"}]
    return mark_copies(docs.drop(*clash).withColumn("text_sha256", settled(digest(text))), "text_sha256", doc_id)
