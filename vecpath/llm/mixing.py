"""Mixing sources to target weights by systematic sampling."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, text_or_empty, word_count

SMALL_SOURCES = 50_000
OFFSETS = 16


def numbered(rows: DataFrame, *order: Column) -> DataFrame:
    """``rows`` with ``_number``, their place from 0 on in the given order; partitions are sorted side by side."""
    rows = cut(rows.orderBy(*order).withColumns({"_part_": F.spark_partition_id(), "_at_": F.monotonically_increasing_id()}))
    sizes = dict(rows.groupBy("_part_").count().collect())  # one row for each partition
    before, first = 0, {}
    for part in sorted(sizes):
        first[part], before = before, before + sizes[part]
    if not first:
        return rows.drop("_part_", "_at_").withColumn("_number", F.lit(0).cast("long"))
    starts = F.create_map(*[F.lit(x) for pair in first.items() for x in pair])
    place = starts[F.col("_part_")] + F.col("_at_").bitwiseAND(F.lit((1 << 33) - 1))
    return rows.withColumn("_number", place.cast("long")).drop("_part_", "_at_")


def _level(per: DataFrame, total: float) -> float | None:
    """The level at which sum(min(_cap, level * _w)) is the total; None if all caps together do not reach it.

    Sources are capped when _cap / _w is below the level.  The range in which
    the level lies is split again and again by sums over all sources, until
    all sources are known to be below or above; the driver sees one row for
    each part of the range.
    """
    per = per.withColumn("_q", F.col("_cap") / F.col("_w"))
    caps, most = per.agg(F.sum("_cap"), F.max("_q")).first()
    if caps is None or caps <= total:
        return None
    low, high, parts = -1.0, float(most), 256
    below, above = 0.0, float(per.agg(F.sum("_w")).first()[0])  # caps of sources under the range, weights of the others
    while True:
        step = (high - low) / parts
        at = F.least(F.floor((F.col("_q") - low) / step), F.lit(parts - 1))
        inside = per.where((F.col("_q") > low) & (F.col("_q") <= high)) if step > 0 else per.where("false")
        got = sorted(tuple(r) for r in inside.groupBy(at.alias("b")).agg(F.sum("_cap"), F.sum("_w"), F.min("_q"), F.max("_q")).collect())
        level = (total - below) / above
        for _, cap, weight, least, last in got:
            if level <= least:  # the sources from here on are not capped
                return level
            after = above - weight
            if after <= 0 or (total - below - cap) / after <= last:
                break  # the level lies among the sources of this part
            below, above = below + cap, after
            level = (total - below) / above
        else:
            return level
        if least == last:
            return level
        low, high = math.nextafter(least, -math.inf), last


def source_targets(sizes: DataFrame, max_repeat: float = 3.0, weights: tuple[float, ...] = (1, 2, 3)) -> DataFrame:
    """(source, n_docs, source_size, target) from rows of (source, size).

    Sources in code-point order, null last, take the weights in turn.  The
    targets share the sum of all sizes by weight; none is above ``max_repeat``
    times its source's size, and what is cut off goes to the others by weight
    until none is above: target = min(cap, level * weight) for the one level
    at which the targets sum to the total.  No task holds all sources.
    """
    per = sizes.groupBy("source").agg(F.count(F.lit(1)).alias("n_docs"), F.sum("size").alias("source_size"))
    turn = F.array(*[F.lit(float(w)) for w in weights])
    per = numbered(per, F.col("source").isNull(), F.col("source").cast("binary"))
    per = cut(
        per.withColumn("_w", F.element_at(turn, (F.pmod("_number", F.lit(len(weights))) + 1).cast("int")))
        .withColumn("_cap", F.col("source_size") * F.lit(float(max_repeat)))
    )
    total = per.agg(F.sum("source_size")).first()[0] or 0
    level = _level(per, float(total))
    target = F.col("_cap") if level is None else F.least(F.col("_cap"), F.col("_w") * F.lit(level))
    return per.select("source", "n_docs", "source_size", target.alias("target"))


def _uniform(*cols: Column) -> Column:
    return F.shiftrightunsigned(F.xxhash64(*cols), 11).cast("double") / float(1 << 53)


def mix(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", source: str = "source", seed: int = 42) -> DataFrame:
    """Every row of ``docs`` with size, source_size, target and copies.

    ``copies`` is how often the mix takes the row (0 to 3).  Within a source a
    row's expected copies are target / source_size.  Rows are ordered by size
    class, a hash and size; their expected copies are summed along this order,
    one random offset for the source is added, and the row is taken once for
    every whole number that the sum crosses.  The order spreads each size
    class evenly.  Of the offsets that stand evenly spaced from a random start,
    a source gets the one by which its words come nearest to its target.

    The prefix sum is distributed: rows are dealt into small cells, a window
    ranks each cell, and the offsets of the cells come from their counts, so
    no source meets in one task.  Reruns give the same copies.  A null text
    has size 0; a source without words has target 0 and is not taken.  Null is
    a source of its own, the last.  Repeated rows are rows of their own.
    Columns of ``docs`` with the four names are replaced.
    """
    clash = [c for c in docs.columns if c.lower() in {"size", "source_size", "target", "copies"}]
    rows = docs.drop(*clash).withColumn("size", word_count(text_or_empty(text)))
    narrow = cut(rows.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), "size"))
    targets = cut(source_targets(narrow))
    total = narrow.count()
    per_cell = max(64, min(5_000, total // 2_000))

    def dealt(df: DataFrame, sid: str, src: str) -> DataFrame:
        t = targets.select(F.col("source").alias("_source"), "n_docs", "source_size", "target")
        if t.count() <= SMALL_SOURCES:
            t = F.broadcast(t)
        df = df.join(t, F.col(src).eqNullSafe(F.col("_source"))).drop("_source")
        ways = F.ceil(F.col("n_docs") / F.lit(per_cell))
        return df.withColumns(
            {
                "_class": F.floor(F.log2(F.col("size") + 1)).cast("int"),
                "_hash": F.xxhash64(F.lit(seed), F.col(sid)),
            }
        ).withColumn("_part", F.pmod("_hash", ways))

    # rows before a cell: those of the classes before its own, and of the cells before it in its class
    cells = cut(dealt(narrow, "doc_id", "source").groupBy("source", "_class", "_part").agg(F.count(F.lit(1)).alias("_n")))
    earlier = lambda w: F.coalesce(F.sum("_n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    classes = cells.groupBy("source", "_class").agg(F.sum("_n").alias("_n")).select(
        F.col("source").alias("_s"), F.col("_class").alias("_c"), earlier(Window.partitionBy("source").orderBy("_class")).alias("_first")
    )
    cells = cells.withColumn("_in", earlier(Window.partitionBy("source", "_class").orderBy("_part"))).join(
        classes, F.col("source").eqNullSafe(F.col("_s")) & (F.col("_class") == F.col("_c"))
    )
    cells = cells.select("_s", "_c", F.col("_part").alias("_p"), (F.col("_first") + F.col("_in")).alias("_before"))

    def ranked(df: DataFrame, sid: str, src: str) -> DataFrame:
        here = Window.partitionBy(src, "_class", "_part").orderBy("size", "_hash", sid)
        out = dealt(df, sid, src).withColumn("_rn", F.row_number().over(here))
        same = F.col(src).eqNullSafe(F.col("_s")) & (F.col("_class") == F.col("_c")) & (F.col("_part") == F.col("_p"))
        out = out.join(cells, same).withColumn("_rank", F.col("_before") + F.col("_rn"))
        return out.drop("_class", "_hash", "_part", "_rn", "_s", "_c", "_p", "_before", "n_docs")

    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))

    def copies(offset: Column) -> Column:
        return (F.floor(F.col("_rank") * rate + offset) - F.floor((F.col("_rank") - 1) * rate + offset)).cast("int")

    start = _uniform(F.lit(seed), F.coalesce(F.col("source"), F.lit("")), F.col("source").isNull())
    starts = [(start + k / OFFSETS) % 1 for k in range(OFFSETS)]
    tried = (
        ranked(narrow, "doc_id", "source")
        .groupBy("source")
        .agg(F.first("target").alias("_t"), *(F.sum(copies(u) * F.col("size")).alias(f"_{k}") for k, u in enumerate(starts)))
    )
    nearest = F.array_min(F.array(*(F.struct(F.abs(F.col(f"_{k}") - F.col("_t")).alias("e"), u.alias("u")) for k, u in enumerate(starts))))
    offsets = cut(tried.select(F.col("source").alias("_s"), nearest["u"].alias("_offset")))
    if offsets.count() <= SMALL_SOURCES:
        offsets = F.broadcast(offsets)
    out = ranked(rows, doc_id, source).join(offsets, F.col(source).eqNullSafe(F.col("_s")))
    return out.withColumn("copies", copies(F.col("_offset"))).drop("_s", "_rank", "_offset")


def repeat(mixed: DataFrame) -> DataFrame:
    """The mix itself: every row of ``mix`` once for each of its copies."""
    return mixed.where("copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).drop(
        "_copy", "copies", "size", "source_size", "target"
    )
