"""Blocked Bloom filters made of SQL bitmaps, without Python on the executors.

A 64-bit hash picks one block of 32,768 bits and three bits in it.  The first
pass counts how many rows set each bit and keeps the bits that two rows or more
have set; a hash whose three bits are all kept may be repeated, any other is
certainly unique.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCK = 15  # a block has 2**15 bits, as Spark's bitmap functions have it
BITS_PER_ROW = 32


def blocks_for(rows: int, max_bytes: int) -> int | None:
    """Number of blocks, a power of two; None if the filter would be too large."""
    bits = max(1 << BLOCK, 1 << (max(rows, 1) * BITS_PER_ROW - 1).bit_length())
    while bits // 8 > max_bytes:
        bits //= 2
    return None if bits < rows * 4 else bits >> BLOCK


def _bits(h: Column) -> list[Column]:
    mask = F.lit((1 << BLOCK) - 1)
    return [F.shiftrightunsigned(h, k * BLOCK).bitwiseAND(mask) for k in range(3)]


def _block(h: Column, blocks: int) -> Column:
    return F.shiftrightunsigned(h, 3 * BLOCK).bitwiseAND(F.lit(blocks - 1))


WORD = 5  # bitmaps are looked up as words of 2**5 bits


def _words(bitmap: Column) -> Column:
    """The bitmap as an array of words, the first byte highest."""
    at = F.sequence(F.lit(0), F.lit((1 << (BLOCK - WORD)) - 1))
    word = lambda i: F.conv(F.hex(F.substring(bitmap, i * 4 + 1, F.lit(4))), 16, 10).cast("long")
    return F.transform(at, word)


def _packed(bits: DataFrame, blocks: int) -> DataFrame:
    """One row: the bitmaps of all blocks, in order."""
    maps = bits.groupBy("block").agg(F.bitmap_construct_agg("bit").alias("map")).select("block", _words(F.col("map")).alias("map"))
    every = bits.sparkSession.range(blocks).select(F.col("id").alias("block"))
    full = every.join(maps, "block", "left").select(
        F.struct("block", "map").alias("x")
    )
    return full.agg(F.transform(F.array_sort(F.collect_list("x")), lambda x: x["map"]).alias("maps"))


def repeated_bits(df: DataFrame, h: str, blocks: int) -> DataFrame:
    """First pass: filter of the hashes that may occur twice or more."""
    col = F.col(h)
    bits = (
        df.select(_block(col, blocks).alias("block"), F.explode(F.array_distinct(F.array(*_bits(col)))).alias("bit"))
        .groupBy("block", "bit")
        .agg(F.count(F.lit(1)).alias("n"))
        .where("n > 1")
    )
    return _packed(bits, blocks)


def present_bits(df: DataFrame, h: str, blocks: int) -> DataFrame:
    """Filter of the hashes that occur at all."""
    col = F.col(h)
    bits = df.select(
        _block(col, blocks).alias("block"), F.explode(F.array_distinct(F.array(*_bits(col)))).alias("bit")
    ).distinct()
    return _packed(bits, blocks)


def may_hold(maps: Column, h: Column, blocks: int) -> Column:
    """Second pass: true unless the filter rules the hash out."""
    mine = F.get(maps, _block(h, blocks).cast("int"))
    found = F.lit(True)
    for bit in _bits(h):
        word = F.get(mine, F.shiftright(bit, WORD).cast("int"))
        place = F.lit(24) - bit.bitwiseAND(F.lit(24)) + bit.bitwiseAND(F.lit(7))  # in its byte, and that in the word
        one = F.call_function("shiftright", F.coalesce(word, F.lit(0)), place.cast("int"))
        found = found & (one.bitwiseAND(F.lit(1)) == 1)
    return found
