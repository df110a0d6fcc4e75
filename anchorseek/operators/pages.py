"""Bit pages: binary cells of 32,768 bits, lowest bit of a byte first, as Spark's bitmap aggregates make them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import PAGE_BITS, PAGE_BYTES


def page_of(pos):
    return F.shiftright(pos, 15)


def offset_of(pos):
    return pos.bitwiseAND(F.lit(PAGE_BITS - 1)).cast("int")


def bit_at(bits, offset):
    """Whether a bit of a page is set. offset: int column in [0, 32768)."""
    byte = F.conv(F.hex(F.substring(bits, F.shiftright(offset, 3) + 1, F.lit(1))), 16, 10).cast("int")
    return F.call_function("getbit", byte, offset.bitwiseAND(F.lit(7)).cast("int")) == 1


def covers(bits, offsets):
    """Whether all bits of an array of offsets are set; a missing page holds no bit."""
    return F.coalesce(F.forall(offsets, lambda o: bit_at(bits, o)), F.lit(False))


def zero_page():
    return F.unhex(F.lit("00" * PAGE_BYTES))


def from_positions(rows: DataFrame, keys, pos="bit") -> DataFrame:
    """(keys, page_no, bits) from one row a bit."""
    return rows.groupBy(*keys, page_of(F.col(pos)).alias("page_no")).agg(F.bitmap_construct_agg(offset_of(F.col(pos)).cast("long")).alias("bits"))


def union(*frames: DataFrame, keys=("filter_id", "rep", "page_no")) -> DataFrame:
    """Pages joined by OR."""
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out.groupBy(*keys).agg(F.bitmap_or_agg("bits").alias("bits"))
