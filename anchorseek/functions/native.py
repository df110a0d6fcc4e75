"""Spark's own Bloom filter: the aggregate that its runtime join filters build, and the test they make, as columns.

Neither has a function of its own in Python, so both are reached through the session's JVM (a classic session).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.internal import InternalFunction

MOST_BITS = "spark.sql.optimizer.runtime.bloomFilter.maxNumBits"
MOST_ITEMS = "spark.sql.optimizer.runtime.bloomFilter.maxNumItems"


def bloom_filter(rows: DataFrame, value, items: int, bits: int, keys=()) -> DataFrame:
    """One row, filter: the Bloom filter of a bigint column, null without rows; with keys a row a group. The session
    bounds its size (8 MB unless set otherwise) and would silently build a smaller one; here that is an error."""
    most_bits, most_items = (int(rows.sparkSession.conf.get(name)) for name in (MOST_BITS, MOST_ITEMS))
    if not 0 < bits <= most_bits or not 0 < items <= most_items:
        raise ValueError(f"a filter of Spark's own holds 1 to {most_bits} bits and is sized for 1 to {most_items} values")
    made = InternalFunction._invoke_internal_function_over_columns("bloom_filter_agg", value, F.lit(items).cast("long"), F.lit(bits).cast("long"))
    return rows.groupBy(*keys).agg(made.alias("filter"))


def might_contain(filter_row: DataFrame, value) -> Column:
    """Whether the filter of bloom_filter may hold a bigint column's value; never false for one that it holds.
    The filter stays in the plan as a scalar subquery. An empty filter, being null, answers null."""
    jvm = filter_row.sparkSession._jvm
    expression = jvm.org.apache.spark.sql.classic.ExpressionUtils.expression
    test = jvm.org.apache.spark.sql.catalyst.expressions.BloomFilterMightContain(expression(filter_row.scalar()._jc), expression(value._jc))
    return type(value)(jvm.org.apache.spark.sql.classic.ExpressionUtils.column(test))


def _murmur(values: np.ndarray, seed) -> np.ndarray:
    """Murmur3 of longs, 32 bits, as Spark's filters take it."""
    h = np.broadcast_to(np.asarray(seed, np.int32).view(np.uint32), values.shape)
    turned = lambda x, by: (x << np.uint32(by)) | (x >> np.uint32(32 - by))
    whole = values.view(np.uint64)
    for word in ((whole & np.uint64(0xFFFFFFFF)).astype(np.uint32), (whole >> np.uint64(32)).astype(np.uint32)):
        h = turned(h ^ (turned(word * np.uint32(0xCC9E2D51), 15) * np.uint32(0x1B873593)), 13) * np.uint32(5) + np.uint32(0xE6546B64)
    h = h ^ np.uint32(8)
    h = (h ^ (h >> np.uint32(16))) * np.uint32(0x85EBCA6B)
    h = (h ^ (h >> np.uint32(13))) * np.uint32(0xC2B2AE35)
    return (h ^ (h >> np.uint32(16))).view(np.int32)


def holds(filter_: bytes, values: np.ndarray) -> np.ndarray:
    """might_contain for an array of longs and a filter that is a value of a row: Spark's own test takes only one
    filter a plan. Reads both forms in which Spark writes its filters."""
    version, functions = (int(x) for x in np.frombuffer(filter_, ">i4", 2))
    if version not in (1, 2):
        raise ValueError(f"no known form of a Bloom filter: {version}")
    seed = int(np.frombuffer(filter_, ">i4", 1, 8)[0]) if version == 2 else 0
    bits = np.frombuffer(filter_, ">u8", offset=12 if version == 1 else 16)
    first = _murmur(values, seed)
    second = _murmur(values, first)
    out = np.ones(len(values), bool)
    for i in range(1, functions + 1):
        if version == 1:
            at = (first + np.int32(i) * second).astype(np.int64)
        else:
            at = first.astype(np.int64) * np.int64(0x7FFFFFFF) + np.int64(i) * second.astype(np.int64)
        at = np.where(at < 0, ~at, at) % np.int64(len(bits) * 64)
        out &= (bits[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1
    return out
