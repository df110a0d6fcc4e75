"""User functions, each with a twin made of built-in expressions that gives the same values."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from .functions import kernel


@F.pandas_udf("array<long>")
def pack2_all(seqs: pd.Series, k: pd.Series) -> pd.Series:
    """Packed grams of ACGT strings; twin: pack2 over gram_array."""
    import pyarrow as pa

    out = []
    for s, width in zip(seqs, k):
        codes, offsets = kernel.symbols(pa.array([s], pa.string()))
        at, _ = kernel.valid_places(codes, offsets, int(width))
        out.append(kernel.packed(codes, int(width))[at])
    return pd.Series(out)


@F.pandas_udf("array<long>")
def rolling_min(values: pd.Series, width: pd.Series) -> pd.Series:
    """Minimum of every `width` consecutive values; twin: sketch.rolling_min."""
    return pd.Series([kernel.sliding_min(np.asarray(v, np.int64), int(w)) for v, w in zip(values, width)])


@F.pandas_udf("binary")
def page_from_offsets(offsets: pd.Series) -> bytes:
    """A page from one row a bit; twin: bitmap_construct_agg."""
    bits = np.zeros(32768, bool)
    bits[offsets.to_numpy()] = True
    return np.packbits(bits, bitorder="little").tobytes()


def register(spark) -> None:
    """Make jaccard, gram_sketch, anchored_position and the table function grams known to SQL."""

    @F.udtf(returnType="pos int, gram string")
    class Grams:
        def eval(self, seq: str, k: int):
            for i in range(len(seq or "") - k + 1):
                yield i, seq[i : i + k]

    spark.udtf.register("grams", Grams)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION jaccard(x ARRAY<STRING>, y ARRAY<STRING>) RETURNS DOUBLE RETURN CASE WHEN size(x) = 0 AND size(y) = 0 THEN 1.0 ELSE size(array_intersect(x, y)) / size(array_union(x, y)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gram_sketch(g STRING, t INT, seed BIGINT) RETURNS BIGINT RETURN array_min(transform(sequence(1, length(g) - t + 1), i -> xxhash64(seed, substring(g, i, t)) & 4611686018427387903))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION anchored_position(g STRING, t INT, m BIGINT, l BIGINT, seed BIGINT) RETURNS BIGINT RETURN pmod(xxhash64(seed + 1, array_min(transform(sequence(1, length(g) - t + 1), i -> xxhash64(seed, substring(g, i, t)) & 4611686018427387903))), m - l + 1) + pmod(xxhash64(seed + 2, g), l)")
