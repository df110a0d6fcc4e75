"""Grams: substrings of length k at every place of a sequence."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bind(value, use):
    """use(value) with value computed once a row, however often higher-order functions use it."""
    return F.element_at(F.transform(F.array(value), use), 1)


def starts(length, k: int, stride: int = 1):
    """Places 1, 1 + stride, ... of the grams of a sequence of the given length; none if it is shorter than k."""
    return F.when(length >= k, F.sequence(F.lit(1), length - (k - 1), F.lit(stride))).otherwise(F.array().cast("array<int>"))


def gram_array(seq, k: int, stride: int = 1):
    """Grams of a string column in order; |seq| - k + 1 of them, or none."""
    return F.transform(starts(F.coalesce(F.length(seq), F.lit(0)), k, stride), lambda i: F.substring(seq, i, F.lit(k)))


def explode_grams(df: DataFrame, seq="seq", k: int = 31, stride: int = 1) -> DataFrame:
    """Every row once a gram, with pos (from 0) and gram in place of the sequence."""
    keep = [c for c in df.columns if c != seq]
    return df.select(*keep, F.posexplode(gram_array(F.col(seq), k, stride)).alias("pos", "gram"))


def gram_set(df: DataFrame, keys=("file_id",), seq="seq", k: int = 31) -> DataFrame:
    """Distinct grams of each key; repeats inside a row go before the shuffle."""
    return df.select(*keys, F.explode(F.array_distinct(gram_array(F.col(seq), k))).alias("gram")).distinct()


def token_grams(tokens, k: int):
    """Grams of an array column: k consecutive tokens, joined with the unit separator."""
    return F.transform(starts(F.coalesce(F.size(tokens), F.lit(0)), k), lambda i: F.array_join(F.slice(tokens, i, k), "\x1f"))


def explode_token_grams(df: DataFrame, tokens="tokens", k: int = 5) -> DataFrame:
    keep = [c for c in df.columns if c != tokens]
    return df.select(*keep, F.posexplode(token_grams(F.col(tokens), k)).alias("pos", "gram"))


def pack2(gram):
    """A gram over ACGT, of at most 31 symbols, as a number with two bits a symbol; null with other symbols."""
    return F.when(gram.rlike("^[ACGT]+$"), F.conv(F.translate(gram, "ACGT", "0123"), 4, 10).cast("long"))


def canonical(gram):
    """The smaller of a DNA gram and its reverse complement."""
    return F.least(gram, F.reverse(F.translate(gram, "ACGT", "TGCA")))


def jaccard(x, y):
    """Similarity of two array columns as sets; 1 if both are empty."""
    return F.when((F.size(x) == 0) & (F.size(y) == 0), F.lit(1.0)).otherwise(F.size(F.array_intersect(x, y)) / F.size(F.array_union(x, y)))
