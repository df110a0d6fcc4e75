"""Views that turn tables into sequences over an alphabet, and sequences into reads."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: The letters a-z, and the DNA letter of each (its number modulo 4).
LETTERS = "abcdefghijklmnopqrstuvwxyz"
DNA = "ACGTACGTACGTACGTACGTACGTAC"


def dna(text):
    """Four-letter view of a text: its letters a-z, each by its number modulo 4."""
    return F.translate(F.regexp_replace(F.lower(text), "[^a-z]", ""), LETTERS, DNA)


def dna_sequences(docs: DataFrame, text="text", seq_id="doc_id", file_id=None) -> DataFrame:
    """(file_id, seq_id, seq); file_id is a column or expression, one file without it."""
    file = F.lit("all") if file_id is None else F.col(file_id) if isinstance(file_id, str) else file_id
    return docs.select(file.cast("string").alias("file_id"), F.col(seq_id).alias("seq_id"), dna(F.col(text)).alias("seq"))


def native_sequences(docs: DataFrame, text="text", seq_id="doc_id", file_id=None) -> DataFrame:
    file = F.lit("all") if file_id is None else F.col(file_id) if isinstance(file_id, str) else file_id
    return docs.select(file.cast("string").alias("file_id"), F.col(seq_id).alias("seq_id"), F.col(text).alias("seq"))


def log_sequences(events: DataFrame, user="user_id", kind="event_type", order=("ts", "event_id")) -> DataFrame:
    """One sequence a user: the first letters of the events in their order."""
    rows = events.groupBy(F.col(user).alias("seq_id")).agg(F.array_sort(F.collect_list(F.struct(*order, F.substring(kind, 1, 1).alias("letter")))).alias("run"))
    return rows.select(F.lit("events").alias("file_id"), "seq_id", F.array_join(F.transform("run", lambda x: x["letter"]), "").alias("seq"))


def token_sequences(docs: DataFrame, text="text", keys=("doc_id",)) -> DataFrame:
    """keys and tokens: lower-case words between white space."""
    return docs.select(*keys, F.filter(F.split(F.lower(F.col(text)), r"\s+"), lambda w: w != "").alias("tokens"))


def vector_sequences(vectors: DataFrame, vector="embedding", seq_id="vec_id", levels: int = 8, low: float = -0.4, high: float = 0.4) -> DataFrame:
    """Quantised vectors as strings: a letter for the level of each dimension."""
    level = lambda x: F.least(F.greatest(F.floor((x - low) / (high - low) * levels), F.lit(0)), F.lit(levels - 1)).cast("int")
    letters = F.transform(vector, lambda x: F.substring(F.lit(LETTERS), level(x.cast("double")) + 1, F.lit(1)))
    return vectors.select(F.lit("vectors").alias("file_id"), F.col(seq_id).alias("seq_id"), F.array_join(letters, "").alias("seq"))


def to_reads(seqs: DataFrame, k: int, max_symbols: int = 230) -> DataFrame:
    """Reads of at most max_symbols with an overlap of k - 1, so that every gram is in exactly one read."""
    if max_symbols < k:
        raise ValueError("a read holds at least one gram")
    step = max_symbols - k + 1
    last = F.greatest(F.ceil((F.length("seq") - (k - 1)) / step) - 1, F.lit(0)).cast("int")
    starts = F.when(F.col("seq").isNull(), F.array().cast("array<int>")).otherwise(F.sequence(F.lit(0), last))
    rows = seqs.select("file_id", "seq_id", F.explode(F.transform(starts, lambda i: F.struct(i.alias("read_no"), F.substring("seq", i * step + 1, F.lit(max_symbols)).alias("seq")))).alias("_r"))
    return rows.select("file_id", "seq_id", "_r.read_no", "_r.seq")


def numbered_files(seqs: DataFrame) -> DataFrame:
    """(file_id, file_ord): files numbered from 0 in their order; one row a file."""
    return seqs.select("file_id").distinct().withColumn("file_ord", F.row_number().over(Window.orderBy("file_id")) - 1)
