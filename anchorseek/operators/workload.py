"""Query sets: random pieces of reads with one symbol changed, and the same pieces unchanged."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import md5_value


def query_id(seq_id="seq_id", read_no="read_no"):
    """A number of a read: its sequence's id (below 2^39) and its place there (below 2^24)."""
    return F.col(seq_id) * F.lit(1 << 24).cast("long") + F.col(read_no)


def poison(reads: DataFrame, k: int = 31, max_len: int = 80, seed: int = 1, alphabet: str = "ACGT") -> DataFrame:
    """(query_id, origin_file, seq, clean, poison_pos, poison_from, poison_to, n_affected) of every read longer than k.

    Length in (k, max_len], start, changed place and new symbol come from hashes of the read's number, so the
    set is the same every time; the new symbol always differs. n_affected: grams that hold the changed symbol.
    """
    rows = reads.where(F.length("seq") > k).withColumn("query_id", query_id())

    def draw(purpose: int, n):
        return F.pmod(md5_value(F.col("query_id"), seed * 10 + purpose), n.cast("long")).cast("int")

    rows = rows.withColumn("_n", F.lit(k + 1) + draw(1, F.least(F.length("seq"), F.lit(max_len)) - k))
    rows = rows.withColumn("_at", draw(2, F.length("seq") - F.col("_n") + 1)).withColumn("poison_pos", draw(3, F.col("_n")))
    rows = rows.withColumn("clean", F.substring("seq", F.col("_at") + 1, F.col("_n"))).withColumn("poison_from", F.substring("clean", F.col("poison_pos") + 1, F.lit(1)))
    old = F.instr(F.lit(alphabet), F.col("poison_from")) - 1
    new = F.pmod(old + 1 + draw(4, F.lit(len(alphabet) - 1)), F.lit(len(alphabet)))
    rows = rows.withColumn("poison_to", F.substring(F.lit(alphabet), new + 1, F.lit(1)))
    grams_n = F.col("_n") - (k - 1)
    affected = F.least(F.col("poison_pos"), grams_n - 1) - F.greatest(F.col("poison_pos") - (k - 1), F.lit(0)) + 1
    changed = F.concat(F.substring("clean", F.lit(1), F.col("poison_pos")), F.col("poison_to"), F.substring("clean", F.col("poison_pos") + 2, F.col("_n")))
    return rows.select("query_id", F.col("file_id").alias("origin_file"), changed.alias("seq"), "clean", "poison_pos", "poison_from", "poison_to", affected.cast("int").alias("n_affected"))


def clean_twins(poisoned: DataFrame) -> DataFrame:
    """The same pieces unchanged: members of their file."""
    return poisoned.select("query_id", "origin_file", F.col("clean").alias("seq"))
