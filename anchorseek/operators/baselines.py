"""Exact references and other ways to the same answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import grams, native, runs, views


def _files_of(reads: DataFrame, queries: DataFrame, k: int, blocks: int) -> DataFrame:
    """(query_id, block, files): bits of the files that hold all grams of a query, for sequences over ACGT and k up to 31.

    reads: (id, seq), id the number of a file. Runs of grams are compared part by part; see functions.runs.
    """
    asked = queries.select(F.col("query_id").cast("long").alias("id"), "seq").mapInArrow(runs.builder(k, 0), runs.SCHEMA)
    known = reads.select(F.col("id").cast("long").alias("id"), "seq").mapInArrow(runs.builder(k, 1), runs.SCHEMA)
    met = asked.unionByName(known).repartition("part").sortWithinPartitions("part", "side")
    found = met.mapInArrow(runs.matcher(k, blocks), "query_id bigint, block int, files bigint")
    return found.groupBy("query_id", "block").agg(F.bit_and("files").alias("files"))


def exact_mt(reads: DataFrame, queries: DataFrame, k: int, alphabet: str = "any") -> DataFrame:
    """(query_id, hit): whether all grams of the query are grams of the set. Without grams: true.

    alphabet `dna` says that all sequences are over ACGT: grams then travel in runs, a byte each, not as strings.
    """
    if alphabet == "dna" and k <= 31:
        found = _files_of(reads.select(F.lit(0).alias("id"), "seq"), queries, k, 1)
        missing = found.where("files = 0").select("query_id", F.lit(True).alias("_m"))
    else:
        known = grams.gram_set(reads, [], "seq", k)
        missing = grams.gram_set(queries, ["query_id"], "seq", k).join(known, "gram", "left_anti").select("query_id").distinct().withColumn("_m", F.lit(True))
    return queries.select("query_id").join(missing, "query_id", "left").select("query_id", F.col("_m").isNull().alias("hit"))


def exact_msmt(reads: DataFrame, queries: DataFrame, k: int, alphabet: str = "any") -> DataFrame:
    """(query_id, file_id, hit) for every query and file, by exact grams; alphabet as in exact_mt."""
    if alphabet == "dna" and k <= 31:
        files = views.numbered_files(reads)
        blocks = (files.count() + runs.FILES - 1) // runs.FILES
        found = _files_of(reads.join(F.broadcast(files), "file_id").select(F.col("file_ord").alias("id"), "seq"), queries, k, max(1, blocks))
        # a row a query and block meets the files; a query without grams has none and is held by all
        asked = queries.select("query_id").crossJoin(F.broadcast(files.select(F.expr(f"file_ord div {runs.FILES}").cast("int").alias("block")).distinct()))
        each = asked.join(found, ["query_id", "block"], "left").join(F.broadcast(files.withColumn("block", F.expr(f"file_ord div {runs.FILES}").cast("int"))), "block")
        return each.select("query_id", "file_id", F.coalesce(F.call_function("getbit", F.col("files"), F.expr(f"cast(file_ord % {runs.FILES} as int)")) == 1, F.lit(True)).alias("hit"))
    wanted = grams.gram_set(queries, ["query_id"], "seq", k)
    known = grams.gram_set(reads, ["file_id"], "seq", k)
    need = wanted.groupBy("query_id").agg(F.count(F.lit(1)).alias("need"))
    have = wanted.join(known, "gram").groupBy("query_id", "file_id").agg(F.count(F.lit(1)).alias("have"))
    grid = queries.select("query_id").join(need, "query_id", "left").crossJoin(F.broadcast(reads.select("file_id").distinct()))
    return grid.join(have, ["query_id", "file_id"], "left").select("query_id", "file_id", (F.coalesce("have", F.lit(0)) == F.coalesce("need", F.lit(0))).alias("hit"))


def exact_pairs(reads: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, file_id) of the files that hold all grams of a query, by exact grams; queries without grams are absent."""
    wanted = grams.gram_set(queries, ["query_id"], "seq", k)
    known = grams.gram_set(reads, ["file_id"], "seq", k)
    need = wanted.groupBy("query_id").agg(F.count(F.lit(1)).alias("need"))
    have = wanted.join(known, "gram").groupBy("query_id", "file_id").agg(F.count(F.lit(1)).alias("have"))
    return have.join(need, "query_id").where("have = need").select("query_id", "file_id")


def exact_grams(reads: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, pos, is_member) of every gram of every query."""
    known = grams.gram_set(reads, [], "seq", k).withColumn("_known", F.lit(True))
    return grams.explode_grams(queries.select("query_id", "seq"), "seq", k).join(known, "gram", "left").select("query_id", "pos", F.col("_known").isNotNull().alias("is_member"))


def substring_scan(seqs: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, hit): whether some sequence holds the whole query. Compares every query with every sequence:
    a stated query set, in broadcast form, against all rows; a reference, not a method for large data."""
    met = seqs.select("seq").join(F.broadcast(queries.select("query_id", F.col("seq").alias("q"))), F.col("seq").contains(F.col("q"))).select("query_id").distinct().withColumn("_h", F.lit(True))
    return queries.select("query_id").join(met, "query_id", "left").select("query_id", F.col("_h").isNotNull().alias("hit"))


def native_filter(reads: DataFrame, k: int, items: int = 4_000_000, bits: int = 1 << 26) -> DataFrame:
    """Spark's own Bloom filter of all grams of the set: one row, of `bits` bits at most, sized for `items` grams."""
    return native.bloom_filter(grams.explode_grams(reads.select("seq"), "seq", k), F.xxhash64("gram"), items, bits)


def native_mt(index: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, hit): whether native_filter's filter may hold all grams of the query. Without grams: true."""
    wanted = grams.explode_grams(queries.select("query_id", "seq"), "seq", k)
    may = F.coalesce(native.might_contain(index, F.xxhash64("gram")), F.lit(False))
    answers = wanted.groupBy("query_id").agg(F.bool_and(may).alias("_all"))
    return queries.select("query_id").join(answers, "query_id", "left").select("query_id", F.coalesce("_all", F.lit(True)).alias("hit"))


def native_bloom(reads: DataFrame, queries: DataFrame, k: int, items: int = 4_000_000, bits: int = 1 << 26) -> DataFrame:
    """The exact answer: grams that Spark's own Bloom filter does not hold never reach the join that decides."""
    known = grams.gram_set(reads, [], "seq", k)
    wanted = grams.gram_set(queries, ["query_id"], "seq", k)
    need = wanted.groupBy("query_id").agg(F.count(F.lit(1)).alias("need"))
    likely = wanted.where(native.might_contain(native_filter(reads, k, items, bits), F.xxhash64("gram")))
    have = likely.join(known, "gram", "left_semi").groupBy("query_id").agg(F.count(F.lit(1)).alias("have"))
    return queries.select("query_id").join(need, "query_id", "left").join(have, "query_id", "left").select("query_id", (F.coalesce("need", F.lit(0)) == F.coalesce("have", F.lit(0))).alias("hit"))


def native_mt_parts(reads: DataFrame, queries: DataFrame, k: int, items: int = 2_000_000, bits: int = 1 << 24) -> DataFrame:
    """(query_id, hit) of as many of Spark's own Bloom filters as the set needs, for sequences over ACGT and k up to 31.

    One filter has a bounded size, so the grams are dealt by their smallest subgram over parts of `items` grams on
    average, repeats counted, each with a filter of its own; a query's grams meet the filters of their parts.
    """
    total = reads.agg(F.sum(F.greatest(F.length("seq") - (k - 1), F.lit(0)))).first()[0] or 0
    parts = max(1, -(-total // items))
    known = reads.select(F.lit(0).cast("long").alias("id"), "seq").mapInArrow(runs.builder(k, 1, parts), runs.SCHEMA)
    hashes = known.repartition("part").mapInArrow(runs.hasher(k, 19), "part int, hash bigint")
    filters = native.bloom_filter(hashes, F.col("hash"), items, bits, ["part"])
    asked = queries.select(F.col("query_id").cast("long").alias("id"), "seq").mapInArrow(runs.builder(k, 1, parts), runs.SCHEMA)
    met = filters.withColumn("side", F.lit(0)).unionByName(asked, allowMissingColumns=True).select("part", "side", "filter", "ids", "sizes", "symbols")
    tested = met.repartition("part").sortWithinPartitions("part", "side").mapInArrow(runs.tester(k, 19), "query_id bigint, hit boolean")
    answers = tested.groupBy("query_id").agg(F.bool_and("hit").alias("hit"))
    return queries.select("query_id").join(answers, "query_id", "left").select("query_id", F.coalesce("hit", F.lit(True)).alias("hit"))
