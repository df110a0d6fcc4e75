"""Accuracy and cost measures."""

from __future__ import annotations

import statistics
import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import grams, kernel, runs
from ..plans.spec import PAGE_BITS


def fpr_mt(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """(negatives, false_hits, fpr): share of hits among queries that are not in the set."""
    rows = answers.select("query_id", F.col("hit").alias("_a")).join(truth.select("query_id", "hit"), "query_id").where(~F.col("hit"))
    return rows.agg(F.count(F.lit(1)).alias("negatives"), F.coalesce(F.sum(F.col("_a").cast("long")), F.lit(0)).alias("false_hits"), F.avg(F.col("_a").cast("double")).alias("fpr"))


def fpr_mt_each(answers: DataFrame, truth: DataFrame, n: int) -> DataFrame:
    """(number, negatives, false_hits, fpr): fpr_mt for each of the n answers that a row (query_id, hits) has."""
    rows = answers.select("query_id", "hits").join(truth.where(~F.col("hit")).select("query_id"), "query_id")
    hit = [F.element_at("hits", i + 1) for i in range(n)]
    got = rows.agg(F.count(F.lit(1)).alias("negatives"), *[F.coalesce(F.sum(h.cast("long")), F.lit(0)).alias(f"f{i}") for i, h in enumerate(hit)], *[F.avg(h.cast("double")).alias(f"r{i}") for i, h in enumerate(hit)])
    return got.select("negatives", F.inline(F.array(*[F.struct(F.lit(i).alias("number"), F.col(f"f{i}").alias("false_hits"), F.col(f"r{i}").alias("fpr")) for i in range(n)]))).select("number", "negatives", "false_hits", "fpr")


def fpr_by(answers: DataFrame, truth: DataFrame, queries: DataFrame, group: str) -> DataFrame:
    """fpr_mt for each value of a column of the queries."""
    rows = answers.select("query_id", F.col("hit").alias("_a")).join(truth.select("query_id", "hit"), "query_id").join(queries.select("query_id", group), "query_id").where(~F.col("hit"))
    return rows.groupBy(group).agg(F.count(F.lit(1)).alias("negatives"), F.sum(F.col("_a").cast("long")).alias("false_hits"), F.avg(F.col("_a").cast("double")).alias("fpr"))


def fpr_msmt(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """(files, macro_fpr, pooled_fpr): mean of the files' rates, and the rate over all pairs; files without negatives do not count."""
    rows = answers.select("query_id", "file_id", F.col("hit").alias("_a")).join(truth.select("query_id", "file_id", "hit"), ["query_id", "file_id"]).where(~F.col("hit"))
    per = rows.groupBy("file_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("_a").cast("long")).alias("f"))
    return per.agg(F.count(F.lit(1)).alias("files"), F.avg(F.col("f") / F.col("n")).alias("macro_fpr"), (F.sum("f") / F.sum("n")).alias("pooled_fpr"))


def fpr_gram(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """The rate over single grams (query_id, pos, hit) against (query_id, pos, is_member)."""
    rows = answers.join(truth, ["query_id", "pos"]).where(~F.col("is_member"))
    return rows.agg(F.count(F.lit(1)).alias("negatives"), F.coalesce(F.sum(F.col("hit").cast("long")), F.lit(0)).alias("false_hits"), F.avg(F.col("hit").cast("double")).alias("fpr"))


def missed(answers: DataFrame, truth: DataFrame, keys=("query_id",)) -> DataFrame:
    """Members that were not reported; always empty for a filter."""
    return truth.where("hit").join(answers.where("hit"), list(keys), "left_anti")


def jaccard_by_gap(reads: DataFrame, k: int, t: int, gaps=(1, 2, 4, 8, 15, 16, 31), alphabet: str = "any") -> DataFrame:
    """(gap, pairs, mean_jaccard): similarity of the subgram sets of grams a gap apart in a read.

    alphabet `dna` says that all reads are over ACGT; with k up to 31 they then go through the Arrow kernel.
    """
    if alphabet == "dna" and k <= 31:
        got = reads.select("seq").mapInArrow(kernel.jaccard_builder(k, t, tuple(gaps)), "gap int, pairs bigint, total double")
        return got.groupBy("gap").agg(F.sum("pairs").alias("pairs"), (F.sum("total") / F.sum("pairs")).alias("mean_jaccard"))
    lists = reads.select(F.transform(grams.gram_array(F.col("seq"), k), lambda g: F.array_distinct(grams.gram_array(g, t))).alias("s"))
    pairs = lists.select("s", F.explode(F.array(*[F.lit(g) for g in gaps])).alias("gap")).where(F.size("s") > F.col("gap"))
    each = pairs.select("gap", F.explode(F.transform(F.slice("s", F.lit(1), F.size("s") - F.col("gap")), lambda x, i: grams.jaccard(x, F.get("s", i + F.col("gap"))))).alias("j"))
    return each.groupBy("gap").agg(F.count(F.lit(1)).alias("pairs"), F.avg("j").alias("mean_jaccard"))


def far_pair_zero_rate(seqs: DataFrame, k: int, t: int, per_seq: int = 4, seed: int = 3) -> DataFrame:
    """(file_id, pairs, zero_rate): share of pairs of grams at least k apart that share no subgram.

    Pairs are drawn by hash, per_seq from every sequence that has any; a sampling measure by nature.
    """
    from ..functions.hashing import md5_value

    n = F.length("seq") - (k - 1)
    rows = seqs.where(n > k).select("file_id", "seq", n.alias("n"), "seq_id", F.explode(F.sequence(F.lit(1), F.lit(per_seq))).alias("draw"))
    key = F.concat_ws("/", "seq_id", "draw")
    rows = rows.withColumn("a", F.pmod(md5_value(key, seed), F.col("n") - k).cast("int"))
    rows = rows.withColumn("b", F.col("a") + k + F.pmod(md5_value(key, seed + 1), F.col("n") - k - F.col("a")).cast("int"))
    subs = lambda at: grams.gram_array(F.substring("seq", F.col(at) + 1, F.lit(k)), t)
    return rows.groupBy("file_id").agg(F.count(F.lit(1)).alias("pairs"), F.avg((~F.arrays_overlap(subs("a"), subs("b"))).cast("double")).alias("zero_rate"))


def similar_count(reads: DataFrame, queries: DataFrame, k: int, t: int) -> DataFrame:
    """(query_id, most_similar): the most grams places that share a subgram with one gram of the query.

    A place of a subgram in the data lies in up to k - t + 1 grams; places are counted once per query gram
    through the starts of grams that hold them.
    """
    long_enough = reads.where(F.length("seq") >= k)  # a shorter one has no gram, and sequence() below would count down
    data = long_enough.select("seq_id", "read_no", F.length("seq").alias("n"), F.posexplode(grams.gram_array(F.col("seq"), t)).alias("at", "sub"))
    q = grams.explode_grams(queries.select("query_id", "seq"), "seq", k).select("query_id", "pos", F.explode(F.array_distinct(grams.gram_array(F.col("gram"), t))).alias("sub"))
    met = q.join(data, "sub").select("query_id", "pos", "seq_id", "read_no", F.explode(F.sequence(F.greatest(F.col("at") - (k - t), F.lit(0)), F.least(F.col("at"), F.col("n") - k))).alias("gram_at"))
    per = met.distinct().groupBy("query_id", "pos").agg(F.count(F.lit(1)).alias("c"))
    return per.groupBy("query_id").agg(F.max("c").alias("most_similar"))


def locality(trace: DataFrame, by=("query_id",), bits: int = PAGE_BITS) -> DataFrame:
    """(accesses, distinct_blocks, changes, blocks_per_access, changes_per_access) of a trace (by, pos, rep, bit).

    A block is a run of `bits` bits; a change is an access of another block than the one before it, of the
    same function, in the order of the grams.
    """
    block = F.call_function("div", F.col("bit"), F.lit(bits).cast("long"))
    rows = trace.withColumn("_b", block)
    w = Window.partitionBy(*by, "rep").orderBy("pos", "bit")
    changed = rows.withColumn("_c", F.coalesce((F.lag("_b").over(w) != F.col("_b")).cast("long"), F.lit(1)))
    per = changed.groupBy(*by, "rep").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("_b").alias("d"), F.sum("_c").alias("c"))
    total = per.agg(F.sum("n").alias("accesses"), F.sum("d").alias("distinct_blocks"), F.sum("c").alias("changes"))
    return total.withColumn("blocks_per_access", F.col("distinct_blocks") / F.col("accesses")).withColumn("changes_per_access", F.col("changes") / F.col("accesses"))


def probe_locality(queries: DataFrame, spec, bits: int = PAGE_BITS) -> DataFrame:
    """locality() of the probes of queries (seq), a query a row, counted where the positions are made: no access is
    shuffled. Needs the Arrow kernel."""
    return _summed(queries, [spec], [bits], [])


def probe_localities(queries: DataFrame, specs: list, blocks: list[int]) -> DataFrame:
    """(number, block, ...): probe_locality for the number of each spec and each size of a block, in one pass over the queries."""
    return _summed(queries, specs, blocks, ["number", "block"])


def _summed(queries: DataFrame, specs: list, blocks: list[int], by: list[str]) -> DataFrame:
    got = queries.select("seq").mapInArrow(kernel.locality_builder(specs, blocks), "number int, block int, accesses bigint, distinct_blocks bigint, changes bigint")
    counted = ["accesses", "distinct_blocks", "changes"]
    total = got.groupBy(*by).agg(*[F.sum(F.when(F.col("accesses") > 0, F.col(c))).alias(c) for c in counted])  # no accesses: null
    return total.withColumn("blocks_per_access", F.col("distinct_blocks") / F.col("accesses")).withColumn("changes_per_access", F.col("changes") / F.col("accesses"))


def index_size(index: DataFrame, m: int, filters: int) -> DataFrame:
    """(stored_pages, stored_bytes, nominal_bytes) of filter pages."""
    return index.agg(F.count(F.lit(1)).alias("stored_pages"), F.coalesce(F.sum(F.length("bits")), F.lit(0)).cast("long").alias("stored_bytes")).withColumn("nominal_bytes", F.lit(m * filters // 8).cast("long"))


def collision_rate(df: DataFrame, key: str, value) -> DataFrame:
    """(keys, pairs, colliding, rate): share of pairs of distinct keys with one value."""
    groups = df.select(key, value.alias("_v")).distinct().groupBy("_v").agg(F.count(F.lit(1)).alias("c"))
    got = groups.agg(F.sum("c").alias("keys"), F.sum(F.expr("c * (c - 1) div 2")).alias("colliding"))
    pairs = F.expr("keys * (keys - 1) div 2")
    return got.select("keys", pairs.alias("pairs"), "colliding", (F.col("colliding") / pairs).alias("rate"))


def gram_collision_rate(reads: DataFrame, k: int, seed: int, m: int, parts: int = 512) -> DataFrame:
    """collision_rate of the distinct grams of reads (seq) over ACGT, k up to 31, under md5 values in [0, m): grams travel
    in runs, and what leaves a task is a counter a value, whatever the number of its grams."""
    known = reads.select(F.lit(0).cast("long").alias("id"), "seq").mapInArrow(runs.builder(k, 1, parts), runs.SCHEMA)
    counts = known.repartition("part").sortWithinPartitions("part").mapInArrow(runs.counter(k, seed, m), runs.COUNTS)
    blocks = counts.repartition("block").sortWithinPartitions("block").mapInArrow(runs.collisions, "keys bigint, colliding bigint")
    got = blocks.agg(F.sum("keys").alias("keys"), F.sum("colliding").alias("colliding"))
    pairs = F.expr("keys * (keys - 1) div 2")
    return got.select("keys", pairs.alias("pairs"), "colliding", (F.col("colliding") / pairs).alias("rate"))


def sensitivity(pairs: DataFrame, distance, same, bands: int = 10, top: float = 2.0) -> DataFrame:
    """(band, pairs, collision): share of pairs that collide, by band of distance."""
    band = F.least(F.floor(distance / F.lit(top / bands)), F.lit(bands - 1)).cast("int")
    return pairs.groupBy(band.alias("band")).agg(F.count(F.lit(1)).alias("pairs"), F.avg(same.cast("double")).alias("collision"))


def preservation(pairs: DataFrame, distance, x, y, L: int, bands: int = 10, top: float = 2.0) -> DataFrame:
    """(band, pairs, close_distinct, close): estimates of the near and far chances of an anchored family."""
    band = F.least(F.floor(distance / F.lit(top / bands)), F.lit(bands - 1)).cast("int")
    gap = F.abs(x - y)
    return pairs.groupBy(band.alias("band")).agg(F.count(F.lit(1)).alias("pairs"), F.avg(((gap > 0) & (gap < L)).cast("double")).alias("close_distinct"), F.avg((gap < L).cast("double")).alias("close"))


def timed(df: DataFrame, runs: int = 1) -> dict[str, float]:
    """Seconds to compute df without output: mean and spread over the runs."""
    took = []
    for _ in range(runs):
        began = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - began)
    return {"mean": statistics.fmean(took), "spread": statistics.stdev(took) if runs > 1 else 0.0, "runs": runs}


def growth(points: DataFrame, size="m", value="seconds") -> DataFrame:
    """(slope, intercept) of a measure over the binary logarithm of the size."""
    return points.agg(F.regr_slope(F.col(value), F.log2(F.col(size))).alias("slope"), F.regr_intercept(F.col(value), F.log2(F.col(size))).alias("intercept"))


def pareto(points: DataFrame, cost="seconds", rate="fpr") -> DataFrame:
    """Points that no other beats: best cost at their rate or less."""
    w = Window.orderBy(rate, cost).rowsBetween(Window.unboundedPreceding, -1)
    return points.withColumn("_best", F.min(cost).over(w)).where(F.col("_best").isNull() | (F.col(cost) < F.col("_best"))).drop("_best")


def compare(base: float, other: float) -> dict[str, float]:
    """Relative reduction and speed-up of other against base."""
    return {"reduction": 1 - other / base, "speed_up": base / other}
