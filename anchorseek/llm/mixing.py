"""Mixing sources to target weights: hash-random order within each source, distributed prefix sums, exact cut.

Each document gets a hash-random key. Within a source the documents stand in key order, dealt over key
ranges whose number follows the source's rows, so no task holds a whole source. Sums per range and a
running sum over the ranges give every document its place; a source takes whole passes over its documents
while its budget lasts and cuts the last pass at the budget, inside one document if need be.

Defined results: null text has size 0 and is never taken; a null source is a source of its own, ranked
last; equal rows share one key and get equal shares; an empty table gives an empty result; columns other
than those named are carried along untouched.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, settled, words_of

ROWS_PER_RANGE = 4096
#: Sources up to this number are broadcast; with more, the join is left to Spark.
BROADCAST_SOURCES = 20_000


def size_of(text):
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def _source_key(source):
    return F.coalesce(F.concat(F.lit("s"), source), F.lit("n"))


def _order_key(doc_id, text, seed: int):
    return F.md5(
        F.concat_ws("|", F.lit(str(seed)), F.coalesce(doc_id.cast("string"), F.lit("")), F.md5(F.coalesce(text, F.lit(""))))
    )


def source_targets(sized: DataFrame, weights, share: float, cap: float) -> DataFrame:
    """(_src, source_size, n_rows, target): weights repeat over the sources by code point, null last.

    A target stops at cap times its source's size; the excess goes to the others by weight. In order of
    cap * size / weight the capped sources come first, so running sums find the final level at once.
    """
    per = sized.groupBy("_src").agg(
        F.first("_source").alias("_source"), F.sum("_size").alias("source_size"), F.count(F.lit(1)).alias("n_rows")
    )
    rank = F.row_number().over(Window.orderBy(F.col("_source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (rank % len(weights) + 1).cast("int"))
    per = per.withColumn("_w", weight).withColumn("_cap", F.lit(float(cap)) * F.col("source_size"))
    everything = Window.partitionBy()
    by_ratio = Window.orderBy(F.col("_cap") / F.col("_w"), F.col("_src"))
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    per = (
        per.withColumn("_total", F.sum("source_size").over(everything) * F.lit(float(share)))
        .withColumn("_cap_before", F.coalesce(F.sum("_cap").over(before), F.lit(0.0)))
        .withColumn("_w_left", F.sum("_w").over(everything) - F.coalesce(F.sum("_w").over(before), F.lit(0.0)))
        .withColumn("_level", (F.col("_total") - F.col("_cap_before")) / F.col("_w_left"))
        .withColumn("_open", F.when(F.col("_cap") > F.col("_level") * F.col("_w"), F.col("_level")))
        .withColumn("_fill", F.first("_open", ignorenulls=True).over(by_ratio.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    )
    target = F.coalesce(F.least(F.col("_cap"), F.col("_fill") * F.col("_w")), F.col("_cap"))
    return per.select("_src", "source_size", "n_rows", target.alias("target"))


def _small(per_source: DataFrame) -> DataFrame:
    """Broadcast a settled table of one row a source, if it is small."""
    return F.broadcast(per_source) if per_source.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES else per_source


def _cutoffs(sized: DataFrame, targets: DataFrame) -> DataFrame:
    """One row per source: full passes, the key at which the last pass ends, and each key holder's share there."""
    budget = F.floor(F.col("target") + 1e-6).cast("long")
    full = F.when(F.col("source_size") > 0, ((budget - budget % F.col("source_size")) / F.col("source_size"))).otherwise(0).cast("long")
    plan = settled(
        targets.withColumn("_full", full)
        .withColumn("_rest", F.greatest(budget - F.col("_full") * F.col("source_size"), F.lit(0)).cast("long"))
        .withColumn("_ranges", F.ceil(F.col("n_rows") / ROWS_PER_RANGE).cast("long")),
        "mix-plan",
    )
    grouped = sized.groupBy("_src", "_key").agg(F.sum("_size").alias("_size"), F.count(F.lit(1)).alias("_same"))
    place = F.floor(F.conv(F.substring("_key", 1, 8), 16, 10).cast("double") / float(1 << 32) * F.col("_ranges"))
    ranged = grouped.join(_small(plan), "_src").withColumn("_range", place.cast("long"))
    sums = ranged.groupBy("_src", "_range").agg(F.sum("_size").alias("_range_size"))
    running = Window.partitionBy("_src").orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.withColumn("_start", F.coalesce(F.sum("_range_size").over(running), F.lit(0)))
    within = Window.partitionBy("_src", "_range").orderBy("_key").rowsBetween(Window.unboundedPreceding, -1)
    placed = (
        ranged.join(starts, ["_src", "_range"])
        .where((F.col("_start") <= F.col("_rest")) & (F.col("_start") + F.col("_range_size") >= F.col("_rest")))
        .withColumn("_before", F.col("_start") + F.coalesce(F.sum("_size").over(within), F.lit(0)))
    )
    cut = (
        placed.where((F.col("_before") < F.col("_rest")) & (F.col("_before") + F.col("_size") >= F.col("_rest")))
        .select("_src", F.col("_key").alias("_cut"), F.floor((F.col("_rest") - F.col("_before")) / F.col("_same")).cast("long").alias("_part"))
    )
    return plan.join(cut, "_src", "left").select("_src", "source_size", "target", "_full", "_cut", "_part")


def with_taken(docs: DataFrame, doc_id="doc_id", text="text", source="source", weights=(5, 2, 1), share=1.0, cap=3.0, seed=42, carry=None) -> DataFrame:
    """docs (or the columns in carry) with size, source_size, target and taken, in place of columns of these names.

    taken: words that the mix takes of the document, repeats counted; at most ceil(cap) times its size.
    """
    spark = docs.sparkSession
    parts = {
        "_src": _source_key(F.col(source)),
        "_key": _order_key(F.col(doc_id), F.col(text), seed),
        "_size": size_of(F.col(text)),
    }
    narrow = settled(
        docs.select(F.col(source).alias("_source"), *[c.alias(n) for n, c in parts.items()], *[F.col(c).alias(f"_c_{c}") for c in carry or []]),
        "mix-sizes",
    )
    cutoffs = settled(_cutoffs(narrow.select("_source", *parts), source_targets(narrow, weights, share, cap)), "mix-cutoffs")
    if carry is None:
        kept = [c for c in docs.columns if c not in ("size", "source_size", "target", "taken")]
        rows = docs.select(F.struct(*docs.columns).alias("_kept"), *[c.alias(n) for n, c in parts.items()])
    else:
        kept = list(carry)
        rows = narrow.select(F.struct(*[F.col(f"_c_{c}").alias(c) for c in carry]).alias("_kept"), *parts)
    last = F.when(F.col("_cut").isNull() | (F.col("_key") > F.col("_cut")), F.lit(0)).when(F.col("_key") == F.col("_cut"), F.least(F.col("_part"), F.col("_size"))).otherwise(F.col("_size"))
    return rows.join(_small(cutoffs), "_src").select(
        *[F.col(f"_kept.`{c}`").alias(c) for c in kept],
        F.col("_size").alias("size"),
        "source_size",
        "target",
        (F.col("_full") * F.col("_size") + last).cast("long").alias("taken"),
    )


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each document once per pass that takes it whole; the document at the cut keeps its first words."""
    columns, text = docs.columns, options.get("text", "text")
    inner = docs.select(F.struct("*").alias("_row"), *[F.col(options.get(n, n)).alias(f"_{n}_in") for n in ("doc_id", "text", "source")])
    taken = with_taken(inner, **{**options, "doc_id": "_doc_id_in", "text": "_text_in", "source": "_source_in"})
    whole = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.col("size"))).otherwise(0).cast("int")
    part = (F.col("taken") - F.col("_n") * F.col("size")).cast("int")
    copies = F.when(F.col("_n") > 0, F.array_repeat(F.lit(0), F.col("_n"))).otherwise(F.array().cast("array<int>"))
    out = (
        taken.withColumn("_n", whole)
        .withColumn("_words", F.explode(F.concat(copies, F.when(part > 0, F.array(part)).otherwise(F.array().cast("array<int>")))))
    )
    cut = F.when(F.col("_words") > 0, F.array_join(F.slice(words_of(F.col("_text_in")), 1, F.col("_words")), " ")).otherwise(F.col("_text_in"))
    return out.select(*[cut.alias(c) if c == text else F.col(f"_row.`{c}`").alias(c) for c in columns])


def op9_mix(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return with_taken(table(spark, sf_dir, "documents"), carry=["doc_id"])


OP9_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         md5('42|' || coalesce(doc_id::VARCHAR, '') || '|' || md5(coalesce(text, ''))) AS k
  FROM documents),
per AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
weighed AS (SELECT *, 3.0 * source_size AS cap,
    [5.0, 2.0, 1.0][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS w FROM per),
levels AS (SELECT *, (sum(source_size) OVER () - coalesce(sum(cap) OVER b, 0)) / (sum(w) OVER () - coalesce(sum(w) OVER b, 0)) AS level,
    row_number() OVER (ORDER BY cap / w, source NULLS LAST) AS r
  FROM weighed WINDOW b AS (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
fill AS (SELECT arg_min(level, r) AS f FROM levels WHERE cap > level * w),
targets AS (SELECT source, source_size, coalesce(least(cap, f * w), cap)::DOUBLE AS target FROM levels LEFT JOIN fill ON true),
budget AS (SELECT *, floor(target + 1e-6)::BIGINT AS b FROM targets),
plan AS (SELECT *, CASE WHEN source_size > 0 THEN b // source_size ELSE 0 END AS passes FROM budget),
placed AS (SELECT s.doc_id, s.size, p.source_size, p.target, p.passes, p.b - p.passes * p.source_size AS rest,
    coalesce(sum(s.size) OVER (PARTITION BY s.source ORDER BY s.k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before
  FROM sized s JOIN plan p ON s.source IS NOT DISTINCT FROM p.source)
SELECT doc_id, size, source_size, target, (passes * size + greatest(0, least(size, rest - before)))::BIGINT AS taken FROM placed
"""
