r"""Quality rules with risk-controlled thresholds, in DataFrame functions only.

Each rule compares one measure of a text with a cutoff. All rules of a stratum are tightened along one path of
steps (grid column by column from lenient to strict, rules in their order): a step sets one rule to one cutoff.
Where the stratum has bad labelled documents, the path holds only the steps that reject one of them which no
step before rejects; the good ones have no part in its choice. Then the path is tested on the stratum's good
labelled documents: a step passes while the exact binomial tail P(Bin(n, risk) <= k) stays at or below the
level, k of n being rejected by any rule as set so far (that is, while the exact upper confidence bound of the
false rejection rate of all rules together is at most the risk). Testing in a fixed order needs no correction
along the path, so the level is divided over the strata only and the risk not at all: with the stated
confidence, in every stratum at once, at most `risk` of the good documents are rejected. A stratum needs
ln(level / strata) / ln(1 - risk) good labels at least; with fewer it gets no cutoff and rejects nothing.

Defined results: null text has no words and fails the base rule; a null stratum is a stratum; labels with a
null doc_id or quality are ignored, and of contradicting labels the good one counts; repeated documents each
get a row; without labels nothing but the base rule rejects.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import bind, settled, table, words_of

#: Characters that count as symbols, white space of the contract.
SYMBOLS = "#*$%&|<>"
WHITE = " \t\n\x0b\f\r"
WINDOW = 5

_SHARES = (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.1, 0.05)
#: Rules: measure -> cutoffs from lenient to strict; a document fails where its measure is above the cutoff.
GRID = {
    "symbols_per_word": (4.0, 3.0, 2.0, 1.5, 1.0, 0.75, 0.5, 0.35, 0.25, 0.15, 0.1, 0.05),
    "bangs_per_word": (4.0, 3.0, 2.0, 1.5, 1.0, 0.75, 0.5, 0.35, 0.25, 0.15, 0.1, 0.05),
    "dup_line_share": _SHARES,
    "repeat_share": _SHARES,
    "capital_share": _SHARES,
    "word_length": (60.0, 45.0, 35.0, 30.0, 25.0, 20.0, 17.0, 15.0, 13.0, 12.0, 11.0, 10.0),
}
RISK = 0.02
LEVEL = 0.05


def _count_of(text, characters: str):
    return (F.length(text) - F.length(F.translate(text, characters, ""))).cast("long")


def repeat_words(words, width: int = WINDOW):
    """Words inside windows of `width` words that stand twice or more in the text, the first included."""

    def covered(hashes):
        marked = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        twice = bind(
            marked,
            lambda s: F.filter(s, lambda x, j: (F.get(s, j - 1)["h"] == x["h"]) | F.coalesce(F.get(s, j + 1)["h"] == x["h"], F.lit(False))),
        )
        places = F.sort_array(F.transform(twice, lambda x: x["i"]))
        return bind(
            places,
            lambda p: F.aggregate(
                F.transform(p, lambda at, j: F.least(F.lit(width), F.coalesce(F.get(p, j + 1) - at, F.lit(width)))),
                F.lit(0).cast("long"),
                lambda a, b: a + b,
            ),
        )

    positions = F.when(F.size(words) >= width, F.sequence(F.lit(0), F.size(words) - width)).otherwise(F.array().cast("array<int>"))
    hashes = F.transform(positions, lambda i: F.xxhash64(*[F.get(words, i + d) for d in range(width)]))
    return bind(hashes, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(covered(h)))


def measured(docs: DataFrame, text="text", carry=("doc_id",), stratum=None) -> DataFrame:
    """carry, _stratum, counts and measures of every document."""
    t = F.coalesce(F.col(text), F.lit(""))
    lines = F.filter(F.split(t, "\n"), lambda x: F.trim(x, F.lit(WHITE)) != F.lit(""))
    line_counts = bind(lines, lambda x: F.struct(F.size(x).cast("long").alias("n"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("dup")))
    word_counts = bind(words_of(t), lambda w: F.struct(F.size(w).cast("long").alias("n"), repeat_words(w).alias("rep")))
    counts = docs.select(
        *carry,
        (F.col(stratum).cast("string") if stratum else F.lit(None).cast("string")).alias("_stratum"),
        word_counts.alias("_w"),
        line_counts.alias("_l"),
        F.length(F.translate(t, WHITE, "")).cast("long").alias("word_chars"),
        _count_of(t, SYMBOLS).alias("n_symbols"),
        _count_of(t, "!").alias("_bangs"),
        F.regexp_count(t, F.lit("[A-Z]")).cast("long").alias("_capitals"),
    )

    def over(a, b):
        return F.when(b > 0, a / b).otherwise(F.lit(0.0))

    words, lines_n = F.col("_w.n"), F.col("_l.n")
    return counts.select(
        *carry,
        "_stratum",
        words.alias("n_words"),
        "word_chars",
        "n_symbols",
        F.col("_l.dup").alias("n_dup_lines"),
        F.col("_w.rep").alias("n_repeat_words"),
        ((words < 10) | (100 * F.col("_w.rep") > 20 * words)).alias("base_failed"),
        over(F.col("n_symbols"), words).alias("symbols_per_word"),
        over(F.col("_bangs"), words).alias("bangs_per_word"),
        over(F.col("_l.dup"), lines_n).alias("dup_line_share"),
        over(F.col("_w.rep"), words).alias("repeat_share"),
        over(F.col("_capitals"), F.col("word_chars")).alias("capital_share"),
        over(F.col("word_chars"), words).alias("word_length"),
    )


def binomial_tail(k, n, p: float):
    """P(Bin(n, p) <= k), summed in logarithms; 1 where k is above the mean (it is then above any useful level)."""
    import math

    odds, first = math.log(p / (1 - p)), n * math.log1p(-p)

    def step(acc, i):
        term = acc["term"] + F.log((n - i + 1) / i) + odds
        high = F.greatest(acc["sum"], term)
        return F.struct(term.alias("term"), (high + F.log(F.exp(acc["sum"] - high) + F.exp(term - high))).alias("sum"))

    start = F.struct(first.cast("double").alias("term"), first.cast("double").alias("sum"))
    steps = F.when(k > 0, F.sequence(F.lit(1).cast("long"), k.cast("long"))).otherwise(F.array().cast("array<bigint>"))
    return F.when(k > n * p, F.lit(1.0)).otherwise(F.exp(F.aggregate(steps, start, step)["sum"]))


def thresholds(holdout: DataFrame, grid=None, risk=RISK, level=LEVEL) -> DataFrame:
    """(_stratum, rule, cutoff, n_good, n_rejected, n_bad, n_bad_rejected), a row a rule with a cutoff.

    holdout: measures, _stratum and _good of labelled documents. The counts are those of the whole stratum; the
    rejected ones are those that fail any of its rules.
    """
    grid = GRID if grid is None else grid
    if not all(list(c) == sorted(c, reverse=True) for c in grid.values()):
        raise ValueError("cutoffs go from lenient to strict")
    steps = [(i, r, float(cs[i])) for i in range(max(map(len, grid.values()))) for r, cs in grid.items() if i < len(cs)]
    every = F.array(*[F.struct(F.lit(n).alias("step"), F.lit(r).alias("rule"), F.lit(c).alias("cutoff")) for n, (_, r, c) in enumerate(steps)])
    fails = F.array_compact(F.array(*[F.when(F.col(r) > c, F.lit(n)) for n, (_, r, c) in enumerate(steps)]))
    # documents that fail the same steps are counted before anything is joined
    rows = holdout.groupBy(F.struct("_stratum").alias("_s"), "_good", fails.alias("fails")).agg(F.count(F.lit(1)).alias("n"))
    of = lambda good: F.sum(F.when(F.col("_good") == good, F.col("n")).otherwise(0))
    sizes = rows.groupBy("_s").agg(of(True).alias("n_good"), of(False).alias("n_bad")).where("n_good > 0")
    # the first step that rejects a bad document, were all steps on the path
    firsts = rows.where(~F.col("_good")).groupBy("_s").agg(F.collect_set(F.get("fails", F.lit(0))).alias("firsts"))
    path = F.when(F.col("n_bad") > 0, F.array_sort("firsts")).otherwise(F.array(*[F.lit(n) for n in range(len(steps))]))
    paths = sizes.join(firsts, "_s", "left").select("_s", "n_good", "n_bad", path.alias("path"))
    met = rows.join(paths.select("_s", "path"), "_s").select("_s", "_good", "n", F.array_min(F.array_intersect("fails", "path")).alias("step"))
    at = met.where("step IS NOT NULL").groupBy("_s", "step").agg(of(True).alias("good"), of(False).alias("bad"))
    in_order = Window.partitionBy("_s").orderBy("step")
    told = (
        paths.select("_s", "n_good", "n_bad", F.explode("path").alias("step"))
        .join(at, ["_s", "step"], "left")
        .withColumn("n_rejected", F.sum(F.coalesce("good", F.lit(0))).over(in_order))
        .withColumn("n_bad_rejected", F.sum(F.coalesce("bad", F.lit(0))).over(in_order))
        .crossJoin(F.broadcast(sizes.agg(F.count(F.lit(1)).alias("_strata"))))  # one row
        .withColumn("_worst", F.max(binomial_tail(F.col("n_rejected"), F.col("n_good"), risk)).over(in_order))
        .where(F.col("_worst") <= F.lit(level) / F.col("_strata"))
        .withColumn("_set", F.element_at(every, F.col("step") + 1))
    )
    whole = Window.partitionBy("_s")
    return (
        told.withColumn("n_rejected", F.max("n_rejected").over(whole))
        .withColumn("n_bad_rejected", F.max("n_bad_rejected").over(whole))
        .groupBy("_s", F.col("_set.rule").alias("rule"), "n_good", "n_rejected", "n_bad", "n_bad_rejected")
        .agg(F.min("_set.cutoff").alias("cutoff"))
        .select("_s._stratum", "rule", "cutoff", "n_good", "n_rejected", "n_bad", "n_bad_rejected")
    )


def labelled(rows: DataFrame, labels: DataFrame, doc_id="doc_id", quality="quality") -> DataFrame:
    """Measures of the labelled documents that pass the base rule, and _good. Rows with one id count once, as the
    binomial asks for: the smallest by stratum and measures."""
    known = labels.where(F.col(doc_id).isNotNull() & F.col(quality).isNotNull()).groupBy(F.col(doc_id).alias("doc_id")).agg((F.max(quality) == 1).alias("_good"))
    some = rows.where(~F.col("base_failed")).join(known, "doc_id")
    rest = [c for c in some.columns if c != "doc_id"]
    return some.groupBy("doc_id").agg(F.min(F.struct(*rest)).alias("_row")).select("doc_id", "_row.*")


def judged(docs: DataFrame, labels: DataFrame, text="text", doc_id="doc_id", stratum="lang", quality="quality", grid=None, risk=RISK, level=LEVEL) -> DataFrame:
    """One row a document: counts, measures, base_failed, reasons (rules that reject it) and kept."""
    grid = GRID if grid is None else grid
    rows = settled(measured(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("_text"), F.col(stratum).alias("_lang")), "_text", ["doc_id"], "_lang"), "quality-measures")
    holdout = labelled(rows, labels, doc_id, quality)
    chosen = settled(thresholds(holdout, grid, risk, level), "quality-thresholds").groupBy("_stratum").agg(F.map_from_entries(F.collect_list(F.struct("rule", "cutoff"))).alias("_cut")).select(F.struct("_stratum").alias("_s"), "_cut")
    failed = F.array_compact(F.array(*[F.when(F.col(r) > F.col("_cut")[r], F.lit(r)) for r in grid]))
    return (
        rows.withColumn("_s", F.struct("_stratum"))
        .join(F.broadcast(chosen) if _few(chosen) else chosen, "_s", "left")
        .withColumn("reasons", F.coalesce(failed, F.array().cast("array<string>")))
        .withColumn("kept", ~F.col("base_failed") & (F.size("reasons") == 0))
        .drop("_s", "_cut")
    )


def _few(strata: DataFrame, most: int = 10_000) -> bool:
    return strata.limit(most + 1).count() <= most


def op2_quality(spark, sf_dir: str) -> DataFrame:
    got = judged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return got.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.array_join("reasons", ",").alias("reasons"))
