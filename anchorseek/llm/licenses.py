r"""License scan by diagonal voting, in DataFrame functions only.

Every text's rolling word k-gram hashes are looked up among those of the templates, where the text is read, and
what is found is joined (broadcast: the templates are a fixed list) with the positions of the grams in the
templates, by hash and wording. A match at text word p and template word q votes for the diagonal p - q. A base
phrase stands where one diagonal has the votes of all the phrase's k-grams. For the longer templates
neighbouring diagonals are merged, which bridges inserted or missing words, and a span counts if enough of the
template's k-grams stand inside a span not much longer than the template, and the words in brackets, which tell
it from its relatives, stand together word for word. Of spans that overlap, the one with the best cover counts,
then the one of the longer template, then the first.

Defined results: null or empty text has no words, no place and no label; repeated documents each get a row
and equal ones are counted once; a text may hold any number of places.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import bind, settled, table, words_of

K = 2
#: Base phrases and their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Wordings of common licences and their labels; words in brackets must stand as they are.
TEMPLATES = [
    ("released under the [mit license]", "mit"),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software", "mit"),
    ("licensed under the [apache license version 2 0]", "apache-2.0"),
    ("[apache license 2 0]", "apache-2.0"),
    ("you may not use this file except in compliance with the license", "apache-2.0"),
    ("redistribution and use in source and binary forms with or without modification are permitted", "bsd"),
    ("[general public license version 3]", "gpl-3.0"),
    ("[general public license version 2]", "gpl-2.0"),
    ("[lesser general public license]", "lgpl"),
    ("[lesser general public license version 2 1]", "lgpl-2.1"),
    ("[lesser general public license version 3]", "lgpl-3.0"),
    ("[affero general public license]", "agpl"),
    ("[affero general public license version 3]", "agpl-3.0"),
    ("[mozilla public license version 2 0]", "mpl-2.0"),
    ("[cc by 4 0]", "cc-by-4.0"),
    ("[cc by nc 4 0]", "cc-by-nc-4.0"),
    ("[cc by sa 4 0]", "cc-by-sa-4.0"),
    ("[cc by nd 4 0]", "cc-by-nd-4.0"),
    ("[cc by nc sa 4 0]", "cc-by-nc-sa-4.0"),
    ("[cc by nc nd 4 0]", "cc-by-nc-nd-4.0"),
    ("[creative commons attribution noncommercial]", "cc-by-nc"),
    ("this is free and unencumbered software released into the public domain", "unlicense"),
    ("permission to use copy modify and or distribute this software for any purpose", "isc"),
]
#: What stands between words.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
COVER = 0.75
#: How far apart neighbouring diagonals may lie, and how much longer than its template a span may be.
DRIFT = 2


def lowered(text):
    """A-Z lowered. lower() does it, except where it would make ASCII letters of others (K sign, dotted I)."""
    from .common import lower_ascii

    return F.when(text.rlike("[Kİ]"), lower_ascii(text)).otherwise(F.lower(text))


def _wordings(text: str) -> tuple[list[str], set[int]]:
    """(words of a template, numbers of the k-grams whose words stand in brackets)."""
    words, inside, held = [], False, []
    for w in text.replace("[", " [ ").replace("]", " ] ").split():
        if w in "[]":
            inside = w == "["
        else:
            words.append(w)
            held.append(inside)
    return words, {q for q in range(len(words) - K + 1) if all(held[q : q + K])}


def template_positions(spark, templates) -> DataFrame:
    """(_h, _gram, _tpl, _q, _must, _musts, _grams, _label, _base) of every k-gram of every template."""
    rows = []
    for i, (text, label, base) in enumerate(templates):
        words, must = _wordings(text)
        if len(words) < K:
            raise ValueError(f"a template has at least {K} words")
        n = len(words) - K + 1
        rows += [(" ".join(words[q : q + K]), i, q, q in must, len(must), n, label, base) for q in range(n)]
    df = spark.createDataFrame(rows, "_gram string, _tpl int, _q int, _must boolean, _musts int, _grams int, _label string, _base boolean")
    return df.withColumn("_h", bind(F.split("_gram", " "), lambda w: _gram_hash(w, F.lit(0))))


def _gram_hash(words, i):
    return F.xxhash64(*[F.get(words, i + d) for d in range(K)])


def _found(words, hashes: list[int]):
    """(n, grams): number of words; place, hash and wording of the k-grams whose hash a template has."""
    starts = F.when(F.size(words) >= K, F.sequence(F.lit(0), F.size(words) - K)).otherwise(F.array().cast("array<int>"))
    met = F.filter(starts, lambda i: _gram_hash(words, i).isin(hashes)) if hashes else F.array().cast("array<int>")
    told = lambda i: F.struct(i.alias("p"), _gram_hash(words, i).alias("h"), F.array_join(F.slice(words, i + 1, F.lit(K)), " ").alias("g"))
    return F.struct(F.size(words).cast("long").alias("n"), F.transform(met, told).alias("grams"))


def _best(spans: DataFrame, key: list[str]) -> DataFrame:
    """Of overlapping spans those that count, one after another from the best on."""
    in_order = Window.partitionBy(*key).orderBy("_first", "_last", "_tpl")
    reach = F.max("_last").over(in_order.rowsBetween(Window.unboundedPreceding, -1))
    lone = spans.withColumn("_new", F.when(F.coalesce(F.col("_first") > reach, F.lit(True)), 1).otherwise(0)).withColumn("_island", F.sum("_new").over(in_order))
    one = F.struct((-F.col("_cover")).alias("worse"), (-F.col("_grams")).alias("shorter"), F.col("_first").alias("first"), F.col("_last").alias("last"), F.col("_label").alias("label"))
    ranked = F.array_sort(F.collect_set(one))
    free = lambda kept, x: ~F.exists(kept, lambda y: (y["first"] <= x["last"]) & (x["first"] <= y["last"]))
    chosen = lone.groupBy(*key, "_island").agg(ranked.alias("r")).select(*key, F.explode(F.aggregate("r", F.slice("r", 1, 0), lambda kept, x: F.when(free(kept, x), F.concat(kept, F.array(x))).otherwise(kept))).alias("s"))
    return chosen.select(*key, F.lit(False).alias("_base"), F.col("s.label").alias("_label"), F.col("s.first").alias("_first"), F.col("s.last").alias("_last"), (-F.col("s.worse")).alias("_cover"))


def scanned(docs: DataFrame, text="text", doc_id="doc_id", base=None, templates=None, cover=COVER, drift=DRIFT) -> DataFrame:
    """(doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans) of every document."""
    spark = docs.sparkSession
    base, templates = BASE if base is None else base, TEMPLATES if templates is None else templates
    known = template_positions(spark, [(p, x, True) for p, x in base.items()] + [(t, x, False) for t, x in templates])
    hashes = sorted({r[0] for r in known.select("_h").collect()})  # those of the fixed list
    words = words_of(lowered(F.coalesce(F.col(text), F.lit(""))), BETWEEN)
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.xxhash64(text).alias("_k"), bind(words, lambda w: _found(w, hashes)).alias("_w"))
    rows = settled(rows.select("doc_id", "_k", F.col("_w.n").alias("n_words"), F.col("_w.grams").alias("_grams")), "licence-grams")
    key = ["doc_id", "_k"]
    votes = (
        rows.select(*key, F.explode("_grams").alias("_m")).select(*key, F.col("_m.p").alias("_p"), F.col("_m.h").alias("_h"), F.col("_m.g").alias("_gram"))
        .join(F.broadcast(known), ["_h", "_gram"])
        .withColumn("_d", F.col("_p") - F.col("_q"))
    )
    diagonals = votes.groupBy(*key, "_tpl", "_label", "_base", "_grams", "_musts", "_d").agg(
        F.collect_set("_q").alias("_qs"), F.size(F.collect_set(F.when(F.col("_must"), F.col("_q")))).alias("_together"), F.min("_p").alias("_first"), F.max("_p").alias("_last")
    )
    along = Window.partitionBy(*key, "_tpl").orderBy("_d")
    whole = F.size("_qs") == F.col("_grams")
    # diagonals within reach of each other and close in the text are one span; a complete diagonal is one by itself
    fresh = (F.col("_d") - F.lag("_d").over(along) > drift) | (F.col("_first") - F.lag("_first").over(along) > F.col("_grams") + drift)
    merged = (
        diagonals.withColumn("_whole", whole)
        .withColumn("_start", F.when(F.coalesce(fresh, F.lit(True)) | F.col("_whole") | F.coalesce(F.lag("_whole").over(along), F.lit(False)), 1).otherwise(0))
        .withColumn("_group", F.sum("_start").over(along))
        .groupBy(*key, "_tpl", "_label", "_base", "_grams", "_musts", "_group")
        .agg(F.size(F.array_distinct(F.flatten(F.collect_list("_qs")))).alias("_votes"), F.max("_whole").alias("_whole"), F.max("_together").alias("_together"), F.min("_first").alias("_first"), (F.max("_last") + K - 1).alias("_last"))
        .withColumn("_cover", F.col("_votes") / F.col("_grams"))
    )
    long_enough = (F.col("_cover") >= cover) & (F.col("_last") - F.col("_first") < F.col("_grams") + K + drift) & (F.col("_together") == F.col("_musts"))
    spans = merged.where(F.when(F.col("_base"), F.col("_whole")).otherwise(long_enough)).select(*key, "_tpl", "_base", "_label", "_first", "_last", "_cover", "_grams")
    counted = spans.where("_base").select(*key, "_base", "_label", "_first", "_last", "_cover").unionByName(_best(spans.where("NOT _base"), key))
    found = counted.groupBy(*key).agg(
        F.sum(F.col("_base").cast("long")).alias("n_base"),
        F.min(F.when(F.col("_base"), F.col("_first"))).cast("long").alias("first_word"),
        F.max(F.when(F.col("_base"), F.col("_first"))).cast("long").alias("last_word"),
        F.array_sort(F.collect_set(F.when(F.col("_base"), F.col("_label")))).alias("_bl"),
        F.array_sort(F.collect_set("_label")).alias("_l"),
        F.max("_cover").alias("_score"),
        F.array_sort(F.collect_list(F.struct(F.col("_first").alias("first"), F.col("_last").alias("last"), F.col("_label").alias("label"), F.col("_cover").alias("cover")))).alias("spans"),
    ).withColumnsRenamed({"doc_id": "_id", "_k": "_k2"})
    return rows.join(found, (F.col("_k") == F.col("_k2")) & F.col("doc_id").eqNullSafe(F.col("_id")), "left").select(
        "doc_id",
        "n_words",
        F.coalesce("n_base", F.lit(0)).cast("long").alias("n_base"),
        "first_word",
        "last_word",
        F.coalesce(F.array_join("_bl", ","), F.lit("")).alias("base_labels"),
        F.coalesce(F.array_join("_l", ","), F.lit("")).alias("labels"),
        F.coalesce("_score", F.lit(0.0)).alias("score"),
        "spans",
    )


def op7_licenses(spark, sf_dir: str) -> DataFrame:
    return scanned(table(spark, sf_dir, "documents")).drop("spans")
