"""The corpus pipeline: language, near duplicates, decontamination, mixing, token files.

Each stage takes (spark, docs, sf_dir), works on all that the one before kept, and returns a DataFrame; run()
writes each stage's result as Parquet to the shared folder and reads it again. Defined results for nulls, empty
texts, repeated rows, empty tables and extra columns are those of the operators.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from anchorseek.llm import langid, lsh_forest, mixing, token_files, winnow
from anchorseek.llm.common import fresh_path, settled, table

#: A document is rejected that has no letters, or whose main language holds less than this share of them.
LEAST_SHARE = 0.5
#: Near duplicates share this part of their five-word shingles or more (intersection over union).
LINK = (80, 100)
TOKENIZER = "byte_bpe_50k.json"


def identify_language(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    columns = docs.columns
    got = langid.identified(docs, langid.contract_model(docs), spans=False)
    return got.where((F.col("lang_pred") != "und") & (F.col("lang_score") >= LEAST_SHARE)).select(*columns)


def drop_near_duplicates(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group the document with the smallest id stays; of rows with one id, one."""
    judged = settled(lsh_forest.near_duplicates(docs, link=LINK).select("doc_id", "kept"), "near-duplicates")
    out = lsh_forest.without(docs, judged.where(~F.col("kept")).select("doc_id"))
    repeated = judged.where("kept AND doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").limit(1).count()
    if repeated:
        named = out.where(F.col("doc_id").isNotNull()).dropDuplicates(["doc_id"])
        out = named.unionByName(out.where(F.col("doc_id").isNull()))
    return out


def decontaminate(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    columns = docs.columns
    return winnow.marked(docs, table(spark, sf_dir, "benchmark")).where(~winnow.is_contaminated()).select(*columns)


def mix_sources(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A document stands once for every pass that takes it; n_chars follows where the budget cuts a text."""
    out = mixing.mixed(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in out.columns else out


def write_token_files(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = fresh_path(spark, "token-files")
    token_files.write_tokens(docs, public_tokenizers.path(TOKENIZER), path)
    return token_files.token_index(spark, path)


STAGES = [
    ("language", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("decontaminate", decontaminate),
    ("mix", mix_sources),
    ("tokens", write_token_files),
]
#: The language model, the tokenizer and the near-duplicate groups are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = settled(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
