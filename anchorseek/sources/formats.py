"""Files of sequences and tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def table(spark, folder: str, name: str, columns=None) -> DataFrame:
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark, path: str, fmt: str, schema) -> DataFrame:
    """A table with an explicit schema; CSV with a header line."""
    reader = spark.read.schema(schema).format(fmt)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def fasta(spark, path: str) -> DataFrame:
    """(file, name, seq) of header and sequence records; records are split at '>' by the reader."""
    rows = spark.read.option("lineSep", ">").text(path).select(F.input_file_name().alias("file"), "value").where(F.trim("value") != "")
    lines = F.split("value", "\r?\n")
    return rows.select("file", F.split(F.get(lines, 0), " ")[0].alias("name"), F.array_join(F.slice(lines, F.lit(2), F.size(lines)), "").alias("seq"))


def fastq(spark, path: str) -> DataFrame:
    """(file, name, seq) of records of four lines. The line number orders lines of one file, so a file is one
    task's work; convert large archives to Parquet once."""
    rows = spark.read.text(path).select("_metadata.file_path", "_metadata.file_block_start", F.monotonically_increasing_id().alias("i"), "value")
    w = Window.partitionBy("file_path").orderBy("file_block_start", "i")
    numbered = rows.withColumn("n", F.row_number().over(w) - 1).withColumn("record", F.floor(F.col("n") / 4)).where("n % 4 < 2")
    got = numbered.groupBy("file_path", "record").agg(F.max(F.when(F.col("n") % 4 == 0, F.col("value"))).alias("head"), F.max(F.when(F.col("n") % 4 == 1, F.col("value"))).alias("seq"))
    return got.select(F.col("file_path").alias("file"), F.split(F.substring("head", 2, 1 << 20), " ")[0].alias("name"), "seq")
