"""Bucket-grid index: R times the files fall at random into B buckets, and each bucket has one filter.

A file is reported if its bucket holds the query in every repetition. All R * B filters are probed in one
join; a query's probe rows are grouped by page before they meet the filters.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import grams, hashing, views
from ..plans.spec import IndexSpec
from . import file_matrix, filters


def defaults(n_files: int) -> tuple[int, int]:
    """(B, R) for a number of files: its square root and its logarithm, rounded up."""
    return max(1, math.ceil(math.sqrt(n_files))), max(1, math.ceil(math.log(n_files))) if n_files > 1 else 1


class BucketGrid:
    def __init__(self, pages: DataFrame, buckets: DataFrame, files: DataFrame, spec: IndexSpec, B: int, R: int):
        self.pages, self.buckets, self.files, self.spec, self.B, self.R = pages, buckets, files, spec, B, R


def bucket_map(files: DataFrame, B: int, R: int, seed: int, family: str = "xxhash64") -> DataFrame:
    """(grid_rep, bucket, file_id); a row a file and repetition."""
    per = F.array(*[F.struct(F.lit(r).alias("grid_rep"), hashing.uniform(F.col("file_id"), seed + 1000 + r, B, family if family in ("md5", "murmur3") else "xxhash64").cast("int").alias("bucket")) for r in range(R)])
    return files.select("file_id", F.explode(per).alias("b")).select("b.grid_rep", "b.bucket", "file_id")


def build(reads: DataFrame, spec: IndexSpec, B: int | None = None, R: int | None = None, buckets: DataFrame | None = None) -> BucketGrid:
    """Index of reads (file_id, seq). buckets: another map of files to buckets than the random one."""
    files = views.numbered_files(reads)
    if (B or spec.B) is None or (R or spec.R) is None:
        auto_b, auto_r = defaults(files.count())
    B, R = B or spec.B or auto_b, R or spec.R or auto_r
    buckets = bucket_map(files, B, R, spec.seed, spec.family) if buckets is None else buckets
    placed = reads.select("file_id", "seq").join(F.broadcast(buckets), "file_id").select(F.concat_ws(":", "grid_rep", "bucket").alias("filter_id"), "seq")
    return BucketGrid(filters.build(placed, spec, "filter_id"), buckets, files, spec, B, R)


def bucket_hits(index: BucketGrid, queries: DataFrame) -> DataFrame:
    """(query_id, grid_rep, bucket) of the filters that hold the query."""
    hits = filters.whole_hits(index.pages, queries, index.spec, index.B * index.R)
    part = F.split("filter_id", ":")
    return hits.select("query_id", F.get(part, 0).cast("int").alias("grid_rep"), F.get(part, 1).cast("int").alias("bucket"))


def search(index: BucketGrid, queries: DataFrame) -> DataFrame:
    """(query_id, file_id, hit) for every query and file."""
    return file_matrix.answers(queries, index.files, file_hits(index, queries), index.spec)


def file_hits(index: BucketGrid, queries: DataFrame) -> DataFrame:
    """(query_id, file_id) of the files whose buckets hold the query in every repetition."""
    met = bucket_hits(index, queries).join(F.broadcast(index.buckets), ["grid_rep", "bucket"])
    return met.groupBy("query_id", "file_id").agg(F.countDistinct("grid_rep").alias("n")).where(F.col("n") == index.R).select("query_id", "file_id")


def refine(candidates: DataFrame, queries: DataFrame, reads: DataFrame, k: int) -> DataFrame:
    """Candidates (query_id, file_id, hit) with hits checked on exact grams.

    Only pairs that hit are looked at: their grams against the grams of their files. A null hit stays null.
    """
    pairs = candidates.where("hit").select("query_id", "file_id")
    wanted = grams.gram_set(queries.join(pairs.select("query_id").distinct(), "query_id", "left_semi"), ["query_id"], "seq", k).join(pairs, "query_id")
    known = grams.gram_set(reads.join(pairs.select("file_id").distinct(), "file_id", "left_semi"), ["file_id"], "seq", k)
    absent = wanted.join(known, ["file_id", "gram"], "left_anti").select("query_id", "file_id").distinct().withColumn("_absent", F.lit(True))
    return candidates.join(absent, ["query_id", "file_id"], "left").select("query_id", "file_id", (F.col("hit") & F.col("_absent").isNull()).alias("hit"))
