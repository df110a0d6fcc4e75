"""File-matrix index: one filter a file, all with the same range, so one position answers for all files.

Layouts: `slices` keeps for every position the files that set it, a 63-bit number for up to 63 files, else a
bitmap for each block of 32,768 files; `files` keeps filter pages with the file as filter id.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import anchored, views
from ..plans.spec import IndexSpec
from . import filters, pages

MASK_FILES = 63


class FileMatrix:
    """Slices or pages, with the files' numbers. few: how many files there are, if that is known and their pages are few."""

    def __init__(self, rows: DataFrame, files: DataFrame, spec: IndexSpec, layout: str, few: int | None = None):
        self.rows, self.files, self.spec, self.layout, self.few = rows, files, spec, layout, few


def build(reads: DataFrame, spec: IndexSpec, layout: str = "auto") -> FileMatrix:
    """Index of reads (file_id, seq). layout: auto, mask, bitmap or files. auto: files if they and their pages
    are few, mask or bitmap by the number of files else."""
    files = views.numbered_files(reads)
    if layout in ("auto", "files"):
        files, few = _few(files, spec, MASK_FILES if layout == "auto" else filters.BROADCAST_PAGES)
        if few is not None or layout == "files":
            return FileMatrix(filters.build(reads, spec), files, spec, "files", few)
        layout = "mask" if files.limit(MASK_FILES + 1).count() <= MASK_FILES else "bitmap"
    bits = anchored.gram_positions(reads.join(F.broadcast(files), "file_id").select("file_ord", "seq"), spec, ["file_ord"])
    if layout == "mask":
        rows = bits.groupBy("rep", "bit").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("file_ord").cast("int"))).alias("files"))
        return FileMatrix(rows, files, spec, layout)
    rows = bits.groupBy("rep", "bit", F.shiftright("file_ord", 15).alias("file_block")).agg(F.bitmap_construct_agg(F.col("file_ord").bitwiseAND(F.lit(32767)).cast("long")).alias("files"))
    return FileMatrix(rows, files, spec, layout)


def _few(files: DataFrame, spec: IndexSpec, most: int) -> tuple[DataFrame, int | None]:
    """The files as a table of the driver's, and their number, if an index of all of them fits; else as they are."""
    most = min(most, filters.BROADCAST_PAGES // spec.pages)
    if not filters.fits(spec):
        return files, None
    rows = files.limit(most + 1).collect()  # bounded by the parameters
    return (files, None) if len(rows) > most else (files.sparkSession.createDataFrame(rows, files.schema).coalesce(1), len(rows))


def _probe_bits(queries: DataFrame, spec: IndexSpec) -> DataFrame:
    return anchored.gram_positions(queries.select("query_id", "seq"), spec, ["query_id"])


def search(index: FileMatrix, queries: DataFrame) -> DataFrame:
    """(query_id, file_id, hit) for every query and file. A query without grams matches, or as the spec says."""
    if index.layout == "files" and index.few:
        held = filters.dealt(index.rows, queries, index.spec, "filters", index.few).crossJoin(F.broadcast(index.files.select("file_id")))
        return held.select("query_id", "file_id", F.when(F.col("short"), filters._empty_answer(index.spec)).otherwise(F.coalesce(F.array_contains("filters", F.col("file_id")), F.lit(False))).alias("hit"))
    return answers(queries, index.files, hits(index, queries), index.spec)


def hits(index: FileMatrix, queries: DataFrame) -> DataFrame:
    """(query_id, file_id) of the files that hold the query; queries without grams are absent."""
    spec = index.spec
    if index.layout == "files" and index.few:
        found = filters.dealt(index.rows, queries, spec, "filters", index.few).select("query_id", F.explode("filters").alias("file_id"))
    elif index.layout == "files":
        found = filters.whole_hits(index.rows, queries, spec).withColumnRenamed("filter_id", "file_id")
    elif index.layout == "mask":
        probes = _probe_bits(queries, spec).select("query_id", "rep", "bit").distinct()
        # a position that no file set answers no for all files
        met = probes.join(index.rows, ["rep", "bit"], "left").groupBy("query_id").agg(F.bit_and(F.coalesce("files", F.lit(0).cast("long"))).alias("files"))
        found = met.join(F.broadcast(index.files), F.call_function("getbit", F.col("files"), F.col("file_ord").cast("int")) == 1).select("query_id", "file_id")
    else:
        probes = _probe_bits(queries, spec).select("query_id", "rep", "bit").distinct()
        need = probes.groupBy("query_id").agg(F.count(F.lit(1)).alias("need"))
        met = probes.join(index.rows, ["rep", "bit"]).groupBy("query_id", "file_block").agg(F.bitmap_and_agg("files").alias("files"), F.count(F.lit(1)).alias("have"))
        held = met.join(need, "query_id").where("have = need")  # a missing row is a zero bitmap
        found = held.join(F.broadcast(index.files.withColumn("file_block", F.shiftright("file_ord", 15))), "file_block").where(pages.bit_at(F.col("files"), F.col("file_ord").bitwiseAND(F.lit(32767)).cast("int"))).select("query_id", "file_id")
    return found


def answers(queries: DataFrame, files: DataFrame, found: DataFrame, spec: IndexSpec) -> DataFrame:
    """The full table of answers from the pairs that hit."""
    empty = filters._empty_answer(spec)
    grid = queries.select("query_id", (F.coalesce(F.length("seq"), F.lit(0)) < spec.k).alias("_none")).crossJoin(F.broadcast(files.select("file_id")))  # the answer itself has a row a query and file
    marked = found.withColumn("_hit", F.lit(True))
    return grid.join(marked, ["query_id", "file_id"], "left").select("query_id", "file_id", F.when(F.col("_none"), empty).otherwise(F.coalesce("_hit", F.lit(False))).alias("hit"))


def coverage(index: FileMatrix, queries: DataFrame) -> DataFrame:
    """(query_id, file_id, n_grams, n_hit, coverage) of the pairs that share a gram by the index."""
    if index.layout == "files" and index.few:
        each = filters.dealt(index.rows, queries, index.spec, "counts", index.few).select("query_id", "n_grams", F.explode("counts").alias("c"))
        return each.select("query_id", F.col("c.filter_id").alias("file_id"), "n_grams", F.col("c.n_hit").alias("n_hit"), (F.col("c.n_hit") / F.col("n_grams")).alias("coverage"))
    if index.layout != "mask":
        raise ValueError("coverage by gram needs the mask layout, or few files")
    probes = _probe_bits(queries, index.spec)
    met = probes.join(index.rows, ["rep", "bit"], "left").groupBy("query_id", "pos").agg(F.bit_and(F.coalesce("files", F.lit(0).cast("long"))).alias("files"))
    sized = met.groupBy("query_id").agg(F.count(F.lit(1)).alias("n_grams"))
    each = met.where("files != 0").join(F.broadcast(index.files), F.call_function("getbit", F.col("files"), F.col("file_ord").cast("int")) == 1)
    return each.groupBy("query_id", "file_id").agg(F.count(F.lit(1)).alias("n_hit")).join(sized, "query_id").select("query_id", "file_id", "n_grams", "n_hit", (F.col("n_hit") / F.col("n_grams")).alias("coverage"))


def top(index: FileMatrix, queries: DataFrame, n: int) -> DataFrame:
    """(query_id, file_id, n_hit, place): the n files that hold most grams of each query, ties by their names."""
    if index.layout == "files" and index.few:
        ranked = F.slice(F.array_sort(F.transform("counts", lambda c: F.struct((-c["n_hit"]).alias("less"), c["filter_id"].alias("file_id")))), 1, n)
        rows = filters.dealt(index.rows, queries, index.spec, "counts", index.few).select("query_id", F.posexplode(ranked).alias("at", "c"))
        return rows.select("query_id", F.col("c.file_id").alias("file_id"), (-F.col("c.less")).alias("n_hit"), (F.col("at") + 1).alias("place"))
    place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("n_hit"), "file_id"))
    return coverage(index, queries).withColumn("place", place).where(F.col("place") <= n).select("query_id", "file_id", "n_hit", "place")
