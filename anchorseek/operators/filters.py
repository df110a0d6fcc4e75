"""Plain filters: one array of bits a set, stored as page rows (filter_id, rep, page_no, bits).

The hash choice touches only where positions come from; building and probing are the same for uniform,
sketch and anchored hashing. A probe groups the bits of a query by page before anything moves, so the rows
that are shuffled and the page rows that are read number the distinct (query, page) pairs, and that is what
anchored hashing makes few.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import anchored, kernel, schemas
from ..plans.spec import PAGE_BYTES, IndexSpec
from . import pages

KEYS = ["filter_id", "rep", "page_no"]
#: An index that can have this many pages (4 KB each) at most, by its parameters, is broadcast to the probes.
BROADCAST_PAGES = 8192


def build(reads: DataFrame, spec: IndexSpec, filter_id="file_id", combine: str = "pages") -> DataFrame:
    """Filter pages of reads (filter_id, seq). filter_id: a column's name, or an expression.

    combine: `pages` gathers each task's distinct bits by page before the shuffle and ships offsets of pages with
    few bits and bitmaps of others; `offsets` does so by aggregates alone; `bits` lets the aggregate take one row a bit.
    """
    name = F.col(filter_id) if isinstance(filter_id, str) else filter_id
    rows = reads.select(name.cast("string").alias("filter_id"), "seq")
    if spec.kernel and combine == "pages":
        return _merged(rows, spec, False)
    bits = anchored.gram_positions(rows, spec, ["filter_id"]).select("filter_id", "rep", "bit")
    if combine == "offsets":
        grouped = bits.groupBy("filter_id", "rep", pages.page_of(F.col("bit")).alias("page_no")).agg(F.collect_set(pages.offset_of(F.col("bit"))).alias("offsets"))
        return grouped.select("filter_id", "rep", "page_no", F.explode("offsets").alias("o")).groupBy(*KEYS).agg(F.bitmap_construct_agg(F.col("o").cast("long")).alias("bits"))
    return pages.from_positions(bits, ["filter_id", "rep"])


def _merged(rows: DataFrame, spec: IndexSpec, tally: bool) -> DataFrame:
    more = ", n bigint, total bigint" * tally
    if fits(spec):  # each task hands on a whole small index at most, so few tasks do
        rows = rows.coalesce(4 * rows.sparkSession.sparkContext.defaultParallelism)
    got = rows.mapInArrow(kernel.page_builder(spec, tally), "filter_id string, rep int, page_no bigint, dense boolean, bits binary" + more)
    return got.repartition(*KEYS).sortWithinPartitions(*KEYS).mapInArrow(kernel.page_merger, "filter_id string, rep int, page_no bigint, bits binary" + more)


def summary(reads: DataFrame, spec: IndexSpec) -> DataFrame:
    """(rep, n, n_bits, total, n_pages): positions of all grams of reads (seq), repeats counted, distinct ones, their
    sum and their pages. Built as a filter is, so what moves grows with the distinct bits and not with the grams."""
    rows = _merged(reads.select(F.lit("all").alias("filter_id"), "seq"), spec, True)
    return rows.groupBy("rep").agg(F.sum("n").alias("n"), F.sum(F.bitmap_count("bits")).alias("n_bits"), F.sum("total").alias("total"), F.count(F.lit(1)).alias("n_pages"))


def group_probes(queries: DataFrame, spec: IndexSpec, with_grams: bool = False) -> DataFrame:
    """(query_id, rep, page_no, offsets[, grams]) of queries (query_id, seq)."""
    schemas.require(queries, schemas.QUERIES)
    rows = queries.select("query_id", "seq")
    if spec.kernel:
        return rows.mapInArrow(kernel.probe_builder(spec, with_grams), "query_id bigint, rep int, page_no bigint, offsets array<int>" + ", grams array<int>" * with_grams)
    bits = anchored.gram_positions(rows, spec, ["query_id"]).withColumn("page_no", pages.page_of(F.col("bit"))).withColumn("o", pages.offset_of(F.col("bit")))
    grouped = bits.groupBy("query_id", "rep", "page_no")
    if with_grams:
        return grouped.agg(F.collect_list(F.struct("o", "pos")).alias("x")).select("query_id", "rep", "page_no", F.col("x.o").alias("offsets"), F.col("x.pos").alias("grams"))
    return grouped.agg(F.collect_set("o").alias("offsets"))


def one_set(index: DataFrame) -> DataFrame:
    """(rep, page_no, bits) of the filter of all sets of an index: pages joined by OR."""
    return pages.union(index.select("rep", "page_no", "bits"), keys=("rep", "page_no"))


def _with_pages(probes: DataFrame, index: DataFrame, spec: IndexSpec, broadcast: bool | None) -> DataFrame:
    """Probes with the bits of their page, null where no page is stored. index: one row a (rep, page_no)."""
    side = index.select("rep", "page_no", "bits")
    if broadcast is None:
        broadcast = spec.pages <= BROADCAST_PAGES
    return probes.join(F.broadcast(side) if broadcast else side, ["rep", "page_no"], "left")


_KEYS: dict[int, list[int]] = {}


def _slots(spark, n: int) -> list[int]:
    """n numbers that Spark's hash deals to n partitions, one to each."""
    if n not in _KEYS:
        rows = spark.range(20 * n + 100).select(F.col("id").cast("int").alias("id")).groupBy(F.pmod(F.hash("id"), F.lit(n)).alias("p")).agg(F.min("id").alias("id"))
        _KEYS[n] = sorted(r.id for r in rows.collect())
    return _KEYS[n]


def fits(spec: IndexSpec, n_filters: int = 1) -> bool:
    """Whether `dealt` takes such an index: its size is bounded by its parameters, and the kernel knows its positions."""
    return spec.kernel and n_filters * spec.pages <= BROADCAST_PAGES


def dealt(index: DataFrame, queries: DataFrame, spec: IndexSpec, answer: str, n_filters: int = 1) -> DataFrame:
    """kernel.ANSWERS[answer] of every query (query_id, seq), a row a query: queries are dealt over slots, each of which
    gets the whole index, so that neither places nor answers are shuffled. For indexes that `fits` lets through."""
    copies = max(4 * queries.sparkSession.sparkContext.defaultParallelism, (1 << 28) // (n_filters * spec.pages * PAGE_BYTES))
    return _dealt(index, queries, copies).mapInArrow(kernel.prober(spec, answer), kernel.ANSWERS[answer])


def _dealt(index: DataFrame, queries: DataFrame, copies: int) -> DataFrame:
    """Rows of kernel.DEALT: queries over slots, each of which gets the whole index."""
    schemas.require(queries, schemas.QUERIES)
    spark = queries.sparkSession
    n = min(int(spark.conf.get("spark.sql.shuffle.partitions")), copies)
    keys = F.array(*[F.lit(x) for x in _slots(spark, n)])
    name = F.col("filter_id") if "filter_id" in index.columns else F.lit("")
    stored = index.select(F.explode(keys).alias("slot"), F.lit(0).alias("side"), name.alias("filter_id"), "rep", "page_no", "bits")
    asked = queries.select(F.element_at(keys, (F.pmod(F.xxhash64("query_id"), F.size(keys)) + 1).cast("int")).alias("slot"), F.lit(1).alias("side"), "query_id", "seq")
    return stored.unionByName(asked, allowMissingColumns=True).repartition(n, "slot").sortWithinPartitions("slot", "side")


def fit(specs: list[IndexSpec]) -> bool:
    """Whether build_each and contains_each take the specs: all their pages together are as few as of one index that `fits`."""
    return all(s.kernel and s.theta == 1 for s in specs) and sum(s.pages for s in specs) <= BROADCAST_PAGES


def build_each(reads: DataFrame, specs: list[IndexSpec]) -> DataFrame:
    """build() of one set (seq) for each spec, in one pass over the reads: filter_id is the number of the spec."""
    rows = reads.select("seq").coalesce(2 * reads.sparkSession.sparkContext.defaultParallelism)  # each task hands on all pages at most
    got = rows.mapInArrow(kernel.several_builder(specs), "filter_id string, rep int, page_no bigint, dense boolean, bits binary")
    return got.repartition(*KEYS).sortWithinPartitions(*KEYS).mapInArrow(kernel.page_merger, "filter_id string, rep int, page_no bigint, bits binary")


def contains_each(index: DataFrame, queries: DataFrame, specs: list[IndexSpec]) -> DataFrame:
    """(query_id, hits): contains() of each filter of build_each, in the order of the specs, in one pass over the queries."""
    found = _dealt(index, queries, 2 * queries.sparkSession.sparkContext.defaultParallelism).mapInArrow(kernel.several_prober(specs), "query_id bigint, hits array<boolean>")
    each = [F.element_at("hits", i + 1) for i in range(len(specs))]
    return found.select("query_id", F.array(*[F.when(h.isNotNull(), h).otherwise(_empty_answer(s)) for h, s in zip(each, specs)]).alias("hits"))


def _empty_answer(spec: IndexSpec):
    return {"match": F.lit(True), "null": F.lit(None).cast("boolean"), "error": F.raise_error(F.lit("a query has no gram")).cast("boolean")}[spec.empty_query]


def _answered(queries: DataFrame, hits: DataFrame, spec: IndexSpec) -> DataFrame:
    """Every query with its hit; queries without grams as the spec says."""
    return queries.select("query_id").join(hits, "query_id", "left").select("query_id", F.when(F.col("hit").isNotNull(), F.col("hit")).otherwise(_empty_answer(spec)).alias("hit"))


def contains(index: DataFrame, queries: DataFrame, spec: IndexSpec, broadcast: bool | None = None, single: bool = False) -> DataFrame:
    """(query_id, hit): whether every bit of every gram of the query is set (at least theta of its grams, if below 1).

    An index of several filters answers for the union of their sets; `single` says that it has one, which spares
    joining the pages.
    """
    if broadcast is None and spec.theta == 1 and spec.exit != "rounds" and fits(spec):
        return dealt(index, queries, spec, "hit").select("query_id", F.when(F.col("hit").isNotNull(), F.col("hit")).otherwise(_empty_answer(spec)).alias("hit"))
    index = index if single else one_set(index)
    if spec.theta < 1:
        found = coverage(index, queries, spec, broadcast, single=True)
        return _answered(queries, found.where("n_grams > 0").select("query_id", (F.col("coverage") >= spec.theta).alias("hit")), spec)
    if spec.exit == "rounds":
        return _in_rounds(index, queries, spec, broadcast)
    if spec.exit == "kernel":
        return _in_kernel(index, queries, spec)
    tested = _with_pages(group_probes(queries, spec), index, spec, broadcast)
    hits = tested.groupBy("query_id").agg(F.bool_and(pages.covers(F.col("bits"), F.col("offsets"))).alias("hit"))
    return _answered(queries, hits, spec)


def _in_rounds(index: DataFrame, queries: DataFrame, spec: IndexSpec, broadcast: bool | None) -> DataFrame:
    """One function after another; queries that missed a bit are not probed again."""
    probes, alive, out = group_probes(queries, spec), None, []
    for rep in range(spec.eta if spec.layout == "partitioned" else 1):
        mine = probes.where(F.col("rep") == rep)
        if alive is not None:
            mine = mine.join(alive, "query_id", "left_semi")
        judged = _with_pages(mine, index.where(F.col("rep") == rep), spec, broadcast).groupBy("query_id").agg(F.bool_and(pages.covers(F.col("bits"), F.col("offsets"))).alias("hit"))
        out.append(judged)
        alive = judged.where("hit").select("query_id")
    hits = out[0]
    for more in out[1:]:
        hits = hits.unionByName(more)
    return _answered(queries, hits.groupBy("query_id").agg(F.bool_and("hit").alias("hit")), spec)


def _in_kernel(index: DataFrame, queries: DataFrame, spec: IndexSpec) -> DataFrame:
    """Pages meet their probe rows in one task, which tests whole rows against the page's bits at once."""
    import numpy as np
    import pandas as pd

    def probe(key, mine: pd.DataFrame, page: pd.DataFrame) -> pd.DataFrame:
        if not len(mine):
            return pd.DataFrame({"query_id": pd.Series([], dtype="int64"), "hit": pd.Series([], dtype=bool)})
        if not len(page):
            return pd.DataFrame({"query_id": mine["query_id"], "hit": False})
        bits = np.unpackbits(np.frombuffer(page["bits"].iloc[0], np.uint8), bitorder="little").astype(bool)
        return pd.DataFrame({"query_id": mine["query_id"], "hit": [bool(bits[np.asarray(o)].all()) for o in mine["offsets"]]})

    probes = group_probes(queries, spec).groupBy("rep", "page_no")
    tested = probes.cogroup(index.select("rep", "page_no", "bits").groupBy("rep", "page_no")).applyInPandas(probe, "query_id bigint, hit boolean")
    return _answered(queries, tested.groupBy("query_id").agg(F.bool_and("hit").alias("hit")), spec)


def probe_grams(index: DataFrame, queries: DataFrame, spec: IndexSpec, broadcast: bool | None = None, single: bool = False) -> DataFrame:
    """(query_id, pos, hit) of every gram of every query, in the union of the index's sets."""
    if broadcast is None and fits(spec):
        return dealt(index, queries, spec, "grams").select("query_id", F.explode("grams").alias("g")).select("query_id", F.col("g.pos").alias("pos"), F.col("g.hit").alias("hit"))
    index = index if single else one_set(index)
    tested = _with_pages(group_probes(queries, spec, with_grams=True), index, spec, broadcast)
    each = tested.select("query_id", F.explode(F.transform(F.arrays_zip("offsets", "grams"), lambda x: F.struct(x["grams"].alias("pos"), F.coalesce(pages.bit_at(F.col("bits"), x["offsets"]), F.lit(False)).alias("hit")))).alias("g"))
    return each.groupBy("query_id", F.col("g.pos").alias("pos")).agg(F.bool_and("g.hit").alias("hit"))


def coverage(index: DataFrame, queries: DataFrame, spec: IndexSpec, broadcast: bool | None = None, single: bool = False) -> DataFrame:
    """(query_id, n_grams, n_hit, coverage) of every query; a query without grams has coverage 1."""
    found = probe_grams(index, queries, spec, broadcast, single).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_grams"), F.sum(F.col("hit").cast("long")).alias("n_hit"))
    rows = queries.select("query_id").join(found, "query_id", "left").na.fill(0, ["n_grams", "n_hit"])
    return rows.withColumn("coverage", F.when(F.col("n_grams") > 0, F.col("n_hit") / F.col("n_grams")).otherwise(1.0))


def union(a: DataFrame, b: DataFrame, spec_a: IndexSpec, spec_b: IndexSpec) -> DataFrame:
    """The filter of both sets; only for filters with the same positions."""
    if not spec_a.compatible(spec_b):
        raise ValueError("filters of different parameters cannot be joined")
    return pages.union(a, b)


def fill(index: DataFrame, spec: IndexSpec) -> DataFrame:
    """(filter_id, rep, n_bits, fill): bits set, and their share of the array."""
    counted = index.groupBy("filter_id", "rep").agg(F.sum(F.bitmap_count("bits")).alias("n_bits"))
    return counted.withColumn("fill", F.col("n_bits") / F.lit(spec.range))


def whole_hits(index: DataFrame, queries: DataFrame, spec: IndexSpec, n_filters: int | None = None) -> DataFrame:
    """(query_id, filter_id): the filters, of an index of many, that hold all bits of the query.

    Probe rows meet the stored pages of all filters at once; a filter holds the query if as many of its
    pages passed as the query has probe rows, so absent pages need no rows. Queries without grams are absent.
    The index is broadcast if n_filters is given and so many filters cannot have too many pages.
    """
    if n_filters is not None and fits(spec, n_filters):
        return dealt(index, queries, spec, "filters", n_filters).select("query_id", F.explode("filters").alias("filter_id"))
    probes = group_probes(queries, spec)
    broadcast = n_filters is not None and n_filters * spec.pages <= BROADCAST_PAGES
    sized = probes.groupBy("query_id").agg(F.count(F.lit(1)).alias("need"))
    met = probes.join(F.broadcast(index) if broadcast else index, ["rep", "page_no"]).where(pages.covers(F.col("bits"), F.col("offsets")))
    return met.groupBy("query_id", "filter_id").agg(F.count(F.lit(1)).alias("have")).join(sized, "query_id").where("have = need").select("query_id", "filter_id")
