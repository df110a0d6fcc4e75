"""The published experiments over the given tables: points of time against rate, growth, many sets, index misses.

Those that time many points take minutes even on small tables and are called by name, not registered:
`time_fpr_points`, `pareto_time_fpr`, `growth_m`, `grid_table`, `matrix_sweep`.

Seconds are measured where a query is called, so these queries run their jobs at once and return small tables.
Runs go round by round over all points, so that no hash is always timed first.
"""

from __future__ import annotations

import statistics

from pyspark.sql import functions as F

from .functions import anchored
from .operators import baselines, bucket_grid, file_matrix, filters, measures
from .plans import cachesim
from .plans.spec import IndexSpec
from .workloads import FAST, K, POISON, QUERY_GRAMS, SEQS, SPEC, _grid_reads, _places_sql, _queries, reads

QUERIES, SQL = {}, {}


def register(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def rounds(jobs: dict, runs: int) -> dict:
    """Mean seconds of each job (a DataFrame computed without output) over the runs; one round before is not counted.

    Every round begins with another job.
    """
    names, took = list(jobs), {name: [] for name in jobs}
    for r in range(runs + 1):
        for name in names[r % len(names) :] + names[: r % len(names)]:
            seconds = measures.timed(jobs[name])["mean"]
            if r:
                took[name].append(seconds)
    return {name: statistics.fmean(t) for name, t in took.items()}


def points(spark, d, specs: list[IndexSpec], runs: int) -> list[dict]:
    """A row a spec: index and query seconds, false positives of the poisoned queries, pages stored."""
    rows, asked = reads(spark, d).persist(), _queries(spark, d).persist()
    n_reads, n_queries = rows.count(), asked.count()
    truth = baselines.exact_mt(rows, asked, K).persist()
    built = {s: filters.build(rows, s) for s in specs}
    index_s = rounds(built, runs)
    kept = {s: b.persist() for s, b in built.items()}
    answers = {s: filters.contains(kept[s], asked, s, single=True) for s in specs}
    query_s = rounds(answers, runs)
    out = []
    for s in specs:
        rate = measures.fpr_mt(answers[s], truth).first()
        out.append({
            "hash": s.hash, "m": s.m, "eta": s.eta, "t": s.t, "L": s.L, "runs": runs, "index_s": index_s[s], "query_s": query_s[s],
            "index_ms_per_read": 1000 * index_s[s] / max(1, n_reads), "query_ms": 1000 * query_s[s] / max(1, n_queries),
            "negatives": rate.negatives, "false_hits": rate.false_hits, "fpr": rate.fpr, "pages": kept[s].count(),
        })
    for df in (*kept.values(), truth, rows, asked):
        df.unpersist()
    return out


POINT = "hash string, m long, eta int, t int, L int, runs int, index_s double, query_s double, index_ms_per_read double, query_ms double, negatives long, false_hits long, fpr double, pages long"
SIZES = (1 << 21, 1 << 22, 1 << 23, 1 << 24)


def _points(spark, d, specs, runs=1):
    return spark.createDataFrame(points(spark, d, specs, runs), POINT)


def _both(**changes):
    return [FAST.with_(hash=h, m=m, **changes) for m in SIZES for h in ("uniform", "anchored")]


def time_fpr_points(spark, d):
    """Index time a read, query time and rate of both hashes on four sizes; five runs in turn."""
    return _points(spark, d, _both(), runs=5)


def pareto_time_fpr(spark, d):
    """The points of each hash that no other point of it beats, and beside each uniform point the fastest anchored
    point of the same rate or less (null: none), for index and for query seconds."""
    got = points(spark, d, _both() + _both(eta=2), 2)
    rows = []
    for cost in ("index_s", "query_s"):
        best = {}
        for h in ("uniform", "anchored"):
            mine = spark.createDataFrame([p for p in got if p["hash"] == h], POINT)
            best[h] = [r.asDict() for r in measures.pareto(mine, cost, "fpr").collect()]
        for h, front in best.items():
            for p in front:
                rival = min((q[cost] for q in best["anchored"] if q["fpr"] <= p["fpr"]), default=None) if h == "uniform" else None
                rows.append((cost, h, p["m"], p["eta"], p["fpr"], p[cost], rival, measures.compare(p[cost], rival)["reduction"] if rival else None))
    return spark.createDataFrame(rows, "cost string, hash string, m long, eta int, fpr double, seconds double, anchored_seconds double, reduction double")


def growth_m(spark, d):
    """Seconds gained by each doubling of the size, for each hash, for index and query."""
    table, out = _points(spark, d, _both(), runs=3), None
    for h in ("uniform", "anchored"):
        for cost in ("index_s", "query_s"):
            got = measures.growth(table.where(F.col("hash") == h), "m", cost).select(F.lit(h).alias("hash"), F.lit(cost).alias("cost"), "slope", "intercept")
            out = got if out is None else out.unionByName(got)
    return out


@register("hash_time_t")
def hash_time_t(spark, d):
    """Seconds to place all grams, by subgram length; three runs in turn."""
    rows = reads(spark, d).persist()
    rows.count()
    jobs = {t: anchored.gram_positions(rows, FAST.with_(t=t)).agg(F.bit_xor("bit")) for t in (8, 12, 16, 20, 24)}
    took = rounds(jobs, 3)
    rows.unpersist()
    return spark.createDataFrame(sorted(took.items()), "t int, seconds double")


@register("index_miss_rates")
def index_miss_rates(spark, d):
    """Simulated two-level cache over each file's insertions, for the three hashes: 32 KB and 512 KB, 2^25 bits."""
    specs = {h: FAST.with_(hash=h, m=1 << 25) for h in ("sketch", "uniform", "anchored")}
    out = cachesim.gram_miss_rates(reads(spark, d, "source"), specs, "file_id", ["seq_id", "read_no"], (512, 8192)).withColumnRenamed("spec", "hash")
    return out.groupBy("hash").agg(F.sum("accesses").alias("accesses"), (F.sum("l1_misses") / F.sum("accesses")).alias("l1_rate"), (F.sum("last_misses") / F.sum("accesses")).alias("last_rate"))


def _metrics_sql(spec):
    return f"SELECT '{spec.hash}' AS hash, count(*)::BIGINT AS probe_rows, (SELECT count(*) FROM (SELECT DISTINCT rep, bit // 32768 FROM places))::BIGINT AS pages, (SELECT count(*) * 4096 FROM (SELECT DISTINCT rep, bit // 32768 FROM places))::BIGINT AS page_bytes FROM (SELECT DISTINCT query_id, rep, bit // 32768 FROM places)"


HASHES = ("uniform", "sketch", "anchored")


@register("plan_metrics", "WITH " + SEQS + ",\n" + POISON + ",\n" + QUERY_GRAMS + "".join(",\n" + f"{h} AS (WITH " + _places_sql(SPEC.with_(hash=h), "qs", "query_id").strip().strip(",") + " " + _metrics_sql(SPEC.with_(hash=h)) + ")" for h in HASHES) + " " + " UNION ALL ".join(f"SELECT * FROM {h}" for h in HASHES))
def plan_metrics(spark, d):
    """What a probe of all queries moves: rows that are shuffled, pages that are read, and their bytes."""
    asked, out = _queries(spark, d), None
    for h in HASHES:
        probes = filters.group_probes(asked, SPEC.with_(hash=h))
        got = probes.agg(F.count(F.lit(1)).alias("probe_rows"), F.countDistinct("rep", "page_no").alias("pages")).select(F.lit(h).alias("hash"), "probe_rows", "pages", (F.col("pages") * 4096).alias("page_bytes"))
        out = got if out is None else out.unionByName(got)
    return out


# ---------------------------------------------------------------- many sets

def _rates(spark, found, truth, n_pairs):
    """(true_pairs, false_pairs, pooled rate, missed pairs) of the pairs that an index reports."""
    both = found.withColumn("_f", F.lit(1)).join(truth.withColumn("_t", F.lit(1)), ["query_id", "file_id"], "full")
    got = both.agg(F.count("_t").alias("t"), F.count(F.when(F.col("_t").isNull(), 1)).alias("f"), F.count(F.when(F.col("_f").isNull(), 1)).alias("lost")).first()
    return got.t, got.f, got.f / max(1, n_pairs - got.t), got.lost


MANY = "index string, hash string, m long, eta int, L int, index_s double, query_s double, disk_query_s double, negatives long, false_pairs long, missed_pairs long, fpr double, stored_pages long"


def _many(spark, d, rows, kind, specs):
    """A row a spec: an index of many files built, searched from memory and from disk, and held against exact pairs."""
    from .sources import index_store

    rows, asked = rows.persist(), _queries(spark, d).persist()
    truth = baselines.exact_pairs(rows, asked, K).persist()
    n_pairs = asked.count() * rows.select("file_id").distinct().count()
    out = []
    warmed = False
    for spec in specs:
        def make(spec=spec):
            return bucket_grid.build(rows, spec, 20, 2) if kind == "grid" else file_matrix.build(rows, spec, "files")

        def pages_of(index):
            return index.pages if kind == "grid" else index.rows

        def ask(index, stored):
            if kind == "grid":
                return bucket_grid.file_hits(bucket_grid.BucketGrid(stored, index.buckets, index.files, index.spec, 20, 2), asked)
            return file_matrix.hits(file_matrix.FileMatrix(stored, index.files, index.spec, "files"), asked)

        index = make()
        if not warmed:  # starts Python workers and compiles code; not timed
            measures.timed(ask(index, pages_of(index)))
            warmed = True
        stored = pages_of(index).persist()
        index_s = measures.timed(stored)["mean"]
        n_pages = stored.count()
        found = ask(index, stored).persist()
        query_s = measures.timed(found)["mean"]
        t, f, rate, lost = _rates(spark, found, truth, n_pairs)
        path = index_store.scratch(spark, "many")
        index_store.write_index(stored, spec, path)
        disk_s = measures.timed(ask(index, index_store.read_index(spark, path, spec)[0]))["mean"]
        for df in (found, stored):
            df.unpersist()
        out.append((kind, spec.hash, spec.m, spec.eta, spec.L, index_s, query_s, disk_s, n_pairs - t, f, lost, rate, n_pages))
    for df in (truth, asked, rows):
        df.unpersist()
    return spark.createDataFrame(out, MANY)


def grid_table(spark, d):
    """Bucket grid of 20 buckets and 2 repetitions, 4 functions: four sizes, uniform against anchored with two L."""
    variants = [("uniform", 2048), ("anchored", 2048), ("anchored", 4096)]
    sizes = (1 << 20, 1 << 21, 3 << 20, 1 << 22)
    return _many(spark, d, _grid_reads(spark, d), "grid", [FAST.with_(hash=h, m=m, L=L) for m in sizes for h, L in variants])


def matrix_sweep(spark, d):
    """File matrix of all sources: four sizes, both hashes, in memory and from disk."""
    return _many(spark, d, reads(spark, d, "source"), "matrix", [FAST.with_(hash=h, m=m, L=2048) for m in (1 << 18, 1 << 19, 1 << 20, 1 << 21) for h in ("uniform", "anchored")])


__all__ = ["QUERIES", "SQL", "points", "rounds"]
