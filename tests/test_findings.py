"""Small cases of findings on large or odd inputs."""

from anchorseek import workloads
from anchorseek.operators import measures
from anchorseek.shipping import ship

SF = "/root/testdata/sf0.001"


def test_reads_without_a_gram_are_not_similar(spark):
    whole = "ACGTTGCAACGTTGCATTGACCATGGATCAAGG"
    reads = spark.createDataFrame([(1, 0, whole[:20]), (2, 0, whole[:30])], "seq_id long, read_no int, seq string")
    asked = spark.createDataFrame([(7, whole)], "query_id long, seq string")
    assert measures.similar_count(reads, asked, 31, 16).collect() == []
    more = reads.union(spark.createDataFrame([(3, 0, whole)], reads.schema))
    assert [tuple(r) for r in measures.similar_count(more, asked, 31, 16).collect()] == [(7, 3)]


def test_closed_forms_read_documents(spark):
    ship(spark)
    for name, rows in (("fpr_formula_table", 9), ("bound_table", 9), ("hash_cost_table", 24)):
        got = workloads.QUERIES[name](spark, SF)
        assert got.inputFiles() and got.count() == rows * workloads.docs(spark, SF, "source").select("file_id").distinct().count()


def test_runs_answer_as_strings_do(spark):
    import random

    from anchorseek.functions import runs
    from anchorseek.operators import baselines

    ship(spark)
    r = random.Random(4)
    seqs = ["".join(r.choice("ACGT") for _ in range(r.choice((0, 5, 30, 31, 32, 90, 230)))) for _ in range(60)] + ["A" * 600, "AC" * 60]
    reads = spark.createDataFrame([(f"f{i % 70}", s) for i, s in enumerate(seqs)] + [(f"f{i}", "ACGT") for i in range(70)] + [("f1", None)], "file_id string, seq string")
    pieces = [(i, s[:n]) for i, (s, n) in enumerate((s, n) for s in seqs for n in (31, 40, 80))] + [(900, "A" * 300), (901, seqs[9][:20] + seqs[10][:60]), (902, ""), (903, None)]
    asked = spark.createDataFrame(pieces, "query_id long, seq string")
    rows = lambda df: sorted(map(tuple, df.collect()))
    for k in (31, 12, 4):
        assert rows(baselines.exact_mt(reads, asked, k, "dna")) == rows(baselines.exact_mt(reads, asked, k))
        assert rows(baselines.exact_msmt(reads, asked, k, "dna")) == rows(baselines.exact_msmt(reads, asked, k))
    shipped = sum(len(x.sizes) + len(x.symbols) for x in spark.createDataFrame([(0, s) for s in seqs], "id long, seq string").mapInArrow(runs.builder(31, 1), runs.SCHEMA).collect())
    assert shipped < 3 * sum(max(0, len(s) - 30) for s in seqs)  # not 31 letters a gram


def test_cache_and_locality_without_traces(spark):
    """Same figures as from whole traces, and no access goes through a shuffle."""
    from pyspark.sql import functions as F

    from anchorseek.functions import anchored
    from anchorseek.plans import cachesim

    ship(spark)
    rows = workloads.reads(spark, SF, "source").where("seq_id < 60")
    flat = lambda df: sorted(map(tuple, df.collect()))
    for h, layout in (("anchored", "partitioned"), ("uniform", "partitioned"), ("sketch", "shared"), ("anchored", "shared")):
        spec = workloads.FAST.with_(hash=h, m=1 << 18, L=512, layout=layout)
        q = rows.select(F.expr("seq_id * 1000 + read_no").alias("query_id"), "seq")
        trace = anchored.gram_positions(q, spec, ["query_id"])
        for bits in (32768, 512):
            assert flat(measures.probe_locality(q, spec, bits)) == flat(measures.locality(trace, bits=bits))
        if layout == "partitioned":
            got = cachesim.gram_miss_rates(rows, spec, "file_id", ["seq_id", "read_no"], (16, 64))
            want = cachesim.miss_rates(anchored.gram_positions(rows, spec), ["file_id"], ["seq_id", "read_no", "pos", "rep"], (16, 64))
            assert flat(got) == flat(want) and flat(want)


def test_similarity_by_gap_in_the_kernel(spark):
    import random

    ship(spark)
    r = random.Random(6)
    seqs = ["".join(r.choice("ACGT") for _ in range(n)) for n in (0, 15, 30, 31, 32, 40, 62, 230)] + ["A" * 90, "AC" * 50, "ACGTTGCAGGTACCATTGA" * 8, None]
    reads = spark.createDataFrame([(s,) for s in seqs], "seq string")
    for k, t in ((31, 16), (12, 3), (8, 8)):
        got, want = ({x.gap: x for x in measures.jaccard_by_gap(reads, k, t, alphabet=a).collect()} for a in ("dna", "any"))
        assert got.keys() == want.keys() and all(got[g].pairs == want[g].pairs and abs(got[g].mean_jaccard - want[g].mean_jaccard) < 1e-9 for g in want)


def test_native_filters_by_part(spark):
    """More grams than one filter is sized for: parts keep the rate; the numpy test is the plan's own."""
    import random

    import numpy as np
    from pyspark.sql import functions as F

    from anchorseek.functions import native
    from anchorseek.operators import baselines

    ship(spark)
    one = native.bloom_filter(spark.range(0, 3000, 3), F.col("id") * 987654321987 - 5, 1000, 4096)
    asked = spark.range(3000).select((F.col("id") * 987654321987 - 5).alias("v"))
    want = [r.h for r in asked.select("v", native.might_contain(one, F.col("v")).alias("h")).orderBy("v").collect()]
    got = native.holds(bytes(one.first()[0]), np.array([i * 987654321987 - 5 for i in range(3000)], np.int64))
    assert got.tolist() == want and 1000 < sum(want) < 2500
    r = random.Random(8)
    draw = lambda n: "".join(r.choice("ACGT") for _ in range(n))
    seqs = [draw(230) for _ in range(400)]
    reads = spark.createDataFrame([(s,) for s in seqs] + [("ACG",), (None,)], "seq string")
    queries = spark.createDataFrame([(i, s[9:80]) for i, s in enumerate(seqs)] + [(1000 + i, draw(31)) for i in range(2000)] + [(5000, "AC"), (5001, None)], "query_id long, seq string")
    hits = lambda df: {x.query_id for x in df.where("hit").collect()}
    parts, single = hits(baselines.native_mt_parts(reads, queries, 31, 2000, 1 << 14)), hits(baselines.native_mt(baselines.native_filter(reads, 31, 2000, 1 << 14), queries, 31))
    members = {*range(400), 5000, 5001}
    assert members <= parts and members <= single
    assert len(parts - members) < 200 and len(single - members) > 1500  # one filter of that size is full


def test_collisions_of_grams_in_runs(spark):
    """Same figures as from a row a gram; the plan shuffles runs and counters, not letters."""
    import random

    from pyspark.sql import functions as F

    from anchorseek.functions import grams, hashing

    ship(spark)
    r = random.Random(3)
    seqs = ["".join(r.choice("ACGT") for _ in range(r.choice((0, 30, 31, 230)))) for _ in range(90)]
    reads = spark.createDataFrame([(s,) for s in seqs * 2 + ["A" * 300, "AC" * 90, None]], "seq string")
    for k, m in ((31, 1 << 10), (31, 40_001), (5, 7)):
        slow = measures.collision_rate(grams.explode_grams(reads, "seq", k).select("gram"), "gram", hashing.uniform(F.col("gram"), 9, m, "md5"))
        fast = measures.gram_collision_rate(reads, k, 9, m)
        assert fast.schema == slow.schema and fast.collect() == slow.collect() and fast.first().colliding > 0
    none = measures.gram_collision_rate(reads.limit(0), 31, 9, 100).first()
    assert none.keys is None and none.rate is None
    plan = workloads.QUERIES["collision_rates"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "symbols" in plan and "md5" not in plan.split("symbols")[0]


def test_dealt_queries_answer_as_joins_do(spark):
    """Small indexes: every query meets all pages in one task; answers are those of the joins, nothing else is shuffled."""
    import random

    from anchorseek.operators import file_matrix, filters

    ship(spark)
    r = random.Random(9)
    seqs = ["".join(r.choice("ACGT") for _ in range(230)) for _ in range(40)]
    reads = spark.createDataFrame([(f"f{i % 7}", s) for i, s in enumerate(seqs)] + [("f8", "ACGT")], "file_id string, seq string")
    asked = spark.createDataFrame([(i * 1000 + a, s[a : a + n]) for i, s in enumerate(seqs) for a, n in ((0, 31), (9, 80), (200, 30))] + [(90_000 + i, s[:40] + seqs[0][:40]) for i, s in enumerate(seqs)] + [(990, ""), (991, None), (992, "N" * 50)], "query_id long, seq string")
    rows = lambda df: sorted(map(repr, df.collect()))
    for changes in ({"hash": "uniform", "eta": 3, "m": 100_000}, {"layout": "shared", "empty_query": "null"}):
        spec = workloads.SPEC.with_(m=1 << 16, L=512).with_(**changes)
        one = filters.build(reads, spec)
        assert filters.fits(spec)
        new, old = (filters.contains(one, asked, spec, broadcast=b) for b in (None, True))
        assert rows(new) == rows(old) == rows(filters.contains(one, asked, spec.with_(exit="kernel"))) and new.where("hit").count() < 140  # of 163
        assert rows(filters.probe_grams(one, asked, spec)) == rows(filters.probe_grams(one, asked, spec, broadcast=False))
        few, mask = file_matrix.build(reads, spec), file_matrix.build(reads, spec, "mask")
        assert (few.layout, few.few, mask.few) == ("files", 8, None)
        joined = file_matrix.FileMatrix(few.rows, few.files, spec, "files")
        assert rows(file_matrix.search(few, asked)) == rows(file_matrix.search(joined, asked)) == rows(file_matrix.search(mask, asked))
        assert rows(file_matrix.hits(few, asked)) == rows(file_matrix.hits(joined, asked))
        assert rows(file_matrix.coverage(few, asked)) == rows(file_matrix.coverage(mask, asked))
        assert rows(file_matrix.top(few, asked, 2)) == rows(file_matrix.top(mask, asked, 2))
    plan = new._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan
    none = filters.build(reads.limit(0), spec)
    assert not filters.contains(none, asked, spec).where("hit").count()


def test_small_arrays_leave_a_task_once(monkeypatch):
    """However many symbols a task reads, it hands on each page of few arrays once; others give the same bits."""
    import random

    import numpy as np
    import pyarrow as pa

    from anchorseek.functions import kernel

    r = random.Random(12)
    batches = [pa.RecordBatch.from_pydict({"filter_id": [f"f{(i + b) % 5}" for i in range(40)], "seq": ["".join(r.choice("ACGT") for _ in range(200)) for _ in range(40)]}) for b in range(6)]
    spec = workloads.FAST.with_(eta=2, m=1 << 18, L=512)

    def pages(tally):
        rows = [x for b in kernel.page_builder(spec, tally)(iter(batches)) for x in b.to_pylist()]
        bits = {(x["filter_id"], x["rep"], x["page_no"], int(o)) for x in rows for o in (np.flatnonzero(np.unpackbits(np.frombuffer(x["bits"], np.uint8), bitorder="little")) if x["dense"] else np.frombuffer(x["bits"], "<u2"))}
        return len(rows), bits, [sum(x[c] for x in rows) for c in ("n", "total")] if tally else None

    monkeypatch.setattr(kernel, "TASK_BITS", 2000)
    monkeypatch.setattr(kernel, "SLICE_SYMBOLS", 3000)
    monkeypatch.setattr(kernel, "FLAGS", 1000)
    n, bits, sums = pages(True)
    assert n <= 5 * spec.pages and pages(False)[1] == bits and sums[0] == 6 * 40 * 170 * 2
    for few in (0, 263):  # never flags; flags until a third filter comes
        monkeypatch.setattr(kernel, "FLAGS", few)
        more, same, again = pages(True)
        assert same == bits and again == sums and more > n


def test_levels_miss_as_the_cache_does():
    """Blocks of accesses miss what one access after another misses, and the repeats of a run need not be seen."""
    import numpy as np

    from anchorseek.plans import cachesim

    r = np.random.default_rng(2)
    for n, sizes in ((3000, (1, 3)), (4000, (16, 64)), (9000, (40, 70)), (30_000, (512, 2048))):
        for high in (3 * sizes[0], 9 * sizes[1], 1 << 50):
            near = np.cumsum(r.integers(-2, 3, n)) % high
            far = np.where(r.random(n) < 0.1, r.integers(0, high, n), near)
            for lines in (r.integers(0, high, n), near, far, np.repeat(far, r.geometric(0.02, n))[:n]):
                cache, made = cachesim.Cache(sizes), cachesim.levels(sizes)
                cache.run(lines.tolist())
                for part in np.array_split(lines, 3):
                    made[0].run(part)
                    made[0].settle(False)
                made[0].settle()
                assert [level.misses for level in made] == cache.misses
                grams = np.stack([np.repeat(lines, r.geometric(0.2, n))[:n] * 4 + j for j in range(4)], axis=1)
                cache, made = cachesim.Cache(sizes), cachesim.levels(sizes)
                cache.run(grams[:5_000].ravel().tolist())
                made[0].run(grams[:5_000][cachesim._edges(grams[:5_000], sizes[0] // 4 - 2)])
                made[0].settle()
                assert [level.misses for level in made] == cache.misses


def test_index_misses_share_a_pass(spark):
    """All hashes in one shuffle of the reads, with the figures of one hash at a time."""
    from anchorseek import experiments
    from anchorseek.plans import cachesim

    ship(spark)
    rows = workloads.reads(spark, SF, "source").where("seq_id < 60")
    specs = {h: workloads.FAST.with_(hash=h, m=1 << 20, k=k) for h, k in (("sketch", 31), ("uniform", 20), ("anchored", 31))}
    got = cachesim.gram_miss_rates(rows, specs, "file_id", ["seq_id", "read_no"], (16, 64))
    one = {h: cachesim.gram_miss_rates(rows, s, "file_id", ["seq_id", "read_no"], (16, 64), ways=64) for h, s in specs.items()}  # one access after another
    for h in specs:
        assert sorted(map(tuple, got.where(f"spec = '{h}'").drop("spec").collect())) == sorted(map(tuple, one[h].collect()))
    plan = experiments.QUERIES["index_miss_rates"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == 1


def test_sweeps_share_their_passes(spark):
    """Filters, answers, rates and localities of several specs at once are those of one spec at a time; a sweep makes
    positions in three passes, whatever the number of its specs."""
    import random

    from pyspark.sql import functions as F

    from anchorseek.operators import filters, measures

    ship(spark)
    r = random.Random(14)
    seqs = ["".join(r.choice("ACGT") for _ in range(230)) for _ in range(60)] + ["A" * 230, "ACGT" * 40]
    reads = spark.createDataFrame([("f", s) for s in seqs] + [("f", "ACGT"), ("f", None)], "file_id string, seq string").repartition(2)
    asked = spark.createDataFrame([(i * 10 + a, s[a : a + n]) for i, s in enumerate(seqs) for a, n in ((0, 31), (9, 80), (3, 30))] + [(90_000 + i, s[:40] + seqs[0][:40]) for i, s in enumerate(seqs)] + [(5, None)], "query_id long, seq string").repartition(2)
    base = workloads.FAST.with_(m=1 << 16, L=512)
    specs = [base, base.with_(hash="sketch", m=1 << 17), base.with_(hash="uniform", eta=3, m=100_000), base.with_(L=64, align="page", layout="shared", empty_query="null"), base.with_(k=20, t=9, oph=False, eta=2), base.with_(family="modprime", eta=1), base.with_(family="md5", eta=2, densify="random")]
    truth = asked.select("query_id", F.expr("query_id % 3 = 0").alias("hit"))
    rows = lambda df: sorted(map(repr, df.collect()))
    index = filters.build_each(reads, specs).cache()
    hits = filters.contains_each(index, asked, specs).cache()
    rates, met = measures.fpr_mt_each(hits, truth, len(specs)).collect(), measures.probe_localities(asked, specs, [32768, 512]).cache()
    for i, spec in enumerate(specs):
        one = filters.build(reads, spec)
        assert rows(index.where(F.col("filter_id") == str(i)).drop("filter_id")) == rows(one.drop("filter_id"))
        answers = filters.contains(one, asked, spec)
        assert rows(hits.select("query_id", F.element_at("hits", i + 1).alias("hit"))) == rows(answers)
        assert [tuple(x)[1:] for x in rates if x.number == i] == [tuple(measures.fpr_mt(answers, truth).first())]
        assert rows(met.where(f"number = {i} AND block = 512").drop("number", "block")) == rows(measures.probe_locality(asked, spec, 512))
    assert tuple(measures.probe_locality(asked.where("query_id < 0"), base).first()) == (None,) * 5
    plan = workloads.QUERIES["fpr_by_hash_table"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == 7  # builder, merger, prober, localities, and three of the exact answer
