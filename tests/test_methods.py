"""The methods against brute force and their stated properties."""

import math
import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from anchorseek.functions import anchored, grams, hashing, kernel, schemas, sketch, views
from anchorseek.operators import baselines, bucket_grid, file_matrix, filters, measures, pages, workload
from anchorseek.plans import cachesim, planner, theory
from anchorseek.plans.spec import IndexSpec
from anchorseek.shipping import ship

SF = "/root/testdata/sf0.001"


def dna(n, seed):
    r = random.Random(seed)
    return "".join(r.choice("ACGT") for _ in range(n))


@pytest.fixture(scope="module")
def reads(spark):
    ship(spark)
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("doc_id < 40")
    return views.to_reads(views.dna_sequences(docs, file_id="source"), 31).cache()


@pytest.fixture(scope="module")
def asked(reads):
    return workload.poison(reads, 31).cache()


def test_gram_counts_and_edges(spark):
    rows = [(None,), ("",), ("ACGTA",), ("ACGTAC",), ("ACGTACG",), ("é日本語x",)]
    got = [r.n for r in spark.createDataFrame(rows, "s string").select(F.size(grams.gram_array(F.col("s"), 6)).alias("n")).collect()]
    assert got == [0, 0, 0, 1, 2, 0]


def test_reads_keep_every_gram_once(spark):
    text = dna(1000, 1)
    seqs = spark.createDataFrame([("f", 1, text), ("f", 2, None), ("f", 3, "ACG")], "file_id string, seq_id long, seq string")
    got = sorted(r.gram for r in grams.explode_grams(views.to_reads(seqs, 31, 100), "seq", 31).collect())
    assert got == sorted(text[i : i + 31] for i in range(970))


def test_pack_limits(spark):
    got = spark.createDataFrame([("T" * 31,), ("ACGT",), ("ACGN",)], "g string").select(grams.pack2(F.col("g")).alias("v")).collect()
    assert [r.v for r in got] == [(1 << 62) - 1, 27, None]


@pytest.mark.parametrize("width", [1, 3, 16, 20, 28])
def test_sliding_minimum_roads(spark, width):
    r = np.random.default_rng(width)
    h = r.integers(0, 1 << 40, 200)
    want = [int(h[i : i + width].min()) for i in range(200 - width + 1)]
    assert kernel.sliding_min(h, width).tolist() == want == kernel.tree_min(h, width).tolist()
    df = spark.createDataFrame([(h.tolist(),)], "h array<long>")
    assert df.select(sketch.rolling_min(F.col("h"), width).alias("m")).first().m == want


@pytest.mark.parametrize("hash_", ["uniform", "sketch", "anchored"])
@pytest.mark.parametrize("eta,oph,layout,align,densify", [(4, True, "partitioned", "free", "rotate"), (2, False, "shared", "page", "rotate"), (3, True, "partitioned", "free", "random"), (1, True, "partitioned", "free", "rotate")])
def test_kernel_equals_expressions(reads, hash_, eta, oph, layout, align, densify):
    spec = IndexSpec(m=1 << 20, eta=eta, oph=oph, layout=layout, align=align, densify=densify, hash=hash_, L=1024)
    mark = lambda s: anchored.gram_positions(reads, s).agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("seq_id", "read_no", "pos", "rep", "bit")), F.min("bit"), F.max("bit")).first()
    a, b = mark(spec), mark(spec.with_(backend="sql"))
    assert a == b and 0 <= a[2] and a[3] < spec.range


def test_oracle_anchor(spark):
    """Figures fixed before the engine was written."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("doc_id < 60")
    spec = IndexSpec(m=1 << 20, eta=1, seed=7, family="md5", backend="sql", L=4096)
    got = anchored.gram_positions(views.to_reads(views.dna_sequences(docs), 31), spec)
    assert tuple(got.agg(F.count(F.lit(1)), F.countDistinct("bit"), F.sum("bit"), F.countDistinct(F.shiftright("bit", 15))).first()) == (111071, 102832, 57613440101, 32)


def test_numpy_hash_is_sparks(spark):
    values = [0, 1, -1, 1 << 61, 12345678901234]
    want = [r.h for r in spark.createDataFrame([(v,) for v in values], "v long").select(F.xxhash64(F.lit(9).cast("long"), "v").alias("h")).collect()]
    assert hashing.xx64_seeded(np.array(values, np.int64), 9).tolist() == want


def test_sketch_collisions_follow_similarity():
    spec = IndexSpec(eta=1, L=64)
    a = dna(31, 5)
    b = a[1:] + "C"
    codes = [kernel.symbols(pa.array([s]))[0] for s in (a, b)]
    subs = [{s[i : i + 16] for i in range(16)} for s in (a, b)]
    similar = len(subs[0] & subs[1]) / len(subs[0] | subs[1])
    meet = np.mean([kernel.sketches(codes[0], spec.with_(seed=s))[0][0] == kernel.sketches(codes[1], spec.with_(seed=s))[0][0] for s in range(2000)])
    assert abs(meet - similar) < 4 * math.sqrt(similar * (1 - similar) / 2000)
    oph = spec.with_(eta=4, oph=True)
    meet = np.mean([[kernel.sketches(codes[0], oph.with_(seed=s))[j][0] == kernel.sketches(codes[1], oph.with_(seed=s))[j][0] for j in range(4)] for s in range(1500)])
    assert abs(meet - similar) < 5 * math.sqrt(similar * (1 - similar) / 6000)


def test_rehash_and_family_bounds():
    r = np.random.default_rng(0)
    m, L, n = 1000, 50, 200_000
    equal = r.random(n) < 0.3
    x, y = r.integers(0, 20, n), r.integers(0, 20, n)
    meet = np.where(equal, True, x == y).mean()
    assert abs(meet - theory.rehash_collision(0.3, 20)) < 0.01
    anchors = r.integers(0, m - L + 1, (2, n))
    offsets = r.integers(0, L, (2, n))
    far = (np.abs(anchors[0] + offsets[0] - anchors[1] - offsets[1]) < L).mean()
    b = theory.family_bounds(1.0, 0.0, m, L)
    assert b["far"] < far <= b["far_true"] + 0.003  # the printed bound leaves out offsets that reach back
    gap = np.abs(offsets[0] - offsets[1])
    assert abs(((gap > 0) & (gap < L)).mean() - b["near"]) < 0.005


@pytest.mark.parametrize("hash_", ["uniform", "sketch", "anchored"])
def test_no_false_negatives(spark, reads, asked, hash_):
    spec = IndexSpec(m=1 << 20, eta=3, hash=hash_, L=1024)
    twins = workload.clean_twins(asked).select("query_id", "seq")
    index = filters.build(reads, spec, filter_id="seq_id").withColumn("filter_id", F.lit("x"))
    index = pages.union(index)
    assert filters.contains(index, twins, spec).where("NOT hit").count() == 0
    matrix = file_matrix.search(file_matrix.build(reads, spec), twins)
    own = asked.select("query_id", F.col("origin_file").alias("file_id"))
    assert matrix.join(own, ["query_id", "file_id"]).where("NOT hit").count() == 0
    grid = bucket_grid.search(bucket_grid.build(reads, spec, 4, 2), twins)
    assert grid.join(own, ["query_id", "file_id"]).where("NOT hit").count() == 0


def test_answers_hold_the_exact_ones(reads, asked):
    spec = IndexSpec(m=1 << 19, eta=2, L=1024)
    q = asked.select("query_id", "seq")
    one = reads.withColumn("file_id", F.lit("all"))
    exact = baselines.exact_mt(reads, q, 31)
    got = filters.contains(filters.build(one, spec), q, spec)
    assert measures.missed(got, exact).count() == 0
    brute = {r.query_id: r.seq for r in q.collect()}
    known = {r.seq[i : i + 31] for r in reads.collect() for i in range(len(r.seq) - 30)}
    want = {k: all(s[i : i + 31] in known for i in range(len(s) - 30)) for k, s in brute.items()}
    assert {r.query_id: r.hit for r in exact.collect()} == want


def test_exits_combines_and_layouts_agree(reads, asked):
    spec = IndexSpec(m=1 << 19, eta=2, L=1024)
    q = asked.select("query_id", "seq").limit(300).cache()
    one = reads.withColumn("file_id", F.lit("all"))
    index = filters.build(one, spec).cache()
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    bits = lambda df: sorted((r.filter_id, r.rep, r.page_no, bytes(r.bits)) for r in df.collect())
    assert bits(index) == bits(filters.build(one, spec, combine="offsets")) == bits(filters.build(one, spec.with_(backend="sql"), combine="bits"))
    want = rows(filters.contains(index, q, spec))
    for other in ("rounds", "kernel"):
        assert rows(filters.contains(index, q, spec.with_(exit=other))) == want
    assert rows(filters.contains(index, q, spec, broadcast=False)) == want
    assert rows(filters.contains(index, q, spec.with_(backend="sql"))) == want
    per = filters.probe_grams(index, q, spec).groupBy("query_id").agg(F.bool_and("hit").alias("hit"))
    assert rows(per.select("query_id", "hit")) == want
    wide = spec.with_(eta=1)
    first = rows(file_matrix.search(file_matrix.build(reads, wide, "mask"), q))
    assert first == rows(file_matrix.search(file_matrix.build(reads, wide, "bitmap"), q)) == rows(file_matrix.search(file_matrix.build(reads, wide, "files"), q))
    files = views.numbered_files(reads)
    own = files.select(F.lit(0).alias("grid_rep"), F.col("file_ord").cast("int").alias("bucket"), "file_id")
    alone = bucket_grid.build(reads, wide, files.count(), 1, own)
    assert rows(bucket_grid.search(alone, q)) == first


def test_many_files_take_bitmaps(spark):
    seqs = spark.createDataFrame([(f"f{i:03d}", i, dna(60, i)) for i in range(70)], "file_id string, seq_id long, seq string")
    spec = IndexSpec(m=1 << 18, eta=2, L=256)
    index = file_matrix.build(views.to_reads(seqs, 31), spec)
    assert index.layout == "bitmap"
    q = seqs.select(F.col("seq_id").alias("query_id"), "seq")
    hits = file_matrix.search(index, q).where("hit")
    assert {(r.query_id, r.file_id) for r in hits.collect()} >= {(i, f"f{i:03d}") for i in range(70)}
    assert hits.count() < 75


def test_empty_queries(spark, reads):
    spec = IndexSpec(m=1 << 24, eta=2, L=256)
    index = filters.build(reads.withColumn("file_id", F.lit("all")), spec)
    q = spark.createDataFrame([(1, ""), (2, None), (3, "ACGT"), (4, "A" * 40)], "query_id long, seq string")
    assert {r.query_id: r.hit for r in filters.contains(index, q, spec).collect()} == {1: True, 2: True, 3: True, 4: False}
    assert {r.query_id: r.hit for r in filters.contains(index, q, spec.with_(empty_query="null")).collect()}[1] is None
    with pytest.raises(Exception):
        filters.contains(index, q, spec.with_(empty_query="error")).collect()


def test_special_cases(reads, asked):
    base = IndexSpec(m=1 << 20, eta=1, L=1024)
    blocks = lambda s: measures.locality(anchored.gram_positions(asked.select("query_id", "seq"), s, ["query_id"])).first().blocks_per_access
    u, a, tk = blocks(base.with_(hash="uniform", m=1 << 24)), blocks(base.with_(m=1 << 24)), blocks(base.with_(t=31, m=1 << 24))
    assert a < 0.35 * u and abs(tk - u) < 0.1
    one = anchored.gram_positions(reads, base.with_(L=1)).agg(F.countDistinct("bit")).first()[0]
    pure = anchored.gram_positions(reads, base.with_(hash="sketch")).agg(F.countDistinct("bit")).first()[0]
    assert abs(one - pure) < 0.01 * pure


def test_rate_order_and_closed_form(spark):
    seqs = spark.createDataFrame([("all", i, dna(400, i)) for i in range(300)], "file_id string, seq_id long, seq string")
    rows = views.to_reads(seqs, 31)
    n = 300 * 370
    absent = spark.createDataFrame([(i, dna(31, 10_000 + i)) for i in range(4000)], "query_id long, seq string")
    rates = {}
    for h in ("uniform", "anchored"):
        spec = IndexSpec(m=1 << 19, eta=2, hash=h, L=2048)
        rates[h] = filters.contains(filters.build(rows, spec), absent, spec).agg(F.avg(F.col("hit").cast("double"))).first()[0]
    want = theory.fpr_uniform(1 << 19, n, 2)
    tolerance = 4 * math.sqrt(want * (1 - want) / 4000)
    assert abs(rates["uniform"] - want) < tolerance
    assert rates["anchored"] <= theory.fpr_anchored_bound(1 << 19, n, 2, 2048, 31, 256) + tolerance
    q = workload.poison(rows, 31).select("query_id", "seq").cache()
    truth = baselines.exact_mt(rows, q, 31).cache()
    poison = {}
    for h in ("uniform", "sketch", "anchored"):
        spec = IndexSpec(m=1 << 20, eta=4, hash=h, L=2048)
        poison[h] = measures.fpr_mt(filters.contains(filters.build(rows, spec), q, spec), truth).first().fpr
    assert poison["sketch"] > 3 * max(poison["anchored"], 0.001) and poison["anchored"] < poison["uniform"] + 0.05


def test_poison_changes_one_symbol(asked):
    for r in asked.limit(200).collect():
        diff = [i for i, (a, b) in enumerate(zip(r.seq, r.clean)) if a != b]
        assert diff == [r.poison_pos] and len(r.seq) == len(r.clean) > 31
        assert r.n_affected == sum(i <= r.poison_pos < i + 31 for i in range(len(r.seq) - 30))


def test_cache_simulator_traces():
    assert cachesim.simulate([0, 0, 0, 1, 0], (1, 2)) == [3, 2]
    assert cachesim.simulate(list(range(8)), (4, 8)) == [8, 8]
    assert cachesim.simulate([0, 1, 2, 0, 1, 2], (2, 3)) == [6, 3]
    assert cachesim.simulate([0, 2, 0, 2], (2,), ways=1) == [4]  # one set for all even lines


def test_planner_and_theory():
    spec = planner.choose(10**6, 1e-3)
    assert abs(theory.fpr_uniform(spec.m, 10**6, spec.eta) - 1e-3) < 3e-4 and spec.L <= 4096
    best = planner.tune_eta(1 << 24, 10**6, 4096, hash="uniform")[0]["eta"]
    assert abs(best - theory.best_eta(1 << 24, 10**6)) <= 1
    assert theory.hash_ops(31, 16, 4)["one_permutation"]["hashes"] == 5 and theory.hash_ops(31, 16, 4)["naive"]["hashes"] == 68
    assert theory.neighbour_jaccard(31, 16) == 15 / 17 and theory.similar_bound(31, 16) == 256
    assert theory.fpr_anchored_bound(100, 10, 4, 10, 31, 256) == 1.0


def test_spec_checks_and_schemas(spark):
    for bad in ({"t": 40}, {"L": 1 << 30}, {"eta": 0}, {"hash": "x"}, {"theta": 0}):
        with pytest.raises(ValueError):
            IndexSpec(**bad)
    assert IndexSpec.from_json(IndexSpec(seed=5).to_json()) == IndexSpec(seed=5)
    assert not IndexSpec().compatible(IndexSpec(L=64)) and IndexSpec(hash="uniform").compatible(IndexSpec(hash="uniform", L=64))
    with pytest.raises(ValueError):
        schemas.require(spark.createDataFrame([(1,)], "a int"), schemas.QUERIES)


def test_partitions_do_not_matter(reads, asked):
    spec = IndexSpec(m=1 << 18, eta=2, L=256)
    one = reads.withColumn("file_id", F.lit("all"))
    bits = lambda n: sorted((r.rep, r.page_no, bytes(r.bits)) for r in filters.build(one.repartition(n), spec).collect())
    assert bits(1) == bits(7) == bits(64)


def test_plans(reads, asked):
    spec = IndexSpec(m=1 << 20, eta=2, L=1024)
    index = filters.build(reads.withColumn("file_id", F.lit("all")), spec)
    plan = filters.contains(index, asked.select("query_id", "seq"), spec, broadcast=True)._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "BroadcastHashJoin" in plan
    sql = spec.with_(backend="sql", family="md5", eta=1)
    text = anchored.gram_positions(reads, sql)._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("md5(") == 3  # subgrams, anchors, offsets: each written once, kept once


def test_native_filter(spark, reads, asked):
    index = baselines.native_filter(reads, 31, 1_000_000, 1 << 24)
    exact = {r.query_id: r.hit for r in baselines.exact_mt(reads, asked, 31).collect()}
    got = {r.query_id: r.hit for r in baselines.native_mt(index, asked, 31).collect()}
    assert got.keys() == exact.keys() and all(got[q] for q, hit in exact.items() if hit)
    joined = baselines.native_bloom(reads, asked, 31, 1_000_000, 1 << 24)
    assert {r.query_id: r.hit for r in joined.collect()} == exact
    plan = joined._jdf.queryExecution().executedPlan().toString()
    assert "bloom_filter_agg" in plan and "might_contain" in plan
    none = baselines.native_mt(baselines.native_filter(reads.limit(0), 31), asked.limit(3), 31)
    assert not any(r.hit for r in none.collect())
    with pytest.raises(ValueError):
        baselines.native_filter(reads, 31, bits=1 << 27)
