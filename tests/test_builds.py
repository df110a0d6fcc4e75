"""Page building by density, roads of sketches, families, and the short way to an index."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from anchorseek.functions import anchored, kernel, sketch, views
from anchorseek.index import Index
from anchorseek.operators import workload
from anchorseek.plans.spec import IndexSpec
from anchorseek.shipping import ship

SF = "/root/testdata/sf0.001"


def slice_of(n, files=1):
    r = random.Random(1)
    seqs = ["".join(r.choice("ACGT") for _ in range(230)) for _ in range(n)]
    return pa.RecordBatch.from_arrays([pa.array([f"f{i % files}" for i in range(n)]), pa.array(seqs)], names=["filter_id", "seq"])


@pytest.mark.parametrize("m", [1 << 20, 1 << 27, 1 << 34])
@pytest.mark.parametrize("files", [1, 40])
def test_what_is_shipped_grows_with_the_bits(m, files):
    import tracemalloc

    batch = slice_of(2000, files)
    spec = IndexSpec(m=m, eta=4, hash="uniform")
    codes, offsets = kernel.symbols(batch.column("seq"))
    at, owner = kernel.valid_places(codes, offsets, spec.k)
    want = {(f"f{o % files}", spec.rep_of(j), int(p)) for j, pos in enumerate(kernel.positions(codes, spec)) for o, p in zip(owner.tolist(), pos[at].tolist())}
    tracemalloc.start()
    out = list(kernel.page_builder(spec)(iter([batch])))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    size = sum(sum(map(len, b.column("bits").to_pylist())) for b in out)
    assert size <= 2 * len(want) and peak < 300 << 20
    rows = sorted((r for b in out for r in b.to_pylist()), key=lambda r: (r["filter_id"], r["rep"], r["page_no"]))
    merged = pa.RecordBatch.from_pylist(rows, out[0].schema)
    got = {(r["filter_id"], r["rep"], r["page_no"] * 32768 + int(o)) for b in kernel.page_merger(iter([merged])) for r in b.to_pylist() for o in np.flatnonzero(np.unpackbits(np.frombuffer(r["bits"], np.uint8), bitorder="little"))}
    assert got == want


def test_full_tasks_hand_on(monkeypatch):
    spec = IndexSpec(m=1 << 22, eta=2, L=512)
    whole = {tuple(r.values()) for b in kernel.page_merger(kernel.page_builder(spec)(iter([slice_of(500)]))) for r in b.to_pylist()}
    monkeypatch.setattr(kernel, "TASK_BITS", 5000)
    monkeypatch.setattr(kernel, "SLICE_SYMBOLS", 5000)
    rows = sorted((r for b in kernel.page_builder(spec)(iter([slice_of(500)])) for r in b.to_pylist()), key=lambda r: (r["filter_id"], r["rep"], r["page_no"]))
    schema = pa.schema([("filter_id", pa.string()), ("rep", pa.int32()), ("page_no", pa.int64()), ("dense", pa.bool_()), ("bits", pa.binary())])
    again = {tuple(r.values()) for b in kernel.page_merger(iter([pa.RecordBatch.from_pylist(rows, schema)])) for r in b.to_pylist()}
    assert again == whole and len(rows) > len(whole)


@pytest.fixture(scope="module")
def reads(spark):
    ship(spark)
    return views.to_reads(views.dna_sequences(spark.read.parquet(f"{SF}/documents.parquet"), file_id="source"), 31).cache()


@pytest.mark.parametrize("kind", ["plain", "matrix", "grid"])
def test_short_way_finds_members_and_keeps_indexes(spark, reads, kind, tmp_path):
    spec = IndexSpec(m=1 << 22, eta=2)
    twins = workload.clean_twins(workload.poison(reads, 31))
    index = Index(spec, kind).fit(reads)
    keys = ["query_id"] if kind == "plain" else ["query_id", "file_id"]
    members = twins.select("query_id", F.col("origin_file").alias("file_id")).select(*keys)
    asked = twins.select("query_id", "seq")
    assert members.join(index.search(asked).where("hit"), keys, "left_anti").count() == 0
    index.save(str(tmp_path / kind))
    held = Index.load(spark, str(tmp_path / kind))
    assert held.kind == kind and sorted(map(tuple, held.search(asked).collect())) == sorted(map(tuple, index.search(asked).collect()))


@pytest.mark.parametrize("eta,oph", [(1, False), (2, False), (3, True)])
def test_naive_road_gives_the_same_positions(reads, eta, oph):
    spec = IndexSpec(m=1 << 20, eta=eta, oph=oph, L=1024)
    few = reads.where("seq_id < 5")
    mark = lambda s: anchored.gram_positions(few, s).agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("seq_id", "read_no", "pos", "rep", "bit"))).first()
    assert mark(spec) == mark(spec.with_(backend="naive"))


def test_families_collide_as_often_as_similar(spark):
    r = np.random.default_rng(3)
    a = r.normal(size=16)
    rows = [(i, a.tolist(), (a + r.normal(size=16) * s).tolist()) for i, s in enumerate([0.05] * 40 + [3.0] * 40)]
    df = spark.createDataFrame(rows, "id long, a array<double>, b array<double>")
    for lsh in (sketch.SignProjections(16, 4), sketch.StableProjections(16, 2.0)):
        same = sum((F.when(lsh.phi(F.col("a"), s) == lsh.phi(F.col("b"), s), 1).otherwise(0) for s in range(5)), F.lit(0))
        near, far = (x[0] for x in df.groupBy((F.col("id") < 40).alias("n")).agg(F.avg(same).alias("s"), F.avg(lsh.similarity(F.col("a"), F.col("b"))).alias("t")).orderBy(F.desc("n")).select(F.struct("s", "t")).collect())
        assert near.s > far.s and near.t > far.t
    sets = spark.createDataFrame([(["x", "y"], ["x", "y"]), (["x", "y"], ["z"])], "a array<string>, b array<string>")
    lsh = sketch.MinwiseSets()
    got = sets.select((lsh.phi(F.col("a"), 1) == lsh.phi(F.col("b"), 1)).alias("e"), lsh.similarity(F.col("a"), F.col("b")).alias("s"), anchored.placed(F.lit("k"), F.col("a"), lsh, 1 << 20, 64).alias("p")).collect()
    assert [(x.e, x.s) for x in got] == [(True, 1.0), (False, 0.0)] and all(0 <= x.p < 1 << 20 for x in got)


def test_parameters_without_effect_are_refused():
    for bad in ({"family": "tabulated"}, {"backend": "window"}, {"lsh": "sign_projection"}):
        with pytest.raises(ValueError):
            IndexSpec(**bad)


@pytest.mark.parametrize("n", [0, 1, 2, 1000])
def test_distinct_values_are_sorted(n):
    x = np.random.default_rng(n).integers(0, 300, n)
    assert kernel.distinct(x).tolist() == sorted(set(x.tolist()))
