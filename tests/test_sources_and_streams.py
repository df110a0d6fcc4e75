"""Index files, sources, streams, and user functions."""

import pytest
from pyspark.sql import functions as F

from anchorseek.functions import views
from anchorseek.operators import filters, pages
from anchorseek.plans.spec import IndexSpec
from anchorseek.shipping import ship
from anchorseek.sources import formats, index_store
from anchorseek.streaming import index_stream

SF = "/root/testdata/sf0.001"
SPEC = IndexSpec(m=1 << 18, eta=2, L=256)


@pytest.fixture(scope="module")
def reads(spark):
    ship(spark)
    return views.to_reads(views.dna_sequences(spark.read.parquet(f"{SF}/documents.parquet").where("doc_id < 30")), 31).cache()


def bits(df):
    return sorted((r.filter_id, r.rep, r.page_no, bytes(r.bits)) for r in df.collect())


def test_index_round_trip(spark, reads, tmp_path):
    index = filters.build(reads, SPEC)
    index_store.write_index(index, SPEC, str(tmp_path / "i"))
    got, spec = index_store.read_index(spark, str(tmp_path / "i"), SPEC)
    assert spec == SPEC and bits(got) == bits(index)
    with pytest.raises(ValueError):
        index_store.read_index(spark, str(tmp_path / "i"), SPEC.with_(L=128))


def test_union_needs_equal_parameters(reads):
    with pytest.raises(ValueError):
        filters.union(filters.build(reads, SPEC), filters.build(reads, SPEC), SPEC, SPEC.with_(seed=1))


def test_stream_builds_and_probes(spark, reads, tmp_path):
    reads.repartition(3).write.parquet(str(tmp_path / "in"))
    source = lambda: spark.readStream.schema(reads.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    index_stream.incremental_build(source(), SPEC, str(tmp_path / "out"), str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    fed = index_stream.merged(spark, str(tmp_path / "out"))
    whole = filters.build(reads, SPEC)
    assert bits(fed) == bits(whole)
    assert bits(pages.union(fed, fed)) == bits(whole)  # a replayed batch changes nothing
    found = {}
    asked = source().select((F.col("seq_id") * 1000 + F.col("read_no")).alias("query_id"), "seq")
    index_stream.streaming_probe(asked, whole.cache(), SPEC, lambda df, n: found.update({r.query_id: r.hit for r in df.collect()}), str(tmp_path / "d")).trigger(availableNow=True).start().awaitTermination()
    assert len(found) == reads.count() and all(found.values())


def test_formats(spark, tmp_path):
    (tmp_path / "a.fastq").write_text("@r1\nACGTACGT\n+\nIIIIIIII\n@r2 x\nTTTT\n+\nIIII\n")
    (tmp_path / "a.fasta").write_text(">s1 first\nACGT\nACGT\n>s2\nGG\n")
    assert sorted((r.name, r.seq) for r in formats.fastq(spark, str(tmp_path / "a.fastq")).collect()) == [("r1", "ACGTACGT"), ("r2", "TTTT")]
    assert sorted((r.name, r.seq) for r in formats.fasta(spark, str(tmp_path / "a.fasta")).collect()) == [("s1", "ACGTACGT"), ("s2", "GG")]
    part = spark.read.parquet(f"{SF}/part.parquet")
    for fmt in ("csv", "json", "orc", "parquet"):
        part.write.format(fmt).options(**({"header": True} if fmt == "csv" else {})).save(str(tmp_path / fmt))
        got = formats.read(spark, str(tmp_path / fmt), fmt, part.schema)
        assert sorted(got.collect()) == sorted(part.collect())


def test_user_functions_have_twins(spark, reads):
    from anchorseek import udfs
    from anchorseek.functions import grams, sketch

    udfs.register(spark)
    rows = reads.limit(50)
    a = rows.select(udfs.pack2_all("seq", F.lit(31)).alias("x")).collect()
    b = rows.select(F.transform(grams.gram_array(F.col("seq"), 31), grams.pack2).alias("x")).collect()
    assert [list(r.x) for r in a] == [list(r.x) for r in b]
    hashes = rows.select(F.transform(grams.gram_array(F.col("seq"), 16), lambda g: F.xxhash64(g)).alias("h"))
    got = hashes.select(udfs.rolling_min("h", F.lit(16)).alias("x"), sketch.rolling_min(F.col("h"), 16).alias("y")).collect()
    assert all(list(r.x) == list(r.y) for r in got)
    assert spark.sql("SELECT count(*) AS n FROM grams('ACGTACGT', 4)").first().n == 5
    bits_ = spark.createDataFrame([(0, 1), (0, 8), (1, 3)], "k int, o int")
    made = {r.k: bytes(r.p) for r in bits_.groupBy("k").agg(udfs.page_from_offsets("o").alias("p")).collect()}
    twin = {r.k: bytes(r.p) for r in bits_.groupBy("k").agg(F.bitmap_construct_agg(F.col("o").cast("long")).alias("p")).collect()}
    assert made == twin


def test_facade(spark, reads):
    from anchorseek.index import Index

    found = Index(SPEC).fit(reads).search(reads.select(F.col("seq_id").alias("query_id"), "seq").where(F.length("seq") > 40).dropDuplicates(["query_id"]))
    assert found.where("NOT hit").count() == 0
