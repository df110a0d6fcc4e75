"""Logic of the timed experiments on made-up points, and survivors-only refinement against the exact answer."""

from pyspark.sql import functions as F

from anchorseek import experiments
from anchorseek.operators import baselines, bucket_grid


def fake(spark, d, specs, runs):
    slow = {"uniform": 2.0, "anchored": 1.0}
    return [{"hash": s.hash, "m": s.m, "eta": s.eta, "t": s.t, "L": s.L, "runs": runs, "index_s": slow[s.hash] * s.m.bit_length(), "query_s": slow[s.hash] * s.m.bit_length(), "index_ms_per_read": 0.0, "query_ms": 0.0, "negatives": 10, "false_hits": 1, "fpr": 2.0**20 / s.m / s.eta, "pages": 1} for s in specs]


def test_fronts_and_growth(spark, monkeypatch):
    monkeypatch.setattr(experiments, "points", fake)
    rows = experiments.pareto_time_fpr(spark, None).collect()
    mine = [r for r in rows if r.hash == "uniform" and r.cost == "query_s"]
    assert mine and all(r.anchored_seconds <= r.seconds / 2 and r.reduction >= 0.5 for r in mine)
    slopes = {(r.hash, r.cost): r.slope for r in experiments.growth_m(spark, None).collect()}
    assert abs(slopes["uniform", "index_s"] - 2) < 1e-9 and abs(slopes["anchored", "query_s"] - 1) < 1e-9


def test_only_true_pairs_survive(spark):
    reads = spark.createDataFrame([("a", "ACGTACGG"), ("b", "TTTTACGT"), ("c", "GGGG")], "file_id string, seq string")
    asked = spark.createDataFrame([(1, "ACGT"), (2, "CGTA"), (3, "GGGGG"), (4, "AC")], "query_id long, seq string")
    every = asked.select("query_id").crossJoin(reads.select("file_id"))
    true = {(1, "a"), (1, "b"), (2, "a"), (3, "c")}
    assert {tuple(r) for r in baselines.exact_pairs(reads, asked, 4).collect()} == true
    got = bucket_grid.refine(every.withColumn("hit", F.lit(True)), asked, reads, 4).where("hit AND query_id < 4")
    assert {(r.query_id, r.file_id) for r in got.collect()} == true
    assert bucket_grid.refine(every.withColumn("hit", F.lit(False)), asked, reads, 4).where("hit").count() == 0
