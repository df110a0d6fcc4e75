"""The md5 family on the Arrow road: values of hashlib and of the expressions, summaries without a row a gram."""

import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from anchorseek import workloads
from anchorseek.functions import anchored, md5_batch
from anchorseek.operators import filters
from anchorseek.plans.spec import IndexSpec
from anchorseek.shipping import ship


def value(text, seed):
    return int(hashlib.md5(f"{seed}:{text}".encode()).hexdigest()[:15], 16)


@pytest.mark.parametrize("width, seed", [(1, 7), (16, 7), (29, 12), (30, 9), (31, 8), (31, 123)])
def test_windows(width, seed):
    text = "".join(random.Random(width).choice("ACGT") for _ in range(300))
    got = md5_batch.of_windows(np.frombuffer(text.encode(), np.uint8), width, seed)
    assert got.tolist() == [value(text[i : i + width], seed) for i in range(301 - width)]


def test_longs():
    numbers = [0, 9, 10, (1 << 62) - 1, *(10**i for i in range(19)), *(random.Random(1).randrange(1 << 62) for _ in range(200))]
    assert md5_batch.of_longs(np.array(numbers, np.int64), 8).tolist() == [value(n, 8) for n in numbers]


@pytest.fixture(scope="module")
def reads(spark):
    ship(spark)
    r = random.Random(2)
    seqs = ["".join(r.choice("ACGT") for _ in range(n)) for n in (0, 5, 30, 31, 32, 230, 230)] + ["A" * 60, "ACGT" * 20]
    return spark.createDataFrame([("f", i, 0, s) for i, s in enumerate(seqs)] + [("f", 99, 0, None)], "file_id string, seq_id long, read_no int, seq string")


@pytest.mark.parametrize("changes", [{}, {"hash": "sketch"}, {"hash": "uniform"}, {"layout": "shared"}, {"oph": True}, {"align": "page"}, {"m": 100003, "L": 77}])
def test_same_places_and_summary_as_expressions(reads, changes):
    spec = IndexSpec(m=1 << 18, eta=2, L=512, seed=7, family="md5", oph=False).with_(**changes)
    assert spec.kernel
    rows = lambda df: sorted(map(tuple, df.collect()))
    slow = anchored.gram_positions(reads, spec.with_(backend="sql"))
    assert rows(anchored.gram_positions(reads, spec)) == rows(slow)
    assert rows(filters.summary(reads, spec)) == rows(workloads._summary(slow))


def test_portable_queries_take_the_kernel_and_ship_pages(spark):
    """A row a gram must not be shuffled: the plan has pages, and no expression of md5."""
    ship(spark)
    assert workloads.SPEC.kernel and workloads.WIDE.kernel
    for name in ("anchored_positions", "anchored_shared_layout", "filter_fill", "filter_mt_anchored"):
        plan = workloads.QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
        assert "dense" in plan and "Expand" not in plan


def test_tallies_of_several_files(reads):
    named = reads.withColumn("file_id", (F.col("seq_id") % 3).cast("string"))
    spec = IndexSpec(m=1 << 16, eta=2, L=512, family="md5")
    got = filters._merged(named.select(F.col("file_id").alias("filter_id"), "seq"), spec, True).groupBy("filter_id").agg(F.sum("n").alias("n"), F.sum("total").alias("t"))
    want = anchored.gram_positions(named, spec).groupBy("file_id").agg(F.count(F.lit(1)).alias("n"), F.sum("bit").alias("t"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
