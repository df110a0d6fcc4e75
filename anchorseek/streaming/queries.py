"""Streams over the given tables run to their end; results equal those of a batch."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators.relational import seconds
from ..sources import index_store
from . import event_stream

QUERIES, SQL = {}, {}


def _root(spark) -> str:
    return index_store.scratch(spark, "stream")


def drained(spark, stream, mode: str = "append"):
    """All rows that a stream gives, through a Parquet sink (append) or the last state (complete)."""
    root = _root(spark)
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/out")

    def keep(batch, n):
        batch.write.mode("overwrite").parquet(f"{root}/last")

    q = stream.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/last")


def source(spark, d, name):
    """A table as a stream of its files, whether it is one file or a folder of them."""
    path = f"{d}/{name}.parquet"
    batch = spark.read.parquet(path)
    reader = spark.readStream.schema(batch.schema)
    if any(f.endswith(f"/{name}.parquet") for f in batch.inputFiles()):
        return reader.option("pathGlobFilter", f"{name}.parquet").parquet(d)
    return reader.parquet(path)


def events(spark, d):
    return source(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def began(column="start"):
    return seconds(F.col(column).cast("timestamp_ntz")).alias("start")


def stream(name, sql=None):
    def add(f):
        QUERIES[f"stream_{name}"] = f
        if sql:
            SQL[f"stream_{name}"] = sql
        return f

    return add


@stream("tumbling", "SELECT floor(epoch(date_trunc('hour', ts)))::BIGINT AS start, event_type, count(*)::BIGINT AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def tumbling(spark, d):
    got = drained(spark, event_stream.tumbling(events(spark, d)), "complete")
    return got.select(began(), "event_type", "n", F.round("total", 4).alias("total"))


@stream("sliding", "SELECT floor(epoch(s))::BIGINT AS start, count(*)::BIGINT AS n FROM (SELECT unnest([time_bucket(INTERVAL 15 MINUTE, ts), time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 15 MINUTE, time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 30 MINUTE, time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 45 MINUTE]) AS s FROM events) GROUP BY s")
def sliding(spark, d):
    return drained(spark, event_stream.sliding(events(spark, d)), "complete").select(began(), "n")


@stream("sessions", """WITH g AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM g)
SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS seq FROM s GROUP BY user_id, n""")
def sessions(spark, d):
    return drained(spark, event_stream.sessions(events(spark, d)), "complete").select("user_id", began(), "seq")


@stream("deduplicated", "SELECT event_type, count(DISTINCT event_id)::BIGINT AS n FROM events GROUP BY event_type")
def deduplicated(spark, d):
    twice = events(spark, d).select("event_id", "ts", "event_type", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy"))
    return drained(spark, event_stream.deduplicated(twice)).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@stream("click_to_purchase", "SELECT p.event_id AS purchase_id, c.event_id AS click_id FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR")
def click_to_purchase(spark, d):
    return drained(spark, event_stream.click_to_purchase(events(spark, d)))


@stream("incremental_index")
def incremental_index(spark, d):
    """An index fed by a stream of reads has the pages of one built at once: pages and bits of either, and of both."""
    from ..functions import views
    from ..operators import filters
    from ..workloads import FAST, K
    from . import index_stream

    path, root = f"{d}/documents.parquet", _root(spark)
    reads = views.to_reads(views.dna_sequences(source(spark, d, "documents")), K)
    index_stream.incremental_build(reads, FAST, f"{root}/pages", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    fed = index_stream.merged(spark, f"{root}/pages")
    whole = filters.build(views.to_reads(views.dna_sequences(spark.read.parquet(path)), K), FAST)
    both = fed.withColumnRenamed("bits", "a").join(whole.withColumnRenamed("bits", "b"), ["filter_id", "rep", "page_no"], "full")
    return both.groupBy("rep").agg(F.count("a").alias("fed_pages"), F.count("b").alias("whole_pages"), F.sum((F.col("a") == F.col("b")).cast("long")).alias("equal_pages"))
