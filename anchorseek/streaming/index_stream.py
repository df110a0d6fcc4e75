"""Indexes fed and probed by streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import anchored
from ..operators import filters, pages
from ..plans.spec import IndexSpec


def incremental_build(reads: DataFrame, spec: IndexSpec, path: str, checkpoint: str):
    """A query that writes each batch's pages below its number: a replayed batch overwrites its own pages,
    and OR over batches is the same however often a page comes."""

    def store(batch: DataFrame, number: int) -> None:
        filters.build(batch, spec).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return reads.writeStream.foreachBatch(store).option("checkpointLocation", checkpoint)


def merged(spark, path: str) -> DataFrame:
    """The index of all batches so far."""
    return pages.union(spark.read.parquet(path).select("filter_id", "rep", "page_no", "bits"))


def streaming_probe(queries: DataFrame, index: DataFrame, spec: IndexSpec, answer: Callable[[DataFrame, int], None], checkpoint: str):
    """A query that hands the answers of each batch of queries (query_id, seq) to `answer`."""
    return queries.writeStream.foreachBatch(lambda batch, n: answer(filters.contains(index, batch, spec), n)).option("checkpointLocation", checkpoint)


def page_state(reads: DataFrame, spec: IndexSpec) -> DataFrame:
    """Pages kept as state: (rep, page_no, bits) after every batch, for streams without a store. 4 KB a key."""
    from pyspark.sql.streaming import StatefulProcessor

    class OrPages(StatefulProcessor):
        def init(self, handle) -> None:
            self.page = handle.getValueState("page", "bits binary")

        def handleInputRows(self, key, rows, timers):
            import numpy as np
            import pandas as pd

            held = self.page.get()
            bits = np.frombuffer(held[0], np.uint8).copy() if held else np.zeros(4096, np.uint8)
            for pdf in rows:
                offsets = pdf["offset"].to_numpy()
                np.bitwise_or.at(bits, offsets >> 3, (1 << (offsets & 7)).astype(np.uint8))
            self.page.update((bits.tobytes(),))
            yield pd.DataFrame({"rep": [int(key[0])], "page_no": [int(key[1])], "bits": [bits.tobytes()]})

        def close(self) -> None:
            pass

    rows = anchored.gram_positions(reads, spec, ["file_id"]).select("rep", pages.page_of(F.col("bit")).alias("page_no"), pages.offset_of(F.col("bit")).alias("offset"))
    return rows.groupBy("rep", "page_no").transformWithStateInPandas(statefulProcessor=OrPages(), outputStructType="rep int, page_no long, bits binary", outputMode="Update", timeMode="None")


def rotating_filters(events: DataFrame, spec: IndexSpec, key: str = "event_type", by: str = "1 day", late: str = "1 day") -> DataFrame:
    """(window, bits set) of one filter a time window, retired with the watermark."""
    pos = anchored.position(F.col(key), F.xxhash64(key), spec.range, spec.L, spec.seed)
    return events.withWatermark("ts", late).groupBy(F.window("ts", by), pages.page_of(pos).alias("page_no")).agg(F.bitmap_construct_agg(pages.offset_of(pos).cast("long")).alias("bits"))
