"""Indexes at rest: Parquet pages sorted by key, with the parameters beside them."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame

from ..functions import schemas
from ..plans.spec import IndexSpec

FORMAT = 1


def scratch(spark, tag: str) -> str:
    """A fresh path in the shared folder the session names; in a temporary one only where it names none."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and the executors share")
    base = base or tempfile.mkdtemp(prefix="anchorseek-index-")
    return f"{base.rstrip('/')}/anchorseek/{uuid.uuid4().hex}/{tag}"


def write_index(pages: DataFrame, spec: IndexSpec, path: str, mode: str = "errorifexists") -> None:
    """Pages range-dealt and sorted by (filter_id, rep, page_no), so that readers skip by their bounds."""
    schemas.require(pages, schemas.FILTER_PAGES)
    spark = pages.sparkSession
    pages.select("filter_id", "rep", "page_no", "bits").repartitionByRange("filter_id", "rep", "page_no").sortWithinPartitions("filter_id", "rep", "page_no").write.mode(mode).parquet(f"{path}/pages")
    _write_meta(spark, spec, path, mode)


def _write_meta(spark, spec: IndexSpec, path: str, mode: str) -> None:
    spark.createDataFrame([(FORMAT, spec.to_json())], "format int, spec string").coalesce(1).write.mode(mode).json(f"{path}/meta")


def write_rows(rows: DataFrame, spec: IndexSpec, path: str, mode: str = "errorifexists") -> None:
    """Rows of any index, sorted by (rep, bit) or by page, with the parameters beside them."""
    order = [c for c in ("rep", "page_no", "bit", "filter_id", "file_block") if c in rows.columns]
    rows.repartitionByRange(*order).sortWithinPartitions(*order).write.mode(mode).parquet(f"{path}/rows")
    _write_meta(rows.sparkSession, spec, path, mode)


def read_rows(spark, path: str) -> tuple[DataFrame, IndexSpec]:
    return spark.read.parquet(f"{path}/rows"), _read_meta(spark, path)


def read_index(spark, path: str, expect: IndexSpec | None = None) -> tuple[DataFrame, IndexSpec]:
    """(pages, parameters); refuses another format, or parameters with other positions than expected."""
    spec = _read_meta(spark, path)
    if expect is not None and not spec.compatible(expect):
        raise ValueError("the index was built with other parameters")
    return spark.read.schema(schemas.FILTER_PAGES).parquet(f"{path}/pages"), spec


def _read_meta(spark, path: str) -> IndexSpec:
    meta = spark.read.schema("format int, spec string").json(f"{path}/meta").first()
    if meta is None or meta["format"] != FORMAT:
        raise ValueError("not an index of this format")
    return IndexSpec.from_json(meta["spec"])


def save_index_table(pages: DataFrame, name: str, buckets: int = 64) -> None:
    """Pages as a catalog table bucketed by page: joins on it leave the index side where it is."""
    pages.write.bucketBy(buckets, "page_no").sortBy("page_no").mode("overwrite").saveAsTable(name)
