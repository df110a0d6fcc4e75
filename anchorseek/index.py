"""A short way to an index: Index(spec).fit(reads).search(queries)."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators import bucket_grid, file_matrix, filters
from .plans.spec import IndexSpec
from .sources import index_store


class Index:
    """kind: plain (one set), matrix (one filter a file) or grid (random buckets of files)."""

    def __init__(self, spec: IndexSpec | None = None, kind: str = "plain"):
        if kind not in ("plain", "matrix", "grid"):
            raise ValueError("kind is plain, matrix or grid")
        self.spec, self.kind, self.held = spec or IndexSpec(), kind, None

    def fit(self, reads: DataFrame) -> Index:
        """Index reads (file_id, seq). A plain index is one filter of all of them, whatever their files."""
        if self.kind == "plain":
            self.held = filters.build(reads, self.spec, filter_id=F.lit("all"))
        else:
            self.held = {"matrix": file_matrix.build, "grid": bucket_grid.build}[self.kind](reads, self.spec)
        return self

    def search(self, queries: DataFrame) -> DataFrame:
        """(query_id[, file_id], hit) of queries (query_id, seq)."""
        if self.kind == "plain":
            return filters.contains(self.held, queries, self.spec)
        return {"matrix": file_matrix.search, "grid": bucket_grid.search}[self.kind](self.held, queries)

    def views(self, spark) -> None:
        """Temporary views index_pages and index_meta of a plain index."""
        if self.kind != "plain":
            raise ValueError("views are of plain indexes")
        self.held.createOrReplaceTempView("index_pages")
        spark.createDataFrame([(self.spec.to_json(),)], "spec string").createOrReplaceTempView("index_meta")

    def save(self, path: str) -> None:
        """Pages or slices with the parameters, the files and, for a grid, its buckets beside them."""
        if self.kind == "plain":
            index_store.write_index(self.held, self.spec, path)
            told = {"kind": "plain"}
        else:
            rows = self.held.rows if self.kind == "matrix" else self.held.pages
            index_store.write_rows(rows, self.spec, path)
            self.held.files.write.parquet(f"{path}/files")
            told = {"kind": self.kind}
            if self.kind == "matrix":
                told["layout"] = self.held.layout
            else:
                self.held.buckets.write.parquet(f"{path}/buckets")
                told |= {"B": self.held.B, "R": self.held.R}
        rows = self.held if self.kind == "plain" else self.held.files
        rows.sparkSession.createDataFrame([(json.dumps(told),)], "told string").coalesce(1).write.text(f"{path}/kind")

    @staticmethod
    def load(spark, path: str) -> Index:
        told = json.loads(spark.read.text(f"{path}/kind").first()[0])
        rows, spec = index_store.read_index(spark, path) if told["kind"] == "plain" else index_store.read_rows(spark, path)
        out = Index(spec, told["kind"])
        if out.kind == "plain":
            out.held = rows
        elif out.kind == "matrix":
            out.held = file_matrix.FileMatrix(rows, spark.read.parquet(f"{path}/files"), spec, told["layout"])
        else:
            out.held = bucket_grid.BucketGrid(rows, spark.read.parquet(f"{path}/buckets"), spark.read.parquet(f"{path}/files"), spec, told["B"], told["R"])
        return out
