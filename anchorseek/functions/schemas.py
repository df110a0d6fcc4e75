"""Schemas of the frames that the operators pass on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

SEQUENCES = T.StructType([T.StructField("file_id", T.StringType()), T.StructField("seq_id", T.LongType()), T.StructField("seq", T.StringType())])
READS = T.StructType([*SEQUENCES.fields[:2], T.StructField("read_no", T.IntegerType()), T.StructField("seq", T.StringType())])
QUERIES = T.StructType([T.StructField("query_id", T.LongType()), T.StructField("seq", T.StringType())])
FILTER_PAGES = T.StructType([T.StructField("filter_id", T.StringType()), T.StructField("rep", T.IntegerType()), T.StructField("page_no", T.LongType()), T.StructField("bits", T.BinaryType())])
SLICES = T.StructType([T.StructField("rep", T.IntegerType()), T.StructField("pos", T.LongType()), T.StructField("file_block", T.IntegerType()), T.StructField("files", T.BinaryType())])
PROBES = T.StructType([T.StructField("query_id", T.LongType()), T.StructField("rep", T.IntegerType()), T.StructField("page_no", T.LongType()), T.StructField("offsets", T.ArrayType(T.IntegerType()))])


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df, if it has the schema's columns with their types; extra columns are allowed."""
    have = {f.name: f.dataType for f in df.schema.fields}
    for f in schema.fields:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing; there are {sorted(have)}")
        if have[f.name].simpleString() != f.dataType.simpleString():
            raise TypeError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df
