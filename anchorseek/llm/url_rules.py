r"""URL filters by a sort-merge range join.

A host is written with its labels reversed, each closed by a dot ("a.example.net" -> "net.example.a."), so
a rule for a host and all its subdomains is one interval of such keys and the rules' intervals are nested
or disjoint. URLs and rules are dealt over the same key ranges and sorted; a sweep over each range keeps a
stack of the rules that enclose the present key. Path prefixes are looked up in the frames of the stack.

Ranges are cut on (key, hash of the row), so one host with a large part of the URLs spreads over many
ranges. A rule goes to the ranges its interval overlaps: a range start lies inside at most as many nested
rules as a host has labels, so the copies number rules + ranges * labels.

Defined results: a URL that is null or has no "://" has empty host and path, matches no rule and gets the
default verdict; of rules that fit, the longest (host and path) wins, a longer host before a longer path at
equal length, then the smaller verdict; repeated rules count once; repeated rows each get a row; a rule
with a null host is ignored, one with a null path covers every path.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, lower_ascii, table

AFTER_SCHEME = r"(?s)^.*?://(.*)$"
#: Rows of one key range, about (it is streamed, so a larger one costs time, not memory); the most ranges;
#: and the rows of the hash sample per range from which the split points come.
ROWS_PER_RANGE = 250_000
MOST_RANGES = 4096
SAMPLE_PER_RANGE = 40


def split_url(url):
    """(host, path) columns; both empty without a scheme."""
    has = F.coalesce(F.instr(url, "://"), F.lit(0)) > 0
    rest = F.regexp_extract(url, AFTER_SCHEME, 1)
    host = F.when(has, lower_ascii(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1))).otherwise(F.lit(""))
    path = F.when(has, F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)).otherwise(F.lit(""))
    return host, path


def reversed_host(host):
    """Labels in reverse order, each with a closing dot; an empty host is one empty label."""
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit("."))


def _splits(keyed: DataFrame) -> list[str]:
    """Ends of key ranges, from a hash sample of bounded size; they steer balance only, never results."""
    rows = keyed.count()
    n = min(MOST_RANGES, max(-(-rows // ROWS_PER_RANGE), int(keyed.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    if rows < 2 or n < 2:
        return []
    keep = int(min(1.0, n * SAMPLE_PER_RANGE / rows) * (1 << 20))
    sample = keyed.where(F.pmod(F.col("_salt"), F.lit(1 << 20)) < keep).select("_at")
    found = sorted(r[0] for r in sample.toLocalIterator())
    return sorted({found[i * len(found) // n] for i in range(1, n)}) if found else []


def _sweep(default_verdict: str, columns: list[str]):
    """For sorted events of one range: rules open frames, URLs look them up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, stack = None, []
        for batch in batches:
            col = {n: batch.column(n).to_pylist() for n in ("_part", "_rev", "_kind", "_path", "_rule", "_verdict")}
            rules, verdicts, keep = [], [], []
            for i in range(batch.num_rows):
                if col["_part"][i] != part:
                    part, stack = col["_part"][i], []
                key, path = col["_rev"][i], col["_path"][i]
                while stack and not key.startswith(stack[-1][0]):
                    stack.pop()
                if col["_kind"][i] == 0:
                    if not stack or stack[-1][0] != key:
                        stack.append((key, {}, []))
                    frame = stack[-1]
                    if path not in frame[1]:
                        frame[1][path] = (col["_rule"][i], col["_verdict"][i])
                        if len(path) not in frame[2]:
                            frame[2].append(len(path))
                            frame[2].sort(reverse=True)
                    continue
                best = None
                for _, by_path, lengths in reversed(stack):
                    for length in lengths:
                        found = by_path.get(path[:length]) if length <= len(path) else None
                        if found:
                            if best is None or len(found[0]) > len(best[0]):
                                best = found
                            break
                keep.append(i)
                rules.append(best[0] if best else None)
                verdicts.append(best[1] if best else default_verdict)
            kept = batch.take(pa.array(keep, pa.int64()))
            yield pa.RecordBatch.from_arrays(
                [kept.column(c) for c in columns] + [pa.array(rules, pa.string()), pa.array(verdicts, pa.string())],
                names=columns + ["rule", "verdict"],
            )

    return lean(run)


def filter_urls(pages: DataFrame, rules: DataFrame, url="url", row_id="page_id", default_verdict="allow") -> DataFrame:
    """(row_id, host, path, rule, verdict) for every row of pages. rules: (host, path, verdict)."""
    spark = pages.sparkSession
    host, path = split_url(F.col(url))
    urls = pages.select(F.col(row_id).alias("_id"), host.alias("host"), path.alias("path"))
    urls = urls.withColumn("_rev", reversed_host(F.col("host"))).withColumn("_salt", F.xxhash64("_id", "host", "path"))
    # a row's place: its key, then its hash; "\u0000" sorts before any character of a longer key
    urls = urls.withColumn("_at", F.concat(F.col("_rev"), F.lit("\u0000"), F.hex("_salt")))
    cuts = _splits(urls)

    @F.pandas_udf("int")
    def place(keys: pd.Series) -> pd.Series:
        return pd.Series([bisect_right(cuts, k) for k in keys], dtype="int32")

    clean = (
        rules.where(F.col("host").isNotNull())
        .select(lower_ascii(F.col("host")).alias("_h"), F.coalesce(F.col("path"), F.lit("")).alias("_path"), F.col("verdict").alias("_verdict"))
        .groupBy("_h", "_path").agg(F.min("_verdict").alias("_verdict"))
        .withColumn("_rev", reversed_host(F.col("_h")))
    )
    first, last = place(F.col("_rev")), place(F.regexp_replace(F.col("_rev"), r"\.$", "/"))
    opened = clean.withColumn("_part", F.explode(F.sequence(first, last)))
    columns = ["_id", "host", "path"]
    id_type = urls.schema["_id"].dataType
    events = urls.select("_id", "host", "path", place(F.col("_at")).alias("_part"), "_rev", F.lit(1).alias("_kind"), F.col("path").alias("_path"), F.lit(None).cast("string").alias("_rule"), F.lit(None).cast("string").alias("_verdict")).unionByName(
        opened.select(F.lit(None).cast(id_type).alias("_id"), F.lit(None).cast("string").alias("host"), F.lit(None).cast("string").alias("path"), "_part", "_rev", F.lit(0).alias("_kind"), "_path", F.concat("_h", "_path").alias("_rule"), "_verdict")
    )
    swept = events.repartitionById(len(cuts) + 1, F.col("_part")).sortWithinPartitions("_part", "_rev", "_kind").mapInArrow(
        _sweep(default_verdict, columns), f"_id {id_type.simpleString()}, host string, path string, rule string, verdict string"
    )
    return swept.withColumnRenamed("_id", row_id)


#: The rules of the contract.
CONTRACT_RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]


def op1_url_filter(spark, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(CONTRACT_RULES, "host string, path string, verdict string")
    return filter_urls(table(spark, sf_dir, "pages"), rules)


OP1_SQL = r"""
WITH cut AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) END AS rest FROM pages),
parts AS (SELECT page_id,
    coalesce(translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
    coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path FROM cut),
rules(h, p, v) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
hits AS (SELECT *, row_number() OVER (PARTITION BY page_id ORDER BY length(h || p) DESC NULLS LAST) AS r
  FROM parts LEFT JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p))
SELECT page_id, host, path, h || p AS rule, coalesce(v, 'allow') AS verdict FROM hits WHERE r = 1
"""
