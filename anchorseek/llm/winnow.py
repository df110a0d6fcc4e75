r"""Benchmark decontamination by winnowing.

Of every `window` consecutive k-grams of words the smallest hash is kept as a fingerprint, so two texts that
share a span of k + window - 1 words keep a common fingerprint inside it. Fingerprints of the documents are
joined with those of the benchmark; every hit is extended along its diagonal, word by word, and counts if
the common span is at least that long. Items shorter than that are looked up whole, by their own length.

A benchmark whose texts hold at most `broadcast_chars` characters (counted first) is broadcast and joined
where the documents are read. A larger one is joined by a shuffle on the fingerprints, after which pairs of
documents and items that share one are extended.

Defined results: null or empty text has no words and no hits; an item without words occurs nowhere; items
with equal ids are reported once, an item with a null id marks words but is not reported; repeated
documents each get a row; an empty benchmark leaves every document clean. Words compare by 64-bit hashes.
"""

from __future__ import annotations

import uuid
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ALNUM_BYTES, kept, lean, settled, table

SPAN = 13
K = 7
BROADCAST_CHARS = 4 << 20
MARK = "struct<n_words:bigint,n_hit:bigint,items:array<string>,spans:array<struct<first:int,last:int>>>"
_MARK_TYPE = pa.struct([("n_words", pa.int64()), ("n_hit", pa.int64()), ("items", pa.list_(pa.string())), ("spans", pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32())])))])


class WordHashes(dict):
    """64-bit hashes of words as bytes; forgets all when it has grown large."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= 200_000:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word)
        return value

    def of(self, text: str | None) -> np.ndarray:
        words = (text or "").encode().translate(ALNUM_BYTES).split()
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def grams(words: np.ndarray, k: int) -> np.ndarray:
    """Mixed hash of every k consecutive words."""
    n = len(words) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    h = words[:n].copy()
    for i in range(1, k):
        h *= np.uint64(0x9E3779B97F4A7C15)
        h += words[i : n + i]
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    return h


def minima(h: np.ndarray, width: int) -> np.ndarray:
    """Smallest value of every `width` consecutive ones; of all, if there are fewer."""
    if len(h) <= width:
        return h.min(keepdims=True) if len(h) else h
    out, have = h, 1
    while have < width:
        step = min(have, width - have)
        out = np.minimum(out[:-step], out[step:])
        have += step
    return out


def fingerprints(words: np.ndarray, span: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, positions) kept of a text: every place that holds the smallest hash of some window."""
    h, width = grams(words, k), span - k + 1
    if not len(h):
        return h, np.empty(0, np.int64)
    low = minima(h, width)
    if len(h) <= width:
        keep = h == low[0]
    else:
        keep = np.zeros(len(h), bool)
        for i in range(width):
            keep[i : i + len(low)] |= h[i : i + len(low)] == low
    at = np.flatnonzero(keep)
    return h[at], at


class Bench:
    """The benchmark's words and fingerprints, for lookup by documents."""

    def __init__(self, rows, span: int, k: int):
        self.span, self.k = span, k
        hashes = WordHashes()
        self.items = [(item, hashes.of(text)) for item, text in rows]
        index, short = defaultdict(list), defaultdict(lambda: defaultdict(list))
        for i, (_, words) in enumerate(self.items):
            if len(words) >= span:
                for h, q in zip(*fingerprints(words, span, k)):
                    index[int(h)].append((i, int(q)))
            elif len(words):
                short[len(words)][int(grams(words, len(words))[0])].append(i)
        self.index, self.short = dict(index), {n: dict(m) for n, m in short.items()}
        self.known = np.sort(np.fromiter(index, np.uint64, len(index)))
        self.short_known = {n: np.sort(np.fromiter(m, np.uint64, len(m))) for n, m in self.short.items()}

    @staticmethod
    def _found(known: np.ndarray, values: np.ndarray) -> np.ndarray:
        if not len(known) or not len(values):
            return np.empty(0, np.int64)
        at = np.searchsorted(known, values)
        at[at == len(known)] = 0
        return np.flatnonzero(known[at] == values)

    def mark(self, words: np.ndarray) -> tuple[np.ndarray, set[int]]:
        """(hit flag of each word, items with an occurring window)."""
        hit, items, seen = np.zeros(len(words), bool), set(), set()
        if len(words) >= self.span and len(self.known):
            h = grams(words, self.k)
            low = minima(h, self.span - self.k + 1)
            if len(self._found(self.known, low)):
                kept, at = fingerprints(words, self.span, self.k)
                for j in self._found(self.known, kept):
                    for i, q in self.index[int(kept[j])]:
                        d = int(at[j]) - q
                        if (i, d) not in seen:
                            seen.add((i, d))
                            if self._extend(words, self.items[i][1], d, hit):
                                items.add(i)
        for n, known in self.short_known.items():
            h = grams(words, n)
            for p in self._found(known, h):
                for i in self.short[n][int(h[p])]:
                    if np.array_equal(words[p : p + n], self.items[i][1]):
                        hit[p : p + n] = True
                        items.add(i)
        return hit, items

    def _extend(self, words: np.ndarray, item: np.ndarray, d: int, hit: np.ndarray) -> bool:
        lo, hi = max(0, -d), min(len(item), len(words) - d)
        same = np.concatenate([[0], (item[lo:hi] == words[lo + d : hi + d]).astype(np.int8), [0]])
        edge = np.diff(same)
        runs = [(a, b) for a, b in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)) if b - a >= self.span]
        for a, b in runs:
            hit[lo + d + a : lo + d + b] = True
        return bool(runs)


def _spans(hit: np.ndarray) -> list[dict]:
    edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return [{"first": int(a), "last": int(b) - 1} for a, b in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1))]


def _marker(sent, span: int, k: int, text: str, carry: list[str]):
    name = f"bench-{uuid.uuid4().hex}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bench, hashes = kept(name, lambda: Bench(sent.value, span, k)), WordHashes()  # once a worker
        for batch in batches:
            marks = []
            for t in batch.column(text):
                words = hashes.of(t.as_py())
                hit, items = bench.mark(words)
                names = sorted({str(bench.items[i][0]) for i in items if bench.items[i][0] is not None})
                marks.append({"n_words": len(words), "n_hit": int(hit.sum()), "items": names, "spans": _spans(hit)})
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in carry), pa.array(marks, _MARK_TYPE)], names=[*carry, "_mark"])

    return lean(run, name)


def _mark_shuffled(docs: DataFrame, bench: DataFrame, text: str, item_id: str, bench_text: str, span: int, k: int, carry: list[str]) -> DataFrame:
    """The same marks when the benchmark is too large to broadcast."""

    def prints(lengths):
        """Fingerprints of texts; for items shorter than a span, the hashes of all grams of their lengths."""

        def run(batches):
            hashes = WordHashes()
            for batch in batches:
                rows, found = [], []
                for i, t in enumerate(batch.column("_t")):
                    words = hashes.of(t.as_py())
                    got = set().union(*(grams(words, n).tolist() for n in lengths)) if lengths else set(fingerprints(words, span, k)[0].tolist()) if len(words) >= span else set()
                    rows += [i] * len(got)
                    found += got
                at = pa.array(rows, pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column("_k").take(at), batch.column("_k2").take(at), pa.array(np.array(found, np.uint64).view(np.int64))], names=["_k", "_k2", "_fp"])

        return lean(run)

    def item_prints(batches):
        hashes = WordHashes()
        for batch in batches:
            keys, found, sizes = [], [], []
            for key, t in zip(batch.column("_i").to_pylist(), batch.column("_bt")):
                words = hashes.of(t.as_py())
                n = min(len(words), span)
                got = {int(h) for h in fingerprints(words, span, k)[0]} if n == span else {int(h) for h in grams(words, n)} if n else set()
                keys += [key] * len(got)
                sizes += [n] * len(got)
                found += got
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(np.array(found, np.uint64).view(np.int64)), pa.array(sizes, pa.int32())], names=["_i", "_fp", "_n"])

    def pair(batches):
        hashes = WordHashes()
        for batch in batches:
            rows, spans, names = [], [], []
            for i, (t, item, bt) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("_t", "_item", "_bt")))):
                hit, items = Bench([(item, bt)], span, k).mark(hashes.of(t))
                if items:
                    rows.append(i)
                    spans.append(_spans(hit))
                    names.append(None if item is None else str(item))
            at = pa.array(rows, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("_k").take(at), batch.column("_k2").take(at), pa.array(names, pa.string()), pa.array(spans, _MARK_TYPE.field("spans").type)], names=["_k", "_k2", "_item", "_spans"])

    names, types = carry, [docs.schema[c].dataType.simpleString() for c in carry]
    carry = [f"_carried{i}" for i in range(len(names))]  # whatever their names, they meet none of ours
    docs = docs.select(F.col(text).alias("_text"), *[F.col(f"`{n}`").alias(c) for n, c in zip(names, carry)])
    text = "_text"
    key = ["_k", "_k2"]  # 128 bits name a text
    whole = F.coalesce(F.col(text), F.lit(""))
    keyed = docs.withColumn("_k", F.xxhash64(whole)).withColumn("_k2", F.xxhash64(F.lit(13), whole))
    texts = keyed.groupBy(*key).agg(F.first(whole).alias("_t"))
    items = bench.where(F.col(bench_text).isNotNull()).select(F.col(item_id).cast("string").alias("_item"), F.col(bench_text).alias("_bt")).distinct()
    items = items.withColumn("_i", F.xxhash64("_item", "_bt"))
    wanted = settled(items.select("_i", "_bt").mapInArrow(lean(item_prints), "_i bigint, _fp bigint, _n int"), "bench-prints")
    lengths = [r[0] for r in wanted.where(F.col("_n") < span).select("_n").distinct().collect()]  # at most span - 1 values
    printed = "_k bigint, _k2 bigint, _fp bigint"
    pairs = texts.mapInArrow(prints([]), printed).join(wanted.where(F.col("_n") == span), "_fp").select(*key, "_i")
    if lengths:
        pairs = pairs.union(texts.mapInArrow(prints(lengths), printed).join(wanted.where(F.col("_n") < span), "_fp").select(*key, "_i"))
    found = pairs.distinct().join(items, "_i").join(texts, key).select(*key, "_t", "_item", "_bt").mapInArrow(lean(pair), "_k bigint, _k2 bigint, _item string, _spans array<struct<first:int,last:int>>")
    marks = found.groupBy(*key).agg(F.array_sort(F.collect_set("_item")).alias("_items"), F.array_sort(F.flatten(F.collect_list("_spans"))).alias("_spans"))

    def merge(batches):
        hashes = WordHashes()
        for batch in batches:
            out = []
            for t, names, spans in zip(*(batch.column(c).to_pylist() for c in (text, "_items", "_spans"))):
                words = hashes.of(t)
                hit = np.zeros(len(words), bool)
                for s in spans or []:
                    hit[s["first"] : s["last"] + 1] = True
                out.append({"n_words": len(words), "n_hit": int(hit.sum()), "items": names or [], "spans": _spans(hit)})
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in carry), pa.array(out, _MARK_TYPE)], names=[*carry, "_mark"])

    schema = ", ".join(f"`{c}` {t}" for c, t in zip(carry, types))
    merged = keyed.join(marks, key, "left").mapInArrow(lean(merge), f"{schema}, _mark {MARK}")
    return merged.select(*[F.col(c).alias(n) for c, n in zip(carry, names)], "_mark")


def marked(docs: DataFrame, bench: DataFrame, text="text", item_id="item_id", bench_text="text", span=SPAN, k=K, carry=None, broadcast_chars=BROADCAST_CHARS) -> DataFrame:
    """The carried columns of docs (all by default) and _mark: words, hit words, items found, hit spans."""
    if not 1 <= k <= span:
        raise ValueError("1 <= k <= span")
    carry = [c for c in docs.columns if c != "_mark"] if carry is None else list(carry)
    chars = bench.agg(F.coalesce(F.sum(F.length(bench_text) + 64), F.lit(0))).first()[0]
    if chars > broadcast_chars:
        return _mark_shuffled(docs, bench, text, item_id, bench_text, span, k, carry)
    rows = [tuple(r) for r in bench.where(F.col(bench_text).isNotNull()).select(item_id, bench_text).distinct().collect()]
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in carry)
    read = docs.select(*dict.fromkeys([*carry, text]))
    sent = docs.sparkSession.sparkContext.broadcast(rows)  # at most broadcast_chars
    return read.mapInArrow(_marker(sent, span, k, text, carry), f"{schema}, _mark {MARK}")


def is_contaminated(mark="_mark"):
    """Fixed rule: at least one hit word, and hit words at least a twentieth of all."""
    return (F.col(f"{mark}.n_hit") > 0) & (20 * F.col(f"{mark}.n_hit") >= F.col(f"{mark}.n_words"))


def op5_decontaminate(spark, sf_dir: str) -> DataFrame:
    got = marked(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), carry=["doc_id"])
    return got.select(
        "doc_id", "_mark.n_words", "_mark.n_hit", F.size("_mark.items").cast("long").alias("n_items"),
        F.sha2(F.array_join("_mark.items", ",").cast("binary"), 256).alias("items_sha256"), is_contaminated().alias("contaminated"),
    )


OP5_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
item_windows AS (SELECT DISTINCT item_id, least(len(w), 13) AS n, array_to_string(w[i:i + least(len(w), 13) - 1], ' ') AS g
  FROM (SELECT *, unnest(range(1, greatest(len(w) - 13, 0) + 2)) AS i FROM b WHERE len(w) > 0)),
lengths AS (SELECT DISTINCT n FROM item_windows),
doc_windows AS (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS g
  FROM (SELECT *, unnest(range(1, len(w) - n + 2)) AS i FROM d, lengths WHERE len(w) >= n)),
hits AS (SELECT doc_id, i, n, item_id FROM doc_windows JOIN item_windows USING (n, g)),
places AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hits) GROUP BY doc_id),
names AS (SELECT doc_id, list_sort(list(DISTINCT item_id::VARCHAR)) AS items FROM hits GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(len(items), 0)::BIGINT AS n_items,
  sha256(coalesce(array_to_string(items, ','), '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN places USING (doc_id) LEFT JOIN names USING (doc_id)
"""
