"""Token-ID output: Parquet list columns in document order, with controlled row groups, pages and encodings.

Documents are range-dealt by id before they are encoded, so the texts move once and the ids never. Each
task encodes its range and writes one file: (doc_id, n_tokens, ids), ids as a list of ints in dictionary or
delta encoding, small pages with a column and offset index. A reader of one document, or of the metadata
columns alone, therefore reads only the pages it needs. Positions in the whole stream come from the files:
sums per file, a running sum over the files, and a running sum of the rows inside each.

Defined results: null text is the empty text; each document ends with the end id, so no list is empty; a
null doc_id sorts first; documents with equal ids are kept, in order of their text, in one file; an empty table gives an
empty set of files that reads back as an empty table.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh_path, kept, lean, parts_of, settled, table

#: Groups whose ids one process remembers, their most bytes, and the bytes of text encoded at once.
MEMORY_PIECES = 800_000
LONGEST_PIECE = 64
SLICE_BYTES = 6 << 20
#: Input bytes of a token file, at least one for each shuffle partition.
FILE_BYTES = 512 << 20


def _byte_letters() -> str:
    """The letter that byte-level models write for each byte: printable bytes stand for themselves, others follow 255."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return "".join(chr(b) if b in plain else chr(next(rest)) for b in range(256))


BYTE_LETTERS = _byte_letters()
#: The groups of byte-level models, for texts in which Python's classes say the same as the
#: library's: below U+0530 and without the separators 1C-1F. Numbers beyond the digits are listed.
_NUMBERS = "\xb2\xb3\xb9\xbc\xbd\xbe"
_LETTER, _NUMBER = rf"[^\W\d_{_NUMBERS}]", rf"[\d{_NUMBERS}]"
GROUPS = re.compile(rf" ?{_LETTER}+|'s|'t|'re|'ve|'m|'ll|'d| ?{_NUMBER}+| ?(?:_|[^\s\w])+|\s+(?!\S)|\s+")
OTHER = re.compile("[\x1c-\x1f\u0530-\U0010ffff]")


class PieceEncoder:
    """Encodes texts with a tokenizers file, remembering the ids of the groups that the model encodes one by one.

    The library's model encodes each group; the groups of common texts are cut here, once a text. Texts with
    characters beyond those of GROUPS, texts that hold the content of an added token (which the library finds
    before it cuts groups), and files of another kind go through the library whole.
    """

    def __init__(self, path: str):
        import json

        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        # what is remembered: groups, where the ids of each begin, the ids, and the slice that last had each
        self.pieces, self.at, self.ids = pa.array([], pa.large_binary()), np.zeros(1, np.int64), np.empty(0, np.int32)
        self.used, self.slices = np.empty(0, np.int64), 0
        told = json.loads(self.tokenizer.to_str())
        self.added = [t["content"] for t in told["added_tokens"] if t["content"]]
        before = told["pre_tokenizer"] or {}
        self.by_group = (
            told["normalizer"] is None and told["model"]["type"] == "BPE" and told["model"].get("dropout") is None
            and before.get("type") == "ByteLevel" and before.get("use_regex") and not before.get("add_prefix_space")
        )

    def whole(self, text: str) -> bytes:
        return np.asarray(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def groups(self, groups: list[bytes]) -> list[list[int]]:
        """Ids of groups; the byte FF, which no UTF-8 text holds and which stands for itself, keeps them apart."""
        letters = b"\xff".join(groups).decode("latin-1").translate(BYTE_LETTERS).split("\xff") if groups else []
        tokenize = self.model.tokenize
        return [[t.id for t in tokenize(x)] for x in letters]

    def encode(self, text: str) -> bytes:
        """Ids of one text, its groups cut by the pattern."""
        if not self.by_group or OTHER.search(text) or any(a in text for a in self.added):
            return self.whole(text)
        return np.array([i for ids in self.groups([g.encode() for g in GROUPS.findall(text)]) for i in ids], "<u4").tobytes()

    def encode_all(self, texts: pa.StringArray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after another, each with the end id; number of ids of each text).

        All texts are cut into groups at once, in their bytes; every distinct group is encoded once and its ids
        are copied to all its places. A text that needs the library as a whole is one group.
        """
        texts = texts.fill_null("").cast(pa.large_binary()) if texts.null_count else texts.cast(pa.large_binary())
        offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        edges = offsets - offsets[0]
        if not edges[-1]:
            return np.full(len(texts), end_id, np.int32), np.ones(len(texts), np.int64)
        raw = np.frombuffer(texts.buffers()[2], np.uint8)[offsets[0] : offsets[-1]]
        if self.by_group:
            starts, alone = self._cut(texts, raw, edges)
        else:
            alone = np.flatnonzero(np.diff(edges))
            starts = edges[alone]
        groups = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(np.append(starts, len(raw))), pa.py_buffer(raw)]).dictionary_encode()
        which = groups.indices.to_numpy()
        whole = {int(which[i]) for i in np.searchsorted(starts, edges[alone])}
        number, at, ids = self._numbers(groups.dictionary, whole)
        before = np.searchsorted(starts, edges)  # groups before the end of each text
        which = np.insert(number[which], before[1:], len(at) - 1)
        at, ids = np.append(at, len(ids) + 1), np.append(ids, np.int32(end_id))
        out = pa.LargeListArray.from_arrays(pa.array(at), pa.array(ids)).take(pa.array(which)).flatten().to_numpy()
        total = np.concatenate([[0], np.cumsum(np.diff(at)[which])])
        return out, np.diff(total[before + np.arange(len(before))])

    def _numbers(self, groups: pa.Array, whole: set[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(number of each distinct group, where the ids of each number begin, ids). Short groups are remembered."""
        number = pc.index_in(groups, value_set=self.pieces).fill_null(-1).to_numpy().astype(np.int64)
        new = np.flatnonzero(number < 0)
        brief = np.asarray(pc.binary_length(groups.take(pa.array(new))), np.int64) <= LONGEST_PIECE
        if whole:
            brief &= ~np.isin(new, list(whole))
        new = np.concatenate([new[brief], new[~brief]])  # the remembered ones first
        stay = int(brief.sum())
        names = groups.take(pa.array(new))
        made = self.groups(names.slice(0, stay).to_pylist())
        made += [np.frombuffer(self.whole(g.decode()), "<i4") if i in whole else self.groups([g])[0] for i, g in zip(new[stay:].tolist(), names.slice(stay).to_pylist())]
        sizes = np.fromiter(map(len, made), np.int64, len(made))
        flat = np.fromiter(chain.from_iterable(made), np.int32, int(sizes.sum()))
        number[new] = len(self.pieces) + np.arange(len(new))
        at, ids = np.append(self.at, self.at[-1] + np.cumsum(sizes)), np.concatenate([self.ids, flat])
        # remembered from here on
        known = len(self.pieces) + stay
        self.pieces = pa.concat_arrays([self.pieces, names.slice(0, stay)])
        self.at, self.ids = at[: known + 1], ids[: at[known]]
        self.slices += 1
        self.used = np.append(self.used, np.zeros(stay, np.int64))
        self.used[number[number < known]] = self.slices
        if known > MEMORY_PIECES:  # the half that was used last stays
            rows = pa.array(np.sort(np.argsort(-self.used, kind="stable")[: MEMORY_PIECES // 2]))
            lists = pa.LargeListArray.from_arrays(pa.array(self.at), pa.array(self.ids)).take(rows)
            self.pieces, self.used = self.pieces.take(rows), self.used[rows.to_numpy()]
            self.at, self.ids = lists.offsets.to_numpy() - lists.offsets[0].as_py(), lists.flatten().to_numpy()
        return number, at, ids

    def _cut(self, texts: pa.Array, raw: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(starts of the groups, numbers of the texts that are one group)."""
        start, odd = group_starts(raw, edges)
        alone = np.searchsorted(edges, odd, side="right") - 1
        for content in self.added:
            alone = np.concatenate([alone, np.flatnonzero(pc.match_substring(texts, content))])
        alone = np.unique(alone).astype(np.int64)
        for t in alone:
            start[edges[t] : edges[t + 1]] = False
            start[edges[t]] = True
        return np.flatnonzero(start), alone


def _classes() -> np.ndarray:
    """Kind of every character below U+0530: 1 letter, 2 number, 3 white space, 0 another."""
    import unicodedata

    kinds = [unicodedata.category(chr(c))[0] for c in range(0x530)]
    out = np.array([1 if k == "L" else 2 if k == "N" else 0 for k in kinds], np.uint8)
    out[[9, 10, 11, 12, 13, 32, 0x85, 0xA0]] = 3
    return out


CLASSES = _classes()
_BYTE_KINDS = np.concatenate([CLASSES[:128], np.zeros(128, np.uint8)])
_SEPARATORS = np.isin(np.arange(256), np.arange(0x1C, 0x20))


def group_starts(raw: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, list[int]]:
    """(whether a group of GROUPS starts at each byte, places of characters beyond those of GROUPS), for UTF-8
    texts one after another, which end at the edges."""
    n = len(raw)
    kind = _BYTE_KINDS[raw]
    odd = np.flatnonzero(_SEPARATORS[raw]).tolist()
    lead = np.flatnonzero(raw >= 0xC0)
    if len(lead):  # both bytes of a two-byte character have its kind
        two = lead[(raw[lead] < 0xD5) & (lead + 1 < n)]
        code = ((raw[two].astype(np.int32) & 31) << 6) | (raw[two + 1] & 63)
        known = code < len(CLASSES)
        kind[two[known]] = kind[two[known] + 1] = CLASSES[code[known]]
        odd += two[~known].tolist() + lead[raw[lead] >= 0xD5].tolist()
    opens = np.zeros(n + 1, bool)
    opens[edges] = True
    run = opens[:-1].copy()
    run[1:] |= kind[1:] != kind[:-1]
    at = np.flatnonzero(run)
    end = np.append(at[1:], n)
    white = kind[at] == 3
    joins = ~white & ~opens[at] & (raw[at - 1] == 32)  # a space before belongs to the group
    start = run
    start[at[joins]] = False
    apart = end[white & ~opens[end]] - 1  # the last white character before others stands apart
    start[apart - ((raw[apart] & 0xC0) == 0x80)] = True
    mark = at[(raw[at] == 39) & ~joins & (end == at + 1) & ~opens[end]]
    if len(mark):
        padded = np.append(raw, [0, 0])
        a, b = padded[mark + 1], padded[mark + 2]
        letter = kind[mark + 1] == 1
        one = letter & np.isin(a, [ord(c) for c in "stmd"])
        two = letter & ~opens[mark + 2] & (((a == ord("r")) | (a == ord("v"))) & (b == ord("e")) | (a == ord("l")) & (b == ord("l")))
        size = np.where(one, 2, np.where(two, 3, 0))
        mark, size = mark[size > 0], size[size > 0]
        start[mark + 1] = False
        rest = mark + size
        rest = rest[rest < n]
        start[rest[(kind[rest] == 1) & (kind[rest - 1] == 1) & ~opens[rest]]] = True
    return start, odd


def _encoder(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import gc
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        encoder = kept(path, lambda: PieceEncoder(path))  # its tasks share what it remembers
        gc.disable()  # no cycles are made here, and many small objects are
        for batch in batches:
            for part in parts_of(batch, "text", batch.num_rows, SLICE_BYTES):
                flat, lengths = encoder.encode_all(part.column("text"), end_id)
                offsets = pa.array(np.concatenate([[0], np.cumsum(lengths)]).astype("int32"))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(lengths), pa.ListArray.from_arrays(offsets, pa.array(flat))], names=["doc_id", "n_tokens", "ids"])
        gc.enable()

    return lean(run, path)


def _ranged(rows: DataFrame) -> DataFrame:
    """Rows dealt over ranges of doc_id, in order of the partitions. Only the ids are read to find the ranges
    (a range partitioner would read the texts for its sample); equal ids stay together."""
    size = int(str(rows._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if size < 1 << 60:  # a plan of unknown size says more
        parts = max(parts, min(size // FILE_BYTES, 1_000_000))
    if parts < 2 or rows.schema["doc_id"].dataType.simpleString() not in ("bigint", "int", "smallint"):
        return rows.repartitionByRange(F.col("doc_id").asc_nulls_first())
    cuts = rows.agg(F.percentile_approx("doc_id", [i / parts for i in range(1, parts)], max(10_000, 20 * parts))).first()[0] or []
    cuts = sorted(set(cuts))
    below = lambda some: F.size(F.filter(some, lambda c: c < F.col("doc_id")))
    known = F.array(*[F.lit(c).cast("long") for c in cuts]) if cuts else F.array().cast("array<bigint>")
    coarse = F.array(*[F.lit(c).cast("long") for c in cuts[63::64]]) if len(cuts) > 63 else F.array().cast("array<bigint>")
    step = below(coarse) * 64
    place = F.when(F.col("doc_id").isNull(), F.lit(0)).otherwise(step + below(F.slice(known, step + 1, F.lit(64))))
    return rows.repartitionById(len(cuts) + 1, place.cast("int"))


def write_tokens(docs: DataFrame, tokenizer_path: str, out_path: str, doc_id="doc_id", text="text", end_id=0, encoding="dictionary", row_group_bytes=32 << 20, page_bytes=64 << 10, page_rows=1000) -> None:
    """Write the token files of docs below out_path. encoding: dictionary or delta."""
    if encoding not in ("dictionary", "delta"):
        raise ValueError("encoding is dictionary or delta")
    ordered = _ranged(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    id_type = ordered.schema["doc_id"].dataType.simpleString()
    encoded = ordered.mapInArrow(_encoder(tokenizer_path, end_id), f"doc_id {id_type}, n_tokens bigint, ids array<int>")
    (
        encoded.write.option("parquet.writer.version", "PARQUET_2_0")
        .option("parquet.enable.dictionary", str(encoding == "dictionary").lower())
        .option("parquet.block.size", row_group_bytes)
        .option("parquet.page.size", page_bytes)
        .option("parquet.page.row.count.limit", page_rows)
        .option("parquet.dictionary.page.size", 1 << 20)
        .option("compression", "snappy")
        .parquet(out_path)
    )


def read_tokens(spark, path: str, first_id=None, last_id=None, columns=("doc_id", "n_tokens", "ids")) -> DataFrame:
    """Chosen columns of a range of documents; the filter reaches row groups and pages."""
    df = spark.read.parquet(path)
    if first_id is not None:
        df = df.where(F.col("doc_id") >= first_id)
    if last_id is not None:
        df = df.where(F.col("doc_id") <= last_id)
    return df.select(*columns)


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column("ids")
        offsets = ids.offsets.to_numpy().astype("int64") * 4
        raw = memoryview(ids.values.to_numpy(zero_copy_only=False).astype("<u4", copy=False)).cast("B")
        sums = [zlib.crc32(raw[a:b]) for a, b in zip(offsets[:-1], offsets[1:])]
        yield pa.RecordBatch.from_arrays(
            [*(batch.column(c) for c in ("doc_id", "_file", "_row")), pa.array(np.diff(offsets) // 4, pa.int64()), pa.array(sums, pa.int64())],
            names=["doc_id", "_file", "_row", "n_tokens", "ids_crc32"],
        )


def token_index(spark, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the files; start counts all ids before it."""
    files = spark.read.parquet(path)
    number = F.regexp_extract("_metadata.file_name", r"part-(\d+)", 1).cast("long")
    read = files.select("doc_id", "ids", number.alias("_file"), F.col("_metadata.row_index").alias("_row"))
    id_type = files.schema["doc_id"].dataType.simpleString()
    rows = settled(read.mapInArrow(lean(_digest), f"doc_id {id_type}, _file bigint, _row bigint, n_tokens bigint, ids_crc32 bigint"), "token-index")
    before = Window.orderBy("_file").rowsBetween(Window.unboundedPreceding, -1)  # one row a file
    files_before = rows.groupBy("_file").agg(F.sum("n_tokens").alias("_n")).select("_file", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    inside = Window.partitionBy("_file").orderBy("_row").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("_in", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0)))
    return placed.join(files_before, "_file").select("doc_id", (F.col("_base") + F.col("_in")).alias("start"), "n_tokens", "ids_crc32")


def op4_tokens(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = fresh_path(spark, "token-files")
    write_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), path)
    return token_index(spark, path)
