"""Exact membership of grams by runs: neighbouring grams with one smallest subgram travel together.

A gram goes to the part that its smallest subgram's hash names, so equal grams meet in one part wherever they stand.
A run of such grams is shipped as its symbols, two bits each, about a byte a gram instead of the gram's letters; grams
are cut from it again only inside the task that compares them. Exact: nothing is hashed but the part.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from . import kernel, md5_batch, native
from .hashing import in_range, xx64_seeded
from .sketch import MASK

#: Parts, tasks take several; subgrams are short, so that runs are long.
PARTS, SUBGRAM = 256, 10
#: Files of one mask.
FILES = 63
#: An odd number whose products have well-mixed upper digits.
MIX = np.int64(-7046029254386353131)
_FIELDS = ("part", "side", "ids", "sizes", "symbols")
SCHEMA = "part int, side int, ids binary, sizes binary, symbols binary"


def _runs(codes: np.ndarray, offsets: np.ndarray, k: int, parts: int = PARTS):
    """(first place, grams, read, part) of the runs of all grams; a run has 200 grams at most, so that its size fits a byte."""
    at, owner = kernel.valid_places(codes, offsets, k)
    if not len(at):
        return (np.empty(0, np.int64),) * 4
    t = min(SUBGRAM, k)
    least = kernel.sliding_min(xx64_seeded(kernel.packed(codes, t), 17) & MASK, k - t + 1)[at]
    new = np.concatenate([[True], (least[1:] != least[:-1]) | (at[1:] != at[:-1] + 1) | (owner[1:] != owner[:-1])])
    first = np.flatnonzero(new)
    since = np.arange(len(at)) - np.repeat(first, np.diff(np.append(first, len(at))))
    first = np.flatnonzero(since % 200 == 0)
    return at[first], np.diff(np.append(first, len(at))), owner[first], (xx64_seeded(least[first], 18) & MASK) % parts


def _spans(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of every span, one after another."""
    ends = np.cumsum(sizes)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(starts - (ends - sizes), sizes)


def builder(k: int, side: int, parts: int = PARTS):
    """Batches of (id, seq) -> rows of SCHEMA: the runs of a slice for one part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in kernel._slices(batch, "seq"):
                codes, offsets = kernel.symbols(part.column("seq"))
                if (codes == 4).any():
                    raise ValueError("runs are of sequences over A, C, G and T")
                at, n, owner, to = _runs(codes, offsets, k, parts)
                if not len(at):
                    continue
                ids = part.column("id").to_numpy()[owner]
                order = np.argsort(to, kind="stable")
                at, n, ids, to = at[order], n[order], ids[order], to[order]
                edge = np.append(np.flatnonzero(np.concatenate([[True], to[1:] != to[:-1]])), len(to))
                rows = []
                for lo, hi in zip(edge[:-1], edge[1:]):
                    symbols = codes[_spans(at[lo:hi], n[lo:hi] + k - 1)]
                    symbols = np.concatenate([symbols, np.zeros(-len(symbols) % 4, np.uint8)]).reshape(-1, 4)
                    rows.append((int(to[lo]), side, ids[lo:hi].astype("<i8").tobytes(), n[lo:hi].astype(np.uint8).tobytes(), (symbols @ np.array([1, 4, 16, 64], np.uint8)).astype(np.uint8).tobytes()))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary()))], names=list(_FIELDS))

    return run


def _grams(ids: bytes, sizes: bytes, symbols: bytes, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(packed grams, their ids) of a row."""
    n = np.frombuffer(sizes, np.uint8).astype(np.int64)
    raw = np.frombuffer(symbols, np.uint8)
    codes = np.stack([raw & 3, raw >> 2 & 3, raw >> 4 & 3, raw >> 6], axis=1).ravel()
    long = n + k - 1
    places = _spans(np.cumsum(long) - long, n)
    return kernel.packed(codes, k)[places], np.repeat(np.frombuffer(ids, "<i8"), n)


def matcher(k: int, blocks: int):
    """Rows of SCHEMA sorted by (part, side), queries (side 0) before reads (side 1, ids are numbers of files) ->
    (query_id, block, files): of the query's grams in this part the files that hold them all, as bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked: list[tuple[np.ndarray, np.ndarray]] = []
        key, grams, masks, marked, shift = None, None, None, None, 0

        def marks(values):
            """Places of grams in the marks: those of the queries are marked, most others are not."""
            return (values * MIX).view(np.uint64) >> np.uint64(shift)

        def close():
            if not asked:
                return None
            g, q = np.concatenate([a[0] for a in asked]), np.concatenate([a[1] for a in asked])
            held = masks[:, np.searchsorted(grams, g)] if masks is not None else np.zeros((blocks, len(g)), np.int64)
            order = np.argsort(q, kind="stable")
            q, held = q[order], held[:, order]
            first = np.flatnonzero(np.concatenate([[True], q[1:] != q[:-1]]))
            files = np.bitwise_and.reduceat(held, first, axis=1)
            return pa.RecordBatch.from_arrays([pa.array(np.tile(q[first], blocks)), pa.array(np.repeat(np.arange(blocks, dtype=np.int32), len(first))), pa.array(files.ravel())], names=["query_id", "block", "files"])

        for batch in batches:
            for part, side, ids, sizes, symbols in zip(*(batch.column(c).to_pylist() for c in _FIELDS)):
                if part != key:
                    if (out := close()) is not None:
                        yield out
                    asked, key, grams, masks = [], part, None, None
                got, of = _grams(ids, sizes, symbols, k)
                if side == 0:
                    asked.append((got, of))
                    continue
                if not asked:
                    continue
                if grams is None:
                    grams = kernel.distinct(np.concatenate([a[0] for a in asked]))
                    masks = np.zeros((blocks, len(grams)), np.int64)
                    shift = 64 - min(24, max(10, (8 * len(grams)).bit_length()))
                    marked = np.zeros(1 << (64 - shift), bool)
                    marked[marks(grams)] = True
                likely = marked[marks(got)]
                got, of = got[likely], of[likely]
                for file in (of[:1] if (of == of[:1]).all() else np.unique(of)):
                    mine = kernel.distinct(got[of == file])
                    at = np.minimum(np.searchsorted(grams, mine), len(grams) - 1)
                    at = at[grams[at] == mine]
                    masks[int(file) // FILES, at] |= np.int64(1 << (int(file) % FILES))
        if (out := close()) is not None:
            yield out

    return run


def hasher(k: int, seed: int):
    """Rows of SCHEMA sorted by part -> (part, hash): hashes of the grams, repeats in a row left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, ids, sizes, symbols in zip(*(batch.column(c).to_pylist() for c in ("part", "ids", "sizes", "symbols"))):
                hashes = xx64_seeded(kernel.distinct(_grams(ids, sizes, symbols, k)[0]), seed)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(hashes), part, np.int32)), pa.array(hashes)], names=["part", "hash"])

    return run


def tester(k: int, seed: int):
    """Rows (part, side, filter, ids, sizes, symbols) sorted by (part, side), a part's filter (side 0) before its queries ->
    (query_id, hit): whether the filter may hold all grams that the row has of the query."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, None
        for batch in batches:
            for part, side, made, ids, sizes, symbols in zip(*(batch.column(c).to_pylist() for c in ("part", "side", "filter", "ids", "sizes", "symbols"))):
                if part != key:
                    key, held = part, None
                if side == 0:
                    held = made
                    continue
                got, of = _grams(ids, sizes, symbols, k)
                hit = np.zeros(len(got), bool) if held is None else native.holds(held, xx64_seeded(got, seed))
                order = np.argsort(of, kind="stable")
                of, hit = of[order], hit[order]
                first = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]]))
                yield pa.RecordBatch.from_arrays([pa.array(of[first]), pa.array(np.logical_and.reduceat(hit, first))], names=["query_id", "hit"])

    return run


#: Values of a block of counters, and grams that a part keeps with repeats before it drops these.
BLOCK, KEPT = 1 << 15, 1 << 22
COUNTS = "block int, width int, counts binary"


def counter(k: int, seed: int, m: int):
    """Rows of SCHEMA sorted by part -> rows of COUNTS: how many distinct grams of the task have each md5 value in [0, m).
    Equal grams are in one part, so counts of tasks add up. A task keeps one counter a value."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(-(-m // BLOCK) * BLOCK, np.uint32)
        key, kept, size = None, [], 0

        def close():
            if kept:
                grams = kernel.distinct(np.concatenate(kept))
                for lo in range(0, len(grams), 1 << 20):
                    values = kernel.distinct_counts(in_range(md5_batch.of_packed(grams[lo : lo + (1 << 20)], k, seed), m))
                    counts[values[0]] += values[1].astype(np.uint32)

        for batch in batches:
            for part, ids, sizes, symbols in zip(*(batch.column(c).to_pylist() for c in ("part", "ids", "sizes", "symbols"))):
                if part != key:
                    close()
                    key, kept, size = part, [], 0
                kept.append(_grams(ids, sizes, symbols, k)[0])
                size += len(kept[-1])
                if size > KEPT:
                    kept = [kernel.distinct(np.concatenate(kept))]
                    size = len(kept[0]) // 2  # hardly any repeats: wait for more before the next try
        close()
        for block, mine in enumerate(counts.reshape(-1, BLOCK)):
            if mine.any():
                width = 1 if mine.max() < 1 << 8 else 2 if mine.max() < 1 << 16 else 4
                yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([width], pa.int32()), pa.array([mine.astype(f"<u{width}").tobytes()], pa.binary())], names=["block", "width", "counts"])

    return run


def collisions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of COUNTS sorted by block -> (keys, colliding): the grams of a block and their pairs with one value."""
    key, total = None, None

    def closed():
        return pa.RecordBatch.from_arrays([pa.array([int(total.sum())]), pa.array([int((total * (total - 1) // 2).sum())])], names=["keys", "colliding"])

    for batch in batches:
        for block, width, counts in zip(*(batch.column(c).to_pylist() for c in ("block", "width", "counts"))):
            if block != key:
                if key is not None:
                    yield closed()
                key, total = block, np.zeros(BLOCK, np.int64)
            total += np.frombuffer(counts, f"<u{width}")
    if key is not None:
        yield closed()
