"""Arrow kernels: positions of all grams of many DNA reads at once, in numpy.

The reads of a batch lie one after another in one buffer. Packing, hashing, sliding minima and positions
run over the whole buffer; places whose gram would leave its read, or holds another symbol than A, C, G or
T, are masked at the end. Values equal those of the expressions in sketch and anchored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401

from ..plans.spec import PAGE_BITS, PAGE_BYTES, IndexSpec
from . import md5_batch
from .hashing import in_range, modprime_longs, xx64_seeded
from .sketch import BORROW, EMPTY, MASK, _shuffled

#: Symbols handled at once, and bits (8 bytes each) that one task keeps before it hands them on.
SLICE_SYMBOLS = 1 << 20
#: Symbols handled at once where arrays are gone through many times: few enough that they stay in a core's own cache.
NEAR_SYMBOLS = 1 << 16
TASK_BITS = 6 << 20
#: Small arrays are kept as a flag (a byte) for each bit they could set, handed on once, at the task's end: up to so many
#: flags for one of TASK_BITS, which is the memory that sorting those takes.
FLAGS = 24
#: Pages with fewer bits than this travel as lists of 2-byte offsets, others as the 4 KB they are.
DENSE = PAGE_BYTES // 2
_CODES = np.full(256, 4, np.uint8)
for _i, _c in enumerate(b"ACGT"):
    _CODES[_c] = _i
_LETTERS = np.frombuffer(b"ACGTN", np.uint8)


def symbols(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(codes of all symbols, offsets of the reads); null reads are empty."""
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None and len(column) else np.empty(0, np.uint8)
    return _CODES[raw], offsets - (offsets[0] if len(offsets) else 0)


def packed(codes: np.ndarray, width: int) -> np.ndarray:
    """Every `width` consecutive symbols as a number, two bits a symbol; doubling."""
    have, out = 1, codes.astype(np.int64) & 3
    parts: list[tuple[int, np.ndarray]] = [(1, out)]
    while have * 2 <= width:
        out = (out[:-have] << (2 * have)) | out[have:] if len(out) > have else out[:0]
        have *= 2
        parts.append((have, out))
    total, made = have, out
    for size, part in reversed(parts[:-1]):
        if total + size <= width:
            n = max(0, min(len(made), len(part) - total))
            made = (made[:n] << (2 * size)) | part[total : total + n]
            total += size
    return made


def sliding_min(h: np.ndarray, width: int) -> np.ndarray:
    have = 1
    while have < width:
        step = min(have, width - have)
        h = np.minimum(h[:-step], h[step:]) if len(h) > step else h[:0]
        have += step
    return h


def tree_min(h: np.ndarray, width: int) -> np.ndarray:
    """The same by a ring of leaves under a segment tree: one leaf changes a step (ablation; slow)."""
    size = 1 << (width - 1).bit_length()
    tree = np.full(2 * size, EMPTY, np.int64)
    out = np.empty(max(0, len(h) - width + 1), np.int64)
    for i, v in enumerate(h):
        at = size + i % width
        tree[at] = v
        at //= 2
        while at:
            tree[at] = min(tree[2 * at], tree[2 * at + 1])
            at //= 2
        if i >= width - 1:
            out[i - width + 1] = tree[1]
    return out


def _keys(codes: np.ndarray, width: int, spec: IndexSpec):
    """What is hashed for all substrings of the given length: packed numbers, or for md5 the letters."""
    return (_LETTERS[codes], width) if spec.family == "md5" else packed(codes, width)


def _md5(keys, seed: int) -> np.ndarray:
    """md5_value of windows of letters or of sketches; equal neighbours, as sketches often are, are hashed once."""
    if isinstance(keys, tuple):
        return md5_batch.of_windows(*keys, seed)
    if not len(keys):
        return keys
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return np.repeat(md5_batch.of_longs(keys[first], seed), np.diff(np.append(first, len(keys))))


def _wide(keys, seed: int, spec: IndexSpec) -> np.ndarray:
    """A wide non-negative hash, as sketch.raw_hash gives it."""
    if spec.family == "md5":
        return _md5(keys, seed)
    return modprime_longs(keys, seed, 1 << 61) if spec.family == "modprime" else xx64_seeded(keys, seed) & MASK


def _placed(keys, seed: int, m: int, spec: IndexSpec) -> np.ndarray:
    if spec.family == "md5":
        return in_range(_md5(keys, seed), m)
    return modprime_longs(keys, seed, m) if spec.family == "modprime" else in_range(xx64_seeded(keys, seed), m)


def _once(made: dict | None, key: tuple, make):
    """make(), or what it gave for the key before."""
    if made is None:
        return make()
    if key not in made:
        made[key] = make()
    return made[key]


def sketches(codes: np.ndarray, spec: IndexSpec) -> list[np.ndarray]:
    """Sketch values of every place, for each function."""
    lowest = tree_min if spec.backend == "segment_tree" else sliding_min
    keys = _keys(codes, spec.t, spec)
    if not (spec.oph and spec.eta > 1):
        return [lowest(_wide(keys, spec.seeds(j)[0], spec), spec.width) for j in range(spec.eta)]
    h = _wide(keys, spec.seeds(0)[0], spec)
    even = spec.eta & (spec.eta - 1) == 0  # h is not negative
    bins, values = (h & np.int64(spec.eta - 1), h >> np.int64(spec.eta.bit_length() - 1)) if even else (h % spec.eta, h // spec.eta)
    minima = [lowest(np.where(bins == b, values, EMPTY), spec.width) for b in range(spec.eta)]
    out = []
    for b in range(spec.eta):
        order = [(b + s) % spec.eta for s in range(spec.eta)] if spec.densify == "rotate" else _shuffled(b, spec.eta)
        got = minima[order[0]].copy()
        empty = np.flatnonzero(got == EMPTY)
        for s in range(1, spec.eta):
            if not len(empty):
                break
            lent = minima[order[s]][empty]
            ok = lent != EMPTY
            got[empty[ok]] = lent[ok] + s * BORROW
            empty = empty[~ok]
        out.append(got)
    return out


def _runs(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(values, lengths) of runs of equal neighbours: a sketch stays the same over several grams."""
    first = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]])) if len(values) else np.empty(0, np.int64)
    return values[first], np.diff(np.append(first, len(values)))


def _hashed(made: dict | None, name: tuple, keys, seed: int, m: int, spec: IndexSpec) -> np.ndarray:
    """_placed(keys, seed, m, spec); hashes that do not depend on the range are kept under the name."""
    if made is None or spec.family == "modprime":
        return _placed(keys, seed, m, spec)
    return in_range(_once(made, (*name, seed), lambda: _md5(keys, seed) if spec.family == "md5" else xx64_seeded(keys, seed)), m)


def positions(codes: np.ndarray, spec: IndexSpec, made: dict | None = None) -> list[np.ndarray]:
    """Bit positions of the gram at every place, for each function.

    made: what several specs have in common for these codes (hashes of grams, sketches and theirs); an empty dict at first.
    """
    name = ("grams", spec.k, spec.family)
    grams = _once(made, name, lambda: _keys(codes, spec.k, spec)) if spec.hash != "sketch" else None
    out = []
    if spec.hash != "uniform":
        sketch = ("sketches", spec.k, spec.t, spec.eta, spec.seed, spec.oph, spec.densify, spec.family, spec.backend)
        values = _once(made, sketch, lambda: [_runs(v) for v in sketches(codes, spec)])
    for j in range(spec.eta):
        _, s1, s2 = spec.seeds(j)
        if spec.hash == "uniform":
            out.append(_hashed(made, name, grams, s2, spec.range, spec))
            continue
        of, sizes = values[j]
        anchor = _hashed(made, (*sketch, j), of, s1, spec.range if spec.hash == "sketch" else spec.anchors, spec)
        if spec.hash == "anchored" and spec.align == "page":
            anchor = anchor // spec.L * spec.L
        anchor = np.repeat(anchor, sizes)
        out.append(anchor if spec.hash == "sketch" else anchor + _hashed(made, name, grams, s2, spec.L, spec))
    return out


def valid_places(codes: np.ndarray, offsets: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(places where a whole gram stands inside its read, number of that read)."""
    sizes = np.diff(offsets)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    n = max(0, len(codes) - k + 1)
    ends = offsets[1:][owner[:n]] if n else np.empty(0, np.int64)
    ok = np.arange(n) + k <= ends
    if (codes == 4).any():
        bad = np.concatenate([[0], np.cumsum(codes == 4)])
        ok &= bad[k : k + n] == bad[:n]
    at = np.flatnonzero(ok)
    return at, owner[at]


def _slices(batch: pa.RecordBatch, name: str, symbols: int | None = None) -> Iterator[pa.RecordBatch]:
    """Parts of a batch with about SLICE_SYMBOLS symbols, or as many as given."""
    symbols = symbols or SLICE_SYMBOLS
    sizes = np.asarray(pa.compute.utf8_length(batch.column(name)).fill_null(0))
    first = total = 0
    for i, n in enumerate(sizes):
        total += int(n)
        if total >= symbols:
            yield batch.slice(first, i + 1 - first)
            first, total = i + 1, 0
    if first < batch.num_rows:
        yield batch.slice(first)


def distinct(values: np.ndarray) -> np.ndarray:
    """Sorted distinct values, by sorting: numpy's own way goes through a hash table, which is many times slower."""
    values = np.sort(values)
    first = np.ones(len(values), bool)
    np.not_equal(values[1:], values[:-1], out=first[1:])
    return values[first]


def distinct_counts(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values, and how often each stands there."""
    values = np.sort(values)
    first = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]])) if len(values) else np.empty(0, np.int64)
    return values[first], np.diff(np.append(first, len(values)))


def page_builder(spec: IndexSpec, tally: bool = False):
    """Batches of (filter_id, seq) -> (filter_id, rep, page_no, dense, bits[, n, total]): the distinct bits of a task by page.

    A task keeps flags of small arrays, of others sorted distinct bits, so memory and what is shuffled grow with the
    bits set, not with the range: pages with few bits go out as offsets, full ones as bitmaps. With tally the number of positions, repeats
    counted, and their sum stand beside one page of each array, 0 beside others.
    """
    reps = 1 if spec.layout == "shared" else spec.eta
    span = -(-spec.range // PAGE_BITS)  # pages of one array

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        numbers: dict[str, int] = {}
        kept: list[np.ndarray] = []
        size = 0
        flags = np.zeros(0, bool)
        tallies: dict[int, tuple[int, int]] = {}  # by array: positions and their sum, not handed on yet

        def joined() -> np.ndarray:
            return kept[0] if len(kept) == 1 else distinct(np.concatenate(kept))

        def hand_on(codes: np.ndarray):
            page = codes >> 15
            first = np.flatnonzero(np.concatenate([[True], page[1:] != page[:-1]]))
            counts = np.diff(np.append(first, len(codes)))
            offsets = (codes & (PAGE_BITS - 1)).astype("<u2")
            dense = counts >= DENSE
            key = page[first]
            array, number = key // span, key % span
            for at in np.array_split(np.flatnonzero(~dense), max(1, int((~dense).sum()) // 4096)):
                if len(at):
                    ends = np.concatenate([[0], np.cumsum(counts[at] * 2)]).astype(np.int32)
                    picked = offsets if len(at) == len(first) else offsets[np.repeat(first[at] - (np.cumsum(counts[at]) - counts[at]), counts[at]) + np.arange(int(counts[at].sum()))]
                    yield rows(array[at], number[at], False, pa.Array.from_buffers(pa.binary(), len(at), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(picked))]))
            for at in np.array_split(np.flatnonzero(dense), max(1, int(dense.sum()) // 256)):
                if len(at):
                    yield rows(array[at], number[at], True, pa.array([bitmap(offsets[first[i] : first[i] + counts[i]]).tobytes() for i in at], pa.binary()))

        def rows(array, number, dense, bits):
            names = np.array(list(numbers), object)[array // reps]
            columns = [pa.array(names, pa.string()), pa.array((array % reps).astype(np.int32)), pa.array(number), pa.array(np.full(len(array), dense)), bits]
            if tally:
                beside = np.zeros((2, len(array)), np.int64)
                for key, first in zip(*np.unique(array, return_index=True)):
                    beside[:, first] = tallies.pop(int(key), (0, 0))
                columns += [pa.array(beside[0]), pa.array(beside[1])]
            return pa.RecordBatch.from_arrays(columns, names=["filter_id", "rep", "page_no", "dense", "bits"] + ["n", "total"] * tally)

        for batch in batches:
            for part in _slices(batch, "seq"):
                codes, offsets = symbols(part.column("seq"))
                at, owner = valid_places(codes, offsets, spec.k)
                if not len(at):
                    continue
                told = part.column("filter_id").dictionary_encode()
                place = np.array([numbers.setdefault(str(n), len(numbers)) for n in told.dictionary.to_pylist()], np.int64)
                of = place[told.indices.to_numpy()][owner] * reps
                if flags is not None and len(numbers) * reps * span * PAGE_BITS > FLAGS * TASK_BITS:  # too many by now
                    for codes_ in flagged(flags):
                        yield from hand_on(codes_)
                    flags = None
                if flags is not None and len(flags) < len(numbers) * reps * span * PAGE_BITS:
                    flags = np.concatenate([flags, np.zeros(len(numbers) * reps * span * PAGE_BITS - len(flags), bool)])
                for j, pos in enumerate(positions(codes, spec)):
                    arrays, bits = of + spec.rep_of(j), pos[at]
                    if tally:
                        for key in np.unique(arrays):
                            mine = bits[arrays == key]
                            n, total = tallies.get(int(key), (0, 0))
                            tallies[int(key)] = (n + len(mine), total + int(mine.sum()))
                    if flags is not None:
                        flags[(arrays * span << 15) + bits] = True
                        continue
                    kept.append(distinct((arrays * span << 15) + bits))
                    size += len(kept[-1])
                    if size > TASK_BITS:
                        kept = [joined()]
                        size = len(kept[0])
                        if size > TASK_BITS // 2:  # hardly any repeats: what is kept would only grow
                            yield from hand_on(kept[0])
                            kept, size = [], 0
        for codes_ in flagged(flags) if flags is not None else ():
            yield from hand_on(codes_)
        if kept:
            yield from hand_on(joined())

    return run


def flagged(flags: np.ndarray, step: int = 256 * PAGE_BITS) -> Iterator[np.ndarray]:
    """Places of the flags that are set, some hundred whole pages at once."""
    for lo in range(0, len(flags), step):
        at = np.flatnonzero(flags[lo : lo + step])
        if len(at):
            yield at + lo


def bitmap(offsets: np.ndarray) -> np.ndarray:
    """The page whose bits are set at the offsets."""
    bits = np.zeros(PAGE_BITS, bool)
    bits[offsets] = True
    return np.packbits(bits, bitorder="little")


def page_merger(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of page_builder sorted by (filter_id, rep, page_no) -> one row (filter_id, rep, page_no, bits[, n, total]) a page."""
    key, page, sparse, sums = None, None, [], (0, 0)
    done: list[tuple] = []
    types = [("filter_id", pa.string()), ("rep", pa.int32()), ("page_no", pa.int64()), ("bits", pa.binary()), ("n", pa.int64()), ("total", pa.int64())]
    tally = False

    def close():
        out = page if page is not None else np.zeros(PAGE_BYTES, np.uint8)
        if sparse:
            out = out | bitmap(np.frombuffer(b"".join(sparse), "<u2"))
        done.append((*key, out.tobytes(), *sums))

    def flushed():
        columns = list(zip(*done))
        done.clear()
        told = types if tally else types[:4]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(columns, told)], names=[n for n, _ in told])

    for batch in batches:
        tally = "n" in batch.schema.names
        beside = zip(batch.column("n").to_pylist(), batch.column("total").to_pylist()) if tally else [(0, 0)] * batch.num_rows
        for name, rep, number, dense, bits, (n, total) in zip(*(batch.column(c).to_pylist() for c in ("filter_id", "rep", "page_no", "dense", "bits")), beside):
            if (name, rep, number) != key:
                if key is not None:
                    close()
                key, page, sparse, sums = (name, rep, number), None, [], (0, 0)
            sums = (sums[0] + n, sums[1] + total)
            if dense:
                more = np.frombuffer(bits, np.uint8)
                page = more if page is None else page | more
            else:
                sparse.append(bits)
            if len(done) >= 512:
                yield flushed()
    if key is not None:
        close()
    if done:
        yield flushed()


def probe_builder(spec: IndexSpec, with_grams: bool = False):
    """Batches of (query_id, seq) -> probes grouped by page: (query_id, rep, page_no, offsets[, grams]).

    Grouping happens inside a query's row, before anything is shuffled; offsets are distinct, or with grams
    one a gram, the gram's number beside it.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch, "seq"):
                codes, offsets = symbols(part.column("seq"))
                at, owner = valid_places(codes, offsets, spec.k)
                ids = part.column("query_id").to_numpy()
                for j, pos in enumerate(positions(codes, spec)):
                    p = pos[at]
                    gram = at - offsets[:-1][owner]
                    if with_grams:
                        order = np.lexsort((gram, p // PAGE_BITS, owner))
                    else:
                        order = np.lexsort((p, owner))
                    o, v, g = owner[order], p[order], gram[order]
                    if not with_grams and len(o):
                        first = np.concatenate([[True], (o[1:] != o[:-1]) | (v[1:] != v[:-1])])
                        o, v, g = o[first], v[first], g[first]
                    page = v // PAGE_BITS
                    edge = np.flatnonzero(np.concatenate([[True], (o[1:] != o[:-1]) | (page[1:] != page[:-1])])) if len(o) else np.empty(0, np.int64)
                    ends = pa.array(np.concatenate([edge, [len(o)]]).astype(np.int32))
                    columns = [pa.array(ids[o[edge]], pa.int64()), pa.array(np.full(len(edge), spec.rep_of(j)), pa.int32()), pa.array(page[edge], pa.int64()), pa.ListArray.from_arrays(ends, pa.array((v % PAGE_BITS).astype(np.int32)))]
                    if with_grams:
                        columns.append(pa.ListArray.from_arrays(ends, pa.array(g.astype(np.int32))))
                    yield pa.RecordBatch.from_arrays(columns, names=["query_id", "rep", "page_no", "offsets"] + ["grams"] * with_grams)

    return run


DEALT = "slot int, side int, filter_id string, rep int, page_no bigint, bits binary, query_id bigint, seq string"
ANSWERS = {
    "hit": "query_id bigint, hit boolean",
    "grams": "query_id bigint, grams array<struct<pos: int, hit: boolean>>",
    "filters": "query_id bigint, short boolean, filters array<string>",
    "counts": "query_id bigint, n_grams bigint, counts array<struct<filter_id: string, n_hit: bigint>>",
}


def prober(spec: IndexSpec, answer: str):
    """Rows of DEALT sorted by (slot, side), every slot with all pages of the index (side 0) before its queries (side 1) ->
    one row of ANSWERS[answer] a query. A task keeps the filters' bits and streams the queries.

    hit, grams: of the union of all filters; hit is null without grams. filters: those that hold all grams of the query,
    none without grams; short says that it is shorter than a gram. counts: the grams that each filter holds, if any.
    """
    reps = 1 if spec.layout == "shared" else spec.eta
    span = -(-spec.range // PAGE_BITS)
    union = answer in ("hit", "grams")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot, tables = None, {}

        def listed(rows: np.ndarray, total: int, values: pa.Array) -> pa.Array:
            ends = np.concatenate([[0], np.cumsum(np.bincount(rows, minlength=total))]).astype(np.int32)
            return pa.ListArray.from_arrays(pa.array(ends), values)

        def answered(part: pa.RecordBatch) -> pa.RecordBatch:
            codes, offsets = symbols(part.column("seq"))
            at, owner = valid_places(codes, offsets, spec.k)
            places = [(spec.rep_of(j) * span << 15) + p[at] for j, p in enumerate(positions(codes, spec))] if len(at) else []
            first = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]])) if len(at) else np.empty(0, np.int64)
            asked, n = owner[first], part.num_rows

            def held(table: np.ndarray) -> np.ndarray:
                ok = np.ones(len(at), bool)
                for p in places:
                    ok &= table[p >> 3] >> (p & 7).astype(np.uint8) & 1 == 1
                return ok

            if union:
                ok = held(tables[""]) if tables else np.zeros(len(at), bool)
                if answer == "hit":
                    hit, none = np.zeros(n, bool), np.ones(n, bool)
                    none[asked] = False
                    if len(at):
                        hit[asked] = np.logical_and.reduceat(ok, first)
                    columns = [pa.array(hit, mask=none)]
                else:
                    columns = [listed(owner, n, pa.StructArray.from_arrays([pa.array((at - offsets[:-1][owner]).astype(np.int32)), pa.array(ok)], names=["pos", "hit"]))]
            else:
                put = np.logical_and.reduceat if answer == "filters" else np.add.reduceat
                found = np.stack([put(held(t).astype(np.int64), first) for t in tables.values()], axis=1) if tables and len(at) else np.zeros((len(asked), len(tables)), np.int64)
                row, which = np.nonzero(found)
                names = pa.array(list(tables), pa.string()).take(pa.array(which))
                if answer == "filters":
                    columns = [pa.array(np.diff(offsets) < spec.k), listed(asked[row], n, names)]
                else:
                    columns = [pa.array(np.bincount(owner, minlength=n).astype(np.int64)), listed(asked[row], n, pa.StructArray.from_arrays([names, pa.array(found[row, which].astype(np.int64))], names=["filter_id", "n_hit"]))]
            return pa.RecordBatch.from_arrays([part.column("query_id"), *columns], names=[c.split()[0] for c in ANSWERS[answer].split("<")[0].split(", ")])

        for batch in batches:
            stored = batch.filter(pa.compute.equal(batch.column("side"), 0))
            for mine, name, rep, number, bits in zip(*(stored.column(c).to_pylist() for c in ("slot", "filter_id", "rep", "page_no", "bits"))):
                slot = mine if slot is None else slot
                if mine == slot:  # a task with several slots gets the index again with each
                    name = "" if union else name
                    if name not in tables:
                        tables[name] = np.zeros(reps * span * PAGE_BYTES, np.uint8)
                    lo = (rep * span + number) * PAGE_BYTES
                    tables[name][lo : lo + PAGE_BYTES] |= np.frombuffer(bits, np.uint8)
            for part in _slices(batch.filter(pa.compute.equal(batch.column("side"), 1)), "seq"):
                yield answered(part)

    return run


def locality_builder(specs: list[IndexSpec], blocks: list[int]):
    """Batches of (seq), a query a row -> (number, block, accesses, distinct_blocks, changes) of a task for the number of each
    spec and each size of a block: sums over queries and arrays. Specs share what their positions have in common."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((len(specs), len(blocks), 3), np.int64)
        for batch in batches:
            for part in _slices(batch, "seq", NEAR_SYMBOLS):
                codes, offsets = symbols(part.column("seq"))
                made = {}
                for i, spec in enumerate(specs):
                    at, owner = valid_places(codes, offsets, spec.k)
                    if not len(at):
                        continue
                    got = [p[at] for p in positions(codes, spec, made)]
                    arrays = [np.sort(np.stack(got, axis=1), axis=1).ravel()] if spec.layout == "shared" else got  # order: gram, bit
                    of = np.repeat(owner, spec.eta) if spec.layout == "shared" else owner
                    new = np.concatenate([[True], of[1:] != of[:-1]])
                    for bits in arrays:
                        for b, size in enumerate(blocks):
                            block = bits // size
                            changed = new.copy()
                            changed[1:] |= block[1:] != block[:-1]
                            heads = np.flatnonzero(changed)  # a block that does not change is no other one
                            sums[i, b] += len(bits), len(distinct(of[heads] * (spec.range // size + 1) + block[heads])), len(heads)
        keys = np.indices(sums.shape[:2]).reshape(2, -1)
        yield pa.RecordBatch.from_arrays([pa.array(keys[0].astype(np.int32)), pa.array(np.array(blocks, np.int32)[keys[1]]), *(pa.array(sums[:, :, c].ravel()) for c in range(3))], names=["number", "block", "accesses", "distinct_blocks", "changes"])

    return run


def several_builder(specs: list[IndexSpec]):
    """Batches of (seq) -> rows of page_builder, filter_id the number of a spec: the pages of a filter for each spec, whose
    positions share what they have in common. A task keeps a flag for each bit, so this is for small arrays."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        flags = [np.zeros((1 if s.layout == "shared" else s.eta, -(-s.range // PAGE_BITS) * PAGE_BITS), bool) for s in specs]
        for batch in batches:
            for part in _slices(batch, "seq", NEAR_SYMBOLS):
                codes, offsets = symbols(part.column("seq"))
                made = {}
                for i, spec in enumerate(specs):
                    if not i or spec.k != specs[i - 1].k:
                        at = valid_places(codes, offsets, spec.k)[0]
                    for j, p in enumerate(positions(codes, spec, made) if len(at) else ()):
                        p = p[at]
                        if spec.hash == "sketch":  # neighbours mostly set the same bit
                            p = p[np.concatenate([[True], p[1:] != p[:-1]])]
                        flags[i][spec.rep_of(j)][p] = True
        for i, mine in enumerate(flags):
            for rep, array in enumerate(mine):
                rows = []
                for number, page in enumerate(array.reshape(-1, PAGE_BITS)):
                    if n := np.count_nonzero(page):
                        rows.append((str(i), rep, number, n >= DENSE, np.packbits(page, bitorder="little").tobytes() if n >= DENSE else np.flatnonzero(page).astype("<u2").tobytes()))
                for lo in range(0, len(rows), 256):
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[lo : lo + 256]), (pa.string(), pa.int32(), pa.int64(), pa.bool_(), pa.binary()))], names=["filter_id", "rep", "page_no", "dense", "bits"])

    return run


def several_prober(specs: list[IndexSpec]):
    """Rows of DEALT as prober takes them, filter_id the number of a spec -> (query_id, hits): for each spec whether its
    filter holds all grams of the query, null without grams."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot = None
        spans = [-(-s.range // PAGE_BITS) for s in specs]
        tables = [np.zeros((1 if s.layout == "shared" else s.eta) * span * PAGE_BYTES, np.uint8) for s, span in zip(specs, spans)]
        for batch in batches:
            stored = batch.filter(pa.compute.equal(batch.column("side"), 0))
            for mine, name, rep, number, bits in zip(*(stored.column(c).to_pylist() for c in ("slot", "filter_id", "rep", "page_no", "bits"))):
                slot = mine if slot is None else slot
                if mine == slot:  # a task with several slots gets the index again with each
                    lo = (rep * spans[int(name)] + number) * PAGE_BYTES
                    tables[int(name)][lo : lo + PAGE_BYTES] |= np.frombuffer(bits, np.uint8)
            for part in _slices(batch.filter(pa.compute.equal(batch.column("side"), 1)), "seq", NEAR_SYMBOLS):
                codes, offsets = symbols(part.column("seq"))
                made, n = {}, part.num_rows
                hits, none = np.zeros((n, len(specs)), bool), np.ones((n, len(specs)), bool)
                for i, spec in enumerate(specs):
                    at, owner = valid_places(codes, offsets, spec.k)
                    if not len(at):
                        continue
                    first = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
                    ok = np.ones(len(at), bool)
                    for j, p in enumerate(positions(codes, spec, made)):
                        p = p[at] + (spec.rep_of(j) * spans[i] << 15)
                        ok &= tables[i][p >> 3] >> (p & 7).astype(np.uint8) & 1 == 1
                    hits[owner[first], i] = np.logical_and.reduceat(ok, first)
                    none[owner[first], i] = False
                ends = pa.array(np.arange(n + 1, dtype=np.int32) * len(specs))
                yield pa.RecordBatch.from_arrays([part.column("query_id"), pa.ListArray.from_arrays(ends, pa.array(hits.ravel(), mask=none.ravel()))], names=["query_id", "hits"])

    return run


def jaccard_builder(k: int, t: int, gaps: tuple[int, ...]):
    """Batches of (seq) -> (gap, pairs, total): pairs of grams a gap apart in a read, and the sum of the similarities of
    their subgram sets. Where no subgram stands twice in a pair the sizes follow from the gap; other pairs are counted.
    """
    w = k - t + 1

    def counted(keys: np.ndarray, at: np.ndarray, gap: int) -> float:
        total = 0.0
        sizes = lambda rows: 1 + (np.diff(np.sort(rows, axis=1), axis=1) != 0).sum(axis=1)
        for lo in range(0, len(at), 1 << 13):
            a = keys[at[lo : lo + (1 << 13), None] + np.arange(w)]
            b = keys[at[lo : lo + (1 << 13), None] + gap + np.arange(w)]
            union = sizes(np.concatenate([a, b], axis=1))
            total += float(((sizes(a) + sizes(b) - union) / union).sum())
        return total

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch, "seq"):
                codes, offsets = symbols(part.column("seq"))
                if (codes == 4).any():
                    raise ValueError("the kernel takes sequences over A, C, G and T")
                at, owner = valid_places(codes, offsets, k)
                if not len(at):
                    continue
                keys = packed(codes, t)
                order = np.argsort(keys, kind="stable")
                same = np.flatnonzero(keys[order[1:]] == keys[order[:-1]])
                before = np.full(len(keys), -1, np.int64)  # where the same subgram stood last
                before[order[same + 1]] = order[same]
                rows = []
                for gap in gaps:
                    mine = at[at + gap + k <= offsets[1:][owner]]
                    if not len(mine):
                        continue
                    twice = -sliding_min(-before, w + gap)[mine] >= mine
                    shared = max(w - gap, 0)
                    rows.append((gap, len(mine), int((~twice).sum()) * (shared / (2 * w - shared)) + counted(keys, mine[twice], gap)))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*rows), (pa.int32(), pa.int64(), pa.float64()))], names=["gap", "pairs", "total"])

    return run


def trace_builder(spec: IndexSpec, keys: list[str]):
    """Batches of (keys, seq) -> (keys, pos, rep, bit): every access in the order gram, function."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch, "seq"):
                codes, offsets = symbols(part.column("seq"))
                at, owner = valid_places(codes, offsets, spec.k)
                got = positions(codes, spec)
                table = np.stack([p[at] for p in got], axis=1) if len(at) else np.empty((0, spec.eta), np.int64)
                rows = pa.array(np.repeat(owner, spec.eta))
                yield pa.RecordBatch.from_arrays(
                    [*(part.column(c).take(rows) for c in keys), pa.array(np.repeat(at - offsets[:-1][owner], spec.eta).astype(np.int32)), pa.array(np.tile([spec.rep_of(j) for j in range(spec.eta)], len(at)).astype(np.int32)), pa.array(table.ravel())],
                    names=[*keys, "pos", "rep", "bit"],
                )

    return run


__all__ = ["PAGE_BYTES", "bitmap", "distinct", "distinct_counts", "jaccard_builder", "locality_builder", "page_builder", "page_merger", "packed", "positions", "probe_builder", "prober", "several_builder", "several_prober", "sketches", "sliding_min", "symbols", "trace_builder", "tree_min", "valid_places"]
