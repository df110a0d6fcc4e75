"""A cache of levels under LRU, for the accesses of a probe or build trace. One task a trace."""

from __future__ import annotations

from collections import OrderedDict

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernel

LINE_BITS = 512


class Cache:
    """Levels under LRU; a level is asked when the one above missed.

    sizes: lines each level holds. ways: lines of a set, the whole level if None.
    """

    def __init__(self, sizes: tuple[int, ...], ways: int | None = None):
        self.levels = []
        for size in sizes:
            per = size if ways is None else min(ways, size)
            self.levels.append(([OrderedDict() for _ in range(max(1, size // per))], per))
        self.misses = [0] * len(sizes)

    def run(self, lines) -> None:
        """Access a sequence of line numbers, after what was accessed before."""
        misses, levels = self.misses, self.levels
        for line in lines:
            for i, (sets, per) in enumerate(levels):
                held = sets[line % len(sets)]
                if line in held:
                    held.move_to_end(line)
                    break
                misses[i] += 1
                held[line] = None
                if len(held) > per:
                    held.popitem(last=False)


#: Accesses that a Level takes at once.
CHUNK = 1 << 16


class Level:
    """One fully associative level under LRU, over many accesses at once; misses as Cache counts them.

    An access misses if as many other lines as the level holds were accessed since its line was.
    below: gets the lines that missed.
    """

    def __init__(self, size: int, below: Level | None = None):
        self.size, self.below, self.misses = size, below, 0
        self.held = np.empty(0, np.int64)  # oldest first
        self.waiting: list[np.ndarray] = []

    def run(self, lines: np.ndarray) -> None:
        self.waiting.append(lines)
        if sum(map(len, self.waiting)) >= CHUNK:
            self.settle(False)

    def settle(self, end: bool = True) -> None:
        """Take the accesses that wait; at the end also those of the levels below."""
        if self.waiting:
            missed = self._missed(np.concatenate(self.waiting))
            self.waiting = []
            self.misses += len(missed)
            if self.below is not None:
                self.below.run(missed)
        if end and self.below is not None:
            self.below.settle()

    def _missed(self, lines: np.ndarray) -> np.ndarray:
        n_held = len(self.held)
        lines = np.concatenate([self.held, lines])
        before, after = _links(lines)
        missed = self._bounded(before, after) if self.size <= 1024 else None  # of such blocks there would be many
        if missed is None:
            missed = self._by_blocks(before, after, n_held)
        missed[:n_held] = False
        self.held = lines[(after == len(lines)).nonzero()[0][-self.size :]]
        return lines[missed]

    def _bounded(self, before: np.ndarray, after: np.ndarray) -> np.ndarray | None:
        """Which accesses miss, from counts over all of them; None if these leave too many open.

        Of the accesses since a line was accessed those are the first of theirs that have not been accessed for longer, so
        counts of such ones bound the number of lines from below, and from above but for the earliest.
        """
        n, size = len(before), self.size
        since = np.arange(n, dtype=np.int32) - before
        missed = before < 0
        since[missed] = n + 1
        open_ = ((since > size) & ~missed).nonzero()[0]
        spans = [size + size // 16]
        for at in range(n // 8, n, n // 8 + 1):  # how many accesses hold `size` lines, in some places
            newest = (after[max(0, at - 8 * size) : at] >= at).nonzero()[0][-size:]
            spans.append(min(at, 8 * size) - int(newest[0]) if len(newest) == size else 0)
        span = max(spans) + max(spans) // 32
        for _ in range(4):
            if len(open_) * 1000 < n:
                break
            rare = np.zeros((2, n + 1), np.int32)
            near = span // 2
            np.cumsum(since > span, out=rare[0, 1:])
            np.cumsum(since > near, out=rare[1, 1:])
            ago = since[open_]
            many = rare[0, open_] - rare[0, open_ - np.minimum(ago, span) + 1] >= size
            few = np.minimum(near, ago) + rare[1, open_] - rare[1, np.minimum(open_ - ago + 1 + near, open_)] < size
            missed[open_[many]] = True
            open_ = open_[~(many | few)]
            span += span // 4
        if len(open_) * 100 > n:
            return None
        for i in open_.tolist():
            missed[i] = np.count_nonzero(before[before[i] + 1 : i] <= before[i]) >= size
        return missed

    def _by_blocks(self, before: np.ndarray, after: np.ndarray, n_held: int) -> np.ndarray:
        """Which accesses miss, block by block.

        Accesses are taken in blocks of `size` at most, so one whose line stands in its block before hits. Of another the
        lines accessed since its line was are those held that are newer, and those that the block has accessed so far and
        that are older or new.
        """
        n, size, step = len(before), self.size, min(self.size, 4096)
        missed = np.zeros(n, bool)
        held = np.arange(n_held)  # places of the last accesses of the lines held, oldest first
        for lo in range(n_held, n, step):
            hi = min(lo + step, n)
            at = before[lo:hi]
            new = (at < lo).nonzero()[0]
            at = at[new]
            miss = at < (held[0] if len(held) == size else 0)
            within = len(held) + len(new) - 1 - size  # the block's own lines push out no more than so many of the oldest
            if within > 0:
                doubt = (~miss & (at < held[within])).nonzero()[0]
                if len(doubt):
                    line = at[doubt]
                    newer = len(held) - 1 - np.searchsorted(held, line) + miss.cumsum()[doubt]  # and the doubtful ones that are older
                    gone = newer >= size
                    left = (~gone & (newer + np.arange(len(doubt)) >= size)).nonzero()[0]
                    for at_ in range(0, len(left), 256):
                        some = left[at_ : at_ + 256]
                        older = (line < line[some, None]) & (np.arange(len(line)) < some[:, None])
                        gone[some] = newer[some] + older.sum(axis=1) >= size
                    miss[doubt[gone]] = True
            missed[lo + new[miss]] = True
            held = np.concatenate([held[after[held] >= hi], lo + (after[lo:hi] >= hi).nonzero()[0]])[-size:]
        return missed


def _links(lines: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every access the place of the access of its line before it (-1: none) and after it (their number: none)."""
    low, high = (int(lines.min()), int(lines.max())) if len(lines) else (0, 0)
    keys = (lines - low).astype(np.uint16) if high - low < 1 << 16 else lines  # sorted by their digits
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    again = (keys[1:] == keys[:-1]).nonzero()[0]
    first, second = order[again], order[again + 1]
    before, after = np.full(len(lines), -1, np.int32), np.full(len(lines), len(lines), np.int32)
    before[second], after[first] = first, second
    return before, after


def levels(sizes: tuple[int, ...]) -> list[Level]:
    """Levels of so many lines, each asked by the one above."""
    out: list[Level] = []
    for size in reversed(sizes):
        out.insert(0, Level(size, out[0] if out else None))
    return out


def simulate(lines, sizes: tuple[int, ...], ways: int | None = None) -> list[int]:
    """Misses of each level for a sequence of line numbers."""
    cache = Cache(sizes, ways)
    cache.run(lines)
    return cache.misses


def miss_rates(trace: DataFrame, by: list[str], order: list[str], sizes: tuple[int, int], line_bits: int = LINE_BITS, ways: int | None = None) -> DataFrame:
    """(by, accesses, l1_misses, last_misses, l1_rate, last_rate) of traces (by, order, rep, bit).

    A trace is one task's work, as a simulated cache has one history; choose traces of bounded length.
    """
    kinds = ", ".join(f"`{c}` {trace.schema[c].dataType.simpleString()}" for c in by)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(order, kind="stable")
        lines = ((pdf["rep"].to_numpy(np.int64) << 52) | (pdf["bit"].to_numpy(np.int64) // line_bits)).tolist()
        first, last = simulate(lines, sizes, ways)
        row = {c: [pdf[c].iloc[0]] for c in by}
        return pd.DataFrame(row | {"accesses": [len(lines)], "l1_misses": [first], "last_misses": [last]})

    got = trace.select(*dict.fromkeys([*by, *order, "rep", "bit"])).groupBy(*by).applyInPandas(run, f"{kinds}, accesses bigint, l1_misses bigint, last_misses bigint")
    return got.withColumn("l1_rate", F.col("l1_misses") / F.col("accesses")).withColumn("last_rate", F.col("last_misses") / F.col("accesses"))


def _edges(lines: np.ndarray, every: int) -> np.ndarray:
    """Which accesses (gram, function) a level of more than (every + 1) * functions lines has to see: the first and the last
    of a function's run on one line, and one in `every` grams between. The others hit; a line they keep in the level is seen
    often enough to stay there, and counts as accessed between any two accesses that are far enough apart to miss.
    """
    out = np.ones(lines.shape, bool)
    if every > 1 and len(lines) > 2:
        same = lines[1:] == lines[:-1]
        out[1:-1] = ~(same[:-1] & same[1:])
        out[::every] = True
    return out


def gram_miss_rates(seqs: DataFrame, specs, by: str, order: list[str], sizes: tuple[int, int], line_bits: int = LINE_BITS, ways: int | None = None) -> DataFrame:
    """miss_rates() of the accesses of all grams of sequences (by, order, seq), in the order of the sequences, grams and
    functions. What is shuffled and sorted are the sequences; their accesses are made and simulated slice by slice,
    so neither disk nor memory holds a trace. Needs the Arrow kernel.

    specs: one, or a dict of several that share the pass over the sequences; their names then stand in a column `spec`.
    """
    named = specs if isinstance(specs, dict) else {"": specs}

    def run(batches):
        schema = pa.schema([(by, pa.string()), ("spec", pa.string()), ("accesses", pa.int64()), ("l1_misses", pa.int64()), ("last_misses", pa.int64())])
        caches, accesses = {}, {}  # of the value of `by` at hand; a cache from its first access on
        name = None

        def rows():
            misses = []
            for key, cache in caches.items():
                if ways is None:
                    cache[0].settle()
                misses.append([level.misses for level in cache] if ways is None else cache.misses)
            return pa.RecordBatch.from_arrays([pa.array([name] * len(caches), pa.string()), pa.array(list(caches), pa.string()), pa.array(list(accesses.values()), pa.int64()), pa.array([m[0] for m in misses], pa.int64()), pa.array([m[-1] for m in misses], pa.int64())], schema=schema)

        def simulated(key, spec, lines):
            if key not in caches:
                caches[key], accesses[key] = levels(sizes) if ways is None else Cache(sizes, ways), 0
            accesses[key] += lines.size
            if ways is None:
                caches[key][0].run(lines[_edges(lines, sizes[0] // spec.eta - 2)])
            else:
                caches[key].run(lines.ravel().tolist())

        for batch in batches:
            for part in kernel._slices(batch, "seq", kernel.NEAR_SYMBOLS):
                codes, offsets = kernel.symbols(part.column("seq"))
                names, made, accessed = part.column(by).to_pylist(), {}, {}
                for key, spec in named.items():
                    at, owner = kernel.valid_places(codes, offsets, spec.k)
                    lines = np.empty((len(at), spec.eta), np.int32 if ways is None and spec.eta * (spec.range // line_bits + 1) < 1 << 31 else np.int64)
                    for j, p in enumerate(kernel.positions(codes, spec, made) if len(at) else ()):
                        first = spec.rep_of(j) * -(-spec.range // line_bits) if ways is None else spec.rep_of(j) << 52
                        lines[:, j] = first + p[at] // line_bits
                    accessed[key] = owner, lines
                edge = [i for i, (a, b) in enumerate(zip([object(), *names], names)) if a != b]
                for lo, hi in zip(edge, [*edge[1:], len(names)]):
                    if names[lo] != name:
                        if caches:
                            yield rows()
                        name, caches, accesses = names[lo], {}, {}
                    for key, (owner, lines) in accessed.items():
                        a, b = np.searchsorted(owner, (lo, hi))
                        if b > a:
                            simulated(key, named[key], lines[a:b])
        if caches:
            yield rows()

    parts = max(int(seqs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 4 * seqs.sparkSession.sparkContext.defaultParallelism)
    sorted_ = seqs.select(F.col(by).cast("string").alias(by), *order, "seq").repartition(parts, by).sortWithinPartitions(by, *order)
    got = sorted_.mapInArrow(run, f"`{by}` string, spec string, accesses bigint, l1_misses bigint, last_misses bigint")
    got = got if isinstance(specs, dict) else got.drop("spec")
    return got.withColumn("l1_rate", F.col("l1_misses") / F.col("accesses")).withColumn("last_rate", F.col("last_misses") / F.col("accesses"))
