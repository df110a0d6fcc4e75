"""Locality-sensitive sketches: min-wise values of grams by several roads, and projections of vectors.

All roads give the same values: `naive` takes the minimum of each gram's subgram hashes, `window` a sliding
window over exploded subgrams, `sql` doubles windows inside arrays, and the kernel does so in numpy.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import hashing
from .grams import bind, pack2, starts

#: Sketch values are below 2^62; an empty bin stands for more than any of them.
MASK = (1 << 62) - 1
EMPTY = (1 << 63) - 1
#: Added to a borrowed value once for each bin it was borrowed over.
BORROW = 0x0123456789ABCDF


class LshFamily(Protocol):
    """A locality-sensitive family: phi gives a long, similar inputs the same one more often."""

    def phi(self, col: Column, seed: int) -> Column: ...

    def similarity(self, x: Column, y: Column) -> Column: ...


class MinwiseSets:
    """Arrays as sets; similarity is their Jaccard index."""

    def __init__(self, family: str = "xxhash64"):
        self.family = family

    def phi(self, col, seed: int):
        return minwise(col, seed, self.family)

    def similarity(self, x, y):
        both = F.size(F.array_intersect(x, y))
        union = F.size(F.array_union(x, y))
        return F.when(union > 0, both / union).otherwise(1.0)


class SignProjections:
    """Vectors by the sides of `bits` random planes; similarity is 1 - angle / pi."""

    def __init__(self, dims: int, bits: int = 12):
        self.dims, self.bits = dims, bits

    def phi(self, col, seed: int):
        return sign_projection(col, unit_planes(self.bits, self.dims, seed))

    def similarity(self, x, y):
        product = F.aggregate(F.zip_with(x, y, lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda a, b: a + b)
        norm = lambda c: F.sqrt(F.aggregate(F.transform(c, lambda a: a.cast("double") * a.cast("double")), F.lit(0.0), lambda a, b: a + b))
        return 1 - F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), product / (norm(x) * norm(y))))) / F.pi()


class StableProjections:
    """Vectors by the cell of a random line; similarity falls with the distance in cells."""

    def __init__(self, dims: int, width: float = 0.5):
        self.dims, self.width = dims, width

    def phi(self, col, seed: int):
        return stable_projection(col, unit_planes(1, self.dims, seed)[0], (seed % 8) / 8 * self.width, self.width)

    def similarity(self, x, y):
        gap = F.aggregate(F.zip_with(x, y, lambda a, b: (a.cast("double") - b.cast("double")) * (a.cast("double") - b.cast("double"))), F.lit(0.0), lambda a, b: a + b)
        return 1 / (1 + F.sqrt(gap) / self.width)


def rehash(phi, m: int, seed: int = 0, family: str = "xxhash64"):
    """A sketch in [0, m): unequal values meet with chance 1/m."""
    return hashing.uniform(phi, seed, m, family)


def raw_hash(key, seed: int, family: str):
    """A wide non-negative hash of a subgram."""
    if family == "md5":
        return hashing.md5_value(key, seed)
    if family == "modprime":
        return hashing.modprime(key, seed, 1 << 61)
    if family == "murmur3":
        return F.hash(F.lit(seed).cast("long"), key).cast("long") + (1 << 31)
    return F.xxhash64(F.lit(seed).cast("long"), key).bitwiseAND(F.lit(MASK).cast("long"))


def keys(seq, width: int, packed: bool):
    """Hash keys of all substrings of the given length."""
    one = lambda i: F.substring(seq, i, F.lit(width))
    return F.transform(starts(F.coalesce(F.length(seq), F.lit(0)), width), lambda i: pack2(one(i)) if packed else one(i))


def minwise(arr, seed: int, family: str = "xxhash64"):
    """Min-wise hash of an array as a set."""
    return F.array_min(F.transform(arr, lambda a: raw_hash(a, seed, family)))


def minwise_perm(sets: DataFrame, perm: DataFrame, key: str, items: str) -> DataFrame:
    """Exact min-wise values: perm(item, rank) is a permutation of a small universe."""
    rows = sets.select(key, F.explode(items).alias("item")).join(F.broadcast(perm), "item")
    return rows.groupBy(key).agg(F.min("rank").alias("minwise"))


def gram_sketch(gram, t: int, seed: int, family: str = "xxhash64", packed: bool = True):
    """The sketch of one gram from scratch: all its subgrams are hashed."""
    return F.array_min(F.transform(keys(gram, t, packed), lambda s: raw_hash(s, seed, family)))


def rolling_min(arr, width: int):
    """Minimum of every `width` consecutive elements; windows double, so log2(width) passes."""

    def shifted(values, by):
        n = F.greatest(F.size(values) - by, F.lit(0))
        return F.zip_with(F.slice(values, F.lit(1), n), F.slice(values, F.lit(1 + by), n), lambda a, b: F.least(a, b))

    have = 1
    while have < width:
        step = min(have, width - have)
        arr = bind(arr, lambda v: shifted(v, step))
        have += step
    return arr


def _div(v, n: int):
    """Whole quotient of a non-negative long, exactly."""
    return F.call_function("div", v, F.lit(n).cast("long"))


def _borrowed(minima: list, eta: int, densify: str, place):
    """For each bin its value, or that of a filled bin, marked with the distance."""
    out = []
    for b in range(eta):
        order = [(b + s) % eta for s in range(eta)] if densify == "rotate" else _shuffled(b, eta)
        value = F.lit(EMPTY).cast("long")
        for s in reversed(range(eta)):
            v = place(minima[order[s]])
            value = F.when(v != EMPTY, v + F.lit(s * BORROW).cast("long")).otherwise(value)
        out.append(value)
    return out


def _shuffled(b: int, eta: int) -> list[int]:
    """A fixed order of all bins that starts with b."""
    rest = [x for x in range(eta) if x != b]
    r = np.random.default_rng(b * 31 + eta)
    r.shuffle(rest)
    return [b, *rest]


def sketch_arrays(seq, spec) -> Column:
    """array<array<long>>: for every function the sketches of all grams of a sequence."""
    if spec.backend == "naive":
        return _naive_arrays(seq, spec)
    if not (spec.oph and spec.eta > 1):
        per = []
        for j in range(spec.eta):
            h = F.transform(keys(seq, spec.t, spec.packed), lambda s: raw_hash(s, spec.seeds(j)[0], spec.family))
            per.append(rolling_min(h, spec.width))
        return F.array(*per)
    h = F.transform(keys(seq, spec.t, spec.packed), lambda s: raw_hash(s, spec.seeds(0)[0], spec.family))

    def binned(values):
        bins = [rolling_min(F.transform(values, lambda v: F.when(F.pmod(v, F.lit(spec.eta)) == b, _div(v, spec.eta)).otherwise(F.lit(EMPTY)).cast("long")), spec.width) for b in range(spec.eta)]
        return bind(F.array(*bins), fill)

    def fill(m):
        n = F.size(F.get(m, 0))
        places = F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
        at = lambda i: _borrowed(list(range(spec.eta)), spec.eta, spec.densify, lambda b: F.get(F.get(m, b), i))
        return F.array(*[F.transform(places, lambda i: at(i)[j]) for j in range(spec.eta)])

    return bind(h, binned)


def _naive_arrays(seq, spec) -> Column:
    """The same from scratch: every gram's subgrams are hashed anew."""
    grams = F.transform(starts(F.coalesce(F.length(seq), F.lit(0)), spec.k), lambda i: F.substring(seq, i, F.lit(spec.k)))
    hashes = lambda g, j: F.transform(keys(g, spec.t, spec.packed), lambda s: raw_hash(s, spec.seeds(j)[0], spec.family))
    if not (spec.oph and spec.eta > 1):
        return bind(grams, lambda gs: F.array(*[F.transform(gs, lambda g: F.array_min(hashes(g, j))) for j in range(spec.eta)]))

    def one(h):
        of = lambda b: F.coalesce(F.array_min(F.transform(F.filter(h, lambda v: F.pmod(v, F.lit(spec.eta)) == b), lambda v: _div(v, spec.eta))), F.lit(EMPTY).cast("long"))
        return bind(F.array(*[of(b) for b in range(spec.eta)]), lambda m: F.array(*_borrowed(list(range(spec.eta)), spec.eta, spec.densify, lambda b: F.get(m, b))))

    return bind(F.transform(grams, lambda g: bind(hashes(g, 0), one)), lambda per: F.array(*[F.transform(per, lambda p: F.get(p, j)) for j in range(spec.eta)]))


def windowed_sketch(reads: DataFrame, spec, by=("file_id", "seq_id", "read_no")) -> DataFrame:
    """(by, pos, sketch) of function 0 by a sliding window over exploded subgrams."""
    rows = reads.select(*by, F.posexplode(keys(F.col("seq"), spec.t, spec.packed)).alias("pos", "sub"))
    rows = rows.select(*by, "pos", raw_hash(F.col("sub"), spec.seeds(0)[0], spec.family).alias("h"))
    w = Window.partitionBy(*by).orderBy("pos").rowsBetween(0, spec.width - 1)
    full = rows.withColumn("sketch", F.min("h").over(w)).withColumn("n", F.count("h").over(w))
    return full.where(F.col("n") == spec.width).select(*by, "pos", "sketch")


def sign_projection(vector, planes: list[list[float]]):
    """Signature of a vector: one bit a plane, 1 where the product with its normal is positive."""
    bits = [F.when(_dot(vector, p) > 0, F.lit(1 << i)).otherwise(F.lit(0)) for i, p in enumerate(planes)]
    out = bits[0]
    for b in bits[1:]:
        out = out + b
    return out.cast("long")


def stable_projection(vector, line: list[float], shift: float, width: float):
    """Number of the cell of a random line that a vector falls in."""
    return F.floor((_dot(vector, line) + shift) / width).cast("long")


def _dot(vector, weights: list[float]):
    w = F.array(*[F.lit(float(x)) for x in weights])
    return F.aggregate(F.zip_with(vector, w, lambda a, b: a.cast("double") * b), F.lit(0.0), lambda a, b: a + b)


def unit_planes(count: int, dims: int, seed: int) -> list[list[float]]:
    """Normals with entries from a fixed small grid, so that sums are the same in any engine."""
    r = np.random.default_rng(seed)
    return (r.integers(-8, 9, (count, dims)) / 8.0).tolist()
