"""Anchored hashing: a re-hashed sketch gives the place, a short uniform hash the offset inside it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import hashing, kernel, sketch
from .grams import bind


def position(x, phi, m: int, L: int, seed: int = 42, family: str = "xxhash64", align: str = "free") -> Column:
    """Position in [0, m) of any key under any sketch: equal sketches share an anchor, keys differ in the offset."""
    anchor = hashing.uniform(phi, seed + 1, m - L + 1, family)
    if align == "page":
        anchor = anchor - F.pmod(anchor, F.lit(L))
    return anchor + hashing.uniform(x, seed + 2, L, family)


def placed(key, x, lsh, m: int, L: int, seed: int = 42, family: str = "xxhash64") -> Column:
    """Position of a key whose value x any locality-sensitive family (sketch.LshFamily) sketches."""
    return position(key, lsh.phi(x, seed), m, L, seed, family)


def sketch_only(phi, m: int, seed: int = 42, family: str = "xxhash64") -> Column:
    """The pure sketch as a hash: equal sketches collide."""
    return hashing.uniform(phi, seed + 1, m, family)


def position_arrays(seq, spec) -> Column:
    """array<array<long>>: for every function the positions of all grams of a sequence."""
    gram_keys = sketch.keys(seq, spec.k, spec.packed)
    if spec.hash == "uniform":
        return bind(gram_keys, lambda g: F.array(*[F.transform(g, lambda x: hashing.uniform(x, spec.seeds(j)[2], spec.range, spec.family)) for j in range(spec.eta)]))
    values = sketch.sketch_arrays(seq, spec)
    if spec.hash == "sketch":
        return bind(values, lambda v: F.array(*[F.transform(F.get(v, j), lambda x: hashing.uniform(x, spec.seeds(j)[1], spec.range, spec.family)) for j in range(spec.eta)]))

    def one(v, g, j):
        def place(s, x):
            anchor = hashing.uniform(s, spec.seeds(j)[1], spec.anchors, spec.family)
            if spec.align == "page":
                anchor = anchor - F.pmod(anchor, F.lit(spec.L))
            return anchor + hashing.uniform(x, spec.seeds(j)[2], spec.L, spec.family)

        return F.zip_with(F.get(v, j), g, place)

    return bind(F.struct(values.alias("v"), gram_keys.alias("g")), lambda b: F.array(*[one(b["v"], b["g"], j) for j in range(spec.eta)]))


def gram_positions(reads: DataFrame, spec, by=("file_id", "seq_id", "read_no")) -> DataFrame:
    """(by, pos, rep, bit): one row a gram and function; pos is the gram's number in the read.

    Both roads leave out grams with symbols outside the alphabet.
    """
    by = list(by)
    types = ", ".join(f"`{c}` {reads.schema[c].dataType.simpleString()}" for c in by)
    if spec.kernel:
        return reads.select(*by, "seq").mapInArrow(kernel.trace_builder(spec, by), f"{types}, pos int, rep int, bit bigint")
    lists = reads.select(*by, F.explode(F.arrays_zip(F.array(*[F.lit(spec.rep_of(j)) for j in range(spec.eta)]).alias("rep"), position_arrays(F.col("seq"), spec).alias("bits"))).alias("f"))
    rows = lists.select(*by, F.col("f.rep").alias("rep"), F.posexplode("f.bits").alias("pos", "bit"))
    return rows.where("bit IS NOT NULL").select(*by, "pos", "rep", "bit")
