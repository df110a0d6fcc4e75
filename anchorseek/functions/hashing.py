"""Seeded hashes into a range, as Column expressions, and their numpy twin for packed grams."""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import functions as F

#: Fixed value: the prime of the modprime family, 2^31 - 1, so that products of 31-bit limbs stay below 2^62.
PRIME = (1 << 31) - 1


def uniform(key, seed: int, m: int, family: str = "xxhash64"):
    """A seeded pseudo-random value in [0, m). md5 and modprime are the same in any SQL engine.

    key is a string or a long column; modprime takes longs below 2^62.
    """
    if family == "xxhash64":
        return F.pmod(F.xxhash64(F.lit(seed).cast("long"), key), F.lit(m).cast("long"))
    if family == "murmur3":
        return F.pmod(F.hash(F.lit(seed).cast("long"), key).cast("long"), F.lit(m).cast("long"))
    if family == "md5":
        return md5_value(key, seed) % F.lit(m).cast("long")
    if family == "modprime":
        return modprime(key, seed, m)
    raise ValueError(f"no expression for the family {family}")


def md5_value(key, seed: int):
    """The first 15 hex digits of md5('<seed>:<key>') as a number."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string")).cast("binary")), 1, 15), 16, 10).cast("long")


def modprime_draw(seed: int) -> tuple[int, int, int]:
    """Coefficients of one function of the 2-universal family."""
    r = random.Random(seed)
    return r.randrange(1, PRIME), r.randrange(PRIME), r.randrange(PRIME)


def modprime(key, seed: int, m: int):
    """((a1 * low + (a2 * high mod p) + b) mod p) mod m over 31-bit limbs; a second draw fills ranges above p."""

    def one(s):
        a1, a2, b = (F.lit(v).cast("long") for v in modprime_draw(s))
        low, high = key.bitwiseAND(F.lit(PRIME).cast("long")), F.shiftright(key, 31)
        return F.pmod(F.pmod(a1 * low, F.lit(PRIME).cast("long")) + F.pmod(a2 * high, F.lit(PRIME).cast("long")) + b, F.lit(PRIME).cast("long"))

    if m <= PRIME:
        return F.pmod(one(seed), F.lit(m).cast("long"))
    return F.pmod(one(seed) * F.lit(1 << 31).cast("long") + one(seed + 7919), F.lit(m).cast("long"))


def modprime_longs(values: np.ndarray, seed: int, m: int) -> np.ndarray:
    """modprime for an array of longs."""

    def one(s):
        a1, a2, b = modprime_draw(s)
        return ((a1 * (values & PRIME)) % PRIME + (a2 * (values >> 31)) % PRIME + b) % PRIME

    return one(seed) % m if m <= PRIME else ((one(seed) << 31) + one(seed + 7919)) % m


def tabulated(spark, universe, m: int, seed: int):
    """(key, h): a purely random function on a small universe, as a table to join with."""
    r = random.Random(seed)
    return spark.createDataFrame([(u, r.randrange(m)) for u in universe], "key string, h long")


_P1, _P2, _P3, _P4, _P5 = (np.uint64(v) for v in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def xx64_long(values: np.ndarray, seed) -> np.ndarray:
    """The 64-bit xx hash of 8-byte values with a seed, as Spark's xxhash64 chains it. Two arrays are made, whatever the steps."""
    with np.errstate(over="ignore"):
        h = values.astype(np.uint64, copy=False) * _P2
        high = h >> np.uint64(33)
        h <<= np.uint64(31)
        h |= high
        h *= _P1
        h ^= np.uint64(seed) + _P5 + np.uint64(8)
        np.right_shift(h, np.uint64(37), out=high)
        h <<= np.uint64(27)
        h |= high
        h *= _P1
        h += _P4
        for shift, prime in ((33, _P2), (29, _P3), (32, None)):
            np.right_shift(h, np.uint64(shift), out=high)
            h ^= high
            if prime is not None:
                h *= prime
        return h


def xx64_seeded(values: np.ndarray, seed: int) -> np.ndarray:
    """Signed 64-bit values of xxhash64(long seed, long value)."""
    first = xx64_long(np.array([seed], np.int64).view(np.uint64), np.uint64(42))[0]
    return xx64_long(values.view(np.uint64), first).view(np.int64)


def in_range(h: np.ndarray, m: int) -> np.ndarray:
    """pmod of signed hashes."""
    return h & np.int64(m - 1) if m & (m - 1) == 0 else np.mod(h, np.int64(m))
