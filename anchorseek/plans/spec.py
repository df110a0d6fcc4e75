"""Parameters of an index, checked once and kept beside it."""

from __future__ import annotations

import json
import warnings
from dataclasses import asdict, dataclass, replace

#: Bits of a page row; Spark's bitmap aggregates use buckets of the same size.
PAGE_BITS = 32_768
PAGE_BYTES = PAGE_BITS // 8

HASHES = ("uniform", "sketch", "anchored")
FAMILIES = ("xxhash64", "murmur3", "md5", "modprime")
BACKENDS = ("naive", "sql", "arrow", "segment_tree")


@dataclass(frozen=True)
class IndexSpec:
    """k, t: gram and subgram length; eta functions on m bits; L: range of the offset of anchored hashing.

    Grams are sketched by `minwise`; other families place their keys by `anchored.placed`. backend `naive` hashes all
    subgrams of each gram anew, `sql` slides minima in expressions, `arrow` in numpy, `segment_tree` over a tree.
    layout `partitioned` gives each function m // eta bits, `shared` gives all functions all bits. align
    `page` snaps anchors to multiples of L, so that a window of L bits never straddles two pages.
    """

    k: int = 31
    t: int = 16
    eta: int = 4
    m: int = 1 << 23
    L: int = 4096
    hash: str = "anchored"
    alphabet: str = "dna"
    family: str = "xxhash64"
    lsh: str = "minwise"
    oph: bool = True
    densify: str = "rotate"
    layout: str = "partitioned"
    align: str = "free"
    backend: str = "arrow"
    exit: str = "none"
    theta: float = 1.0
    B: int | None = None
    R: int | None = None
    seed: int = 42
    empty_query: str = "match"

    def __post_init__(self):
        if not 1 <= self.t <= self.k:
            raise ValueError("1 <= t <= k")
        if not 1 <= self.eta <= 16:
            raise ValueError("1 <= eta <= 16")
        if not 1 <= self.m <= 1 << 62:
            raise ValueError("1 <= m <= 2^62")
        if not 1 <= self.L <= self.range:
            raise ValueError("1 <= L <= bits of one function")
        for name, allowed in (("hash", HASHES), ("family", FAMILIES), ("backend", BACKENDS), ("layout", ("shared", "partitioned")), ("align", ("free", "page")), ("exit", ("none", "rounds", "kernel")), ("densify", ("rotate", "random")), ("alphabet", ("dna", "any")), ("empty_query", ("match", "null", "error")), ("lsh", ("minwise",))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {allowed}")
        if not 0 < self.theta <= 1:
            raise ValueError("0 < theta <= 1")
        if self.L > PAGE_BITS and self.hash == "anchored":
            warnings.warn("L above the page size gives up the locality of pages", stacklevel=2)
        if self.t == 1:
            warnings.warn("t = 1 leaves one sketch value a symbol: almost all grams share an anchor", stacklevel=2)

    @property
    def range(self) -> int:
        """Bits that one function addresses."""
        return self.m if self.layout == "shared" else self.m // self.eta

    @property
    def width(self) -> int:
        """Subgrams in a gram."""
        return self.k - self.t + 1

    @property
    def anchors(self) -> int:
        """Places an anchor may take, so that anchor + offset stays below the range."""
        return self.range - self.L + 1

    def seeds(self, j: int) -> tuple[int, int, int]:
        """Seeds of function j: subgrams, anchor, offset. One-permutation sketches share the first."""
        first = self.seed + 3 * j
        return (self.seed if self.oph and self.eta > 1 else first), first + 1, first + 2

    @property
    def packed(self) -> bool:
        """Whether grams are hashed as packed numbers rather than strings."""
        return self.alphabet == "dna" and self.k <= 31 and self.family != "md5"

    @property
    def kernel(self) -> bool:
        """Whether the Arrow kernel computes these positions."""
        return self.backend in ("arrow", "segment_tree") and self.alphabet == "dna" and self.k <= 31 and self.family in ("xxhash64", "modprime", "md5") and self.lsh == "minwise"

    @property
    def pages(self) -> int:
        """Pages that one filter can have at most."""
        return -(-self.range // PAGE_BITS) * (1 if self.layout == "shared" else self.eta)

    def rep_of(self, j: int) -> int:
        """Number of the bit array that function j addresses."""
        return 0 if self.layout == "shared" else j

    def with_(self, **changes) -> IndexSpec:
        return replace(self, **changes)

    def compatible(self, other: IndexSpec) -> bool:
        """Whether filters of the two hold the same positions for the same grams."""
        places = ("k", "t", "eta", "m", "L", "hash", "alphabet", "family", "lsh", "oph", "densify", "layout", "align", "seed")
        mine, theirs = self, other
        return all(getattr(mine, p) == getattr(theirs, p) for p in places if not (self.hash == other.hash == "uniform" and p in ("t", "L", "oph", "densify", "align")))

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> IndexSpec:
        return IndexSpec(**json.loads(text))
