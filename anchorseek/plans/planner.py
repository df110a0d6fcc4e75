"""Choice of parameters."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import grams
from . import theory
from .spec import PAGE_BITS, IndexSpec


def count_grams(reads: DataFrame, k: int, error: float = 0.02) -> int:
    """Distinct grams, approximately."""
    return reads.select(F.explode(grams.gram_array(F.col("seq"), k)).alias("g")).agg(F.approx_count_distinct("g", error)).first()[0]


def choose(n: int, eps: float = 1e-3, page_bits: int = PAGE_BITS, **changes) -> IndexSpec:
    """Parameters for n grams and a rate a gram: the range by the closed form, L inside a page, eta near its best."""
    m = max(page_bits, math.ceil(theory.bits_for(max(1, n), eps)))
    eta = min(16, max(1, round(theory.best_eta(m, max(1, n)))))
    spec = IndexSpec(m=m, eta=eta, L=min(4096, page_bits, m // eta))
    return spec.with_(**changes) if changes else spec


def tune_eta(m: int, n: int, L: int, k: int = 31, t: int = 16, hash: str = "anchored", neighbours: int | None = None) -> list[dict]:
    """Rates by the number of functions, best first: the closed form for uniform hashing, else the bound."""
    best = round(theory.best_eta(m, n))
    span = range(1, 17) if neighbours is None else range(max(1, best - neighbours), min(16, best + neighbours) + 1)
    rate = (lambda e: theory.fpr_uniform(m, n, e)) if hash == "uniform" else (lambda e: theory.fpr_anchored_bound(m, n, e, L, k, theory.similar_bound(k, t)))
    return sorted(({"eta": e, "rate": rate(e)} for e in span), key=lambda r: (r["rate"], r["eta"]))
