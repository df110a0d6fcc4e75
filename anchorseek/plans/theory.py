"""Closed forms: false-positive rates, bounds, costs."""

from __future__ import annotations

import math


def fpr_uniform(m: float, n: float, eta: int, exact: bool = False) -> float:
    """Chance that an absent gram passes a filter with a uniform hash."""
    empty = (1 - 1 / m) ** (eta * n) if exact else math.exp(-eta * n / m)
    return (1 - empty) ** eta


def best_eta(m: float, n: float) -> float:
    return math.log(2) * m / n


def bits_for(n: float, eps: float) -> float:
    """Range for a rate eps at the best number of functions."""
    return -n * math.log(eps) / math.log(2) ** 2


def fpr_anchored_bound(m: float, n: float, eta: int, L: float, w1: float, w2: float, exact: bool = False) -> float:
    """Upper bound of the rate with anchored hashing under the two assumptions, at most 1; loose."""
    if w1 * eta >= m:
        return 1.0
    tail = (1 - w1 * eta / m) ** (n / (2 * w1)) if exact else math.exp(-eta * n / (2 * m))
    return min(1.0, (w2 * (1 / L + eta / m) + 2 * (1 - tail)) ** eta)


def fpr_anchored_limit(eta: int, L: float, w2: float) -> float:
    """What the bound tends to as the range grows."""
    return min(1.0, (w2 / L) ** eta)


def rehash_collision(similarity: float, m: float) -> float:
    return similarity + (1 - similarity) / m


def family_bounds(p1: float, p2: float, m: float, L: float) -> dict[str, float]:
    """Near and far chances of the anchored family; `far` as printed, `far_true` with all offsets counted."""
    return {"near": p1 * (L - 1) / L, "far": p2 + L / m, "far_true": p2 + (2 * L - 1) / (m - L + 1)}


def similar_bound(k: int, t: int) -> int:
    """Grams that can share a subgram with one, if each subgram stands at one place."""
    return (k - t + 1) ** 2


def neighbour_jaccard(k: int, t: int) -> float:
    """Similarity of neighbours if all subgrams are distinct."""
    w = k - t + 1
    return (w - 1) / (w + 1)


def empty_bin_chance(eta: int, width: int) -> float:
    return (1 - 1 / eta) ** width


def hash_ops(k: int, t: int, eta: int) -> dict[str, dict[str, float]]:
    """Hashes and comparisons a gram by each road."""
    w = k - t + 1
    tree = math.ceil(math.log2(w)) if w > 1 else 0
    return {
        "uniform": {"hashes": eta, "compares": 0},
        "naive": {"hashes": eta * (w + 1), "compares": eta * (w - 1)},
        "rolling": {"hashes": 2 * eta, "compares": eta * tree},
        "one_permutation": {"hashes": eta + 1, "compares": eta * tree},
    }
