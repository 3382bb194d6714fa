"""Bounds on path weights: thresholds, worst-case bounds of a length, and the quality ratio."""

from __future__ import annotations

from functools import lru_cache, reduce

from .graph.model import SCALE

NONE_LEFT = float("-inf")
#: How two weights make one, for each aggregate; all grow with both sides, which is all that the bounds need.
COMBINED = {"sum": lambda a, b: a + b, "mean": lambda a, b: a + b, "min": min, "max": max, "product": lambda a, b: a * b / SCALE}


def repeated(weight: float, n: int, agg: str = "sum") -> float:
    """The weight of n edges of one weight."""
    return reduce(COMBINED[agg], [weight] * n)


def rank_scan_bound(last_read: float, heaviest: float, length: int, agg: str = "sum") -> float:
    """No path with an unread edge weighs more."""
    return last_read if length == 1 else COMBINED[agg](last_read, repeated(heaviest, length - 1, agg))


def first_bounds(length: int, heaviest: float, agg: str = "sum") -> dict[int, float]:
    return {i: repeated(heaviest, i, agg) for i in range(2, length + 1)}


def after_read(last_read: float, agg: str = "sum") -> float:
    """Bound on length-2 paths still to come."""
    return repeated(last_read, 2, agg)


def after_release(best_unreleased: float, bound: float, slack: float, agg: str = "sum") -> float:
    """Bound on paths one edge longer, after a release; slack: the heaviest edge they can have more."""
    return COMBINED[agg](max(best_unreleased, bound), slack)


def split_bound(best: dict[int, float], length: int, j: int, heaviest: float) -> float:
    """Worst-case bound on `length` from optimal weights below the last non-empty buffer j."""
    unit = j - 1
    if unit < 1 or unit not in best:
        return length * heaviest
    q, r = divmod(length, unit)
    return q * best[unit] + (best[r] if r else 0)


def best_split_bound(best: dict[int, float], length: int) -> float:
    """The least bound over all splits of the length into known lengths."""

    @lru_cache(None)
    def least(n: int) -> float:
        return 0 if n == 0 else min(best[i] + least(n - i) for i in best if i <= n)

    return least(length)


def rho(found: float | None, bound: float) -> float | None:
    """Found weight over its bound: never above the ratio to the optimum."""
    return None if found is None or not bound else found / bound
