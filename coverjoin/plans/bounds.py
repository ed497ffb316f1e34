"""Bounds on the output size of a join."""

from __future__ import annotations

import math
from collections.abc import Sequence
from fractions import Fraction
from itertools import combinations

from .lp import cost, is_cover, optimal_cover
from .model import Hypergraph


def log_bound(h: Hypergraph, sizes: Sequence[int], x: Sequence | None = None) -> float:
    x = optimal_cover(h, sizes) if x is None else x
    if not is_cover(h, x):
        raise ValueError("not a cover")
    return float("-inf") if 0 in sizes else cost(x, sizes)


def cover_bound(h: Hypergraph, sizes: Sequence[int], x: Sequence | None = None) -> float:
    """Product of size ** weight over the relations, for the cheapest cover or a given one. 0 with an empty relation."""
    return math.exp(log_bound(h, sizes, x)) if 0 not in sizes else 0.0


def floor_bound(h: Hypergraph, sizes: Sequence[int], x: Sequence | None = None) -> int:
    """The bound rounded down, exactly: by integer roots, as weights are fractions."""
    if 0 in sizes:
        return 0
    x = optimal_cover(h, sizes) if x is None else x
    q = math.lcm(*(Fraction(w).denominator for w in x))
    power = math.prod(s ** int(Fraction(w) * q) for s, w in zip(sizes, x))
    return integer_root(power, q)


def integer_root(value: int, k: int) -> int:
    """Largest r with r ** k <= value."""
    if value < 2 or k == 1:
        return value
    lo, hi = 1, 1 << (value.bit_length() // k + 1)
    while lo < hi:
        mid = (lo + hi + 1) // 2
        lo, hi = (mid, hi) if mid**k <= value else (lo, mid - 1)
    return lo


def product_bound(sizes: Sequence[int]) -> int:
    return math.prod(sizes)


def integral_cover_bound(h: Hypergraph, sizes: Sequence[int]) -> int:
    """Least product of sizes over the sets of relations that have all attributes."""
    best = None
    for k in range(1, h.m + 1):
        for s in combinations(range(h.m), k):
            if set().union(*(h.edges[i] for i in s)) == set(h.vertices):
                p = math.prod(sizes[i] for i in s)
                best = p if best is None else min(best, p)
    return best
