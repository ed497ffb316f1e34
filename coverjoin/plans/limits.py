"""Where every join tree loses: a witness that a query has instances with a quadratic gap."""

from __future__ import annotations

from itertools import combinations

from .model import Hypergraph


def relevant(h: Hypergraph, u: frozenset, v: str) -> bool:
    """Every edge with v meets u."""
    return v not in u and all(e & u for e in h.edges if v in e)


def troublesome(h: Hypergraph, u: frozenset, v: str) -> bool:
    """Every edge with v contains u."""
    return v not in u and all(u <= e for e in h.edges if v in e)


def gap_witness(h: Hypergraph, least: int = 3) -> tuple[frozenset, tuple[int, ...]] | None:
    """(U, F): attributes and as many edges, such that each attribute of U is in all but one of F, relevant ones are in at least
    that many, and none is troublesome; the largest U first, of ``least`` attributes at least (two meet the conditions on
    paths, too, where the gap is nothing). None where there is none. Query-sized search."""
    for k in range(h.n, least - 1, -1):
        for u in map(frozenset, combinations(h.vertices, k)):
            if any(troublesome(h, u, v) for v in h.vertices):
                continue
            need = [v for v in h.vertices if relevant(h, u, v)]
            for f in combinations(range(h.m), k):
                deg = lambda v: sum(v in h.edges[i] for i in f)  # noqa: B023, E731
                if all(deg(v) == k - 1 for v in u) and all(deg(v) >= k - 1 for v in need):
                    return u, f
    return None
