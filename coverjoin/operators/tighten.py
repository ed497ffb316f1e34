"""Rewriting an instance so that every attribute is covered exactly once, by splitting slack edges into projections."""

from __future__ import annotations

from collections.abc import Sequence
from fractions import Fraction

from ..plans import lp
from ..plans.model import Hypergraph, JoinQuery, Relation


def tighten_edges(h: Hypergraph, cover: Sequence[Fraction]) -> list[tuple[int, frozenset, Fraction]]:
    """(origin edge, attributes, weight) such that all sums are exactly 1. An edge of positive weight over a slack attribute
    gives part of its weight to its projection without that attribute."""
    edges = [(i, e, Fraction(w)) for i, (e, w) in enumerate(zip(h.edges, cover))]
    for v in h.vertices:
        while (slack := sum((w for _, e, w in edges if v in e), Fraction(0)) - 1) > 0:
            k = max((i for i, (_, e, w) in enumerate(edges) if v in e and w > 0), key=lambda i: edges[i][2])
            origin, e, w = edges[k]
            part = min(w, slack)
            edges[k] = (origin, e, w - part)
            if rest := e - {v}:
                edges.append((origin, rest, part))
    return edges


def tighten(q: JoinQuery, cover: Sequence[Fraction] | None = None) -> tuple[JoinQuery, tuple[Fraction, ...]]:
    """An equal query and a tight cover of it. Relations that lost their weight stay as filters."""
    cover = lp.optimal_cover(q.hypergraph, q.sizes()) if cover is None else cover
    if not lp.is_cover(q.hypergraph, cover):
        raise ValueError("not a fractional cover")
    rels, weights = [], []
    for origin, e, w in tighten_edges(q.hypergraph, cover):
        r = q.relations[origin]
        same = e == frozenset(r.attrs)
        if not same and w == 0:
            continue
        rels.append(r if same else Relation(f"{r.name}|{'.'.join(a for a in r.attrs if a in e)}", r.project(a for a in r.attrs if a in e)))
        weights.append(w)
    return JoinQuery(rels, q.attrs), tuple(weights)
