"""Anchor trees: the recursion of the general method, and the attribute order it implies."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from .model import Hypergraph


@dataclass(frozen=True)
class AnchorNode:
    """``universe`` is solved with relations order[0] .. order[rank]; order[rank] is the anchor. ``left`` solves what is
    outside the anchor, ``right`` what is inside; both with one relation less."""

    rank: int
    universe: frozenset[str]
    left: AnchorNode | None
    right: AnchorNode | None
    leaf: bool


def build(h: Hypergraph, order: Sequence[int] | None = None) -> tuple[AnchorNode, tuple[int, ...]]:
    """Tree over all attributes, and the edge order used; the last edge of the order is the root's anchor."""
    order = tuple(range(h.m)) if order is None else tuple(order)
    if sorted(order) != list(range(h.m)):
        raise ValueError("the order must name each relation once")
    edges = [h.edges[i] for i in order]

    def node(universe: frozenset, rank: int) -> AnchorNode | None:
        if rank < 0 or not any(e & universe for e in edges[: rank + 1]):
            return None
        if all(universe <= e for e in edges[: rank + 1]):
            return AnchorNode(rank, universe, None, None, True)
        return AnchorNode(rank, universe, node(universe - edges[rank], rank - 1), node(universe & edges[rank], rank - 1), False)

    return node(frozenset(h.vertices), h.m - 1), order


def attribute_order(h: Hypergraph, tree: AnchorNode, order: Sequence[int]) -> list[str]:
    """All attributes: outside the anchor first, then inside; what an absent child owes is listed directly."""
    edges = [h.edges[i] for i in order]
    place = {v: i for i, v in enumerate(h.vertices)}
    listed = lambda s: sorted(s, key=place.__getitem__)

    def walk(t: AnchorNode) -> list[str]:
        if t.leaf:
            return listed(t.universe)
        out, inside = t.universe - edges[t.rank], t.universe & edges[t.rank]
        return (walk(t.left) if t.left else listed(out)) + (walk(t.right) if t.right else listed(inside))

    return walk(tree)


def local_order(attrs: Sequence[str], total: Sequence[str]) -> list[str]:
    return [a for a in total if a in set(attrs)]


def nodes(t: AnchorNode | None):
    if t:
        yield t
        yield from nodes(t.left)
        yield from nodes(t.right)
