"""Graph queries: cycles of any length, and covers that fall into stars and odd cycles."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass
from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import lp
from ..plans.model import Hypergraph, JoinQuery, Relation
from ..storage import PRODUCT_ROWS, product, settle
from . import keys
from .allbutone import semi, triangle


def _cross(rels: Sequence[Relation]) -> DataFrame:
    out, rows = None, 1
    for r in sorted(rels, key=lambda r: -r.size):
        out = r.df if out is None else product(out, r.df, rows, r.size)
        rows *= r.size
    return out


def _linked(parts: Sequence[Relation], links: Sequence[Relation]) -> DataFrame:
    """The product of ``parts`` filtered by ``links`` between their ends, without making the product: parts are attached one after the other
    through the link that touches them."""
    out, parts, links = parts[0].df, list(parts[1:]), list(links)
    while parts:
        have = set(out.columns)
        step = next(((p, s) for p in parts for s in links if set(s.attrs) & have and set(s.attrs) & set(p.attrs)), None)
        if step is None:
            out = product(settle(out), parts.pop(0).df)
            continue
        p, s = step
        parts.remove(p)
        links.remove(s)
        out = out.join(s.df, [a for a in s.attrs if a in have])
        out = out.join(p.df, [a for a in p.attrs if a in out.columns])
        for x in [x for x in links if set(x.attrs) <= set(out.columns)]:
            out = semi(out, x)
            links.remove(x)
    return reduce(semi, links, out)


def _ring(q: JoinQuery) -> tuple[list[Relation], list[str]]:
    found = q.hypergraph.cycle()
    if found is None:
        raise ValueError("not a cycle")
    q.sizes()
    edges, vertices = found
    return [q.relations[i] for i in edges], vertices


def _by_keys(q: JoinQuery, spend: bool = False) -> DataFrame | None:
    """The join, if some relation joins others by a key, else None."""
    core, late = keys.reduced(q)
    if len(core.relations) == len(q.relations):
        return None
    if spend:
        keys.spent(q, core, late)
    return keys.finish(q, core, late, keys.answer)


def even_cycle(q: JoinQuery, form: str = "linked", spend: bool = False) -> DataFrame:
    """The alternating half with the smaller product has all attributes already; the other half filters it.

    form "product" makes that product (at most the root of the product of all sizes); "linked", the default, reaches the same rows by
    joins through the filtering edges. Edges with a key at one end are joined to their neighbours before. spend: q is not read again,
    and what it has settled is deleted once that is done.
    """
    ring, _ = _ring(q)
    if len(ring) % 2:
        raise ValueError("an odd cycle")
    if 0 in q.sizes():
        return q.empty()
    if form == "linked" and (known := _by_keys(q, spend)) is not None:
        return known
    halves = sorted((ring[0::2], ring[1::2]), key=lambda h: math.prod(r.size for r in h))
    if form == "product":
        if math.prod(r.size for r in halves[0]) > PRODUCT_ROWS:
            raise ValueError("the product is too large to make: use form='linked'")
        return reduce(semi, halves[1], _cross(halves[0])).select(*q.attrs)
    return _linked(halves[0], halves[1]).select(*q.attrs)


@dataclass
class OddPlan:
    """What was chosen: whether the cycle was reversed, the size of the inner path, and the closing side."""

    reversed: bool = False
    inner: int = 0
    closing: str = ""


def distinct_values(ring: Sequence[Relation]) -> list[dict[str, int]]:
    """Approximate numbers of distinct values of each relation's attributes, by one job."""
    counts = [r.df.agg(F.lit(i).alias("i"), F.array(*(F.approx_count_distinct(a) for a in r.attrs)).alias("n")) for i, r in enumerate(ring)]
    return [dict(zip(ring[row["i"]].attrs, row["n"])) for row in sorted(reduce(DataFrame.unionByName, counts).collect(), key=lambda row: row["i"])]


def _path_rows(ring: Sequence[Relation], distinct: Sequence[dict[str, int]], path: Sequence[int]) -> float:
    """Estimated rows of the joins along a path of edges, all prefixes together."""
    rows = total = float(ring[path[0]].size)
    for a, b in zip(path, path[1:]):
        v = next(iter(set(ring[a].attrs) & set(ring[b].attrs)))
        rows *= ring[b].size / max(1, distinct[a][v], distinct[b][v])
        total += rows
    return total


def odd_cycle(q: JoinQuery, form: str = "linked", plan: OddPlan | None = None, spend: bool = False) -> DataFrame:
    """Odd cycles: of length 3 by heavy and light keys; longer ones are bundled into a triangle.

    The closing edge is set aside. X, the smaller alternating half of the other edges, spans all vertices but the last; W is X
    without its two ends, filtered by the inner edges. W times one of the two last edges gives the second side, whichever keeps it
    within the bound; the third side is the other of them. The bundle of inner vertices is one join key. spend: as in even_cycle().
    """
    ring, vs = _ring(q)
    n = len(ring)
    if n % 2 == 0:
        raise ValueError("an even cycle")
    if 0 in q.sizes():
        return q.empty()
    if n == 3:
        return triangle(q)
    if form == "linked" and plan is None and (known := _by_keys(q, spend)) is not None:
        return known
    plan = plan or OddPlan()
    # edges 1 .. n-1 along the path, the n-th closes; the half 1, 3, .., n-2 spans vertices 1 .. n-1. The smaller half of any closing
    # edge keeps to the bound. As a product the smallest is taken; linked, the one whose path has the fewest rows by estimate
    part = lambda k, first: math.prod(ring[(k + 1 + i) % n].size for i in range(first, n - 1, 2))
    least = lambda k: (min(part(k, 0), part(k, 1)), (k + 1) % n)
    if form == "product":
        k = min(range(n), key=least)
    else:
        distinct = distinct_values(ring)
        turned = lambda k: part(k, 0) > part(k, 1)
        path = lambda k: [(k - 1 - i if turned(k) else k + 1 + i) % n for i in range(n - 2)]
        k = min(range(n), key=lambda k: (_path_rows(ring, distinct, path(k)), *least(k)))
    ring, vs = ring[k + 1 :] + ring[: k + 1], vs[k + 1 :] + vs[: k + 1]
    if math.prod(r.size for r in ring[0 : n - 1 : 2]) > math.prod(r.size for r in ring[1 : n - 1 : 2]):
        # backwards with the same closing edge the halves change places
        ring, vs, plan.reversed = [*ring[n - 2 :: -1], ring[n - 1]], [vs[0], *vs[:0:-1]], True
    half, inner = ring[0 : n - 2 : 2], ring[1 : n - 3 : 2]
    if form == "product" and math.prod(r.size for r in half) <= PRODUCT_ROWS:
        x = reduce(semi, inner, _cross(half))
    else:
        x = _linked(half, inner)
    x = settle(x, "half")
    ends = [v for v in x.columns if sum(v in r.attrs for r in ring[: n - 2]) == 1]
    first = next(v for v in ends if v in ring[n - 1].attrs)
    last = next(v for v in ends if v in ring[n - 2].attrs)
    middle = [v for v in x.columns if v not in (first, last)]
    apex = next(v for v in ring[n - 1].attrs if v != first)
    w = settle(x.select(*middle).distinct(), "inner")
    plan.inner = w.count()
    limit = math.isqrt(math.prod(r.size for r in ring))
    if plan.inner * ring[n - 2].size <= limit:
        plan.closing, near, far, end, other = "n-1", ring[n - 2], ring[n - 1], last, first
    else:
        plan.closing, near, far, end, other = "n", ring[n - 1], ring[n - 2], first, last
    # bundle: the inner vertices with the end that the second side has
    bundle = [*middle, end]
    key = F.struct(*bundle).alias("_bundle")
    pairs = x.select(*bundle).distinct()  # W meets the edge only where X has the end, too
    side = pairs.join(near.df, end)
    tri = JoinQuery([Relation("X", x.select(other, key).distinct()), Relation("Y", side.select(key, apex).distinct()), Relation("Z", far.df.select(other, apex))])
    return triangle(tri, split="_bundle").select(other, apex, *(F.col(f"_bundle.{b}").alias(b) for b in bundle)).select(*q.attrs)


def cycle(q: JoinQuery, form: str = "linked", spend: bool = False) -> DataFrame:
    return (odd_cycle if len(q.relations) % 2 else even_cycle)(q, form, spend=spend)


# -- half-integral covers


@dataclass(frozen=True)
class Decomposition:
    stars: tuple[tuple[int, ...], ...]  # edges of weight 1, grouped by their common vertex
    cycles: tuple[tuple[int, ...], ...]  # edges of weight 1/2: disjoint odd cycles
    filters: tuple[int, ...]  # edges of weight 0


def decompose(h: Hypergraph, x: Sequence[Fraction]) -> Decomposition:
    """Edges of a basic optimal cover of a graph, by weight. Raises where weights are not 0, 1/2 or 1."""
    if not h.is_graph():
        raise ValueError("not a graph query")
    half = Fraction(1, 2)
    if any(w not in (0, half, 1) for w in x):
        raise ValueError("the cover is not half-integral")

    def groups(edges: list[int]) -> list[tuple[int, ...]]:
        out: list[set[int]] = []
        for e in edges:
            touching = [g for g in out if any(h.edges[e] & h.edges[i] for i in g)]
            out = [g for g in out if g not in touching] + [set().union({e}, *touching)]
        return sorted(tuple(sorted(g)) for g in out)

    cycles = groups([i for i, w in enumerate(x) if w == half])
    for c in cycles:
        sub = Hypergraph(tuple(dict.fromkeys(v for i in c for v in sorted(h.edges[i]))), tuple(h.edges[i] for i in c))
        if sub.cycle() is None or len(c) % 2 == 0:
            raise ValueError("edges of weight 1/2 do not form odd cycles: the cover is not basic")
    return Decomposition(tuple(groups([i for i, w in enumerate(x) if w == 1])), tuple(cycles), tuple(i for i, w in enumerate(x) if w == 0))


def graph_join(q: JoinQuery, form: str = "linked", spend: bool = False) -> DataFrame:
    """Query whose relations have at most two attributes: odd cycles and stars of the cheapest basic cover, put together; the
    edges without weight filter as soon as both their ends are there. Unary relations filter first. Linked, edges with a key at
    one end are joined to their neighbours before. spend: as in even_cycle()."""
    if not q.hypergraph.is_graph():
        raise ValueError("a relation has more than two attributes")
    if 0 in q.sizes():
        return q.empty()
    if form == "linked" and any(len(r.attrs) == 2 for r in q.relations) and (known := _by_keys(q, spend)) is not None:
        return known
    ones = [r for r in q.relations if len(r.attrs) == 1]
    wide = [r for r in q.relations if len(r.attrs) == 2]
    rels = [Relation(r.name, reduce(semi, [o for o in ones if o.attrs[0] in r.attrs], r.df)) for r in wide]
    alone = [o for o in ones if not any(o.attrs[0] in r.attrs for r in wide)]
    rels += [Relation(a, reduce(DataFrame.intersect, [o.df for o in alone if o.attrs[0] == a])) for a in dict.fromkeys(o.attrs[0] for o in alone)]
    sub = JoinQuery(rels, [a for a in q.attrs if any(a in r.attrs for r in rels)])
    sizes = sub.sizes()
    if 0 in sizes:
        return q.empty()
    plan = decompose(sub.hypergraph, lp.optimal_cover(sub.hypergraph, sizes))
    parts = [cycle(sub.pick(c), form) for c in plan.cycles]
    parts += [reduce(lambda d, i: d.join(sub.relations[i].df, [a for a in sub.relations[i].attrs if a in d.columns]), s[1:], sub.relations[s[0]].df) for s in plan.stars]
    filters = [sub.relations[i] for i in plan.filters]
    out, parts = parts[0], parts[1:]
    while True:
        ready = [f for f in filters if set(f.attrs) <= set(out.columns)]
        out = reduce(semi, ready, out)
        filters = [f for f in filters if f not in ready]
        if not parts:
            return out.select(*q.attrs)
        # a part that a filter links to what is there is joined through it, others multiply
        link = next(((p, f) for p in parts for f in filters if set(f.attrs) & set(out.columns) and set(f.attrs) & set(p.columns)), None)
        if link:
            p, f = link
            filters.remove(f)
            out = out.join(f.df, [a for a in f.attrs if a in out.columns]).join(p, [a for a in f.attrs if a in p.columns])
        else:
            p = parts[0]
            out = product(settle(out), settle(p))
        parts = [x for x in parts if x is not p]
