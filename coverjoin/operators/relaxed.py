"""Relaxed joins: rows over all attributes that agree with all but r of the relations."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import anchor as trees
from ..plans import bounds, lp
from ..plans.model import Hypergraph, JoinQuery
from ..storage import settle
from . import anchored, cycles, grid, kernel

MOST_SETS = 100_000


def covering_sets(h: Hypergraph, r: int) -> list[frozenset[int]]:
    """Sets of at least m - r relations that have all attributes."""
    out = []
    for k in range(max(1, h.m - r), h.m + 1):
        for s in combinations(range(h.m), k):
            if set().union(*(h.edges[i] for i in s)) == set(h.vertices):
                out.append(frozenset(s))
                if len(out) > MOST_SETS:
                    raise ValueError("too many covering sets of relations: lower r")
    return out


def minimal_sets(h: Hypergraph, r: int) -> list[frozenset[int]]:
    """Those that contain no other: the join over a set lies in the join over each of its subsets."""
    out: list[frozenset[int]] = []
    for s in sorted(covering_sets(h, r), key=len):
        if not any(t <= s for t in out):
            out.append(s)
    return out


def support_classes(h: Hypergraph, sizes: Sequence[int], r: int) -> dict[frozenset[int], frozenset[int]]:
    """Relations with weight in the cheapest basic cover -> one minimal set with that support."""
    out: dict[frozenset[int], frozenset[int]] = {}
    for s in minimal_sets(h, r):
        ids = sorted(s)
        x = lp.optimal_cover(Hypergraph(h.vertices, tuple(h.edges[i] for i in ids)), [sizes[i] for i in ids])
        out.setdefault(frozenset(i for i, w in zip(ids, x) if w > 0), s)
    return out


def _bound(h: Hypergraph, sizes, s) -> int:
    ids = sorted(s)
    return bounds.floor_bound(Hypergraph(h.vertices, tuple(h.edges[i] for i in ids)), [sizes[i] for i in ids])


def sum_bound(h: Hypergraph, sizes: Sequence[int], r: int) -> int:
    return sum(_bound(h, sizes, s) for s in minimal_sets(h, r))


def class_bound(h: Hypergraph, sizes: Sequence[int], r: int) -> int:
    return sum(_bound(h, sizes, s) for s in support_classes(h, sizes, r).values())


def family_sizes(h: Hypergraph, sizes: Sequence[int], r: int) -> dict[str, int]:
    return {"covering": len(covering_sets(h, r)), "minimal": len(minimal_sets(h, r)), "classes": len(support_classes(h, sizes, r))}


def naive(q: JoinQuery, r: int) -> DataFrame:
    """By the definition: the union over all covering sets of at least m - r relations."""
    sets = covering_sets(q.hypergraph, r)
    if not sets:
        return q.empty()
    q.sizes()
    return reduce(DataFrame.unionByName, [anchored.join(q.pick(sorted(s), q.attrs)) for s in sets]).distinct()


def _candidates(q: JoinQuery, sets: Sequence[frozenset[int]]) -> float:
    """Estimated rows of the joins over the sets, all together: sizes, over the distinct values of each shared attribute but for the
    relation that has the fewest. One job of sketches."""
    distinct, total = cycles.distinct_values(q.relations), 0.0
    for s in sets:
        rows = float(math.prod(q.relations[i].size for i in s))
        for a in q.attrs:
            rows /= math.prod(max(1, n) for n in sorted(distinct[i][a] for i in s if a in distinct[i])[1:])
        total += rows
    return total


def _on_grid(q: JoinQuery, r: int, sets: Sequence[frozenset[int]], share: dict[str, int]) -> DataFrame:
    """Each cell of a grid makes its part of the joins over the sets. It has every relation's rows that a combination of values can
    agree with, so it tells there how many agree, and whether an earlier set gave the row already: candidates are never shuffled."""
    h, sizes, least = q.hypergraph, q.sizes(), q.hypergraph.m - r
    plans = []
    for s in sets:
        ids = sorted(s)
        sub = Hypergraph(h.vertices, tuple(h.edges[i] for i in ids))
        tree, order = trees.build(sub)
        cover = lp.optimal_cover(sub, [sizes[i] for i in ids])
        plans.append((s, tree, [ids[k] for k in order], tuple(cover[k] for k in order)))

    def solve(rels: list[kernel.Sections]) -> Iterator[kernel.Bindings]:
        for k, (s, tree, order, y) in enumerate(plans):
            yield from (kernel.agreeing(rows, rels, s, [p[0] for p in plans[:k]], least) for rows in kernel.blocks(kernel.solve(tree, y, [rels[i] for i in order])))

    return grid.by_cell(q, share, solve)


def join(q: JoinQuery, r: int, share: bool = True) -> DataFrame:
    """One join per support class (share=False: per minimal set), repeated rows dropped, and those kept that agree with at least
    m - r relations. Relations that every class has agree by construction and are not tested. Where the joins make more rows by estimate
    than the relations' rows that a grid moves, the grid does it."""
    h, sizes = q.hypergraph, q.sizes()
    sets = list(support_classes(h, sizes, r)) if share else minimal_sets(h, r)
    if not sets:
        return q.empty()
    if share and len(sets) > 1 and grid.simple(q):
        cells = grid.shares(q, grid.CELLS, grid.ROWS)
        sent = grid.replication(q, cells)
        if sum(_bound(h, sizes, s) for s in sets) > sent and _candidates(q, sets) > sent:
            return _on_grid(q, r, sets, cells)
    rows = reduce(DataFrame.unionByName, [anchored.join(q.pick(sorted(s), q.attrs)) for s in sets])
    rows = settle(rows.distinct(), "candidates") if len(sets) > 1 else rows
    always = frozenset.intersection(*sets)
    for i, rel in enumerate(q.relations):
        if i not in always:
            rows = rows.join(rel.df.withColumn(f"_in{i}", F.lit(1)), list(rel.attrs), "left")
    agree = sum((F.coalesce(F.col(f"_in{i}"), F.lit(0)) for i in range(h.m) if i not in always), F.lit(len(always)))
    return rows.filter(agree >= h.m - r).select(*q.attrs)
