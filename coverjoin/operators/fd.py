"""Simple functional dependencies: closure, expansion of relations, and joins that use them."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import bounds
from ..plans.model import FD, JoinQuery, Relation
from ..storage import small
from . import anchored


def closure(fds: Sequence[FD], attrs) -> frozenset:
    """All attributes that the given ones determine, themselves included."""
    known, more = set(attrs), True
    while more:
        new = {f.v for f in fds if f.u in known} - known
        known, more = known | new, bool(new)
    return frozenset(known)


def violations(df: DataFrame, u: str, v: str) -> DataFrame:
    """Values of u with more than one v, and how many; rows with a null on either side do not count."""
    return df.filter(F.col(u).isNotNull() & F.col(v).isNotNull()).groupBy(u).agg(F.count_distinct(v).alias("n_values")).filter("n_values > 1")


def expand(q: JoinQuery, fds: Sequence[FD]) -> JoinQuery:
    """Each relation with all attributes its own ones determine. Rows whose u has no partner go: the owner of the dependency is
    in the query, so they join with nothing. Relations that come to have equal attributes are intersected."""
    by_name = {r.name: r for r in q.relations}
    q.sizes()
    by_name = {r.name: r for r in q.relations}
    maps = {}
    for f in fds:
        owner = by_name[f.relation]
        m = owner.project([f.u, f.v])
        maps[f] = small(m, owner.size)
    out: dict[frozenset, list[Relation]] = {}
    for r in q.relations:
        df, have, more = r.df, list(r.attrs), True
        while more:
            more = False
            for f in fds:
                if f.u in have and f.v not in have:
                    df, more = df.join(maps[f], f.u), True
                    have.append(f.v)
        # further dependencies into columns that were there already hold as filters by the owner's own relation
        out.setdefault(frozenset(have), []).append(Relation(r.name, df.select(*have)))
    merged = []
    for rs in out.values():
        first = rs[0]
        df = reduce(lambda d, x: d.join(x.df, list(first.attrs), "left_semi"), rs[1:], first.df)
        merged.append(Relation("&".join(x.name for x in rs), df))
    return JoinQuery(merged, q.attrs)


def join(q: JoinQuery, fds: Sequence[FD] | None = None, **how) -> DataFrame:
    """The natural join, planned on expanded relations; without dependencies the plain method."""
    return anchored.join(expand(q, fds) if fds else q, **how)


def bound(q: JoinQuery, fds: Sequence[FD] | None = None) -> int:
    """Cover bound with (or without) the dependencies."""
    p = expand(q, fds) if fds else q
    return bounds.floor_bound(p.hypergraph, p.sizes())
