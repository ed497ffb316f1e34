"""Full conjunctive queries brought to natural joins: constants and repeated variables become filters of the scan."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import Const, JoinQuery, Relation, Rule
from ..plans.parse import parse_rule


def reduce_rule(rule: Rule | str, tables: Mapping[str, DataFrame]) -> JoinQuery:
    """One relation per atom over its variables; a table may occur more than once. An atom with constants only becomes no relation
    where it holds, and makes the query empty where it does not."""
    rule = parse_rule(rule) if isinstance(rule, str) else rule
    rels, holds = [], []
    for k, atom in enumerate(rule.body):
        df = tables[atom.table]
        if len(atom.terms) != len(df.columns):
            raise ValueError(f"{atom.table} has {len(df.columns)} columns, not {len(atom.terms)}")
        first: dict[str, str] = {}
        for c, t in zip(df.columns, atom.terms):
            if isinstance(t, Const):
                df = df.filter(F.col(c) == F.lit(t.value))
            elif t in first:
                df = df.filter(F.col(c) == F.col(first[t]))
            else:
                first[t] = c
        if first:
            rels.append(Relation(f"{atom.table}#{k}", df.select(*(F.col(c).alias(v) for v, c in first.items())).distinct()))
        else:
            holds.append(df)
    q = JoinQuery(rels)
    if any(d.isEmpty() for d in holds):
        q = JoinQuery([Relation(r.name, r.df.limit(0)) for r in rels])
    return q


def answer(rule: Rule | str, tables: Mapping[str, DataFrame], strategy: str = "auto") -> DataFrame:
    from . import planner

    rule = parse_rule(rule) if isinstance(rule, str) else rule
    q = reduce_rule(rule, tables)
    out = planner.join(q, strategy)
    return out.select(*rule.head) if set(rule.head) == set(q.attrs) else out.select(*rule.head).distinct()
