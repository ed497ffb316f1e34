from __future__ import annotations

import itertools
import random

from coverjoin.plans.model import JoinQuery, Relation


def rel(spark, name, attrs, rows) -> Relation:
    return Relation(name, spark.createDataFrame(sorted(rows), ", ".join(f"{a} long" for a in attrs)))


def random_rows(rng: random.Random, k: int, share: float, domain: int = 3):
    return {t for t in itertools.product(range(domain), repeat=k) if rng.random() < share} or {(0,) * k}


def brute(rels, attrs, domain: int = 3) -> set:
    """By the definition: all assignments that every relation agrees with."""
    out = set()
    for t in itertools.product(range(domain), repeat=len(attrs)):
        d = dict(zip(attrs, t))
        if all(tuple(d[a] for a in e) in rows for e, rows in rels):
            out.add(t)
    return out


def query(spark, rels, attrs) -> JoinQuery:
    return JoinQuery([rel(spark, f"R{i}", e, rows) for i, (e, rows) in enumerate(rels)], attrs)


def same(df, expected: set) -> None:
    got = [tuple(r) for r in df.collect()]
    assert len(got) == len(set(got)), "a row comes twice"
    assert set(got) == expected
