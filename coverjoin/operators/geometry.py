"""Point sets and their projections: two inequalities, and points rebuilt from projections."""

from __future__ import annotations

import math
from collections.abc import Sequence
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import lp
from ..plans.model import Hypergraph, JoinQuery, Relation
from . import anchored


def _counts(points: DataFrame, families: Sequence[Sequence[str]]) -> DataFrame:
    """One pass: the number of points and of each projection's points."""
    return points.distinct().agg(F.count("*").alias("points"), *(F.count_distinct(F.struct(*f)).alias(f"p{i + 1}") for i, f in enumerate(families)))


def regular_projection_check(points: DataFrame, family: Sequence[Sequence[str]]) -> DataFrame:
    """points, p1 .. pk (projections' sizes), d, holds: points ** d <= product of the sizes, where every coordinate is in exactly
    d projections."""
    h = Hypergraph(tuple(dict.fromkeys(a for f in family for a in f)), tuple(map(frozenset, family)))
    d = int(1 / lp.regular_cover(h)[0])
    out = _counts(points.select(*h.vertices), family)
    right = sum((F.ln(f"p{i + 1}") for i in range(len(family))), F.lit(0.0))
    return out.withColumn("d", F.lit(d)).withColumn("holds", (F.col("points") == 0) | (F.ln(F.col("points")) * d <= right + 1e-9))


def hyperplane_check(points: DataFrame, cols: Sequence[str]) -> DataFrame:
    """The case of all projections that omit one coordinate: d = n - 1."""
    return regular_projection_check(points, [[a for a in cols if a != c] for c in cols])


def replicate(h: Hypergraph, cover: Sequence[Fraction]) -> tuple[tuple[frozenset, ...], int]:
    """From a tight cover: a family with d = common denominator in which edge e stands weight * d times."""
    if not lp.is_tight(h, cover):
        raise ValueError("the cover is not tight")
    d = math.lcm(*(Fraction(w).denominator for w in cover))
    return tuple(e for e, w in zip(h.edges, cover) for _ in range(int(w * d))), d


def reconstruct(projections: Sequence[Relation]) -> DataFrame:
    """All points whose projections lie in the given ones; every coordinate is in the same number of them."""
    q = JoinQuery(projections)
    return anchored.join(q, lp.regular_cover(q.hypergraph))
