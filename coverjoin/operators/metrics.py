"""Cost measures: sizes of inputs, intermediates and outputs against their bounds."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from functools import reduce
from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import anchor as trees
from ..plans import bounds, lp
from ..plans.model import JoinQuery, Relation
from . import allbutone, anchored
from .keys import join_rows


def bound_ratio(q: JoinQuery, rows: int) -> float:
    """Output over cover bound: at most 1."""
    b = bounds.cover_bound(q.hypergraph, q.sizes())
    return rows / b if b else 0.0


def observed(df: DataFrame, name: str) -> tuple[DataFrame, Callable[[], int]]:
    """The same rows, and a function that tells their number once an action has run: no second pass."""
    from pyspark.sql import Observation

    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), lambda: seen.get["rows"]


def pairwise_sizes(q: JoinQuery) -> dict[tuple[str, str], int]:
    """Exact size of the join of each pair of relations with a common attribute, from degrees alone."""
    out = {}
    for i, r in enumerate(q.relations):
        for s in q.relations[i + 1 :]:
            on = [a for a in r.attrs if a in s.attrs]
            if on:
                x, y = r.df.groupBy(*on).agg(F.count("*").alias("x")), s.df.groupBy(*on).agg(F.count("*").alias("y"))
                out[r.name, s.name] = int(x.join(y, on).agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0))).first()[0])
    return out


def gap(q: JoinQuery) -> float:
    """Least largest intermediate of all left-deep pairwise plans' first joins, over the cover bound."""
    return min(pairwise_sizes(q).values()) / max(1.0, bounds.cover_bound(q.hypergraph, q.sizes()))


def split_sizes(q: JoinQuery, tau=None, split: str | None = None) -> DataFrame:
    """n_heavy (keys), heavy_product (heavy keys times #T), light_join (rows of light R joined with S): one row."""
    r, s, t, a, b, c = allbutone.roles(q, split)
    size = dict(zip((x.name for x in q.relations), q.sizes()))
    cut = allbutone.split_at((size[r.name], size[s.name], size[t.name]), tau)
    deg = r.df.groupBy(b).agg(F.count("*").alias("_x")).withColumn("_heavy", cut.heavy(F.col("_x")))
    both = deg.join(s.df.groupBy(b).agg(F.count("*").alias("_y")), b, "left")
    return both.agg(F.coalesce(F.sum(F.col("_heavy").cast("long")), F.lit(0)).alias("n_heavy"), (F.coalesce(F.sum(F.col("_heavy").cast("long")), F.lit(0)) * size[t.name]).alias("heavy_product"), F.coalesce(F.sum(F.when(~F.col("_heavy"), F.col("_x") * F.coalesce("_y", F.lit(0)))), F.lit(0)).alias("light_join"))


def case_counts(q: JoinQuery, **how) -> list[dict]:
    """Bindings per node of the general method that recursed, were scanned, or ended in a leaf."""
    c = anchored.Counters(on=True)
    anchored.join(q, counters=c, **how)
    return c.rows


def node_budget(q: JoinQuery, **how) -> list[dict]:
    """For each node that the general method visits: its bindings, the rows it gives and the sum of the bindings' budgets, a
    budget being the product of the sections' sizes to their weights; worst: the largest share of its budget that a
    binding uses. All in the one run."""
    c = anchored.Counters(budget=True)
    anchored.join(q, counters=c, **how)
    return c.budgets


def phases(q: JoinQuery, **how) -> dict[str, float]:
    """Seconds for preparing the query, counting the inputs, and running it."""
    t0 = time.perf_counter()
    sizes = q.sizes()
    t1 = time.perf_counter()
    lp.optimal_cover(q.hypergraph, sizes)
    trees.build(q.hypergraph)
    t2 = time.perf_counter()
    rows = anchored.join(q, **how).count()
    return {"data": t1 - t0, "query": t2 - t1, "evaluation": time.perf_counter() - t2, "rows": rows}


def growth(make: Callable[[int], JoinQuery], ns: Sequence[int]) -> list[tuple[int, int, int, int]]:
    """For a family of triangles as it grows: n, largest intermediate of the pairwise plan (both exact, from degrees), rows that the
    heavy/light method makes, bound."""
    out = []
    for n in ns:
        q = make(n)
        split = split_sizes(q).first()
        out.append((n, allbutone.split_costs(q)[q.attrs[1]], split["heavy_product"] + split["light_join"], bounds.floor_bound(q.hypergraph, q.sizes())))
    return out


def plan_gap(q: JoinQuery) -> dict:
    """The left-deep plan without products whose largest intermediate is least, that intermediate, and its ratio to the cover bound.
    Intermediates are counted, not made; there are as many plans as orders, so this is for few relations."""
    best, known = None, {}
    rows = lambda some: known[some] if some in known else known.setdefault(some, join_rows([q.relations[i] for i in sorted(some)]))
    q.sizes()
    for order in permutations(range(len(q.relations))):
        have, linked = set(q.relations[order[0]].attrs), True
        for i in order[1:]:
            linked &= bool(have & set(q.relations[i].attrs))
            have |= set(q.relations[i].attrs)
        if linked and order[0] < order[1]:
            most = max(rows(frozenset(order[:k])) for k in range(2, len(order) + 1))
            best = min(best, (most, order)) if best else (most, order)
    return {"largest": best[0], "order": best[1], "gap": best[0] / max(1.0, bounds.cover_bound(q.hypergraph, q.sizes()))}


def index_cost(r: Relation) -> list[tuple[str, int]]:
    """Rows of the prefix tables of all column orders of a relation: what its indexes cost to keep."""
    out: dict[tuple[str, ...], int] = {}
    for order in permutations(r.attrs):
        for k in range(1, len(order) + 1):
            same = next((p for p in out if set(p) == set(order[:k])), None)
            out[order[:k]] = out[same] if same else r.project(order[:k]).count()
    return [(",".join(p), n) for p, n in out.items()]


def key_skew(r: Relation) -> DataFrame:
    """attribute, largest number of rows that one of its values has, and its ratio to the mean."""
    one = lambda a: r.df.groupBy(a).agg(F.count("*").alias("n")).agg(F.lit(a).alias("attribute"), F.max("n").alias("largest"), F.round(F.max("n") / F.avg("n"), 6).alias("ratio"))
    return reduce(DataFrame.unionByName, map(one, r.attrs))


def moved(spark, run: Callable[[], object]) -> dict[str, float]:
    """Megabytes shuffled and spilled by all stages that ``run`` starts, and the largest share of a stage's shuffled rows that one of
    its tasks read; from Spark's own status store."""
    store = spark.sparkContext._jsc.sc().statusStore()
    empty = spark.sparkContext._jvm.java.util.ArrayList()

    def stages():
        it = store.stageList(empty, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), empty).iterator()
        out = {}
        while it.hasNext():
            s = it.next()
            out[s.stageId(), s.attemptId()] = (s.shuffleWriteBytes(), s.diskBytesSpilled())
        return out

    before = stages()
    run()
    new = [v for k, v in stages().items() if k not in before]
    return {"stages": len(new), "shuffle_mb": round(sum(v[0] for v in new) / 1e6, 2), "spill_mb": round(sum(v[1] for v in new) / 1e6, 2)}
