"""What the methods are compared with: pairwise plans, join-project plans, the engine's own optimiser, brute force."""

from __future__ import annotations

import math
import uuid
from collections.abc import Sequence
from functools import reduce
from itertools import combinations, product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import JoinQuery
from ..storage import drop_unread, freeing, settle
from .keys import join_rows


def _pair(a: DataFrame, b: DataFrame) -> DataFrame:
    on = [c for c in a.columns if c in b.columns]
    return a.join(b, on) if on else a.crossJoin(b)


def left_deep(q: JoinQuery, order: Sequence[int] | None = None, trace: list[int] | None = None) -> DataFrame:
    """One relation after the other. trace: gets the exact size of each intermediate join, which is counted without making it."""
    order = list(order if order is not None else range(len(q.relations)))
    out = q.relations[order[0]].df
    for i in order[1:]:
        out = _pair(out, q.relations[i].df)
    if trace is not None:
        q.sizes()
        trace += [join_rows([q.relations[i] for i in order[:k]]) for k in range(2, len(order) + 1)]
    return out.select(*q.attrs)


def bushy(q: JoinQuery, tree, trace: list[int] | None = None) -> DataFrame:
    """tree: nested pairs of relation numbers."""
    def walk(t) -> DataFrame:
        if isinstance(t, int):
            return q.relations[t].df
        out = _pair(walk(t[0]), walk(t[1]))
        if trace is not None:
            trace.append(out.count())
        return out

    return walk(tree).select(*q.attrs)


def dp_tree(q: JoinQuery):
    return dp_plan(q)[0]


def dp_plan(q: JoinQuery):
    """(tree, estimated rows of all its joins) of the cheapest pairwise tree by dynamic programming over subsets, with textbook estimates: size
    of a join is the product over the larger number of distinct values of each shared attribute."""
    sizes = q.sizes()
    seen = q.relations
    distinct = [r.df.agg(*(F.approx_count_distinct(a).alias(a) for a in r.attrs)).first().asDict() for r in seen]
    best = {frozenset([i]): (0.0, float(sizes[i]), distinct[i], i) for i in range(len(seen))}
    for k in range(2, len(seen) + 1):
        for s in map(frozenset, combinations(range(len(seen)), k)):
            options = []
            for j in range(1, k // 2 + 1):
                for left in map(frozenset, combinations(sorted(s), j)):
                    a, b = best[left], best[s - left]
                    on = set(a[2]) & set(b[2])
                    rows = a[1] * b[1]
                    for c in on:
                        rows /= max(1, a[2][c], b[2][c])
                    nd = {c: min(rows, a[2].get(c, float("inf")), b[2].get(c, float("inf"))) for c in set(a[2]) | set(b[2])}
                    options.append((a[0] + b[0] + rows, rows, nd, (a[3], b[3])))
            best[s] = min(options, key=lambda o: (o[0], str(o[3])))
    cost, _, _, tree = best[frozenset(range(len(seen)))]
    return tree, cost


def dp_order(q: JoinQuery) -> DataFrame:
    return bushy(q, dp_tree(q))


#: Rows between two joins of Spark's plan that may be shuffled at once. Where there are more, the plan runs in rounds.
ROUND_ROWS = 64_000_000
#: Rows of one relation that a task of a round holds, on average.
HELD_ROWS = 1_200_000
#: Rows that a round sends to its cells, and cells that it has at least.
SENT_ROWS, ROUND_CELLS = 48_000_000, 16


def _natural(q: JoinQuery, dfs: Sequence[DataFrame], hint: str = "") -> DataFrame:
    names = [f"_natural_{uuid.uuid4().hex}" for _ in dfs]
    for name, df in zip(names, dfs):
        df.createOrReplaceTempView(name)
    hint = f"/*+ {hint}({', '.join(names[1:])}) */ " if hint else ""
    return q.spark.sql(f"SELECT {hint}* FROM " + " NATURAL JOIN ".join(names)).select(*q.attrs)


def optimised_order(q: JoinQuery) -> list[int]:
    """The order of the relations in the plan of Spark's own optimiser, which is told their statistics: tables are registered and analysed
    in a session of their own for that. It goes by the order of the text where it knows none."""
    q.sizes()
    tables = [r.df if hasattr(r.df, "_settled_at") else settle(r.df, "relation") for r in q.relations]
    session, names = q.spark.newSession(), [f"natural_{uuid.uuid4().hex}" for _ in tables]
    session.conf.set("spark.sql.cbo.enabled", "true")
    session.conf.set("spark.sql.cbo.joinReorder.enabled", "true")
    try:
        for name, df in zip(names, tables):
            session.sql(f"CREATE TABLE {name} USING parquet LOCATION '{df._settled_at}'")
            session.sql(f"ANALYZE TABLE {name} COMPUTE STATISTICS FOR ALL COLUMNS")
        plan = session.sql("SELECT * FROM " + " NATURAL JOIN ".join(names))._jdf.queryExecution().optimizedPlan().toString()
    finally:
        for name in names:
            session.sql(f"DROP TABLE IF EXISTS {name}")
    at = [plan.find(name) for name in names]
    return sorted(range(len(names)), key=lambda i: at[i])


def catalyst_sql(q: JoinQuery) -> DataFrame:
    """Spark's own plan for NATURAL JOIN. What lies between its joins is shuffled and sorted; where that would be more than ROUND_ROWS rows, the
    optimiser is told the relations' statistics, and the same plan runs over a grid of cells, so that all its joins take place where
    the rows are: a round has some of the cells, and what it gives is settled."""
    if len(q.relations) < 3 or 0 in q.sizes():
        return _natural(q, [r.df for r in q.relations])
    with freeing(q.spark):
        between = max(join_rows(q.relations[:k]) for k in range(2, len(q.relations)))
    if between <= ROUND_ROWS:
        return _natural(q, [r.df for r in q.relations])
    order, share = optimised_order(q), dict.fromkeys(q.attrs, 1)
    rows = lambda z: max(n / math.prod(z[a] for a in r.attrs) for n, r in zip(q.sizes(), q.relations))
    sent = lambda z: sum(n * math.prod(z[a] for a in q.attrs if a not in r.attrs) for n, r in zip(q.sizes(), q.relations))
    while rows(share) > HELD_ROWS or math.prod(share.values()) < ROUND_CELLS:
        share = min((share | {a: share[a] * 2} for a in q.attrs), key=lambda z: (rows(z), sent(z)))
    # a round has the cells whose hashes agree in what they leave over the turns
    turns = dict.fromkeys(q.attrs, 1)
    while sent(share) > SENT_ROWS * math.prod(turns.values()) and math.prod(share.values()) > ROUND_CELLS * math.prod(turns.values()):
        a = max(q.attrs, key=lambda a: share[a] // turns[a])
        turns[a] *= 2
    rest = {a: share[a] // turns[a] for a in q.attrs}
    cells, steps = math.prod(rest.values()), {a: math.prod(list(rest.values())[:i]) for i, a in enumerate(rest)}
    hashed = lambda a: F.pmod(F.xxhash64(a, F.lit(a)), F.lit(share[a]))
    # cells have names that Spark deals to one task each
    named = q.spark.range(64 * cells).selectExpr("id", f"pmod(hash(id), {cells}) AS t").groupBy("t").agg(F.min("id").alias("id")).orderBy("t")
    names = F.array(*(F.lit(r["id"]) for r in named.collect()))

    def dealt(r, at: dict[str, int]) -> DataFrame:
        df = reduce(lambda d, a: d.filter(hashed(a) % turns[a] == at[a]) if turns[a] > 1 else d, r.attrs, r.df)
        own = reduce(lambda x, a: x + F.floor(hashed(a) / turns[a]) * steps[a], r.attrs, F.lit(0).cast("long"))
        free = [a for a in q.attrs if a not in r.attrs]
        offsets = [sum(steps[a] * v for a, v in zip(free, vs)) for vs in product(*(range(rest[a]) for a in free))]
        df = df.withColumn("_cell", F.explode(F.array(*(own + o for o in offsets))))
        return df.withColumn("_cell", F.element_at(names, (F.col("_cell") + 1).cast("int"))).repartition(cells, "_cell")

    # joins over the cell and more take place where the cell is
    spark, out = q.spark, []
    held = {"spark.sql.requireAllClusterKeysForCoPartition": "false", "spark.sql.shuffle.partitions": str(cells)}
    before = {key: spark.conf.get(key, None) for key in held}
    try:
        for key, value in held.items():
            spark.conf.set(key, value)
        for vs in product(*(range(turns[a]) for a in q.attrs)):
            out.append(settle(_natural(q, [dealt(q.relations[i], dict(zip(q.attrs, vs))) for i in order], "SHUFFLE_HASH"), "round"))
    finally:
        for key, value in before.items():
            spark.conf.set(key, value) if value is not None else spark.conf.unset(key)
    drop_unread(q.own, out)
    return reduce(DataFrame.unionAll, out)


def join_project(q: JoinQuery, attr_order: Sequence[str] | None = None, trace: list[int] | None = None) -> DataFrame:
    """Grow by one attribute at a time: join the result with every relation's projection on the attributes so far."""
    order = list(attr_order or q.attrs)
    out = None
    for k, a in enumerate(order):
        now = set(order[: k + 1])
        for r in sorted((r for r in q.relations if a in r.attrs), key=lambda r: -len(now & set(r.attrs))):
            p = r.df.select(*(c for c in order if c in now and c in r.attrs)).distinct()
            out = p if out is None else _pair(out, p)
            if trace is not None:
                trace.append(out.count())
        out = out.distinct()
    return out.select(*q.attrs)


def run_plan(q: JoinQuery, expr, trace: list[int] | None = None) -> DataFrame:
    """Any join-project plan: a relation number, ("join", x, y), or ("project", x, attributes)."""
    if isinstance(expr, int):
        return q.relations[expr].df
    if expr[0] == "project":
        out = run_plan(q, expr[1], trace).select(*expr[2]).distinct()
    elif expr[0] == "join":
        out = _pair(run_plan(q, expr[1], trace), run_plan(q, expr[2], trace))
    else:
        raise ValueError(f"unknown operation {expr[0]!r}")
    if trace is not None:
        trace.append(out.count())
    return out


def brute(q: JoinQuery) -> DataFrame:
    """By the definition: all combinations of attribute values, tested against every relation. Tiny inputs only."""
    values = [reduce(DataFrame.intersect, [r.df.select(a) for r in q.relations if a in r.attrs]).distinct() for a in q.attrs]
    space = reduce(DataFrame.crossJoin, values)
    return reduce(lambda d, r: d.join(r.df, list(r.attrs), "left_semi"), q.relations, space).select(*q.attrs)
