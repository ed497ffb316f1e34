"""General method: any natural join, for any cover, by an anchor tree - set at a time.

Per tree node there is one plan over the table of all bindings, not one call per binding: the rescaled cover depends on the
path in the tree only. Each binding is sent to one of two branches by a size check on section counts; the check decides cost, never
rows.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field, replace
from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..plans import anchor as trees
from ..plans import lp
from ..plans.model import JoinQuery
from ..storage import product, settle
from .allbutone import split_costs
from .index import PrefixIndex

#: Rows that the bindings of one step may give before they are tested; more bindings are dealt into slices, one after the other.
SLICE_ROWS = 64_000_000
#: Rows of a relation that a task may hold, for a test of a slice to go by hash instead of sorting.
HASHED_ROWS = 2_000_000


@dataclass
class Counters:
    """What each node did, filled only when asked for, as each number is a job: ``on`` counts bindings (rows), ``budget`` holds
    what each node gives against its share of the bound, binding by binding (budgets)."""

    on: bool = False
    budget: bool = False
    rows: list[dict] = field(default_factory=list)
    budgets: list[dict] = field(default_factory=list)


def join(q: JoinQuery, cover: Sequence | None = None, order: Sequence[int] | str | None = None, indexes: dict[str, PrefixIndex] | None = None, counters: Counters | None = None) -> DataFrame:
    """Natural join of any shape. cover: any fractional cover (default: the cheapest for the sizes). order: edge order of the anchor
    tree, or "size" / "arity", or for triangles "degrees": bind the attribute of the least degree sum first. indexes: prebuilt, by relation name. An empty relation gives an empty result at once."""
    h, sizes = q.hypergraph, q.sizes()
    cover = tuple(map(Fraction, cover)) if cover is not None else lp.optimal_cover(h, sizes)
    if not lp.is_cover(h, cover):
        raise ValueError("not a fractional cover")
    if 0 in sizes:
        return q.empty()
    if h.m == 1:
        return q.relations[0].df.select(*q.attrs)
    if hidden := _null_private(q):
        # nulls of attributes that one relation alone has must come through equality tests: they travel inside a struct
        wrapped = [replace(r, df=r.df.withColumns({a: F.struct(a) for a in r.attrs if a in hidden})) for r in q.relations]
        out = join(JoinQuery(wrapped, q.attrs), cover, order, {k: v for k, v in (indexes or {}).items() if not hidden & set(v.rel.attrs)}, counters)
        return out.select(*(F.col(a)[a].alias(a) if a in hidden else F.col(a) for a in q.attrs))
    if order == "size":
        order = sorted(range(h.m), key=lambda i: (sizes[i], i))
    elif order == "degrees":
        costs = split_costs(q)
        first = min(costs, key=lambda a: (costs[a], a))
        order = sorted(range(h.m), key=lambda i: (first not in h.edges[i], i))
    elif order == "arity":
        order = sorted(range(h.m), key=lambda i: (-len(h.edges[i]), i))
    tree, order = trees.build(h, order)
    total = trees.attribute_order(h, tree, order)
    run = _Run([q.relations[i] for i in order], total, indexes or {}, counters or Counters())
    return run.solve(tree, tuple(cover[i] for i in order), frozenset(), None).select(*q.attrs)


def _null_private(q: JoinQuery) -> set[str]:
    """Attributes of one relation only that have a null."""
    out = set()
    for r in q.relations:
        mine = [a for a in r.attrs if q.hypergraph.degree(a) == 1 and r.df.schema[a].nullable and not isinstance(r.df.schema[a].dataType, StructType)]
        if mine:
            seen = r.df.agg(*(F.coalesce(F.bool_or(F.col(a).isNull()), F.lit(False)).alias(a) for a in mine)).first()
            out |= {a for a in mine if seen[a]}
    return out


def _child_cover(y: tuple[Fraction, ...], k: int) -> tuple[Fraction, ...]:
    """Inside the anchor the other weights grow by 1 / (1 - weight of the anchor)."""
    return tuple(w / (1 - y[k]) for w in y[:k])


class _Run:
    def __init__(self, rels, total, indexes, counters):
        self.edges = [frozenset(r.attrs) for r in rels]
        self.index = [indexes.get(r.name) or PrefixIndex(r, trees.local_order(r.attrs, total)) for r in rels]
        self.counters = counters

    def note(self, node, what: str, rows: int):
        if self.counters.on:
            self.counters.rows.append({"rank": node.rank, "universe": tuple(sorted(node.universe)), "what": what, "rows": rows})

    def extend(self, df: DataFrame | None, i: int, bound: frozenset, new: frozenset, tests: Sequence[int] = ()) -> DataFrame:
        """Bindings with the new columns of relation i's sections. Where relation i has no bound column, they meet through a
        relation that will be tested and has both kinds, so that no product is made."""
        if df is None:
            return self.index[i].list(new)
        table = self.index[i].list((bound & self.edges[i]) | new)
        if not bound & self.edges[i]:
            link = next((j for j in tests if j != i and self.edges[j] & bound and self.edges[j] & new), None)
            if link is None:
                return product(df, table, None, self.index[i].total(new))
            df = df.join(self.index[link].list(self.edges[link] & (bound | new)), sorted(self.edges[link] & bound))
            return df.join(table, sorted(self.edges[link] & new))
        return df.join(table, [a for a in self.index[i].order if a in bound & self.edges[i]])

    def counted(self, df: DataFrame, i: int, bound: frozenset, rest: frozenset) -> tuple[DataFrame, object]:
        """The bindings with the size of their section of relation i; those without one fall away."""
        on = [a for a in self.index[i].order if a in bound & self.edges[i]]
        if not on:
            return df, F.lit(self.index[i].total(rest)).cast("long")
        name = f"_n{i}"
        return df.join(self.index[i].count(on, rest, name), on), F.col(name)

    def branches(self, df: DataFrame, by: str, own: list[str], choice, rows=None) -> dict:
        """Bindings by the branch they go to, and how many: settled first, so that no branch repeats the work before it and no
        plan holds its tree's history. Branches without bindings are left out. rows: what a binding gives at most; then the third value
        is the number of slices, to which a binding that is too large for one counts as one."""
        share = F.lit(0.0) if rows is None else F.least(rows, F.lit(float(SLICE_ROWS)))
        df = settle(df.withColumns({by: choice, "_share": share}).select(*own, by, "_share"), "bindings")
        told = df.groupBy(by).agg(F.count("*").alias("n"), F.sum("_share").alias("rows")).collect()
        return {r[by]: (df.filter(F.col(by) == r[by]).select(*own), r["n"], max(1, int(r["rows"] // SLICE_ROWS))) for r in told}

    def sliced(self, run, d: DataFrame, n: int) -> DataFrame:
        """run() over n slices of the bindings, each settled before the next begins: the rows to be tested are on disk for one at a time."""
        if n == 1:
            return run(d)
        tasks = int(d.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        for x in self.index:
            x.hashed = (x.rel.size or math.inf) <= HASHED_ROWS * tasks
        slot = F.pmod(F.xxhash64(*d.columns), F.lit(n))
        return reduce(DataFrame.unionByName, [settle(run(d.filter(slot == i)), "slice") for i in range(n)])

    def leaf(self, node, bound: frozenset, df: DataFrame | None) -> DataFrame:
        every, u = range(node.rank + 1), node.universe
        test = lambda d, skip: reduce(lambda x, j: self.index[j].member(x, (bound & self.edges[j]) | u), (j for j in every if j != skip), d)
        if df is None:
            best = min(every, key=lambda i: (self.index[i].total(u), i))
            return test(self.extend(None, best, bound, u), best)
        if node.rank == 0:
            return self.extend(df, 0, bound, u)
        cols, own, start = [], df.columns, df
        for i in every:
            df, c = self.counted(df, i, bound, u)
            cols.append(c)
        least = F.least(*cols)
        pick = reduce(lambda acc, i: F.when(cols[i] == least, i).otherwise(acc), reversed(every), F.lit(-1))
        sent = self.branches(df, "_pick", own, pick)
        self.note(node, "leaf bindings", sum(x[1] for x in sent.values()))
        made = [test(self.extend(d, i, bound, u, every), i) for i, (d, *_) in sorted(sent.items())]
        return reduce(DataFrame.unionByName, made) if made else self.nothing(start, u)

    def nothing(self, df: DataFrame | None, new: frozenset) -> DataFrame:
        """No rows over the columns of df and the new ones."""
        kinds = {f.name: f for i in self.index for f in i.rel.df.schema.fields}
        fields = ([] if df is None else list(df.schema.fields)) + [kinds[a] for a in sorted(new)]
        return self.index[0].rel.df.sparkSession.createDataFrame([], StructType(fields))

    def solve(self, node, y: tuple[Fraction, ...], bound: frozenset, df: DataFrame | None) -> DataFrame:
        """Rows over bound + universe that all relations of the node agree with, for bindings df over ``bound``."""
        out = self.leaf(node, bound, df) if node.leaf else self.inner(node, y, bound, df)
        if self.counters.budget:
            out = settle(out, "node")
            self.measure(node, y, bound, df, out)
        return out

    def inner(self, node, y: tuple[Fraction, ...], bound: frozenset, df: DataFrame | None) -> DataFrame:
        k, anchor = node.rank, self.edges[node.rank]
        outside, inside = node.universe - anchor, node.universe & anchor
        left = self.solve(node.left, y[:k], bound, df) if node.left else df
        if not inside:
            return left
        now = bound | outside
        others = [i for i in range(k) if self.edges[i] & inside]

        def scan(d: DataFrame | None) -> DataFrame:
            out = self.extend(d, k, now, inside, others)
            return reduce(lambda x, i: self.index[i].member(x, (now & self.edges[i]) | (inside & self.edges[i])), others, out)

        def descend(d: DataFrame | None) -> DataFrame:
            return self.index[k].member(self.solve(node.right, _child_cover(y, k), now, d), (now & anchor) | inside)

        if y[k] >= 1 or node.right is None:
            if left is not None and self.counters.on:
                left = settle(left, "bindings")
                self.note(node, "scan (always)", left.count())
            return scan(left)
        weigh = [i for i in others if y[i] > 0]
        if left is None:
            a = math.fsum(float(y[i] / (1 - y[k])) * math.log(max(1, self.index[i].total(inside & self.edges[i]))) for i in weigh)
            recurse = a < math.log(max(1, self.index[k].total(inside)))
            self.note(node, "recurse (all)" if recurse else "scan (all)", 1)
            return descend(None) if recurse else scan(None)
        own, start, terms = left.columns, left, []
        for i in weigh:
            left, c = self.counted(left, i, now, inside & self.edges[i])
            terms.append(F.ln(c) * float(y[i] / (1 - y[k])))
        left, c = self.counted(left, k, now, inside)
        within = reduce(lambda a, b: a + b, terms, F.lit(0.0))
        sent = self.branches(left, "_in", own, within < F.ln(c), F.least(F.exp(within), c.cast("double")))
        for name, into in (("recurse", True), ("scan", False)):
            self.note(node, name, sent[into][1] if into in sent else 0)
        made = [self.sliced(descend if into else scan, d, n) for into, (d, _, n) in sorted(sent.items(), reverse=True)]
        return reduce(DataFrame.unionByName, made) if made else self.nothing(start, inside)

    def measure(self, node, y: tuple[Fraction, ...], bound: frozenset, df: DataFrame | None, out: DataFrame) -> None:
        """Rows that the node gives against its budget, the product of its sections' sizes to their weights: for each binding."""
        mine = [i for i in range(node.rank + 1) if self.edges[i] & node.universe]
        told = {"rank": node.rank, "universe": tuple(sorted(node.universe)), "bound": tuple(sorted(bound))}
        if df is None:
            rows = out.count()
            budget = math.exp(math.fsum(float(y[i]) * math.log(max(1, self.index[i].total(self.edges[i] & node.universe))) for i in mine))
            self.counters.budgets.append(told | {"bindings": 1, "rows": rows, "budget": budget, "worst": rows / budget})
            return
        on = sorted(bound)
        own, terms = df.select(*on).distinct(), []
        for i in mine:
            own, c = self.counted(own, i, bound, self.edges[i] & node.universe)
            terms.append(F.ln(c) * float(y[i]))
        budget = own.select(*on, F.exp(reduce(lambda a, b: a + b, terms, F.lit(0.0))).alias("_budget"))
        given = out.groupBy(*on).agg(F.count("*").alias("_rows"))
        seen = given.join(budget, on, "full").select(F.coalesce("_rows", F.lit(0)).alias("r"), F.coalesce("_budget", F.lit(0.0)).alias("b"))
        # rows of a binding without sections would be beyond any budget
        used = F.when((F.col("r") > 0) & (F.col("b") > 0), F.col("r") / F.col("b")).when(F.col("r") > 0, float("inf")).otherwise(0.0)
        n, rows, total, worst = seen.agg(F.count("*"), F.sum("r"), F.sum("b"), F.max(used)).first()
        self.counters.budgets.append(told | {"bindings": n, "rows": rows or 0, "budget": total or 0.0, "worst": worst or 0.0})
