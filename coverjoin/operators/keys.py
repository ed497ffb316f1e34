"""Relations with a key: where one attribute determines the others, a join over it makes no more rows than there were."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce as fold

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import bounds
from ..plans.model import JoinQuery, Relation
from ..storage import drop_unread, small


def keys_of(q: JoinQuery) -> list[set[str]]:
    """For each relation the attributes no value of which occurs twice. Sketches rule most out, the others are counted: two jobs."""
    sizes = q.sizes()
    told = [r.df.agg(F.lit(i).alias("i"), F.array(*(F.approx_count_distinct(a) for a in r.attrs)).alias("n")) for i, r in enumerate(q.relations)]
    near = [(row["i"], a) for row in fold(DataFrame.unionByName, told).collect() for a, n in zip(q.relations[row["i"]].attrs, row["n"]) if n >= 0.8 * sizes[row["i"]]]
    out: list[set[str]] = [set() for _ in q.relations]
    if near:
        most = [q.relations[i].df.groupBy(a).count().agg(F.lit(k).alias("k"), F.max("count").alias("n")) for k, (i, a) in enumerate(near)]
        for row in fold(DataFrame.unionByName, most).collect():
            if row["n"] == 1:
                out[near[row["k"]][0]].add(near[row["k"]][1])
    return out


def reduced(q: JoinQuery) -> tuple[JoinQuery, list[tuple[Relation, str]]]:
    """The query without the relations that a key joins to another one. A relation whose other attributes nobody else has is put
    off and joined in the end, in reverse order; others go into the relation that has most of their attributes, smallest first."""
    if len(q.relations) < 2 or 0 in q.sizes():
        return q, []
    rels, sizes, late = list(q.relations), q.sizes(), []
    keys = keys_of(q)

    def step() -> bool:
        for absorb in (False, True):
            for i in sorted(range(len(rels)), key=lambda i: (sizes[i], i)):
                r = rels[i]
                for a in sorted(keys[i]):
                    others = [j for j in range(len(rels)) if j != i and a in rels[j].attrs]
                    own = [b for b in r.attrs if b != a and not any(b in x.attrs for x in rels if x is not r)]
                    alone = bool(own) and len(own) == len(r.attrs) - 1
                    if not others or alone == absorb:
                        continue
                    if alone:
                        late.append((r, a))
                    else:
                        j = max(others, key=lambda j: (len(set(r.attrs) & set(rels[j].attrs)), -sizes[j], -j))
                        rels[j] = Relation(rels[j].name, rels[j].df.join(small(r.df, sizes[i]), [b for b in rels[j].attrs if b in r.attrs]))
                    for x in (rels, sizes, keys):
                        del x[i]
                    return True
        return False

    while len(rels) > 1 and step():
        pass
    attrs = [a for a in q.attrs if any(a in r.attrs for r in rels)]
    return JoinQuery(rels, attrs), late


def join(q: JoinQuery, run: Callable[[JoinQuery], DataFrame] | None = None, spend: bool = False) -> DataFrame:
    """Natural join: ``run`` answers what the keys leave over (default: by its shape). spend: q is not read again, see spent()."""
    if 0 in q.sizes():
        return q.empty()
    core, late = reduced(q)
    if spend:
        spent(q, core, late)
    return finish(q, core, late, run or answer)


def spent(q: JoinQuery, core: JoinQuery, late: list[tuple[Relation, str]]) -> None:
    """What the keys leave over is settled, and the tables that q had settled go where nothing reads them any more: neither they nor
    the shuffle files of the joins by keys are on disk beside those of the join to come."""
    core.sizes()
    drop_unread(q.own, [r.df for r in core.relations] + [r.df for r, _ in late])


def finish(q: JoinQuery, core: JoinQuery, late: list[tuple[Relation, str]], run: Callable[[JoinQuery], DataFrame]) -> DataFrame:
    out = core.relations[0].df if len(core.relations) == 1 else run(core)
    return fold(lambda d, k: d.join(small(k[0].df, k[0].size), k[1]), reversed(late), out).select(*q.attrs)


def answer(core: JoinQuery) -> DataFrame:
    """Two relations are one join. More go pairwise if the estimate keeps to the bound, else by the shape's method."""
    from . import baselines, planner

    if len(core.relations) == 2 and set(core.relations[0].attrs) & set(core.relations[1].attrs):
        return baselines.left_deep(core)
    if 0 in core.sizes():
        return core.empty()
    if planner.choose(core) == "anchored":
        tree, cost = baselines.dp_plan(core)
        if cost <= bounds.cover_bound(core.hypergraph, core.sizes()):
            return baselines.bushy(core, tree)
    return planner.join(core)


def join_rows(rels: list[Relation] | tuple[Relation, ...]) -> int:
    """Exact number of rows of a natural join. Of two relations it is told by degrees, and no pair is made."""
    q = JoinQuery(rels)
    if len(rels) == 1:
        return q.sizes()[0]
    if len(rels) == 2:
        r, s = q.relations
        on = [a for a in r.attrs if a in s.attrs]
        if not on:
            return q.sizes()[0] * q.sizes()[1]
        x, y = (t.df.groupBy(*on).agg(F.count("*").cast("decimal(19,0)").alias(n)) for t, n in ((r, "_x"), (s, "_y")))
        return int(x.join(y, on).agg(F.coalesce(F.sum(F.col("_x") * F.col("_y")), F.lit(0))).first()[0])
    return join(q).count()
