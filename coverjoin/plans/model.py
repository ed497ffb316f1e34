"""Relations, queries and their hypergraphs."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field, replace
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..storage import settle_all, shuffles, sized


@dataclass(frozen=True)
class Hypergraph:
    """Vertices in declared order and edges; an edge may occur more than once."""

    vertices: tuple[str, ...]
    edges: tuple[frozenset[str], ...]

    def __post_init__(self):
        if uncovered := set(self.vertices) - set().union(*self.edges, frozenset()):
            raise ValueError(f"no relation has {sorted(uncovered)}")

    @property
    def n(self) -> int:
        return len(self.vertices)

    @property
    def m(self) -> int:
        return len(self.edges)

    def degree(self, v: str) -> int:
        return sum(v in e for e in self.edges)

    def is_graph(self) -> bool:
        return all(len(e) <= 2 for e in self.edges)

    def is_all_but_one(self) -> bool:
        """n attributes, n relations, relation i omits exactly one attribute, each a different one."""
        return self.n >= 2 and self.m == self.n and {frozenset(self.vertices) - e for e in self.edges} == {frozenset([v]) for v in self.vertices}

    def cycle(self) -> tuple[list[int], list[str]] | None:
        """If the edges form one cycle: edge numbers and vertices in cyclic order; edge i joins vertices i and i + 1."""
        if self.m < 3 or self.m != self.n or any(len(e) != 2 for e in self.edges) or any(self.degree(v) != 2 for v in self.vertices):
            return None
        at, used, edges, vertices = self.vertices[0], set(), [], []
        while len(edges) < self.m:
            k = next((i for i, e in enumerate(self.edges) if at in e and i not in used), None)
            if k is None:
                return None
            used.add(k)
            edges.append(k)
            vertices.append(at)
            at = next(iter(self.edges[k] - {at}))
        return (edges, vertices) if at == vertices[0] and len(set(vertices)) == self.n else None


@dataclass(frozen=True)
class Relation:
    """A set of rows over named attributes. ``size`` is its row count, where known."""

    name: str
    df: DataFrame = field(compare=False)
    size: int | None = None

    @property
    def attrs(self) -> tuple[str, ...]:
        return tuple(self.df.columns)

    def section(self, **values) -> Relation:
        """Rows that agree with the values, without the bound columns."""
        df = reduce(lambda d, kv: d.filter(F.col(kv[0]) == F.lit(kv[1])), values.items(), self.df)
        return Relation(self.name, df.drop(*values).distinct())

    def project(self, attrs: Iterable[str]) -> DataFrame:
        attrs = list(attrs)
        df = self.df.select(*attrs)
        return df if set(attrs) == set(self.attrs) else df.distinct()


class JoinQuery:
    """A natural join of relations, matched by attribute name. Rows with a null in an attribute that two or more relations
    have can join with nothing and are left out; nulls elsewhere stay."""

    def __init__(self, relations: Iterable[Relation], attrs: Iterable[str] | None = None):
        rels = tuple(relations)
        if not rels:
            raise ValueError("a query has at least one relation")
        seen = list(dict.fromkeys(a for r in rels for a in r.attrs))
        shared = {a for a in seen if sum(a in r.attrs for r in rels) > 1}
        for a in shared:
            kinds = {r.df.schema[a].dataType.simpleString() for r in rels if a in r.attrs}
            if len(kinds) > 1:
                raise TypeError(f"attribute {a} has types {sorted(kinds)}: cast one on load")
            if isinstance(next(r.df.schema[a].dataType for r in rels if a in r.attrs), (T.MapType, T.VariantType)):
                raise TypeError(f"attribute {a} cannot be compared")
        self.attrs = tuple(attrs or seen)
        if set(self.attrs) != set(seen):
            raise ValueError("the declared attributes are not those of the relations")
        # not dropna, which takes not-a-number for missing; joins take it for a value
        held = lambda r: [F.col(a).isNotNull() for a in r.attrs if a in shared and r.df.schema[a].nullable]
        self.relations = tuple(replace(r, df=r.df.filter(reduce(and_, held(r))) if held(r) else r.df) for r in rels)
        self.hypergraph = Hypergraph(self.attrs, tuple(frozenset(r.attrs) for r in rels))
        self.own: list[DataFrame] = []  # tables that sizes() has settled

    @property
    def spark(self):
        return self.relations[0].df.sparkSession

    def sizes(self) -> list[int]:
        """Row counts of all relations, in one job for those that are not known yet. Relations that a shuffle makes (most often the one
        that drops repeated rows) are settled first, as degrees, sections and the join itself read them again; bare scans stay scans."""
        missing = [i for i, r in enumerate(self.relations) if r.size is None]
        if missing:
            made = [i for i in missing if shuffles(self.relations[i].df)]
            tables = dict(zip(made, settle_all([self.relations[i].df for i in made], "relation")))
            self.own += tables.values()
            self.relations = tuple(replace(r, df=tables.get(i, r.df)) for i, r in enumerate(self.relations))
            counts = reduce(DataFrame.unionAll, [self.relations[i].df.select(F.lit(i).alias("i")) for i in missing]).groupBy("i").count().collect()
            got = {r["i"]: r["count"] for r in counts}
            self.relations = tuple(replace(r, df=sized(r.df, got.get(i, 0)), size=got.get(i, 0)) if i in missing else r for i, r in enumerate(self.relations))
        return [r.size for r in self.relations]

    def pick(self, which: Iterable[int], attrs: Iterable[str] | None = None) -> JoinQuery:
        return JoinQuery([self.relations[i] for i in which], attrs)

    def empty(self) -> DataFrame:
        fields = {f.name: f for r in self.relations for f in r.df.schema.fields}
        return self.spark.createDataFrame([], T.StructType([fields[a] for a in self.attrs]))


@dataclass(frozen=True)
class FD:
    """In the relation of this name, u determines v."""

    relation: str
    u: str
    v: str


@dataclass(frozen=True)
class Atom:
    """A table and its terms: a name is a variable, a ``Const`` a constant."""

    table: str
    terms: tuple


@dataclass(frozen=True)
class Const:
    value: object


@dataclass(frozen=True)
class Rule:
    head: tuple[str, ...]
    body: tuple[Atom, ...]
