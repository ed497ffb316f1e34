"""Prefix indexes: membership, section counts and section listing for a fixed column order, as tables."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import Relation
from ..storage import settle


class PrefixIndex:
    """Distinct projections of one relation and counts of sections: plans over the relation's table, or tables of their own where
    they were counted, saved or loaded.

    count(prefix, rest): for each value of the prefix, how many values of ``rest`` it has. With an empty prefix that is one
    number, found once in the driver.
    """

    def __init__(self, rel: Relation, order: list[str] | None = None):
        self.rel, self.order = rel, list(order or rel.attrs)
        self.hashed = False  # tests go by hash tables of the relation, one a task
        self._lists: dict[frozenset, DataFrame] = {}
        self._counts: dict[tuple, DataFrame] = {}
        self._totals: dict[frozenset, int] = {}

    def list(self, attrs) -> DataFrame:
        key = frozenset(attrs)
        if key == frozenset(self.rel.attrs):
            return self.rel.df
        return self._lists[key] if key in self._lists else self.rel.project(a for a in self.order if a in key)

    def count(self, prefix, rest, name: str = "_count") -> DataFrame:
        key = (frozenset(prefix), frozenset(rest))
        made = self._counts[key] if key in self._counts else self.list(key[0] | key[1]).groupBy(*(a for a in self.order if a in key[0])).agg(F.count("*").alias("_count"))
        return made.withColumnRenamed("_count", name)

    def total(self, attrs) -> int:
        key = frozenset(attrs)
        if key == frozenset(self.rel.attrs) and self.rel.size is not None:
            return self.rel.size
        if key not in self._totals:
            # counting makes the rows: they are settled, as a section that is counted is mostly listed, too
            self._lists[key] = settle(self.list(key), "section")
            self._totals[key] = self._lists[key].count()
        return self._totals[key]

    def member(self, df: DataFrame, attrs) -> DataFrame:
        """Rows of df whose values of ``attrs`` occur in the relation."""
        on = [a for a in self.order if a in set(attrs)]
        # a semijoin needs no distinct rows on its right
        known = self._lists.get(frozenset(on), self.rel.df).select(*on)
        return df.join(known.hint("shuffle_hash") if self.hashed else known, on, "left_semi") if on else df

    def save(self, path: str) -> None:
        """All prefixes of the order with their counts of next values, each sorted; a later query needs no pass over the
        relation itself."""
        for k in range(len(self.order)):
            prefix, rest = self.order[:k], self.order[k:]
            self.list(self.order[: k + 1]).sortWithinPartitions(*self.order[: k + 1]).write.mode("overwrite").parquet(f"{path}/list={k + 1}")
            if k:
                self.count(prefix, rest).sortWithinPartitions(*prefix).write.mode("overwrite").parquet(f"{path}/count={k}")

    @classmethod
    def load(cls, spark, path: str, order: list[str], name: str = "") -> PrefixIndex:
        full = spark.read.parquet(f"{path}/list={len(order)}").select(*order)
        out = cls(Relation(name, full), order)
        for k in range(1, len(order)):
            out._lists[frozenset(order[:k])] = spark.read.parquet(f"{path}/list={k}").select(*order[:k])
            out._counts[frozenset(order[:k]), frozenset(order[k:])] = spark.read.parquet(f"{path}/count={k}")
        return out


def build_all_orders(rel: Relation, most: int = 4) -> dict[tuple[str, ...], PrefixIndex]:
    """An index per column order, for queries not known yet; arity! of them, so the arity is limited."""
    if len(rel.attrs) > most:
        raise ValueError(f"{len(rel.attrs)} columns have too many orders")
    return {o: PrefixIndex(rel, list(o)) for o in permutations(rel.attrs)}


def intersect_small(a: DataFrame, b: DataFrame, size_a: int, size_b: int) -> DataFrame:
    """Rows in both, reading the smaller as the probe: cost follows the smaller set."""
    small, large = (a, b) if size_a <= size_b else (b, a)
    return small.distinct().join(large.select(*small.columns), small.columns, "left_semi")
