"""Constructed instance families, made inside Spark from ranges of keys."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.model import JoinQuery, Relation


def _named(df: DataFrame, cols: Sequence[str], name: str) -> Relation:
    return Relation(name, df.toDF(*cols))


def bad_triangle(keys: DataFrame, n: int) -> JoinQuery:
    """Three copies of {(0, j)} and {(j, 0)}, j = 1 .. n/2: pairwise joins have n²/4 + n/2 rows, the triangle none.
    keys: one long column that has 1 .. n/2."""
    k = keys.toDF("j").filter(F.col("j").between(1, n // 2))
    zero = F.lit(0).cast("long")
    pairs = k.select(zero.alias("x"), F.col("j").alias("y")).union(k.select(F.col("j"), zero))
    return JoinQuery([_named(pairs, c, r) for r, c in (("R", ("a", "b")), ("S", ("b", "c")), ("T", ("a", "c")))])


def grid(values: DataFrame, attrs: Sequence[str]) -> JoinQuery:
    """All-but-one instance of full products: k^(n-1) rows each, k^n in the output. values: one column."""
    rels = []
    for i, out in enumerate(attrs):
        cols = [a for a in attrs if a != out]
        df = reduce(lambda d, a: d.crossJoin(F.broadcast(values.toDF(a))), cols[1:], values.toDF(cols[0]))
        rels.append(Relation(f"R{i + 1}", df))
    return JoinQuery(rels, attrs)


def one_nonzero(keys: DataFrame, attrs: Sequence[str], c: int) -> JoinQuery:
    """All-but-one instance whose rows have at most one non-zero value, 1 .. c: size 1 + (n-1) c, output n c + 1."""
    k = keys.toDF("j").filter(F.col("j").between(1, c))
    zero = F.lit(0).cast("long")
    rels = []
    for i, out in enumerate(attrs):
        cols = [a for a in attrs if a != out]
        parts = [k.limit(0).sparkSession.range(1).select(*(zero.alias(a) for a in cols))]
        parts += [k.select(*(F.col("j").alias(b) if b == a else zero.alias(b) for b in cols)) for a in cols]
        rels.append(Relation(f"R{i + 1}", reduce(DataFrame.union, parts)))
    return JoinQuery(rels, attrs)


def extend_constant(q: JoinQuery, pendants: Sequence[tuple[str, str]], value: int = 0) -> JoinQuery:
    """One more relation (attribute, pendant) for each pair, its pendant column a single value."""
    rels = list(q.relations)
    for k, (a, p) in enumerate(pendants):
        own = next(r for r in rels if a in r.attrs)
        rels.append(Relation(f"P{k}", own.df.select(a).distinct().withColumn(p, F.lit(value).cast("long"))))
    return JoinQuery(rels, (*q.attrs, *(p for _, p in pendants)))


def cnf(spark: SparkSession, clauses: Sequence[Sequence[int]]) -> JoinQuery:
    """One relation per clause of three literals (+v or -v): the seven assignments that satisfy it."""
    rels = []
    for i, c in enumerate(clauses):
        cols = [f"v{abs(x)}" for x in c]
        if len(set(cols)) != 3:
            raise ValueError("a clause has three different variables")
        rows = [bits for bits in product((0, 1), repeat=3) if any(b == (x > 0) for b, x in zip(bits, c))]
        rels.append(Relation(f"C{i + 1}", spark.createDataFrame(rows, ", ".join(f"{a} int" for a in cols))))
    return JoinQuery(rels, sorted({a for r in rels for a in r.attrs}))


def cnf_by_key(keys: DataFrame, clauses: DataFrame, n: int = 3) -> JoinQuery:
    """A formula of n variables for each key. A clause (key, m) excludes the one assignment whose bits are m; relation C_m has, for each
    key, the assignments that the clause leaves over, which are all where the key has no such clause. keys: one column."""
    key = keys.columns[0]
    every = keys.distinct().withColumn("_m", F.explode(F.sequence(F.lit(0), F.lit(2**n - 1))))
    bits = [F.shiftright("_m", j).bitwiseAND(1).alias(f"v{j + 1}") for j in range(n)]
    told = clauses.toDF(key, "_m").select(key, F.col("_m").cast("int")).distinct()
    rels = [Relation(f"C{m}", every.join(told.filter(F.col("_m") == m), [key, "_m"], "left_anti").select(key, *bits)) for m in range(2**n)]
    return JoinQuery(rels, [key, *(f"v{j + 1}" for j in range(n))])


def fd_family(keys: DataFrame, n: int, k: int, primes: Sequence[int] = (7, 11, 13, 17)) -> JoinQuery:
    """Pairs R_i(a, b_i), S_i(b_i, z): a determines each b_i (a modulo a prime); z has one value, and so any b_i joins."""
    a = keys.toDF("a").filter(F.col("a") < n)
    rels = []
    for i in range(k):
        b = f"b{i + 1}"
        rels.append(Relation(f"R{i + 1}", a.select("a", (F.col("a") % primes[i]).alias(b))))
        rels.append(Relation(f"S{i + 1}", a.select((F.col("a") % primes[i]).alias(b), F.lit(0).cast("long").alias("z")).distinct()))
    return JoinQuery(rels)


def relaxed_tight(keys: DataFrame, n: int, size: int, block: str = "") -> list[Relation]:
    """n unary relations 1 .. size and one wide diagonal of size + 1 .. 2 size."""
    k = keys.toDF("j")
    ones = [_named(k.filter(F.col("j").between(1, size)), [f"a{block}{i + 1}"], f"U{block}{i + 1}") for i in range(n)]
    wide = k.filter(F.col("j").between(size + 1, 2 * size)).select(*(F.col("j").alias(f"a{block}{i + 1}") for i in range(n)))
    return [*ones, Relation(f"W{block}", wide)]
