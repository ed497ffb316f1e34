"""First method: instances in which relation i omits exactly attribute i. Light join keys are joined, heavy ones deferred."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import JoinQuery, Relation
from ..storage import BROADCAST_ROWS, ProductTooLarge, drop, freeing, product, settle, small

def semi(df: DataFrame, r: Relation, attrs=None) -> DataFrame:
    on = [a for a in (attrs or r.attrs) if a in df.columns]
    return df.join(r.df.select(*on), on, "left_semi") if on else df


def prune(df: DataFrame, rels) -> DataFrame:
    return reduce(semi, rels, df)


def prune_in_steps(df: DataFrame, rels) -> DataFrame:
    """The same rows as by prune(). What each filter reads is settled and the table before it deleted, so that of many rows the shuffle
    files of one step at a time are on disk."""
    before = None
    for r in rels:
        now = settle(df, "part")
        if before is not None:
            drop(before)
        df, before = semi(now, r), now
    return df


# -- three attributes


@dataclass(frozen=True)
class Split:
    """Heavy keys have more than num/den rows (den = 0: none are heavy)."""

    num: int
    den: int
    root: bool  # compare squares: degree² * den > num

    def heavy(self, deg):
        if self.den == 0:
            return F.lit(False)
        if self.root:
            return deg.cast("decimal(38,0)") * deg.cast("decimal(19,0)") > F.lit(self.num // self.den).cast("decimal(38,0)")
        return deg > self.num // self.den


def split_at(sizes: tuple[int, int, int], tau=None) -> Split:
    """tau² = #R * #T / #S unless a number is given; squares are compared, so no root is taken."""
    nr, ns, nt = sizes
    return Split(nr * nt, ns, True) if tau is None else Split(math.floor(tau), 1, False)


def roles(q: JoinQuery, split: str | None = None) -> tuple[Relation, Relation, Relation, str, str, str]:
    """(R(A,B), S(B,C), T(A,C), A, B, C) for the split attribute B."""
    if q.hypergraph.n != 3 or not q.hypergraph.is_all_but_one():
        raise ValueError("not a triangle")
    b = split or q.attrs[1]
    r, s = [x for x in q.relations if b in x.attrs]
    t = next(x for x in q.relations if b not in x.attrs)
    return r, s, t, next(x for x in r.attrs if x != b), b, next(x for x in s.attrs if x != b)


def split_costs(q: JoinQuery) -> dict[str, int]:
    """For each attribute, the exact size of the pairwise join over it: sum of products of degrees."""
    out = {}
    for b in q.attrs:
        r, s = [x for x in q.relations if b in x.attrs]
        with freeing(q.spark):
            d = r.df.groupBy(b).agg(F.count("*").alias("x")).join(s.df.groupBy(b).agg(F.count("*").alias("y")), b)
            out[b] = int(d.agg(F.coalesce(F.sum(F.col("x").cast("decimal(19,0)") * F.col("y").cast("decimal(19,0)")), F.lit(0))).first()[0])
    return out


def triangle(q: JoinQuery, tau=None, heavy: str = "probe", split: str | None = None) -> DataFrame:
    """Triangle by heavy and light keys of the split attribute B.

    Keys of R(A,B) with more than tau rows are heavy: there are fewer than #R / tau. Light rows are joined with S(B,C), which
    gives at most tau * #S rows; heavy keys meet T(A,C), by probing T with the heavy rows of R (never more than the
    product), or as a product with T where ``heavy`` is "product". What each side lacks is a semijoin. The sides are disjoint.
    """
    r, s, t, a, b, c = roles(q, split)
    sizes = {x.name: n for x, n in zip(q.relations, q.sizes())}
    if 0 in sizes.values():
        return q.empty()
    cut = split_at((sizes[r.name], sizes[s.name], sizes[t.name]), tau)
    heavy_keys = r.df.groupBy(b).agg(F.count("*").alias("_deg")).filter(cut.heavy(F.col("_deg"))).select(b)
    tau_value = math.isqrt(cut.num // cut.den) if cut.root and cut.den else cut.num
    most = sizes[r.name] // max(1, tau_value)  # there are no more heavy keys than this
    keys = small(heavy_keys, most)
    light = semi(r.df.join(keys, b, "left_anti").join(s.df, b), t)
    if heavy == "product":
        heavy_keys = settle(heavy_keys, "heavy")
        try:
            side = semi(semi(product(t.df, heavy_keys, sizes[t.name]), r), s)
        except ProductTooLarge as e:
            raise ProductTooLarge(f"heavy keys times {t.name}: {e}; heavy='probe' makes no product") from None
    elif heavy == "probe":
        side = semi(r.df.join(keys, b, "left_semi").join(t.df, a), s)
    else:
        raise ValueError("heavy is 'probe' or 'product'")
    return light.select(*q.attrs).unionByName(side.select(*q.attrs))


# -- n attributes


@dataclass(frozen=True)
class SplitNode:
    """Node of a binary tree over the attributes; ``leaves`` are those below it, its label is all the others."""

    leaves: tuple[str, ...]
    left: SplitNode | None = None
    right: SplitNode | None = None


def split_tree(attrs: tuple[str, ...], shape: str = "balanced") -> SplitNode:
    if len(attrs) == 1:
        return SplitNode(attrs)
    cut = {"balanced": len(attrs) // 2, "left": len(attrs) - 1, "right": 1}[shape]
    return SplitNode(attrs, split_tree(attrs[:cut], shape), split_tree(attrs[cut:], shape))


def first_pair(node: SplitNode) -> tuple[str, ...]:
    """The two leaves that are merged before any others."""
    if len(node.leaves) == 2:
        return node.leaves
    return first_pair(node.left if len(node.left.leaves) > 1 else node.right)


def leaf_order(q: JoinQuery, shape: str) -> tuple[str, ...]:
    """The attributes, dealt to the leaves so that the pair merged first is the one whose relations' join has the fewest rows by
    estimate: where all its keys are light, it has the whole join. One job of sketches."""
    sizes, pairs = q.sizes(), list(combinations(q.attrs, 2))
    gap = {next(iter(set(q.attrs) - set(r.attrs))): i for i, r in enumerate(q.relations)}
    label = lambda p: [a for a in q.attrs if a not in p]
    told = [q.relations[gap[a]].df.agg(F.lit(k).alias("k"), F.approx_count_distinct(F.struct(*label(p))).alias("n")) for k, p in enumerate(pairs) for a in p]
    distinct = {k: 1 for k in range(len(pairs))}
    for row in reduce(DataFrame.unionByName, told).collect():
        distinct[row["k"]] = max(distinct[row["k"]], row["n"])
    best = min(range(len(pairs)), key=lambda k: sizes[gap[pairs[k][0]]] * sizes[gap[pairs[k][1]]] / distinct[k])
    place, rest = first_pair(split_tree(q.attrs, shape)), iter(label(pairs[best]))
    first = dict(zip(place, pairs[best]))
    return tuple(first[a] if a in first else next(rest) for a in q.attrs)


def light_threshold(sizes: list[int], d_right: int) -> int:
    """Least k with (k * d_right) ** (n-1) >= product of the sizes, which is the rounded-up share of the bound per right row."""
    n, total = len(sizes), math.prod(sizes)
    lo, hi = 0, 1
    while (hi * d_right) ** (n - 1) < total:
        lo, hi = hi, hi * 2
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if (mid * d_right) ** (n - 1) >= total else (mid + 1, hi)
    return lo


@dataclass
class NodeSize:
    leaves: tuple[str, ...]
    emitted: int
    deferred: int


@dataclass
class Part:
    """What a node hands up: sets of rows over all attributes, each with the relations it agrees with by construction, and a set
    of ``rows`` partial rows over the node's label. A row of the join is in one of the sets, or its label part is in ``open``."""

    done: list[tuple[DataFrame, frozenset[str]]]
    open: DataFrame
    rows: int
    exact: str | None = None  # the relation that ``open`` is, at a leaf


def join(q: JoinQuery, shape: str = "balanced", trace: list[NodeSize] | None = None) -> DataFrame:
    """All-but-one join over a binary split tree.

    At an inner node the left side's partial rows are counted per key of the label; keys that the right side has, too, are
    joined at once if their count keeps the joined rows within the bound, and handed up else. A child that hands nothing up has all rows of
    the join already, so its sibling is not looked at. The root joins what is left through the relation that shares attributes with both
    sides. In the end each set is filtered by the relations that it was not made from.
    The pair of relations with the smallest join by estimate is merged first.
    One count per inner node and the sketches for that reach the driver. trace: visits every node and collects exact set sizes (extra jobs).
    """
    if not q.hypergraph.is_all_but_one():
        raise ValueError("not an all-but-one query")
    sizes = q.sizes()
    if 0 in sizes:
        return q.empty()
    if len(q.attrs) == 2:
        a, b = q.relations
        return product(a.df, b.df, a.size, b.size).select(*q.attrs)
    by_gap = {next(iter(set(q.attrs) - set(r.attrs))): r for r in q.relations}

    def note(node, part: Part) -> Part:
        if trace is not None:
            trace.append(NodeSize(node.leaves, sum(d.count() for d, _ in part.done), part.rows))
        return part

    def merge(node: SplitNode, left: Part, right: Part) -> Part:
        """Light keys joined, heavy keys left open."""
        label = [a for a in q.attrs if a not in node.leaves]
        done = [*left.done, *right.done]
        if right.rows == 0:
            return Part(done, left.open.select(*label).limit(0), 0)
        most = light_threshold(sizes, right.rows) - 1
        fan = settle(left.open.groupBy(*label).agg(F.count("*").alias("_fan")).join(right.open.select(*label), label, "left_semi"), "fan")
        few, many = (n or 0 for n in fan.agg(F.count_if(F.col("_fan") <= most), F.count_if(F.col("_fan") > most)).first())
        if few:
            rows = left.open if not many else left.open.join(fan.filter(F.col("_fan") <= most).select(*label), label, "left_semi")
            done.append((rows.join(right.open, label).select(*q.attrs), frozenset(x.exact for x in (left, right) if x.exact)))
        return Part(done, fan.filter(F.col("_fan") > most).select(*label), many)

    def through(node: SplitNode, left: Part, right: Part) -> Part:
        """The root: labels of the two sides are disjoint. A relation of the side with more leaves has all of the one label and all but one
        attribute of the other: joining through it gives no more rows than the product, which the bound allows."""
        done = [*left.done, *right.done]
        if left.rows and right.rows:
            wide, low, high = (node.right, right, left) if len(node.right.leaves) > 1 else (node.left, left, right)
            link = min((by_gap[a] for a in wide.leaves), key=lambda r: r.size)
            rows = semi(link.df, Relation("", low.open)) if low.exact != link.name else link.df
            done.append((rows.join(high.open, [a for a in high.open.columns if a in link.attrs]).select(*q.attrs), frozenset([link.name, *(x.exact for x in (left, right) if x.exact)])))
        return Part(done, left.open.limit(0), 0)

    def solve(node: SplitNode, root: bool = False) -> Part:
        if node.left is None:
            r = by_gap[node.leaves[0]]
            return Part([], r.df, r.size, r.name)
        left = solve(node.left)
        if left.rows == 0 and trace is None:
            return left
        right = solve(node.right)
        if right.rows == 0 and trace is None:
            return right
        return note(node, (through if root else merge)(node, left, right))

    done = solve(split_tree(leaf_order(q, shape), shape), True).done
    if not done:
        return q.empty()
    filtered = prune_in_steps if max(sizes) > BROADCAST_ROWS else prune
    out = reduce(DataFrame.unionByName, [filtered(d, [r for r in q.relations if r.name not in known]) for d, known in done])
    return (out.distinct() if len(done) > 1 else out).select(*q.attrs)


def invariants(q: JoinQuery, shape: str = "balanced") -> list[tuple[NodeSize, bool]]:
    """Set sizes per inner node and whether they keep to the method's limits: emitted rows at most (leaves - 1) * P, deferred
    at most min(least size, product / P ** (leaves - 1))."""
    trace: list[NodeSize] = []
    join(q, shape, trace)
    sizes, n = q.sizes(), len(q.attrs)
    p = math.prod(sizes) ** (1 / (n - 1))
    return [(t, t.emitted <= (len(t.leaves) - 1) * p * (1 + 1e-9) and t.deferred <= min(min(sizes), math.prod(sizes) / p ** (len(t.leaves) - 1)) * (1 + 1e-9)) for t in trace]
