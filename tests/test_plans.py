import math
import random
from fractions import Fraction

import pytest
from coverjoin.operators import allbutone, cycles, relaxed, tighten
from coverjoin.plans import anchor, bounds, limits, lp, parse
from coverjoin.plans.model import Const, Hypergraph

H = Fraction(1, 2)
TRIANGLE = Hypergraph(("a", "b", "c"), tuple(map(frozenset, ("ab", "bc", "ac"))))
EXAMPLE = Hypergraph(tuple("123456"), tuple(map(frozenset, ("1245", "1346", "123", "246", "356"))))


def random_graph(rng, edges=2):
    n = rng.randint(2, 5)
    vs = [f"v{i}" for i in range(n)]
    es = [frozenset(rng.sample(vs, rng.randint(1, min(edges, n)))) for _ in range(rng.randint(2, 7))]
    return Hypergraph(tuple(v for v in vs if any(v in e for e in es)), tuple(es))


def test_known_covers():
    assert lp.optimal_cover(TRIANGLE, [100, 100, 100]) == (H, H, H)
    assert lp.optimal_cover(EXAMPLE, [1875, 21875, 3125, 175, 525]) == (H, *(Fraction(1, 4),) * 3, H)
    abo = Hypergraph(tuple("abcd"), tuple(map(frozenset, ("bcd", "acd", "abd", "abc"))))
    assert lp.optimal_cover(abo, [50] * 4) == lp.abo_cover(4) == lp.regular_cover(abo)
    assert lp.is_cover(EXAMPLE, lp.trivial_cover(EXAMPLE)) and not lp.is_cover(TRIANGLE, (H, H, 0))


def test_optimal_cover_is_cheapest_of_many():
    rng = random.Random(1)
    for _ in range(80):
        h = random_graph(rng, 4)
        sizes = [rng.randint(1, 1000) for _ in h.edges]
        x = lp.optimal_cover(h, sizes)
        assert lp.is_cover(h, x)
        for _ in range(40):
            y = [Fraction(rng.randint(0, 4), 4) for _ in h.edges]
            if lp.is_cover(h, y):
                assert lp.cost(x, sizes) <= lp.cost(y, sizes) + 1e-9


def test_graph_covers_fall_into_stars_and_odd_cycles():
    rng = random.Random(2)
    for _ in range(60):
        h = random_graph(rng)
        h = Hypergraph(h.vertices, tuple(e for e in h.edges))
        d = cycles.decompose(h, lp.optimal_cover(h, [rng.randint(2, 500) for _ in h.edges]))
        assert all(len(c) % 2 for c in d.cycles)
        for s in d.stars:
            if len(s) > 1:
                assert frozenset.intersection(*(h.edges[i] for i in s))


def test_bounds():
    assert bounds.floor_bound(TRIANGLE, [4, 4, 4]) == 8
    assert bounds.floor_bound(EXAMPLE, [1875, 21875, 3125, 175, 525]) == 328125
    assert bounds.integral_cover_bound(TRIANGLE, [2, 3, 4]) == 6 and bounds.product_bound([2, 3, 4]) == 24
    assert bounds.cover_bound(TRIANGLE, [0, 5, 5]) == 0 == bounds.floor_bound(TRIANGLE, [0, 5, 5])
    assert bounds.integer_root(10**30, 3) == 10**10 and bounds.integer_root(10**30 - 1, 3) == 10**10 - 1
    with pytest.raises(ValueError):
        bounds.cover_bound(TRIANGLE, [5, 5, 5], (H, H, 0))


def test_worked_example_tree():
    tree, order = anchor.build(EXAMPLE)
    assert (tree.rank, tree.left.universe, tree.right.universe) == (4, frozenset("124"), frozenset("356"))
    assert anchor.attribute_order(EXAMPLE, tree, order) == list("142536")


def test_attribute_order_loses_nothing():
    rng = random.Random(3)
    hard = Hypergraph(tuple("0234") + ("1",), tuple(map(frozenset, ("034", "034", "023", "134"))))
    for h in [hard] + [random_graph(rng, 4) for _ in range(100)]:
        order = rng.sample(range(h.m), h.m)
        tree, order = anchor.build(h, order)
        assert sorted(anchor.attribute_order(h, tree, order)) == sorted(h.vertices)
        for t in anchor.nodes(tree):
            if t.left:
                assert t.left.universe == t.universe - h.edges[order[t.rank]]
            if t.right:
                assert t.right.universe == t.universe & h.edges[order[t.rank]]


def test_tight_cover():
    rng = random.Random(4)
    for _ in range(60):
        h = random_graph(rng, 4)
        x = [Fraction(rng.randint(0, 4), 2) for _ in h.edges]
        if lp.is_cover(h, x):
            got = tighten.tighten_edges(h, x)
            for v in h.vertices:
                assert sum((w for _, e, w in got if v in e), Fraction(0)) == 1
            assert len(got) <= h.m + h.n * h.m


def test_light_threshold_is_exact():
    for sizes, d in (([7, 9, 11], 4), ([100, 100, 100], 7), ([5, 5, 5, 5], 3)):
        k = allbutone.light_threshold(sizes, d)
        total, n = math.prod(sizes), len(sizes)
        assert (k * d) ** (n - 1) >= total > ((k - 1) * d) ** (n - 1)


def test_gap_witness():
    assert limits.gap_witness(TRIANGLE)[0] == frozenset("abc")
    assert limits.gap_witness(Hypergraph(tuple("abcd"), tuple(map(frozenset, ("ab", "bc", "cd"))))) is None


def test_relaxed_families():
    h = Hypergraph(("c", "s", "p"), tuple(map(frozenset, ("cs", "sp", "cp", "csp"))))
    assert [len(relaxed.covering_sets(h, r)) for r in range(4)] == [1, 5, 11, 12]
    assert [len(relaxed.minimal_sets(h, r)) for r in range(4)] == [1, 4, 6, 4]
    for r in range(4):
        assert relaxed.class_bound(h, [20, 30, 40, 50], r) <= relaxed.sum_bound(h, [20, 30, 40, 50], r)


def test_parse():
    r = parse.parse_rule("q(x) :- E(x, y), T(y, 'it''s', 3, 2.5)")
    assert r.head == ("x",) and r.body[1].terms == ("y", Const("it's"), Const(3), Const(2.5))
    assert parse.parse_natural("a NATURAL JOIN b natural join c.d;") == ["a", "b", "c.d"]
    for bad in ("q(x) :- E(y, z)", "q(x) E(x)", "q(x) :- E(x"):
        with pytest.raises(ValueError):
            parse.parse_rule(bad)
