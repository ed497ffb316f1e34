import itertools
import random

import numpy as np
import pytest
from coverjoin.operators import allbutone, anchored, baselines, cycles, fd, geometry, grid, kernel, keys, metrics, planner, relaxed, tighten
from coverjoin.operators.index import PrefixIndex, build_all_orders
from coverjoin.operators.reduction import answer
from coverjoin.plans import anchor, lp
from coverjoin.plans.model import FD, JoinQuery, Relation
from coverjoin.sources import generators
from helpers import brute, query, random_rows, rel, same


def shape(rng):
    n = rng.randint(2, 5)
    vs = [f"v{i}" for i in range(n)]
    es = [rng.sample(vs, rng.randint(1, min(n, 4))) for _ in range(rng.randint(1, 5))]
    vs = [v for v in vs if any(v in e for e in es)]
    return vs, [(e, random_rows(rng, len(e), rng.choice([0.3, 0.6, 0.9]))) for e in es]


@pytest.mark.parametrize("block", [1, 7, 1 << 20])
def test_kernel_fuzz(monkeypatch, block):
    monkeypatch.setattr(kernel, "BLOCK", block)
    rng = random.Random(5)
    for _ in range(150):
        vs, rels = shape(rng)
        from coverjoin.plans.model import Hypergraph

        h = Hypergraph(tuple(vs), tuple(frozenset(e) for e, _ in rels))
        tree, order = anchor.build(h, rng.sample(range(h.m), h.m))
        x = rng.choice([lp.trivial_cover(h), lp.optimal_cover(h, [len(r) for _, r in rels])])
        ks = [kernel.Sections(rels[i][0], list(np.array(sorted(rels[i][1]), np.int64).T)) for i in order]
        cols = kernel.solve(tree, [x[i] for i in order], ks)
        got = list(zip(*(cols[a].tolist() for a in vs)))
        assert set(got) == brute(rels, vs) and len(got) == len(set(got))


def test_kernel_makes_no_product(monkeypatch):
    """Two relations over one attribute: bindings of the one meet the other's rows through it."""
    made, repeat = [], np.repeat
    monkeypatch.setattr(np, "repeat", lambda x, n: made.append(repeat(x, n)) or made[-1])
    from coverjoin.plans.model import Hypergraph

    h = Hypergraph(tuple("abc"), (frozenset("ab"), frozenset("bc")))
    tree, order = anchor.build(h)
    k = np.arange(1000)
    rels = [kernel.Sections(e, [k, k]) for e in ("ab", "bc")]
    cols = kernel.solve(tree, lp.optimal_cover(h, [1000, 1000]), [rels[i] for i in order])
    assert sorted(cols["c"].tolist()) == k.tolist() and max(map(len, made)) <= 1000


@pytest.mark.parametrize("seed", range(5))
def test_general_method_fuzz(spark, seed):
    rng = random.Random(seed)
    vs, rels = shape(rng)
    q, want = query(spark, rels, vs), brute(rels, vs)
    same(anchored.join(q, order=rng.sample(range(len(rels)), len(rels))), want)
    same(grid.join(q, 8), want)
    t, x = tighten.tighten(q)
    assert lp.is_tight(t.hypergraph, x)


@pytest.mark.parametrize("n,kind", [(2, "balanced"), (3, "left"), (4, "balanced"), (4, "right")])
def test_all_but_one(spark, n, kind):
    rng = random.Random(n)
    vs = [f"v{i}" for i in range(n)]
    rels = [([a for a in vs if a != o], random_rows(rng, n - 1, 0.7)) for o in vs]
    q = query(spark, rels, vs)
    same(allbutone.join(q, kind), brute(rels, vs))
    if n > 2:
        assert all(ok for _, ok in allbutone.invariants(q, kind))


@pytest.mark.parametrize("tau", [None, 0, 1, 9])
def test_triangle_both_branches(spark, tau):
    r = {(a, 0) for a in range(30)} | {(a, a + 1) for a in range(30)}
    s = {(b, c) for b in range(31) for c in (b, 5)}
    t = {(a, c) for a in range(30) for c in range(0, 31, 5)}
    want = {(a, b, c) for a, b in r for b2, c in s if b == b2 and (a, c) in t}
    q = JoinQuery([rel(spark, "R", "ab", r), rel(spark, "S", "bc", s), rel(spark, "T", "ac", t)], list("abc"))
    for heavy in ("probe", "product"):
        same(allbutone.triangle(q, tau, heavy), want)
    sizes = metrics.split_sizes(q, tau).first()
    if tau:
        assert sizes["n_heavy"] < len(r) / tau and sizes["light_join"] <= tau * len(s)


@pytest.mark.parametrize("length,seed", [(4, 0), (5, 1), (5, 2), (6, 3), (7, 4)])
def test_cycles(spark, length, seed):
    rng = random.Random(seed)
    vs = [f"v{i}" for i in range(length)]
    rels = [([vs[i], vs[(i + 1) % length]], random_rows(rng, 2, rng.choice([0.3, 0.6, 0.9]))) for i in range(length)]
    want = brute(rels, vs)
    rng.shuffle(rels)
    for form in ("linked", "product"):
        same(cycles.cycle(query(spark, rels, vs), form), want)


def test_graph_with_star_cycle_unary_and_filter(spark):
    rng = random.Random(7)
    vs = list("abcde")
    rels = [(list(e), random_rows(rng, 2, 0.6)) for e in ("ab", "bc", "ca", "ad", "de", "ae")] + [(["b"], {(0,), (1,)})]
    same(cycles.graph_join(query(spark, rels, vs)), brute(rels, vs))


@pytest.mark.parametrize("r", [0, 1, 2])
def test_relaxed(spark, r):
    rng = random.Random(8)
    vs = list("abc")
    rels = [(list(e), random_rows(rng, len(e), 0.4)) for e in ("ab", "bc", "ac", "abc")]
    q = query(spark, rels, vs)
    want = set()
    import itertools

    for t in itertools.product(range(3), repeat=3):
        d = dict(zip(vs, t))
        ok = [set(e) for e, rows in rels if tuple(d[a] for a in e) in rows]
        if len(ok) >= 4 - r and set().union(*ok) == set(vs):
            want.add(t)
    same(relaxed.join(q, r), want)
    same(relaxed.join(q, r, share=False), want)
    same(relaxed.naive(q, r), want)


def test_relaxed_on_grid(spark, monkeypatch):
    """Where candidates outnumber what a grid moves they are never shuffled, and rows that several classes give come once."""
    rng = random.Random(4)
    domain = 12
    rels = [(list(e), {t for t in itertools.product(range(domain), repeat=2) if rng.random() < 0.9}) for e in ("ab", "bc", "ac")]
    rels.append((list("abc"), {t for t in itertools.product(range(domain + 1), repeat=3) if rng.random() < 0.02}))
    q = query(spark, rels, list("abc"))
    monkeypatch.setattr(relaxed, "settle", None)
    monkeypatch.setattr(grid, "CELLS", 2)
    monkeypatch.setattr(grid, "ROWS", 300)
    for r in (2, 3):
        want = set()
        for t in itertools.product(range(domain + 1), repeat=3):
            d = dict(zip("abc", t))
            ok = [set(e) for e, rows in rels if tuple(d[a] for a in e) in rows]
            if len(ok) >= 4 - r and set().union(*ok) == set("abc"):
                want.add(t)
        same(relaxed.join(q, r), want)


def test_baselines_agree(spark):
    rng = random.Random(9)
    vs = list("abcd")
    rels = [(list(e), random_rows(rng, 2, 0.6)) for e in ("ab", "bc", "cd", "da")]
    q, want = query(spark, rels, vs), brute(rels, vs)
    for df in (baselines.left_deep(q, [1, 0, 3, 2]), baselines.bushy(q, ((0, 1), (2, 3))), baselines.dp_order(q), baselines.catalyst_sql(q), baselines.join_project(q), baselines.brute(q), planner.join(q)):
        same(df, want)


def test_all_but_one_filters_in_steps(spark, monkeypatch):
    """Where relations are large, each set of rows is filtered step by step, and only the last step's input stays."""
    rng = random.Random(2)
    vs = list("abcd")
    rels = [([a for a in vs if a != o], random_rows(rng, 3, 0.7)) for o in vs]
    made, gone = [], []
    settle, drop = allbutone.settle, allbutone.drop
    monkeypatch.setattr(allbutone, "BROADCAST_ROWS", 0)
    monkeypatch.setattr(allbutone, "settle", lambda df, what="table": made.append(what) or settle(df, what))
    monkeypatch.setattr(allbutone, "drop", lambda df: gone.append(df) or drop(df))
    same(allbutone.join(query(spark, rels, vs)), brute(rels, vs))
    assert made.count("part") > len(gone) > 0


def test_bad_families_have_their_sizes(spark):
    keys = spark.range(200).toDF("k")
    trace = []
    q = generators.bad_triangle(keys, 16)
    assert baselines.left_deep(q, trace=trace).count() == 0 and trace[0] == 16 * 16 // 4 + 8
    assert allbutone.triangle(q).count() == 0
    q = generators.one_nonzero(keys, list("abcd"), 3)
    assert q.sizes() == [10] * 4 and allbutone.join(q).count() == anchored.join(q).count() == 13
    assert min(metrics.pairwise_sizes(q).values()) >= 16
    growth = metrics.growth(lambda n: generators.bad_triangle(keys, n), [20, 40, 80])
    assert growth[2][1] > 12 * growth[0][1] and growth[2][2] == 4 * growth[0][2]


def test_nulls_duplicates_and_empty(spark):
    r = Relation("R", spark.createDataFrame([(1, None), (1, 2), (None, 2)], "a long, b long"))
    s = Relation("S", spark.createDataFrame([(2, 5), (None, 6)], "b long, c long"))
    q = JoinQuery([r, s], ["a", "b", "c"])
    for df in (baselines.left_deep(q), anchored.join(q), anchored.join(q, order=[1, 0]), grid.join(q, 4)):
        same(df, {(1, 2, 5), (None, 2, 5)})
    e = rel(spark, "E", "ab", {(1, 2)})
    none = Relation("T", spark.createDataFrame([], "a long, c long"))
    q = JoinQuery([e, rel(spark, "S", "bc", {(2, 3)}), none], list("abc"))
    for how in ("triangle", "anchored", "grid", "auto"):
        assert planner.join(q, how).count() == 0
    with pytest.raises(TypeError):
        JoinQuery([e, Relation("X", spark.createDataFrame([("2",)], "b string"))])


def test_grid_cells_are_bounded(spark, monkeypatch):
    """Too few cells asked for: there are more, each with a part that fits."""
    monkeypatch.setattr(grid, "ROWS", 50)
    seen = []
    dealt = grid.by_cell
    monkeypatch.setattr(grid, "by_cell", lambda q, share, solve: seen.append(share) or dealt(q, share, solve))
    edges = {(a, b) for a in range(40) for b in range(40) if (a * 7 + b * 3) % 5 == 0}
    q = query(spark, [(list(e), edges) for e in ("ab", "bc", "ac")], list("abc"))
    same(grid.join(q, 2), {(a, b, c) for a, b in edges for c in range(40) if (b, c) in edges and (a, c) in edges})
    sent, cells = grid.replication(q, seen[0]), seen[0]["a"] * seen[0]["b"] * seen[0]["c"]
    assert cells > 2 and sent <= 50 * cells


def test_grid_of_other_types(spark):
    """Not-a-number equals itself and zero its negative, as in Spark's joins; a null in an attribute of one relation is a value."""
    import datetime
    from decimal import Decimal

    nan, old = float("nan"), datetime.date(1800, 1, 1)
    r = Relation("R", spark.createDataFrame([(nan, "x", 0.5), (1.0, "y", nan), (-0.0, "é", None), (1.0, "x", None)], "a double, b string, p double"))
    s = Relation("S", spark.createDataFrame([("x", Decimal("1.50"), old), ("é", Decimal("2.00"), None), ("y", Decimal("9.99"), None)], "b string, c decimal(9,2), t date"))
    t = Relation("T", spark.createDataFrame([(nan, Decimal("1.50"), True), (0.0, Decimal("2.00"), None), (1.0, Decimal("9.99"), False)], "a double, c decimal(9,2), f boolean"))
    q = JoinQuery([r, s, t])
    told = lambda df: sorted(repr(tuple(0.0 if x == 0 and isinstance(x, float) else x for x in row)) for row in df.select("a", "b", "c", "f", "p", "t").collect())
    assert told(grid.join(q, 8)) == told(baselines.left_deep(q)) and len(told(grid.join(q, 8))) == 3


def test_dependencies(spark):
    keys = spark.range(60).toDF("k")
    q = generators.fd_family(keys, 40, 3)
    fds = [FD(f"R{i}", "a", f"b{i}") for i in (1, 2, 3)]
    assert fd.closure(fds, ["a"]) == {"a", "b1", "b2", "b3"}
    assert fd.bound(q, fds) < fd.bound(q)
    aware, plain = fd.join(q, fds), fd.join(q)
    assert {tuple(r) for r in aware.collect()} == {tuple(r) for r in plain.collect()} and aware.count() == 40
    bad = spark.createDataFrame([(1, 1), (1, 2), (2, 1), (3, None)], "u long, v long")
    assert [tuple(r) for r in fd.violations(bad, "u", "v").collect()] == [(1, 2)]


def test_rules(spark):
    t = {"E": spark.createDataFrame([(1, 2), (2, 3), (1, 3), (3, 3)], "x long, y long"), "L": spark.createDataFrame([(1, "p"), (2, "q"), (3, "p")], "x long, t string")}
    same(answer("q(a, b, c) :- E(a, b), E(b, c), E(a, c)", t), {(1, 2, 3), (1, 3, 3), (2, 3, 3), (3, 3, 3)})
    same(answer("q(a, b) :- E(a, b), L(a, 'p')", t), {(1, 2), (1, 3), (3, 3)})
    same(answer("q(a) :- E(a, a), L(a, u)", t), {(3,)})
    assert answer("q(a, b) :- E(a, b), L(7, 'p')", t).count() == 0


def test_unique_assignment(spark):
    clauses = [(a, b * 2, c * 3) for a in (1, -1) for b in (1, -1) for c in (1, -1)]
    same(anchored.join(generators.cnf(spark, clauses[1:])), {(0, 0, 0)})
    assert anchored.join(generators.cnf(spark, clauses)).count() == 0


def test_geometry(spark):
    pts = spark.createDataFrame([(i % 3, i % 5, i % 7) for i in range(60)], "x long, y long, z long")
    r = geometry.hyperplane_check(pts, ["x", "y", "z"]).first()
    assert r["holds"] and r["d"] == 2 and r["points"] == 60
    full = spark.createDataFrame([(x, y, z) for x in range(3) for y in range(3) for z in range(3)], "x long, y long, z long")
    back = geometry.reconstruct([Relation(f, full.select(*f).distinct()) for f in ("xy", "yz", "xz")])
    assert back.count() == 27
    fam, d = geometry.replicate(query(spark, [(list("ab"), {(0, 0)}), (list("bc"), {(0, 0)}), (list("ac"), {(0, 0)})], list("abc")).hypergraph, lp.abo_cover(3))
    assert d == 2 and len(fam) == 3


def test_index(spark, tmp_path):
    r = rel(spark, "R", "abc", {(1, 1, 1), (1, 1, 2), (1, 2, 1), (2, 1, 1)})
    ix = PrefixIndex(r, ["a", "b", "c"])
    assert {tuple(x) for x in ix.count(["a"], ["b"]).collect()} == {(1, 2), (2, 1)} and ix.total(["b"]) == 2
    ix.save(f"file://{tmp_path}/ix")
    back = PrefixIndex.load(spark, f"file://{tmp_path}/ix", ["a", "b", "c"], "R")
    assert back.list(["a", "b"]).count() == 3 and back.member(r.df, ["a", "b", "c"]).count() == 4
    assert len(build_all_orders(r)) == 6


def test_general_method_reports(spark):
    rng = random.Random(10)
    rels = [(list(e), random_rows(rng, 2, 0.7)) for e in ("ab", "bc", "ac")]
    q = query(spark, rels, list("abc"))
    assert metrics.case_counts(q)
    assert all(b["rows"] <= b["budget"] + 1e-9 and b["worst"] <= 1 + 1e-9 for b in metrics.node_budget(q))
    assert metrics.bound_ratio(q, anchored.join(q).count()) <= 1
    with pytest.raises(planner.TooLarge):
        planner.join(q, max_output_rows=1)


def six(spark, rows=((0, 1, 0, 1, 0, 1), (1, 1, 0, 0, 2, 1), (2, 0, 1, 1, 0, 0), (0, 1, 1, 1, 2, 1), (1, 2, 0, 1, 0, 1))):
    edges = [[f"a{i}" for i in e] for e in ("1245", "1346", "123", "246", "356")]
    return query(spark, [(e, {tuple(r[int(a[1]) - 1] for a in e) for r in rows}) for e in edges], [f"a{i}" for i in "123456"])


@pytest.mark.parametrize("cover", [None, ("1/2", "1/2", "1/2", "1/2", "1/2")])
def test_plans_of_the_general_method_stay_small(spark, cover):
    """Each branching node starts at a table, so the plan grows with the tree and not with the number of paths in it."""
    q = six(spark)
    out = anchored.join(q, cover, order=[4, 3, 2, 1, 0])
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert len(plan) < 30_000 and plan.count("Relation [") < 60
    rels = [(list(r.attrs), {tuple(x) for x in r.df.collect()}) for r in q.relations]
    same(out, brute(rels, q.attrs))


def test_every_node_keeps_to_its_budget(spark):
    got = metrics.node_budget(six(spark), cover=["1/2"] * 5, order=[4, 3, 2, 1, 0])
    assert any(g["bound"] for g in got) and all(g["worst"] <= 1 + 1e-9 for g in got)
    assert got[-1]["bound"] == () and set(got[-1]["universe"]) == {f"a{i}" for i in "123456"}


def test_empty_branches_are_left_out(spark):
    q = query(spark, [(["a", "b"], {(1, 1)}), (["b", "c"], {(2, 2)}), (["a", "c"], {(1, 2)})], ["a", "b", "c"])
    assert anchored.join(q, ("1/2", "1/2", "1/2")).count() == 0


def test_products_are_counted_and_refused(spark, monkeypatch):
    from coverjoin import storage

    q = query(spark, [(["a"], {(i,) for i in range(5)}), (["b"], {(i,) for i in range(5)})], ["a", "b"])
    assert anchored.join(q).count() == 25
    monkeypatch.setattr(storage, "PRODUCT_ROWS", 24)
    with pytest.raises(storage.ProductTooLarge):
        anchored.join(q)


def test_settled_tables(spark):
    from pyspark.sql import functions as F

    from coverjoin import storage

    df = spark.range(10).select("id", F.struct("id").alias("s"), F.lit(None).alias("n"))
    assert storage.settle(df).count() == 10  # a column without a type is kept another way
    t = storage.settle(df.drop("n"))
    assert t.filter("s.id > 4").count() == 5 and not storage.shuffles(t) and storage.shuffles(t.groupBy("id").count())
    storage.drop(t)
    assert storage.narrow(df.select("id")) and not storage.narrow(df.select("s"))


def test_the_planner_weighs(spark):
    from coverjoin.operators import planner

    n = 40
    bad = [(e, {(0, j) for j in range(1, n)} | {(j, 0) for j in range(1, n)}) for e in (["a", "b"], ["b", "c"], ["a", "c"])]
    q = query(spark, bad, ["a", "b", "c"])
    cost = planner.weigh(q)
    assert cost["pairwise"] > cost["bound"] and planner.choose(q) == "triangle"
    same(planner.join(q), brute(bad, ["a", "b", "c"], n))
    chain = query(spark, [(["a", "b", "x"], {(i, i, i) for i in range(3)}), (["b", "c"], {(i, i) for i in range(3)}), (["c", "d", "y"], {(i, i, i) for i in range(3)})], ["a", "b", "c", "d", "x", "y"])
    cost = planner.weigh(chain)
    assert cost["pairwise"] <= cost["bound"] and planner.join(chain).count() == 3


def test_settled_tables_of_many_rows_are_not_broadcast(spark, monkeypatch):
    """A table of one value is small on disk; the size of its files says nothing about its rows in memory."""
    from coverjoin import storage

    monkeypatch.setattr(storage, "BROADCAST_ROWS", 100)
    many, few = (storage.settle(spark.range(n).selectExpr("id % 7 as k", "0 as z")) for n in (5000, 50))
    plan = lambda d: d._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan(spark.range(9).toDF("k").join(many, "k"))
    assert "BroadcastHashJoin" in plan(spark.range(9).toDF("k").join(few, "k"))
    kept = JoinQuery([Relation("R", spark.range(5000).toDF("a")), Relation("S", spark.range(50).toDF("a"))])
    kept.sizes()
    assert "BroadcastHashJoin" not in plan(kept.relations[0].df.join(kept.relations[0].df.toDF("a"), "a"))


def _nation_cycle(spark):
    cn, sn = {(c, c % 3) for c in range(9)}, {(s, s % 3) for s in range(6)}
    sp, cp = {(s, p) for s in range(6) for p in range(5) if (s + p) % 2}, {(c, p) for c in range(9) for p in range(5) if (c * p) % 3 != 1}
    want = {(c, n, s, p) for c, n in cn for s, m in sn if m == n for p in range(5) if (s, p) in sp and (c, p) in cp}
    return [rel(spark, "cn", "cn", cn), rel(spark, "sn", "sn", sn), rel(spark, "sp", "sp", sp), rel(spark, "cp", "cp", cp)], want


def test_relations_with_a_key_are_joined_first(spark):
    """The customers and suppliers of a nation never meet without the part that both have."""
    rels, want = _nation_cycle(spark)
    q = JoinQuery(rels, "cnsp")
    core, late = keys.reduced(q)
    assert sorted(sorted(r.attrs) for r in core.relations) == [list("cnp"), list("nps")] and not late
    for got in (cycles.even_cycle(q), keys.join(q), keys.join(q, anchored.join), cycles.even_cycle(q, "product")):
        same(got, want)


def test_keys_in_graphs(spark):
    rels, want = _nation_cycle(spark)
    cm, rich = {(c, c % 2) for c in range(9)}, {(s,) for s in (1, 2, 5)}
    q = JoinQuery([*rels, rel(spark, "cm", "cg", cm), rel(spark, "rich", "s", rich)], "cnspg")
    assert len(keys.reduced(q)[0].relations) == 2
    same(cycles.graph_join(q), {(c, n, s, p, c % 2) for c, n, s, p in want if (s,) in rich})


def test_pendants_with_a_key_are_put_off(spark):
    q = generators.extend_constant(generators.one_nonzero(spark.range(1, 5).toDF("k"), list("abc"), 4), [("a", "d")])
    core, late = keys.reduced(q)
    assert len(core.relations) == 3 and [a for _, a in late] == ["a"]
    same(keys.join(q, anchored.join), {(*t, 0) for t in {(0, 0, 0)} | {tuple(j if i == k else 0 for i in range(3)) for j in range(1, 5) for k in range(3)}})


def test_intermediates_are_counted_without_being_made(spark):
    """200,000 keys make 4 * 10^10 pairs, which no test could wait for."""
    n = 200_000
    trace: list[int] = []
    baselines.left_deep(generators.bad_triangle(spark.range(1, n + 1).toDF("k"), 2 * n), trace=trace)
    assert trace == [n * n + n, 0]
    q = generators.one_nonzero(spark.range(1, n + 1).toDF("k"), list("abc"), n)
    assert metrics.plan_gap(q)["largest"] == (n + 1) ** 2 + n


def test_formulas_by_key(spark):
    clauses = {(k, m) for k in range(6) for m in range(8) if m != k and (k != 3 or m % 2)}
    q = generators.cnf_by_key(spark.range(7).toDF("k"), spark.createDataFrame(sorted(clauses) + [(0, 1)], "k long, m long"))
    same(anchored.join(q), {(k, m & 1, m >> 1 & 1, m >> 2) for k in range(7) for m in range(8) if (k, m) not in clauses})


@pytest.mark.parametrize("shape", ["balanced", "left", "right"])
def test_the_smallest_pair_is_merged_first(spark, shape):
    """s and m have few values and follow from a and b: the join over (a, b) has 144 rows, the one over (s, m) more."""
    rows = [(a, b, (a + b) % 2, a * b % 3 % 2) for a in range(12) for b in range(12)]
    q = JoinQuery([rel(spark, e, e, {tuple(dict(zip("absm", r))[x] for x in e) for r in rows}) for e in ("bsm", "asm", "abm", "abs")], "absm")
    tree = allbutone.split_tree(allbutone.leaf_order(q, shape), shape)
    assert set(allbutone.first_pair(tree)) == {"s", "m"}
    same(allbutone.join(q, shape), set(rows))


def test_tables_that_nothing_reads_are_deleted(spark):
    from pathlib import Path

    rng = random.Random(8)
    cs, sp = ({(rng.randrange(6), rng.randrange(6)) for _ in range(20)} for _ in range(2))
    expected = {(c, c % 2, s, p) for c, p in cs for s, q in sp if p == q and c % 2 == s % 2}

    def made():
        r = {n: rel(spark, n, a, rows) for n, a, rows in (("cp", "cp", cs), ("sp", "sp", sp), ("cn", "cn", {(i, i % 2) for i in range(6)}), ("sn", "sn", {(i, i % 2) for i in range(6)}))}
        return JoinQuery([r["cn"], r["sn"], *(Relation(n, r[n].df.distinct()) for n in ("sp", "cp"))], list("cnsp"))

    there = lambda q: [Path(t._settled_at.removeprefix("file:")).exists() for t in q.own]
    for run in (lambda q, **k: cycles.cycle(q, **k), lambda q, **k: keys.join(q, anchored.join, **k)):
        same(run(kept := made()), expected)
        assert there(kept) == [True, True]
        same(run(gone := made(), spend=True), expected)
        assert there(gone) == [False, False]


@pytest.mark.parametrize("order", ["degrees", None])
def test_bindings_are_dealt_into_slices(spark, monkeypatch, order):
    rng = random.Random(9)
    rels = [(e, {(rng.randrange(12), rng.randrange(12)) for _ in range(70)}) for e in ("cs", "sp", "cp")]
    q = query(spark, rels, list("csp"))
    made, settle = [], anchored.settle
    monkeypatch.setattr(anchored, "settle", lambda d, what="table": made.append(what) or settle(d, what))
    monkeypatch.setattr(anchored, "SLICE_ROWS", 60)
    same(anchored.join(q, order=order), brute(rels, list("csp"), 12))
    assert made.count("slice") > 2


def test_the_least_degree_sum_is_bound_first(spark):
    # all meet in one s, and p is a key on both sides
    rels = [("cs", {(i, 0) for i in range(12)}), ("sp", {(0, i) for i in range(12)}), ("cp", {(i, i) for i in range(12)})]
    told = anchored.Counters(on=True)
    same(anchored.join(query(spark, rels, list("csp")), order="degrees", counters=told), {(i, 0, i) for i in range(12)})
    assert max(t["rows"] for t in told.rows) <= 12


@pytest.mark.parametrize("block", [3, 4096])
def test_triangles_of_points_that_share_buckets(spark, monkeypatch, block):
    monkeypatch.setattr(kernel, "BLOCK", 5)
    rng = random.Random(11)
    # ids come more than once, and a quarter of the points share all their buckets
    points = [(rng.randrange(-20, 20), [0, 0, 0] if i % 4 == 0 else [rng.randrange(6) for _ in range(3)]) for i in range(60)]
    edges = {(x, y) for x, a in points for y, b in points if x < y and any(p == q for p, q in zip(a, b))}
    out = grid.bucket_triangles(spark.createDataFrame([*points, (None, [0, 0, 0])], "v long, b array<int>"), block=block)
    same(out, {(x, y, z) for x, y in edges for w, z in edges if w == y and (x, z) in edges})
    assert "Join" not in out._jdf.queryExecution().optimizedPlan().toString()
    same(grid.bucket_triangles(spark.createDataFrame([], "v long, b array<int>")), set())


def test_few_packed_rows_are_sent_for_triangles_of_points(spark, monkeypatch):
    import re

    monkeypatch.setattr(grid, "TILE", 4, raising=False)
    rng, far = random.Random(12), 2**62
    points = [(rng.choice([-far, 0, far]) + rng.randrange(30), [rng.randrange(-9, 9), rng.choice([-(2**31), 7, 2**31 - 1]), i]) for i in range(200)]
    edges = {(x, y) for x, a in points for y, b in points if x < y and any(p == q for p, q in zip(a, b))}
    out = grid.bucket_triangles(spark.createDataFrame(points, "v long, b array<int>"))
    after = {x: {z for w, z in edges if w == x} for x, _ in edges}
    same(out, {(x, y, z) for x, y in edges for z in after.get(y, set()) & after[x]})
    # a row for each block, however many points it has
    sent = out._jdf.queryExecution().optimizedPlan().toString()
    assert len(re.findall("FlatMapGroupsInArrow", sent)) == 2 and "_buckets" in sent


def test_triangles_of_vectors_without_components(spark, tmp_path):
    import duckdb
    from coverjoin import workloads

    vectors = [(0, None), (1, None), (2, [-1.0] * 64), (3, [1.0] * 64), (4, [1.0] * 8), (5, [None] * 60 + [1.0] * 4), (6, [1.0] * 8 + [-1.0] * 56)]
    at = f"{tmp_path}/embeddings.parquet"
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>").coalesce(1).write.parquet(at)
    expected = duckdb.sql(workloads.ORACLES["triangle_embeddings"].replace("FROM embeddings", f"FROM '{at}/*.parquet'")).fetchall()
    assert (0, 1, 2) in expected
    same(workloads.QUERIES["triangle_embeddings"](spark, str(tmp_path)), set(expected))


def test_a_cycle_that_is_counted_leaves_no_tables(spark):
    from pathlib import Path

    from coverjoin import storage, workloads

    folder = Path(storage.scratch(spark, "x").removeprefix("file://")).parent
    before = set(folder.glob("*"))
    assert [r["n_relations"] for r in workloads.QUERIES["size_factor"](spark, "/root/testdata/sf0.001").collect()] == [4, 5, 6, 7]
    assert set(folder.glob("*")) == before


@pytest.mark.parametrize("name", ["graph_star_cycle", "graph_with_unary"])
def test_lines_and_orders_are_joined_once(spark, monkeypatch, name):
    from coverjoin import workloads

    settled, settle = [], workloads.settle
    monkeypatch.setattr(workloads, "settle", lambda df, what="table": settled.append(settle(df, what)) or settled[-1])
    out = workloads.QUERIES[name](spark, "/root/testdata/sf0.001")
    assert len(settled) == 1 and not any("lineitem" in f for f in out.inputFiles())
    assert out.count() == len(set(map(tuple, out.collect())))


def test_points_of_one_cell_meet_intervals_in_several_tasks(spark, monkeypatch):
    from pyspark.sql import functions as F

    from coverjoin import surround

    monkeypatch.setattr(surround, "CHUNK", 10, raising=False)
    # bounds of cells and intervals, two points that are equal, an empty interval, missing values
    points = [(i, 3 + i % 9 / 32) for i in range(90)] + [(0, 3.0), (90, -0.25), (91, -0.26), (92, 0.0), (93, 4.0), (94, None)]
    intervals = [(j, 3.0, 3.25) for j in range(5)] + [(5, -0.3, 0.0), (6, 2.9, 4.0), (7, 3.1, 3.1), (8, None, 1.0), (9, -0.25, 3.125)]
    left = spark.createDataFrame(points, "i long, x double").repartition(1)
    out = surround.interval_join(left, spark.createDataFrame(intervals, "j long, a double, z double"), "x", "a", "z", 0.25)
    expected = sorted((i, j) for i, x in points for j, a, z in intervals if None not in (x, a) and a <= x < z)
    assert sorted(map(tuple, out.select("i", "j").collect())) == expected
    assert out.filter("j = 0").select(F.spark_partition_id().alias("t")).distinct().count() > 3
    with pytest.raises(ValueError):
        surround.interval_join(left, left, "x", "x", "x", 0.3)


def test_the_engines_plan_runs_in_rounds_without_a_shuffle_between_joins(spark, monkeypatch):
    for name, n in (("ROUND_ROWS", 100), ("HELD_ROWS", 20), ("SENT_ROWS", 60), ("ROUND_CELLS", 2)):
        monkeypatch.setattr(baselines, name, n, raising=False)
    rng = random.Random(13)
    rels = [(e, {(rng.randrange(12) if i else rng.randrange(5), rng.randrange(5) if i != 1 else rng.randrange(12)) for _ in range(90)}) for i, e in enumerate(("cs", "sp", "cp"))]
    # all meet in few s: the optimiser, told so, joins over it last
    plans, settle = [], baselines.settle
    monkeypatch.setattr(baselines, "settle", lambda d, what="table": plans.append((what, d._jdf.queryExecution().executedPlan().toString())) or settle(d, what), raising=False)
    same(baselines.catalyst_sql(query(spark, rels, list("csp"))), brute(rels, list("csp"), 12))
    rounds = [p for what, p in plans if what == "round"]
    assert len(rounds) > 2 and all(p.count("Join") == 2 and p.count("Exchange") == 3 and "Sort" not in p for p in rounds)
    assert spark.conf.get("spark.sql.shuffle.partitions") == "3"
