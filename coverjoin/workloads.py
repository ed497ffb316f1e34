"""The registered queries of the join methods, each beside its SQL (DuckDB's dialect)."""

from __future__ import annotations

import math
from collections.abc import Callable
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions.scalar import sign_bucket
from .operators import allbutone, anchored, baselines, cycles, fd, geometry, grid, metrics, planner, relaxed, tighten
from .operators.index import PrefixIndex, intersect_small
from .operators.keys import join as keyed_join
from .operators.reduction import answer
from .plans import bounds, lp
from .plans.model import FD, Hypergraph, JoinQuery, Relation
from .sources import generators
from .sources.relations import json_attr, keyed, load, relation
from .storage import drop, passing, scratch, settle

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


# -- relations on the tables

OL = "lineitem JOIN orders ON l_orderkey = o_orderkey"
REL = {
    "cs": f"SELECT DISTINCT o_custkey AS c, l_suppkey AS s FROM {OL}",
    "sp": f"SELECT DISTINCT l_suppkey AS s, l_partkey AS p FROM {OL}",
    "cp": f"SELECT DISTINCT o_custkey AS c, l_partkey AS p FROM {OL}",
    "edges": "SELECT DISTINCT least(u, v) AS x, greatest(u, v) AS y FROM (SELECT user_id AS u, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS v FROM events) WHERE u <> v",
    "cn": "SELECT c_custkey AS c, c_nationkey AS n FROM customer",
    "sn": "SELECT s_suppkey AS s, s_nationkey AS n FROM supplier",
}


def ol(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "lineitem").join(load(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))


def facts(spark: SparkSession, d: str, lines: DataFrame | None = None) -> dict[str, Relation]:
    j = ol(spark, d) if lines is None else lines
    return {"cs": relation(j, {"c": "o_custkey", "s": "l_suppkey"}, "cs"), "sp": relation(j, {"s": "l_suppkey", "p": "l_partkey"}, "sp"), "cp": relation(j, {"c": "o_custkey", "p": "l_partkey"}, "cp")}


def w01(spark: SparkSession, d: str) -> JoinQuery:
    r = facts(spark, d)
    return JoinQuery([r["cs"], r["sp"], r["cp"]], ["c", "s", "p"])


TRIANGLE = f"WITH cs AS ({REL['cs']}), sp AS ({REL['sp']}), cp AS ({REL['cp']}) "
W01_SQL = TRIANGLE + "SELECT cs.c, cs.s, cp.p FROM cs JOIN cp ON cp.c = cs.c JOIN sp ON sp.s = cs.s AND sp.p = cp.p"


def edges(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events")
    nxt = F.lead("user_id").over(W.partitionBy(F.date_trunc("hour", F.col("ts").cast("timestamp"))).orderBy("ts", "event_id"))
    return e.select(F.col("user_id").alias("u"), nxt.alias("v")).filter("u <> v").select(F.least("u", "v").alias("x"), F.greatest("u", "v").alias("y")).distinct()


def three(e: DataFrame) -> JoinQuery:
    """Triangles a < b < c of a graph of edges x < y."""
    return JoinQuery([Relation("R", e.toDF("a", "b")), Relation("S", e.toDF("b", "c")), Relation("T", e.toDF("a", "c"))])


EDGE_TRIANGLE = "SELECT r.x AS a, r.y AS b, s.y AS c FROM e r JOIN e s ON s.x = r.y JOIN e t ON t.x = r.x AND t.y = s.y"
W04_SQL = f"WITH e AS ({REL['edges']}) {EDGE_TRIANGLE}"


def keys(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "part").select(F.col("p_partkey").cast("long").alias("k"))


# -- triangles


@query("triangle_cust_supp_part", W01_SQL)
def _(spark, d):
    return planner.join(w01(spark, d))


@query("triangle_heavy_probe", W01_SQL)
def _(spark, d):
    return allbutone.triangle(w01(spark, d), heavy="probe", split="s")


@query("triangle_heavy_product", W01_SQL)
def _(spark, d):
    return allbutone.triangle(w01(spark, d), heavy="product", split="s")


@query("triangle_handoff", W04_SQL)
def _(spark, d):
    return allbutone.triangle(three(edges(spark, d)))


@query("triangle_tau_sweep", f"SELECT t.tau, count(*) AS n FROM ({W04_SQL}) CROSS JOIN (VALUES (1), (20), (1000)) AS t(tau) GROUP BY t.tau")
def _(spark, d):
    q = three(edges(spark, d))
    out = [allbutone.triangle(q, tau=t).groupBy().agg(F.count("*").alias("n")).select(F.lit(t).alias("tau"), "n") for t in (1, 20, 1000)]
    return out[0].union(out[1]).union(out[2])


@query("triangle_split_sizes", TRIANGLE + """, n AS (SELECT (SELECT count(*) FROM cs) AS nr, (SELECT count(*) FROM sp) AS ns, (SELECT count(*) FROM cp) AS nt),
    deg AS (SELECT s, count(*) AS x FROM cs GROUP BY s), fan AS (SELECT s, count(*) AS y FROM sp GROUP BY s),
    bothsides AS (SELECT x, coalesce(y, 0) AS y, x * x * (SELECT ns FROM n) > (SELECT nr * nt FROM n) AS heavy FROM deg LEFT JOIN fan USING (s))
    SELECT CAST(sum(CASE WHEN heavy THEN 1 ELSE 0 END) AS BIGINT) AS n_heavy, CAST(sum(CASE WHEN heavy THEN 1 ELSE 0 END) * (SELECT nt FROM n) AS BIGINT) AS heavy_product,
    CAST(sum(CASE WHEN heavy THEN 0 ELSE x * y END) AS BIGINT) AS light_join FROM bothsides""")
def _(spark, d):
    return metrics.split_sizes(w01(spark, d), split="s")


@query("triangle_event_props", """WITH e AS (SELECT user_id AS u, CAST(json_extract(props, '$.k') AS INTEGER) AS k, event_type AS t FROM events),
    r AS (SELECT DISTINCT u, k FROM e), s AS (SELECT DISTINCT k, t FROM e), w AS (SELECT DISTINCT u, t FROM e)
    SELECT r.u, r.k, s.t FROM r JOIN s USING (k) JOIN w ON w.u = r.u AND w.t = s.t""")
def _(spark, d):
    e = load(spark, d, "events").select(F.col("user_id").alias("u"), json_attr("props", "k").alias("k"), F.col("event_type").alias("t"))
    return planner.join(JoinQuery([relation(e, ["u", "k"], "r"), relation(e, ["k", "t"], "s"), relation(e, ["u", "t"], "w")], ["u", "k", "t"]))


@query("triangle_doc_facets", """WITH d AS (SELECT lang AS l, source AS s, CAST(quality AS INTEGER) AS q FROM documents JOIN labels USING (doc_id)),
    r AS (SELECT DISTINCT l, s FROM d), t AS (SELECT DISTINCT s, q FROM d), w AS (SELECT DISTINCT l, q FROM d)
    SELECT r.l, r.s, t.q FROM r JOIN t USING (s) JOIN w ON w.l = r.l AND w.q = t.q""")
def _(spark, d):
    x = load(spark, d, "documents").select("doc_id", "lang", "source").join(load(spark, d, "labels"), "doc_id").select(F.col("lang").alias("l"), F.col("source").alias("s"), F.col("quality").cast("int").alias("q"))
    return planner.join(JoinQuery([relation(x, ["l", "s"], "r"), relation(x, ["s", "q"], "t"), relation(x, ["l", "q"], "w")], ["l", "s", "q"]))


BITS = " + ".join(f"(CASE WHEN embedding[b * 8 + {j + 1}] >= 0 THEN {1 << j} ELSE 0 END)" for j in range(8))
BANDS = f"SELECT vec_id AS v, b, {BITS} AS bits FROM embeddings CROSS JOIN (SELECT unnest(range(8)) AS b)"


def bands(spark: SparkSession, d: str) -> DataFrame:
    """Vectors with the sign bits of their bands; a component that is not there counts as negative."""
    return load(spark, d, "embeddings").select(F.col("vec_id").alias("v"), F.array(*(F.coalesce(sign_bucket(F.col("embedding"), 8 * b, 8), F.lit(0)) for b in range(8))).alias("bits"))


@query("triangle_embeddings", f"WITH g AS ({BANDS}), e AS (SELECT DISTINCT r.v AS x, s.v AS y FROM g r JOIN g s ON r.b = s.b AND r.bits = s.bits AND r.v < s.v) {EDGE_TRIANGLE}")
def _(spark, d):
    return grid.bucket_triangles(bands(spark, d))


@query("triangle_per_vertex", f"WITH e AS ({REL['edges']}), t AS ({EDGE_TRIANGLE}) SELECT v, count(*) AS n_triangles FROM (SELECT a AS v FROM t UNION ALL SELECT b FROM t UNION ALL SELECT c FROM t) GROUP BY v")
def _(spark, d):
    t = allbutone.triangle(three(edges(spark, d)))
    return t.select(F.explode(F.array("a", "b", "c")).alias("v")).groupBy("v").agg(F.count("*").alias("n_triangles"))


# -- covers and bounds

COUNTS = TRIANGLE + ", n AS (SELECT (SELECT count(*) FROM cs) AS r, (SELECT count(*) FROM sp) AS s, (SELECT count(*) FROM cp) AS t) "


@query("lp_triangle_bound", COUNTS + "SELECT CAST(floor(least(sqrt(CAST(r AS DOUBLE) * s * t), CAST(r AS DOUBLE) * s, CAST(r AS DOUBLE) * t, CAST(s AS DOUBLE) * t)) AS BIGINT) AS bound FROM n")
def _(spark, d):
    q = w01(spark, d)
    return spark.createDataFrame([(bounds.floor_bound(q.hypergraph, q.sizes()),)], "bound long")


@query("bound_ladder", COUNTS + """SELECT 'integral' AS measure, CAST(least(r * s, r * t, s * t) AS DOUBLE) AS value FROM n
    UNION ALL SELECT 'product', CAST(r AS DOUBLE) * s * t FROM n UNION ALL SELECT 'cover', floor(least(sqrt(CAST(r AS DOUBLE) * s * t), CAST(r AS DOUBLE) * s, CAST(r AS DOUBLE) * t, CAST(s AS DOUBLE) * t)) FROM n""")
def _(spark, d):
    return spark.createDataFrame(list(planner.bound_report(w01(spark, d)).items()), "measure string, value double")


@query("bound_report", f"SELECT count(*) AS n_rows, CAST(TRUE AS BOOLEAN) AS within FROM ({W04_SQL})")
def _(spark, d):
    q = three(edges(spark, d))
    b = bounds.floor_bound(q.hypergraph, q.sizes())
    return allbutone.triangle(q).agg(F.count("*").alias("n_rows")).withColumn("within", F.col("n_rows") <= b)


@query("sizes", TRIANGLE + "SELECT 'cs' AS relation, count(*) AS n_rows FROM cs UNION ALL SELECT 'sp', count(*) FROM sp UNION ALL SELECT 'cp', count(*) FROM cp")
def _(spark, d):
    q = w01(spark, d)
    return spark.createDataFrame([(r.name, n) for r, n in zip(q.relations, q.sizes())], "relation string, n_rows long")


@query("tighten_same_answer", W04_SQL)
def _(spark, d):
    q, x = tighten.tighten(three(edges(spark, d)), (Fraction(1), Fraction(1), Fraction(1, 2)))
    return anchored.join(q, x)


# -- constructed triangles


def _top(k: DataFrame) -> int:
    """Largest key: the families below are as large as the table allows."""
    return k.agg(F.max("k")).first()[0]


def _bad(spark, d):
    k = keys(spark, d)
    return generators.bad_triangle(k, 2 * _top(k))


BAD = "WITH g AS (SELECT CAST(0 AS BIGINT) AS x, CAST(p_partkey AS BIGINT) AS y FROM part WHERE p_partkey >= 1 UNION ALL SELECT CAST(p_partkey AS BIGINT), CAST(0 AS BIGINT) FROM part WHERE p_partkey >= 1) "


@query("bad_triangle", BAD + "SELECT r.x AS a, r.y AS b, s.y AS c FROM g r JOIN g s ON s.x = r.y JOIN g t ON t.x = r.x AND t.y = s.y")
def _(spark, d):
    return allbutone.triangle(_bad(spark, d))


@query("bad_triangle_pairwise", BAD + "SELECT count(*) AS intermediate, CAST(0 AS BIGINT) AS n_rows FROM g r JOIN g s ON s.x = r.y")
def _(spark, d):
    trace: list[int] = []
    baselines.left_deep(_bad(spark, d), trace=trace)
    return spark.createDataFrame([tuple(trace)], "intermediate long, n_rows long")


@query("tight_triangle", "SELECT x.n_nationkey AS a, y.n_nationkey AS b, z.n_nationkey AS c FROM nation x, nation y, nation z")
def _(spark, d):
    v = load(spark, d, "nation").select("n_nationkey")
    return allbutone.triangle(generators.grid(v, ["a", "b", "c"]))


# -- all-but-one queries


def w05(spark, d):
    x = ol(spark, d).select(F.col("o_custkey").alias("c"), F.col("l_partkey").alias("p"), F.col("l_suppkey").alias("s"), F.month("l_shipdate").alias("m"))
    x = settle(x, "lines")  # the join of lines and orders, once for all four
    q = JoinQuery([relation(x, list(a), a) for a in ("psm", "csm", "cpm", "cps")], ["c", "p", "s", "m"])
    q.sizes()  # settles the four
    drop(x)
    return q


W05_SQL = f"""WITH x AS (SELECT o_custkey AS c, l_partkey AS p, l_suppkey AS s, CAST(month(l_shipdate) AS INTEGER) AS m FROM {OL}),
    r1 AS (SELECT DISTINCT p, s, m FROM x), r2 AS (SELECT DISTINCT c, s, m FROM x), r3 AS (SELECT DISTINCT c, p, m FROM x), r4 AS (SELECT DISTINCT c, p, s FROM x)
    SELECT r4.c, r4.p, r4.s, r3.m FROM r4 JOIN r3 USING (c, p) JOIN r2 ON r2.c = r4.c AND r2.s = r4.s AND r2.m = r3.m JOIN r1 ON r1.p = r4.p AND r1.s = r4.s AND r1.m = r3.m"""


@query("abo4_lineitem", W05_SQL)
def _(spark, d):
    return allbutone.join(w05(spark, d))


@query("abo4_left_deep", W05_SQL)
def _(spark, d):
    return allbutone.join(w05(spark, d), shape="left")


@query("abo4_right_deep", W05_SQL)
def _(spark, d):
    return allbutone.join(w05(spark, d), shape="right")


@query("abo_empty_side", "SELECT CAST(0 AS BIGINT) AS a, CAST(0 AS BIGINT) AS b, CAST(0 AS BIGINT) AS c, CAST(0 AS BIGINT) AS d WHERE FALSE")
def _(spark, d):
    q = generators.one_nonzero(keys(spark, d), ["a", "b", "c", "d"], 3)
    rels = [Relation(r.name, r.df.limit(0)) if i == 0 else r for i, r in enumerate(q.relations)]
    return allbutone.join(JoinQuery(rels, q.attrs))


@query("abo2_product", "SELECT a.n_nationkey AS a, b.r_regionkey AS b FROM nation a, region b")
def _(spark, d):
    return allbutone.join(JoinQuery([relation(load(spark, d, "region"), {"b": "r_regionkey"}, "B"), relation(load(spark, d, "nation"), {"a": "n_nationkey"}, "A")], ["a", "b"]))


@query("abo_tight", "SELECT x.n_nationkey AS a, y.n_nationkey AS b, z.n_nationkey AS c, w.n_nationkey AS d FROM nation x, nation y, nation z, nation w")
def _(spark, d):
    v = load(spark, d, "nation").select("n_nationkey")
    return allbutone.join(generators.grid(v, ["a", "b", "c", "d"]))


def _one_nonzero(spark, d, attrs: str) -> JoinQuery:
    k = keys(spark, d)
    return generators.one_nonzero(k, list(attrs), _top(k))


def _one_nonzero_sql(attrs: str) -> str:
    zero = "SELECT " + ", ".join(f"CAST(0 AS BIGINT) AS {a}" for a in attrs)
    return zero + "".join(" UNION ALL SELECT " + ", ".join("CAST(p_partkey AS BIGINT)" if b == a else "CAST(0 AS BIGINT)" for b in attrs) + f" FROM part WHERE p_partkey >= 1" for a in attrs)


@query("abo_bad_n3", _one_nonzero_sql("abc"))
def _(spark, d):
    return allbutone.join(_one_nonzero(spark, d, "abc"))


@query("abo_bad_n4", _one_nonzero_sql("abcd"))
def _(spark, d):
    return allbutone.join(_one_nonzero(spark, d, "abcd"))


@query("abo_bad_anchored", _one_nonzero_sql("abcd"))
def _(spark, d):
    return anchored.join(_one_nonzero(spark, d, "abcd"))


@query("abo_bad_pairwise", f"WITH x AS ({_one_nonzero_sql('abc')}), r AS (SELECT DISTINCT b, c FROM x), s AS (SELECT DISTINCT a, c FROM x) SELECT (SELECT count(*) FROM r JOIN s USING (c)) AS least_pair, (SELECT count(*) FROM x) AS n_rows")
def _(spark, d):
    q = _one_nonzero(spark, d, "abc")
    trace: list[int] = []
    baselines.left_deep(q, trace=trace)
    return spark.createDataFrame([(min(metrics.pairwise_sizes(q).values()), trace[-1])], "least_pair long, n_rows long")


@query("abo_invariants", "SELECT CAST(n AS BIGINT) AS leaves, CAST(TRUE AS BOOLEAN) AS holds, CAST(k AS BIGINT) AS n_nodes FROM (VALUES (2, 2), (4, 1)) AS t(n, k)")
def _(spark, d):
    got = allbutone.invariants(w05(spark, d))
    return spark.createDataFrame([(len(t.leaves), ok) for t, ok in got], "leaves long, holds boolean").groupBy("leaves").agg(F.bool_and("holds").alias("holds"), F.count("*").alias("n_nodes"))


@query("gap_extended", "SELECT a, b, c, CAST(0 AS BIGINT) AS d FROM (" + _one_nonzero_sql("abc") + ")")
def _(spark, d):
    return keyed_join(generators.extend_constant(_one_nonzero(spark, d, "abc"), [("a", "d")]), anchored.join)


@query("gap_growth", """WITH t AS (SELECT max(p_partkey) // 4 AS m0 FROM part), h AS (SELECT m0 * f AS m FROM t, (VALUES (1), (2), (4)) AS v(f)), k AS (SELECT CAST(p_partkey AS BIGINT) AS j FROM part WHERE p_partkey >= 1),
    g AS (SELECT m, CAST(0 AS BIGINT) AS x, j AS y FROM k JOIN h ON j <= m UNION ALL SELECT m, j, 0 FROM k JOIN h ON j <= m),
    o AS (SELECT m, y AS v, count(*) AS n FROM g GROUP BY ALL), i AS (SELECT m, x AS v, count(*) AS n FROM g GROUP BY ALL)
    SELECT 2 * o.m AS n, CAST(sum(o.n * i.n) AS BIGINT) AS pairwise, CAST(sum(CASE WHEN o.n * o.n > 2 * o.m THEN 2 * o.m ELSE o.n * i.n END) AS BIGINT) AS method, CAST(floor(power(2 * o.m, 1.5) + 1e-6) AS BIGINT) AS bound
    FROM o JOIN i ON i.m = o.m AND i.v = o.v GROUP BY o.m""")
def _(spark, d):
    """The bad family at a quarter, a half and all of its size: pairwise plans grow with the square, the heavy/light method in proportion."""
    k = keys(spark, d)
    m = _top(k) // 4
    return spark.createDataFrame(metrics.growth(lambda n: generators.bad_triangle(k, n), [2 * m, 4 * m, 8 * m]), "n long, pairwise long, method long, bound long")


@query("gap_plans", f"WITH x AS ({_one_nonzero_sql('abc')}), r AS (SELECT DISTINCT b, c FROM x), s AS (SELECT DISTINCT a, c FROM x) SELECT (SELECT count(*) FROM r JOIN s USING (c)) AS best_plan, CAST(floor(power((SELECT count(*) FROM r), 1.5) + 1e-6) AS BIGINT) AS bound")
def _(spark, d):
    """Largest intermediate of the best of all left-deep plans, against the bound."""
    q = _one_nonzero(spark, d, "abc")
    return spark.createDataFrame([(metrics.plan_gap(q)["largest"], bounds.floor_bound(q.hypergraph, q.sizes()))], "best_plan long, bound long")


# -- the general method


W08_EDGES = ("1245", "1346", "123", "246", "356")


def w08_rows(spark, d) -> DataFrame:
    x = ol(spark, d).join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(load(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    x = x.select(F.col("c_nationkey").alias("a1"), F.col("c_mktsegment").alias("a2"), F.col("p_brand").alias("a3"), F.col("o_orderpriority").alias("a4"), F.col("l_returnflag").alias("a5"), F.year("l_shipdate").alias("a6"))
    return settle(x.distinct())


def w08(spark, d):
    x = w08_rows(spark, d)
    return JoinQuery([relation(x, [f"a{i}" for i in e], f"R{e}") for e in W08_EDGES], [f"a{i}" for i in "123456"])


W08_SQL = f"""WITH x AS (SELECT c_nationkey AS a1, c_mktsegment AS a2, p_brand AS a3, o_orderpriority AS a4, l_returnflag AS a5, CAST(year(l_shipdate) AS INTEGER) AS a6
    FROM {OL} JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey),
    r1 AS (SELECT DISTINCT a1, a2, a4, a5 FROM x), r2 AS (SELECT DISTINCT a1, a3, a4, a6 FROM x), r3 AS (SELECT DISTINCT a1, a2, a3 FROM x), r4 AS (SELECT DISTINCT a2, a4, a6 FROM x), r5 AS (SELECT DISTINCT a3, a5, a6 FROM x)
    SELECT r1.a1, r1.a2, r2.a3, r1.a4, r1.a5, r2.a6 FROM r1 JOIN r2 ON r1.a1 = r2.a1 AND r1.a4 = r2.a4 JOIN r3 ON r3.a1 = r1.a1 AND r3.a2 = r1.a2 AND r3.a3 = r2.a3
    JOIN r4 ON r4.a2 = r1.a2 AND r4.a4 = r1.a4 AND r4.a6 = r2.a6 JOIN r5 ON r5.a3 = r2.a3 AND r5.a5 = r1.a5 AND r5.a6 = r2.a6"""


@query("anchored_worked_example", W08_SQL)
def _(spark, d):
    return anchored.join(w08(spark, d))


@query("anchored_order_size", W08_SQL)
def _(spark, d):
    return anchored.join(w08(spark, d), order="size")


@query("anchored_order_arity", W08_SQL)
def _(spark, d):
    return anchored.join(w08(spark, d), order="arity")


@query("anchored_order_given", W08_SQL)
def _(spark, d):
    return anchored.join(w08(spark, d), order=[4, 3, 2, 1, 0])


@query("anchored_allones_cover", W04_SQL)
def _(spark, d):
    q = three(edges(spark, d))
    return anchored.join(q, lp.trivial_cover(q.hypergraph))


@query("anchored_triangle", W01_SQL)
def _(spark, d):
    return anchored.join(w01(spark, d), order="degrees")


@query("bound_tight_example", f"""WITH x AS (SELECT DISTINCT c_nationkey, c_mktsegment, p_brand, o_orderpriority, l_returnflag, year(l_shipdate) AS y FROM {OL} JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey),
    n AS (SELECT count(DISTINCT c_nationkey) AS n1, count(DISTINCT c_mktsegment) AS n2, count(DISTINCT p_brand) AS n3, count(DISTINCT o_orderpriority) AS n4, count(DISTINCT l_returnflag) AS n5, count(DISTINCT y) AS n6 FROM x)
    SELECT CAST(n1 * n2 * n3 * n4 * n5 * n6 AS BIGINT) AS bound, CAST(2 AS INTEGER) AS half, CAST(3 AS INTEGER) AS quarter FROM n""")
def _(spark, d):
    """On the full grid of the six attributes' values the bound is the grid, with two weights of 1/2 and three of 1/4."""
    x = w08_rows(spark, d)
    n = x.agg(*(F.count_distinct(a).alias(a) for a in x.columns)).first().asDict()
    edges = [[f"a{i}" for i in e] for e in W08_EDGES]
    h, sizes = Hypergraph(tuple(n), tuple(map(frozenset, edges))), [math.prod(n[a] for a in e) for e in edges]
    w = lp.optimal_cover(h, sizes)
    return spark.createDataFrame([(bounds.floor_bound(h, sizes, w), w.count(Fraction(1, 2)), w.count(Fraction(1, 4)))], "bound long, half int, quarter int")


@query("anchored_budget", f"SELECT CAST(TRUE AS BOOLEAN) AS within, count(*) AS n_rows FROM ({W08_SQL})")
def _(spark, d):
    """Every node of the tree, every binding; the root's rows are the join's."""
    got = metrics.node_budget(w08(spark, d))
    return spark.createDataFrame([(all(g["worst"] <= 1 + 1e-9 for g in got), got[-1]["rows"])], "within boolean, n_rows long")


@query("anchored_case_counts", f"""WITH e AS ({REL['edges']}), v AS (SELECT p.y AS b, p.n AS i, s.n AS o FROM (SELECT y, count(*) AS n FROM e GROUP BY y) p JOIN (SELECT x, count(*) AS n FROM e GROUP BY x) s ON s.x = p.y),
    w AS (SELECT *, i * o < (SELECT count(*) FROM e) AS small FROM v)
    SELECT CAST(2 AS INTEGER) AS rank, 'a,b,c' AS universe, 'recurse' AS what, CAST(coalesce(sum(small::INT), 0) AS BIGINT) AS n_bindings FROM w
    UNION ALL SELECT 2, 'a,b,c', 'scan', CAST(coalesce(sum((NOT small)::INT), 0) AS BIGINT) FROM w
    UNION ALL SELECT 1, 'a,c', 'scan (always)', CAST(sum(i) AS BIGINT) FROM w WHERE small HAVING count(*) > 0""")
def _(spark, d):
    q = three(edges(spark, d))
    rows = metrics.case_counts(q, cover=(Fraction(1, 2),) * 3)
    return spark.createDataFrame([(r["rank"], ",".join(r["universe"]), r["what"], r["rows"]) for r in rows], "rank int, universe string, what string, n_bindings long")


@query("empty_relation_join", "SELECT CAST(0 AS BIGINT) AS c, CAST(0 AS BIGINT) AS s, CAST(0 AS BIGINT) AS p WHERE FALSE")
def _(spark, d):
    r = facts(spark, d)
    return anchored.join(JoinQuery([r["cs"], r["sp"], Relation("cp", r["cp"].df.filter("c < 0"))], ["c", "s", "p"]))


@query("grid_triangle", W04_SQL)
def _(spark, d):
    return grid.join(three(edges(spark, d)), cells=16)


@query("auto_abo", W05_SQL)
def _(spark, d):
    return planner.join(w05(spark, d))


@query("auto_general", W08_SQL)
def _(spark, d):
    return planner.join(w08(spark, d))


# -- indexes


@query("index_counts", f"WITH x AS ({REL['cp']}) SELECT c, count(*) AS n FROM x GROUP BY c")
def _(spark, d):
    return PrefixIndex(facts(spark, d)["cp"], ["c", "p"]).count(["c"], ["p"], "n")


@query("index_prebuilt_join", W04_SQL)
def _(spark, d):
    """The indexes of all relations are written, read back, and used in their place."""
    q = three(edges(spark, d))
    got = {}
    for r, order in zip(q.relations, (["b", "a"], ["b", "c"], ["a", "c"])):
        at = scratch(spark, f"index-{r.name}")
        PrefixIndex(r, order).save(at)
        got[r.name] = PrefixIndex.load(spark, at, order, r.name)
    return anchored.join(q, indexes=got)


@query("index_cost", f"WITH x AS ({REL['cp']}) SELECT 'c' AS prefix, count(DISTINCT c) AS n_rows FROM x UNION ALL SELECT 'c,p', count(*) FROM x UNION ALL SELECT 'p', count(DISTINCT p) FROM x UNION ALL SELECT 'p,c', count(*) FROM x")
def _(spark, d):
    """Rows of the prefix tables of both column orders of one relation."""
    return spark.createDataFrame(metrics.index_cost(facts(spark, d)["cp"]), "prefix string, n_rows long")


@query("key_skew", f"WITH x AS ({REL['cp']}) SELECT 'c' AS attribute, max(n) AS largest, round(max(n) / avg(n), 6) AS ratio FROM (SELECT c, count(*) AS n FROM x GROUP BY c) UNION ALL SELECT 'p', max(n), round(max(n) / avg(n), 6) FROM (SELECT p, count(*) AS n FROM x GROUP BY p)")
def _(spark, d):
    """How far the heaviest key of each attribute is from the mean: what one reducer would get."""
    return metrics.key_skew(facts(spark, d)["cp"])


@query("intersect_small", f"SELECT DISTINCT s_nationkey AS n FROM supplier INTERSECT SELECT DISTINCT c_nationkey FROM customer WHERE c_acctbal > 0")
def _(spark, d):
    a = load(spark, d, "supplier").select(F.col("s_nationkey").alias("n"))
    b = load(spark, d, "customer").filter("c_acctbal > 0").select(F.col("c_nationkey").alias("n"))
    return intersect_small(a, b, a.count(), b.count())


@query("index_sorted", f"WITH x AS ({REL['cp']}) SELECT c, p FROM x")
def _(spark, d):
    return facts(spark, d)["cp"].df.sortWithinPartitions("c", "p")


# -- cycles and graphs


def star(spark, d, lines: DataFrame | None = None) -> dict[str, Relation]:
    cust, supp, nat = (load(spark, d, t) for t in ("customer", "supplier", "nation"))
    return facts(spark, d, lines) | {
        "cn": keyed(cust, {"c": "c_custkey", "n": "c_nationkey"}, "cn"), "sn": keyed(supp, {"s": "s_suppkey", "n": "s_nationkey"}, "sn"),
        "cn1": keyed(cust, {"c": "c_custkey", "n1": "c_nationkey"}, "cn1"), "n1r": keyed(nat, {"n1": "n_nationkey", "r": "n_regionkey"}, "n1r"),
        "n2r": keyed(nat, {"n2": "n_nationkey", "r": "n_regionkey"}, "n2r"), "sn2": keyed(supp, {"s": "s_suppkey", "n2": "s_nationkey"}, "sn2"),
        "cm": keyed(cust, {"c": "c_custkey", "g": "c_mktsegment"}, "cm"), "oc": keyed(load(spark, d, "orders"), {"o": "o_orderkey", "c": "o_custkey"}, "oc"),
        "op": relation(load(spark, d, "lineitem"), {"o": "l_orderkey", "p": "l_partkey"}, "op"),
    }


def pick(spark, d, names: str, attrs: str | None = None) -> JoinQuery:
    r = star(spark, d)
    return JoinQuery([r[n] for n in names.split()], attrs.split() if attrs else None)


def star_cycle(spark, d, *more: Relation) -> JoinQuery:
    """The graph query. Lines and orders are joined once for its three relations; the joined lines go once these are settled."""
    lines = settle(ol(spark, d).select("o_custkey", "l_suppkey", "l_partkey"), "lines")
    r = star(spark, d, lines)
    q = JoinQuery([*(r[n] for n in "cs sp cp cn cm sn".split()), *more], "c s p n g".split())
    q.sizes()
    drop(lines)
    return q


C4_SQL = TRIANGLE + f", cn AS ({REL['cn']}), sn AS ({REL['sn']}) SELECT cp.c, cn.n, sn.s, cp.p FROM cp JOIN cn ON cn.c = cp.c JOIN sn ON sn.n = cn.n JOIN sp ON sp.s = sn.s AND sp.p = cp.p"
C5_SQL = TRIANGLE + "SELECT cs.c, c.c_nationkey AS n1, x.n_regionkey AS r, s.s_nationkey AS n2, cs.s FROM cs JOIN customer c ON c.c_custkey = cs.c JOIN supplier s ON s.s_suppkey = cs.s JOIN nation x ON x.n_nationkey = c.c_nationkey JOIN nation y ON y.n_nationkey = s.s_nationkey AND y.n_regionkey = x.n_regionkey"
C6_SQL = TRIANGLE + "SELECT cp.c, c.c_nationkey AS n1, x.n_regionkey AS r, s.s_nationkey AS n2, sp.s, cp.p FROM cp JOIN sp ON sp.p = cp.p JOIN customer c ON c.c_custkey = cp.c JOIN supplier s ON s.s_suppkey = sp.s JOIN nation x ON x.n_nationkey = c.c_nationkey JOIN nation y ON y.n_nationkey = s.s_nationkey AND y.n_regionkey = x.n_regionkey"
C7_SQL = TRIANGLE + ", op AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem) SELECT oc.o_custkey AS c, c.c_nationkey AS n1, x.n_regionkey AS r, s.s_nationkey AS n2, sp.s, op.p, op.o FROM op JOIN orders oc ON oc.o_orderkey = op.o JOIN sp ON sp.p = op.p JOIN customer c ON c.c_custkey = oc.o_custkey JOIN supplier s ON s.s_suppkey = sp.s JOIN nation x ON x.n_nationkey = c.c_nationkey JOIN nation y ON y.n_nationkey = s.s_nationkey AND y.n_regionkey = x.n_regionkey"


@query("cycle4_nation", C4_SQL)
def _(spark, d):
    return cycles.even_cycle(pick(spark, d, "cn sn sp cp", "c n s p"))


@query("cycle5_region", C5_SQL)
def _(spark, d):
    return cycles.odd_cycle(pick(spark, d, "cn1 n1r n2r sn2 cs", "c n1 r n2 s"))


@query("cycle6_region", C6_SQL)
def _(spark, d):
    return cycles.even_cycle(pick(spark, d, "cn1 n1r n2r sn2 sp cp", "c n1 r n2 s p"))


@query("cycle7_orders", C7_SQL)
def _(spark, d):
    return cycles.odd_cycle(pick(spark, d, "cn1 n1r n2r sn2 sp op oc", "c n1 r n2 s p o"), spend=True)


@query("cycle4_anchored", C4_SQL)
def _(spark, d):
    return keyed_join(pick(spark, d, "cn sn sp cp", "c n s p"), anchored.join, spend=True)


@query("auto_cycle", C5_SQL)
def _(spark, d):
    return planner.join(pick(spark, d, "cn1 n1r n2r sn2 cs", "c n1 r n2 s"))


@query("size_factor", " UNION ALL ".join(f"SELECT CAST({n} AS INTEGER) AS n_relations, count(*) AS n_rows, TRUE AS within FROM ({sql})" for n, sql in ((4, C4_SQL), (5, C5_SQL), (6, C6_SQL), (7, C7_SQL))))
def _(spark, d):
    """Output against bound as the cycle gets longer (seconds per length are a line of bench.py)."""
    out = []
    for names, attrs in (("cn sn sp cp", "c n s p"), ("cn1 n1r n2r sn2 cs", "c n1 r n2 s"), ("cn1 n1r n2r sn2 sp cp", "c n1 r n2 s p"), ("cn1 n1r n2r sn2 sp op oc", "c n1 r n2 s p o")):
        q = pick(spark, d, names, attrs)
        with passing(spark):
            n = cycles.cycle(q, spend=True).count()
        out.append((len(q.relations), n, n <= bounds.floor_bound(q.hypergraph, q.sizes())))
    return spark.createDataFrame(out, "n_relations int, n_rows long, within boolean")


GRAPH_SQL = TRIANGLE + "SELECT cs.c, cs.s, cp.p, c.c_nationkey AS n, c.c_mktsegment AS g FROM cs JOIN cp ON cp.c = cs.c JOIN sp ON sp.s = cs.s AND sp.p = cp.p JOIN customer c ON c.c_custkey = cs.c JOIN supplier x ON x.s_suppkey = cs.s AND x.s_nationkey = c.c_nationkey"


@query("graph_star_cycle", GRAPH_SQL)
def _(spark, d):
    return cycles.graph_join(star_cycle(spark, d), spend=True)


@query("graph_with_unary", GRAPH_SQL + " WHERE x.s_acctbal > 0")
def _(spark, d):
    rich = keyed(load(spark, d, "supplier").filter("s_acctbal > 0"), {"s": "s_suppkey"}, "rich")
    return cycles.graph_join(star_cycle(spark, d, rich), spend=True)


# -- rules


def rule_tables(spark, d) -> dict[str, DataFrame]:
    e = load(spark, d, "events")
    nxt = F.lead("user_id").over(W.partitionBy(F.date_trunc("hour", F.col("ts").cast("timestamp"))).orderBy("ts", "event_id"))
    return {"E": edges(spark, d), "H": e.select(F.col("user_id").alias("u"), nxt.alias("v")).filter("v is not null"), "T": e.select("user_id", "event_type")}


HANDS = "SELECT user_id AS u, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS v FROM events"


@query("rule_self_join", W04_SQL)
def _(spark, d):
    return answer("q(a, b, c) :- E(a, b), E(b, c), E(a, c)", rule_tables(spark, d))


@query("rule_constant", f"WITH e AS ({REL['edges']}), t AS (SELECT DISTINCT user_id AS u FROM events WHERE event_type = 'purchase') SELECT e.x, e.y FROM e JOIN t a ON a.u = e.x JOIN t b ON b.u = e.y")
def _(spark, d):
    return answer("q(x, y) :- E(x, y), T(x, 'purchase'), T(y, 'purchase')", rule_tables(spark, d))


@query("rule_repeat_var", f"WITH h AS (SELECT DISTINCT u, v FROM ({HANDS}) WHERE v IS NOT NULL) SELECT a.u, b.v AS w FROM h a JOIN h b ON b.u = a.u WHERE a.u = a.v")
def _(spark, d):
    return answer("q(u, w) :- H(u, u), H(u, w)", rule_tables(spark, d))


@query("rule_projected_head", f"WITH e AS ({REL['edges']}) SELECT DISTINCT r.x FROM e r JOIN e s ON s.x = r.y")
def _(spark, d):
    return answer("q(x) :- E(x, y), E(y, z)", rule_tables(spark, d))


@query("sat_unique", """WITH a AS (SELECT c_custkey AS k, CAST(m & 1 AS INTEGER) AS v1, CAST((m >> 1) & 1 AS INTEGER) AS v2, CAST((m >> 2) & 1 AS INTEGER) AS v3
    FROM customer, (SELECT unnest(range(8)) AS m) WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderkey % 8 = m))
    SELECT * FROM a WHERE k IN (SELECT k FROM a GROUP BY k HAVING count(*) = 1)""")
def _(spark, d):
    """A formula for each customer, an order being a clause of three literals; those that one assignment alone satisfies."""
    clauses = load(spark, d, "orders").select("o_custkey", F.col("o_orderkey") % 8)
    found = anchored.join(generators.cnf_by_key(load(spark, d, "customer").select(F.col("c_custkey").alias("k")), clauses))
    one = found.groupBy("k").agg(F.count("*").alias("_n"), *(F.first(v).alias(v) for v in ("v1", "v2", "v3")))
    return one.filter("_n = 1").drop("_n")


# -- dependencies


def w16(spark, d) -> tuple[JoinQuery, list[FD]]:
    r = star(spark, d)
    lines = relation(load(spark, d, "lineitem"), {"o": "l_orderkey", "p": "l_partkey", "s": "l_suppkey"}, "L")
    nat = keyed(load(spark, d, "nation"), {"n": "n_nationkey", "r": "n_regionkey"}, "nr")
    return JoinQuery([r["oc"], r["cn"], nat, lines], ["o", "p", "s", "c", "n", "r"]), [FD("oc", "o", "c"), FD("cn", "c", "n"), FD("nr", "n", "r")]


FD_SQL = f"WITH l AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM lineitem) SELECT l.o, l.p, l.s, o_custkey AS c, c_nationkey AS n, n_regionkey AS r FROM l JOIN orders ON o_orderkey = l.o JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey"


@query("fd_expand_orders", FD_SQL)
def _(spark, d):
    q, fds = w16(spark, d)
    return fd.join(q, fds)


@query("fd_unaware_orders", FD_SQL)
def _(spark, d):
    return fd.join(w16(spark, d)[0])


@query("auto_fd", FD_SQL)
def _(spark, d):
    q, fds = w16(spark, d)
    return planner.join(q, fds=fds)


@query("fd_check", """SELECT 'o_orderkey -> o_custkey' AS fd, count(*) AS n_violations FROM (SELECT o_orderkey FROM orders GROUP BY 1 HAVING count(DISTINCT o_custkey) > 1)
    UNION ALL SELECT 'p_brand -> p_size', count(*) FROM (SELECT p_brand FROM part GROUP BY 1 HAVING count(DISTINCT p_size) > 1)""")
def _(spark, d):
    told = lambda t, u, v: fd.violations(load(spark, d, t), u, v).agg(F.count("*").alias("n_violations")).select(F.lit(f"{u} -> {v}").alias("fd"), "n_violations")
    return told("orders", "o_orderkey", "o_custkey").union(told("part", "p_brand", "p_size"))


FAMILY_SQL = "SELECT CAST(p_partkey AS BIGINT) AS a, CAST(p_partkey % 7 AS BIGINT) AS b1, CAST(0 AS BIGINT) AS z, CAST(p_partkey % 11 AS BIGINT) AS b2 FROM part"


def _family(spark, d, k: int) -> JoinQuery:
    a = keys(spark, d)
    return generators.fd_family(a, _top(a) + 1, k)


@query("fd_family_join", FAMILY_SQL)
def _(spark, d):
    return fd.join(_family(spark, d, 2), [FD("R1", "a", "b1"), FD("R2", "a", "b2")])


@query("fd_unaware_join", FAMILY_SQL)
def _(spark, d):
    return fd.join(_family(spark, d, 2))


@query("fd_bound", "SELECT count(*) * 7 * 11 AS unaware, count(*) * 7 AS aware FROM part")
def _(spark, d):
    """Three pairs; the second relations have 7, 11 and 13 rows. Without dependencies all but one of them multiply."""
    q = _family(spark, d, 3)
    return spark.createDataFrame([(fd.bound(q), fd.bound(q, [FD(f"R{i}", "a", f"b{i}") for i in (1, 2, 3)]))], "unaware long, aware long")


# -- relaxed joins


def w18(spark, d) -> JoinQuery:
    """The lead triangle with a fourth relation, the returned lines."""
    j = ol(spark, d)
    r = facts(spark, d)
    return JoinQuery([r["cs"], r["sp"], r["cp"], relation(j.filter("l_returnflag = 'R'"), {"c": "o_custkey", "s": "l_suppkey", "p": "l_partkey"}, "Q")], ["c", "s", "p"])


def w18g(spark, d) -> JoinQuery:
    """Triangles of hand-offs with a fourth relation: three different users one after the other."""
    e = load(spark, d, "events")
    w = W.partitionBy(F.date_trunc("hour", F.col("ts").cast("timestamp"))).orderBy("ts", "event_id")
    run = e.select(F.array_sort(F.array("user_id", F.lead("user_id", 1).over(w), F.lead("user_id", 2).over(w))).alias("u")).filter("u[0] < u[1] and u[1] < u[2]")
    q = three(settle(edges(spark, d)))
    return JoinQuery([*q.relations, relation(run, {x: F.col("u")[i] for i, x in enumerate("abc")}, "Q")], ["a", "b", "c"])


def _relaxed_sql(with_: str, rels: list[tuple[str, str]], attrs: str, r: int) -> str:
    """Rows of all joins of two linked relations that have all attributes, kept where all but r of the relations agree."""
    pairs = [(x, y) for i, x in enumerate(rels) for y in rels[i + 1 :] if set(x[1]) & set(y[1]) and set(x[1]) | set(y[1]) == set(attrs)]
    cols, joins = ", ".join(attrs), []
    for x, y in pairs:
        joins.append(f"SELECT {cols} FROM {x[0]} JOIN {y[0]} USING ({', '.join(a for a in attrs if a in x[1] and a in y[1])})")
    wide = [f"SELECT {cols} FROM {n}" for n, a in rels if set(a) == set(attrs)]
    agree = " + ".join(f"(CASE WHEN {n}.{a[0]} IS NULL THEN 0 ELSE 1 END)" for n, a in rels)
    tests = " ".join(f"LEFT JOIN {n} ON " + " AND ".join(f"{n}.{c} = k.{c}" for c in a) for n, a in rels)
    return f"{with_}, k AS ({' UNION '.join(joins + wide)}), g AS (SELECT k.*, {agree} AS n FROM k {tests}) SELECT {cols} FROM g WHERE n >= {len(rels) - r}"


def relaxed_sql(r: int) -> str:
    return _relaxed_sql(TRIANGLE + f", q AS (SELECT DISTINCT o_custkey AS c, l_suppkey AS s, l_partkey AS p FROM {OL} WHERE l_returnflag = 'R')", [("cs", "cs"), ("sp", "sp"), ("cp", "cp"), ("q", "csp")], "csp", r)


def relaxed_graph_sql(r: int) -> str:
    w = "OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id)"
    q = f"SELECT DISTINCT u[1] AS a, u[2] AS b, u[3] AS c FROM (SELECT list_sort([user_id, lead(user_id, 1) {w}, lead(user_id, 2) {w}]) AS u FROM events) WHERE u[1] < u[2] AND u[2] < u[3]"
    return _relaxed_sql(f"WITH e AS ({REL['edges']}), r AS (SELECT x AS a, y AS b FROM e), s AS (SELECT x AS b, y AS c FROM e), t AS (SELECT x AS a, y AS c FROM e), q AS ({q})", [("r", "ab"), ("s", "bc"), ("t", "ac"), ("q", "abc")], "abc", r)


# two relations more may disagree on the graph only: on the facts that is nearly the join over one attribute
for _r in range(2):
    query(f"relaxed_r{_r}", relaxed_sql(_r))(lambda spark, d, r=_r: relaxed.join(w18(spark, d), r))
for _r in range(2, 4):
    query(f"relaxed_r{_r}", relaxed_graph_sql(_r))(lambda spark, d, r=_r: relaxed.join(w18g(spark, d), r))
query("relaxed_noshare", relaxed_graph_sql(1))(lambda spark, d: relaxed.join(w18g(spark, d), 1, share=False))
query("relaxed_naive", relaxed_graph_sql(1))(lambda spark, d: relaxed.naive(w18g(spark, d), 1))


@query("relaxed_bound_report", "SELECT CAST(r AS BIGINT) AS r, CAST(a AS BIGINT) AS covering, CAST(b AS BIGINT) AS minimal, CAST(TRUE AS BOOLEAN) AS ordered FROM (VALUES (0, 1, 1), (1, 5, 4), (2, 11, 6), (3, 12, 4)) AS t(r, a, b)")
def _(spark, d):
    q = w18(spark, d)
    h, s = q.hypergraph, q.sizes()
    rows = []
    for r in range(4):
        f = relaxed.family_sizes(h, s, r)
        rows.append((r, f["covering"], f["minimal"], relaxed.class_bound(h, s, r) <= relaxed.sum_bound(h, s, r) and f["classes"] <= f["minimal"]))
    return spark.createDataFrame(rows, "r long, covering long, minimal long, ordered boolean")


#: Side of the unary relations: as large as the output, its cube, may be for the number of parts.
SIDE = "(SELECT CAST(floor(power(count(*), 1.0 / 3) + 1e-9) AS BIGINT) FROM part)"


def _tight_sql(r: int) -> str:
    wide = "SELECT j AS a1, j AS a2, j AS a3 FROM k, side WHERE j > m" + ("" if r >= 3 else " AND FALSE")
    return f"""WITH side AS (SELECT {SIDE} AS m), k AS (SELECT CAST(p_partkey AS BIGINT) AS j FROM part, side WHERE p_partkey BETWEEN 1 AND 2 * m)
    SELECT x.j AS a1, y.j AS a2, z.j AS a3 FROM k x, k y, k z, side WHERE greatest(x.j, y.j, z.j) <= m UNION ALL {wide}"""


def _tight(spark, d) -> JoinQuery:
    k = keys(spark, d)
    return JoinQuery(generators.relaxed_tight(k, 3, bounds.integer_root(k.count(), 3)))


query("relaxed_tight", _tight_sql(3))(lambda spark, d: relaxed.join(_tight(spark, d), 3))
query("relaxed_tight_r1", _tight_sql(1))(lambda spark, d: relaxed.join(_tight(spark, d), 1))


@query("relaxed_blocks", """WITH z AS (SELECT CAST(floor(power(count(*), 0.25) + 1e-9) AS BIGINT) AS m FROM part), v AS (SELECT CAST(p_partkey AS BIGINT) AS j, m FROM part, z WHERE p_partkey BETWEEN 1 AND 2 * m),
    b AS (SELECT x.j AS p, y.j AS q, (x.j <= x.m)::INT + (y.j <= y.m)::INT AS n, (x.j = y.j AND x.j > x.m)::INT AS w FROM v x, v y),
    g AS (SELECT s.p AS ax1, s.q AS ax2, t.p AS ay1, t.q AS ay2, s.n + s.w + t.n + t.w AS n, (s.n = 2 OR s.w = 1) AND (t.n = 2 OR t.w = 1) AS ok FROM b s, b t)
    SELECT ax1, ax2, ay1, ay2 FROM g WHERE ok AND n >= 4""")
def _(spark, d):
    """Two blocks of two unary relations and a wide one each, two relations may disagree."""
    k = keys(spark, d)
    m = bounds.integer_root(k.count(), 4)
    return relaxed.join(JoinQuery([*generators.relaxed_tight(k, 2, m, "x"), *generators.relaxed_tight(k, 2, m, "y")], ["ax1", "ax2", "ay1", "ay2"]), 2)


# -- geometry


def points(spark, d) -> DataFrame:
    return load(spark, d, "lineitem").select(F.col("l_partkey").alias("p"), F.col("l_suppkey").alias("s"), F.month("l_shipdate").alias("m")).distinct()


POINTS = "WITH x AS (SELECT DISTINCT l_partkey AS p, l_suppkey AS s, CAST(month(l_shipdate) AS INTEGER) AS m FROM lineitem) "


@query("geo_hyperplane_check", POINTS + "SELECT count(*) AS points, (SELECT count(*) FROM (SELECT DISTINCT s, m FROM x)) AS p1, (SELECT count(*) FROM (SELECT DISTINCT p, m FROM x)) AS p2, (SELECT count(*) FROM (SELECT DISTINCT p, s FROM x)) AS p3, CAST(2 AS INTEGER) AS d, CAST(TRUE AS BOOLEAN) AS holds FROM x")
def _(spark, d):
    return geometry.hyperplane_check(points(spark, d), ["p", "s", "m"])


GEO = "WITH g AS (" + BANDS + "), x AS (SELECT v, max(CASE WHEN b = 0 THEN bits END) AS b0, max(CASE WHEN b = 1 THEN bits END) AS b1, max(CASE WHEN b = 2 THEN bits END) AS b2, max(CASE WHEN b = 3 THEN bits END) AS b3 FROM g GROUP BY v) "


@query("geo_regular_check", GEO + "SELECT (SELECT count(*) FROM (SELECT DISTINCT b0, b1, b2, b3 FROM x)) AS points, (SELECT count(*) FROM (SELECT DISTINCT b0, b1 FROM x)) AS p1, (SELECT count(*) FROM (SELECT DISTINCT b1, b2 FROM x)) AS p2, (SELECT count(*) FROM (SELECT DISTINCT b2, b3 FROM x)) AS p3, (SELECT count(*) FROM (SELECT DISTINCT b3, b0 FROM x)) AS p4, CAST(2 AS INTEGER) AS d, CAST(TRUE AS BOOLEAN) AS holds")
def _(spark, d):
    e = load(spark, d, "embeddings").select(*(sign_bucket(F.col("embedding"), 8 * b, 8).alias(f"b{b}") for b in range(4)))
    return geometry.regular_projection_check(e, [["b0", "b1"], ["b1", "b2"], ["b2", "b3"], ["b3", "b0"]])


@query("geo_reconstruct", POINTS + ", a AS (SELECT DISTINCT s, m FROM x), b AS (SELECT DISTINCT p, m FROM x), c AS (SELECT DISTINCT p, s FROM x) SELECT c.p, c.s, b.m FROM c JOIN b ON b.p = c.p JOIN a ON a.s = c.s AND a.m = b.m")
def _(spark, d):
    x = settle(points(spark, d))
    return geometry.reconstruct([relation(x, ["p", "s"], "ps"), relation(x, ["p", "m"], "pm"), relation(x, ["s", "m"], "sm")])


# -- baselines


query("pairwise_left_deep", W04_SQL)(lambda spark, d: baselines.left_deep(three(edges(spark, d))))
query("pairwise_bushy", C4_SQL)(lambda spark, d: baselines.bushy(pick(spark, d, "cn sn sp cp", "c n s p"), ((0, 3), (1, 2))))
query("pairwise_dp", C4_SQL)(lambda spark, d: baselines.dp_order(pick(spark, d, "cn sn sp cp", "c n s p")))


@query("pairwise_catalyst", W01_SQL)
def _(spark, d):
    """Lines and orders are joined once for the three relations; the joined lines go once these are settled."""
    lines = settle(ol(spark, d).select("o_custkey", "l_suppkey", "l_partkey"), "lines")
    r = facts(spark, d, lines)
    q = JoinQuery([r["cs"], r["sp"], r["cp"]], ["c", "s", "p"])
    q.sizes()
    drop(lines)
    return baselines.catalyst_sql(q)


query("join_project_plan", W04_SQL)(lambda spark, d: baselines.join_project(three(edges(spark, d))))
query("join_project_tree", f"WITH e AS ({REL['edges']}) SELECT DISTINCT r.x AS a, s.y AS c FROM e r JOIN e s ON s.x = r.y")(
    lambda spark, d: baselines.run_plan(three(edges(spark, d)), ("project", ("join", 0, 1), ["a", "c"]))
)


@query("pairwise_intermediates", TRIANGLE + "SELECT 's' AS attribute, CAST(sum(x * y) AS BIGINT) AS n_rows FROM (SELECT s, count(*) AS x FROM cs GROUP BY s) JOIN (SELECT s, count(*) AS y FROM sp GROUP BY s) USING (s) UNION ALL SELECT 'p', CAST(sum(x * y) AS BIGINT) FROM (SELECT p, count(*) AS x FROM sp GROUP BY p) JOIN (SELECT p, count(*) AS y FROM cp GROUP BY p) USING (p) UNION ALL SELECT 'c', CAST(sum(x * y) AS BIGINT) FROM (SELECT c, count(*) AS x FROM cs GROUP BY c) JOIN (SELECT c, count(*) AS y FROM cp GROUP BY c) USING (c)")
def _(spark, d):
    return spark.createDataFrame(list(allbutone.split_costs(w01(spark, d)).items()), "attribute string, n_rows long")


from . import surround  # noqa: E402, F401  registers the operators around the methods
