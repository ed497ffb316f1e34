"""Operators that a user of the join methods needs around them: scans, filters, physical joins, aggregates, windows, sinks, streams."""

from __future__ import annotations

import math
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions import scalar
from .functions.grouped import heavy_summary
from .operators import allbutone, metrics, planner
from .sources.relations import load, read, relation, write
from .sql import cover_join
from .storage import scratch, settle, small
from .streaming import streams
from .workloads import EDGE_TRIANGLE, OL, REL, TRIANGLE, W04_SQL, edges, facts, ol, query, three

PAIRS = f"WITH cs AS ({REL['cs']}), sp AS ({REL['sp']}) "

# -- projections and filters


@query("proj_distinct", f"SELECT DISTINCT o_custkey AS c, l_suppkey AS s FROM {OL}")
def _(spark, d):
    return facts(spark, d)["cs"].df


@query("section_const", f"WITH cp AS ({REL['cp']}) SELECT p FROM cp WHERE c = 7")
def _(spark, d):
    return facts(spark, d)["cp"].section(c=7).df


@query("filter_semi", PAIRS + "SELECT c, s FROM cs WHERE s IN (SELECT s_suppkey FROM supplier WHERE s_acctbal > 0)")
def _(spark, d):
    rich = relation(load(spark, d, "supplier").filter("s_acctbal > 0"), {"s": "s_suppkey"})
    return allbutone.semi(facts(spark, d)["cs"].df, rich)


@query("heavy_keys", PAIRS + "SELECT c, count(*) AS degree FROM cs GROUP BY c HAVING count(*) > 40")
def _(spark, d):
    return facts(spark, d)["cs"].df.groupBy("c").agg(F.count("*").alias("degree")).filter("degree > 40")


@query("pre_filter_range", "SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem WHERE l_quantity BETWEEN 5 AND 10 AND l_returnflag IN ('R', 'A')")
def _(spark, d):
    return relation(load(spark, d, "lineitem").filter(F.col("l_quantity").between(5, 10) & F.col("l_returnflag").isin("R", "A")), {"o": "l_orderkey", "p": "l_partkey"}).df


@query("pre_filter_like", "SELECT DISTINCT p_partkey AS p FROM part WHERE (p_name LIKE '%a%' OR p_brand IS NULL) AND NOT p_size < 10")
def _(spark, d):
    return relation(load(spark, d, "part").filter((F.col("p_name").like("%a%") | F.col("p_brand").isNull()) & ~(F.col("p_size") < 10)), {"p": "p_partkey"}).df


# -- joins

NATION = "SELECT c_custkey AS c, c_nationkey AS n, s_suppkey AS s FROM customer JOIN supplier ON s_nationkey = c_nationkey"


def _sides(spark, d):
    return load(spark, d, "customer").select(F.col("c_custkey").alias("c"), F.col("c_nationkey").alias("n")), load(spark, d, "supplier").select(F.col("s_suppkey").alias("s"), F.col("s_nationkey").alias("n"))


def _hinted(hint: str):
    def run(spark, d):
        a, b = _sides(spark, d)
        return a.join(b.hint(hint), "n").select("c", "n", "s")

    return run


query("join_hash", NATION)(_hinted("shuffle_hash"))
query("join_sort_merge", NATION)(_hinted("merge"))
query("join_broadcast", NATION)(_hinted("broadcast"))
query("join_cross", "SELECT n_nationkey AS n, r_regionkey AS r FROM nation CROSS JOIN region")(lambda spark, d: load(spark, d, "nation").select(F.col("n_nationkey").alias("n")).crossJoin(F.broadcast(load(spark, d, "region").select(F.col("r_regionkey").alias("r")))))
query("join_semi", "SELECT c_custkey AS c FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000)")(
    lambda spark, d: load(spark, d, "customer").select(F.col("c_custkey").alias("c")).join(load(spark, d, "orders").filter("o_totalprice > 100000").select(F.col("o_custkey").alias("c")), "c", "left_semi")
)
query("join_anti", "SELECT o_orderkey AS o FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")(
    lambda spark, d: load(spark, d, "orders").select(F.col("o_orderkey").alias("o")).join(load(spark, d, "lineitem").select(F.col("l_orderkey").alias("o")), "o", "left_anti")
)


@query("join_restricted", PAIRS + "SELECT cs.c, cs.s, sp.p FROM cs JOIN sp USING (s) WHERE s IN (1, 2, 3)")
def _(spark, d):
    r = facts(spark, d)
    few = load(spark, d, "supplier").filter("s_suppkey in (1, 2, 3)").select(F.col("s_suppkey").alias("s"))
    return r["cs"].df.join(few, "s", "left_semi").join(r["sp"].df.join(few, "s", "left_semi"), "s").select("c", "s", "p")


@query("join_outer_flags", PAIRS + "SELECT s_suppkey AS s, CAST(CASE WHEN max(cs.c) IS NULL THEN 0 ELSE 1 END AS INTEGER) AS sold FROM supplier LEFT JOIN cs ON cs.s = s_suppkey AND cs.c < 20 GROUP BY s_suppkey")
def _(spark, d):
    seen = facts(spark, d)["cs"].df.filter("c < 20").select("s").distinct().withColumn("sold", F.lit(1))
    return load(spark, d, "supplier").select(F.col("s_suppkey").alias("s")).join(seen, "s", "left").fillna(0, ["sold"])


@query("join_null_safe", "SELECT a.o, count(*) AS n FROM (SELECT o_orderkey AS o, CASE WHEN o_orderkey % 500 = 0 THEN NULL ELSE o_orderkey END AS k FROM orders) a JOIN (SELECT CASE WHEN l_orderkey % 500 = 0 THEN NULL ELSE l_orderkey END AS k FROM lineitem WHERE l_quantity < 3) b ON a.k IS NOT DISTINCT FROM b.k GROUP BY a.o")
def _(spark, d):
    gap = lambda c: F.when(F.col(c) % 500 == 0, None).otherwise(F.col(c))
    a = load(spark, d, "orders").select(F.col("o_orderkey").alias("o"), gap("o_orderkey").alias("k"))
    b = load(spark, d, "lineitem").filter("l_quantity < 3").select(gap("l_orderkey").alias("k2")).groupBy("k2").agg(F.count("*").alias("x"))
    return a.join(b, F.col("k").eqNullSafe(F.col("k2"))).groupBy("o").agg(F.sum("x").alias("n"))


@query("join_theta", "SELECT s_suppkey AS s, count(*) AS n FROM supplier JOIN customer ON c_nationkey = s_nationkey AND c_acctbal > s_acctbal GROUP BY s_suppkey")
def _(spark, d):
    s, c = load(spark, d, "supplier"), load(spark, d, "customer")
    return c.join(s, (c["c_nationkey"] == s["s_nationkey"]) & (c["c_acctbal"] > s["s_acctbal"])).groupBy(F.col("s_suppkey").alias("s")).agg(F.count("*").alias("n"))


#: Rows of a cell that one task gets at a time, where intervals are joined.
CHUNK = 4096


def interval_join(left: DataFrame, right: DataFrame, at: str, start: str, end: str, width: float) -> DataFrame:
    """Rows of left whose ``at`` lies in [start, end) of a row of right: both are dealt into cells of ``width``, each interval to all cells it
    has a part of, so the join is on equal cells and only then on the bounds. A cell's rows of left are dealt out in chunks of about CHUNK, and
    its intervals go to each chunk: cells may be few and uneven. width: a power of two, for which the bounds of cells are exact."""
    if math.frexp(width)[0] != 0.5:
        raise ValueError("the width of cells is a power of two")
    spark, last = left.sparkSession, F.ceil(F.col(end) / width) - 1
    points = left.withColumn("_cell", F.floor(F.col(at) / width)).filter("_cell IS NOT NULL")
    cells = right.filter(F.col(start) < F.col(end)).withColumn("_cell", F.explode(F.sequence(F.floor(F.col(start) / width), last)))
    chunks = settle(points.groupBy("_cell").agg(F.ceil(F.count("*") / CHUNK).alias("_chunks")), "chunks")
    chunks = small(chunks, chunks.count())
    points = points.withColumn("_chunk", F.xxhash64(*left.columns)).join(chunks, "_cell").withColumn("_chunk", F.pmod("_chunk", "_chunks"))
    cells = cells.join(chunks, "_cell").withColumn("_chunk", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_chunks") - 1)))
    # their number is not that of the bytes: a task's work is in the rows that it makes
    parts = max(64, int(spark.conf.get("spark.sql.shuffle.partitions")))
    points, cells = (d.drop("_chunks").repartition(parts, "_cell", "_chunk") for d in (points, cells))
    return points.join(cells, ["_cell", "_chunk"]).filter((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_cell", "_chunk")


@query("join_interval", "SELECT e.event_id, CAST(p.p_partkey AS BIGINT) AS p FROM events e JOIN part p ON e.value >= p.p_size AND e.value < p.p_size + 0.25")
def _(spark, d):
    iv = load(spark, d, "part").select(F.col("p_partkey").cast("long").alias("p"), F.col("p_size").cast("double").alias("a"), (F.col("p_size") + F.lit(0.25)).alias("z"))
    return interval_join(load(spark, d, "events").select("event_id", "value"), iv, "value", "a", "z", 0.25).select("event_id", "p")


@query("join_asof", "SELECT event_id, last_value(CASE WHEN event_type = 'signup' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_signup FROM events")
def _(spark, d):
    """Each event with the same user's latest earlier sign-up: both kinds of rows in one ordered pass, no range join."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    return load(spark, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w).alias("last_signup"))


# -- aggregates

query("degree_count", PAIRS + "SELECT s, count(*) AS degree FROM sp GROUP BY s")(lambda spark, d: facts(spark, d)["sp"].df.groupBy("s").agg(F.count("*").alias("degree")))
query("agg_partial_final", "SELECT l_returnflag AS f, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM lineitem GROUP BY l_returnflag")(
    lambda spark, d: load(spark, d, "lineitem").groupBy(F.col("l_returnflag").alias("f")).agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))
)


@query("degree_approx", PAIRS + "SELECT c, count(*) AS degree, TRUE AS near FROM cs GROUP BY c")
def _(spark, d):
    """Approximate degrees, held against the exact ones: within five times the sketch's relative error."""
    seen = facts(spark, d)["cs"].df.groupBy("c").agg(F.approx_count_distinct("s", 0.05).alias("about"), F.count("*").alias("degree"))
    return seen.select("c", "degree", (F.abs(F.col("about") - F.col("degree")) <= 0.25 * F.col("degree") + 1).alias("near"))


@query("agg_rollup_join", f"WITH e AS ({REL['edges']}), t AS ({EDGE_TRIANGLE}) SELECT a % 3 AS g, b % 2 AS h, count(*) AS n FROM t GROUP BY ROLLUP (a % 3, b % 2)")
def _(spark, d):
    t = allbutone.triangle(three(edges(spark, d)))
    return t.select((F.col("a") % 3).alias("g"), (F.col("b") % 2).alias("h")).rollup("g", "h").agg(F.count("*").alias("n"))


@query("agg_cube_join", f"WITH e AS ({REL['edges']}), t AS ({EDGE_TRIANGLE}) SELECT a % 3 AS g, b % 2 AS h, count(*) AS n, max(c) AS top FROM t GROUP BY CUBE (a % 3, b % 2)")
def _(spark, d):
    t = allbutone.triangle(three(edges(spark, d)))
    return t.select((F.col("a") % 3).alias("g"), (F.col("b") % 2).alias("h"), "c").cube("g", "h").agg(F.count("*").alias("n"), F.max("c").alias("top"))


@query("agg_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY user_id")
def _(spark, d):
    return load(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).fillna(0)


@query("clustering_coefficient", f"WITH e AS ({REL['edges']}), t AS ({EDGE_TRIANGLE}), n AS (SELECT v, count(*) AS k FROM (SELECT x AS v FROM e UNION ALL SELECT y FROM e) GROUP BY v), c AS (SELECT v, count(*) AS n_triangles FROM (SELECT a AS v FROM t UNION ALL SELECT b FROM t UNION ALL SELECT c FROM t) GROUP BY v) SELECT n.v, round(2.0 * coalesce(n_triangles, 0) / (k * (k - 1)), 6) AS coefficient FROM n LEFT JOIN c USING (v) WHERE k > 1")
def _(spark, d):
    e = edges(spark, d)
    t = allbutone.triangle(three(e)).select(F.explode(F.array("a", "b", "c")).alias("v")).groupBy("v").agg(F.count("*").alias("n"))
    k = e.select(F.explode(F.array("x", "y")).alias("v")).groupBy("v").agg(F.count("*").alias("k")).filter("k > 1")
    return k.join(t, "v", "left").select("v", F.round(2.0 * F.coalesce("n", F.lit(0)) / (F.col("k") * (F.col("k") - 1)), 6).alias("coefficient"))


@query("heavy_share", PAIRS + """, n AS (SELECT c % 4 AS g, count(*) AS degree FROM cs GROUP BY c), r AS (SELECT g, degree, row_number() OVER (PARTITION BY g ORDER BY degree DESC) AS place, count(*) OVER (PARTITION BY g) AS k FROM n)
    SELECT g, round(sum(CASE WHEN place <= greatest(1, k // 10) THEN degree ELSE 0 END) / sum(degree), 9) AS share FROM r GROUP BY g""")
def _(spark, d):
    deg = facts(spark, d)["cs"].df.groupBy("c").agg(F.count("*").alias("degree"))
    return deg.groupBy((F.col("c") % 4).alias("g")).agg(F.round(heavy_summary()("degree"), 9).alias("share"))


# -- windows, order, sets

query("win_rank_degree", PAIRS + "SELECT c, n, rank() OVER (PARTITION BY c % 10 ORDER BY n DESC) AS place, dense_rank() OVER (PARTITION BY c % 10 ORDER BY n DESC) AS dense FROM (SELECT c, count(*) AS n FROM cs GROUP BY c)")(
    lambda spark, d: facts(spark, d)["cs"].df.groupBy("c").agg(F.count("*").alias("n")).select("c", "n", F.rank().over(W.partitionBy(F.col("c") % 10).orderBy(F.desc("n"))).cast("long").alias("place"), F.dense_rank().over(W.partitionBy(F.col("c") % 10).orderBy(F.desc("n"))).cast("long").alias("dense"))
)
query("win_running", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS three, max(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS top FROM events")(
    lambda spark, d: load(spark, d, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)).alias("three"), F.max("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)).alias("top"))
)
query("topk_heavy", PAIRS + "SELECT c, count(*) AS degree FROM cs GROUP BY c ORDER BY degree DESC, c LIMIT 10")(lambda spark, d: facts(spark, d)["cs"].df.groupBy("c").agg(F.count("*").alias("degree")).orderBy(F.desc("degree"), "c").limit(10))
query("set_intersect", "SELECT c_nationkey AS n FROM customer INTERSECT SELECT s_nationkey FROM supplier")(lambda spark, d: load(spark, d, "customer").select(F.col("c_nationkey").alias("n")).intersect(load(spark, d, "supplier").select("s_nationkey")))
query("set_except", "SELECT p_partkey AS p FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 49")(
    lambda spark, d: load(spark, d, "part").select(F.col("p_partkey").alias("p")).distinct().join(load(spark, d, "lineitem").filter("l_quantity > 49").select(F.col("l_partkey").alias("p")), "p", "left_anti")
)
query("set_union", "SELECT c_nationkey AS n FROM customer UNION SELECT s_nationkey FROM supplier")(lambda spark, d: load(spark, d, "customer").select(F.col("c_nationkey").alias("n")).union(load(spark, d, "supplier").select("s_nationkey")).distinct())

# -- files, SQL


def _path(spark, what: str) -> str:
    return scratch(spark, what)


def _roundtrip(fmt: str):
    def run(spark, d):
        at = _path(spark, fmt)
        write(load(spark, d, "nation").select("n_nationkey", "n_regionkey"), at, fmt)
        return read(spark, fmt, at, "n_nationkey int, n_regionkey int")

    return run


for _f in ("csv", "json", "orc"):
    query(f"roundtrip_{_f}", "SELECT n_nationkey, n_regionkey FROM nation")(_roundtrip(_f))


@query("sink_parquet", "SELECT c_custkey, c_nationkey FROM customer WHERE c_nationkey = 3")
def _(spark, d):
    at = _path(spark, "sink")
    write(load(spark, d, "customer").select("c_custkey", "c_nationkey"), at, partition_by=["c_nationkey"], sort_by=["c_custkey"])
    return spark.read.parquet(at).filter("c_nationkey = 3").select("c_custkey", "c_nationkey")


@query("sql_cover_join", W04_SQL)
def _(spark, d):
    q = three(edges(spark, d))
    for r in q.relations:
        r.df.createOrReplaceTempView(f"edge_{r.name.lower()}")
    return cover_join(spark, "edge_r NATURAL JOIN edge_s NATURAL JOIN edge_t").select("a", "b", "c")


@query("sql_cover_bound", f"WITH e AS ({REL['edges']}) SELECT CAST(floor(power(count(*), 1.5) + 1e-6) AS BIGINT) AS bound, CAST(floor(power(count(*), 1.5) + 1e-6) AS BIGINT) AS report FROM e")
def _(spark, d):
    scalar.register(spark)
    n = edges(spark, d).count()
    return spark.sql(f"SELECT CAST(floor(cover_bound(array({n}L, {n}L, {n}L), array(0.5D, 0.5D, 0.5D)) + 1e-6) AS BIGINT) AS bound, CAST(r.value AS BIGINT) AS report FROM bound_report('a,b;b,c;a,c', '{n};{n};{n}') r WHERE r.measure = 'cover'")


@query("sql_cells", f"WITH e AS ({REL['edges']}) SELECT count(*) * 4 AS n_rows, CAST(8 AS BIGINT) AS n_cells FROM e")
def _(spark, d):
    """The table function that deals a row to its cells: two of three attributes are known, the third has four shares."""
    scalar.register(spark)
    edges(spark, d).createOrReplaceTempView("edges_to_deal")
    return spark.sql("SELECT count(*) AS n_rows, count(DISTINCT c.cell) AS n_cells FROM edges_to_deal e, LATERAL cells(array(e.x, e.y, NULL), array(2, 1, 4)) c")


@query("guard_output", "SELECT TRUE AS refused")
def _(spark, d):
    try:
        planner.join(three(edges(spark, d)), max_output_rows=10)
    except planner.TooLarge:
        return spark.createDataFrame([(True,)], "refused boolean")
    return spark.createDataFrame([(False,)], "refused boolean")


@query("observed_rows", f"SELECT count(*) AS n_rows FROM ({W04_SQL})")
def _(spark, d):
    df, told = metrics.observed(allbutone.triangle(three(edges(spark, d))), f"rows-{uuid.uuid4().hex}")
    df.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(told(),)], "n_rows long")


# -- streams


def _stream(name: str, make, sql: str, mode: str = "append"):
    def run(spark, d):
        return streams.drain(make(streams.source(spark, d)), f"{name}_{uuid.uuid4().hex[:8]}", mode)

    query(name, sql)(run)


_stream("stream_source", lambda s: s.select("event_id", "user_id"), "SELECT event_id, user_id FROM events")
_stream("stream_tumbling", streams.tumbling, "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n_events FROM events GROUP BY ALL", "complete")
_stream("stream_sliding", streams.sliding, "SELECT time_bucket(INTERVAL 15 MINUTE, ts) - to_minutes(15 * k) AS start, count(*) AS n_events FROM events CROSS JOIN (SELECT unnest(range(4)) AS k) GROUP BY ALL", "complete")
_stream("stream_heavy", lambda s: streams.heavy_per_window(s, 5), "SELECT date_trunc('day', ts) AS start, user_id, count(*) AS degree FROM events GROUP BY ALL HAVING count(*) > 5", "complete")
_stream("stream_dedupe", lambda s: streams.as_set(s, ["user_id", "event_type"], "3650 days").select("user_id", "event_type"), "SELECT DISTINCT user_id, event_type FROM events")
query("stream_session", """WITH l AS (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 30 MINUTE, TRUE) AS fresh FROM events), s AS (SELECT *, sum(fresh::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM l)
    SELECT user_id, min(ts) AS start, count(*) AS n_events FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR""")(lambda spark, d: streams.drain(streams.sessions(streams.source(spark, d)), f"stream_session_{uuid.uuid4().hex[:8]}"))
query("stream_watermark", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n_events FROM events GROUP BY ALL HAVING date_trunc('day', min(ts)) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")(lambda spark, d: streams.drain(streams.tumbling(streams.source(spark, d)), f"stream_watermark_{uuid.uuid4().hex[:8]}"))
query("stream_handoff", "SELECT event_type, least(u, v) AS x, greatest(u, v) AS y FROM (SELECT event_type, user_id AS u, lag(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS v FROM events) WHERE u <> v")(lambda spark, d: streams.drain(streams.last_user(streams.source(spark, d)), f"stream_handoff_{uuid.uuid4().hex[:8]}"))


@query("stream_static_triangle", f"WITH e AS ({REL['edges']}) SELECT r.x, s.y AS z, r.y FROM e r JOIN e s ON s.x = r.x JOIN e t ON t.x = s.y AND t.y = r.y")
def _(spark, d):
    at = _path(spark, "edges")
    write(edges(spark, d), at)
    s = spark.readStream.schema("x long, y long").parquet(at)
    return streams.drain(streams.static_triangle(s, spark.read.parquet(at)), f"static_{uuid.uuid4().hex[:8]}")


@query("stream_delta_triangle", W04_SQL)
def _(spark, d):
    at = _path(spark, "edge-stream")
    write(edges(spark, d).repartition(3, "x"), at)
    s = spark.readStream.schema("x long, y long").option("maxFilesPerTrigger", 2).parquet(at)
    return streams.delta_triangle(s, "edges")
