"""Mixing sources to target weights by a low-discrepancy schedule.

Each source's texts, put in a shuffled order, form a stream of words that is cut into blocks of equal length. A schedule of
slots decides which source gives the next block: slot i of N takes the lattice point ``i * g mod N`` with g coprime to N and
nearest to N / golden ratio, and maps it through the sources' cumulative slot counts. As those points are a permutation of
0..N-1, every source gets exactly its count of slots, and any stretch of the schedule holds each source near its share.
Slots are ranked per source and joined with the source's blocks; past the end of a stream the next epoch begins.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import WORD, cut, plain

GOLDEN = (1 + math.sqrt(5)) / 2


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def default_weights(sources: list[str | None], cycle: tuple[float, ...] = (5, 2, 1)) -> dict[str | None, float]:
    """Sources by code point, null last, get the weights of ``cycle`` in turn."""
    order = sorted((s for s in sources if s is not None), key=lambda s: s.encode()) + [None] * (None in sources)
    return {s: float(cycle[i % len(cycle)]) for i, s in enumerate(order)}


def targets(sizes: dict, weights: dict, most: int = 3, total: int | None = None) -> dict:
    """Words to take from each source: weight shares of ``total`` (default: all words), none above ``most`` times its
    source's size; what is cut off is shared again by weight among the others until none is above. Sources without a
    positive weight or words get 0."""
    total = sum(sizes.values()) if total is None else total
    out = {s: 0.0 for s in sizes}
    live = {s for s in sizes if sizes[s] > 0 and weights.get(s, 0) > 0}
    left = float(total)
    while live:
        w = math.fsum(weights[s] for s in live)
        over = {s for s in live if left * weights[s] / w > most * sizes[s]}
        if not over:
            for s in live:
                out[s] = left * weights[s] / w
            break
        for s in over:
            out[s] = float(most * sizes[s])
        left -= math.fsum(most * sizes[s] for s in over)
        live -= over
    return out


def lattice_step(n: int) -> int:
    """The number coprime to n that is nearest to n / golden ratio."""
    g = max(1, round(n / GOLDEN))
    for d in range(n + 1):
        for c in (g - d, g + d):
            if 1 <= c and math.gcd(c, n) == 1:
                return c
    return 1


def ranked(df: DataFrame, keys: list[str], spread: Column, order: list[Column], add: Column, out: str, pieces: int) -> DataFrame:
    """Running sum of ``add`` before each row within ``keys``, in the order of (spread, order). spread: a number in [0, 1)
    that rows of one key are sorted by first. A key is cut into ``pieces`` ranges of it, so that no task holds a whole key:
    ranges are summed first, and only the small table of sums is put in sequence per key."""
    df = df.withColumn("_piece", F.floor(spread * pieces).cast("int")).withColumn("_add", add)
    sums = df.groupBy(*keys, "_piece").agg(F.sum("_add").alias("_sum"))
    before = sums.withColumn("_base", F.coalesce(F.sum("_sum").over(W.partitionBy(*keys).orderBy("_piece").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).drop("_sum")
    own = F.coalesce(F.sum("_add").over(W.partitionBy(*keys, "_piece").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return df.withColumn("_own", own).join(before, [*keys, "_piece"]).withColumn(out, (F.col("_own") + F.col("_base")).cast("long")).drop("_piece", "_add", "_own", "_base")


def mix(docs: DataFrame, weights=None, block: int = 1024, most: int = 3, total: int | None = None, seed: int = 0, text: str = "text", source: str = "source", key: str = "doc_id"):
    """Mix ``docs`` to target weights. Returns (sources, schedule, spans, sized):

    - sources: source, source_size, target, take (whole words) - one row per source; None where there are no rows.
    - schedule: slot, source, rank, epoch position as (lo, hi) in the source's stream, hi exclusive.
    - spans: slot, source, row, key, epoch, from_word, to_word: what each slot takes of each document, whole words.
    - sized: row, key, source, size, hash, one row per input row; ``row`` links spans to it where keys repeat.

    weights: source -> weight, or a function of the list of sources (default: 5, 2, 1 by code point, null last). Sources are
    the unit in which weights are stated, so their totals fit the driver; documents, slots and blocks stay distributed.
    Null or empty texts have size 0 and are never taken. Repeated keys are separate documents with equal keys. An empty
    table gives empty results. A rerun agrees: order depends on seed, source, key and text only.
    """
    spark = docs.sparkSession
    sized = docs.select(F.col(key).alias("key"), F.col(source).alias("source"), word_count(F.col(text)).alias("size"), F.xxhash64(F.lit(seed), F.col(key), F.col(text)).alias("_h"), F.monotonically_increasing_id().alias("row"))
    sized = cut(sized, "mix-sizes")
    got = sized.groupBy("source").agg(F.sum("size").alias("n"), F.count("*").alias("c")).collect()
    sizes = {r["source"]: int(r["n"]) for r in got}
    weights = (weights or default_weights)(list(sizes)) if weights is None or callable(weights) else weights
    want = targets(sizes, weights, most, total)
    take = {s: min(round(want[s]), most * sizes[s]) for s in sizes}
    slots = {s: -(-take[s] // block) for s in sizes}
    n = sum(slots.values())
    src = [(s, sizes[s], want[s], take[s]) for s in sizes]
    sources = spark.createDataFrame(src, "source string, source_size long, target double, take long")
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    ends, at = [], 0
    for s in order:
        at += slots[s]
        ends.append(at)
    step = lattice_step(max(n, 1))
    # slots: the lattice point, then the number of cumulative counts at or below it
    point = F.expr(f"cast((cast(id as decimal(20,0)) * {step}) % {max(n, 1)} as long)")
    which = F.expr(f"size(filter(array({', '.join(f'{e}L' for e in ends) or '0L'}), e -> e <= point))")
    chosen = spark.range(n).select(F.col("id").alias("slot"), point.alias("point")).withColumn("s", which)
    pieces = max(1, n >> 16)
    placed = ranked(chosen.drop("point"), ["s"], F.col("slot") / max(n, 1), [F.col("slot")], F.lit(1), "rank", pieces)
    names = spark.createDataFrame([(i, s, sizes[s], take[s]) for i, s in enumerate(order)], "s int, source string, n long, take long")
    schedule = placed.join(F.broadcast(names), "s").select("slot", "source", F.col("rank"), (F.col("rank") * block).alias("lo"), F.least((F.col("rank") + 1) * block, F.col("take")).alias("hi"), "n")
    # a slot's words by epoch, then by block of the source's stream
    parts = schedule.withColumn("epoch", F.explode(F.expr("sequence(lo div n, (hi - 1) div n)"))).select("slot", "source", "epoch", F.greatest(F.lit(0), F.expr("lo - epoch * n")).alias("p"), F.least(F.col("n"), F.expr("hi - epoch * n")).alias("q"))
    cells = parts.withColumn("block", F.explode(F.expr(f"sequence(p div {block}, (q - 1) div {block})")))
    rows = sum(r["c"] for r in got)
    stream = ranked(sized.filter("size > 0").withColumn("source", F.col("source")).withColumn("_null", F.col("source").isNull()).fillna("", ["source"]), ["source", "_null"], (F.shiftrightunsigned("_h", 11) / float(1 << 53)), [F.col("_h"), F.col("key"), F.col("size"), F.col("row")], F.col("size"), "start", max(64, rows >> 14))
    blocks = stream.withColumn("block", F.explode(F.expr(f"sequence(start div {block}, (start + size - 1) div {block})")))
    cells = cells.withColumn("_null", F.col("source").isNull()).fillna("", ["source"])
    spans = cells.join(blocks, ["source", "_null", "block"]).select(
        "slot", F.when(~F.col("_null"), F.col("source")).alias("source"), "row", "key", "epoch",
        (F.greatest(F.expr(f"greatest(p, block * {block})"), F.col("start")) - F.col("start")).alias("from_word"),
        (F.least(F.expr(f"least(q, (block + 1) * {block})"), F.col("start") + F.col("size")) - F.col("start")).alias("to_word"),
    ).filter("to_word > from_word")
    return sources, schedule.drop("n"), spans, sized.withColumnRenamed("_h", "hash")


def mixed(docs: DataFrame, weights=None, block: int = 1024, most: int = 3, seed: int = 0, text: str = "text", source: str = "source", key: str = "doc_id", counter: str | None = None) -> DataFrame:
    """The mix as rows of ``docs``: one row per time that a document is taken whole, and for one taken in part a row with its
    first words, joined by one space. Documents that the mix does not take are not there. counter: also keep this length
    column true ("n_chars" by default where there is one). Rows that repeat key and text share what is taken of them."""
    _, _, spans, sized = mix(docs, weights, block, most, None, seed, text, source, key)
    counter = counter or ("n_chars" if "n_chars" in docs.columns else None)
    taken = spans.groupBy("row").agg(F.sum(F.col("to_word") - F.col("from_word")).alias("_taken"))
    taken = sized.join(taken, "row").groupBy(F.col("key").alias("_key"), F.col("hash").alias("_own_hash")).agg(F.sum("_taken").alias("_taken"), F.first("size").alias("_size"))
    given = docs.columns
    docs, to = plain(docs)
    key, text, counter = to[key], to[text], to.get(counter)
    linked = docs.withColumn("_hash", F.xxhash64(F.lit(seed), F.col(key), F.col(text))).join(taken, F.col(key).eqNullSafe(F.col("_key")) & (F.col("_hash") == F.col("_own_hash")))
    # of equal rows the first are served first
    turn = F.row_number().over(W.partitionBy(key, "_hash").orderBy(F.lit(0))) - 1
    own = F.least(F.col("_size") * most, F.greatest(F.lit(0), F.col("_taken") - F.col("_turn") * F.col("_size") * most))
    copies = linked.withColumn("_turn", turn).withColumn("_own", own).filter("_own > 0").withColumn("_copy", F.explode(F.expr("sequence(1, cast((_own + _size - 1) div _size as int))")))
    left = F.least(F.col("_size"), F.col("_own") - (F.col("_copy") - 1) * F.col("_size")).cast("int")
    part = F.col("_left") < F.col("_size")
    short = F.array_join(F.slice(F.regexp_extract_all(F.col(text), F.lit(WORD), F.lit(0)), F.lit(1), F.col("_left")), " ")
    out = copies.withColumn("_left", left).withColumn(text, F.when(part, short).otherwise(F.col(text)))
    if counter:
        out = out.withColumn(counter, F.when(part, F.char_length(text).cast("long")).otherwise(F.col(counter)))
    return out.select(*(F.col(to[c]).alias(c) for c in given))
