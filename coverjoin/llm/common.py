"""Shared parts of the training-data operators: lineage cuts, word splitting, connected components."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import drop, scratch, settle, shared_dir  # noqa: F401

#: A word is a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

def cut(df: DataFrame, what: str = "cut") -> DataFrame:
    """Write the rows as a table in the shared folder and read it back, so that later steps neither repeat the work nor
    depend on the executors that did it."""
    return settle(df, what)


def drop_cut(df: DataFrame) -> None:
    """Delete a table made by cut() that nothing reads any more."""
    drop(df)


def plain(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """The rows under names that clash with none of an operator's own (c0, c1, ...), and these by the names given."""
    to = {c: f"c{i}" for i, c in enumerate(docs.columns)}
    return docs.toDF(*to.values()), to


def named(df: DataFrame, to: dict[str, str], new: dict[str, str]) -> DataFrame:
    """Back under the given names. new: the operator's columns by the names they get; one that is there already is replaced
    in its place, the others follow."""
    return df.select(*(F.col(new.get(c, x)).alias(c) for c, x in to.items()), *(F.col(x).alias(c) for c, x in new.items() if c not in to))


def parts(spark: SparkSession, least: int = 1) -> int:
    return max(least, int(spark.conf.get("spark.sql.shuffle.partitions")))


def split_words(texts: pa.Array, lower: bool = False) -> tuple[pa.Array, np.ndarray]:
    """Words of each text, flat, and the offset of each text's first word. A null text has none."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = pc.fill_null(texts, "")
    lists = pc.ascii_split_whitespace(pc.ascii_lower(texts) if lower else texts)
    flat, off = lists.flatten(), np.asarray(lists.offsets, dtype=np.int64)
    off = off - off[0]
    full = pc.not_equal(flat, "").to_numpy(zero_copy_only=False)
    if full.all():
        return flat, off
    return flat.filter(pa.array(full)), np.concatenate([[0], np.cumsum(full)]).astype(np.int64)[off]


def small_batches(batches, text: str = "text", most: int = 8 << 20):
    """Record batches cut to about ``most`` bytes of text each; a longer text is a batch of its own."""
    for b in batches:
        sizes = np.asarray(pc.fill_null(pc.binary_length(b.column(b.schema.get_field_index(text))), 0), dtype=np.int64)
        if not len(sizes):
            continue
        ends = np.cumsum(sizes)
        at = 0
        while at < len(sizes):
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + most, side="right")))
            yield b.slice(at, to - at)
            at = to


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers whose output bits all depend on all input bits."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def hash_words(flat: pa.Array) -> np.ndarray:
    """64-bit hashes of words; each distinct word of the batch is hashed once."""
    import xxhash

    if not len(flat):
        return np.zeros(0, np.uint64)
    d = flat.dictionary_encode()
    own = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in d.dictionary.cast(pa.binary()).to_pylist()), np.uint64, len(d.dictionary))
    return own[d.indices.to_numpy()]


#: A node with more edges than this, and than its share of 1 / HUBS of all of them, is a hub; so there are at most 2 * HUBS.
HUB_EDGES, HUBS = 512, 1 << 13


def _with_least(pairs: DataFrame, n: int, least_of) -> DataFrame:
    """The pairs (u, v) with the least neighbour m of u. Where u is a hub, the minimum is broadcast, as the number of hubs is
    bounded, so that a hub's edges stay where they are; the others meet theirs in a shuffle."""
    low = cut(pairs.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")), "components-least")
    most = max(HUB_EDGES, 2 * n // HUBS)
    hubs = low.filter(F.col("n") > most).select(F.col("u").alias("hub"), "m")
    if hubs.isEmpty():
        return pairs.join(low.select("u", "m"), "u").withColumn("m", least_of)
    at_hubs = pairs.join(F.broadcast(hubs), F.col("u") == F.col("hub")).select("u", "v", "m")
    others = pairs.join(F.broadcast(hubs.select("hub")), F.col("u") == F.col("hub"), "left_anti").join(low.select("u", "m"), "u").select("u", "v", "m")
    return others.unionByName(at_hubs).withColumn("m", least_of)


def components(edges: DataFrame, a: str = "a", b: str = "b", what: str = "components", most_rounds: int = 64) -> DataFrame:
    """Connected components of an undirected graph by alternating large and small stars.

    edges: two long columns; loops and repeats are allowed. Returns (node, component_id), the smallest node reachable, for
    every node that has an edge to another. Each round is a few shuffles with map-side minima; its result is written to
    the shared folder, so no lineage grows and a lost executor costs one round at most. A hub's edges are never
    gathered in one task.
    """
    e = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).filter("u <> v").distinct()
    e = cut(e, what)
    n, seen = e.count(), None
    for _ in range(most_rounds):
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = cut(_with_least(both, 2 * n, F.least("m", "u")).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), what)
        # large now has u > v, and v is the least neighbour seen from a hub of u
        small = _with_least(large, 2 * n, F.col("m")).select(F.explode(F.array(F.struct("u", F.col("m").alias("w")), F.struct(F.col("v").alias("u"), F.col("m").alias("w")))).alias("x")).select(F.col("x.u").alias("u"), F.col("x.w").alias("v")).filter("u <> v").distinct()
        new = cut(small, what)
        state = tuple(new.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        drop_cut(e)
        drop_cut(large)
        e, n = new, state[0]
        if state == seen:
            return e.select(F.col("u").alias("node"), F.col("v").alias("component_id")).union(e.select(F.col("v").alias("node"), F.col("v").alias("component_id")).distinct())
        seen = state
    raise RuntimeError(f"components: not settled after {most_rounds} rounds")
