"""Near-duplicate texts: circulant MinHash, banding, and exact verification on full shingle sets.

Two permutations of 0 .. 2^32 - 1 make the whole signature: the first places a shingle, the second, shifted circularly by k, gives
coordinate k as its least value over the set. Texts with equal sets are one class from the start. Classes that share a band
are joined with the band's smallest member only; the components of these links are families, and every link between two
texts lies inside a family (up to the chance that all bands miss it: below 1e-4 at the similarity of 0.8, and much less
above). Inside a family full sets are compared in blocks of a bounded size, and only links that join two components are
given out.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut, hash_words, mix64, parts, small_batches, split_words

ROWS, BANDS = 5, 25
#: Shingles and members of a block at most (a larger single set is a block of its own).
BLOCK_SHINGLES, BLOCK_MEMBERS = 2 << 20, 4096
#: Of the filter that keeps most documents without a family out of the second pass; any size gives the same result.
FILTER_BITS = 1 << 23


def shingle_sets(texts: pa.Array, n: int) -> list[np.ndarray]:
    """Distinct hashed n-word shingles of each text, sorted; with fewer words the whole sequence is one; none without words."""
    flat, off = split_words(texts, lower=True)
    h = hash_words(flat)
    out = []
    for a, b in zip(off[:-1], off[1:]):
        w = h[a:b]
        if not len(w):
            out.append(w)
            continue
        m = min(n, len(w))
        s = w[: len(w) - m + 1]
        for k in range(1, m):
            s = mix64(s) + w[k : len(w) - m + 1 + k]
        out.append(np.unique(mix64(s + np.uint64(m))))
    return out


def _place(x: np.ndarray) -> np.ndarray:
    """First permutation: where a shingle's hash lies on the circle."""
    x = x.astype(np.uint32)
    x = (x ^ (x >> np.uint32(16))) * np.uint32(0x7FEB352D)
    x = (x ^ (x >> np.uint32(15))) * np.uint32(0x846CA68B)
    return x ^ (x >> np.uint32(16))


def signatures(sets: list[np.ndarray], coordinates: int = ROWS * BANDS, step: int = 1 << 15) -> np.ndarray:
    """One row per set (empty sets: the largest value everywhere)."""
    out = np.full((len(sets), coordinates), 0xFFFFFFFF, np.uint32)
    at = 0
    while at < len(sets):
        to, total = at, 0
        while to < len(sets) and (to == at or total + len(sets[to]) <= step):
            total += len(sets[to])
            to += 1
        full = [i for i in range(at, to) if len(sets[i])]
        if full:
            where = _place(np.concatenate([sets[i] for i in full]) >> np.uint64(32))
            starts = np.cumsum([0] + [len(sets[i]) for i in full[:-1]])
            for k in range(coordinates):
                x = where + np.uint32(k)  # the second permutation, shifted by k
                x ^= x >> np.uint32(16)
                x *= np.uint32(0x85EBCA6B)
                x ^= x >> np.uint32(13)
                x *= np.uint32(0xC2B2AE35)
                x ^= x >> np.uint32(16)
                out[full, k] = np.minimum.reduceat(x, starts)
        at = to
    return out


def bands(sig: np.ndarray, rows: int = ROWS) -> np.ndarray:
    """64-bit hash of each band, distinct between bands."""
    n = sig.shape[1] // rows
    h = np.broadcast_to(np.arange(1, n + 1, dtype=np.uint64) << np.uint64(40), (len(sig), n)).copy()
    for r in range(rows):
        h = mix64(h + sig[:, r::rows].astype(np.uint64))
    return h.view(np.int64)


def _joins(ids: np.ndarray, sets: list[np.ndarray], own: np.ndarray, least: tuple[int, int], across: bool) -> list[tuple[int, int]]:
    """Links of a spanning forest over the sets whose similarity is at least least[0] / least[1]; across: only between
    different values of own."""
    size = np.array([len(s) for s in sets])
    order = np.lexsort((ids, size))
    ids, own, size = ids[order], own[order], size[order]
    _, flat = np.unique(np.concatenate([sets[i] for i in order]), return_inverse=True)
    off = np.concatenate([[0], np.cumsum(size)])
    mark = np.zeros(int(flat.max()) + 1 if len(flat) else 1, np.int32)
    label = np.arange(len(ids))
    out = []
    top = np.searchsorted(size, size * least[1] // least[0], side="right")
    for x in range(len(ids) - 1):
        a, b = x + 1, int(top[x])
        ask = label[a:b] != label[x]
        if across:
            ask &= own[a:b] != own[x]
        if b <= a or not ask.any():
            continue
        mine = flat[off[x] : off[x + 1]]
        mark[mine] = 1
        common = np.add.reduceat(mark[flat[off[a] : off[b]]], off[a:b] - off[a])
        mark[mine] = 0
        for y in np.flatnonzero(ask & (least[1] * common >= least[0] * (size[x] + size[a:b] - common))) + a:
            if label[y] != label[x]:
                out.append((int(ids[x]), int(ids[y])))
                label[label == label[y]] = label[x]
    return out


def near_duplicates(docs: DataFrame, shingle: int = 5, least: tuple[int, int] = (80, 100), rows: int = ROWS, n_bands: int = BANDS, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per row of ``docs``: key, n_shingles (size of its set), component_id (smallest key reachable over links, itself
    included), kept (key = component_id). Two texts are linked if the sizes of their sets' intersection and union satisfy
    least[1] * intersection >= least[0] * union.

    Null and empty texts, and texts without words, have empty sets and link with nothing; so do rows with a null key. Rows
    that repeat a key count as one node; with equal texts they give equal rows. An empty table gives no rows. Texts are
    read twice: once for signatures, once for the members of families.

    rows, n_bands: texts of similarity s share a band with probability 1 - (1 - s ** rows) ** n_bands. Families grow with chance
    collisions, n_bands * s ** rows for each of the other texts: for billions of texts of one kind take more rows (8 by 54
    misses no more links than 5 by 25 and has 1e4 times fewer collisions at a similarity of 0.05).
    """
    spark = docs.sparkSession
    docs = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))

    def sketch(batches):
        for b in small_batches(batches):
            sets = shingle_sets(b.column(1), shingle)
            sig = bands(signatures(sets, rows * n_bands), rows)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) and i is not None else None for s, i in zip(sets, b.column(0).to_pylist())], pa.binary()), pa.array([r.tobytes() if len(s) else None for r, s in zip(sig, sets)], pa.binary())],
                ["id", "n", "same", "bands"],
            )

    sketched = cut(docs.mapInArrow(sketch, "id long, n long, same binary, bands binary"), "minhash-sketch")
    classes = cut(sketched.filter("same is not null").groupBy("same").agg(F.min("id").alias("rep"), F.first("n").alias("n"), F.first("bands").alias("bands")), "minhash-classes")

    def spread(batches):
        for b in batches:
            h = np.frombuffer(b"".join(b.column(1).to_pylist()), np.int64)
            n = len(h) // max(1, b.num_rows)
            yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(np.repeat(b.column(0).to_numpy(), n))], ["h", "rep"])

    members = classes.select("rep", "bands").mapInArrow(spread, "h long, rep long")
    hubs = members.groupBy("h").agg(F.min("rep").alias("hub"), F.max("rep").alias("last")).filter("last > hub").select("h", "hub")
    stars = members.join(hubs, "h").filter("rep <> hub").select("rep", "hub").distinct()
    family = components(stars, "rep", "hub", "minhash-families").withColumnRenamed("component_id", "family")
    members = classes.select(F.col("rep").alias("node"), "n").join(family, "node")
    sizes = members.groupBy("family").agg(F.greatest(F.ceil(F.sum("n") / BLOCK_SHINGLES), F.ceil(F.count("*") / BLOCK_MEMBERS)).cast("int").alias("nb"))
    members = cut(members.select("node", "family").distinct().join(sizes, "family"), "minhash-members")

    # a bit set of fixed size tells most documents outside families apart before their sets are made and sent
    slot = F.pmod(F.xxhash64("node"), F.lit(FILTER_BITS))
    words = members.select(F.shiftright(slot, 6).alias("w"), F.expr(f"shiftleft(1L, cast(pmod(xxhash64(node), {FILTER_BITS}) % 64 as int))").alias("x")).groupBy("w").agg(F.bit_or("x").alias("x")).collect()
    bits = np.zeros(FILTER_BITS // 64, np.int64)
    bits[[r["w"] for r in words]] = [r["x"] for r in words]
    sent = spark.sparkContext.broadcast(bits)

    def sets_of(batches):
        for b in batches:
            at = b.column(2).to_numpy()
            maybe = (sent.value[at >> 6] >> (at & 63)) & 1 == 1
            for c in small_batches([b.filter(pa.array(maybe))]):
                yield pa.RecordBatch.from_arrays([c.column(0), pa.array([s.tobytes() for s in shingle_sets(c.column(1), shingle)], pa.binary())], ["id", "shingles"])

    found = docs.filter("id is not null").select("id", "text", F.pmod(F.xxhash64("id"), F.lit(FILTER_BITS)).alias("slot")).mapInArrow(sets_of, "id long, shingles binary")
    # always a merge join: the list of members grows with the table, and a plan that changes with the size would, too
    full = found.join(members.hint("merge"), found["id"] == members["node"]).select("node", "family", "nb", "shingles").filter(F.octet_length("shingles") > 0)
    dealt = full.withColumn("own", F.pmod(F.xxhash64("node"), F.col("nb")).cast("int")).withColumn("o", F.explode(F.expr("sequence(0, nb - 1)"))).withColumn("i", F.least("own", "o")).withColumn("j", F.greatest("own", "o"))
    unit = ["family", "i", "j"]
    placed = dealt.select(*unit, "own", "node", "shingles").repartition(parts(spark), *unit).sortWithinPartitions(*unit, "own", "node")

    def verify(batches):
        now, held, out = None, [], []

        def close():
            if len(held) > 1:
                ids, own = np.array([h[1] for h in held]), np.array([h[0] for h in held])
                out.extend(_joins(ids, [np.frombuffer(h[2], np.uint64) for h in held], own, least, now[1] != now[2]))

        def pack():
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], ["a", "b"])

        for b in batches:
            for row in zip(*(c.to_pylist() for c in b.columns)):
                if row[:3] != now:
                    close()
                    now, held = row[:3], []
                held.append(row[3:])
            if len(out) > 20000:
                yield pack()
                out = []
        close()
        if out:
            yield pack()

    links = placed.mapInArrow(verify, "a long, b long")
    found = components(links, what="minhash-components")
    salts = 16
    told = classes.select("same", "rep").join(found, classes["rep"] == found["node"], "left").select("same", F.coalesce("component_id", "rep").alias("component_id"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    own = F.coalesce("component_id", "id")
    return (
        sketched.select("id", "n", "same", F.pmod(F.xxhash64("id"), F.lit(salts)).cast("int").alias("salt"))
        .join(told, ["same", "salt"], "left")
        .select(F.col("id").alias(key), F.col("n").alias("n_shingles"), own.alias("component_id"), F.coalesce(F.col("id") == own, F.lit(True)).alias("kept"))
    )
