"""Near-duplicate vectors by spherical-cap filters from random product codes.

A unit vector is cut into ``blocks`` parts. Each part has a codebook of random unit directions; a filter takes one direction of
each book, and its score for a vector is the sum of the parts' inner products. A vector belongs to all filters whose score
exceeds a threshold, found by list decoding: partial sums that cannot reach it any more are dropped. Vectors are joined on
common filters, and each pair is verified by its exact cosine, once, in its smallest common filter.
"""

from __future__ import annotations

import hashlib
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut, parts
from .vectors import scaled, usable

BLOCK = 1536


class Code:
    """Random product code for vectors of ``dim`` numbers: size ** blocks filters, of which a vector gets about ``lists``."""

    def __init__(self, dim: int, size: int, lists: int, blocks: int = 4, seed: int = 5):
        blocks = max(1, min(blocks, dim // 2))
        rng = np.random.default_rng([seed, dim])
        self.turn = np.linalg.qr(rng.standard_normal((dim, dim)))[0]  # spreads a vector evenly over the parts
        edges = np.linspace(0, dim, blocks + 1).astype(int)
        self.parts = list(zip(edges[:-1], edges[1:]))
        self.books = []
        for a, b in self.parts:
            c = rng.standard_normal((size, b - a))
            self.books.append(c / np.linalg.norm(c, axis=1, keepdims=True))
        self.size, self.lists = size, lists
        share = min(0.5, lists / size**blocks)
        self.least = NormalDist().inv_cdf(1 - share) * np.sqrt(blocks / dim)

    def decode(self, u: np.ndarray) -> np.ndarray:
        """Filters of a unit vector, ascending: those above the threshold, and at least lists / 2 of the best."""
        v = u @ self.turn
        scores = [book @ v[a:b] for (a, b), book in zip(self.parts, self.books)]
        rest = np.append(np.cumsum([s.max() for s in scores][::-1])[::-1], 0.0)
        least = min(self.least, rest[0] * 0.999)
        while True:
            ids, sums = np.zeros(1, np.int64), np.zeros(1)
            for i, s in enumerate(scores):
                total = sums[:, None] + s[None, :]
                keep = total + rest[i + 1] >= least
                ids, sums = (ids[:, None] * self.size + np.arange(self.size)[None, :])[keep], total[keep]
            if len(ids) >= min(self.lists // 2, self.size ** len(scores)):
                break
            least -= 0.05
        return np.sort(ids)


def _links(x: np.ndarray, f: int, lists: list[np.ndarray], least: float, split: int | None) -> np.ndarray:
    """Boolean matrix of the verified pairs whose smallest common filter is f. split: only pairs across this row."""
    n = np.sqrt((x * x).sum(axis=1))
    u = x / n[:, None]
    near = u @ u.T >= least - 1e-9
    np.fill_diagonal(near, False)
    if split is not None:
        near[:split, :split] = near[split:, split:] = False
    a, b = np.nonzero(np.triu(near))
    if not len(a):
        return np.zeros_like(near)
    for at in range(0, len(a), 1 << 16):  # exactly, in double precision
        i, j = a[at : at + (1 << 16)], b[at : at + (1 << 16)]
        far = (x[i] * x[j]).sum(axis=1) / (n[i] * n[j]) < least
        near[i[far], j[far]] = near[j[far], i[far]] = False
    rows = np.unique(np.concatenate([a, b]))
    flat = [lists[r][lists[r] < f] for r in rows]
    ids, inv, many = np.unique(np.concatenate(flat), return_inverse=True, return_counts=True)
    who = np.repeat(np.arange(len(rows)), [len(z) for z in flat])
    ok = many[inv] > 1
    if ok.any():
        cols, inv = np.unique(inv[ok], return_inverse=True)
        earlier = np.zeros((len(rows), len(rows)), bool)
        for c in range(0, len(cols), 4096):
            m = np.zeros((len(rows), min(4096, len(cols) - c)), np.float32)
            here = (inv >= c) & (inv < c + 4096)
            m[who[ok][here], inv[here] - c] = 1
            earlier |= (m @ m.T) > 0
        near[np.ix_(rows, rows)] &= ~earlier
    return near


def _roots(near: np.ndarray) -> np.ndarray:
    """Smallest row index reachable over the links, by repeated minima."""
    label = np.arange(len(near))
    a, b = np.nonzero(near)
    while len(a):
        low = label.copy()
        np.minimum.at(low, a, label[b])
        low = low[low]
        if (low == label).all():
            break
        label = low
    return label


def near_duplicates(rows: DataFrame, least: float = 0.98, lists: int = 20, seed: int = 5, key: str = "vec_id", vector: str = "embedding", label: str | None = "label") -> DataFrame:
    """One row per input row: key, n_links (other rows linked to it directly), component_id (smallest key reachable, itself
    included), kept (key = component_id). Two rows are linked if their labels are equal and not null (where ``label`` is
    named), both vectors are usable and of equal length, and their cosine is at least ``least``.

    Vectors that are null, zero, or hold null or non-finite components, and rows with a null label or key, link with nothing.
    Rows with equal label and vector are one class: they are linked with each other, and the class is compared once. Repeated
    keys with unequal vectors are separate rows of one component. An empty table gives no rows. The number of filters grows
    with the table; a filter with many classes is split into pairs of blocks of a bounded size.
    """
    lab = F.col(label) if label else F.lit(0)
    # a float is exact in 32 bits: rows that meet in filters carry vectors as narrow as they came
    item = getattr(rows.schema[vector].dataType, "elementType", None)
    kind_of = np.dtype(np.float32 if item is not None and item.typeName() == "float" else np.float64)
    base = rows.select(F.col(key).cast("long").alias("id"), lab.alias("label"), F.col(vector).cast("array<double>").alias("v"), (usable(F.col(vector)) & lab.isNotNull() & F.col(key).isNotNull()).alias("ok"))

    def classify(batches):
        for b in batches:
            vs = b.column(2).to_pylist()
            ok = b.column(3).to_pylist()
            raw = [np.asarray(v, np.float64) + 0.0 if o else None for v, o in zip(vs, ok)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([None if r is None else hashlib.blake2b(r.tobytes(), digest_size=16).digest() for r in raw], pa.binary()), pa.array([None if r is None else r.astype(kind_of).tobytes() for r in raw], pa.binary())], ["id", "label", "same", "v"])

    kind = dict(base.dtypes)["label"]
    keyed = cut(base.mapInArrow(classify, f"id long, label {kind}, same binary, v binary"), "caps-rows")
    classes = keyed.filter("same is not null").groupBy("label", "same").agg(F.min("id").alias("rep"), F.count("*").alias("n"), F.first("v").alias("v"))
    classes = cut(classes, "caps-classes")
    total = classes.count()
    size = max(16, int(np.ceil((max(total, 1) * lists / 4) ** 0.25)))

    filter_kind = np.dtype(np.int32 if size**4 < 1 << 31 else np.int64)

    def decode(batches):
        codes: dict[int, Code] = {}
        for b in batches:
            out = []
            for lb, rep, n, v in zip(*(b.column(c).to_pylist() for c in ("label", "rep", "n", "v"))):
                x = np.frombuffer(v, kind_of).astype(np.float64)
                s = scaled(x[None, :])[0]
                code = codes.setdefault(len(x), Code(len(x), size, lists, seed=seed))
                fs = code.decode(s / np.linalg.norm(s))
                raw = fs.astype(filter_kind).tobytes()
                out += [(lb, len(x), int(f), rep, n, v, raw) for f in fs]
                if len(out) > 4000:
                    yield pack(out)
                    out = []
            if out:
                yield pack(out)

    def pack(out):
        names = ["label", "dim", "f", "rep", "n", "v", "fs"]
        types = [None, pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]
        cols = list(zip(*out))
        return pa.RecordBatch.from_arrays([pa.array(c, t) if t else pa.array(c, lab_type) for c, t in zip(cols, types)], names)

    from pyspark.sql.pandas.types import to_arrow_type

    lab_type = to_arrow_type(keyed.schema["label"].dataType)
    members = classes.mapInArrow(decode, f"label {kind}, dim int, f long, rep long, n long, v binary, fs binary")
    members = cut(members, "caps-filters")
    by = ["label", "dim", "f"]
    sizes = members.groupBy(*by).agg(F.count("*").alias("c")).filter("c > 1").withColumn("nb", F.ceil(F.col("c") / BLOCK).cast("int"))
    dealt = members.join(sizes.drop("c"), by).withColumn("own", F.pmod(F.xxhash64("rep"), F.col("nb")).cast("int"))
    # block i meets block j in the pair (i, j), i <= j
    dealt = dealt.withColumn("o", F.explode(F.expr("sequence(0, nb - 1)"))).withColumn("i", F.least("own", "o")).withColumn("j", F.greatest("own", "o"))
    unit = [*by, "i", "j"]
    placed = dealt.select(*unit, "own", "rep", "n", "v", "fs").repartition(parts(members.sparkSession), *unit).sortWithinPartitions(*unit, "own", "rep")

    def verify(batches):
        now, held, out = None, [], []

        def close():
            if len(held) < 2:
                return
            x = scaled(np.stack([np.frombuffer(h[3], kind_of) for h in held]).astype(np.float64))
            i, j = now[3], now[4]
            split = None if i == j else sum(h[0] == i for h in held)
            if split is not None and not 0 < split < len(held):
                return
            near = _links(x, now[2], [np.frombuffer(h[4], filter_kind).astype(np.int64) for h in held], least, split)
            n = np.array([h[2] for h in held])
            deg, root = near.astype(np.float64) @ n, _roots(near)
            for t in np.flatnonzero(deg):
                out.append((held[t][1], held[root[t]][1], int(deg[t])))

        for b in batches:
            cols = [b.column(c).to_pylist() for c in (*unit, "own", "rep", "n", "v", "fs")]
            for row in zip(*cols):
                if row[:5] != now:
                    close()
                    now, held = row[:5], []
                held.append(row[5:])
            if len(out) > 20000:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], ["a", "b", "links"])
                out = []
        close()
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], ["a", "b", "links"])

    edges = cut(placed.mapInArrow(verify, "a long, b long, links long"), "caps-links")
    links = edges.groupBy(F.col("a").alias("rep")).agg(F.sum("links").alias("links"))
    comp = components(edges, what="caps-components").withColumnRenamed("node", "rep")
    told = classes.select("label", "same", "rep", "n").join(links, "rep", "left").join(comp, "rep", "left").select("label", "same", (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component_id", "rep").alias("component_id"))
    # a hot class is spread over salts
    salts = 16
    told = told.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    out = keyed.drop("v").withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(salts)).cast("int")).join(told, ["label", "same", "salt"], "left")
    found = F.coalesce("component_id", "id")
    return out.select(F.col("id").alias(key), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), found.alias("component_id"), F.coalesce(F.col("id") == found, F.lit(True)).alias("kept"))
