"""Toxicity: a linear classifier on character n-grams scaled by naive Bayes log-count ratios.

A text's features are the distinct hashed n-grams of its lower-cased bytes, each scaled by the log ratio of its smoothed
frequencies in the two classes; a ridge-penalised logistic regression is fitted on the scaled features. Labels come from a
bounded, balanced sample of labelled rows (``per_class``), smallest key hashes first; every text is scored whole.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, drop_cut, small_batches

GRAMS = (3, 4, 5)
BITS = 20


@dataclass(frozen=True)
class Model:
    weight: np.ndarray  # float32, by hashed n-gram; zero where unused
    bias: float
    bits: int = BITS
    grams: tuple[int, ...] = GRAMS


def gram_ids(text: bytes | np.ndarray, bits: int = BITS, grams: tuple[int, ...] = GRAMS) -> list[np.ndarray]:
    """Hashed n-grams at each position, one array per length."""
    b = np.frombuffer(text, np.uint8).astype(np.uint32) if isinstance(text, bytes) else text
    out, h = [], np.zeros(len(b), np.uint32)
    for n in range(1, max(grams) + 1):
        if len(b) < n:
            break
        h = (h[: len(b) - n + 1] ^ b[n - 1 :]) * np.uint32(0x01000193)
        h = h ^ (h >> np.uint32(15))
        if n in grams:
            out.append(((h * np.uint32(0x9E3779B1)) >> np.uint32(32 - bits)).astype(np.int32))
    return out


def _bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of the lower-cased texts, each between spaces, and each text's start."""
    t = pc.binary_join_element_wise("", pc.ascii_lower(pc.fill_null(texts.cast(pa.string()), "")), "", " ")
    if isinstance(t, pa.ChunkedArray):
        t = t.combine_chunks()
    off = np.frombuffer(t.buffers()[1], np.int32, len(t) + 1, t.offset * 4).astype(np.int64)
    data = np.frombuffer(t.buffers()[2] or b"", np.uint8)[off[0] : off[-1]] if len(t) else np.zeros(0, np.uint8)
    return data.astype(np.uint32), off - (off[0] if len(off) else 0)


def scores(texts: pa.Array, model: Model) -> np.ndarray:
    """Probability of the positive class for each text: distinct used n-grams' weights are summed."""
    data, off = _bytes(texts)
    n, total = len(off) - 1, np.full(max(len(off) - 1, 0), model.bias)
    keys = []
    ends = off[1:]
    for k, ids in zip(model.grams, gram_ids(data, model.bits, model.grams)):
        at = np.flatnonzero(model.weight[ids])
        doc = np.searchsorted(ends, at, side="right")
        inside = at + k <= ends[doc] if len(at) else np.zeros(0, bool)
        keys.append((doc[inside].astype(np.int64) << 32) | ids[at[inside]].astype(np.int64))
    if keys and n:
        u = np.unique(np.concatenate(keys))
        total = total + np.bincount(u >> 32, weights=model.weight[u & 0xFFFFFFFF], minlength=n)
    return 1 / (1 + np.exp(-np.clip(total, -40, 40)))


def _distinct(texts: pa.Array, bits: int, grams) -> list[np.ndarray]:
    out = []
    data, off = _bytes(texts)
    for a, b in zip(off[:-1], off[1:]):
        ids = gram_ids(data[a:b], bits, grams)
        out.append(np.unique(np.concatenate(ids)) if ids else np.zeros(0, np.int32))
    return out


def train(rows: DataFrame, per_class: int = 3000, features: int = 1 << 14, bits: int = BITS, grams: tuple[int, ...] = GRAMS, ridge: float = 0.5, steps: int = 200) -> Model:
    """Fit on ``rows`` (text string, label int), already a bounded sample of at most 2 * per_class rows.

    Presence counts per class are summed on the executors; the ``features`` n-grams with the most evidence are kept, and
    only their indices per row reach the driver (two bytes each; at most 2 ** 16 features and as many rows). With one class
    only, the model gives that class's rate.
    """
    if features > 1 << 16 or 2 * per_class > 1 << 16:
        raise ValueError("at most 2 ** 16 features and training rows")
    def count(batches):
        pos, neg, np_, nn = np.zeros(1 << bits, np.int32), np.zeros(1 << bits, np.int32), 0, 0
        for b in small_batches(batches, most=1 << 20):
            for ids, y in zip(_distinct(b.column("text"), bits, grams), b.column("label").to_pylist()):
                (pos if y else neg)[ids] += 1
                np_, nn = np_ + bool(y), nn + (not y)
        at = np.flatnonzero(pos + neg)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1), pa.int32()), pa.array(np.append(pos[at], np_), pa.int64()), pa.array(np.append(neg[at], nn), pa.int64())], ["f", "pos", "neg"])

    counts = rows.mapInArrow(count, "f int, pos long, neg long").groupBy("f").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    sums = {"pos": 0, "neg": 0}
    all_counts = cut(counts, "tox-counts")
    if head := all_counts.filter("f = -1").first():
        sums = head.asDict()
    p, n = sums["pos"] or 0, sums["neg"] or 0
    weight = np.zeros(1 << bits, np.float32)
    if not p or not n:
        drop_cut(all_counts)
        return Model(weight, float(np.log((p + 0.5) / (n + 0.5))), bits, grams)
    ratio = F.log(((F.col("pos") + 1) / (p + 2)) / ((F.col("neg") + 1) / (n + 2)))
    best = all_counts.filter("f >= 0").withColumn("r", ratio).withColumn("gain", F.abs(F.col("pos") / p - F.col("neg") / n) * F.abs("r")).orderBy(F.desc("gain"), "f").limit(features).collect()
    drop_cut(all_counts)
    ids = np.array(sorted(r["f"] for r in best), np.int32)
    r = np.zeros(1 << bits, np.float32)
    for x in best:
        r[x["f"]] = x["r"]
    slot = np.full(1 << bits, -1, np.int32)
    slot[ids] = np.arange(len(ids))

    def present(batches):
        for b in small_batches(batches, most=1 << 20):
            got = [slot[i][slot[i] >= 0] for i in _distinct(b.column("text"), bits, grams)]
            yield pa.RecordBatch.from_arrays([b.column("label").cast(pa.int32()), pa.array([x.astype(np.uint16).tobytes() for x in got], pa.binary())], ["y", "x"])

    got = rows.mapInArrow(present, "y int, x binary").orderBy("y", "x").collect()
    y = np.array([g["y"] for g in got], np.float64)
    w, b = _fit([np.frombuffer(bytes(g["x"]), np.uint16) for g in got], y, r[ids].astype(np.float64), ridge, steps)
    weight[ids] = w.astype(np.float32)
    return Model(weight, b, bits, grams)


def _sums(values: np.ndarray, at: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Sums of values[at] over the runs between edges; a run may be empty."""
    full = np.flatnonzero(np.diff(edges))
    out = np.zeros(len(edges) - 1)
    if len(full):
        out[full] = np.add.reduceat(values.astype(np.float32)[at], edges[full], dtype=np.float64)
    return out


def _fit(cols: list[np.ndarray], y: np.ndarray, scale: np.ndarray, ridge: float, steps: int) -> tuple[np.ndarray, float]:
    """Ridge-penalised logistic regression on presence times ``scale``, by accelerated gradient steps. Features are binary, so the data
    are two lists of two-byte indices, by row and by feature; returned weights are already times ``scale``."""
    many, n = np.array([len(c) for c in cols]), len(scale)
    col = np.concatenate(cols) if cols else np.zeros(0, np.uint16)
    by_row = np.concatenate([[0], np.cumsum(many)])
    row = np.repeat(np.arange(len(cols), dtype=np.uint16), many)[np.argsort(col, kind="stable")]
    by_col = np.concatenate([[0], np.cumsum(np.bincount(col, minlength=n))])
    w, b = np.zeros(n), float(np.log(y.mean() / (1 - y.mean())))
    # the step follows from the rows' mean squared length
    norm = max(1.0, float(_sums(scale * scale, col, by_row).mean()))
    rate, v, vb, old, oldb = 4.0 / (norm + ridge), w, b, w, b
    for t in range(1, steps + 1):
        z = _sums(scale * v, col, by_row) + vb
        g = 1 / (1 + np.exp(-np.clip(z, -40, 40))) - y
        w = v - rate * (scale * _sums(g, row, by_col) / len(y) + ridge * v / len(y))
        b = vb - rate * float(g.mean())
        k = (t - 1) / (t + 2)
        v, vb, old, oldb = w + k * (w - old), b + k * (b - oldb), w, b
    return w * scale, b


def held_out(key: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(key).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, per_class: int = 3000, key: str = "doc_id", text: str = "text", label: str = "toxic") -> DataFrame:
    """At most ``per_class`` labelled rows of each class that are not held out, smallest key hashes first. The list of
    keys is bounded by that parameter, so it is broadcast and the texts are not shuffled. Where labels of a key differ, the
    largest counts; null labels and keys are left out."""
    known = labels.filter(F.col(key).isNotNull() & F.col(label).isNotNull() & ~held_out(key)).groupBy(key).agg(F.max(label).cast("int").alias("label"))
    some = [known.filter(F.col("label") == y).orderBy(F.xxhash64(key), key).limit(per_class) for y in (1, 0)]
    chosen = some[0].unionByName(some[1])
    rows = docs.select(F.col(key), F.col(text).alias("text")).join(F.broadcast(chosen), key).select("text", "label")
    return cut(rows, "tox-train")


def score(docs: DataFrame, model: Model, text: str = "text", out: str = "score") -> DataFrame:
    """Add ``out``, the probability of toxicity (double in 0..1). A null text scores as an empty one. Other columns pass."""
    if out in docs.columns:
        docs = docs.drop(out)
    shared = docs.sparkSession.sparkContext.broadcast((model.weight, model.bias, model.bits, model.grams))  # 2 ** bits weights: a fixed size

    def run(batches):
        at = None
        for b in small_batches(batches, text, 1 << 20):
            at = b.schema.get_field_index(text) if at is None else at
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(scores(b.column(at), Model(*shared.value)), pa.float64())], [*b.schema.names, out])

    from pyspark.sql.types import DoubleType, StructField, StructType

    return docs.mapInArrow(run, StructType([*docs.schema.fields, StructField(out, DoubleType())]))
