"""Nearest neighbours by collision counting over single projections.

Rows lie in blocks of a fixed size. A block keeps, for each of ``lines`` random directions, its rows' projections in sorted
order. A query opens a window around its own projection on every line and widens all windows together, level by level
(virtual rehashing: level R stands for the search radius R, windows have half-width ``width`` * R); each level only counts the rows that
the wider windows add. A row that has collided on at least ``threshold`` of the lines is verified by its exact cosine. A block
is done with a query once its k-th best verified row is within the radius, or everything was seen; then the blocks' answers
are merged. There is no cap on candidates.

With half-width R a row at distance R collides on a line with probability 0.683, one at distance 1.4 R with 0.525; with 64
lines and a threshold of 0.56 a row within the radius is missed with probability of about 2 %.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .vectors import cosines, matrix, scaled, usable


class Block:
    """Sorted projections of one block of rows."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, lines: int, seed: int):
        order = np.argsort(ids, kind="stable")
        self.ids, self.x = ids[order], scaled(x[order])
        self.norms = np.sqrt((self.x * self.x).sum(axis=1))
        self.lines = np.random.default_rng(seed).standard_normal((lines, x.shape[1]))
        p = (self.x / self.norms[:, None]) @ self.lines.T
        self.order = np.argsort(p, axis=0, kind="stable").T.astype(np.intp).copy()
        self.sorted = np.take_along_axis(p, self.order.T, axis=0).T.copy()

    def search(self, qid: int, q: np.ndarray, k: int, threshold: float, first: float, ratio: float, width: float) -> tuple[np.ndarray, np.ndarray]:
        n, m = len(self.ids), len(self.lines)
        q = scaled(q[None, :])[0]
        qn = float(np.sqrt((q * q).sum()))
        at = self.lines @ (q / qn)
        count = np.zeros(n, np.int32)
        left = np.array([np.searchsorted(self.sorted[i], at[i]) for i in range(m)])
        right, need = left.copy(), int(np.ceil(threshold * m))
        done = np.zeros(n, bool)
        found, score = np.zeros(0, np.int64), np.zeros(0)
        radius = first
        while True:
            parts = []
            half = radius * width
            for i in range(m):
                s = self.sorted[i]
                a, b = s.searchsorted(at[i] - half), s.searchsorted(at[i] + half, side="right")
                parts += [self.order[i, a : left[i]], self.order[i, right[i] : b]]
                left[i], right[i] = min(a, left[i]), max(b, right[i])
            new = np.concatenate(parts)
            if len(new):
                count += np.bincount(new, minlength=n).astype(np.int32)
            hit = np.flatnonzero((count >= need) & ~done)
            if len(hit):
                done[hit] = True
                hit = hit[self.ids[hit] != qid]
                found = np.concatenate([found, hit])
                score = np.concatenate([score, cosines(self.x[hit], self.norms[hit], q, qn)])
            if len(found) >= k:
                kth = np.partition(score, len(score) - k)[len(score) - k]
                if 2 - 2 * kth <= radius * radius:
                    break
            if radius > 64 or (left == 0).all() and (right == n).all():
                break
            radius *= ratio
        best = np.lexsort((self.ids[found], -score))[:k]
        return self.ids[found][best], score[best]


def nearest(rows: DataFrame, queries: DataFrame, k: int = 5, lines: int = 64, threshold: float = 0.56, first: float = 0.3, ratio: float = 1.4, width: float = 1.0, block: int = 1 << 13, seed: int = 3, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """The k rows of largest cosine found for each query: query_id, rank (from 1), vec_id, score. A row is no candidate of a
    query with the same key. Vectors that are null, zero, or hold null or non-finite components take no part; only vectors of
    equal length are compared. Ties go to the smaller key; fewer than k candidates are all returned. Repeated keys are
    separate candidates. Empty tables give no rows. Blocks have a fixed size, their number grows: every row is sent once,
    to its block, and every query to all blocks, through which queries stream a batch at a time.
    """
    slim = lambda df: df.filter(usable(F.col(vector))).select(F.col(key).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v"), F.size(vector).alias("dim")).filter("id is not null")
    data, asked = slim(rows), slim(queries)
    blocks = max(1, -(-data.count() // block))
    data = data.select(F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("b"), "dim", F.lit(0).alias("kind"), "id", "v")
    asked = asked.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b"), "dim", F.lit(1).alias("kind"), "id", "v")
    dealt = data.unionByName(asked).repartitionById(blocks, "b").sortWithinPartitions("b", "dim", "kind")

    def run(batches):
        now, held, index = None, [], None
        for b in batches:
            dims, kinds, ids = (b.column(c).to_numpy() for c in (1, 2, 3))
            edges = np.concatenate([[0], np.flatnonzero((np.diff(dims) != 0) | (np.diff(kinds) != 0) | (np.diff(b.column(0).to_numpy()) != 0)) + 1, [b.num_rows]])
            for lo, hi in zip(edges[:-1], edges[1:]):
                if lo == hi:
                    continue
                if (b.column(0)[int(lo)].as_py(), dims[lo]) != now:
                    now, held, index = (b.column(0)[int(lo)].as_py(), dims[lo]), [], None
                x = matrix(b.column(4).slice(lo, hi - lo), int(dims[lo]))
                if kinds[lo] == 0:
                    held.append((ids[lo:hi], x))
                    continue
                if held and index is None:
                    index = Block(*(np.concatenate(c) for c in zip(*held)), lines, seed)
                if index is None:
                    continue
                out: list[list] = [[], [], []]
                for qid, q in zip(ids[lo:hi].tolist(), x):
                    near, score = index.search(qid, q, k, threshold, first, ratio, width)
                    out[0] += [qid] * len(near)
                    out[1] += near.tolist()
                    out[2] += score.tolist()
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64())], ["query_id", "vec_id", "score"])

    found = dealt.mapInArrow(run, "query_id long, vec_id long, score double")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
