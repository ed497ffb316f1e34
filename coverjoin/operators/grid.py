"""One-round parallel form: rows are sent to the cells of a grid over the attributes, and each cell runs the general method alone.

Every attribute gets a share of the cells; a row goes to all cells that agree with the hashes of its values. One shuffle replaces those
of all tree nodes, at the price of replication over the attributes a relation does not have.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from fractions import Fraction
from functools import reduce
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from ..plans import anchor as trees
from ..plans import lp
from ..plans.model import JoinQuery
from . import kernel


#: Cells of a grid, where nothing else is asked for.
CELLS = 64
#: Rows that a cell may get on average: where the cells asked for would get more, there are more cells.
ROWS = 500_000
#: Rows that a cell gives back at once.
BATCH = 1 << 18
#: Points of a block, where a cell holds three blocks.
POINTS = 1 << 18
#: Points of a block that a cell compares with others at a time.
TILE = 4096
#: Least number of blocks: there are as many cells as threes of them.
BLOCKS = 8


def shares(q: JoinQuery, cells: int, rows: int | None = None) -> dict[str, int]:
    """Whole shares per attribute, product at most ``cells``, or more until a cell gets no more than ``rows`` on average, with the least
    number of rows sent; found by doubling the share that lowers the largest cell's load most."""
    sizes, s = q.sizes(), {a: 1 for a in q.attrs}
    load = lambda z: sum(n / math.prod(z[a] for a in r.attrs) for n, r in zip(sizes, q.relations))
    while math.prod(s.values()) * 2 <= cells or (rows is not None and load(s) > rows):
        s = min((s | {a: s[a] * 2} for a in s), key=load)
    return s


def replication(q: JoinQuery, share: dict[str, int]) -> int:
    """Rows that the shuffle moves."""
    return sum(n * math.prod(v for a, v in share.items() if a not in r.attrs) for n, r in zip(q.sizes(), q.relations))


def simple(q: JoinQuery) -> bool:
    """Whether all columns can be coded: values without parts."""
    return not any(isinstance(f.dataType, (T.StructType, T.ArrayType, T.MapType, T.VariantType)) for r in q.relations for f in r.df.schema.fields)


def by_cell(q: JoinQuery, share: dict[str, int], solve: Callable[[list[kernel.Sections]], Iterator[kernel.Bindings]]) -> DataFrame:
    """One shuffle: every relation's rows to their cells, and ``solve`` on each cell's parts, given in the query's order. A combination
    of values of all attributes has one cell, which gets every row that agrees with it: what cells give is disjoint."""
    steps, at = {}, 1
    for a in q.attrs:
        steps[a], at = at, at * share[a]
    types = {f.name: f.dataType for r in q.relations for f in r.df.schema.fields}
    # a negative zero is equal to zero
    plain = lambda a: (F.col(a) + F.lit(0.0).cast(types[a])).alias(a) if isinstance(types[a], (T.FloatType, T.DoubleType)) else F.col(a)
    parts = []
    for i, r in enumerate(q.relations):
        own = reduce(lambda x, a: x + F.pmod(F.xxhash64(a, F.lit(a)), F.lit(share[a])) * steps[a], r.attrs, F.lit(0).cast("long"))
        free = [a for a in q.attrs if a not in r.attrs and share[a] > 1]
        offsets = [sum(steps[a] * v for a, v in zip(free, vs)) for vs in product(*(range(share[a]) for a in free))]
        cols = [plain(a) if a in r.attrs else F.lit(None).cast(types[a]).alias(a) for a in q.attrs]
        parts.append(r.df.select(F.explode(F.array(*(own + o for o in offsets))).alias("_cell"), F.lit(i).cast("short").alias("_rel"), *cols))
    attrs, held = list(q.attrs), [list(r.attrs) for r in q.relations]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # one code per value of an attribute, the same in all relations
        got = pa.Table.from_batches(list(batches))
        which, codes, values = got.column("_rel").to_numpy(), {}, {}
        for a in attrs:
            coded = got.column(a).combine_chunks().dictionary_encode(null_encoding="encode")
            coded = coded.combine_chunks() if isinstance(coded, pa.ChunkedArray) else coded
            codes[a], values[a] = coded.indices.to_numpy(zero_copy_only=False), coded.dictionary
            got = got.drop_columns([a])
        own = [np.flatnonzero(which == i) for i in range(len(held))]
        rels = [kernel.Sections(held[i], [codes[a][own[i]].astype(np.int64) for a in held[i]]) for i in range(len(held))]
        del codes, own, which
        for rows in solve(rels):
            for low in range(0, len(rows[attrs[0]]), BATCH):
                yield pa.RecordBatch.from_arrays([values[a].take(pa.array(rows[a][low : low + BATCH])) for a in attrs], names=attrs)

    schema = T.StructType([T.StructField(a, types[a]) for a in attrs])
    return reduce(DataFrame.unionByName, parts).groupBy("_cell").applyInArrow(run, schema)


def join(q: JoinQuery, cells: int = CELLS, cover=None) -> DataFrame:
    """Natural join in one shuffle. A cell holds its part of every relation in memory: where ``cells`` are too few for parts of at most
    ROWS rows on average, there are more of them."""
    h, sizes = q.hypergraph, q.sizes()
    if 0 in sizes:
        return q.empty()
    cover = tuple(map(Fraction, cover)) if cover is not None else lp.optimal_cover(h, sizes)
    tree, order = trees.build(h)
    y = tuple(cover[i] for i in order)

    def solve(rels: list[kernel.Sections]) -> Iterator[kernel.Bindings]:
        yield kernel.solve(tree, y, [rels[i] for i in order])

    return by_cell(q, shares(q, cells, ROWS), solve)


# -- graphs whose edges are told by their vertices


def bucket_triangles(points: DataFrame, attrs: tuple[str, str, str] = ("a", "b", "c"), block: int = POINTS) -> DataFrame:
    """Triangles a < b < c of the graph whose vertices are points (id, buckets) and whose edges are pairs of points with the same bucket in
    some place, without the edges: their number grows with the square of the points, so the points are sent, to one cell for each three
    blocks they may lie in, and the cell makes the edges between its blocks, TILE points at a time, and meets the neighbours of their ends.
    A block goes to half the square of the number of blocks: it is large, as a cell can hold, and packed to one row before it is sent. An id that
    comes more than once has the buckets of all its rows. points: a whole-number column and an array column of one length without nulls."""
    v, kept = points.columns[0], points.columns[1]
    points = points.filter(F.col(v).isNotNull())
    s = max(BLOCKS, -(-points.count() // block))
    cells, session = s * (s + 1) * (s + 2) // 6, points.sparkSession
    span = lambda low: F.explode(F.sequence(low, F.lit(s - 1)))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = pa.Table.from_batches(list(batches))
        ids, buckets = got.column(v).to_numpy().astype(np.int64), np.concatenate([c.flatten().to_numpy() for c in got.column(kept).chunks]).reshape(got.num_rows, -1)
        order = np.argsort(ids, kind="stable")
        ids = ids[order]
        # ids as steps from one to the next
        packed = {"_block": got.column("_block")[0].as_py(), "_least": int(ids[0]), "_ids": kernel.pack(np.diff(ids, prepend=ids[:1])[None]), "_buckets": kernel.pack(buckets[order].T)}
        yield pa.RecordBatch.from_pylist([packed], schema=row)

    row = pa.schema([("_block", pa.int32()), ("_least", pa.int64()), ("_ids", pa.binary()), ("_buckets", pa.binary())])
    sent = points.withColumn("_block", F.pmod(F.xxhash64(v), F.lit(s)).cast("int")).groupBy("_block").applyInArrow(pack, "_block int, _least long, _ids binary, _buckets binary")
    sent = sent.withColumn("_p", span(F.lit(0))).withColumn("_q", span(F.col("_p")))
    three = F.array_sort(F.array("_block", "_p", "_q"))
    # their number is that of the cells, not of the bytes: a cell's work is in the rows that it makes
    parts = min(cells, max(64, int(session.conf.get("spark.sql.shuffle.partitions"))))
    sent = sent.select(three.alias("_cell"), "_block", "_least", "_ids", "_buckets").repartition(parts, "_cell")
    kind = points.schema[v].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = pa.Table.from_batches(list(batches)).to_pylist()
        at, whole = got[0]["_cell"], {x["_block"]: (x["_least"] + kernel.unpack(x["_ids"])[0].cumsum(dtype=np.int64), kernel.unpack(x["_buckets"]).T) for x in got}
        tiles = {h: kernel.tiles(*whole[h], TILE) if h in whole else [] for h in at}
        for i, j, k in product(*(range(len(tiles[h])) for h in at)):
            if at[0] == at[1] and i > j or at[1] == at[2] and j > k:
                continue
            for found in kernel.triangles([tiles[h][t] for h, t in zip(at, (i, j, k))], [at[0] == at[1] and i == j, at[1] == at[2] and j == k]):
                for low in range(0, len(found[0]), BATCH):
                    yield pa.RecordBatch.from_arrays([pa.array(x[low : low + BATCH]).cast(to) for x in found], names=list(attrs))

    to = to_arrow_type(kind)
    return sent.groupBy("_cell").applyInArrow(run, T.StructType([T.StructField(a, kind) for a in attrs]))
