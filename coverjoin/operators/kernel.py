"""The general method on one cell of a grid, held in memory: whole-number codes in sorted arrays, all bindings of a node at a time."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np

from ..plans.anchor import AnchorNode

#: Candidates that are made and tested at once.
BLOCK = 1 << 20

Bindings = dict[str, np.ndarray]


class Trie:
    """Distinct rows of some columns in sorted order. The row numbers of each prefix are codes of their own, so a prefix of any
    width is looked up by one binary search a column."""

    def __init__(self, cols: Sequence[np.ndarray], n: int):
        self.levels, self.sizes, ids = [], [], np.zeros(n, np.int64)
        self.prefix = [ids]
        for c in cols:
            size = int(c.max()) + 1 if n else 1
            keys, first, ids = np.unique(ids * size + c, return_index=True, return_inverse=True)
            self.levels.append(keys)
            self.sizes.append(size)
            self.prefix.append(ids)
        self.values = [c[first] for c in cols] if cols else []
        self.first = first if cols else np.zeros(min(n, 1), np.int64)

    def find(self, cols: Sequence[np.ndarray], n: int) -> np.ndarray:
        """Numbers of the prefixes that the columns spell, -1 where there is none."""
        ids = np.zeros(n, np.int64) if len(self.prefix[0]) else np.full(n, -1)
        for c, size, keys in zip(cols, self.sizes, self.levels):
            want = np.where((ids < 0) | (c >= size), -1, ids * size + c)
            at = np.searchsorted(keys, want)
            at[at == len(keys)] = 0
            ids = np.where(keys[at] == want, at, -1) if len(keys) else np.full(n, -1)
        return ids

    def starts(self, width: int) -> np.ndarray:
        """Where the rows of each prefix of that width begin, and the end of the last."""
        own = self.prefix[width][self.first]
        return np.searchsorted(own, np.arange(own[-1] + 2 if len(own) else 1))


class Sections:
    """One relation of a cell: for bound columns, the sections of others."""

    def __init__(self, attrs: Sequence[str], cols: Sequence[np.ndarray]):
        self.attrs, self.cols = tuple(attrs), dict(zip(attrs, cols))
        self.n = len(cols[0])
        self.tries: dict[tuple, tuple[Trie, np.ndarray]] = {}

    def _trie(self, bound: Bindings, want: tuple[str, ...]):
        on = tuple(a for a in self.attrs if a in bound and a not in want)
        if (on, want) not in self.tries:
            t = Trie([self.cols[a] for a in on + want], self.n)
            self.tries[on, want] = t, t.starts(len(on))
        return on, *self.tries[on, want]

    def ranges(self, bound: Bindings, n: int, want: tuple[str, ...]) -> tuple[np.ndarray, np.ndarray, Trie]:
        """First row and number of rows of each binding's section."""
        on, trie, starts = self._trie(bound, want)
        ids = trie.find([bound[a] for a in on], n)
        low = starts[np.maximum(ids, 0)]
        return low, np.where(ids < 0, 0, starts[np.minimum(np.maximum(ids, 0) + 1, len(starts) - 1)] - low), trie

    def holds(self, bound: Bindings, n: int, want: tuple[str, ...]) -> np.ndarray:
        """Whether the bindings, which have values of ``want`` too, are in the relation's projection."""
        on, trie, _ = self._trie({a: x for a, x in bound.items() if a not in want}, want)
        return trie.find([bound[a] for a in on + want], n) >= 0


def _take(b: Bindings, at: np.ndarray) -> Bindings:
    return {a: x[at] for a, x in b.items()}


def _extend(bound: Bindings, n: int, source: Sections, want: tuple[str, ...], tests: Sequence[tuple[Sections, tuple[str, ...]]]) -> tuple[np.ndarray, Bindings]:
    """Each binding with each row of its section in ``source`` that all ``tests`` hold: numbers of the bindings, and their new values.
    Candidates are made BLOCK by BLOCK and tested at once (one section may be longer). Where ``source`` has no bound column, they
    meet through a test that has both kinds, so that no product is made."""
    if n > 1 and not any(a in bound for a in source.attrs):
        link = next(((r, attrs) for r, attrs in tests if any(a in bound and a not in attrs for a in r.attrs)), None)
        if link:
            some, rest = link[1], tuple(a for a in want if a not in link[1])
            first, found = _extend(bound, n, link[0], some, [] if rest else [(source, want), *(t for t in tests if t is not link)])
            if not rest:
                return first, found
            which, new = _extend(_take(bound, first) | found, len(first), source, rest, [(r, tuple(a for a in attrs if a in rest) or attrs) for r, attrs in tests if r is not link[0]])
            return first[which], _take(found, which) | new
    low, many, trie = source.ranges(bound, n, want)
    ends, out, done = np.cumsum(many), [], 0
    values = trie.values[len(trie.values) - len(want) :]
    while done < n:
        upto = max(done + 1, int(np.searchsorted(ends, (ends[done - 1] if done else 0) + BLOCK, side="right")))
        part = many[done:upto]
        which = np.repeat(np.arange(done, upto), part)
        row = np.arange(len(which)) - np.repeat(np.cumsum(part) - part, part) + low[which]
        new = {a: v[row] for a, v in zip(want, values)}
        for rel, attrs in tests:
            ok = rel.holds(_take(bound, which) | new, len(which), attrs)
            which, new = which[ok], _take(new, ok)
        out.append((which, new))
        done = upto
    return _join(out, want)


def _join(parts: Sequence[tuple[np.ndarray, Bindings]], attrs: Sequence[str]) -> tuple[np.ndarray, Bindings]:
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *(w for w, _ in parts)]), {a: np.concatenate([none, *(b[a] for _, b in parts)]) for a in attrs}


def _node(node: AnchorNode, y, bound: Bindings, n: int, rels: Sequence[Sections]) -> tuple[np.ndarray, Bindings]:
    """For n bindings: the values of the node's universe that all relations up to its rank agree with, and the binding of each."""
    if node.leaf:
        u, live = tuple(sorted(node.universe)), rels[: node.rank + 1]
        least = np.stack([r.ranges(bound, n, u)[1] for r in live]).argmin(axis=0)
        parts = []
        for i, r in enumerate(live):
            at = np.flatnonzero(least == i)
            which, new = _extend(_take(bound, at), len(at), r, u, [(s, u) for s in live if s is not r])
            parts.append((at[which], new))
        return _join(parts, u)
    k, inside = node.rank, tuple(sorted(node.universe & set(rels[node.rank].attrs)))
    which, found = _node(node.left, y[:k], bound, n, rels) if node.left else (np.arange(n), {})
    if not inside:
        return which, found
    now = _take(bound, which) | found
    many = rels[k].ranges(now, len(which), inside)[1]
    others = [(r, a) for r in rels[:k] if (a := tuple(x for x in inside if x in r.attrs))]
    deeper = np.zeros(len(which), bool)
    if y[k] < 1 and node.right:
        with np.errstate(divide="ignore"):
            weight = np.zeros(len(which))
            for w, r in zip(y, rels[:k]):
                a = tuple(x for x in inside if x in r.attrs)
                if a and w > 0:
                    weight += float(w / (1 - y[k])) * np.log(r.ranges(now, len(which), a)[1])
            deeper = (many > 0) & (weight < np.log(many))
    parts, at = [], np.flatnonzero(deeper)
    if len(at):
        own, new = _node(node.right, tuple(w / (1 - y[k]) for w in y[:k]), _take(now, at), len(at), rels)
        ok = rels[k].holds(_take(now, at[own]) | new, len(own), inside)
        parts.append((at[own[ok]], _take(new, ok)))
    at = np.flatnonzero(~deeper & (many > 0))
    own, new = _extend(_take(now, at), len(at), rels[k], inside, others)
    parts.append((at[own], new))
    own, new = _join(parts, inside)
    return which[own], _take(found, own) | new


def solve(tree: AnchorNode, y, rels: Sequence[Sections]) -> Bindings:
    """The join of the relations, given in the tree's order with their cover weights: one array of codes per attribute."""
    if any(r.n == 0 for r in rels):
        return {a: np.zeros(0, np.int64) for r in rels for a in r.attrs}
    return _node(tree, tuple(y), {}, 1, rels)[1]


def blocks(rows: Bindings) -> Iterator[Bindings]:
    """BLOCK rows at a time."""
    for low in range(0, len(next(iter(rows.values()))), BLOCK):
        yield {a: x[low : low + BLOCK] for a, x in rows.items()}


def agreeing(rows: Bindings, rels: Sequence[Sections], made: frozenset[int], before: Sequence[frozenset[int]], least: int) -> Bindings:
    """Of the join over the relations ``made``, the rows that agree with ``least`` relations, and not with all of any set ``before``."""
    n = len(next(iter(rows.values())))
    holds = [np.ones(n, bool) if i in made else r.holds(rows, n, r.attrs) for i, r in enumerate(rels)]
    keep = np.sum(holds, axis=0) >= least
    for s in before:
        keep &= ~np.logical_and.reduce([holds[i] for i in s])
    return _take(rows, keep)


def _touching(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], after: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct ids of two sorted blocks of points (id, buckets), and whether a point of the first has a bucket of one of the second in
    its place. after: the blocks are one, and only later ids count."""
    near = np.zeros((len(a[0]), len(b[0])), bool)
    for x, y in zip(a[1].T, b[1].T):
        near |= x[:, None] == y
    (ids, first), (others, begin) = np.unique(a[0], return_index=True), np.unique(b[0], return_index=True)
    if len(ids) < len(a[0]):
        near = np.logical_or.reduceat(near, first, axis=0)
    if len(others) < len(b[0]):
        near = np.logical_or.reduceat(near, begin, axis=1)
    return ids, others, np.triu(near, 1) if after else near


def pack(x: np.ndarray) -> bytes:
    """An array of two axes; whole numbers in the least type that holds them."""
    if x.size and x.dtype.kind in "iu":
        low, high = int(x.min()), int(x.max())
        x = x.astype(np.min_scalar_type(high if low >= 0 else min(low, -high - 1)))
    return f"{x.dtype.str} {x.shape[0]} {x.shape[1]};".encode() + np.ascontiguousarray(x).tobytes()


def unpack(packed: bytes) -> np.ndarray:
    head, _, body = packed.partition(b";")
    kind, rows, columns = head.decode().split(" ")
    return np.frombuffer(body, kind).reshape(int(rows), int(columns))


def tiles(ids: np.ndarray, buckets: np.ndarray, most: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """A block of points, sorted by id, in parts of equal size, at most about ``most``; all rows of an id stay together."""
    n = max(1, -(-len(ids) // most))
    cuts = sorted({int(np.searchsorted(ids, ids[k * len(ids) // n])) for k in range(1, n)} - {0})
    return [(ids[low:high], buckets[low:high]) for low, high in zip([0, *cuts], [*cuts, len(ids)])]


def triangles(points: Sequence[tuple[np.ndarray, np.ndarray]], same: Sequence[bool]) -> Iterator[list[np.ndarray]]:
    """Ids a < b < c that touch each other, one of each of three blocks of points, sorted by id. same: whether the second block is the
    first, and the third the second. About BLOCK candidates at a time, however large a neighbourhood is."""
    if any(len(ids) == 0 for ids, _ in points):
        return
    (p, q, r), (pq, qr) = points, same
    u, v, uv = _touching(p, q, pq)
    _, w, vw = _touching(q, r, qr)
    uw = uv if qr else vw if pq else _touching(p, r, False)[2]
    out, many = [], 0
    for i in range(len(u)):
        ys, zs = np.flatnonzero(uv[i]), np.flatnonzero(uw[i])
        if not len(ys) or not len(zs):
            continue
        step = max(1, BLOCK // len(zs))
        for low in range(0, len(ys), step):
            j, k = np.nonzero(vw[np.ix_(ys[low : low + step], zs)])
            if len(j):
                out.append((np.full(len(j), u[i]), v[ys[low + j]], w[zs[k]]))
                many += len(j)
            if many >= BLOCK:
                yield _ordered(out)
                out, many = [], 0
    if many:
        yield _ordered(out)


def _ordered(parts: Sequence[tuple[np.ndarray, ...]]) -> list[np.ndarray]:
    """The three ids of each row, least first."""
    x, y, z = (np.concatenate(c) for c in zip(*parts))
    x, y = np.minimum(x, y), np.maximum(x, y)
    y, z = np.minimum(y, z), np.maximum(y, z)
    return [np.minimum(x, y), np.maximum(x, y), z]
