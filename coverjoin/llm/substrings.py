"""Substring dedup: words covered by long passages that an earlier document has too, found with FM-indexes.

A window is ``window`` consecutive words. Of the ``anchor``-word grams in a window, the one of least hash is its anchor, so equal
windows have equal anchors wherever they stand. The work is in three steps, none of which sends whole texts to one place:

1. Anchors that only one document has cannot belong to a shared window. Each task reports its anchors as packed hashes,
   one entry per anchor and task, to the anchor's bucket; what is shared inside a task is known there at once.
2. Around shared anchors, texts are cut into fragments: maximal runs of windows with that anchor. Equal fragments of a task
   are reduced to the one of the smallest document. Fragments go to the shard of their anchor.
3. A shard indexes its fragments in compressed FM-indexes and streams the same fragments through them: backward search over
   wavelet trees gives the interval of a whole fragment or, if that fails, of each of its windows, stopping where only the fragment itself is
   left. An interval that holds a smaller document is a match. Matched word ranges are joined by document and return packed by
   the documents' buckets, as the notes did.

Words are compared by hashes: an anchor by 64 bits, the other words of a window by 40 bits each.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hash_words, mix64, parts, small_batches, split_words
from .fmindex import FMIndex

#: Words of one FM-index, about.
SHARD = 1 << 19
#: Matched ranges that a task holds before it sends them.
RANGES = 1 << 18


def anchors(h: np.ndarray, window: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """For a text's word hashes: the hashes of its k-grams, and the anchor position of each window (leftmost least)."""
    n = len(h) - k + 1
    g = h[:n]
    for i in range(1, k):
        g = mix64(g) + h[i : n + i]
    g = mix64(g)
    w = window - k + 1
    m = len(h) - window + 1
    best, at = g[:m].copy(), np.arange(m)
    for i in range(1, w):
        less = g[i : m + i] < best
        best = np.where(less, g[i : m + i], best)
        at = np.where(less, np.arange(i, m + i), at)
    return g, at


def _hashed(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    flat, off = split_words(texts)
    return hash_words(flat), off


def _batch_anchors(h: np.ndarray, off: np.ndarray, window: int, k: int):
    """For all texts of a batch at once: k-gram hashes, and of each window inside a text its anchor's position, its text, and its
    first word. Positions count from the batch's first word; windows across texts are left out."""
    if len(h) < window:
        none = np.zeros(0, np.int64)
        return h, none, none, none
    g, at = anchors(h, window, k)
    who = np.repeat(np.arange(len(off) - 1), np.diff(off))[: len(at)]
    inside = np.flatnonzero(np.arange(len(at)) + window <= off[who + 1])
    return g, at[inside], who[inside], inside


def _binary(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    """Binary values cut out of one run of bytes."""
    return pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(np.ascontiguousarray(data).tobytes())])


def _packed_ranges(ids: np.ndarray, hs: np.ndarray, starts: np.ndarray, ends: np.ndarray, nb: int):
    """Rows (home bucket, data, number of ranges) from ranges of documents, overlapping ones joined: many documents lie in
    one row. Data: starts and ends, then of each document the number of its ranges, its key and its hash."""
    if not len(ids):
        return
    home = ids % nb
    order = np.lexsort((starts, hs, ids, home))
    ids, hs, home, starts, ends = ids[order], hs[order], home[order], starts[order].astype(np.int64), ends[order].astype(np.int64)
    doc = np.cumsum(np.concatenate([[0], (ids[1:] != ids[:-1]) | (hs[1:] != hs[:-1])]))
    far = doc * (int(ends.max()) + 1)
    top = np.maximum.accumulate(far + ends)  # a document's values are above all of the one before
    new = np.concatenate([[True], (far + starts)[1:] > top[:-1]]) | np.concatenate([[True], doc[1:] != doc[:-1]])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(ids)) - 1
    starts, ends, ids, hs, home, doc = starts[first], (top - far)[last], ids[first], hs[first], home[first], doc[first]
    edges = np.searchsorted(home, np.arange(nb + 1))
    for k in np.flatnonzero(np.diff(edges)):
        x = slice(edges[k], edges[k + 1])
        lead, many = np.unique(doc[x], return_index=True, return_counts=True)[1:]
        yield int(k), np.stack([starts[x], ends[x]]).astype(np.int32).tobytes() + many.astype(np.int32).tobytes() + ids[x][lead].tobytes() + hs[x][lead].tobytes(), int(edges[k + 1] - edges[k])


def _joined_ranges(rows: list):
    """(key, hash, packed start-end pairs) of each document of one home bucket's rows, ranges of all rows joined."""
    parts = []
    for data, n in rows:
        docs = (len(data) - 8 * n) // 20
        many = np.frombuffer(data, np.int32, docs, 8 * n)
        ids, hs = (np.repeat(np.frombuffer(data[8 * n + 4 * docs + 8 * docs * x : 8 * n + 4 * docs + 8 * docs * (x + 1)], np.int64), many) for x in (0, 1))
        parts.append((ids, hs, np.frombuffer(data, np.int32, n), np.frombuffer(data, np.int32, n, 4 * n)))
    for _, data, n in _packed_ranges(*(np.concatenate(c) for c in zip(*parts)), 1):
        docs = (len(data) - 8 * n) // 20
        pairs = np.frombuffer(data, np.int32, 2 * n).reshape(2, n).T.copy()
        edges = np.concatenate([[0], np.cumsum(np.frombuffer(data, np.int32, docs, 8 * n))])
        ids, hs = (np.frombuffer(data[8 * n + 4 * docs + 8 * docs * x : 8 * n + 4 * docs + 8 * docs * (x + 1)], np.int64) for x in (0, 1))
        raw = pairs.tobytes()
        for d in range(docs):
            yield int(ids[d]), int(hs[d]), raw[8 * edges[d] : 8 * edges[d + 1]]


def _pack6(h: np.ndarray) -> bytes:
    """The upper 48 bits of anchors: what shares them by chance is only looked at in vain."""
    return (h >> np.uint64(32)).astype(np.uint32).tobytes() + ((h >> np.uint64(16)) & np.uint64(0xFFFF)).astype(np.uint16).tobytes()


def _unpack6(b: bytes, n: int) -> np.ndarray:
    return (np.frombuffer(b, np.uint32, n).astype(np.uint64) << np.uint64(16)) | np.frombuffer(b, np.uint16, n, 4 * n)


def _unpack5(b: bytes) -> np.ndarray:
    out = np.zeros((len(b) // 5, 8), np.uint8)
    out[:, 3:] = np.frombuffer(b, np.uint8).reshape(-1, 5)
    return out.view(np.uint64).ravel() >> np.uint64(24)


KEY = "id long, h long"


def repeats(docs: DataFrame, window: int = 13, anchor: int = 5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, h, ranges): for each document with words to remove, the packed (start, end) word ranges, int32 pairs, disjoint and
    ascending, of the windows that also start in a document with a smaller key. h is the 64-bit hash of the text: rows that
    repeat a key count as one document, and each text of it gets its own ranges.
    """
    return _repeats(docs.select(F.col(key).cast("long").alias("id"), F.xxhash64(text).alias("h"), F.col(text).alias("text")), window, anchor)


def _repeats(docs: DataFrame, window: int, anchor: int) -> DataFrame:
    spark = docs.sparkSession
    nb = parts(spark)

    # 1. anchors. kind < nb: packed anchors of a bucket; else a packet of notes for documents of the bucket kind - nb
    def report(batches):
        for b in small_batches(batches, most=16 << 20):
            ids, hs = b.column(0).to_numpy(), b.column(1).to_numpy()
            h, off = _hashed(b.column(2))
            g, at, who = _batch_anchors(h, off, window, anchor)[:3]
            if not len(at):
                continue
            new = np.concatenate([[True], at[1:] != at[:-1]])
            at, who = at[new], who[new]
            got = g[at]
            order = np.lexsort((ids[who], got))
            got, who = got[order], who[order]
            new = np.concatenate([[True], got[1:] != got[:-1]])
            group, first = np.cumsum(new) - 1, np.flatnonzero(new)
            last = np.concatenate([first[1:], [len(got)]]) - 1
            shared = (ids[who[first]] < ids[who[last]])[group]
            rows = notes(ids, hs, who[shared], got[shared])
            bucket = got[first] % np.uint64(nb)
            order = np.argsort(bucket, kind="stable")
            edges = np.searchsorted(bucket[order], np.arange(nb + 1, dtype=np.uint64))
            for k in range(nb):
                f = first[order[edges[k] : edges[k + 1]]]
                if len(f):
                    docs_of, inv = np.unique(who[f], return_inverse=True)
                    # a document that shares the anchor inside the task needs no answer; it only lends its key
                    told = shared[f].astype(np.uint32) << np.uint32(31)
                    rows.append((k, _pack6(got[f]) + (inv.astype(np.uint32) | told).tobytes() + ids[docs_of].tobytes() + hs[docs_of].tobytes(), len(f)))
            yield batch(rows)

    def batch(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.int32()))] if rows else [pa.array([], t) for t in (pa.int32(), pa.binary(), pa.int32())], ["kind", "data", "n"])

    def notes(ids, hs, who, got):
        """Shared anchors of documents, packed by the documents' bucket: numbers per document, anchors, keys."""
        home = ids[who] % nb
        order = np.lexsort((got, who, home))
        who, got, home = who[order], got[order], home[order]
        new = np.concatenate([[True], (who[1:] != who[:-1]) | (got[1:] != got[:-1])]) if len(who) else np.zeros(0, bool)
        who, got, home = who[new], got[new], home[new]
        edges = np.searchsorted(home, np.arange(nb + 1))
        rows = []
        for k in np.flatnonzero(np.diff(edges)):
            part = slice(edges[k], edges[k + 1])
            docs_of, many = np.unique(who[part], return_counts=True)
            rows.append((nb + int(k), _pack6(got[part]) + many.astype(np.int32).tobytes() + ids[docs_of].tobytes() + hs[docs_of].tobytes(), edges[k + 1] - edges[k]))
        return rows

    # buckets are dealt evenly: hashes of as many numbers as there are partitions would leave some empty and others with several
    schema, bucket = "kind int, data binary, n int", F.pmod("kind", F.lit(nb))
    reported = docs.filter("id is not null").select("id", "h", "text").mapInArrow(report, schema).repartitionById(nb, bucket).sortWithinPartitions("kind")

    def gather(batches):
        held, now = [], None

        def close():
            if len(held) < 2:
                return
            got = np.concatenate([_unpack6(d, n) for d, n in held])
            code = [np.frombuffer(d, np.uint32, n, 6 * n) for d, n in held]
            tail = [np.frombuffer(d, np.int64, -1, 10 * n) if len(d) > 10 * n else np.zeros(0, np.int64) for d, n in held]
            base = np.concatenate([[0], np.cumsum([len(t) // 2 for t in tail])])
            ids, hs = (np.concatenate([t[: len(t) // 2] if x == 0 else t[len(t) // 2 :] for t in tail]) for x in (0, 1))
            who = np.concatenate([(c & np.uint32(0x7FFFFFFF)).astype(np.int64) + o for c, o in zip(code, base)])
            told = np.concatenate([(c >> np.uint32(31)).astype(bool) for c in code])
            order = np.lexsort((ids[who], got))
            got, who, told = got[order], who[order], told[order]
            new = np.concatenate([[True], got[1:] != got[:-1]])
            group, first = np.cumsum(new) - 1, np.flatnonzero(new)
            last = np.concatenate([first[1:], [len(got)]]) - 1
            # shared if two documents have it, be they of different tasks or of one
            shared = (ids[who[first]] < ids[who[last]]) | (np.maximum.reduceat(told, first))
            ask = shared[group] & ~told
            yield batch(notes(ids, hs, who[ask], got[ask] << np.uint64(16)))

        for b in batches:
            kinds = b.column(0).to_numpy()
            for x in range(b.num_rows):
                if kinds[x] >= nb:
                    continue
                if kinds[x] != now:
                    yield from close()
                    held, now = [], kinds[x]
                held.append((b.column(1)[x].as_py(), b.column(2)[x].as_py()))
            keep = b.filter(pa.array(kinds >= nb))
            if keep.num_rows:
                yield keep
        yield from close()

    packets = reported.mapInArrow(gather, schema).repartitionById(nb, bucket).sortWithinPartitions("kind")

    def unpack(batches):
        """One row per document: all its shared anchors."""
        held, now = [], None

        def close():
            if not held:
                return
            got = np.concatenate([_unpack6(d, n) for d, n in held])
            tails = [(len(d) - 6 * n) // 20 for d, n in held]
            many = np.concatenate([np.frombuffer(d, np.int32, t, 6 * n) for (d, n), t in zip(held, tails)])
            ids, hs = (np.concatenate([np.frombuffer(d[6 * n + (4 + 8 * x) * t : 6 * n + (12 + 8 * x) * t], np.int64) for (d, n), t in zip(held, tails)]) for x in (0, 1))
            ends = np.cumsum(many)
            order = np.lexsort((hs, ids))
            cut_at = np.flatnonzero((np.diff(ids[order]) != 0) | (np.diff(hs[order]) != 0)) + 1
            rows = []
            for grp in np.split(order, cut_at):
                all_of = np.concatenate([got[ends[i] - many[i] : ends[i]] for i in grp])
                rows.append((ids[grp[0]], hs[grp[0]], all_of.tobytes()))
                if len(rows) >= 4096:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.binary()))], ["id", "h", "notes"])
                    rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.binary()))], ["id", "h", "notes"])

        for b in batches:
            for k, d, n in zip(*(c.to_pylist() for c in b.columns)):
                if k != now:
                    yield from close()
                    held, now = [], k
                held.append((d, n))
        yield from close()

    noted = packets.mapInArrow(unpack, "id long, h long, notes binary")
    # left, like the last join: then both read one exchange of the texts
    asked = docs.join(noted.hint("merge"), ["id", "h"], "left").select("id", "h", "notes", "text")

    # 2. fragments (kind = 0) and ranges known inside the task (kind = 1)
    def fragments(batches):
        for b in small_batches(batches, most=16 << 20):
            # rows with a null key have no notes: their number does not matter
            ids, hs = b.column(0).fill_null(0).to_numpy(), b.column(1).to_numpy()
            told = [np.frombuffer(x, np.uint64) if x else np.zeros(0, np.uint64) for x in b.column(2).to_pylist()]
            if not any(map(len, told)):
                continue
            h, off = _hashed(b.column(3))
            g, at, who, at_window = _batch_anchors(h, off, window, anchor)
            if not len(at):
                continue
            s = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
            size = np.diff(np.append(s, len(at))) + window - 1
            start, pos, who = at_window[s], at[s], who[s]
            # notes hold for their document only: its number is mixed in
            mark = lambda d, x: mix64(x + (d.astype(np.uint64) << np.uint64(48)))
            known = np.concatenate([mark(np.full(len(x), d), x) for d, x in enumerate(told)])
            ok = np.isin(mark(who, g[pos] >> np.uint64(16)), known)
            if not ok.any():
                continue
            start, pos, who, size = start[ok], pos[ok], who[ok], size[ok]
            frag = g[pos]
            # a fragment's content hash: running over its words, by length
            content = frag + size.astype(np.uint64)
            for i in range(int(size.max())):
                live = np.flatnonzero(size > i)
                content[live] = mix64(content[live] * np.uint64(31) + h[start[live] + i])
            place = start - off[who]
            order = np.lexsort((place, ids[who], content, frag))
            frag, who, start, size, content, place, pos = (v[order] for v in (frag, who, start, size, content, place, pos))
            new = np.concatenate([[True], (frag[1:] != frag[:-1]) | (content[1:] != content[:-1])])
            group, first = np.cumsum(new) - 1, np.flatnonzero(new)
            later = ids[who] > ids[who[first]][group]
            known = list(_packed_ranges(ids[who[later]], hs[who[later]], place[later], (place + size)[later], nb))
            if known:
                home, data, many = zip(*known)
                yield pa.RecordBatch.from_arrays([pa.array([1] * len(known), pa.int8()), pa.array(home, pa.int64()), pa.array(many, pa.int64()), pa.array([0] * len(known), pa.int64()), pa.array(data, pa.binary()), pa.array([b""] * len(known), pa.binary())], ["kind", "anchor", "id", "h", "places", "words"])
            # of the smallest document, each text's places travel with the fragment
            mine = np.flatnonzero(~later)
            who_m, group_m = who[mine], group[mine]
            x = np.flatnonzero(np.concatenate([[True], (group_m[1:] != group_m[:-1]) | (who_m[1:] != who_m[:-1])]))
            f = mine[x]
            places = _binary(place[mine].astype(np.int32).view(np.uint8), 4 * np.append(x, len(mine)))
            # the anchor's words are known by its hash: one byte says where they stand
            lead, n = pos[f] - start[f], size[f]
            within = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
            other = (within < np.repeat(lead, n)) | (within >= np.repeat(lead + anchor, n))
            body = h[(np.repeat(start[f], n) + within)[other]][:, None].view(np.uint8).reshape(-1, 8)[:, 3:]
            ends = np.concatenate([[0], np.cumsum(1 + 5 * (n - anchor))])
            data = np.empty(int(ends[-1]), np.uint8)
            rest = np.ones(len(data), bool)
            rest[ends[:-1]] = False
            data[ends[:-1]], data[rest] = lead, body.ravel()
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(f), np.int8)), pa.array(frag[f].view(np.int64)), pa.array(ids[who[f]]), pa.array(hs[who[f]]), places, _binary(data, ends)], ["kind", "anchor", "id", "h", "places", "words"])

    # kind 1, packed ranges that are known already, passes through: anchor is the documents' home bucket, id the number of ranges
    cut_up = asked.mapInArrow(fragments, "kind byte, anchor long, id long, h long, places binary, words binary")
    shards = cut_up.repartitionById(nb, F.pmod("anchor", F.lit(nb)).cast("int")).sortWithinPartitions("kind", "anchor")

    # 3. an FM-index over whole anchors' fragments, about SHARD words at a time
    def match(batches):
        held, words, now, ready, many = [], 0, None, [], 0

        def packed(rows):
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.int32()))], ["kind", "data", "n"])

        def flush():
            yield from packed(list(_packed_ranges(*(np.concatenate(c) for c in zip(*ready)), nb)) if ready else [])

        for b in batches:
            kinds = b.column(0).to_numpy()
            if kinds.any():
                known = b.filter(pa.array(kinds == 1))
                yield from packed(list(zip(*(known.column(c).to_pylist() for c in (1, 4, 2)))))
                b = b.filter(pa.array(kinds == 0))
            for a, i, t, p, w in zip(*(c.to_pylist() for c in b.columns[1:])):
                if a != now and words >= SHARD:
                    ready.append(search(held, window, anchor))
                    many += len(ready[-1][0])
                    held, words = [], 0
                    if many >= RANGES:
                        yield from flush()
                        ready, many = [], 0
                now = a
                held.append((a, i, t, p, w))
                words += len(w) // 5 + anchor
        if held:
            ready.append(search(held, window, anchor))
        yield from flush()

    found = shards.mapInArrow(match, schema).repartitionById(nb, "kind").sortWithinPartitions("kind")

    def gathered(batches):
        held, now = [], None
        arrow = (pa.int64(), pa.int64(), pa.binary())

        def close():
            rows = []
            for row in _joined_ranges(held) if held else ():
                rows.append(row)
                if len(rows) >= 4096:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow)], ["id", "h", "ranges"])
                    rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow)], ["id", "h", "ranges"])

        for b in batches:
            for k, d, n in zip(*(c.to_pylist() for c in b.columns)):
                if k != now:
                    yield from close()
                    held, now = [], k
                held.append((d, n))
        yield from close()

    return found.mapInArrow(gathered, KEY + ", ranges binary")


def search(rows: list, window: int, k: int):
    """Ranges (keys, hashes, starts, ends) of the fragments' windows that a smaller document has too: one FM-index over all of them. Equal
    fragments stand in it once, with their smallest document; for the others of them every window is a match. A window meets only
    those of its own anchor, as the anchor's words are part of it."""
    low: dict[tuple, int] = {}
    for f in rows:
        c = (f[0], f[4])
        low[c] = min(f[1], low.get(c, f[1]))
    held = [f for f in rows if f[1] == low[f[0], f[4]]]
    beaten = [f for f in rows if f[1] != low[f[0], f[4]]]
    ids = np.array([f[1] for f in held])
    rest = np.array([len(f[4]) // 5 for f in held])
    size = rest + k
    given = _unpack5(b"".join(f[4][1:] for f in held))
    # words of a fragment: given ones up to the anchor, k that stand for the anchor's own, the others
    n = len(held)
    begin = np.cumsum(size) - size
    at = begin + np.array([f[4][0] for f in held])
    own = np.zeros(int(size.sum()), bool)
    own[(at[:, None] + np.arange(k)).ravel()] = True
    words = np.empty(len(own), np.uint64)
    words[~own] = given
    kinds, kind = np.unique(np.array([f[0] for f in held], np.int64), return_inverse=True)
    words[own] = ((np.uint64(1) << np.uint64(41)) + (kind[:, None] * k + np.arange(k)).astype(np.uint64)).ravel()
    names, code = np.unique(words, return_inverse=True)
    begin = np.concatenate([[0], np.cumsum(size + 1)[:-1]])
    seq = np.zeros(int(size.sum()) + n, np.int64)
    inside = np.ones(len(seq), bool)
    inside[begin + size] = False
    seq[inside] = code + 1
    index = FMIndex(seq, len(names) + 1, int(size.max()))
    doc_at = np.repeat(ids, size + 1)[index.sa]

    def smaller(lo, hi, who):
        """Whether each interval holds a document smaller than ``who``; equal intervals are looked through once."""
        out = np.zeros(len(lo), bool)
        if not len(lo):
            return out
        pair, inv = np.unique(lo * np.int64(len(seq) + 1) + hi, return_inverse=True)
        a, b = pair // (len(seq) + 1), pair % (len(seq) + 1)
        ext = np.append(doc_at, np.iinfo(np.int64).max)
        low = np.minimum.reduceat(ext, np.stack([a, b], axis=1).ravel())[::2]
        return low[inv] < who

    def backward(end: np.ndarray, length: np.ndarray, who: np.ndarray) -> np.ndarray:
        """Whether the pattern of ``length`` words that ends before ``end`` starts in a smaller document, too."""
        lo, hi = np.zeros(len(end), np.int64), np.full(len(end), len(seq), np.int64)
        live = np.arange(len(end))
        for k in range(int(length.max()) if len(length) else 0):
            go = live[(length[live] > k)]
            s = seq[end[go] - 1 - k]
            lo[go], hi[go] = index.extend(s, lo[go], hi[go])
            alone = hi[go] - lo[go] <= 1  # only the pattern's own place is left
            hi[go[alone]] = lo[go[alone]]
            live = live[hi[live] > lo[live]]
        out = np.zeros(len(end), bool)
        out[live] = smaller(lo[live], hi[live], who[live])
        return out

    whole = backward(begin + size, size, ids)
    rest = np.flatnonzero(~whole)
    many = size[rest] - window + 1
    frag = np.repeat(rest, many)
    shift = np.arange(len(frag)) - np.repeat(np.cumsum(many) - many, many)
    hit = backward(begin[frag] + shift + window, np.full(len(frag), window), ids[frag])
    frag = np.concatenate([np.flatnonzero(whole), frag[hit]])
    a = np.concatenate([np.zeros(int(whole.sum()), np.int64), shift[hit]])
    b = np.concatenate([size[whole], shift[hit] + window])
    hits = [held[f] for f in frag] + beaten
    none = np.zeros(0, np.int64)
    if not hits:
        return none, none, none, none
    a = np.concatenate([a, np.zeros(len(beaten), np.int64)])
    b = np.concatenate([b, [len(f[4]) // 5 + k for f in beaten]]).astype(np.int64)
    places = [np.frombuffer(f[3], np.int32) for f in hits]
    times = np.array([len(p) for p in places])
    at = np.concatenate(places).astype(np.int64)
    return np.repeat(np.array([f[1] for f in hits], np.int64), times), np.repeat(np.array([f[2] for f in hits], np.int64), times), at + np.repeat(a, times), at + np.repeat(b, times)


def dedup(docs: DataFrame, window: int = 13, anchor: int = 5, key: str = "doc_id", text: str = "text", out: str = "kept_text") -> DataFrame:
    """Add n_words, n_removed and ``out``: the words that are left, joined by one space. Removed are the words covered by a
    window whose word sequence also starts in a document with a smaller key; windows are judged on the texts as given.

    A null or empty text has no words; one of fewer words than a window loses none. A row with a null key neither loses words
    nor takes any from others. Columns of the added names are replaced, others pass. An empty table gives no rows.
    """
    names = [c for c in docs.columns if c == text or c not in ("n_words", "n_removed", out)]
    kind = docs.schema[key].dataType
    base = docs.select(F.col(key).cast("long").alias("id"), F.xxhash64(text).alias("h"), F.col(text).alias("text"), *(F.col(c).alias(f"_{i}") for i, c in enumerate(names) if c not in (key, text)))
    ranges = _repeats(base, window, anchor)
    back = {key: F.col("id").cast(kind).alias(key), text: F.col("text").alias(text)}
    both = base.join(ranges.hint("merge"), ["id", "h"], "left").select(*(back.get(c, F.col(f"_{i}").alias(c)) for i, c in enumerate(names)), F.col("ranges").alias("_ranges"))
    at, place = names.index(text), len(names)

    def remove(batches):
        for b in small_batches(batches, text):
            flat, off = split_words(b.column(at))
            keep = np.ones(len(flat), bool)
            gone = np.zeros(b.num_rows, np.int64)
            for d, rs in enumerate(b.column(place).to_pylist()):
                if rs:
                    x, y = off[d], off[d + 1]
                    for s, e in np.frombuffer(rs, np.int32).reshape(-1, 2):
                        keep[x + s : x + e] = False
                    gone[d] = (~keep[x:y]).sum()
            left = flat.filter(pa.array(keep))
            new = np.concatenate([[0], np.cumsum(keep)])[off]
            import pyarrow.compute as pc

            told = pc.binary_join(pa.ListArray.from_arrays(pa.array(new, pa.int32()), left), " ")
            cols = {n: b.column(i) for i, n in enumerate(names)} | {"n_words": pa.array(np.diff(off)), "n_removed": pa.array(gone), out: told}
            yield pa.RecordBatch.from_arrays(list(cols.values()), list(cols))

    from pyspark.sql.types import LongType, StringType, StructField, StructType

    fields = {f.name: f for f in both.schema.fields[:-1]} | {"n_words": StructField("n_words", LongType()), "n_removed": StructField("n_removed", LongType()), out: StructField(out, StringType())}
    return both.mapInArrow(remove, StructType(list(fields.values())))
