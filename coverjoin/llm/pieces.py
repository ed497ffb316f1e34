"""SentencePiece encoding and decoding by a streaming Viterbi pass.

The pass goes over a text once, left to right. For each boundary it keeps a back pointer to the boundary where the best last
piece starts; only boundaries within the longest piece's length can still be extended. Whenever the back-pointer paths of all
those boundaries meet in one earlier boundary, the ids up to there are final: they are given out and forgotten.

Two models of what "best" means are covered: unigram models take the largest sum of scores; for BPE models the last piece is
the one that the merge order would leave there, found by the rule that two pieces may stand side by side if and only if
merging their joined text gives exactly these two. That rule leaves one path, so ids equal those of the merge procedure.
"""

from __future__ import annotations

import re
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import small_batches

SPACE = "▁"


class Pieces:
    """A piece table. pieces: (text, score, kind) by id; kind: normal, unknown, control, byte, unused."""

    HEAD = 6

    def __init__(self, pieces: list[tuple[str, float, str]], bpe: bool, dummy_prefix: bool = True):
        self.pieces, self.bpe, self.dummy_prefix = pieces, bpe, dummy_prefix
        self.id = {p: i for i, (p, _, k) in enumerate(pieces) if k == "normal"}
        self.score = [s for _, s, _ in pieces]
        self.unk = next((i for i, (_, _, k) in enumerate(pieces) if k == "unknown"), 0)
        self.bytes = {int(p[3:5], 16): i for i, (p, _, k) in enumerate(pieces) if k == "byte"}
        self.longest = max(map(len, self.id), default=1)
        self.least = min((self.score[i] for i in self.id.values()), default=0.0) - 10.0  # of an unknown character
        self.halves = self._halves() if bpe else None
        #: Pieces that can stand in an encoding, by id, and -1 for what only begins one.
        self.begins: dict[str, int] = {}
        for p, i in self.id.items():
            if self.halves is None or len(p) == 1 or p in self.halves:
                self.begins[p] = i
        #: The same, read from the end.
        self.ends: dict[str, int] = {}
        for p, i in self.begins.items():
            if i >= 0:
                self.ends[p] = i
                for k in range(1, len(p)):
                    self.ends.setdefault(p[k:], -1)
        for p in list(self.begins):
            for k in range(1, len(p)):
                self.begins.setdefault(p[:k], -1)
        self.heads: dict[str, tuple] = {}
        inner = any(SPACE in p.lstrip(SPACE) for p in self.id)
        #: Where no piece holds a mark behind another character, all paths meet before each run of marks.
        self.seams = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+") if not inner else None
        self.byte_of = {i: b for b, i in self.bytes.items()}
        self.names = [p if k == "normal" else " \u2047 " if k == "unknown" else "" for p, _, k in pieces]
        self.special = frozenset(self.byte_of)
        self.known: dict[str, bytes] = {}
        self.pair_fits: dict[int, bool] = {}

    # -- the merge rule of BPE models

    def _halves(self) -> dict[str, tuple[str, str, float]]:
        """Of each piece that merging can make: the two pieces of its last merge, and the rank of that merge."""
        out = {}
        for p, i in self.id.items():
            parts = list(p)
            while len(parts) > 2:
                best = max(((self.score[k], -x) for x in range(len(parts) - 1) if (k := self.id.get(parts[x] + parts[x + 1])) is not None), default=None)
                if best is None:
                    break
                x = -best[1]
                parts[x : x + 2] = [parts[x] + parts[x + 1]]
            if len(parts) == 2:
                out[p] = (parts[0], parts[1], -self.score[i])
        for p, (a, b, rank) in out.items():
            if any(len(x) > 1 and (x not in out or out[x][2] > rank) for x in (a, b)):
                raise ValueError(f"piece {p!r} is older than its parts: the merge order cannot be told from the scores")
        return out

    def side_by_side(self, a: str, b: str) -> bool:
        """Whether merging a + b leaves exactly the two: going back in time from the whole pieces to their parts at the seam,
        no merge across it may have come first. Of equal ranks the left one comes first."""
        halves, before, x, y, ok = self.halves, float("inf"), a, b, True
        while True:
            k = self.id.get(x + y)
            if k is not None and -self.score[k] < before:
                ok = False
                break
            u, v = halves.get(x), halves.get(y)
            if u is None and v is None:
                break
            if u is None or v is not None and v[2] >= u[2]:
                y, before = v[0], v[2] + 0.5  # a merge of the same rank across the seam lies further left: it wins
            else:
                x, before = u[1], u[2]
        return ok

    # -- the streaming pass

    def _forward(self, s: str, j: int, back: dict, best: dict) -> None:
        """Let the pieces that start at boundary j reach the boundaries behind it."""
        begins, n = self.begins, len(s)
        if self.bpe:
            prev = s[back[j] : j] if j else None
            for e in range(j + 1, n + 1):
                p = s[j:e]
                k = begins.get(p)
                if k is None and e > j + 1:
                    return
                if (k is None or k >= 0 or e == j + 1) and e not in back and (prev is None or self.side_by_side(prev, p)):
                    back[e] = j
                if k is None:
                    return
        else:
            here = best[j]
            for e in range(j + 1, n + 1):
                p = s[j:e]
                k = begins.get(p)
                if k is None and e > j + 1:
                    return
                if k is not None and k >= 0 or e == j + 1:
                    total = here + (self.score[k] if k is not None and k >= 0 else self.least)
                    if e not in best or total > best[e]:
                        best[e], back[e] = total, j
                if k is None:
                    return

    def stream(self, s: str):
        """Pieces of ``s``, given out as soon as they are final."""
        n, span = len(s), self.longest
        back, best = {0: -1}, {0: 0.0}
        done, check = 0, span * 4
        for i in range(1, n + 1):
            self._forward(s, i - 1, back, best)
            if i - done < check and i < n:
                continue
            ends = {i} if i == n else set(range(max(done, i - span + 1), i + 1))
            while len(ends) > 1:
                x = max(ends)
                ends.discard(x)
                ends.add(max(done, back[x]))
            x = ends.pop()
            if x > done:
                cuts = [x]
                while cuts[-1] > done:
                    cuts.append(back[cuts[-1]])
                yield from (s[a:b] for a, b in zip(cuts[::-1], cuts[-2::-1]))
                for y in range(done, x):
                    back.pop(y, None)
                    best.pop(y, None)
                done, check = x, span * 4
            else:
                check *= 2

    def ids_of(self, piece: str) -> list[int]:
        k = self.id.get(piece)
        if k is not None:
            return [k]
        raw = piece.encode("utf-8", "surrogatepass")
        return [self.bytes[b] for b in raw] if all(b in self.bytes for b in raw) else [self.unk]

    def _short(self, s: str) -> list[int]:
        """The same pass over a segment that fits into one window (BPE models): for each boundary, the id of the last piece and
        where it starts. The boundaries of a common beginning are the same in all segments, so those of the first
        ``HEAD`` characters are remembered."""
        n, ends, names = len(s), self.ends, self.pieces
        fits, head = self.pair_fits, s[: self.HEAD]
        state = self.heads.get(head)
        last, start = ([None], [0]) if state is None else (list(state[0]), list(state[1]))
        for i in range(len(last), n + 1):
            last.append(-1)
            start.append(i - 1)
            for j in range(i - 1, -1, -1):
                k = ends.get(s[j:i])
                if k is None:
                    break
                if k >= 0:
                    prev = last[j] if j else -1
                    if prev >= 0:
                        ok = fits.get(prev << 20 | k)
                        if ok is None:
                            ok = self.side_by_side(names[prev][0], names[k][0])
                            if len(fits) < 1 << 20:
                                fits[prev << 20 | k] = ok
                        if not ok:
                            continue
                    last[i], start[i] = k, j
                    break
            if i == self.HEAD and state is None and len(self.heads) < 1 << 16:
                self.heads[head] = (tuple(last), tuple(start))
        out, e = [], n
        while e:
            j = start[e]
            out += [last[e]] if last[e] >= 0 else self.ids_of(s[j:e])[::-1]
            e = j
        return out[::-1]

    def segment(self, s: str) -> bytes:
        """Ids of a segment as packed 32-bit integers; short ones are remembered."""
        ids = self.known.get(s)
        if ids is None:
            short = len(s) <= 64
            ids = array("i", self._short(s) if short and self.bpe else (k for p in self.stream(s) for k in self.ids_of(p))).tobytes()
            if short and len(self.known) < 1 << 18:
                self.known[s] = ids
        return ids

    def encode(self, text: str) -> np.ndarray:
        if not text:
            return np.zeros(0, np.int32)
        s = text.replace(" ", SPACE)
        s = SPACE + s if self.dummy_prefix else s
        if self.seams is None:
            return np.frombuffer(self.segment(s), np.int32)
        segs = self.seams.findall(s)
        return np.frombuffer(b"".join([ids if ids is not None else self.segment(g) for g, ids in zip(segs, map(self.known.get, segs))]), np.int32)

    def encode_all(self, texts: pa.Array) -> list[np.ndarray]:
        """encode() of each text (null: empty). Texts of words with one space between them are taken together: their distinct words
        are solved once, and ids are laid out by word number."""
        texts = pc.fill_null(texts.combine_chunks() if isinstance(texts, pa.ChunkedArray) else texts, "")
        odd = pc.or_(pc.match_substring(texts, SPACE), pc.match_substring_regex(texts, "^ | $|  |^$"))
        plain = pc.invert(odd).to_numpy(zero_copy_only=False) if self.seams is not None and self.dummy_prefix else np.zeros(len(texts), bool)
        out: list = [None] * len(texts)
        if plain.any():
            lists = pc.split_pattern(texts.filter(pa.array(plain)), " ")
            off = np.asarray(lists.offsets, dtype=np.int64)
            words = lists.flatten().dictionary_encode()
            own = [self.known.get(w) or self.segment(w) for w in (SPACE + w for w in words.dictionary.to_pylist())]
            size = np.array([len(x) // 4 for x in own])
            ids, begin = np.frombuffer(b"".join(own), np.int32), np.cumsum(size) - size
            which = words.indices.to_numpy()
            n = size[which]
            ends = np.concatenate([[0], np.cumsum(n)])
            flat = ids[np.repeat(begin[which] - ends[:-1], n) + np.arange(ends[-1])]
            cuts = ends[off - off[0]]
            for d, a, b in zip(np.flatnonzero(plain), cuts[:-1], cuts[1:]):
                out[d] = flat[a:b]
        for d in np.flatnonzero(~plain):
            out[d] = self.encode(texts[d].as_py())
        return out

    def decode_all(self, lists: pa.ListArray) -> pa.Array:
        """decode() of each list of ids (null: null). Lists without byte pieces are joined together."""
        lists = lists.combine_chunks() if isinstance(lists, pa.ChunkedArray) else lists
        flat, off = lists.flatten().to_numpy(), np.asarray(pc.list_value_length(lists).fill_null(0)).astype(np.int64)
        ends = np.concatenate([[0], np.cumsum(off)])
        raw = np.zeros(len(self.pieces) + 1, bool)
        raw[list(self.special)] = True
        hits = np.concatenate([[0], np.cumsum(raw[flat])])
        plain = hits[ends[1:]] == hits[ends[:-1]]
        names = pa.array([n.replace(SPACE, " ") for n in self.names])
        joined = pc.binary_join(pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), names.take(pa.array(flat))), "")
        if self.dummy_prefix:
            joined = pc.if_else(pc.starts_with(joined, " "), pc.utf8_slice_codeunits(joined, 1), joined)
        if not plain.all():
            own = {int(d): self.decode(flat[ends[d] : ends[d + 1]].tolist()) for d in np.flatnonzero(~plain)}
            joined = pc.replace_with_mask(joined, pa.array(~plain), pa.array([own[d] for d in sorted(own)]))
        return pc.if_else(lists.is_null(), pa.scalar(None, pa.string()), joined)

    def decode(self, ids) -> str:
        if self.special.isdisjoint(ids):
            s = "".join(map(self.names.__getitem__, ids))
        else:
            out, raw = [], bytearray()
            for i in ids:
                if i in self.byte_of:
                    raw.append(self.byte_of[i])
                    continue
                if raw:
                    out.append(raw.decode("utf-8", "replace"))
                    raw.clear()
                out.append(self.names[i])
            if raw:
                out.append(raw.decode("utf-8", "replace"))
            s = "".join(out)
        s = s.replace(SPACE, " ")
        return s[1:] if self.dummy_prefix and s.startswith(" ") else s


def load(path: str) -> Pieces:
    """Read a .model file; its library is used for reading only."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    m = pb.ModelProto()
    with open(path, "rb") as f:
        m.ParseFromString(f.read())
    norm = m.normalizer_spec
    if norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.escape_whitespaces or m.trainer_spec.model_type not in (1, 2):
        raise ValueError("only unigram and BPE models that leave the text as it is, but for a leading space, are read")
    kinds = {1: "normal", 2: "unknown", 3: "control", 4: "normal", 5: "unused", 6: "byte"}
    return Pieces([(p.piece, p.score, kinds[p.type]) for p in m.pieces], m.trainer_spec.model_type == 2, norm.add_dummy_prefix)


def encode(docs: DataFrame, table: Pieces, text: str = "text", out: str = "ids", keep_text: bool = True) -> DataFrame:
    """Add ``out``, the ids (array<int>) of each whole text: null for a null text, empty for an empty one. Other columns
    pass; one named ``out`` is replaced. No shuffle: texts are taken in small batches, and distinct segments are solved once
    a worker. A text longer than any batch is a batch of its own. keep_text=False leaves the texts behind."""
    from pyspark.sql.types import ArrayType, IntegerType, StructField, StructType

    docs = docs.drop(out) if out in docs.columns else docs
    raw = docs.sparkSession.sparkContext.broadcast({"table": (table.pieces, table.bpe, table.dummy_prefix)})  # a fixed vocabulary

    def run(batches):
        t = raw.value.get("ready") or raw.value.setdefault("ready", Pieces(*raw.value["table"]))  # once a worker
        for b in small_batches(batches, text, 4 << 20):
            texts = b.column(b.schema.get_field_index(text))
            got = t.encode_all(texts)
            ends = np.concatenate([[0], np.cumsum([len(g) for g in got])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(got)), mask=texts.is_null())
            names = [c for c in b.schema.names if keep_text or c != text]
            yield pa.RecordBatch.from_arrays([*(b.column(b.schema.get_field_index(c)) for c in names), lists], [*names, out])

    fields = [f for f in docs.schema.fields if keep_text or f.name != text]
    return docs.mapInArrow(run, StructType([*fields, StructField(out, ArrayType(IntegerType()))]))


def decode(rows: DataFrame, table: Pieces, ids: str = "ids", out: str = "decoded") -> DataFrame:
    """Add ``out``, the text of each array of ids (null for null). A text comes back as it was, but that U+2581 becomes a
    space and unpaired surrogates and characters outside a table without byte pieces are replaced."""
    from pyspark.sql.types import StringType, StructField, StructType

    rows = rows.drop(out) if out in rows.columns else rows
    raw = rows.sparkSession.sparkContext.broadcast({"table": (table.pieces, table.bpe, table.dummy_prefix)})

    def run(batches):
        t = raw.value.get("ready") or raw.value.setdefault("ready", Pieces(*raw.value["table"]))  # once a worker
        for b in batches:
            for at in range(0, b.num_rows, 512):
                c = b.slice(at, 512)
                yield pa.RecordBatch.from_arrays([*c.columns, t.decode_all(c.column(c.schema.get_field_index(ids)))], [*c.schema.names, out])

    return rows.mapInArrow(run, StructType([*rows.schema.fields, StructField(out, StringType())]))
