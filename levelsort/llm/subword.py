"""SentencePiece-compatible encoding and decoding as a weighted finite-state transducer.

The transducer is the composition of three machines: the normaliser (blank to the visible-space mark, a mark put
before the text), the piece lexicon with byte fallback (arcs: piece -> id, weight = -score), and, for merge-trained
models, a two-piece constraint whose arcs have weight infinity where the merge order could not leave the two pieces
side by side. Its tropical shortest path over an input is the encoding: with the constraint every prefix has exactly
one path of finite weight, so the relaxation keeps one predecessor per position; without it (unigram models) it is
the usual least-cost path. Decoding runs the lexicon backwards.

No arc crosses a position whose two characters are adjacent in no piece, so an input falls apart there and paths of
the parts are concatenated; parts repeat a lot, so their paths are kept in a bounded memo.

Defined results: null text encodes as empty (no ids); byte pieces that are not valid UTF-8 decode to U+FFFD; a null
id decodes as nothing; repeated rows get equal results; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MARK = "▁"
# Fixed values of the model format: piece types, trainer model types.
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, MERGES = 1, 2
#: Memo entries per worker; frequent parts come early, so a full memo is left as it is.
PARTS, WORDS = 900_000, 500_000


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Field numbers and raw values of one protocol-buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        shift = value = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 127) << shift
            shift += 7
            if b < 128:
                return value

    while at < len(data):
        key = varint()
        if key & 7 == 0:
            yield key >> 3, varint()
        elif key & 7 == 2:
            n = varint()
            yield key >> 3, data[at : at + n]
            at += n
        else:
            n = 4 if key & 7 == 5 else 8
            yield key >> 3, data[at : at + n]
            at += n


class PieceModel:
    """What the transducer needs of a model file: pieces with scores and types, model type, normaliser switches."""

    def __init__(self, data: bytes):
        import struct

        self.pieces: list[tuple[str, float, int]] = []
        self.kind, self.fallback = UNIGRAM, False
        self.dummy_prefix, self.squeeze, self.escape, self.charsmap = True, True, True, b""
        for n, v in _fields(data):
            if n == 1:
                x = dict(_fields(v))
                self.pieces.append((x.get(1, b"").decode("utf-8"), struct.unpack("<f", x[2])[0] if 2 in x else 0.0, x.get(3, NORMAL)))
            elif n == 2:
                x = dict(_fields(v))
                self.kind, self.fallback = x.get(3, UNIGRAM), bool(x.get(35, 0))
            elif n == 3:
                x = dict(_fields(v))
                self.charsmap = x.get(2, b"")
                self.dummy_prefix, self.squeeze, self.escape = (bool(x.get(k, 1)) for k in (3, 4, 5))

    @classmethod
    def load(cls, path: str) -> PieceModel:
        with open(path, "rb") as f:
            return cls(f.read())


class Transducer:
    """Compiled once per worker; ``encode`` and ``decode`` are the two directions."""

    def __init__(self, model: PieceModel):
        if model.charsmap:
            raise ValueError("models with a character map need its normaliser compiled first; this one has none of its rules")
        self.model = model
        self.cost, self.ids, self.bytes, self.output = {}, {}, {}, []
        self.unknown = 0
        for i, (piece, score, kind) in enumerate(model.pieces):
            self.output.append(b"" if kind == CONTROL else " ⁇ ".encode() if kind == UNKNOWN else piece.encode("utf-8"))
            if kind in (NORMAL, USER_DEFINED):
                self.ids[piece], self.cost[piece] = i, -score
            elif kind == BYTE:
                self.bytes[int(piece[3:5], 16)] = i
                self.output[i] = bytes([int(piece[3:5], 16)])
            elif kind == UNKNOWN:
                self.unknown = i
        self.longest = max(map(len, self.ids), default=1)
        self.starts: dict[str, int] = {}
        for p in self.ids:  # longest piece by first character bounds the arcs tried from a position
            self.starts[p[0]] = max(self.starts.get(p[0], 0), len(p))
        self.ends: dict[str, list[int]] = {}
        for p in self.ids:
            self.ends.setdefault(p[-1], set()).add(len(p))
        self.ends = {c: sorted(n, reverse=True) for c, n in self.ends.items()}
        self.glued = {(a, b) for p in self.ids for a, b in zip(p, p[1:], strict=False)}
        self.pairs: dict[tuple[str, str], bool] = {}
        self.parts: dict[str, tuple[int, ...]] = {}
        self.words: dict[str, bytes] = {}

    def normalise(self, text: str) -> str:
        m = self.model
        if m.squeeze:
            text = re.sub(" +", " ", text).strip(" ")
        if not text:
            return ""
        if m.dummy_prefix:
            text = " " + text
        return text.replace(" ", MARK) if m.escape else text

    def _merge(self, s: str) -> list[str]:
        """The merge order applied to one string of two pieces; decides whether the two may stand side by side."""
        parts = list(s)
        while len(parts) > 1:
            best, at = math.inf, -1
            for i in range(len(parts) - 1):
                c = self.cost.get(parts[i] + parts[i + 1], math.inf)
                if c < best:
                    best, at = c, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def allowed(self, a: str, b: str) -> bool:
        ok = self.pairs.get((a, b))
        if ok is None:
            if len(self.pairs) > 1_000_000:
                self.pairs.clear()
            ok = self.pairs[a, b] = self._merge(a + b) == [a, b]
        return ok

    def _fallback(self, c: str) -> list[int]:
        return [self.bytes[b] for b in c.encode("utf-8", "replace")] if self.model.fallback and self.bytes else [self.unknown]

    def path(self, s: str) -> tuple[int, ...]:
        """Ids of the shortest path over one part."""
        n, merges = len(s), self.model.kind == MERGES
        dist, last = [0.0] + [math.inf] * n, [""] * (n + 1)
        for end in range(1, n + 1):
            for size in self.ends.get(s[end - 1], ()):
                lo = end - size
                if lo < 0 or dist[lo] == math.inf:
                    continue
                p = s[lo:end]
                c = self.cost.get(p)
                if c is None or dist[lo] + c >= dist[end]:
                    continue
                if merges:
                    before = last[lo]
                    if (before and before in self.cost and not self.allowed(before, p)) or (size > 2 and not self.reachable(p)):
                        continue
                    dist[end], last[end] = dist[lo] + c, p
                    break
                dist[end], last[end] = dist[lo] + c, p
            if dist[end] == math.inf and s[end - 1] not in self.ids:
                dist[end], last[end] = dist[end - 1] + 1e6, s[end - 1]
        out: list[str] = []
        while n:
            out.append(last[n])
            n -= len(last[n])
        return tuple(i for p in reversed(out) for i in ([self.ids[p]] if p in self.ids else self._fallback(p)))

    def reachable(self, p: str) -> bool:
        """Whether merging ever makes the piece."""
        ok = self.pairs.get((p, ""))
        if ok is None:
            ok = self.pairs[p, ""] = self._merge(p) == [p]
        return ok

    def _part(self, s: str) -> tuple[int, ...]:
        ids = self.parts.get(s)
        if ids is None:
            ids = self.path(s)
            if len(s) <= 32 and len(self.parts) < PARTS:
                self.parts[s] = ids
        return ids

    def _word(self, w: str) -> bytes:
        lo, ids, glued = 0, [], self.glued
        for i in range(1, len(w)):
            if (w[i - 1], w[i]) not in glued:
                ids += self._part(w[lo:i])
                lo = i
        ids += self._part(w[lo:])
        return b"".join(i.to_bytes(4, "little") for i in ids)

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian 32-bit numbers."""
        s = self.normalise(text or "")
        if not s:
            return b""
        if not self.spaced:
            return self._word(s)
        # a mark after another character starts a new part, as no piece has that pair; runs of marks stay together
        words, res, run = self.words, [], 0
        for k, w in enumerate(s.split(MARK)):
            run += k > 0
            if not w:
                continue
            if run == 1:
                x = words.get(w)
                if x is None:
                    x = self._word(MARK + w)
                    if len(w) <= 32 and len(words) < WORDS:
                        words[w] = x
            else:
                x = self._word(MARK * run + w)
            res.append(x)
            run = 0
        if run:
            res.append(self._word(MARK * run))
        return b"".join(res)

    @property
    def spaced(self) -> bool:
        """No piece has a mark after another character, so parts may be cut before every run of marks."""
        if not hasattr(self, "_spaced"):
            self._spaced = self.model.escape and not any(b == MARK and a != MARK for a, b in self.glued)
        return self._spaced

    def decode(self, ids: Iterator[int]) -> str:
        s = b"".join(map(self.output.__getitem__, ids)).decode("utf-8", "replace")
        if self.model.escape:
            s = s.replace(MARK, " ")
        return s[1:] if self.model.dummy_prefix and s.startswith(" ") else s


#: One compiled transducer, with its memos, per Python worker and model file.
_MACHINES: dict[str, Transducer] = {}


def _machine(model_path: str) -> Transducer:
    if model_path not in _MACHINES:
        _MACHINES[model_path] = Transducer(PieceModel.load(model_path))
    return _MACHINES[model_path]


def encode_documents(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids (binary, little-endian 32-bit), n_ids, ids_crc32, decoded (the round trip)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import array

        machine = _machine(model_path)
        for b in batches:
            for at in range(0, b.num_rows, 128):
                part = b.slice(at, 128)
                ids = [machine.encode(t) for t in part.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(ids, pa.binary()), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(map(zlib.crc32, ids), pa.int64()), pa.array([machine.decode(array.array("I", x)) for x in ids])],
                    ["doc_id", "ids", "n_ids", "ids_crc32", "decoded"],
                )

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return texts.mapInArrow(run, "doc_id long, ids binary, n_ids long, ids_crc32 long, decoded string")


def decode_documents(encoded: DataFrame, model_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, text from encoded ids (binary)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import array

        machine = _machine(model_path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([machine.decode(array.array("I", x or b"")) for x in b.column("ids").to_pylist()])], ["doc_id", "text"])

    return encoded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(run, "doc_id long, text string")
