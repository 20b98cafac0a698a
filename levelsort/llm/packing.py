"""Best-fit-decreasing packing of token pieces into windows.

Documents are tokenised once; overlong ones are first cut into full windows, what is left over is one piece of
1 to window-1 tokens. Best-fit decreasing only looks at lengths, so it is solved exactly on the histogram of
lengths (at most ``window`` numbers, whatever the corpus): pieces are taken from long to short, and a segment
tree over remaining capacities finds the tightest open window class; the windows of that class are filled with the
length at once, each with as many pieces as it holds. The outcome is a table of fills - for a length, ranks lo to hi
go to windows from a start number, so many to a window from one offset on - which is joined back to the pieces by
(length, rank). Its size depends on ``window`` alone: a step either finishes a length or fills a run of equal windows.

Ranks come from counts per (length, salt), so a length that a third of all documents share is no hot task.

Defined results: null or empty text is the document end token alone; repeated rows are packed each; null ids are
carried as they are; an empty table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelsort.llm.common import Stage, lean

WINDOW, END_ID, SALTS = 4096, 2, 256
MEMO_ENTRIES, SLICE = 300_000, 1024
CLOSING = ".,;:!?"


class WordIds:
    """White-space-separated lower-case word -> its ids as little-endian bytes, in a bounded memo.

    The memo has two generations: a full one becomes the former one, and its words come back as they are met again, so
    frequent words are never learnt twice and rare ones do not pile up.

    Ids are the library's own: unseen words go to it many at a time, and the ids are cut at word ends or at marks set
    between words. A slice of texts is split, and its distinct words found, by
    Arrow kernels; Python touches each distinct word of a slice once, and one take lays out the ids of all its texts.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks are the parallelism; threads of the library only contend
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        self.mark = np.array(self._library("§"), "<u4")
        vocabulary = self.tokenizer.get_vocab()
        self.ends_word = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends_word[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self.known, self.former = {"": b""}, {}

    def _library(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def _cut(self, words: list[str], glue: str, ends_of) -> None:
        """Library ids of words joined by ``glue``; ``ends_of`` gives each word's (start, stop), or None where the
        count of words does not fit - those words then go to the library alone."""
        groups = [words[at : at + 200] for at in range(0, len(words), 200)]
        for g, e in zip(groups, self.tokenizer.encode_batch_fast([glue.join(g) for g in groups], add_special_tokens=False), strict=True):
            ids = np.array(e.ids, "<u4")
            starts, stops = ends_of(ids)
            if len(stops) != len(g):
                self.known.update((w, np.array(self._library(w), "<u4").tobytes()) for w in g)
                continue
            raw = ids.tobytes()
            self.known.update((w, raw[a:z]) for w, a, z in zip(g, (4 * starts).tolist(), (4 * stops).tolist(), strict=True))

    def _at_word_ends(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        stops = np.flatnonzero(self.ends_word[ids]) + 1
        return np.concatenate(([0], stops[:-1])), stops

    def _at_marks(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = len(self.mark)
        at = np.flatnonzero((ids[:-1] == self.mark[0]) & (ids[1:] == self.mark[1]) if n == 2 else ids == self.mark[0])
        return np.concatenate(([0], at + n)), np.concatenate((at, [len(ids)]))

    def learn(self, words: list[str]) -> None:
        """A word of letters is one unit to the library, and has at least one word end: as many ends as words in a
        group means one each. Letters before closing punctuation are a unit of their own as well. All else is marked."""
        letters, tailed, other, alone = set(), [], set(), []
        for w in words:
            if w.isalpha():
                letters.add(w)
                continue
            stem = w.rstrip(CLOSING)
            if stem.isalpha():
                tail = w[len(stem) :]
                tailed.append((w, stem, tail))
                if stem not in self.known:
                    letters.add(stem)
                if tail not in self.known:
                    other.add(tail)
            elif "§" in w:
                alone.append(w)
            else:
                other.add(w)
        self._cut(list(letters), " ", self._at_word_ends)
        self._cut(list(other), " § ", self._at_marks)
        self.known.update((w, np.array(self._library(w), "<u4").tobytes()) for w in alone)
        self.known.update((w, self.known[stem] + self.known[tail]) for w, stem, tail in tailed)

    def encode_all(self, texts: pa.Array) -> list[bytes]:
        """All ids of each text (null: none), equal to the library's on the whole text."""
        texts = pc.fill_null(texts, "")
        # a reserved token may be in a text with its first two characters: the library decides on such a text as a whole
        whole = pc.match_substring(texts, "<|")
        words = pc.ascii_split_whitespace(pc.ascii_lower(pc.if_else(whole, "", texts)))
        coded = words.flatten().dictionary_encode()
        distinct = coded.dictionary.to_numpy(zero_copy_only=False).tolist()
        if len(self.known) > MEMO_ENTRIES:
            self.former, self.known = self.known, {"": b""}
        unseen = []
        for w in distinct:
            if w not in self.known:
                if (ids := self.former.get(w)) is None:
                    unseen.append(w)
                else:
                    self.known[w] = ids
        self.learn(unseen)
        ids = pa.array(list(map(self.known.__getitem__, distinct)), pa.large_binary()).take(coded.indices)
        if not len(ids):
            out = [b""] * len(texts)
        else:
            at = np.frombuffer(ids.buffers()[1], "<i8", len(ids) + 1, 8 * ids.offset)
            ends = at[words.offsets.to_numpy() - words.offsets[0].as_py()].tolist()
            data = memoryview(ids.buffers()[2])
            out = [bytes(data[a:z]) for a, z in zip(ends, ends[1:])]
        for i in np.flatnonzero(whole.to_numpy(zero_copy_only=False)).tolist():
            out[i] = np.array(self._library(texts[i].as_py()), "<u4").tobytes()
        return out


#: One memo per Python worker and tokenizer file; tasks of the same worker share it.
_MEMOS: dict[str, WordIds] = {}


def _pieces(path: str, window: int, end_id: int, with_ids: bool):
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if path not in _MEMOS:
            _MEMOS[path] = WordIds(path)
        memo = _MEMOS[path]
        for b in batches:
            for at in range(0, b.num_rows, SLICE):
                part, cols = b.slice(at, SLICE), ([], [], [], [], [], [])
                coded = memo.encode_all(part.column("text"))
                for doc, raw in zip(part.column("doc_id").to_pylist(), coded, strict=True):
                    ids = raw + end
                    n = len(ids) // 4
                    for lo in range(0, n, window):
                        cut = ids[4 * lo : 4 * (lo + window)]
                        for c, v in zip(cols, (doc, lo, len(cut) // 4, zlib.crc32(cut), n, cut if with_ids else None), strict=True):
                            c.append(v)
                yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols[:5]), pa.array(cols[5], pa.binary())], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "ids"])

    return run


def pieces(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, ids (the ids as bytes where asked for)."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return texts.mapInArrow(lean(_pieces(tokenizer_path, window, end_id, with_ids)), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, ids binary")


class TightestFit:
    """Segment tree over remaining capacities 0..size-1; each leaf says whether a window of it is open."""

    def __init__(self, size: int):
        self.base = 1 << max(1, (size - 1).bit_length())
        self.any = [False] * (2 * self.base)

    def put(self, capacity: int, is_open: bool) -> None:
        i = self.base + capacity
        self.any[i] = is_open
        while i > 1:
            i //= 2
            self.any[i] = self.any[2 * i] or self.any[2 * i + 1]

    def at_least(self, need: int) -> int | None:
        """Smallest open capacity >= need."""
        i = self.base + need
        if self.any[i]:
            return need
        while i > 1:
            if i % 2 == 0 and self.any[i + 1]:
                i += 1
                while i < self.base:
                    i = 2 * i if self.any[2 * i] else 2 * i + 1
                return i - self.base
            i //= 2
        return None


def fills(histogram: dict[int, int], window: int = WINDOW) -> list[tuple[int, int, int, int, int, int]]:
    """(length, lo, hi, first window, offset, per): pieces of that length with rank lo <= r < hi go to the windows from
    first on, ``per`` to a window, one behind the other from offset on.

    After a piece of a length, its window is the tightest one for the next piece of that length while it has room for
    it, so best-fit fills a window with the length before it turns to the next; equal windows are filled at once.
    """
    tree, open_runs, out, windows = TightestFit(window + 1), {}, [], 0

    def leave(capacity: int, first: int, size: int) -> None:
        if capacity and size:
            open_runs.setdefault(capacity, []).append((first, size))
            tree.put(capacity, True)

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left:
            capacity = tree.at_least(length)
            if capacity is None:
                capacity = window
                first, size = windows, -(-left // (window // length))
                windows += size
            else:
                runs = open_runs[capacity]
                first, size = runs.pop()
                if not runs:
                    tree.put(capacity, False)
            per = capacity // length
            full = min(size, left // per)
            rest = left - full * per if full < size else 0  # fewer than ``per``, in one more window
            for at, n, k in ((first, full, per), (first + full, 1, rest)):
                if n * k:
                    out.append((length, rank, rank + n * k, at, window - capacity, k))
                    leave(capacity - k * length, at, n)
                    rank, left = rank + n * k, left - n * k
            used = full + (rest > 0)
            leave(capacity, first + used, size - used)
    return out


def placements(histogram: dict[int, int], window: int = WINDOW) -> list[tuple[int, int, int, int, int]]:
    """``fills`` by single offsets, (length, lo, hi, first window, offset): rank lo <= r < hi goes to window first + r - lo."""
    out = []
    for length, lo, hi, first, offset, per in fills(histogram, window):
        size = (hi - lo) // per
        out += [(length, lo + k * size, lo + (k + 1) * size, first, offset + k * length) for k in range(per)]
    return out


def pack(cut: DataFrame, window: int = WINDOW, salts: int = SALTS) -> DataFrame:
    """Adds sequence_id and offset to pieces (doc_id, start, length, ids_crc32, doc_tokens)."""
    spark = cut.sparkSession
    stage = Stage(cut.withColumn("salt", F.pmod(F.xxhash64("doc_id", "start"), F.lit(salts)).cast("int")), "pieces")
    counts = Stage(stage.df.groupBy("length", "salt").agg(F.count("*").alias("n")), "length-counts")
    histogram = {r["length"]: r["n"] for r in counts.df.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `window` rows
    table = fills(histogram, window)
    plan = spark.createDataFrame(pa.table({k: pa.array([x[i] for x in table], pa.int64()) for i, k in enumerate(("length", "lo", "hi", "first", "offset", "per"))}))
    from pyspark.sql import Window as W

    before = F.coalesce(F.sum("n").over(W.partitionBy("length").orderBy("salt").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    bases = counts.df.select("length", "salt", before.alias("base"))  # at most window * salts rows
    local = F.row_number().over(W.partitionBy("length", "salt").orderBy("doc_id", "start", "ids_crc32")) - 1
    ranked = stage.df.withColumn("local", local).join(bases, ["length", "salt"]).withColumn("rank", F.col("base") + F.col("local"))
    placed = ranked.join(F.broadcast(plan), "length").where("rank >= lo and rank < hi")
    return placed.select(*[c for c in cut.columns], F.expr("first + (rank - lo) div per").alias("sequence_id"), F.expr("offset + (rank - lo) % per * length").alias("offset"))


def padding(packed: DataFrame, window: int = WINDOW) -> DataFrame:
    """One row: sequences, tokens, padded tokens; a sequence whose length is a power of two needs none."""
    used = packed.groupBy("sequence_id").agg(F.sum("length").alias("used"))
    pad = F.when(F.bit_count("used") == 1, F.lit(0)).otherwise(window - F.col("used"))
    return used.agg(F.count("*").alias("sequences"), F.sum("used").alias("tokens"), F.sum(pad).alias("padding"))


def packed_documents(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, end_id: int = END_ID, with_ids: bool = False) -> DataFrame:
    """Pieces with their place; ``with_ids`` keeps their ids (little-endian), which then move with the pieces."""
    cut = pieces(docs, tokenizer_path, window, end_id, with_ids=with_ids)
    return pack(cut if with_ids else cut.drop("ids"), window)
