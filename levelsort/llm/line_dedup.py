"""Line de-duplication over levelled sorted runs of line hashes (DataFrame functions only).

A run is a table of (k1, k2, n): a 128-bit hash of a normalised line and the number of documents of one batch that
hold it, written in key order inside hash partitions. Every batch is anti-joined with the keys that the runs so far settle -
those found in ``least`` documents already - and what is left is counted and added as a run of level 0; once a level
holds ``fanout`` runs they are merged, counts added up, into one run of the next level, so a key is rewritten once
per level and at most fanout runs a level are open. With ``least`` 1 the anti-join leaves the lines never seen before; with the
threshold of common lines, what is settled needs no more counting, so lines found nearly everywhere leave the later
batches before they are shuffled. Hash collisions apart (128 bits for lines, 64 for documents) the result is exact.

Defined results: null or empty text is one empty line; keys of no code points are never dropped; a document (doc_id)
counts once for a key however often it repeats it, also in several rows; a row without doc_id is a document of its own,
equal ones being one; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelsort.llm.common import SPACE_CHARS, Stage, ascii_lower, small, spread_join

HOT_BROADCAST = 200_000
KEY = ["k1", "k2"]


def line_key(line: Column) -> Column:
    return ascii_lower(F.btrim(line, F.lit(SPACE_CHARS)))


def _row_keys(doc_id: Column, text: Column) -> list[Column]:
    """d1 names the document, (d1, d2) the row."""
    return [F.when(doc_id.isNull(), F.xxhash64(F.lit(3), text)).otherwise(F.xxhash64(doc_id)).alias("d1"), F.xxhash64(F.lit(7), text).alias("d2")]


def line_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 1) -> DataFrame:
    """One row per line that may be dropped: d1, d2 (row key), pos, k1, k2."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    lines = docs.select(*_row_keys(F.col(id_col), text), F.posexplode(F.split(text, "\n", -1)).alias("pos", "line")).withColumn("key", line_key(F.col("line")))
    return lines.where(F.length("key") >= max(1, min_chars)).select("d1", "d2", "pos", F.xxhash64(F.lit(1), "key").alias("k1"), F.xxhash64(F.lit(2), "key").alias("k2"))


class LevelledRuns:
    """The runs; keys found in ``least`` documents are settled."""

    def __init__(self, fanout: int = 4, least: int = 1):
        self.fanout, self.least = fanout, least
        self.levels: list[list[Stage]] = []
        self.compactions = 0
        self._settled: Stage | None = None
        self._n_settled = 0

    def _write(self, run: DataFrame, level: int) -> None:
        if len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(Stage(run.sortWithinPartitions(*KEY), f"run-{level}"))
        if len(self.levels[level]) >= self.fanout:
            old, self.levels[level] = self.levels[level], []
            self.compactions += 1
            self._write(self._merged([s.df for s in old]), level + 1)
            for s in old:
                s.drop()

    @staticmethod
    def _merged(runs: list[DataFrame]) -> DataFrame:
        both = runs[0]
        for r in runs[1:]:
            both = both.unionByName(r)
        return both.groupBy(*KEY).agg(F.sum("n").alias("n"))

    def unseen(self, lines: DataFrame) -> DataFrame:
        """Lines whose key the runs do not settle."""
        if self._settled is None:
            return lines
        return lines.join(small(self._settled.df.select(*KEY), self._n_settled, HOT_BROADCAST), KEY, "left_anti")

    def add(self, lines: DataFrame) -> None:
        """A batch's line table, whole documents: its unseen lines become a run; each document counts once for a key."""
        once = self.unseen(lines).select("d1", *KEY).distinct()
        self._write(once.groupBy(*KEY).agg(F.count("*").alias("n")), 0)
        counts = self._merged([s.df for level in self.levels for s in level])
        old, self._settled = self._settled, Stage(counts.where(F.col("n") >= self.least), "settled")
        self._n_settled = self._settled.df.count()
        if old is not None:
            old.drop()

    def settled(self) -> Stage | None:
        """Keys found in at least ``least`` documents, with the documents counted until they were settled."""
        return self._settled

    def drop(self) -> None:
        for s in [x for level in self.levels for x in level]:
            s.drop()


def common_line_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_docs: int = 10, min_chars: int = 1, batches: int = 4, fanout: int = 4) -> DataFrame:
    """Drop lines whose key is in at least ``min_docs`` documents: doc_id, n_lines, n_dropped, kept_text."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    lines = Stage(line_table(docs, id_col, text_col, min_chars), "lines")
    runs = LevelledRuns(fanout, min_docs)
    for b in range(batches):
        runs.add(lines.df.where(F.pmod(F.col("d1"), F.lit(batches)) == b))
    runs.drop()
    common = runs.settled().df.select(*KEY)
    n_common = common.count()
    if n_common <= HOT_BROADCAST:
        found = lines.df.join(F.broadcast(common), KEY, "left_semi")
    else:
        sizes = lines.df.join(common, KEY, "left_semi").groupBy(*KEY).agg(F.count("*").alias("m"))
        found = spread_join(lines.df, common, KEY, "d1", sizes, "inner")
    drops = found.groupBy("d1", "d2").agg(F.collect_set("pos").alias("drops"))
    rows = docs.select(F.col(id_col).alias("doc_id"), text.alias("text")).select("doc_id", "text", *_row_keys(F.col("doc_id"), F.col("text")))
    drop_at = F.coalesce("drops", F.array().cast("array<int>"))
    split = rows.join(drops, ["d1", "d2"], "left").select("doc_id", "text", F.split("text", "\n", -1).alias("all_lines"), drop_at.alias("drops"))
    stay = F.array_except(F.sequence(F.lit(0), F.size("all_lines") - 1), F.col("drops"))
    return split.select(
        "doc_id",
        F.size("all_lines").cast("long").alias("n_lines"),
        F.size("drops").cast("long").alias("n_dropped"),
        F.when(F.size("drops") == 0, F.col("text")).otherwise(F.array_join(F.transform(stay, lambda i: F.get("all_lines", i)), "\n")).alias("kept_text"),
    )


def incremental_line_dedup(batches: list[DataFrame], id_col: str = "doc_id", text_col: str = "text", fanout: int = 4) -> list[DataFrame]:
    """Batch by batch: the keys (d1, d2, pos, k1, k2) of lines first seen in that batch, and none seen before."""
    runs, out = LevelledRuns(fanout), []
    for batch in batches:
        lines = Stage(line_table(batch, id_col, text_col), "batch-lines")
        out.append(Stage(runs.unseen(lines.df), "unseen").df)
        runs.add(lines.df)
    return out
