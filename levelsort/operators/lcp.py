"""Common-prefix tables of sorted string sets, what follows from them, and front coding."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.functions.text import lcp
from levelsort.operators.mergesort import ORDER, numbered
from levelsort.staging import cut


def lcp_array(s: DataFrame) -> DataFrame:
    """rank, src_id, pos, s, h (null for the first) and h2, the next one's; neighbours across partitions included.

    Strings move twice: to their range, and with their lane number for the windows. Neighbours over the border of two
    lanes come from a table of one row per lane.
    """
    rows = cut(numbered(s.select("src_id", "pos", "s").repartitionByRange(*ORDER)))
    across = W.orderBy("lane")  # one row per lane
    ends = rows.groupBy("lane").agg(F.count("*").alias("n"), F.min_by("s", "lpos").alias("first"), F.max_by("s", "lpos").alias("last"))
    base = F.coalesce(F.sum("n").over(across.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    edges = ends.select("lane", base.alias("base"), F.lag("last").over(across).alias("before"), F.lead("first").over(across).alias("after"))
    lane = W.partitionBy("lane").orderBy("lpos")
    near = rows.join(F.broadcast(edges), "lane").withColumn("before", F.coalesce(F.lag("s").over(lane), F.col("before")))
    both = near.withColumn("h", lcp(F.col("s"), F.col("before"))).withColumn("h2", F.coalesce(F.lead("h").over(lane), lcp(F.col("s"), F.col("after"))))
    return both.select((F.col("base") + F.col("lpos")).cast("bigint").alias("rank"), "src_id", "pos", "s", "h", "h2")


def dist_prefix(table: DataFrame) -> DataFrame:
    """src_id, pos, len, dist: characters needed to rank each string, sentinel included."""
    d = F.greatest(F.coalesce("h", F.lit(0)), F.coalesce("h2", F.lit(0))) + 1
    return table.select("src_id", "pos", F.length("s").alias("len"), F.least(d, F.length("s") + 1).alias("dist"))


def string_stats(table: DataFrame) -> DataFrame:
    """One row: n, chars, avg_len, avg_lcp, dn_ratio, max_len, min_len, max_dist, from an LCP table."""
    d = F.least(F.greatest(F.coalesce("h", F.lit(0)), F.coalesce("h2", F.lit(0))) + 1, F.length("s"))
    rows = table.withColumn("d", d)
    return rows.agg(
        F.count("*").alias("n"), F.sum(F.length("s")).alias("chars"), F.round(F.sum(F.length("s")) / F.count("*"), 6).alias("avg_len"), F.round(F.sum(F.coalesce("h", F.lit(0))) / F.count("*"), 6).alias("avg_lcp"),
        F.round(F.sum("d") / F.sum(F.length("s")), 6).alias("dn_ratio"), F.max(F.length("s")).cast("bigint").alias("max_len"), F.min(F.length("s")).cast("bigint").alias("min_len"), F.max("d").cast("bigint").alias("max_dist"),
    )


def alphabet(s: DataFrame) -> DataFrame:
    """n_unique strings and sigma characters of a set; characters are made distinct per string before they move."""
    letters = s.select(F.explode(F.array_distinct(F.split("s", ""))).alias("c")).where("c <> ''").agg(F.countDistinct("c").alias("sigma"))
    return s.agg(F.countDistinct("s").alias("n_unique")).crossJoin(F.broadcast(letters)).select("n_unique", "sigma")


def front_encode(rows: DataFrame) -> DataFrame:
    """lane, lpos, src_id, pos, h, tail: only what the string before it in its lane does not share."""
    w = W.partitionBy("lane").orderBy(*ORDER)
    h = F.coalesce(lcp(F.col("s"), F.lag("s").over(w)), F.lit(0))
    return rows.withColumn("lpos", F.row_number().over(w)).withColumn("h", h).select("lane", "lpos", "src_id", "pos", "h", F.expr("substring(s, h + 1)").alias("tail"))


def front_decode(encoded: DataFrame) -> DataFrame:
    """Back to lane, src_id, pos, s; streams a lane with one string of state."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lane, last = None, ""
        for b in batches:
            out = []
            for a, h, tail in zip(b.column("lane").to_pylist(), b.column("h").to_pylist(), b.column("tail").to_pylist(), strict=True):
                last = (last[:h] if a == lane else "") + tail
                lane = a
                out.append(last)
            yield pa.RecordBatch.from_arrays([b.column("lane"), b.column("src_id"), b.column("pos"), pa.array(out, pa.string())], ["lane", "src_id", "pos", "s"])

    return encoded.repartition("lane").sortWithinPartitions("lane", "lpos").mapInArrow(run, "lane int, src_id bigint, pos int, s string")
