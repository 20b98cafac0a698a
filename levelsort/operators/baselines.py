"""What the level sorts are compared with: hypercube quicksort, one box, Spark's range sort."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.operators.merge import merge_lanes
from levelsort.operators.mergesort import ORDER, dense_index, global_rank, lane_bases, numbered
from levelsort.staging import cut


def fold_hash(lanes: int) -> Column:
    """Random permutation by a hash of the locator, folded onto 2^floor(log2 p) lanes."""
    d = lanes.bit_length() - 1
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.col("src_id").cast("string"), F.col("pos").cast("string"))), 1, 15), 16, 10).cast("bigint")
    return F.pmod(h, F.lit(1 << d)).cast("int")


def hypercube_round(state: DataFrame, bit: int, lanes: int, keys: tuple[str, ...] = ORDER) -> DataFrame:
    """One split across a dimension: the pivot of a sub-cube is the lower median of its lanes' lower medians."""
    cube = F.shiftright("lane", bit + 1).alias("cube")
    lane = W.partitionBy("lane").orderBy(*keys)
    mid = state.withColumn("r", F.row_number().over(lane)).withColumn("n", F.count("*").over(W.partitionBy("lane"))).where(F.col("r") == F.floor((F.col("n") + 1) / 2))
    c = W.partitionBy("cube")
    medians = mid.select(cube, *keys)
    pivots = medians.withColumn("r", F.row_number().over(c.orderBy(*keys))).withColumn("n", F.count("*").over(c)).where(F.col("r") == F.floor((F.col("n") + 1) / 2)).select("cube", F.struct(*keys).alias("pivot"))
    above = (F.struct(*keys) > F.col("pivot")).cast("int")
    base = F.col("lane").bitwiseAND(F.lit((lanes - 1) ^ (1 << bit)))
    return state.withColumn("cube", F.shiftright("lane", bit + 1)).join(F.broadcast(pivots), "cube").withColumn("lane", (base + above * (1 << bit)).cast("int")).drop("cube", "pivot")


def hypercube_moves(s: DataFrame, p: int, keys: tuple[str, ...] = ORDER) -> Iterator[DataFrame]:
    """State after each of the d rounds: run (the lane a row came from), lane, and the columns of ``s``."""
    d = p.bit_length() - 1
    state = s.select(fold_hash(p).alias("lane"), *s.columns)
    for bit in reversed(range(d)):
        split = hypercube_round(state.withColumn("run", F.col("lane")), bit, 1 << d, keys)
        moved = cut(split.select("run", "lane", *s.columns).repartitionById(1 << d, F.col("lane")))
        yield moved
        state = moved.drop("run")


def hypercube_sort(s: DataFrame, p: int, with_lcp: bool = False) -> DataFrame:
    """Ranked result; d rounds, each moves every string at most once. ``with_lcp`` ends with the prefix-aware merge of the
    runs that meet in a lane, otherwise lanes are sorted."""
    if p < 2:
        return global_rank(s.select(F.lit(0).alias("lane"), "src_id", "pos", "s"))
    *_, last = hypercube_moves(s.select("src_id", "pos", "s"), p)
    if not with_lcp:
        return global_rank(last.drop("run"))
    before = F.coalesce(F.sum("n").over(W.orderBy("lane").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    offsets = last.groupBy("lane").agg(F.count("*").alias("n")).select("lane", before.alias("base"))  # one row per lane
    merged = merge_lanes(last).join(F.broadcast(offsets), "lane").select((F.col("base") + F.col("lpos")).cast("bigint").alias("rank"), "src_id", "pos")
    return merged.join(last.select("src_id", "pos", "s"), ["src_id", "pos"]).select("rank", "src_id", "pos", "s")


def hypercube_merge_work(s: DataFrame, p: int) -> DataFrame:
    """round, with_lcp, plain: characters that merging looks at in each round, summed over the lanes."""
    out = None
    for i, moved in enumerate(hypercube_moves(s.select("src_id", "pos", "s"), p), 1):
        total = lambda kind: merge_lanes(moved, kind).groupBy("lane").agg(F.max("looked").alias("x")).agg(F.sum("x").alias("with_lcp" if kind else "plain"))  # noqa: E731, B023
        one = total(True).crossJoin(total(False)).select(F.lit(i).alias("round"), "with_lcp", "plain")
        out = one if out is None else out.unionByName(one)
    return out


def single_node_sort(s: DataFrame) -> DataFrame:
    """The whole input in one task: the sequential baseline."""
    return s.coalesce(1).select(F.row_number().over(W.orderBy(*ORDER)).cast("bigint").alias("rank"), "src_id", "pos", "s")


def single_box_sort(s: DataFrame, cores: int | None = None) -> DataFrame:
    """One machine with shared memory: as many tasks as it has cores, splitters from a sample of all of them."""
    cores = cores or s.sparkSession.sparkContext.defaultParallelism
    rows = cut(numbered(s.select("src_id", "pos", "s").repartitionByRange(cores, *ORDER)))
    return rows.join(F.broadcast(lane_bases(rows)), "lane").select((F.col("base") + F.col("lpos")).cast("bigint").alias("rank"), "src_id", "pos", "s")


def spark_sort(s: DataFrame) -> DataFrame:
    """Range partitions by sampled keys, local sort, dense numbers."""
    return dense_index(s.select("src_id", "pos", "s"), list(ORDER)).select((F.col("idx") + 1).cast("bigint").alias("rank"), "src_id", "pos", "s")
