"""Relational operators around the sorts, each a composition of built-in DataFrame operations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.functions.text import DoublingPrefixes
from levelsort.operators.mergesort import ORDER, dense_index
from levelsort.sources.strings import load, pieces

BROADCAST_BYTES = 64 << 20


def filter_prefix(df: DataFrame, key: str, prefix: str) -> DataFrame:
    """Reaches the scan as a pushed StartsWith filter."""
    return df.where(F.col(key).startswith(prefix))


def filter_range(df: DataFrame, key: str, lo: str, hi: str) -> DataFrame:
    return df.where((F.col(key) >= lo) & (F.col(key) < hi))


def join_on(a: DataFrame, b: DataFrame, on: str, how: str = "inner", strategy: str = "auto") -> DataFrame:
    """``strategy``: merge, shuffle_hash, broadcast (only if the right side's estimated size allows), auto."""
    if strategy == "broadcast":
        size = int(b._jdf.queryExecution().optimizedPlan().stats().sizeInBytes().longValue())
        return a.join(F.broadcast(b) if size <= BROADCAST_BYTES else b, on, how)
    return a.join(b if strategy == "auto" else b.hint(strategy), on, how)


def range_assign(df: DataFrame, key: str, bounds: list[float]) -> DataFrame:
    """band = number of bounds below the value; a decision tree in generated code instead of a range join."""
    band = F.lit(0)
    for b in bounds:
        band = band + (F.col(key) > F.lit(b)).cast("int")
    return df.withColumn("band", band)


def asof(left: DataFrame, right: DataFrame, on: str, by: str, value: str) -> DataFrame:
    """Last ``value`` of ``right`` at or before each left row: one shuffle of the union, no pairs."""
    rows = left.withColumn("_side", F.lit(1)).unionByName(right.withColumn("_side", F.lit(0)), allowMissingColumns=True)
    w = W.partitionBy(by).orderBy(on, "_side", F.col(value).asc_nulls_last()).rowsBetween(W.unboundedPreceding, 0)
    return rows.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").drop("_side")


def within(left: DataFrame, right: DataFrame, by: str, on: str, seconds: int) -> DataFrame:
    """Pairs with left.on <= right.on <= left.on + seconds: equal keys and time slots, so a busy key is spread over slots."""
    slot = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("_slot", F.explode(F.array(slot(on), slot(on) + 1))).withColumnRenamed(on, "_a")
    b = right.withColumn("_slot", slot(on)).withColumnRenamed(on, "_b")
    met = a.join(b, [by, "_slot"]).where((F.col("_b") >= F.col("_a")) & (F.col("_b") <= F.col("_a") + F.expr(f"INTERVAL {seconds} SECONDS")))
    return met.select(*[c for c in left.columns if c not in (by, on)], *[c for c in right.columns if c not in (by, on)])


def prefix_groups(df: DataFrame, key: str, d: int, id_col: str = "page_id") -> DataFrame:
    """Groups of strings that share a d-prefix, by aggregate instead of a pair join."""
    return df.groupBy(F.left(key, F.lit(d)).alias("prefix")).agg(F.count("*").alias("n"), F.min(id_col).alias("first")).where("n > 1")


def running(df: DataFrame, by: str, order: str, value: str) -> DataFrame:
    return df.withColumn("total", F.sum(value).over(W.partitionBy(by).orderBy(order)))


def ith_string(s: DataFrame, i: int, parts: int = 64) -> DataFrame:
    """The string of 0-based rank i, without sorting the others: sampled splitters, counts per bucket, one bucket sorted.

    Equal strings share a bucket; a bucket is sorted by its own numbered rows, so it may take more than one task.
    """
    rows = s.select("src_id", "pos", "s")
    lanes = rows.sample(0.02, 7).select("s").union(rows.select("s").limit(parts))  # the sample only balances: any splitters are right
    at = [k / parts for k in range(1, parts)]
    cuts = lanes.select(F.ntile(parts).over(W.orderBy("s")).alias("tile"), "s").groupBy("tile").agg(F.max("s").alias("s"))
    arrays = F.broadcast(cuts.where(F.col("tile") <= len(at)).agg(F.array_sort(F.collect_set("s")).alias("fs")))  # parts strings
    below = lambda acc, x: acc + (x < F.col("s")).cast("int")
    dealt = rows.crossJoin(arrays).select("src_id", "pos", "s", F.aggregate("fs", F.lit(0), below).alias("bucket"))
    sizes = dealt.groupBy("bucket").agg(F.count("*").alias("n")).withColumn("stop", F.sum("n").over(W.orderBy("bucket")))
    mine = F.broadcast(sizes.where((F.col("stop") > i) & (F.col("stop") - F.col("n") <= i)).select("bucket", (F.lit(i) - F.col("stop") + F.col("n")).alias("rest")))
    inside = dense_index(dealt.join(mine, "bucket").select("src_id", "pos", "s", "rest"), list(ORDER))
    return inside.where(F.col("idx") == F.col("rest")).select("src_id", "pos", "s")


def median_string(s: DataFrame) -> DataFrame:
    """The lower median of the order by (s, src_id, pos)."""
    return ith_string(s, (s.count() - 1) // 2)


def lines_of(spark: SparkSession, sf_dir: str, lang: str) -> DataFrame:
    return pieces(load(spark, sf_dir, "documents").where(F.col("lang") == lang), "doc_id", "text").select("s")


def set_op(a: DataFrame, b: DataFrame, kind: str) -> DataFrame:
    return {"union": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[kind]()


def dedup(s: DataFrame, key: str) -> DataFrame:
    return s.groupBy(key).agg(F.min("src_id").alias("src_id"))


def regular_sample(df: DataFrame, by: str, order: list[str], k: int) -> DataFrame:
    """k evenly spaced rows of each group in its order."""
    ranked = df.withColumn("_r", F.row_number().over(W.partitionBy(by).orderBy(*order))).withColumn("_n", F.count("*").over(W.partitionBy(by)))
    return ranked.where(F.array_contains(F.transform(F.sequence(F.lit(1), F.lit(k)), lambda t: F.floor(t * F.col("_n") / (k + 1))), F.col("_r").cast("bigint"))).drop("_r", "_n")


def prefix_lookup(s: DataFrame, prefix: str) -> DataFrame:
    """Strings with a prefix; on a sorted sink only the files whose range meets it are read."""
    return s.where(F.col("s").startswith(prefix))


def doubling_prefixes(s: DataFrame) -> DataFrame:
    spark = s.sparkSession
    spark.udtf.register("doubling_prefixes", DoublingPrefixes)
    s.select("src_id", "s").createOrReplaceTempView("_doubling_in")
    return spark.sql("SELECT src_id, p.d, p.prefix FROM _doubling_in, LATERAL doubling_prefixes(s) p")
