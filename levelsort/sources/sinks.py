"""Sinks of sorted sets: one folder per lane with a manifest, permutations, front-coded lanes; lookup on them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def manifest(rows: DataFrame) -> DataFrame:
    """lane, first, last, n, chars: what a lookup prunes lanes by."""
    return rows.groupBy("lane").agg(F.min("s").alias("first"), F.max("s").alias("last"), F.count("*").alias("n"), F.sum(F.length("s")).alias("chars"))


def write_sorted(rows: DataFrame, path: str) -> None:
    """Sorted rows (lane, src_id, pos, s) by lane, and the manifest beside them."""
    rows.sortWithinPartitions("lane", "s", "src_id", "pos").write.partitionBy("lane").parquet(f"{path}/lanes")
    manifest(rows.sparkSession.read.parquet(f"{path}/lanes")).write.parquet(f"{path}/manifest")


def write_table(df: DataFrame, path: str) -> None:
    """Permutations (rank, src_id, pos) and front-coded lanes (lane, lpos, src_id, pos, h, tail)."""
    df.write.parquet(path)


def prefix_lookup(spark: SparkSession, path: str, prefix: str) -> DataFrame:
    """Rows with a prefix: lanes are pruned by the manifest (one row per lane), files by their statistics."""
    m = spark.read.parquet(f"{path}/manifest").where((F.left("first", F.lit(len(prefix))) <= prefix) & (F.col("last") >= prefix))
    lanes = [r["lane"] for r in m.select("lane").collect()]  # at most one per lane
    return spark.read.parquet(f"{path}/lanes").where(F.col("lane").isin(lanes) & F.col("s").startswith(prefix))
