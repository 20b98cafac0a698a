"""Shared helpers of the corpus operators: reading tables, cutting lineage, size-checked broadcasts."""

from __future__ import annotations

import ctypes
import gc
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from levelsort.staging import shared_dir

#: ASCII white space as the contracts name it: blank and code points 9 to 13.
SPACE_CLASS = r"[\x20\x09-\x0D]"
SPACE_CHARS = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows that a Python map gets at a time while a stage is written. Whole texts and sets of hashes are kilobytes each, so Spark's
#: own 10,000 rows are tens of MB, held by the writing JVM, the worker and the pools of both.
ARROW_ROWS = 1024
_ROWS_KEY = "spark.sql.execution.arrow.maxRecordsPerBatch"


@contextmanager
def short_batches(spark: SparkSession) -> Iterator[None]:
    """Arrow batches of at most ``ARROW_ROWS`` rows for what runs inside; the session's setting is put back."""
    before = spark.conf.get(_ROWS_KEY, None)
    if 0 < int(spark.conf.get(_ROWS_KEY)) <= ARROW_ROWS:
        yield
        return
    spark.conf.set(_ROWS_KEY, str(ARROW_ROWS))
    try:
        yield
    finally:
        spark.conf.unset(_ROWS_KEY) if before is None else spark.conf.set(_ROWS_KEY, before)


def give_back() -> None:
    """Memory that this process has freed goes back to the system; Arrow's pool and the C heap keep it otherwise."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim is not None:
        trim(0)


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run`` for mapInArrow, giving back freed memory before and after: Spark's workers go from task to task, so what
    one task leaves in its pools would be there in all later stages."""

    def mapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        give_back()
        try:
            yield from run(batches)
        finally:
            give_back()

    return mapped


_written: ContextVar[list[Stage] | None] = ContextVar("written", default=None)


class Stage:
    """A written intermediate table: cuts lineage, survives lost executors, can be dropped early."""

    def __init__(self, df: DataFrame, label: str):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/levelsort-{label}-{uuid.uuid4().hex}"
        with short_batches(self.spark):
            df.write.parquet(self.path)
        jvm = self.spark._jvm
        self._path = jvm.org.apache.hadoop.fs.Path(self.path)
        self._fs = self._path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        self._fs.deleteOnExit(self._path)
        if (written := _written.get()) is not None:
            written.append(self)

    @property
    def df(self) -> DataFrame:
        return self.spark.read.parquet(self.path)

    def drop(self) -> None:
        self._fs.delete(self._path, True)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner remove shuffle files of plans that nothing refers to any more."""
    gc.collect()
    spark._jvm.System.gc()


def settled(make: Callable[[], DataFrame], label: str) -> Stage:
    """``make()`` written as a table; those that ``make`` wrote on the way are dropped then, and shuffle files can go."""
    before = _written.set(passed := [])
    try:
        out = Stage(make(), label)
    finally:
        _written.reset(before)
    for stage in passed:
        if stage is not out:
            stage.drop()
    if (outer := _written.get()) is not None:
        outer.append(out)
    release(out.spark)
    return out


def fresh(df: DataFrame, name: str) -> str:
    """A column name that ``df`` does not have, in any case."""
    taken = {c.lower() for c in df.columns}
    while (name := "_" + name).lower() in taken:
        pass
    return name


def small(df: DataFrame, rows: int, bound: int) -> DataFrame:
    """Broadcast hint only when the counted rows are within the bound; a shuffled join serves beyond it."""
    return F.broadcast(df) if rows <= bound else df


def largest(hot: DataFrame, size: str, bound: int) -> DataFrame:
    """Rows of a written table ``hot`` with the largest ``size``, fewer than ``bound``, broadcast.

    Where it holds more, those above the total over ``bound`` stay (there cannot be ``bound`` of them); a key left out has
    less than that share of all rows and needs no splitting.
    """
    n, total = hot.agg(F.count("*"), F.sum(size)).first()
    return F.broadcast(hot if n < bound else hot.where(F.col(size) > F.lit(total) / bound))


HOT_ROWS = 2000


def spread_join(left: DataFrame, right: DataFrame, keys: list[str], by: str, sizes: DataFrame, how: str = "left", hot_rows: int = HOT_ROWS, bound: int = 500_000) -> DataFrame:
    """Join on ``keys``, unique in ``right``; ``sizes`` (keys, m) counts their rows in ``left``.

    Keys of more than ``hot_rows`` rows are dealt by ``by`` over one salt per ``hot_rows`` rows, the right row being repeated.
    """
    hot = Stage(sizes.where(F.col("m") > hot_rows).select(*keys, "m", F.ceil(F.col("m") / hot_rows).cast("int").alias("salts")), "hot-keys")
    if hot.df.isEmpty():
        return left.join(right, keys, how)
    salts = largest(hot.df, "m", bound).drop("m")
    dealt = left.join(salts, keys, "left").withColumn("salt", F.coalesce(F.pmod(F.xxhash64(by), F.col("salts")).cast("int"), F.lit(0))).drop("salts")
    spread = right.join(salts, keys, "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("salts") - 1, F.lit(0))))).drop("salts")
    return dealt.join(spread, [*keys, "salt"], how).drop("salt")


def ascii_lower(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def table_bytes(spark: SparkSession, sf_dir: str, name: str) -> int:
    return int(table(spark, sf_dir, name)._jdf.queryExecution().optimizedPlan().stats().sizeInBytes().longValue())
