"""Cutting lineage between levels and rounds: reliable checkpoints, and tables bucketed by key, in the cluster's shared folder."""

from __future__ import annotations

import gc
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession

_made: ContextVar[list[DataFrame] | None] = ContextVar("made", default=None)


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, or the one set on the context; without either there is no safe default."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = sc.getConf().get("spark.checkpoint.dir")
        if not named:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            import tempfile

            named = tempfile.mkdtemp(prefix="levelsort-")  # one machine: its folder is shared by all tasks
        sc.setCheckpointDir(named)
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame, keep: bool = False) -> DataFrame:
    """``df`` computed once, with short lineage; ``keep``: it outlasts the ``scratch`` block it is made in."""
    shared_dir(df.sparkSession)
    out, made = df.checkpoint(), _made.get()
    if made is not None and not keep:
        made.append(out)
    return out


def forget(df: DataFrame) -> None:
    """Delete the files of a table that ``cut`` returned and that nothing reads any more."""
    at = df._jdf.queryExecution().logical().rdd().getCheckpointFile()
    if at.isDefined():
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(at.get())
        path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Tables that ``cut`` makes inside are deleted at the end, and shuffle files that nothing refers to can go."""
    held: list[DataFrame] = []
    before = _made.set(held)
    try:
        yield
    finally:
        _made.reset(before)
        for df in held:
            forget(df)
        held.clear()
        gc.collect()
        spark._jvm.System.gc()


class Bucketed:
    """``df`` as a table bucketed by ``keys``: joins and aggregates on them do not move its rows again."""

    def __init__(self, df: DataFrame, keys: list[str], buckets: int):
        self.spark, self.name = df.sparkSession, f"levelsort_{uuid.uuid4().hex}"
        path = f"{shared_dir(self.spark)}/{self.name}"
        dealt = df.repartition(buckets, *keys)
        dealt.write.format("parquet").bucketBy(buckets, *keys).option("path", path).saveAsTable(self.name)
        jvm = self.spark._jvm
        self._path = jvm.org.apache.hadoop.fs.Path(path)
        self._fs = self._path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        self._fs.deleteOnExit(self._path)

    @property
    def df(self) -> DataFrame:
        return self.spark.table(self.name)

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        self._fs.delete(self._path, True)
