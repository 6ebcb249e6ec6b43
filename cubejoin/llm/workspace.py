"""Shared, executor-loss-proof materialisation.

Intermediate tables are written as Parquet below the folder named by
``spark.checkpoint.dir`` (where that is unset: a folder in the warehouse, which
executors share as well) and read back, which cuts the lineage: a lost executor
costs a re-read, never a recomputation chain.  The setting is only read.

Tables do not outlive their use: an operator drops what its result does not
read, ``transient`` drops the tables of all operators that ran inside it, and
what is left goes when the driver's process ends.
"""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Iterator
from contextlib import contextmanager, suppress

from pyspark.sql import DataFrame, SparkSession

#: Folders still in use and how to delete them, in the order of their creation.
_OPEN: dict[str, Workspace] = {}


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors see."""
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if not configured:
        configured = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not configured:
        configured = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_cubejoin_work"
    return configured.rstrip("/")


@contextmanager
def small_batches(spark: SparkSession, rows: int = 512) -> Iterator[None]:
    """Fewer rows per Arrow batch while an eager step runs: long texts then take little memory in
    the JVM's buffers and the Python workers."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


class Workspace:
    """Named Parquet tables of one operator run.

    ``table`` writes and rereads; ``drop`` removes tables that no returned
    DataFrame reads any more, ``keep`` all but the named ones, ``close`` all.
    """

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_folder(spark)}/{label}_{uuid.uuid4().hex}"
        self._paths: dict[str, str] = {}
        self._hadoop = (spark.sparkContext._jvm.org.apache.hadoop.fs.Path, spark.sparkContext._jsc.hadoopConfiguration())
        _OPEN[self.root] = self

    def table(self, name: str, frame: DataFrame, batch: int = 512) -> DataFrame:
        """Written and read back; ``batch`` rows go to a Python worker at a time."""
        path = f"{self.root}/{name}"
        schema = frame.schema
        with small_batches(self.spark, batch):
            frame.write.mode("overwrite").parquet(path)
        self._paths[name] = path
        return self.spark.read.schema(schema).parquet(path)

    def _delete(self, where: str) -> None:
        make, conf = self._hadoop
        path = make(where)
        path.getFileSystem(conf).delete(path, True)

    def drop(self, *names: str) -> None:
        for name in names:
            self._delete(self._paths.pop(name))

    def keep(self, *names: str) -> None:
        self.drop(*(n for n in [*self._paths] if n not in names))

    def close(self) -> None:
        _OPEN.pop(self.root, None)
        self._paths.clear()
        self._delete(self.root)


@contextmanager
def transient(spare: Workspace | None = None) -> Iterator[None]:
    """Closes every workspace opened inside, but ``spare``, once the block's own results are written."""
    before = set(_OPEN)
    try:
        yield
    finally:
        for root in [r for r in _OPEN if r not in before]:
            if _OPEN[root] is not spare:
                _OPEN[root].close()


@atexit.register
def _sweep() -> None:
    for work in [*_OPEN.values()]:
        with suppress(Exception):  # the JVM may be gone by then
            work.close()
