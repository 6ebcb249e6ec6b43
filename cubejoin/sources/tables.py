"""Scans and sinks."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Iterator, Sequence
from contextlib import contextmanager, suppress

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_tables(spark: SparkSession, sf_dir: str, names: Sequence[str] = TABLES) -> dict[str, DataFrame]:
    return {n: table(spark, sf_dir, n) for n in names}


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", kind: T.DataType | None = None, **options) -> DataFrame:
    """(src, dst) of an edge list in csv, json, orc or parquet; the schema is given, never inferred."""
    kind = kind or T.LongType()
    schema = T.StructType([T.StructField("src", kind), T.StructField("dst", kind)])
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def materialize(frame: DataFrame, path: str, order: Sequence[str] | None = None, parts: int | None = None) -> DataFrame:
    """A Parquet copy, distinct and range-sorted by ``order``, read back: row-group statistics then prune scans."""
    columns = list(order or frame.columns)
    spark = frame.sparkSession
    out = frame.distinct()
    out = out.repartitionByRange(parts, *columns) if parts else out.repartitionByRange(*columns)
    out.sortWithinPartitions(*columns).write.mode("overwrite").parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


_WRITTEN: list[tuple[object, object, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """A folder that all executors see: the one named by ``spark.checkpoint.dir``, else one in the warehouse."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    return (named or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_cubejoin_work").rstrip("/")


def run_folder(spark: SparkSession, label: str) -> str:
    """A new folder name below the shared one; what is there goes when the driver's process ends."""
    path = f"{shared_folder(spark)}/{label}_{uuid.uuid4().hex}"
    _WRITTEN.append((spark.sparkContext._jvm.org.apache.hadoop.fs.Path, spark.sparkContext._jsc.hadoopConfiguration(), path))
    return path


@contextmanager
def swept_shuffles(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what is written meanwhile go as soon as it is written, not when the driver collects its garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def written(spark: SparkSession, frame: DataFrame, label: str) -> DataFrame:
    """The frame as a table in the shared folder: computed once, whatever executors are lost later."""
    path, schema = run_folder(spark, label), frame.schema
    with swept_shuffles(spark):
        frame.write.parquet(path)
    return spark.read.schema(schema).parquet(path)


def dropped(path: str) -> None:
    """A folder of ``run_folder`` goes before the driver's process ends."""
    for at, (make, conf, known) in enumerate(_WRITTEN):
        if known == path:
            _delete(make, conf, path)
            del _WRITTEN[at]
            return


def _delete(make, conf, path: str) -> None:
    at = make(path)
    at.getFileSystem(conf).delete(at, True)


@atexit.register
def _sweep() -> None:
    for made in _WRITTEN:
        with suppress(Exception):  # the JVM may be gone by then
            _delete(*made)


def write_result(frame: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: Sequence[str] = ()) -> None:
    writer = frame.write.mode(mode).format(fmt)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.save(path)


def write_blocks(frame: DataFrame, scope: Sequence[str], order: Sequence[str], shares: Sequence[int], path: str, hashing: str = "xxhash64") -> None:
    """The relation's blocks as folders by identifier: a reader of one cell lists its block only."""
    from ..operators.shuffle import partition_ids

    ids = [f"s_{k}" for k in range(1, len(scope) + 1)]
    partition_ids(frame, scope, order, shares, hashing).repartition(*ids).sortWithinPartitions(*sorted(scope, key=list(order).index)).write.mode("overwrite").partitionBy(*ids).parquet(path)


def read_block(spark: SparkSession, path: str, ids: Sequence[int], scope: Sequence[str]) -> DataFrame:
    """One block of a store; the filter prunes to its folder."""
    frame = spark.read.parquet(path)
    for k, i in enumerate(ids, 1):
        frame = frame.where(f"s_{k} = {int(i)}")
    return frame.select(*scope)
