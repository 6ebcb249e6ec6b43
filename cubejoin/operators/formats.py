"""Other sparse layouts of a binary relation, and the index as rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import written


def to_coo(edges: DataFrame) -> DataFrame:
    """Coordinates: distinct (src, dst), sorted within partitions."""
    return edges.toDF("src", "dst").distinct().sortWithinPartitions("src", "dst")


def to_csr(edges: DataFrame) -> DataFrame:
    """(src, lo, hi, dsts): sorted neighbour list of each source and its range in the joint array.

    Sources are range-partitioned and written with their partition; a running
    sum inside partitions and one over partition totals (a row each) make the
    offsets, so no task sees all sources.
    """
    spark = edges.sparkSession
    lists = edges.toDF("src", "dst").distinct().groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("dsts"))
    ranged = written(spark, lists.repartitionByRange("src").withColumn("p", F.spark_partition_id()), "csr")
    n = F.size("dsts").cast("long")
    totals = ranged.groupBy("p").agg(F.sum(n).alias("c"))
    start = F.coalesce(F.sum("c").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = ranged.join(F.broadcast(totals.select("p", start.alias("start"))), "p")  # one row a partition
    before = Window.partitionBy("p").orderBy("src").rowsBetween(Window.unboundedPreceding, -1)
    lo = F.col("start") + F.coalesce(F.sum(n).over(before), F.lit(0))
    return placed.select("src", lo.alias("lo"), (lo + n).alias("hi"), "dsts")


def to_csc(edges: DataFrame) -> DataFrame:
    """The same by target: (dst, lo, hi, srcs)."""
    flipped = edges.toDF("src", "dst").select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return to_csr(flipped).toDF("dst", "lo", "hi", "srcs")


def to_dcsr(edges: DataFrame, parts: int = 8) -> DataFrame:
    """Doubly compressed per partition: (part, src, lo, hi, dsts), only sources that exist, ranges
    local to the partition, so no global order is needed."""
    part = F.pmod(F.xxhash64("src"), F.lit(parts)).cast("int")
    lists = edges.toDF("src", "dst").distinct().groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("dsts")).withColumn("part", part)
    before = Window.partitionBy("part").orderBy("src").rowsBetween(Window.unboundedPreceding, -1)
    n = F.size("dsts").cast("long")
    lo = F.coalesce(F.sum(n).over(before), F.lit(0))
    return lists.select("part", "src", lo.alias("lo"), (lo + n).alias("hi"), "dsts")


def trie_levels(relation: DataFrame) -> DataFrame:
    """The packed index of a whole relation as rows (level, pos, value, lo, hi); lo and hi are null at
    the last level.  For inspection of small relations: positions are global windows."""
    columns = relation.columns
    out = None
    distinct = relation.distinct()
    for level in range(len(columns)):
        prefix = columns[: level + 1]
        nodes = distinct.groupBy(*prefix).agg(F.countDistinct(columns[level + 1]).alias("c") if level + 1 < len(columns) else F.lit(0).cast("long").alias("c"))
        order = Window.orderBy(*prefix)
        pos = F.row_number().over(order).cast("long") - 1
        lo = F.coalesce(F.sum("c").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        last = level + 1 == len(columns)
        null = F.lit(None).cast("long")
        rows = nodes.select(F.lit(level).alias("level"), pos.alias("pos"), F.col(columns[level]).cast("long").alias("value"), (null if last else lo).alias("lo"), (null if last else lo + F.col("c")).alias("hi"))
        out = rows if out is None else out.unionAll(rows)
    return out
