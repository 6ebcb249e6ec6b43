"""Relational helpers around the joins."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def equi_join(left: DataFrame, right: DataFrame, keys: Sequence[str], how: str = "inner", strategy: str | None = None) -> DataFrame:
    """inner, left, right, full, left_semi or left_anti; strategy: broadcast, merge or shuffle_hash."""
    hints = {None: None, "broadcast": "broadcast", "merge": "merge", "shuffle_hash": "shuffle_hash"}
    if strategy not in hints:
        raise ValueError(f"unknown strategy {strategy}")
    return left.join(right.hint(strategy) if strategy else right, list(keys), how)


def salted_join(left: DataFrame, right: DataFrame, keys: Sequence[str], salts: int = 16) -> DataFrame:
    """Inner join whose hot keys on the left are spread over ``salts`` tasks; the right side is copied so often."""
    spread = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    copied = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return spread.join(copied, [*keys, "_salt"]).drop("_salt")


def range_join(left: DataFrame, right: DataFrame, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of ``left`` whose number ``at`` lies in [lo, hi) of a row of ``right``, by buckets of ``width``:
    an interval is copied to every bucket it touches and each point looks in its own only."""
    points = left.withColumn("_bucket", F.floor(F.col(at) / width))
    spans = right.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))))
    return points.join(spans, "_bucket").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_bucket")


def as_of_join(left: DataFrame, right: DataFrame, keys: Sequence[str], at: str, values: Sequence[str]) -> DataFrame:
    """Each left row with the latest right row of its key at or before ``at`` (nulls if none).

    Both sides go through one shuffle on the key and one sort: a union and a
    running last value, no pairs.
    """
    mine = left.columns
    a = left.select(*mine, F.lit(1).alias("_side"), *(F.lit(None).cast(right.schema[v].dataType).alias(f"_{v}") for v in values))
    blank = [F.col(c) if c in (*keys, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in mine]
    b = right.select(*blank, F.lit(0).alias("_side"), *(F.col(v).alias(f"_{v}") for v in values))
    order = Window.partitionBy(*keys).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    held = F.last(F.when(F.col("_side") == 0, F.struct(*(f"_{v}" for v in values))), ignorenulls=True).over(order)
    rows = a.unionAll(b).withColumn("_held", held).where("_side = 1")
    return rows.select(*mine, *(F.col(f"_held._{v}").alias(f"as_of_{v}") for v in values))


def top_k(frame: DataFrame, k: int, *order: Column) -> DataFrame:
    return frame.orderBy(*order).limit(k)


def top_k_per(frame: DataFrame, keys: Sequence[str], k: int, *order: Column) -> DataFrame:
    """The k first rows of each key; ranks are limited before the shuffle too."""
    ranked = frame.withColumn("rank", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)))
    return ranked.where(F.col("rank") <= k)


def vertex_triangles(edges: DataFrame) -> DataFrame:
    """(v, triangles) of an undirected graph, each triangle counted once per corner."""
    from ..sources.tables import written
    from .factorize import orient_by_degree

    up = written(edges.sparkSession, orient_by_degree(edges), "oriented")
    wedges = up.toDF("a", "b").join(up.toDF("b", "c"), "b").join(up.toDF("a", "c"), ["a", "c"])
    return wedges.select(F.explode(F.array("a", "b", "c")).alias("v")).groupBy("v").agg(F.count("*").alias("triangles"))


def degrees(edges: DataFrame) -> DataFrame:
    """(v, out_degree, in_degree) of distinct edges."""
    e = edges.toDF("src", "dst").distinct()
    sides = e.select(F.col("src").alias("v"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionAll(e.select("dst", F.lit(0), F.lit(1)))
    return sides.groupBy("v").agg(F.sum("o").cast("long").alias("out_degree"), F.sum("i").cast("long").alias("in_degree"))


def clustering(edges: DataFrame) -> DataFrame:
    """(v, degree, triangles, coefficient) of an undirected graph: closed share of neighbour pairs."""
    e = edges.toDF("src", "dst")
    both = e.union(e.select("dst", "src")).where("src <> dst").distinct()
    degree = both.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))
    joined = degree.join(vertex_triangles(edges), "v", "left").select("v", "degree", F.coalesce("triangles", F.lit(0)).alias("triangles"))
    return joined.withColumn("coefficient", F.when(F.col("degree") > 1, 2.0 * F.col("triangles") / (F.col("degree") * (F.col("degree") - 1))).otherwise(0.0))
