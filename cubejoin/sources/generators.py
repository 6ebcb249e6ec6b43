"""Synthetic relations, generated on the executors."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def tensor_relation(spark: SparkSession, n: int, dims: Sequence[int], seed: int, columns: Sequence[str] | None = None, counters: DataFrame | None = None) -> DataFrame:
    """About n distinct points of a grid: coordinates are a counter's residues, one multiplier per axis
    (plain arithmetic, so that any SQL engine can make the same points).  ``counters`` (a column
    ``id`` below 2**26) takes the place of 0, 1, ... n - 1."""
    names = columns or [f"x{k}" for k in range(len(dims))]
    axes = [F.expr(axis_sql("id", seed, k, d)).alias(c) for k, (d, c) in enumerate(zip(dims, names, strict=True))]
    return (spark.range(n) if counters is None else counters).select(*axes).distinct()


def axis_sql(counter: str, seed: int, axis: int, domain: int) -> str:
    """Coordinate of a counter below 2**26 on an axis, in SQL that Spark and other engines share."""
    step = 1_000_003 + 7_919 * (31 * seed + axis)
    return f"((({counter} * {step} + {97 * seed + 13 * axis}) % 2147483647) * 48271 % 2147483647) % {domain}"


def tensor_dims(kind: str, n: int, domain: int, small: int = 8, sparsity: float | None = None) -> dict[str, tuple[int, int, int]]:
    """Domains of the seven relations of ``tensor_workload``."""
    if kind == "sparse":
        share = sparsity or 0.001
        domain = max(2, round((n / share) ** (1 / 3)))
        wide = max(2, round((n / (10 * share) / small) ** 0.5))
    elif kind == "dense":
        wide = domain
    else:
        raise ValueError(f"unknown kind {kind}")
    return {f"t{k}": (domain,) * 3 for k in range(1, 5)} | {f"t{k}": (small, wide, wide) for k in range(5, 8)}


def tensor_workload(spark: SparkSession, kind: str, n: int, domain: int, small: int = 8, sparsity: float | None = None, counters: DataFrame | None = None) -> dict[str, DataFrame]:
    """Seven ternary relations: 1-4 over equal domains, 5-7 with a small first axis.

    dense: the domain as given (tuples fill much of it); sparse: domains grow so
    that n tuples fill the fraction ``sparsity``.  ``counters``: see ``tensor_relation``.
    """
    dims = tensor_dims(kind, n, domain, small, sparsity)
    return {name: tensor_relation(spark, n, d, int(name[1:]), counters=counters) for name, d in dims.items()}


def worst_case_edges(spark: SparkSession, n: int) -> DataFrame:
    """{0} x [n] and [n] x {0}: any two-way plan of the triangle makes n^2 rows, its output is O(n)."""
    ids = spark.range(n).select(F.col("id"))
    zero = F.lit(0).cast("long")
    return ids.select(zero.alias("src"), F.col("id").alias("dst")).union(ids.select(F.col("id").alias("src"), zero.alias("dst"))).distinct()


def hub_edges(spark: SparkSession, n: int, share: float = 0.5) -> DataFrame:
    """n edges, a share of which leave vertex 0."""
    hot = F.col("id") < int(n * share)
    src = F.when(hot, F.lit(0).cast("long")).otherwise(F.pmod(F.xxhash64("id", F.lit(1)), F.lit(n)))
    return spark.range(n).select(src.alias("src"), F.pmod(F.xxhash64("id", F.lit(2)), F.lit(n)).alias("dst")).where("src <> dst").distinct()
