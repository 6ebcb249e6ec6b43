"""Partition identifiers, routing of rows to cells, and the one exchange of the cube join."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from functools import reduce
from math import prod

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.tables import written

_DIRECT = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


def join_code(column: Column, kind: T.DataType) -> Column | None:
    """The long that stands for a value in joins, or None where a dictionary is needed."""
    if isinstance(kind, _DIRECT):
        return column.cast("long")
    if isinstance(kind, T.BooleanType):
        return column.cast("int").cast("long")
    if isinstance(kind, T.DateType):
        return F.unix_date(column).cast("long")
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(column)
    if isinstance(kind, (T.ArrayType, T.MapType, T.StructType, T.CalendarIntervalType, T.YearMonthIntervalType, T.DayTimeIntervalType)):
        raise ValueError(f"{kind.simpleString()} cannot be a join key; wrap it with to_json or a hash")
    return None


def from_code(column: Column, kind: T.DataType) -> Column:
    """The value back from its long (direct kinds)."""
    if isinstance(kind, T.BooleanType):
        return column.cast("boolean")
    if isinstance(kind, T.DateType):
        return F.date_from_unix_date(column.cast("int"))
    if isinstance(kind, T.TimestampType):
        return F.timestamp_micros(column)
    return column.cast(kind)


def partition_id(column: Column, share: int, seed: int, hashing: str = "xxhash64") -> Column:
    """Identifier in [0, share) of a value; every variable has its own seed.  ``mod`` takes the value itself."""
    if share == 1:
        return F.lit(0)
    source = column.cast("long") if hashing == "mod" else F.xxhash64(F.lit(seed), column)
    return F.pmod(source, F.lit(share)).cast("int")


def partition_ids(frame: DataFrame, scope: Sequence[str], order: Sequence[str], shares: Sequence[int], hashing: str = "xxhash64") -> DataFrame:
    """Adds ``s_<k>`` per column of the scope (k from 1)."""
    for k, v in enumerate(scope, 1):
        at = list(order).index(v)
        frame = frame.withColumn(f"s_{k}", partition_id(F.col(v), shares[at], at + 1, hashing))
    return frame


def block_id(scope: Sequence[str], order: Sequence[str], shares: Sequence[int]) -> Column:
    """Row-major number of a block from its identifiers."""
    at = F.lit(0)
    for k, v in enumerate(scope, 1):
        at = at * F.lit(shares[list(order).index(v)]) + F.col(f"s_{k}")
    return at


def partition_relation(frame: DataFrame, scope: Sequence[str], order: Sequence[str], shares: Sequence[int], hashing: str = "xxhash64") -> DataFrame:
    """The relation dealt into its blocks, without copies: one Spark partition per block."""
    blocks = prod(shares[list(order).index(v)] for v in scope)
    frame = partition_ids(frame, scope, order, shares, hashing).withColumn("block", block_id(scope, order, shares))
    return frame.repartitionById(blocks, F.col("block"))


def partition_layout(frame: DataFrame, scope: Sequence[str], order: Sequence[str], shares: Sequence[int], hashing: str = "xxhash64") -> DataFrame:
    """(s_1.., n, start) of every block, empty ones included: sizes and exclusive prefix sums.

    The grid has as many rows as blocks (a plan parameter), so its window may
    run in one task.
    """
    ids = [f"s_{k}" for k in range(1, len(scope) + 1)]
    counts = partition_ids(frame, scope, order, shares, hashing).groupBy(*ids).agg(F.count("*").alias("n"))
    spark = frame.sparkSession
    grid = reduce(
        lambda a, b: a.crossJoin(b),
        [spark.range(shares[list(order).index(v)]).select(F.col("id").cast("int").alias(f"s_{k}")) for k, v in enumerate(scope, 1)],
    )
    full = grid.join(F.broadcast(counts), ids, "left").select(*ids, F.coalesce("n", F.lit(0)).alias("n"))
    before = Window.orderBy(*ids).rowsBetween(Window.unboundedPreceding, -1)
    return full.select(*ids, "n", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))


def sort_blocks(frame: DataFrame, scope: Sequence[str], order: Sequence[str], shares: Sequence[int], strategy: str = "auto", cores: int = 8, hashing: str = "xxhash64") -> DataFrame:
    """Blocks sorted by the global order: block by block where there are many, by one range-partitioned
    sort where there are fewer blocks than cores."""
    held = sorted(scope, key=list(order).index)
    blocks = prod(shares[list(order).index(v)] for v in scope)
    if strategy == "auto":
        strategy = "block" if blocks > cores else "global"
    if strategy == "block":
        return partition_relation(frame, scope, order, shares, hashing).sortWithinPartitions("block", *held)
    if strategy != "global":
        raise ValueError(f"unknown strategy {strategy}")
    marked = partition_ids(frame, scope, order, shares, hashing).withColumn("block", block_id(scope, order, shares))
    return marked.repartitionByRange(cores, "block", *held).sortWithinPartitions("block", *held)


def strides(shares: Sequence[int]) -> list[int]:
    """Weight of each coordinate in a cell number."""
    out = [1] * len(shares)
    for k in range(len(shares) - 2, -1, -1):
        out[k] = out[k + 1] * shares[k + 1]
    return out


def missing_offsets(scope: Sequence[str], order: Sequence[str], shares: Sequence[int]) -> list[int]:
    """Cell offsets over all coordinates of the variables that a relation lacks."""
    step = strides(shares)
    out = [0]
    for k, v in enumerate(order):
        if v not in scope:
            out = [o + s * step[k] for o in out for s in range(shares[k])]
    return out


def route_rows(frames: Sequence[DataFrame], scopes: Sequence[Sequence[str]], order: Sequence[str], shares: Sequence[int], hashing: str = "xxhash64", weight: str | None = None, numbers: Sequence[int] | None = None, width: int | None = None) -> DataFrame:
    """Rows (cell, atom, v0.., and w if there is a weight) of all relations: each row goes to every cell
    that agrees with its identifiers.  ``numbers`` are the atoms' numbers if not 0, 1, ..."""
    step = strides(shares)
    width = width or max(map(len, scopes))
    routed = []
    for j, frame, scope in zip(numbers or range(len(frames)), frames, scopes, strict=True):
        held = sorted(scope, key=list(order).index)
        base = F.lit(0)
        for v in held:
            at = list(order).index(v)
            base = base + partition_id(F.col(v), shares[at], at + 1, hashing) * F.lit(step[at])
        offsets = missing_offsets(scope, order, shares)
        columns = [F.col(v).cast("long").alias(f"v{k}") for k, v in enumerate(held)]
        columns += [F.lit(0).cast("long").alias(f"v{k}") for k in range(len(held), width)]  # no nulls: Arrow columns stay integers
        extra = [F.col(weight).cast("long").alias("w")] if weight else []
        rows = frame.select(base.alias("base"), *columns, *extra)
        if offsets == [0]:
            rows = rows.withColumnRenamed("base", "cell")
        else:
            rows = rows.withColumn("offset", F.explode(F.array(*map(F.lit, offsets)))).withColumn("cell", F.col("base") + F.col("offset"))
        routed.append(rows.select("cell", F.lit(j).alias("atom"), *(f"v{k}" for k in range(width)), *(["w"] if weight else [])))
    return reduce(DataFrame.unionAll, routed)


def route_once(base: DataFrame, atoms: Sequence[tuple[int, Sequence[str]]], order: Sequence[str], shares: Sequence[int], hashing: str, width: int) -> DataFrame:
    """``route_rows`` of one relation of longs that several atoms read: (atom number, variable of each column).

    One pass over the relation: a row becomes one struct per atom, and each of
    these one row per agreeing cell.
    """
    step = strides(shares)
    copies, offsets = [], []
    for slot, (j, scope) in enumerate(atoms):
        column = dict(zip(scope, base.columns, strict=True))
        held = sorted(scope, key=list(order).index)
        first = F.lit(0)
        for v in held:
            at = list(order).index(v)
            first = first + partition_id(F.col(column[v]), shares[at], at + 1, hashing) * F.lit(step[at])
        values = [F.col(column[v]).cast("long").alias(f"v{k}") for k, v in enumerate(held)] + [F.lit(0).cast("long").alias(f"v{k}") for k in range(len(held), width)]
        copies.append(F.struct(F.lit(slot).alias("slot"), F.lit(j).alias("atom"), first.alias("base"), *values))
        offsets.append(F.array(*map(F.lit, missing_offsets(held, order, shares))))
    rows = base.select(F.explode(F.array(*copies)).alias("x")).select("x.*", F.explode(F.element_at(F.array(*offsets), F.col("x.slot") + 1)).alias("offset"))
    return rows.select((F.col("base") + F.col("offset")).alias("cell"), "atom", *(f"v{k}" for k in range(width)))


def exchange(rows: DataFrame, tasks: int) -> DataFrame:
    """The one shuffle: cells go to tasks by number, rows are grouped by cell.

    The sort has one integer key, which Spark sorts by radix and spills if it
    must; the relations of a cell are sorted in the kernel, where they are
    buffered anyway and sort as packed integers.
    """
    return rows.repartitionById(tasks, F.pmod(F.col("cell"), F.lit(tasks)).cast("int")).sortWithinPartitions("cell")


def encode_domains(frames: Mapping[str, DataFrame], columns: Mapping[str, Sequence[str]]) -> tuple[dict[str, DataFrame], DataFrame]:
    """Relations with the named columns replaced by dense long codes, and the dictionary (value, code).

    Codes are ranks within range partitions plus partition offsets, so no task
    sees more than its range; only one count per partition reaches the driver.
    The ranked values are written to the shared folder before anything reads
    them, so every use sees the same codes.  Values keep their order.  All columns share one dictionary and should have
    one type.
    """
    values = reduce(DataFrame.unionAll, [frames[name].select(F.col(c).alias("value")) for name, cs in columns.items() for c in cs]).where("value is not null").distinct()
    spark = values.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = values.repartitionByRange(parts, "value").sortWithinPartitions("value")
    placed = written(spark, ranged.select("value", F.spark_partition_id().alias("p"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("i")), "dictionary")
    counts = sorted((r.p, r["count"]) for r in placed.groupBy("p").count().collect())
    starts, total = [], 0
    for p, n in counts:
        starts.append((p, total))
        total += n
    offsets = spark.createDataFrame(starts or [(0, 0)], "p int, start long")
    dictionary = placed.join(F.broadcast(offsets), "p").select("value", (F.col("start") + F.col("i")).alias("code"))
    out = dict(frames)
    for name, cs in columns.items():
        frame = frames[name]
        for c in cs:
            look = dictionary.select(F.col("value").alias(f"_{c}"), F.col("code").alias(f"_{c}_code"))
            kept = [F.col(f"_{c}_code").alias(x) if x == c else F.col(x) for x in frame.columns]
            frame = frame.join(look, F.col(c) == F.col(f"_{c}"), "left").select(*kept)
        out[name] = frame
    return out, dictionary
