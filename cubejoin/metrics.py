"""Measures of plans and runs."""

from __future__ import annotations

import time
from collections.abc import Callable, Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators.executor import bind_relations, cell_profile
from .operators.trie import PackedTrie
from .plans.planner import JoinPlan
from .query import ConjunctiveQuery


def bench(run: Callable[[], object], repeats: int = 3, warmup: int = 1, timeout: float = 10_000.0) -> dict:
    """Mean seconds over ``repeats`` after ``warmup`` runs; ``timed_out`` once a run passes ``timeout``
    (a run is not interrupted, but none follows it)."""
    for _ in range(warmup):
        began = time.perf_counter()
        run()
        if time.perf_counter() - began > timeout:
            return {"seconds": None, "timed_out": True, "runs": []}
    runs = []
    for _ in range(repeats):
        began = time.perf_counter()
        run()
        runs.append(time.perf_counter() - began)
        if runs[-1] > timeout:
            return {"seconds": None, "timed_out": True, "runs": runs}
    return {"seconds": sum(runs) / len(runs), "timed_out": False, "runs": runs}


def cell_work(profile: DataFrame) -> DataFrame:
    """(cell, work): values visited and comparisons, which do not depend on the machine."""
    visited = F.aggregate("visited", F.lit(0).cast("long"), lambda s, x: s + x)
    return profile.select("cell", (visited + F.col("comparisons")).alias("work"), "rows_in", "rows_out", "seconds")


def skew_summary(profile: DataFrame, cells: int, column: str = "work") -> DataFrame:
    """max/mean, p99/p50, coefficient of variation and the top 1% cells' share; cells without a row have no work."""
    work = cell_work(profile) if "work" not in profile.columns else profile
    everyone = profile.sparkSession.range(cells).select(F.col("id").cast("int").alias("cell")).join(work.select("cell", column), "cell", "left").select(F.coalesce(F.col(column), F.lit(0)).cast("double").alias("x"))
    top = max(1, cells // 100)
    largest = everyone.orderBy(F.desc("x")).limit(top).agg(F.sum("x").alias("t"))
    base = everyone.agg(F.avg("x").alias("mean"), F.max("x").alias("max"), F.stddev_pop("x").alias("sd"), F.expr("percentile(x, 0.5)").alias("p50"), F.expr("percentile(x, 0.99)").alias("p99"), F.sum("x").alias("all"))
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    c = F.col
    return base.crossJoin(largest).select(ratio(c("max"), c("mean")).alias("max_over_mean"), ratio(c("p99"), c("p50")).alias("p99_over_p50"), ratio(c("sd"), c("mean")).alias("cv"), ratio(c("t"), c("all")).alias("top1_share"))


def runtime_curve(profile: DataFrame, tiles: int = 10) -> DataFrame:
    """(tile, work): mean work of the cells by decile, the curve of cells sorted by work."""
    from pyspark.sql import Window

    tiled = cell_work(profile).withColumn("tile", F.ntile(tiles).over(Window.orderBy("work")))
    return tiled.groupBy("tile").agg(F.avg("work").alias("work"))


def duplication(profile: DataFrame, distinct_per_level: Sequence[int]) -> DataFrame:
    """(level, visited, distinct, factor): values visited by all cells over the distinct ones."""
    rows = profile.select(F.posexplode("visited").alias("level", "n")).groupBy("level").agg(F.sum("n").alias("visited"))
    known = profile.sparkSession.createDataFrame(list(enumerate(distinct_per_level)), "level int, distinct long")
    return rows.join(known, "level").withColumn("factor", F.col("visited") / F.greatest(F.col("distinct"), F.lit(1)))


def relative_speed(mine: float, other: float) -> float:
    """How many times faster ``mine`` is."""
    return other / mine


def speedups(seconds: Mapping[int, float]) -> dict[int, float]:
    """T(1) / T(c) by cores."""
    return {c: seconds[1] / s for c, s in seconds.items()}


def index_size(frame: DataFrame) -> dict:
    """Bytes of the packed index of a small relation (one block) and of its rows."""
    import numpy as np

    rows = sorted(set(map(tuple, frame.select(*(F.col(c).cast("long") for c in frame.columns)).toPandas().itertuples(index=False))))
    columns = [np.array([r[k] for r in rows], np.int64) for k in range(len(frame.columns))]
    trie = PackedTrie.build(columns)
    return {"index_bytes": trie.nbytes, "row_bytes": 8 * len(rows) * len(columns)}


def phase_times(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan) -> dict:
    """Seconds of preprocessing (routing, exchange, sorting into a persisted copy) and of the rest."""
    from .operators.executor import _kernel
    from .operators.kernel import KernelPlan
    from .operators.shuffle import exchange, route_rows

    folded, frames, _, _ = bind_relations(query, relations)
    scopes = [tuple(sorted(a.vars, key=plan.order.index)) for a in folded.atoms]
    began = time.perf_counter()
    rows = exchange(route_rows(frames, scopes, plan.order, plan.shares, plan.hashing), plan.tasks or plan.cells).persist()
    rows.count()
    middle = time.perf_counter()
    kernel = KernelPlan(plan.order, tuple(scopes), tuple((x.level, x.at_depth, x.inputs) for x in plan.lifts), plan.index, plan.search)
    n = rows.mapInArrow(_kernel(kernel, "count", None), "n long").agg(F.sum("n")).first()[0]
    end = time.perf_counter()
    rows.unpersist()
    return {"preprocess": middle - began, "join": end - middle, "share": (middle - began) / (end - began), "n": n}


def measured_communication(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan) -> DataFrame:
    """(cell, rows) as routed, counted over the data."""
    from .operators.shuffle import route_rows

    folded, frames, _, _ = bind_relations(query, relations)
    scopes = [tuple(sorted(a.vars, key=plan.order.index)) for a in folded.atoms]
    return route_rows([f.distinct() for f in frames], scopes, plan.order, plan.shares, plan.hashing).groupBy("cell").agg(F.count("*").alias("rows"))


def cpu_utilisation(profile: DataFrame, wall: float, cores: int) -> float:
    """Share of the cores' time that cells spent joining."""
    busy = profile.agg(F.sum("seconds")).first()[0] or 0.0
    return busy / (wall * cores)


def share_study(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plans: Sequence[JoinPlan]) -> list[dict]:
    """Total and largest cell work of each plan: what its order and shares cost."""
    out = []
    for plan in plans:
        got = cell_work(cell_profile(spark, query, relations, plan)).agg(F.sum("work").alias("total"), F.max("work").alias("largest"), F.sum("rows_in").alias("rows_in"), F.sum("rows_out").alias("rows_out")).first()
        out.append({"order": plan.order, "shares": plan.shares, **got.asDict()})
    return out
