"""Heavy values: residual queries in which hot values get cells of their own.

A value with more rows than a block's fair share defeats hashing of its
variable.  Each variable's rows split into heavy and light ones; every
combination is a query of its own over filtered relations, in which a variable
that is heavy is not split (its few values cannot fill partitions) and its share
goes to the other variables.  The results are disjoint.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import replace
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.planner import JoinPlan, quick_plan
from ..query import ConjunctiveQuery, fold_predicates
from ..sources.tables import written
from .executor import cube_join


#: Values of a list that is broadcast, at most.
BROADCAST_VALUES = 1_000_000


def heavy_values(frames: Mapping[str, DataFrame], scopes: list[tuple[str, ...]], threshold: int) -> dict[str, DataFrame]:
    """Per variable the values with more than ``threshold`` rows in some relation: at most
    rows / threshold of them, so a broadcast of the list is bounded by the threshold chosen."""
    found: dict[str, list[DataFrame]] = {}
    for j, scope in enumerate(scopes):
        for v in scope:
            counted = frames[f"r{j}"].groupBy(v).agg(F.count("*").alias("c")).where(F.col("c") > threshold)
            found.setdefault(v, []).append(counted.select(v))
    return {v: reduce(DataFrame.unionAll, fs).distinct() for v, fs in found.items()}


def residual_shares(plan: JoinPlan, heavy: tuple[str, ...]) -> tuple[int, ...]:
    """Shares with the heavy variables' factors moved to the light ones, smallest first."""
    shares = [1 if v in heavy else p for v, p in zip(plan.order, plan.shares, strict=True)]
    light = [k for k, v in enumerate(plan.order) if v not in heavy]
    spare = plan.cells
    for p in shares:
        spare //= p
    while spare > 1 and light:
        k = min(light, key=lambda k: (shares[k], k))
        shares[k] *= 2
        spare //= 2
    return tuple(shares)


def heavy_split_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan | None = None, threshold: int = 100_000, mode: str = "count") -> DataFrame:
    """The cube join with heavy values apart; only variables that have heavy values are split."""
    plan = plan or quick_plan(query)
    folded, frames = fold_predicates(query, relations)
    frames = {k: f.distinct() for k, f in frames.items()}
    scopes = folded.scopes
    lists = {v: written(spark, h, "heavy") for v, h in heavy_values(frames, scopes, threshold).items()}
    sizes = {v: h.count() for v, h in lists.items()}
    hot = [v for v in plan.order if sizes.get(v)]
    lists = {v: F.broadcast(h) if sizes[v] <= BROADCAST_VALUES else h for v, h in lists.items()}
    parts = []
    for choice in product((False, True), repeat=len(hot)):
        chosen = dict(zip(hot, choice, strict=True))
        kept = {}
        for j, scope in enumerate(scopes):
            frame = frames[f"r{j}"]
            for v in scope:
                if v in chosen:
                    frame = frame.join(lists[v], v, "left_semi" if chosen[v] else "left_anti")
            kept[f"r{j}"] = frame.select(*scope)
        own = replace(plan, shares=residual_shares(plan, tuple(v for v in hot if chosen[v])), tasks=None)
        parts.append(cube_join(spark, folded, kept, own, mode))
    out = reduce(DataFrame.unionAll, parts)
    return out.agg(F.sum("n").cast("long").alias("n")) if mode == "count" else out
