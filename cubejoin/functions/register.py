"""User functions: sorted-set sizes, a skew index, and pattern matching as a table function."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf


@arrow_udf(T.LongType())
def sorted_intersect_size(a: pa.Array, b: pa.Array) -> pa.Array:
    """Common elements of two sorted duplicate-free arrays; null if either is null."""
    out = []
    for x, y in zip(a, b, strict=True):
        if not x.is_valid or not y.is_valid:
            out.append(None)
            continue
        p, q = x.values.to_numpy(zero_copy_only=False), y.values.to_numpy(zero_copy_only=False)
        if len(p) > len(q):
            p, q = q, p
        at = np.searchsorted(q, p)
        at[at == len(q)] = 0
        out.append(int((q[at] == p).sum()) if len(q) else 0)
    return pa.array(out, pa.int64())


@pandas_udf(T.DoubleType())
def skew_index(v: pd.Series) -> float:
    """Largest over mean."""
    mean = v.mean()
    return float(v.max() / mean) if len(v) and mean else 0.0


class PatternMatch:
    """Table function: rows (src, dst) of one partition and a rule over E, to result arrays.

    ``SELECT * FROM match_pattern(TABLE(e) WITH SINGLE PARTITION, 'Q(x,y,z) :- E(x,y), E(y,z), E(x,z)')``.
    With PARTITION BY a cell number and rows routed to cells it runs per cell.
    """

    def __init__(self):
        self.rows: list[tuple[int, int]] = []
        self.rule = None

    def eval(self, row, rule: str):
        self.rule = rule
        self.rows.append((row["src"], row["dst"]))

    def terminate(self):
        from ..operators.kernel import generic_join
        from ..plans.planner import quick_plan
        from ..query import parse_rule

        if self.rule is None:
            return
        query = parse_rule(self.rule)
        order = quick_plan(query).order
        rows = [[tuple(r[a.vars.index(v)] for v in s) for r in self.rows] for a, s in zip(query.atoms, query.scopes, strict=True)]
        for found in generic_join(rows, order, query.scopes):
            yield ([found[order.index(v)] for v in query.head],)


def register_functions(spark: SparkSession) -> None:
    """Makes the functions above and match_pattern visible to SQL."""
    from pyspark.sql.functions import udtf

    spark.udf.register("sorted_intersect_size", sorted_intersect_size)
    spark.udf.register("skew_index", skew_index)
    spark.udtf.register("match_pattern", udtf(PatternMatch, returnType="binding: array<bigint>"))


def parse_props(frame: DataFrame, column: str = "props") -> DataFrame:
    """The number under ``k`` of a JSON text column, JVM-side."""
    return frame.withColumn("k", F.get_json_object(column, "$.k").cast("long"))


def plan_to_json(plan) -> str:
    return json.dumps({"order": plan.order, "shares": plan.shares, "lifts": [[x.level, x.at_depth, list(x.inputs)] for x in plan.lifts], "executor": plan.executor})
