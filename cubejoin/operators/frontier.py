"""The same loop nest as DataFrame steps: one level of bindings at a time, no replication.

Each binding proposes the values of the atom with the fewest continuations and
the other atoms keep those they also have.  Every step is an equi join that
Catalyst and AQE see, so skewed values are split at run time and traffic is the
sum of the level sizes: the executor for inputs whose replication would cost too
much.
"""

from __future__ import annotations

from collections.abc import Mapping
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.planner import JoinPlan, quick_plan
from ..query import ConjunctiveQuery, fold_predicates


def frontier_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan | None = None, mode: str = "tuples", checkpoint_every: int = 0, distinct_inputs: bool = False) -> DataFrame:
    """All bindings (head order) or their number ``n``; set semantics.

    ``checkpoint_every`` materialises every so many levels through
    ``checkpoint()``, for long queries.  ``distinct_inputs`` says that the
    relations hold no equal rows.
    """
    plan = plan or quick_plan(query)
    folded, frames = fold_predicates(query, relations)
    scopes = folded.scopes
    full = {j: (frames[f"r{j}"] if distinct_inputs else frames[f"r{j}"].distinct()) for j in range(len(scopes))}
    lifted = {level: [x for x in plan.lifts if x.level == level] for level in range(len(plan.order))}
    bindings: DataFrame | None = None
    bound: list[str] = []
    pending = list(folded.filters)
    for level, v in enumerate(plan.order):
        held = [j for j, s in enumerate(scopes) if v in s]
        parts: list[tuple[tuple[str, ...], DataFrame]] = []
        used: set[int] = set()
        table = None
        for x in sorted(lifted[level], key=lambda x: x.at_depth):
            # The lifted intersection as a relation over the variables it depends on.
            for j in x.inputs:
                if j < 0 or j in used:
                    continue
                known = [b for b in bound if b in scopes[j]]
                one = full[j].select(*known, v).distinct()
                if table is None:
                    table = (tuple(known), one)
                else:
                    common = [b for b in known if b in table[0]] + [v]
                    keys = tuple(dict.fromkeys([*table[0], *known]))
                    table = (keys, table[1].join(one, common).select(*keys, v))
                used.add(j)
        if table is not None:
            parts.append(table)
        for j in held:
            if j not in used:
                known = tuple(b for b in bound if b in scopes[j])
                whole = set(known) | {v} == set(scopes[j])
                parts.append((known, full[j].select(*known, v) if whole else full[j].select(*known, v).distinct()))
        bindings = _extend(bindings, bound, v, parts)
        bound.append(v)
        ready = [f for f in pending if set(f[0]) <= set(bound)]
        pending = [f for f in pending if not set(f[0]) <= set(bound)]
        if ready:
            bindings = bindings.where(reduce(and_, (c(*(F.col(x) for x in vs)) for vs, c in ready)))
        if checkpoint_every and (level + 1) % checkpoint_every == 0 and level + 1 < len(plan.order):
            if spark.sparkContext.getCheckpointDir() is None:
                raise ValueError("checkpoint_every needs a checkpoint folder")
            bindings = bindings.checkpoint()
    result = bindings.select(*query.head)
    return result.agg(F.count("*").alias("n")) if mode == "count" else result


def _extend(bindings: DataFrame | None, bound: list[str], v: str, parts: list[tuple[tuple[str, ...], DataFrame]]) -> DataFrame:
    """Bindings with one more variable: the values common to all parts."""
    if bindings is None:
        return reduce(lambda a, b: a.join(b, v, "left_semi"), [f.select(v).distinct() if known else f for known, f in parts])
    tied = [(known, f) for known, f in parts if known]
    free = [f for known, f in parts if not known]
    if not tied:
        # A disconnected variable: the product is part of the result.
        return bindings.crossJoin(reduce(lambda a, b: a.join(b, v, "left_semi"), free))
    filters = [((), f) for f in free]
    if len(tied) == 1:
        out = bindings.join(tied[0][1], list(tied[0][0]))
        return reduce(lambda a, f: a.join(f[1], [*f[0], v], "left_semi"), filters, out)
    sized = bindings
    for k, (known, f) in enumerate(tied):
        degree = f.groupBy(*known).agg(F.count("*").alias(f"_d{k}"))
        sized = sized.join(degree, list(known))
    least = F.least(*(F.col(f"_d{k}") for k in range(len(tied))))
    turn = F.lit(len(tied) - 1)
    for k in range(len(tied) - 2, -1, -1):
        turn = F.when(F.col(f"_d{k}") == least, F.lit(k)).otherwise(turn)
    marked = sized.select(*bound, turn.alias("_turn"))
    branches = []
    for k, (known, f) in enumerate(tied):
        out = marked.where(F.col("_turn") == k).drop("_turn").join(f, list(known))
        for m, (others, g) in enumerate(tied):
            if m != k:
                out = out.join(g, [*others, v], "left_semi")
        for _, g in filters:
            out = out.join(g, [v], "left_semi")
        branches.append(out.select(*bound, v))
    return reduce(DataFrame.unionAll, branches)


def semi_reduce(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], rounds: int = 1) -> tuple[ConjunctiveQuery, dict[str, DataFrame]]:
    """Relations without rows that have no partner in some other atom (a full reducer for acyclic
    queries after enough rounds); the result set stays the same.

    A round reads the relations of the round before, so plans grow by the number
    of atoms a round: materialise between rounds if more than two are wanted.
    """
    folded, frames = fold_predicates(query, relations)
    scopes = folded.scopes
    for _ in range(rounds):
        reduced = {}
        for j, scope in enumerate(scopes):
            frame = frames[f"r{j}"]
            for k, other in enumerate(scopes):
                common = [x for x in scope if x in other]
                if j != k and common:
                    frame = frame.join(frames[f"r{k}"].select(*common).distinct(), common, "left_semi")
            reduced[f"r{j}"] = frame.select(*scope)
        frames = reduced
    return folded, frames
