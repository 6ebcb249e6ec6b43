"""The joins that the cube join is compared with, by role."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import replace
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.planner import JoinPlan, communication_shares, known_stats, quick_plan
from ..plans.rewrite import lift_intersections
from ..query import ConjunctiveQuery, check_order, fold_predicates
from .executor import cube_join
from .frontier import frontier_join


def brute_force(query: ConjunctiveQuery, rows: Mapping[str, Sequence[tuple]]) -> list[tuple]:
    """Every result by trying every combination of rows; tiny inputs only."""
    found = set()
    for chosen in product(*(rows[a.relation] for a in query.atoms)):
        bound: dict = {}
        good = True
        for atom, row in zip(query.atoms, chosen, strict=True):
            names = iter(atom.vars)
            for at, value in enumerate(row):
                if at in atom.constants:
                    good = good and value == atom.constants[at]
                elif value is None or bound.setdefault(next(names), value) != value:
                    good = False
                if not good:
                    break
            if not good:
                break
        if good:
            found.add(tuple(bound[v] for v in query.head))
    return sorted(found)


def serial_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan | None = None, mode: str = "count") -> DataFrame:
    """One cell, one task."""
    base = plan or quick_plan(query)
    return cube_join(spark, query, relations, replace(base, shares=(1,) * len(base.order), tasks=1), mode)


def top_variable_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], cells: int = 16, order: Sequence[str] | None = None, mode: str = "count", index: str = "packed", lift: str = "all") -> DataFrame:
    """Only the first variable is partitioned; relations without it go whole to every cell."""
    base = quick_plan(query, lift=lift)
    chosen = check_order(query, order) if order is not None else base.order
    lifts = tuple(lift_intersections(query.scopes, chosen)) if lift == "all" and index == "packed" else ()
    search = "vector" if index == "packed" else "adaptive"
    return cube_join(spark, query, relations, JoinPlan(chosen, (cells,) + (1,) * (len(chosen) - 1), lifts, index=index, search=search), mode)


def cube_equal_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], sizes: Sequence[int] | None = None, cells: int = 16, mode: str = "count") -> DataFrame:
    """Shares by rows sent only, every level partitioned alike (the shared-nothing ancestor)."""
    base = quick_plan(query, lift="none")
    counted = sizes or [known_stats(relations[a.relation], spark.sparkContext.applicationId).rows for a in query.atoms]
    return cube_join(spark, query, relations, replace(base, shares=communication_shares(query.scopes, counted, base.order, cells)), mode)


def _chain(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], written: bool, hint: str | None, narrow: bool) -> DataFrame:
    folded, frames = fold_predicates(query, relations)
    left = [(s, frames[f"r{j}"].distinct()) for j, s in enumerate(folded.scopes)]
    out, seen = None, set()
    while left:
        at = 0
        if not written:
            at = max(range(len(left)), key=lambda k: (len(set(left[k][0]) & seen), -k))
        scope, frame = left.pop(at)
        common = [v for v in scope if v in seen]
        if hint:
            frame = frame.hint(hint)
        if out is None:
            out = frame
        elif common:
            out = out.join(frame, common)
        else:
            out = out.crossJoin(frame)
        seen |= set(scope)
        if narrow:
            out = out.distinct()
    for vs, condition in folded.filters:
        out = out.where(condition(*(F.col(v) for v in vs)))
    return out.select(*query.head)


#: Rows that a hint may send whole through the driver to every executor.
BROADCAST_ROWS = 500_000


def binary_join(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], hint: str | None = None, mode: str = "count") -> DataFrame:
    """A tree of two-way joins; Catalyst picks their order and form (or ``hint`` does, a broadcast
    only of relations counted small)."""
    if hint == "broadcast" and any(relations[n].count() > BROADCAST_ROWS for n in {a.relation for a in query.atoms}):
        hint = None
    out = _chain(query, relations, False, hint, False)
    return out.agg(F.count("*").alias("n")) if mode == "count" else out


def written_order_join(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], mode: str = "count") -> DataFrame:
    """Two-way joins in the order of the atoms, de-duplicated after every step."""
    out = _chain(query, relations, True, None, True)
    return out.agg(F.count("*").alias("n")) if mode == "count" else out


#: Rows of all atoms beyond which a lazy hash count goes group by group.
GROUP_ROWS = 32_000_000


def lazy_hash_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], cells: int = 16, mode: str = "count") -> DataFrame:
    """Top-variable split over hash tries that grow where the join goes.

    Counts of more than ``GROUP_ROWS`` rows whose atoms fall into groups that meet in the top variable only are made
    group by group over the same tries: cells that hold all groups would need every row thousands of times."""
    if mode == "count" and not query.filters:
        from . import factorize

        plan = quick_plan(query, lift="none")
        bags = factorize.bags_joined_at(query, plan.order[0])
        counted = {n: relations[n].count() for n in {a.relation for a in query.atoms}} if len(bags) > 1 else {}
        if sum(counted.get(a.relation, 0) for a in query.atoms) > GROUP_ROWS:
            return factorize.eager_count(spark, query, relations, plan.order[0], lambda bag: replace(quick_plan(bag, cells, lift="none"), index="hash_lazy", search="adaptive"))
    return top_variable_join(spark, query, relations, cells, mode=mode, index="hash_lazy", lift="none")


def eager_hash_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan | None = None, mode: str = "count") -> DataFrame:
    """The cube join over hash tries built at once: the index ablation."""
    base = plan or quick_plan(query)
    return cube_join(spark, query, relations, replace(base, index="hash_eager", search="adaptive", lifts=()), mode)


def hinted_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], order: Sequence[str], cells: int = 16, mode: str = "count") -> DataFrame:
    """Multi-way join in the user's order over the first variable's partitions; graphs only."""
    if any(len(s) > 2 for s in query.scopes):
        raise ValueError("hinted_join takes binary relations only")
    return top_variable_join(spark, query, relations, cells, order, mode, lift="none")


def lookup_expand_join(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], mode: str = "count") -> DataFrame:
    """Each step first looks up which bindings have a partner in every remaining connected atom, and
    only then expands along one."""
    folded, frames = fold_predicates(query, relations)
    left = {j: (s, frames[f"r{j}"].distinct()) for j, s in enumerate(folded.scopes)}
    scope, out = left.pop(0)
    bound = list(scope)
    while left:
        for j, (s, f) in list(left.items()):
            known = [v for v in s if v in bound]
            if known:
                out = out.join(f.select(*known).distinct(), known, "left_semi")
                if len(known) == len(s):
                    del left[j]
        if not left:
            break
        j = max(left, key=lambda j: (len(set(left[j][0]) & set(bound)), -j))
        s, f = left.pop(j)
        known = [v for v in s if v in bound]
        out = out.join(f, known) if known else out.crossJoin(f)
        bound += [v for v in s if v not in bound]
    for vs, condition in folded.filters:
        out = out.where(condition(*(F.col(v) for v in vs)))
    out = out.select(*query.head)
    return out.agg(F.count("*").alias("n")) if mode == "count" else out


def expand3(ab: DataFrame, bc: DataFrame, ac: DataFrame) -> DataFrame:
    """The ternary triangle step over (a, b), (b, c), (a, c): wedges from the smaller side of every
    edge, then a lookup of the closing edge."""
    edges = ab.toDF("a", "b").distinct()
    right = bc.toDF("b", "c").distinct()
    closing = ac.toDF("a", "c").distinct()
    out_b = right.groupBy("b").agg(F.count("*").alias("nb"))
    out_a = closing.groupBy("a").agg(F.count("*").alias("na"))
    sized = edges.join(out_b, "b").join(out_a, "a")
    via_b = sized.where("nb <= na").select("a", "b").join(right, "b").join(closing, ["a", "c"], "left_semi")
    via_a = sized.where("nb > na").select("a", "b").join(closing, "a").join(right, ["b", "c"], "left_semi")
    return via_b.select("a", "b", "c").unionAll(via_a.select("a", "b", "c"))


def intermediate_rows(query: ConjunctiveQuery, relations: Mapping[str, DataFrame]) -> int:
    """Rows that the two-way plan makes before its last join (a measure, runs jobs)."""
    folded, frames = fold_predicates(query, relations)
    left = [(s, frames[f"r{j}"].distinct()) for j, s in enumerate(folded.scopes)]
    scope, out = left.pop(0)
    seen, total = set(scope), 0
    while left:
        at = max(range(len(left)), key=lambda k: (len(set(left[k][0]) & seen), -k))
        s, f = left.pop(at)
        common = [v for v in s if v in seen]
        out = out.join(f, common) if common else out.crossJoin(f)
        seen |= set(s)
        if left:
            total += out.count()
    return total


METHODS = {
    "cube": lambda spark, q, rels, mode: cube_join(spark, q, rels, mode=mode),
    "serial": lambda spark, q, rels, mode: serial_join(spark, q, rels, mode=mode),
    "topvar": lambda spark, q, rels, mode: top_variable_join(spark, q, rels, mode=mode),
    "cubeequal": lambda spark, q, rels, mode: cube_equal_join(spark, q, rels, mode=mode),
    "binary": lambda spark, q, rels, mode: binary_join(q, rels, mode=mode),
    "written": lambda spark, q, rels, mode: written_order_join(q, rels, mode=mode),
    "hashlazy": lambda spark, q, rels, mode: lazy_hash_join(spark, q, rels, mode=mode),
    "hasheager": lambda spark, q, rels, mode: eager_hash_join(spark, q, rels, mode=mode),
    "lookup": lambda spark, q, rels, mode: lookup_expand_join(q, rels, mode=mode),
    "hinted": lambda spark, q, rels, mode: hinted_join(spark, q, rels, quick_plan(q).order, mode=mode),
    "nolift": lambda spark, q, rels, mode: cube_join(spark, q, rels, quick_plan(q, lift="none"), mode=mode),
    "frontier": lambda spark, q, rels, mode: frontier_join(spark, q, rels, mode=mode),
}


def combined(parts: Sequence[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionAll, parts)
