"""Counting without listing: decomposition, elimination and eager aggregation."""

from __future__ import annotations

from collections.abc import Callable, Mapping, Sequence
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.planner import JoinPlan, fitted, quick_plan, starting_cells
from ..query import ConjunctiveQuery
from .executor import _blocks, _cells, bind_relations, count_by, cube_join
from .kernel import KernelPlan
from .shuffle import exchange, route_rows


#: Rows of a relation whose wedges may be shuffled.
LOOKUP_ROWS = 16_000_000


def bags_joined_at(query: ConjunctiveQuery, pivot: str) -> list[list[int]]:
    """Groups of atoms that meet in the pivot variable only."""
    scopes = query.scopes
    left, groups = set(range(len(scopes))), []
    while left:
        todo, group = [min(left)], set()
        while todo:
            j = todo.pop()
            if j in group:
                continue
            group.add(j)
            todo += [k for k in left if k not in group and (set(scopes[j]) & set(scopes[k])) - {pivot}]
        groups.append(sorted(group))
        left -= group
    return groups


def _bag(query: ConjunctiveQuery, atoms: Sequence[int]) -> ConjunctiveQuery:
    held = [query.atoms[j] for j in atoms]
    head = [v for v in query.head if any(v in a.vars for a in held)]
    return ConjunctiveQuery(tuple(head), tuple(held))


def decomposed_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], pivot: str, mode: str = "count") -> DataFrame:
    """Tree decomposition at one variable: each bag by a cube join, bags joined on the pivot."""
    out = None
    for atoms in bags_joined_at(query, pivot):
        bag = cube_join(spark, _bag(query, atoms), relations)
        out = bag if out is None else out.join(bag, pivot)
    out = out.select(*query.head)
    return out.agg(F.count("*").alias("n")) if mode == "count" else out


def eliminate_variables(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], pivot: str) -> DataFrame:
    """Count by bags listed and reduced to (pivot, count) by eliminating their own variables."""
    return _product_of_counts([cube_join(spark, _bag(query, atoms), relations).groupBy(pivot).agg(F.count("*").alias("c")) for atoms in bags_joined_at(query, pivot)], pivot)


def eager_count(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], pivot: str, planned: Callable[[ConjunctiveQuery], JoinPlan] | None = None) -> DataFrame:
    """Count with aggregation pushed below the bags' join, into the cells: each bag becomes (pivot,
    count) where its results are found, and nothing of a bag is listed or shuffled.  ``planned`` gives a bag's plan, if not the planner."""
    bags = [_bag(query, atoms) for atoms in bags_joined_at(query, pivot)]
    return _product_of_counts([count_by(spark, b, relations, pivot, planned(b) if planned else None) for b in bags], pivot)


def two_way_variant(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], pivot: str, lookup: bool = False, eager: bool = False) -> DataFrame:
    """Count by the expand engine with a tree decomposition: bags by two-way joins, or by looking up
    before expanding, joined on the pivot or reduced to counts first.

    Over more than ``LOOKUP_ROWS`` rows the steps of an eager look-up run in the cells of a block store: a binding
    looks for partners in the atoms that it meets and only then expands, and no wedge is shuffled."""
    from .baselines import binary_join, lookup_expand_join

    if lookup and eager and not query.filters:
        counted = {n: relations[n].count() for n in {a.relation for a in query.atoms}}
        if max(counted.values()) > LOOKUP_ROWS:
            spark = next(iter(relations.values())).sparkSession
            return eager_count(spark, query, relations, pivot, lambda b: fitted(quick_plan(b, lift="none"), b.scopes, [counted[a.relation] for a in b.atoms]))
    one = lookup_expand_join if lookup else binary_join
    bags = [one(_bag(query, atoms), relations, mode="tuples") for atoms in bags_joined_at(query, pivot)]
    if eager:
        return _product_of_counts([b.groupBy(pivot).agg(F.count("*").alias("c")) for b in bags], pivot)
    out = bags[0]
    for b in bags[1:]:
        out = out.join(b, pivot)
    return out.agg(F.count("*").alias("n"))


def _product_of_counts(counts: list[DataFrame], pivot: str) -> DataFrame:
    """Sum over pivot values of the product of the bags' counts, in decimals until the end."""
    out, product = None, F.lit(1).cast("decimal(38,0)")
    for k, c in enumerate(counts):
        c = c.withColumnRenamed("c", f"c{k}")
        out = c if out is None else out.join(c, pivot)
        product = (product * F.col(f"c{k}").cast("decimal(19,0)")).cast("decimal(38,0)")
    return out.agg(F.coalesce(F.sum(product), F.lit(0)).cast("long").alias("n"))


def degree_product_count(edges: DataFrame, condition: Column | None = None) -> DataFrame:
    """Paths of two edges by degrees alone: sum over vertices of in-degree times out-degree."""
    edges = edges.toDF("src", "dst").distinct()
    ins = edges.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("i"))
    outs = edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("o"))
    joined = ins.join(outs, "v")
    if condition is not None:
        joined = joined.where(condition)
    return joined.agg(F.coalesce(F.sum(F.col("i") * F.col("o")), F.lit(0)).cast("long").alias("n"))


def orient_by_degree(edges: DataFrame) -> DataFrame:
    """An undirected graph's edges from lower to higher (degree, id): hubs keep few outgoing edges and
    each triangle appears once."""
    both = edges.toDF("src", "dst")
    both = both.union(both.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).where("src <> dst").distinct()
    degree = both.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("d"))
    a, b = degree.toDF("src", "ds"), degree.toDF("dst", "dd")
    return both.join(a, "src").join(b, "dst").where(F.struct("ds", "src") < F.struct("dd", "dst")).select("src", "dst")


def twin_paths(query: ConjunctiveQuery) -> tuple[str, list[str], str] | None:
    """(first end, middles, last end) of a query that is several copies of one two-step path between the
    same ends, and nothing else; None for other queries."""
    if query.filters or any(a.constants or len(a.vars) != 2 or len(set(a.vars)) != 2 for a in query.atoms) or len(query.atoms) < 4:
        return None
    starts, stops = {a.vars[0] for a in query.atoms} - {a.vars[1] for a in query.atoms}, {a.vars[1] for a in query.atoms} - {a.vars[0] for a in query.atoms}
    if len(starts) != 1 or len(stops) != 1:
        return None
    (x,), (u,) = starts, stops
    middles = [v for v in query.head if v not in (x, u)]
    steps = {a.vars: a.relation for a in query.atoms}
    if set(steps) != {p for m in middles for p in ((x, m), (m, u))} or len(steps) != len(query.atoms) or set(query.head) != {v for a in query.atoms for v in a.vars}:
        return None
    if len({(steps[x, m], steps[m, u]) for m in middles}) != 1:
        return None
    return x, middles, u


def powers_of_paths(x: np.ndarray, m: np.ndarray, n: np.ndarray, u: np.ndarray, copies: int, chunk: int = 1 << 21) -> int:
    """Sum over (x, u) of the ``copies``-th power of the number of paths x, m, u over the sets (x, m) and (n, u)."""
    xs, x = np.unique(x, return_inverse=True)
    us, u = np.unique(u, return_inverse=True)
    ms, both = np.unique(np.concatenate([m, n]), return_inverse=True)
    left = np.unique(x * len(ms) + both[: len(m)])
    right = np.unique(both[len(m) :] * len(us) + u)
    x, m = np.divmod(left, len(ms))
    n, u = np.divmod(right, len(us))
    first = np.searchsorted(n, np.arange(len(ms) + 1))
    degree = first[m + 1] - first[m]
    ends = np.concatenate(([0], np.cumsum(degree)))
    edges = np.searchsorted(x, np.arange(len(xs) + 1))  # of each x
    total, lo = 0, 0
    while lo < len(xs):
        hi = max(lo + 1, int(np.searchsorted(ends[edges], ends[edges[lo]] + chunk, "right")) - 1)
        counts = np.zeros(len(us) if hi == lo + 1 else 0, np.int64)
        at, stop = int(edges[lo]), int(edges[hi])
        while at < stop:  # one turn, unless a single x has more paths than a chunk
            to = min(stop, max(at + 1, int(np.searchsorted(ends, ends[at] + chunk, "right")) - 1))
            size = int(ends[to] - ends[at])
            place = np.arange(size) - np.repeat(ends[at:to] - ends[at] - first[m[at:to]], degree[at:to])
            if hi == lo + 1:
                counts += np.bincount(u[place], minlength=len(us))
            else:
                keys = np.repeat(x[at:to] - lo, degree[at:to]) * len(us) + u[place]
                room = (hi - lo) * len(us)
                counts = np.bincount(keys) if room <= 8 * size else np.unique(keys, return_counts=True)[1]
            at = to
        values, often = np.unique(counts, return_counts=True)
        total += sum(int(v) ** copies * int(k) for v, k in zip(values, often, strict=True) if v)
        lo = hi
    return total


def twin_path_count(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], cell_rows: int = 2_000_000) -> DataFrame:
    """Number of results of a ``twin_paths`` query: cells hold all paths between their ends, count them for
    each pair of ends and add the powers, so that no combination of middles is ever listed."""
    x, middles, u = twin_paths(query)
    m = middles[0]
    path = ConjunctiveQuery((x, m, u), tuple(a for a in query.atoms if m in a.vars))
    folded, frames, _, _ = bind_relations(path, relations)
    rows = max(f.count() for f in frames)
    cells = starting_cells(rows, spark.sparkContext.defaultParallelism)
    while 2 * rows > cell_rows * cells**0.5:
        cells *= 2
    bits = cells.bit_length() - 1
    shares = (1 << (bits + 1) // 2, 1, 1 << bits // 2)
    order, scopes = (x, m, u), [a.vars for a in folded.atoms]
    kernel = KernelPlan(order, tuple(tuple(sorted(s, key=order.index)) for s in scopes))
    swap = kernel.scopes[0][0] != x
    copies = len(middles)

    def run(batches):
        for _, table in _cells(batches):
            blocks = _blocks(table, kernel)[0]
            del table
            one, two = reversed(blocks) if swap else blocks
            n = powers_of_paths(*one, *two, copies) if len(one[0]) and len(two[0]) else 0
            yield pa.RecordBatch.from_arrays([pa.array([Decimal(n)], pa.decimal128(38, 0))], names=["n"])

    routed = exchange(route_rows([f.dropna() for f in frames], scopes, order, shares), cells)
    return routed.mapInArrow(run, "n decimal(38,0)").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
