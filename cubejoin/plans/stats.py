"""Statistics of relations for the cost model."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query import ConjunctiveQuery


@dataclass
class RelationStats:
    """rows: distinct rows; distinct: count per set of columns; max_degree: per (bound columns, column)
    the most values one binding has.  Columns are the atom's variables."""

    rows: int
    distinct: dict[frozenset, int] = field(default_factory=dict)
    max_degree: dict[tuple[frozenset, str], int] = field(default_factory=dict)
    exact: bool = True

    def renamed(self, names: Mapping[str, str]) -> RelationStats:
        sub = lambda s: frozenset(names[v] for v in s)
        return RelationStats(self.rows, {sub(k): n for k, n in self.distinct.items()}, {(sub(b), names[v]): n for (b, v), n in self.max_degree.items()}, self.exact)


#: Buckets in which rows are counted for the degrees' upper bounds: a fixed size.
BUCKETS = 1 << 16


def _sketched(frame: DataFrame) -> RelationStats:
    """Two passes with map-side combining, no grouping by values.

    Distinct counts come from sketches.  Rows are counted in hashed buckets per
    column set: the fullest bucket bounds the largest degree from above, so what
    is built on it stays pessimistic.
    """
    columns = frame.columns
    sets = [frozenset(c) for k in range(1, len(columns) + 1) for c in combinations(columns, k)]
    ordered = [[c for c in columns if c in s] for s in sets]
    got = frame.agg(F.count("*").alias("n"), *(F.approx_count_distinct(F.xxhash64(*s), 0.05).alias(f"d{i}") for i, s in enumerate(ordered))).first()
    distinct = {s: max(1, int(got[f"d{i}"])) for i, s in enumerate(sets)}
    distinct[frozenset(columns)] = min(distinct[frozenset(columns)], got.n) if got.n else 0
    bound = [(i, s) for i, s in enumerate(ordered) if len(s) < len(columns)]
    fullest = {}
    if bound:
        marks = F.array(*(F.struct(F.lit(i).alias("i"), F.pmod(F.xxhash64(*s), F.lit(BUCKETS)).alias("b")) for i, s in bound))
        counts = frame.select(F.explode(marks).alias("m")).groupBy("m.i", "m.b").agg(F.count("*").alias("c")).groupBy("i").agg(F.max("c").alias("c"))
        fullest = {r.i: r.c for r in counts.collect()}  # one row a column set
    degrees = {(frozenset(s), v): min(fullest.get(i, 0), distinct[frozenset({v})]) for i, s in bound for v in columns if v not in s}
    return RelationStats(distinct[frozenset(columns)], distinct, degrees, False)


def collect_relation(frame: DataFrame, exact: bool = True) -> RelationStats:
    """One relation's statistics; only a few numbers reach the driver.

    ``exact=False`` counts with sketches and bounds degrees by hashed buckets,
    for relations too large to group by every column set.
    """
    columns = frame.columns
    base = frame.distinct()
    if not exact:
        return _sketched(frame)
    base = base.persist()
    try:
        distinct, degrees = {}, {}
        rows = base.count()
        distinct[frozenset(columns)] = rows
        for k in range(1, len(columns)):
            for bound in combinations(columns, k):
                rest = [c for c in columns if c not in bound]
                grouped = base.groupBy(*bound).agg(*(F.countDistinct(v).alias(f"d_{v}") for v in rest))
                got = grouped.agg(F.count("*").alias("n"), *(F.max(f"d_{v}").alias(f"m_{v}") for v in rest)).first()
                distinct[frozenset(bound)] = got.n
                for v in rest:
                    degrees[frozenset(bound), v] = got[f"m_{v}"] or 0
        return RelationStats(rows, distinct, degrees)
    finally:
        base.unpersist()


def collect_stats(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], exact: bool = True) -> list[RelationStats]:
    """Statistics per atom; relations that several atoms share are read once."""
    cache: dict[str, RelationStats] = {}
    out = []
    for atom in query.atoms:
        if len(set(atom.vars)) != len(atom.vars) or atom.constants:
            raise ValueError("fold predicates before collecting statistics")
        frame = relations[atom.relation]
        if atom.relation not in cache:
            cache[atom.relation] = collect_relation(frame, exact)
        out.append(cache[atom.relation].renamed(dict(zip(frame.columns, atom.vars, strict=True))))
    return out


def stats_of_rows(scope: Sequence[str], rows) -> RelationStats:
    """Statistics of Python rows (tests and small studies)."""
    rows = set(rows)
    distinct, degrees = {}, {}
    for k in range(1, len(scope) + 1):
        for bound in combinations(range(len(scope)), k):
            names = frozenset(scope[i] for i in bound)
            distinct[names] = len({tuple(r[i] for i in bound) for r in rows})
            for i, v in enumerate(scope):
                if i not in bound:
                    held: dict = {}
                    for r in rows:
                        held.setdefault(tuple(r[b] for b in bound), set()).add(r[i])
                    degrees[names, v] = max((len(x) for x in held.values()), default=0)
    return RelationStats(len(rows), distinct, degrees)
