"""Connected components by randomised contraction of an edge table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .workspace import Workspace


def connected_components(work: Workspace, edges: DataFrame, label: str) -> DataFrame:
    """Component of every vertex that has an edge.

    ``edges`` holds longs ``a``, ``b`` (self loops and repeats allowed); the
    result holds ``node`` and ``root``, equal for vertices of one component
    (which root is unspecified).

    Each round every vertex moves to the neighbour (or itself) of smallest
    pseudo-random priority and edges are rewritten to the new names, so the
    number of vertices that still have edges shrinks geometrically whatever the
    shape of the graph; sorted chains are no worst case.  Priorities hold for two
    rounds: a star, whose leaves would halve a round under fresh ones, is one
    vertex after two.  Rounds run until no edge is left; the moves, fewer each
    round, are then composed from the last one back.  All steps are joins and
    map-side-combined aggregates over materialised tables; nothing is collected
    but one emptiness flag a round.
    """
    current = work.table(f"{label}_edges0", edges.select("a", "b").where("a <> b").distinct())
    steps: list[DataFrame] = []
    while not current.isEmpty():
        turn = len(steps)
        both = current.union(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        rank = lambda c: F.xxhash64(F.col(c), F.lit(turn // 2))
        best = both.groupBy("a").agg(F.min(F.struct(rank("b").alias("p"), F.col("b").alias("to"))).alias("m"))
        step = work.table(
            f"{label}_step{turn}",
            best.select(F.col("a").alias("node"), F.when(F.col("m.p") < rank("a"), F.col("m.to")).otherwise(F.col("a")).alias("root")),
        )
        left = step.select(F.col("node").alias("a"), F.col("root").alias("ra"))
        right = step.select(F.col("node").alias("b"), F.col("root").alias("rb"))
        moved = current.join(left, "a").join(right, "b").where("ra <> rb")
        current = work.table(
            f"{label}_edges{turn + 1}",
            moved.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(),
        )
        work.drop(f"{label}_edges{turn}")
        steps.append(step)
    if not steps:
        return current.select(F.col("a").alias("node"), F.col("b").alias("root"))
    moves = steps[-1]
    for step in reversed(steps[:-1]):
        later = moves.select(F.col("node").alias("root"), F.col("root").alias("next"))
        moves = step.join(later, "root", "left").select("node", F.coalesce("next", "root").alias("root"))
    moves = work.table(f"{label}_moves", moves)
    work.drop(*(f"{label}_step{k}" for k in range(len(steps))))
    return moves
