"""The sorted array index of a relation block, and hash tries for the ablation."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class PackedTrie:
    """Levels of sorted values; node p of level l has children offsets[l][p]:offsets[l][p+1] of level l+1.

    ``weights`` holds the multiplicity of each leaf (bag semantics); None for
    unique relations, whose last level therefore needs no offsets.
    """

    values: list[np.ndarray]
    offsets: list[np.ndarray]
    weights: np.ndarray | None = None

    @classmethod
    def build(cls, columns: list[np.ndarray], unique: bool = True, weights: np.ndarray | None = None) -> PackedTrie:
        """From columns of rows in lexicographic order; equal rows fold into one leaf."""
        n = len(columns[0]) if columns else 0
        changed = np.zeros(n, bool)
        if n:
            changed[0] = True
        starts, values = [], []
        for column in columns:
            if n:
                changed[1:] |= column[1:] != column[:-1]
            at = np.flatnonzero(changed)
            starts.append(at)
            values.append(column[at])
        offsets = [np.append(np.searchsorted(below, own), len(below)) for own, below in zip(starts, starts[1:], strict=False)]
        folded = None
        if not unique:
            folded = np.ones(n, np.int64) if weights is None else weights.astype(np.int64)
            folded = np.add.reduceat(folded, starts[-1]) if n else folded
        return cls(values, offsets, folded)

    def root(self) -> tuple[int, int]:
        return 0, len(self.values[0]) if self.values else 0

    def children(self, level: int, pos: int) -> tuple[int, int]:
        """Range of the children of a node, in the values of the next level."""
        return int(self.offsets[level][pos]), int(self.offsets[level][pos + 1])

    @property
    def nbytes(self) -> int:
        return sum(a.nbytes for a in (*self.values, *self.offsets)) + (self.weights.nbytes if self.weights is not None else 0)

    def parents(self, level: int) -> np.ndarray:
        """Parent position of each node of a level (zeros at the top)."""
        if level == 0:
            return np.zeros(len(self.values[0]), np.int64)
        return np.repeat(np.arange(len(self.values[level - 1])), np.diff(self.offsets[level - 1]))

    def to_rows(self) -> list[tuple]:
        """The indexed rows, rebuilt from the last level upwards."""
        if not self.values:
            return []
        at = np.arange(len(self.values[-1]))
        columns = []
        for level in range(len(self.values) - 1, -1, -1):
            columns.append(self.values[level][at])
            at = self.parents(level)[at]
        return list(zip(*(c.tolist() for c in reversed(columns)), strict=True))

    def check_sorted(self) -> None:
        """Values ascend strictly below each parent; offsets do not fall and end at the level's length."""
        for level, values in enumerate(self.values):
            parents = self.parents(level)
            same = parents[1:] == parents[:-1]
            if np.any(values[1:][same] <= values[:-1][same]):
                raise AssertionError(f"level {level} is not sorted")
        for level, offsets in enumerate(self.offsets):
            if np.any(np.diff(offsets) < 0) or offsets[-1] != len(self.values[level + 1]):
                raise AssertionError(f"offsets of level {level} are wrong")


class HashTrie:
    """Nested dictionaries; eager ones are built at once, lazy ones when a node is first visited.

    Rows stay in sorted arrays: a node that is not built yet is a range of them,
    and the last level's dictionaries hold keys only.  ``nodes_built`` counts
    dictionaries, the work that threads would contend for if a lazy trie were
    shared.
    """

    def __init__(self, rows: list[tuple] | list[np.ndarray], lazy: bool):
        """Rows as tuples, or as columns that are sorted and hold no row twice."""
        self.lazy = lazy
        self.nodes_built = 0
        if rows and not isinstance(rows[0], np.ndarray):
            rows = [np.array(c, np.int64) for c in zip(*sorted(set(rows)), strict=True)]
        self.columns = rows
        self.depth = len(rows)
        self.size = len(rows[0]) if rows else 0
        self.root: dict | None = None
        if not lazy and self.size:
            self.root = self._expand(0, self.size, 0)
            self._build_all(self.root, 1)

    def _expand(self, lo: int, hi: int, depth: int) -> dict:
        self.nodes_built += 1
        own = self.columns[depth][lo:hi]
        if depth + 1 == self.depth:
            return dict.fromkeys(own.tolist())
        starts = np.flatnonzero(own[1:] != own[:-1]) + 1
        values = own[np.append(0, starts)].tolist()
        at = (starts + lo).tolist()
        return dict(zip(values, zip([lo, *at], [*at, hi], strict=True), strict=True))

    def _build_all(self, node: dict, depth: int) -> None:
        if depth >= self.depth:
            return
        for value, (lo, hi) in node.items():
            node[value] = child = self._expand(lo, hi, depth)
            self._build_all(child, depth + 1)

    def top(self) -> dict:
        if self.root is None:
            self.root = self._expand(0, self.size, 0) if self.size else {}
        return self.root

    def child(self, node: dict, value, depth: int) -> dict | None:
        """Children of ``value`` in a node whose own values lie at ``depth``; None below the last level."""
        below = node[value]
        if isinstance(below, tuple):
            below = node[value] = self._expand(*below, depth + 1)
        return below
