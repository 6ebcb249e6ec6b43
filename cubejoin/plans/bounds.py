"""Output bounds: fractional edge covers and degree chains."""

from __future__ import annotations

from collections.abc import Sequence
from functools import lru_cache
from itertools import combinations
from math import exp, log

import numpy as np


def edge_cover(scopes: Sequence[Sequence[str]], sizes: Sequence[float]) -> tuple[float, list[float]]:
    """The least product of sizes to a fractional cover of all variables, and the cover.

    The linear program is tiny (one unknown per atom), so its vertices are
    enumerated.  Empty relations make the bound zero.
    """
    variables = sorted({v for s in scopes for v in s})
    m = len(scopes)
    if any(n <= 0 for n in sizes):
        return 0.0, [0.0] * m
    costs = np.array([log(n) for n in sizes])
    rows = [[1.0 if v in s else 0.0 for s in scopes] for v in variables]
    rhs = [1.0] * len(variables)
    for j in range(m):
        rows.append([1.0 if k == j else 0.0 for k in range(m)])
        rhs.append(0.0)
    a, b = np.array(rows), np.array(rhs)
    best, cover = np.inf, None
    for chosen in combinations(range(len(rows)), m):
        picked = a[list(chosen)]
        if abs(np.linalg.det(picked)) < 1e-9:
            continue
        x = np.linalg.solve(picked, b[list(chosen)])
        if np.all(a @ x >= b - 1e-9) and costs @ x < best - 1e-12:
            best, cover = float(costs @ x), x
    if cover is None:
        return 1.0, [0.0] * m
    return exp(best), [float(c) for c in cover]


def agm_bound(scopes: Sequence[Sequence[str]], sizes: Sequence[float]) -> float:
    """Largest possible output of a query over relations of these sizes."""
    return _bound(tuple(map(tuple, scopes)), tuple(sizes))


@lru_cache(maxsize=4096)
def _bound(scopes: tuple, sizes: tuple) -> float:
    return edge_cover(scopes, sizes)[0]
