"""Searches for the first element >= a target in a sorted range, with comparison counts.

These scalar forms are the reference of the vectorised kernel and the subject of
the search study; each returns (position, comparisons).
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

Search = Callable[[Sequence[int], int, int, int], tuple[int, int]]


def search_linear(a: Sequence[int], lo: int, hi: int, x: int) -> tuple[int, int]:
    seen = 0
    while lo < hi:
        seen += 1
        if a[lo] >= x:
            break
        lo += 1
    return lo, seen


def search_binary(a: Sequence[int], lo: int, hi: int, x: int) -> tuple[int, int]:
    seen = 0
    while lo < hi:
        mid = (lo + hi) // 2
        seen += 1
        if a[mid] < x:
            lo = mid + 1
        else:
            hi = mid
    return lo, seen


def search_gallop(a: Sequence[int], lo: int, hi: int, x: int) -> tuple[int, int]:
    """Doubling steps from the cursor, then binary search in the last step."""
    seen, step, below = 0, 1, lo
    at = lo
    while at < hi:
        seen += 1
        if a[at] >= x:
            break
        below = at + 1
        at = lo + step
        step *= 2
    found, more = search_binary(a, below, min(at, hi), x)
    return found, seen + more


def search_stride(a: Sequence[int], lo: int, hi: int, x: int, stride: int = 64, scan: int = 16) -> tuple[int, int]:
    """Fixed strides to the segment of the target, which is searched with a quarter of the stride or scanned."""
    seen = 0
    while lo + stride <= hi:
        seen += 1
        if a[lo + stride - 1] >= x:
            hi = lo + stride
            break
        lo += stride
    if stride // 4 > scan:
        found, more = search_stride(a, lo, hi, x, stride // 4, scan)
    else:
        found, more = search_linear(a, lo, hi, x)
    return found, seen + more


def choose_search(n_inputs: int, sizes: Sequence[int], linear_max: int = 32, stride_max: int = 1024) -> Search:
    """By the width of the intersection and the length of its ranges: with many inputs the cursor
    moves little at a time, so shorter-sighted searches win for longer ranges."""
    gap = max(sizes) / max(1, min(sizes)) if sizes else 1
    if max(sizes, default=0) <= linear_max or gap <= 2 * (n_inputs - 1):
        return search_linear
    if max(sizes) <= stride_max:
        return search_stride
    return search_gallop


SEARCHES: dict[str, Search] = {"linear": search_linear, "stride": search_stride, "gallop": search_gallop, "binary": search_binary}


def intersect_leap(ranges: Sequence[tuple[Sequence[int], int, int]], search: str = "adaptive") -> tuple[list[tuple[int, tuple[int, ...]]], int]:
    """Common values of sorted ranges (array, lo, hi) with their position in each, and comparisons.

    The cursor on the smallest value leaps to the largest one seen, round-robin,
    until one range is exhausted.
    """
    if not ranges or any(lo >= hi for _, lo, hi in ranges):
        return [], 0
    if len(ranges) == 1:
        a, lo, hi = ranges[0]
        return [(a[p], (p,)) for p in range(lo, hi)], 0
    seek = choose_search(len(ranges), [hi - lo for _, lo, hi in ranges]) if search == "adaptive" else SEARCHES[search]
    cursors = [lo for _, lo, _ in ranges]
    out, seen, n = [], 0, len(ranges)
    largest = max(a[lo] for a, lo, _ in ranges)
    agreeing, at = 0, 0
    while True:
        a, _, hi = ranges[at]
        found, more = seek(a, cursors[at], hi, largest)
        seen += more
        cursors[at] = found
        if found >= hi:
            return out, seen
        agreeing = agreeing + 1 if a[found] == largest else 1
        largest = a[found]
        if agreeing == n:
            out.append((largest, tuple(cursors)))
            cursors[at] += 1
            if cursors[at] >= hi:
                return out, seen
            largest, agreeing = a[cursors[at]], 1
        at = (at + 1) % n


def intersect_smallest(ranges: Sequence[tuple[Sequence[int], int, int]], search: str = "binary") -> tuple[list[tuple[int, tuple[int, ...]]], int]:
    """Common values found by looking every value of the smallest range up in the others."""
    if not ranges or any(lo >= hi for _, lo, hi in ranges):
        return [], 0
    seek = SEARCHES[search]
    least = min(range(len(ranges)), key=lambda j: ranges[j][2] - ranges[j][1])
    a, lo, hi = ranges[least]
    cursors = [r[1] for r in ranges]
    out, seen = [], 0
    for at in range(lo, hi):
        x, cursors[least] = a[at], at
        for j, (b, _, end) in enumerate(ranges):
            if j == least:
                continue
            cursors[j], more = seek(b, cursors[j], end, x)
            seen += more
            if cursors[j] >= end or b[cursors[j]] != x:
                break
        else:
            out.append((x, tuple(cursors)))
    return out, seen
