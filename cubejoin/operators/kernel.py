"""The join of one cell: nested intersections, level by level over chunks of bindings.

A chunk holds many prefix bindings at once as arrays: the bound codes, the trie
node of every atom, and the rows of temporaries computed for an earlier prefix.
For the next variable every binding proposes the values of its shortest input
and looks them up in the others; comparisons are counted as they are made (one
for a filter read, the bits of the index length for a binary search).  Chunks are cut so that a level never expands
more than ``chunk_rows`` rows at a time (depth first), which bounds memory
whatever the output.  The module knows nothing of Spark.
"""

from __future__ import annotations

import tempfile
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from math import prod

import numpy as np

from .search import SEARCHES, intersect_leap
from .trie import HashTrie, PackedTrie


@dataclass(frozen=True)
class KernelPlan:
    """What a cell needs to know; plain values only, so it ships to workers.

    scopes: variables of each atom in the global order; lifts: (level, depth,
    atoms or -1 for the running temporary of that level), levels from 0 and
    depth = number of bound variables.
    """

    order: tuple[str, ...]
    scopes: tuple[tuple[str, ...], ...]
    lifts: tuple[tuple[int, int, tuple[int, ...]], ...] = ()
    index: str = "packed"
    search: str = "vector"
    bag: bool = False
    chunk_rows: int = 1 << 18


@dataclass
class CellCounters:
    """Deterministic work counts of a cell."""

    rows_in: int = 0
    rows_out: int = 0
    probes: int = 0
    comparisons: int = 0
    nodes_built: int = 0
    index_bytes: int = 0
    visited: list[int] = field(default_factory=list)
    seconds: float = 0.0


_MIX = np.uint64(0x9E3779B97F4A7C15)


class KeyFilter:
    """Hashed membership of sorted keys, eight slots a key: most values that are not there are told by one read."""

    __slots__ = ("slots", "down")

    def __init__(self, keys: np.ndarray):
        bits = max(6, int(len(keys)).bit_length() + 3)
        self.down = np.uint64(64 - bits)
        self.slots = np.zeros(1 << bits, bool)
        self.slots[self._at(keys)] = True

    def _at(self, keys: np.ndarray) -> np.ndarray:
        return (keys.astype(np.uint64) * _MIX) >> self.down

    def maybe(self, keys: np.ndarray) -> np.ndarray:
        return self.slots[self._at(keys)]


class KeyTable:
    """Hashed places of distinct keys, two slots a key at least: the level of a hash trie, searched for many keys at a time."""

    __slots__ = ("keys", "slots", "down", "mask")

    def __init__(self, keys: np.ndarray):
        bits = max(6, int(len(keys)).bit_length() + 1)
        self.keys, self.down, self.mask = keys, np.uint64(64 - bits), (1 << bits) - 1
        self.slots = np.full(1 << bits, -1, np.int32)
        left = np.arange(len(keys), dtype=np.int32)
        at = self._at(keys)
        while len(left):
            free = self.slots[at] < 0
            self.slots[at[free]] = left[free]  # one of those that want a slot gets it
            lost = self.slots[at] != left
            left, at = left[lost], (at[lost] + 1) & self.mask

    def _at(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * _MIX) >> self.down).astype(np.int64)

    def find(self, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """Places of keys, whether they exist, and the slots read."""
        at = self._at(wanted)
        found, ok, steps = np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool), len(wanted)
        place = self.slots[at]
        left = np.flatnonzero(place >= 0)
        while len(left):
            own = place[left]
            same = self.keys[own] == wanted[left]
            found[left[same]], ok[left[same]] = own[same], True
            left = left[~same]
            at[left] = (at[left] + 1) & self.mask
            place[left] = self.slots[at[left]]
            steps += len(left)
            left = left[place[left] >= 0]
        return found, ok, steps


class _Input:
    """One sorted input of a level: value ranges per binding, and how to look values up.

    Look-ups adapt to their number: few go straight to binary search, many
    (against ``filters``, kept with the index) pass a membership filter first.
    Hash tries (``tables``) look up by hash only; a level's table is made when it is first searched.
    """

    __slots__ = ("codes", "keys", "domain", "lo", "hi", "parent", "adopt", "filters", "place", "tables")

    def __init__(self, codes, keys, domain, lo, hi, parent, adopt, filters=None, place=None, tables=None):
        self.codes, self.keys, self.domain = codes, keys, domain
        self.lo, self.hi, self.parent, self.adopt = lo, hi, parent, adopt
        self.filters, self.place, self.tables = filters, place, tables

    def find(self, rows: np.ndarray, codes: np.ndarray, of: int = 0) -> tuple[np.ndarray, np.ndarray, int]:
        """Positions of codes below the parents of binding rows, whether they exist, and the comparisons made.

        ``of`` is the number of look-ups that these are a part of, which decides about the filter.
        """
        wanted = self.parent[rows] * self.domain + codes
        n = len(self.keys)
        if not n:
            return np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool), 0
        if self.tables is not None:
            if self.place not in self.tables:
                self.tables[self.place] = KeyTable(self.keys)
            return self.tables[self.place].find(wanted)
        steps = int(n).bit_length()
        if self.filters is not None and (self.place in self.filters or 4 * max(of, len(wanted)) >= n):
            if self.place not in self.filters:
                self.filters[self.place] = KeyFilter(self.keys)
            likely = np.flatnonzero(self.filters[self.place].maybe(wanted))
            found = np.searchsorted(self.keys, wanted[likely])
            found[found == n] = 0
            same = self.keys[found] == wanted[likely]
            at, ok = np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool)
            at[likely], ok[likely] = found, same
            return at, ok, len(wanted) + steps * len(likely)
        at = np.searchsorted(self.keys, wanted)
        at[at == n] = 0
        return at, self.keys[at] == wanted, steps * len(wanted)


class _NarrowInput(_Input):
    """An input without stored keys: values are searched between the borders of their parents.  Comparisons count as with
    keys, and a filter, where there is one, holds the same keys."""

    __slots__ = ()

    def find(self, rows: np.ndarray, codes: np.ndarray, of: int = 0) -> tuple[np.ndarray, np.ndarray, int]:
        n = len(self.codes)
        if not n:
            return np.zeros(len(codes), np.int64), np.zeros(len(codes), bool), 0
        steps = int(n).bit_length()
        if self.place in self.filters or 4 * max(of, len(codes)) >= n:
            if self.place not in self.filters:
                self.filters[self.place] = KeyFilter(self.keys())
            likely = np.flatnonzero(self.filters[self.place].maybe(self.parent[rows] * self.domain + codes))
            at, ok = np.zeros(len(codes), np.int64), np.zeros(len(codes), bool)
            at[likely], ok[likely] = self._search(rows[likely], codes[likely])
            return at, ok, len(codes) + steps * len(likely)
        return *self._search(rows, codes), steps * len(codes)

    def _search(self, rows: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        last = len(self.codes) - 1
        if self.place[1] == 0:
            at = np.searchsorted(self.codes, codes)
            at[at > last] = 0
            return at, self.codes[at] == codes
        at = self.lo[rows]
        end = self.hi[rows]
        left = end - at
        for _ in range(int(left.max(initial=0)).bit_length()):
            half = left >> 1
            middle = at + half
            below = self.codes[np.minimum(middle, last)] < codes
            below &= left > 0
            at = np.where(below, middle + 1, at)
            left = np.where(below, left - half - 1, half)
        ok = at < end
        at[~ok] = 0
        ok &= self.codes[at] == codes
        return at, ok


def _domain(columns: list[np.ndarray]) -> np.ndarray:
    """Values that codes stand for: all from 0 on where the columns are about as dense (codes are then the
    values themselves), else the distinct ones."""
    rows = sum(map(len, columns))
    if min(int(c.min()) for c in columns) >= 0 and (most := max(int(c.max()) for c in columns)) <= 2 * rows:
        return np.arange(most + 1)
    return np.unique(np.concatenate(columns))


def _coded(domain: np.ndarray, values: np.ndarray) -> np.ndarray:
    if len(domain) and domain[0] == 0 and domain[-1] == len(domain) - 1:
        return values
    return np.searchsorted(domain, values)


def _ascending(packed: np.ndarray) -> np.ndarray:
    """Sorted in place, repeats taken out."""
    packed.sort()
    keep = np.ones(len(packed), bool)
    np.not_equal(packed[1:], packed[:-1], out=keep[1:])
    return packed[keep]


def sort_rows(columns: list[np.ndarray], sizes: list[int], weights: np.ndarray | None, bag: bool) -> tuple[list[np.ndarray], np.ndarray | None]:
    """Rows of codes in lexicographic order; sets without repeats, as packed integers where they fit."""
    room = 1
    for n in sizes:
        room *= max(n, 1)
    if not bag and room < 1 << 62:
        packed = columns[0].astype(np.int64)
        for c, n in zip(columns[1:], sizes[1:], strict=True):
            packed = packed * n + c
        if not np.all(packed[1:] > packed[:-1]):
            packed = _ascending(packed)
            out = []
            for n in reversed(sizes[1:]):
                packed, c = np.divmod(packed, n)
                out.append(c)
            columns = [packed, *reversed(out)]
        return columns, None
    order = np.lexsort(columns[::-1])
    return [c[order] for c in columns], weights[order] if weights is not None else None


class CellJoin:
    """Joins the blocks of one cell; results come in chunks, so output of any size takes bounded memory."""

    def __init__(self, plan: KernelPlan, blocks: list[list[np.ndarray]], weights: list[np.ndarray | None], counters: CellCounters | None = None):
        self.plan = plan
        self.counters = counters or CellCounters()
        self.counters.visited = [0] * len(plan.order)
        self.domains = []
        for v in plan.order:
            self.domains.append(_domain([blocks[j][scope.index(v)] for j, scope in enumerate(plan.scopes) if v in scope]))
        self.tries, self.keys = [], []
        self.filters: dict[tuple[int, int], KeyFilter] | None = {} if plan.search == "vector" else None
        for j, scope in enumerate(plan.scopes):
            coded = [_coded(self.domains[plan.order.index(v)], c) for v, c in zip(scope, blocks[j], strict=True)]
            coded, weight = sort_rows(coded, [len(self.domains[plan.order.index(v)]) for v in scope], weights[j], plan.bag)
            trie = PackedTrie.build(coded, unique=not plan.bag, weights=weight)
            self.tries.append(trie)
            self.keys.append([trie.parents(d) * len(self.domains[plan.order.index(v)]) + trie.values[d] for d, v in enumerate(scope)])
            self.counters.rows_in += len(blocks[j][0])
            self.counters.index_bytes += trie.nbytes
        self.tables: dict[tuple[int, int], KeyTable] | None = {} if plan.search == "hashed" else None
        if plan.search == "hashed" and plan.index == "hash_eager":
            self.tables = {(j, d): KeyTable(k) for j, own in enumerate(self.keys) for d, k in enumerate(own)}

    def results(self, limit: int | None = None, tuples: bool = True) -> Iterator[tuple[list[np.ndarray], np.ndarray | None]]:
        """Chunks of result columns (in order of variables) and weights, as they are found; without
        ``tuples`` nothing is yielded and only ``total`` grows."""
        self.tuples, self.limit, self.total = tuples, limit, 0
        nodes = [np.zeros(1, np.int64) for _ in self.tries]
        weight = np.ones(1, np.int64) if self.plan.bag else None
        yield from self._extend(0, [], nodes, weight, {})

    def run(self, emit: Callable[[list[np.ndarray], np.ndarray | None], None] | None, limit: int | None = None) -> int:
        """Total (weighted) number of results; chunks go to ``emit`` if given."""
        for columns, weight in self.results(limit, emit is not None):
            emit(columns, weight)
        return self.total

    def _atom_input(self, j: int, level: int, nodes: np.ndarray) -> _Input:
        """The children of atom j's node for the variable of ``level``."""
        depth = self.plan.scopes[j].index(self.plan.order[level])
        trie = self.tries[j]
        if depth == 0:
            lo, hi = np.zeros(len(nodes), np.int64), np.full(len(nodes), len(trie.values[0]))
            parent = np.zeros(len(nodes), np.int64)
        else:
            lo, hi = trie.offsets[depth - 1][nodes], trie.offsets[depth - 1][nodes + 1]
            parent = nodes
        return _Input(trie.values[depth], self.keys[j][depth], len(self.domains[level]), lo, hi, parent, {j: None}, self.filters, (j, depth), self.tables)

    def _meet(self, inputs: list[_Input], rows: np.ndarray | None = None, counting: bool = False):
        """Per binding the common codes of all inputs: (binding row, code, position in each input), or their number only.

        What a driver proposes meets the first other input in pieces, so that no more than those that pass are held.
        """
        n = len(inputs[0].lo)
        rows = np.arange(n) if rows is None else rows
        sizes = np.stack([i.hi[rows] - i.lo[rows] for i in inputs])
        least = sizes.argmin(0)
        own_rows, own_codes, own_places = [], [], []
        number = 0
        for k, driver in enumerate(inputs):
            at = rows[least == k]
            if not len(at):
                continue
            count = driver.hi[at] - driver.lo[at]
            total = int(count.sum())
            if not total:
                continue
            self._seen(total)
            others = [m for m in range(len(inputs)) if m != k]
            found = []
            for lo, hi in self._chunks(count, MEET_ROWS):
                some, heads = count[lo:hi], np.cumsum(count[lo:hi]) - count[lo:hi]
                binding = np.repeat(at[lo:hi], some)
                place = np.arange(len(binding)) - np.repeat(heads - driver.lo[at[lo:hi]], some)
                found.append(self._passed(inputs, others[:1], binding, driver.codes[place], {k: place}, total, counting and len(others) < 2))
            if counting and len(others) < 2:
                number += sum(found)
                continue
            binding, codes = (np.concatenate([f[i] for f in found]) if len(found) > 1 else found[0][i] for i in (0, 1))
            places = {m: np.concatenate([f[2][m] for f in found]) if len(found) > 1 else found[0][2][m] for m in (k, *others[:1])}
            got = self._passed(inputs, others[1:], binding, codes, places, 0, counting)
            if counting:
                number += got
                continue
            binding, codes, places = got
            own_rows.append(binding)
            own_codes.append(codes)
            own_places.append([places[m] for m in range(len(inputs))])
        if counting:
            return number
        if not own_rows:
            empty = np.empty(0, np.int64)
            return empty, empty, [empty] * len(inputs)
        if len(own_rows) == 1:
            return own_rows[0], own_codes[0], own_places[0]
        binding = np.concatenate(own_rows)
        order = np.argsort(binding, kind="stable")
        joined = [np.concatenate([p[m] for p in own_places])[order] for m in range(len(inputs))]
        return binding[order], np.concatenate(own_codes)[order], joined

    def _passed(self, inputs: list[_Input], others: list[int], binding: np.ndarray, codes: np.ndarray, places: dict[int, np.ndarray], of: int, counting: bool):
        """Those of the proposed codes that the other inputs hold too, with their places there, or their number only."""
        for m in others:
            if not len(binding):
                places[m] = np.empty(0, np.int64)
                continue
            found, ok, steps = inputs[m].find(binding, codes, of)
            self.counters.probes += len(codes)
            self.counters.comparisons += steps
            if counting and m == others[-1]:
                return int(np.count_nonzero(ok))
            if not ok.all():
                binding, codes, found = binding[ok], codes[ok], found[ok]
                places = {i: p[ok] for i, p in places.items()}
            places[m] = found
        return len(binding) if counting else (binding, codes, places)

    def _seen(self, n: int) -> None:
        self.counters.visited[self._level] += n

    def _temporary(self, level: int, inputs: list[_Input], n: int) -> _Input:
        """The intersection of inputs per binding, kept for all later bindings of the prefix."""
        rows, codes, places = self._meet(inputs)
        if len(rows):
            order = np.lexsort((codes, rows))
            rows, codes, places = rows[order], codes[order], [p[order] for p in places]
        borders = np.searchsorted(rows, np.arange(n + 1))
        domain = len(self.domains[level])
        adopt = {}
        for source, place in zip(inputs, places, strict=True):
            for j, carried in source.adopt.items():
                adopt[j] = place if carried is None else carried[place]
        return _Input(codes, rows * domain + codes, domain, borders[:-1], borders[1:], np.arange(n), adopt)

    def _inputs(self, level: int, nodes: list[np.ndarray], temps: dict) -> list[_Input]:
        v = self.plan.order[level]
        covered: set[int] = set()
        inputs = []
        if level in temps:
            table, ref = temps[level]
            inputs.append(_Input(table.codes, table.keys, table.domain, table.lo[ref], table.hi[ref], ref, table.adopt))
            covered = set(table.adopt)
        inputs += [self._atom_input(j, level, nodes[j]) for j, s in enumerate(self.plan.scopes) if v in s and j not in covered]
        return inputs

    def _extend(self, level: int, bound: list[np.ndarray], nodes: list[np.ndarray], weight: np.ndarray | None, temps: dict) -> Iterator[tuple[list[np.ndarray], np.ndarray | None]]:
        n = len(nodes[0])
        if not n or (self.limit is not None and self.total >= self.limit):
            return
        for at, depth, members in self.plan.lifts:
            if depth == level:
                self._level = at
                sources = []
                for j in members:
                    if j < 0:
                        table, ref = temps[at]
                        sources.append(_Input(table.codes, table.keys, table.domain, table.lo[ref], table.hi[ref], ref, table.adopt))
                    else:
                        sources.append(self._atom_input(j, at, nodes[j]))
                temps = {**temps, at: (self._temporary(at, sources, n), np.arange(n))}
        inputs = self._inputs(level, nodes, temps)
        last = level == len(self.plan.order) - 1
        sizes = np.minimum.reduce([i.hi - i.lo for i in inputs])
        self._level = level
        if last and not self.tuples and len(inputs) == 1 and weight is None:
            self.total += int(sizes.sum())
            self.counters.rows_out += int(sizes.sum())
            return
        for lo, hi in self._chunks(sizes):
            rows = np.arange(lo, hi)
            self._level = level
            if last and not self.tuples and weight is None:
                found = self._meet(inputs, rows, True)
                self.total += found
                self.counters.rows_out += found
                if self.limit is not None and self.total >= self.limit:
                    return
                continue
            binding, codes, places = self._meet(inputs, rows)
            if not len(binding):
                continue
            below = [x[binding] for x in nodes]
            new_weight = weight[binding] if weight is not None else None
            for source, place in zip(inputs, places, strict=True):
                for j, carried in source.adopt.items():
                    below[j] = place if carried is None else carried[place]
            if new_weight is not None:
                v = self.plan.order[level]
                for j, scope in enumerate(self.plan.scopes):
                    if scope[-1] == v:
                        new_weight = new_weight * self.tries[j].weights[below[j]]
            if last:
                found = int(new_weight.sum()) if new_weight is not None else len(binding)
                self.total += found
                self.counters.rows_out += found
                if self.tuples:
                    columns = [*(b[binding] for b in bound), codes]
                    yield [d[c] for d, c in zip(self.domains, columns, strict=True)], new_weight
                if self.limit is not None and self.total >= self.limit:
                    return
            else:
                carried_temps = {k: (t, ref[binding]) for k, (t, ref) in temps.items() if k > level}
                yield from self._extend(level + 1, [*(b[binding] for b in bound), codes], below, new_weight, carried_temps)

    def _chunks(self, sizes: np.ndarray, most: int | None = None) -> Iterator[tuple[int, int]]:
        """Binding ranges whose expansions stay within ``chunk_rows`` (one binding at least)."""
        ends = np.cumsum(sizes)
        lo = 0
        while lo < len(sizes):
            base = ends[lo - 1] if lo else 0
            hi = int(np.searchsorted(ends, base + (most or self.plan.chunk_rows), "right"))
            hi = max(hi, lo + 1)
            yield lo, hi
            lo = hi


#: Proposed values that meet the next input at a time.
MEET_ROWS = 1 << 20
#: Rows of an index that are worked on at a time.
PART_ROWS = 1 << 20
#: Bytes from which an array of a compact index lies in a file.
MAPPED_BYTES = 32 << 20


def _array(n: int, kind) -> np.ndarray:
    """Room for n numbers; much room is a file without a name in the worker's scratch folder, whose pages the system
    may write out, instead of the worker's own memory."""
    if n * np.dtype(kind).itemsize < MAPPED_BYTES:
        return np.empty(n, kind)
    with tempfile.TemporaryFile() as file:
        return np.asarray(np.memmap(file, kind, "w+", shape=n))


def _narrow(most: int):
    return np.int32 if most < 1 << 31 else np.int64


@dataclass
class StoredAtom:
    """An atom's rows in one cell, left where they are stored: how many were routed (with repeats) and are stored, the
    least and greatest value of each column, and a reader of the columns, part by part."""

    rows: int
    stored: int
    ends: list[tuple[int, int]]
    read: Callable[[], Iterator[list[np.ndarray]]]


class CompactJoin(CellJoin):
    """The same join, step by step and count by count, for cells of any size: the index is packed part by part into
    narrow arrays without keys, which lie in files where they are large."""

    def __init__(self, plan: KernelPlan, atoms: list[StoredAtom], counters: CellCounters):
        self.plan, self.counters = plan, counters
        counters.visited = [0] * len(plan.order)
        counters.rows_in = sum(a.rows for a in atoms)
        self.filters, self.tables = {}, None
        self.domains = [self._values([(a, s.index(v)) for a, s in zip(atoms, plan.scopes, strict=True) if v in s]) for v in plan.order]
        self.tries = []
        for atom, scope in zip(atoms, plan.scopes, strict=True):
            trie = self._packed(atom, [self.domains[plan.order.index(v)] for v in scope])
            self.tries.append(trie)
            counters.index_bytes += 8 * sum(map(len, (*trie.values, *trie.offsets)))  # as plain longs

    @staticmethod
    def _values(columns: list[tuple[StoredAtom, int]]) -> np.ndarray:
        """``_domain`` of a variable's columns."""
        most = max(a.ends[k][1] for a, k in columns)
        if min(a.ends[k][0] for a, k in columns) >= 0 and most <= 2 * sum(a.rows for a, _ in columns):
            return np.arange(most + 1)
        known = np.empty(0, np.int64)
        for atom, k in columns:
            for part in atom.read():
                known = np.union1d(known, part[k])
        return known.astype(np.int64)

    @staticmethod
    def _packed(atom: StoredAtom, domains: list[np.ndarray]) -> PackedTrie:
        sizes = [len(d) for d in domains]
        if prod(max(n, 1) for n in sizes) >= 1 << 62:
            parts = list(atom.read())
            columns, _ = sort_rows([_coded(d, np.concatenate([p[k] for p in parts]).astype(np.int64)) for k, d in enumerate(domains)], sizes, None, False)
            return PackedTrie.build(columns)
        packed, n = _array(atom.stored, np.int64), 0
        for part in atom.read():
            row = _coded(domains[0], part[0]).astype(np.int64)
            for k in range(1, len(domains)):
                row = row * sizes[k] + _coded(domains[k], part[k])
            packed[n : n + len(row)] = row
            n += len(row)
        packed = packed[:n]
        packed.sort()
        packed = packed[: CompactJoin._fold(packed, None)]
        values, offsets = [], []
        for size in reversed(sizes[1:]):
            own, starts = _array(len(packed), _narrow(size)), []
            for lo in range(0, len(packed), PART_ROWS):
                part = packed[lo : lo + PART_ROWS]
                above = part // size
                own[lo : lo + PART_ROWS] = part - above * size
                packed[lo : lo + PART_ROWS] = above
            below = len(packed)
            packed = packed[: CompactJoin._fold(packed, starts)]
            at = _array(len(packed) + 1, _narrow(below))
            done = 0
            for s in starts:
                at[done : done + len(s)] = s
                done += len(s)
            at[done] = below
            values.insert(0, own)
            offsets.insert(0, at)
        top = _array(len(packed), _narrow(sizes[0]))
        top[:] = packed
        return PackedTrie([top, *values], offsets)

    @staticmethod
    def _fold(packed: np.ndarray, starts: list[np.ndarray] | None) -> int:
        """Takes repeats out of ascending numbers, in place; their new length.  ``starts`` gets where each first was."""
        length, before = 0, None
        for lo in range(0, len(packed), PART_ROWS):
            part = packed[lo : lo + PART_ROWS]
            keep = np.ones(len(part), bool)
            np.not_equal(part[1:], part[:-1], out=keep[1:])
            keep[0] = before is None or part[0] != before
            before = int(part[-1])
            if starts is not None:
                starts.append((np.flatnonzero(keep) + lo).astype(_narrow(len(packed))))
            kept = part[keep]
            packed[length : length + len(kept)] = kept
            length += len(kept)
        return length

    def _atom_input(self, j: int, level: int, nodes: np.ndarray) -> _Input:
        depth = self.plan.scopes[j].index(self.plan.order[level])
        trie, domain = self.tries[j], len(self.domains[level])
        if depth == 0:
            lo, hi = np.zeros(len(nodes), np.int64), np.full(len(nodes), len(trie.values[0]))
            parent = np.zeros(len(nodes), np.int64)
        else:
            lo, hi = trie.offsets[depth - 1][nodes].astype(np.int64), trie.offsets[depth - 1][nodes + 1].astype(np.int64)
            parent = nodes
        return _NarrowInput(trie.values[depth], lambda: trie.parents(depth) * domain + trie.values[depth], domain, lo, hi, parent, {j: None}, self.filters, (j, depth))


class ScalarJoin:
    """Reference loop nest over packed or hash tries, one binding at a time, counting comparisons."""

    def __init__(self, plan: KernelPlan, blocks: list[list[np.ndarray]], counters: CellCounters | None = None):
        self.plan = plan
        self.counters = counters or CellCounters()
        self.counters.visited = [0] * len(plan.order)
        self.packed = plan.index == "packed"
        self.tries: list = []
        for block in blocks:
            self.counters.rows_in += len(block[0])
            if self.packed:
                order = np.lexsort(block[::-1])
                trie = PackedTrie.build([c[order] for c in block])
                self.tries.append(PackedTrie([v.tolist() for v in trie.values], [o.tolist() for o in trie.offsets]))
                self.counters.index_bytes += trie.nbytes
            else:
                order = np.lexsort(block[::-1])
                held = [c[order] for c in block]
                fresh = np.ones(len(order), bool)
                fresh[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in held])
                self.tries.append(HashTrie([c[fresh] for c in held], plan.index == "hash_lazy"))

    def run(self, emit=None, limit: int | None = None) -> int:
        self.emit, self.limit, self.out = emit, limit, []
        start = [(0, len(t.values[0])) if self.packed else t.top() for t in self.tries]
        n = self._level(0, (), start)
        if emit is not None and self.out:
            emit([np.array(c, np.int64) for c in zip(*self.out, strict=True)], None)
        if not self.packed:
            self.counters.nodes_built = sum(t.nodes_built for t in self.tries)
        self.counters.rows_out = n
        return n

    def _level(self, level: int, bound: tuple, at: list) -> int:
        if level == len(self.plan.order):
            if self.emit is not None:
                self.out.append(bound)
            return 1
        v = self.plan.order[level]
        inputs = [j for j, s in enumerate(self.plan.scopes) if v in s]
        if level + 1 == len(self.plan.order) and not self.packed and self.emit is None and self.limit is None:
            return self._matches(level, sorted((at[j] for j in inputs), key=len))
        total = 0
        for value, below in self._common(v, inputs, at):
            self.counters.visited[level] += 1
            child = list(at)
            for j, b in below.items():
                child[j] = b
            total += self._level(level + 1, (*bound, value), child)
            if self.limit is not None and total >= self.limit:
                break
        return total

    def _matches(self, level: int, nodes: list[dict]) -> int:
        """Common values of the last variable, counted without a step per value."""
        least, *others = nodes
        self.counters.probes += len(least) * len(others)
        if len(others) == 1:
            found = sum(map(others[0].__contains__, least))
        else:
            common = least.keys()
            for o in others:
                common = common & o.keys()
            found = len(common)
        self.counters.visited[level] += found
        return found

    def _common(self, v: str, inputs: list[int], at: list):
        if not self.packed:
            least = min(inputs, key=lambda j: len(at[j]))
            for value in at[least]:
                self.counters.probes += len(inputs) - 1
                if all(value in at[j] for j in inputs):
                    depths = {j: self.plan.scopes[j].index(v) for j in inputs}
                    yield value, {j: self.tries[j].child(at[j], value, depths[j]) for j in inputs}
            return
        ranges = []
        for j in inputs:
            depth = self.plan.scopes[j].index(v)
            ranges.append((self.tries[j].values[depth], *at[j]))
        search = self.plan.search if self.plan.search in SEARCHES or self.plan.search == "adaptive" else "adaptive"
        found, seen = intersect_leap(ranges, search)
        self.counters.comparisons += seen
        for value, places in found:
            below = {}
            for j, p in zip(inputs, places, strict=True):
                depth = self.plan.scopes[j].index(v)
                if depth + 1 < len(self.plan.scopes[j]):
                    below[j] = (self.tries[j].offsets[depth][p], self.tries[j].offsets[depth][p + 1])
            yield value, below


def join_cell(plan: KernelPlan, blocks: list[list[np.ndarray]], weights: list[np.ndarray | None], emit=None, limit: int | None = None) -> tuple[int, CellCounters]:
    """Result count and counters of one cell; an empty block ends it at once."""
    counters = CellCounters()
    if any(len(b[0]) == 0 for b in blocks):
        counters.rows_in = sum(len(b[0]) for b in blocks)
        counters.visited = [0] * len(plan.order)
        return 0, counters
    began = time.perf_counter()
    if plan.search == "hashed" or (plan.index == "packed" and plan.search in ("vector", "unfiltered")):
        total = CellJoin(plan, blocks, weights, counters).run(emit, limit)
    else:
        if plan.bag:
            raise ValueError("bag semantics need the packed index and the vector search")
        total = ScalarJoin(plan, blocks, counters).run(emit, limit)
    counters.seconds = time.perf_counter() - began
    return total, counters


def join_stored(plan: KernelPlan, atoms: list[StoredAtom]) -> CellCounters:
    """Counters of one cell whose rows are stored, as ``join_cell`` finds them."""
    counters = CellCounters()
    if any(a.rows == 0 for a in atoms):
        counters.rows_in = sum(a.rows for a in atoms)
        counters.visited = [0] * len(plan.order)
        return counters
    began = time.perf_counter()
    CompactJoin(plan, atoms, counters).run(None)
    counters.seconds = time.perf_counter() - began
    return counters


def generic_join(rows: list[list[tuple]], order: tuple[str, ...], scopes: list[tuple[str, ...]], mode: str = "tuples", **options):
    """Serial worst-case optimal join of Python rows: sorted result tuples, or their number.

    ``scopes`` names the variables of each row list; columns are brought to the
    global order here.
    """
    ordered = [tuple(sorted(s, key=order.index)) for s in scopes]
    blocks = []
    for data, scope, target in zip(rows, scopes, ordered, strict=True):
        picked = sorted({tuple(r[scope.index(v)] for v in target) for r in data})
        blocks.append([np.array([r[k] for r in picked], np.int64) for k in range(len(target))])
    plan = KernelPlan(tuple(order), tuple(ordered), **options)
    found: list[tuple] = []
    emit = None if mode == "count" else (lambda columns, _: found.extend(zip(*(c.tolist() for c in columns), strict=True)))
    total, _ = join_cell(plan, blocks, [None] * len(blocks), emit)
    return total if mode == "count" else sorted(found)
