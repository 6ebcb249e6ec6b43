import bisect

import numpy as np
import pytest
from hypothesis import given
from hypothesis import strategies as st

from cubejoin.operators.search import SEARCHES, choose_search, intersect_leap, intersect_smallest
from cubejoin.operators.trie import HashTrie, PackedTrie

ROWS = [(1, 2, 3), (1, 2, 4), (1, 5, 1), (2, 2, 2), (3, 1, 1), (3, 1, 2), (3, 4, 9)]


def columns(rows):
    return [np.array(c) for c in zip(*rows, strict=True)]


def test_levels_and_offsets():
    trie = PackedTrie.build(columns(ROWS))
    assert [v.tolist() for v in trie.values] == [[1, 2, 3], [2, 5, 2, 1, 4], [3, 4, 1, 2, 1, 2, 9]]
    assert [o.tolist() for o in trie.offsets] == [[0, 2, 3, 5], [0, 2, 3, 4, 6, 7]]
    assert trie.children(0, 2) == (3, 5)
    assert trie.weights is None
    assert trie.to_rows() == ROWS
    trie.check_sorted()
    assert trie.nbytes <= 2 * 8 * 3 * len(ROWS)


def test_repeated_rows_fold_with_weights():
    trie = PackedTrie.build(columns(sorted(ROWS + ROWS[:2])), unique=False)
    assert trie.to_rows() == ROWS
    assert trie.weights.tolist() == [2, 2, 1, 1, 1, 1, 1]


def test_empty_relation():
    trie = PackedTrie.build([np.empty(0, np.int64)] * 2)
    assert trie.to_rows() == [] and trie.root() == (0, 0)


@given(st.lists(st.tuples(st.integers(0, 5), st.integers(0, 5), st.integers(0, 5)), min_size=1, max_size=60))
def test_rows_come_back(rows):
    rows = sorted(rows)
    trie = PackedTrie.build(columns(rows))
    trie.check_sorted()
    assert trie.to_rows() == sorted(set(rows))


@pytest.mark.parametrize("name", sorted(SEARCHES))
@given(data=st.lists(st.integers(0, 300), max_size=200), x=st.integers(-1, 301), lo=st.integers(0, 50))
def test_searches_match_bisect(name, data, x, lo):
    data = sorted(data)
    lo = min(lo, len(data))
    assert SEARCHES[name](data, lo, len(data), x)[0] == bisect.bisect_left(data, x, lo)


@pytest.mark.parametrize("search", [*SEARCHES, "adaptive"])
@given(sets=st.lists(st.sets(st.integers(0, 80)), min_size=1, max_size=4))
def test_intersections(search, sets):
    ranges = [(sorted(s), 0, len(s)) for s in sets]
    common = sorted(set.intersection(*sets))
    got, _ = intersect_leap(ranges, search)
    assert [v for v, _ in got] == common
    assert all(r[0][p] == v for v, places in got for r, p in zip(ranges, places, strict=True))
    if search != "adaptive":
        assert [v for v, _ in intersect_smallest(ranges, search)[0]] == common


def test_meeting_ranges():
    values = [4, 5, 0, 2, 4]
    assert intersect_leap([(values, 0, 2), (values, 2, 5)])[0] == [(4, (0, 4))]


def test_adaptive_choice():
    assert choose_search(2, [10, 10]).__name__ == "search_linear"
    assert choose_search(2, [10, 900]).__name__ == "search_stride"
    assert choose_search(2, [10, 90_000]).__name__ == "search_gallop"


def test_lazy_trie_builds_less():
    eager, lazy = HashTrie(ROWS, False), HashTrie(ROWS, True)
    assert lazy.nodes_built == 0
    top = lazy.top()
    lazy.child(top, 3, 0)
    assert 0 < lazy.nodes_built < eager.nodes_built


def test_hash_tries_keep_no_rows_below_the_last_level():
    rows = sorted(set(ROWS))
    columns = [np.array(c, np.int64) for c in zip(*rows, strict=True)]
    for lazy in (False, True):
        trie = HashTrie(columns, lazy)
        found = []
        todo = [((), trie.top(), 0)]
        while todo:
            prefix, node, depth = todo.pop()
            for value in list(node):
                below = trie.child(node, value, depth)
                if below is None:
                    found.append((*prefix, value))
                else:
                    todo.append(((*prefix, value), below, depth + 1))
        assert sorted(found) == rows
    assert HashTrie([], True).top() == {}
