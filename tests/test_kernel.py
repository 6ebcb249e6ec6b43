import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cubejoin.operators.baselines import brute_force
from cubejoin.operators.kernel import CellCounters, CellJoin, KernelPlan, generic_join, join_cell
from cubejoin.plans.planner import enumerate_orders
from cubejoin.plans.rewrite import lift_intersections
from cubejoin.query import parse_rule
from cubejoin.workloads import CT_RULE, LW_RULE, PATTERNS

EDGES = st.lists(st.tuples(st.integers(0, 6), st.integers(0, 6)), max_size=25)


def run(rule, relations, order, **options):
    query = parse_rule(rule)
    rows = [relations[a.relation] for a in query.atoms]
    return [tuple(r[order.index(v)] for v in query.head) for r in generic_join(rows, tuple(order), query.scopes, **options)]


@pytest.mark.parametrize("name", ["q1d", "q1c", "q2", "q4"])
@settings(max_examples=15, deadline=None)
@given(edges=EDGES)
def test_patterns_match_brute_force(name, edges):
    edges = sorted(set(edges))[:12]
    query = parse_rule(PATTERNS[name])
    assert sorted(run(PATTERNS[name], {"e": edges}, query.head)) == brute_force(query, {"e": edges})


def lifts_of(query, order):
    scopes = [tuple(sorted(s, key=order.index)) for s in query.scopes]
    return tuple((x.level, x.at_depth, x.inputs) for x in lift_intersections(scopes, order))


def test_every_order_lift_and_search_agree_on_the_clique():
    rng = random.Random(1)
    edges = sorted({(rng.randrange(12), rng.randrange(12)) for _ in range(70)})
    query = parse_rule(PATTERNS["q6"])
    expected = None
    for order in enumerate_orders(query.head):
        for options in ({}, {"lifts": lifts_of(query, order)}, {"lifts": lifts_of(query, order), "chunk_rows": 3}, {"search": "adaptive"}, {"index": "hash_lazy"}, {"index": "hash_eager"}):
            got = sorted(run(PATTERNS["q6"], {"e": edges}, order, **options))
            expected = got if expected is None else expected
            assert got == expected, (order, options)
    assert expected


@pytest.mark.parametrize("rule,names,width", [(LW_RULE, ("lw1", "lw2", "lw3", "lw4"), 3), (CT_RULE, ("ct5", "ct6", "ct7"), 3)])
def test_hyperedges(rule, names, width):
    rng = random.Random(2)
    relations = {n: sorted({tuple(rng.randrange(4) for _ in range(width)) for _ in range(22)}) for n in names}
    query = parse_rule(rule)
    assert sorted(run(rule, relations, query.head)) == sorted(set(run(rule, relations, tuple(reversed(query.head)))))
    assert lifts_of(query, query.head) == ()
    small = {n: r[:7] for n, r in relations.items()}
    assert sorted(run(rule, small, query.head)) == brute_force(query, small)


def test_count_equals_tuples_and_limit():
    edges = sorted({(a, b) for a in range(8) for b in range(8) if a != b})
    query = parse_rule(PATTERNS["q1d"])
    rows = [edges] * 3
    assert generic_join(rows, query.head, query.scopes, mode="count") == 8 * 7 * 6
    columns = [np.array(c) for c in zip(*edges, strict=True)]
    plan = KernelPlan(query.head, (("x", "y"), ("y", "z"), ("x", "z")), chunk_rows=4)
    total, _ = join_cell(plan, [columns] * 3, [None] * 3, limit=5)
    assert 5 <= total < 336


def test_bag_weights_multiply():
    plan = KernelPlan(("x", "y"), (("x", "y"), ("y",)), bag=True)
    blocks = [[np.array([1, 1, 2]), np.array([5, 5, 5])], [np.array([5, 5, 6])]]
    assert join_cell(plan, blocks, [np.ones(3, np.int64), np.ones(3, np.int64)])[0] == 6


def test_empty_block_ends_at_once():
    plan = KernelPlan(("x", "y"), (("x", "y"), ("y",)))
    total, counters = join_cell(plan, [[np.array([1]), np.array([2])], [np.empty(0, np.int64)]], [None, None])
    assert total == 0 and counters.rows_in == 1 and counters.visited == [0, 0]


def work(lifted):
    rng = random.Random(3)
    edges = sorted({(rng.randrange(40), rng.randrange(40)) for _ in range(500)})
    query = parse_rule(PATTERNS["q6"])
    columns = [np.array(c) for c in zip(*edges, strict=True)]
    plan = KernelPlan(query.head, tuple(query.scopes), lifts_of(query, query.head) if lifted else ())
    counters = CellCounters()
    CellJoin(plan, [columns] * 6, [None] * 6, counters).run(None)
    return counters


def test_lifting_saves_comparisons_on_the_clique():
    assert work(True).comparisons < work(False).comparisons
    assert work(True).rows_out == work(False).rows_out


def test_worst_case_stays_linear():
    n = 60
    edges = sorted({(0, i) for i in range(n)} | {(i, 0) for i in range(n)})
    query = parse_rule(PATTERNS["q1d"])
    columns = [np.array(c) for c in zip(*edges, strict=True)]
    counters = CellCounters()
    CellJoin(KernelPlan(query.head, tuple(query.scopes)), [columns] * 3, [None] * 3, counters).run(None)
    wedges = sum(1 for a in edges for b in edges if a[1] == b[0])
    assert sum(counters.visited) < 8 * n < n * n < wedges


def test_key_table_finds_what_is_there():
    import numpy as np

    from cubejoin.operators.kernel import KeyTable

    rng = np.random.default_rng(4)
    for n in (0, 1, 63, 5000):
        keys = np.unique(rng.integers(0, 3 * n + 1, n) - n)
        table = KeyTable(keys)
        wanted = np.arange(-2 * n - 5, 3 * n + 5)
        at, ok, _ = table.find(wanted)
        assert (ok == np.isin(wanted, keys)).all() and (keys[at[ok]] == wanted[ok]).all()
