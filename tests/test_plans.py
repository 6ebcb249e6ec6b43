import random
from math import comb

import pytest

from cubejoin.plans.bounds import agm_bound, edge_cover
from cubejoin.plans.cost import communication_rows, estimate_total_cost, exact_level_costs, intersection_cost, level_bound, replicated_cost
from cubejoin.plans.planner import JoinPlan, best_order_dp, communication_shares, enumerate_orders, enumerate_shares, evenness, pick_executor, pick_shares, plan_query, prune_cost, prune_domain, quick_plan
from cubejoin.plans.rewrite import Lift, is_optimal, lift_intersections, reduced_query
from cubejoin.plans.stats import collect_relation, collect_stats, stats_of_rows
from cubejoin.query import parse_rule
from cubejoin.workloads import CT_RULE, LW_RULE, graph, pattern

TRIANGLE = [("x", "y"), ("y", "z"), ("x", "z")]
CLIQUE = [("x", "y"), ("x", "z"), ("x", "u"), ("y", "z"), ("y", "u"), ("z", "u")]


@pytest.mark.parametrize("n,count", [(3, 66), (4, 286), (5, 1001)])
def test_share_vectors(n, count):
    shares = enumerate_shares(1024, n)
    assert len(shares) == len(set(shares)) == count == comb(10 + n - 1, n - 1)


def test_bad_cells():
    with pytest.raises(ValueError):
        enumerate_shares(12, 2)


def test_evenness():
    assert evenness((32, 32, 1)) == pytest.approx(32 * 0.99 + 32 * 0.98 + 0.97)
    assert evenness((1,) * 30) == pytest.approx(sum(max(1 - i / 100, 0.75) for i in range(1, 31)))
    assert evenness((8, 8, 16)) < evenness((32, 32, 1)) < evenness((1024, 1, 1))


def test_pruning_rules():
    assert prune_cost((1, 10, 1000), (32, 32, 1)) and not prune_cost((1, 1000, 1000), (8, 8, 16))
    assert prune_domain((1000, 1000), (32, 1)) and not prune_domain((100, 100), (32, 1))
    assert not prune_domain((470, 1), (32, 1)) and prune_domain((470, 1), (32, 1), log_base=2.718281828)


def test_shares_with_exact_costs_of_the_graphs():
    assert pick_shares((3968, 1121206, 13247727), (2000, 2000, 2000), 64)[0] == (4, 4, 4)
    assert pick_shares((3000, 214335, 324591), (1500, 1500, 1500), 64)[0] == (4, 8, 2)
    assert pick_shares((1, 1, 1), (2, 2, 2), 1024) == ((1, 1, 1), 1)


def test_communication_optimum_is_even_for_equal_relations():
    assert communication_shares(TRIANGLE, [100] * 3, "xyz", 4096) == (16, 16, 16)
    assert communication_rows(TRIANGLE, [100] * 3, "xyz", (4, 4, 4)) == {"total": 1200.0, "per_cell": 18.75}


def test_edge_cover_bounds():
    assert agm_bound(TRIANGLE, [100] * 3) == pytest.approx(1000)
    assert agm_bound(CLIQUE, [100] * 6) == pytest.approx(10_000)
    assert agm_bound([("x", "y"), ("y",)], [100, 5]) == pytest.approx(100)
    assert agm_bound(TRIANGLE, [0, 5, 5]) == 0
    assert edge_cover(TRIANGLE, [100] * 3)[1] == pytest.approx([0.5] * 3)


def test_lifts_of_the_clique():
    assert lift_intersections(CLIQUE, ("x", "y", "z", "u")) == [Lift(1, 0, (3, 4)), Lift(2, 1, (1, 5)), Lift(3, 2, (2, 4))]


def test_nothing_to_lift():
    assert lift_intersections(TRIANGLE, ("x", "y", "z")) == []
    assert lift_intersections(parse_rule(LW_RULE).scopes, ("x", "y", "z", "u")) == []
    assert lift_intersections(parse_rule(CT_RULE).scopes, ("u", "x", "y", "z")) == []


def test_lift_optimality():
    order = ("x", "y", "z", "u")
    lifts = lift_intersections(CLIQUE, order)
    assert reduced_query(CLIQUE, order, lifts) == [("x",), ("x", "z"), ("x", "u"), ("y",), ("y", "u"), ("z",)]
    even = {j: 100 for j in range(6)}
    ends = {0: 2, 1: 1000, 2: 1000, 3: 1000, 4: 1000, 5: 2}
    assert is_optimal(CLIQUE, order, lifts, even)
    assert not is_optimal(CLIQUE, order, lifts, ends)
    plan = plan_query(pattern("q6"), [stats_of_rows(s, [(i, i + 1) for i in range(ends[j])]) for j, s in enumerate(CLIQUE)], lift="safe", order_hint=order, share_hint=(64, 1, 1, 1))
    assert plan.lifts == ()


def test_level_bound_holds_for_random_sizes():
    rng = random.Random(4)
    for _ in range(200):
        k = rng.randint(2, 4)
        sizes = [[rng.randint(1, 500) for _ in range(k)] for _ in range(rng.randint(1, 30))]
        exact = sum(map(intersection_cost, sizes))
        assert exact <= level_bound(k, sum(map(min, sizes)), sum(map(max, sizes))) * (1 + 1e-9)


def test_replication():
    assert replicated_cost((1, 10, 100), (4, 2, 8)) == 16 + 80 + 100
    assert replicated_cost((1, 10, 100), (64, 1, 1)) == 111


def test_exact_costs_below_bounds_on_a_graph(spark, tiny):
    for name in ("custord", "succ"):
        edges = graph(spark, tiny, name).persist()
        for level in exact_level_costs(spark, pattern("q1d"), {"e": edges}, ("x", "y", "z")):
            assert level.exact <= level.bound * (1 + 1e-9)


def test_stats_agree_with_rows(spark):
    rows = [(1, 2), (1, 3), (2, 3), (2, 3), (4, 1)]
    frame = spark.createDataFrame(rows, "a long, b long")
    got, expected = collect_relation(frame), stats_of_rows(("a", "b"), rows)
    assert (got.rows, got.distinct, got.max_degree) == (expected.rows, expected.distinct, expected.max_degree)
    rough = collect_relation(frame, exact=False)
    assert not rough.exact and rough.distinct[frozenset("a")] == 3


def test_planner_modes():
    rng = random.Random(5)
    rows = [(rng.randrange(300), rng.randrange(300)) for _ in range(4000)]
    query = pattern("q1d")
    stats = [stats_of_rows(s, rows) for s in query.scopes]
    staged = plan_query(query, stats, cells=64)
    joint = plan_query(query, stats, cells=64, mode="joint")
    assert staged.cells == joint.cells == 64
    assert sum(estimate_total_cost(query.scopes, stats, staged.order)) == min(sum(estimate_total_cost(query.scopes, stats, o)) for o in enumerate_orders(query.head))
    assert sorted(best_order_dp(query.scopes, stats)) == ["x", "y", "z"]
    assert plan_query(query, stats, objective="communication").shares == (4, 4, 4)
    assert plan_query(query, stats, objective="combined").cells == 64
    assert "for each common value of" in staged.explain(query)
    with pytest.raises(ValueError):
        plan_query(query, stats, share_hint=(2, 2, 2))
    with pytest.raises(ValueError):
        plan_query(query, stats, order_hint=("x", "y"))
    with pytest.raises(ValueError):
        plan_query(query, stats, mode="other")


def test_executor_choice():
    plan = JoinPlan(("x", "y", "z"), (4, 4, 4))
    assert pick_executor(plan, TRIANGLE, [10**6] * 3).executor == "cube"
    assert pick_executor(plan, TRIANGLE, [10**12] * 3).executor == "frontier"


def test_quick_plan_is_connected():
    plan = quick_plan(pattern("q8"))
    assert plan.order[0] == "z" and plan.cells == 16 and plan.shares[-1] == 1


def test_collect_stats_per_atom(spark):
    frame = spark.createDataFrame([(1, 2), (2, 3)], "a long, b long")
    stats = collect_stats(pattern("q1d"), {"e": frame})
    assert stats[1].distinct[frozenset({"y", "z"})] == 2


def test_cells_of_large_inputs_fit_a_worker():
    from cubejoin.plans.cost import communication_rows
    from cubejoin.plans.planner import CELL_ROWS, fitted

    for index, rows in (("packed", 18_000_000), ("hash_lazy", 18_000_000), ("packed", 144_000_000)):
        plan = fitted(JoinPlan(("x", "y", "z"), (16, 1, 1), index=index), TRIANGLE, [rows] * 3)
        assert plan.exchange == "grid"
        assert communication_rows(TRIANGLE, [rows] * 3, plan.order, plan.shares)["per_cell"] <= CELL_ROWS[index]
