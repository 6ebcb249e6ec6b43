import random

import pytest
from pyspark.sql import functions as F

from cubejoin.metrics import bench, cell_work, duplication, index_size, measured_communication, phase_times, relative_speed, runtime_curve, share_study, skew_summary, speedups
from cubejoin.operators import baselines, factorize, formats, relops
from cubejoin.operators.executor import cell_profile, cube_join, shared_files_join
from cubejoin.operators.frontier import frontier_join, semi_reduce
from cubejoin.operators.shuffle import encode_domains, exchange, partition_layout, partition_relation, route_rows, sort_blocks
from cubejoin.plans.cost import communication_rows
from cubejoin.plans.planner import JoinPlan, enumerate_shares, quick_plan
from cubejoin.plans.rewrite import lift_intersections
from cubejoin.query import Atom, ConjunctiveQuery, parse_rule
from cubejoin.sources.generators import hub_edges, worst_case_edges
from cubejoin.workloads import CT_RULE, PATTERNS, ct_relations, flagship, graph, pattern, symmetric


@pytest.fixture(scope="module")
def edges(spark):
    rng = random.Random(7)
    rows = sorted({(rng.randrange(15), rng.randrange(15)) for _ in range(80)})
    return rows, spark.createDataFrame(rows, "src long, dst long").persist()


def rows_of(frame, head):
    return sorted(tuple(r[v] for v in head) for r in frame.collect())


def expected(name, rows):
    from cubejoin.operators.kernel import generic_join

    query = pattern(name)
    return generic_join([rows] * len(query.atoms), query.head, query.scopes)


@pytest.mark.parametrize("shares", enumerate_shares(8, 3))
def test_all_shares_give_the_triangles(spark, edges, shares):
    rows, frame = edges
    plan = JoinPlan(("y", "x", "z"), shares)
    assert rows_of(cube_join(spark, pattern("q1d"), {"e": frame}, plan), "xyz") == expected("q1d", rows)


@pytest.mark.parametrize("name", ["q2", "q4", "q6"])
@pytest.mark.parametrize("method", sorted(baselines.METHODS))
def test_methods_agree(spark, edges, name, method):
    rows, frame = edges
    got = baselines.METHODS[method](spark, pattern(name), {"e": frame}, "count").first().n
    assert got == len(expected(name, rows))


@pytest.mark.parametrize("method", ["cube", "frontier", "binary", "lookup", "hashlazy"])
def test_tuples_agree(spark, edges, method):
    rows, frame = edges
    assert rows_of(baselines.METHODS[method](spark, pattern("q4"), {"e": frame}, "tuples"), "xyzu") == expected("q4", rows)


def test_lifted_frontier(spark, edges):
    rows, frame = edges
    query = pattern("q6")
    plan = JoinPlan(("x", "y", "z", "u"), (1, 1, 1, 1), tuple(lift_intersections(query.scopes, ("x", "y", "z", "u"))))
    assert rows_of(frontier_join(spark, query, {"e": frame}, plan), "xyzu") == expected("q6", rows)


def test_shared_files(spark, edges, tmp_path):
    rows, frame = edges
    got = shared_files_join(spark, pattern("q1d"), {"e": frame}, JoinPlan(("x", "y", "z"), (2, 2, 2)), str(tmp_path / "blocks"))
    assert got.first().n == len(expected("q1d", rows))


def test_flagship(spark, tiny):
    assert flagship(spark, tiny).count() == 832


@pytest.mark.parametrize("name,counts", [("copart", (125_968, 755_808, 1_364_801)), ("hubs", (47_216, 179_898, 727_436)), ("custord", (832, 6_054, 487)), ("custhub", (1_490, 9_240, 1_362)), ("succ", (2_615, 2_730, 33_015)), ("words", (41_634, 166_542, 663_606))])
def test_known_counts(spark, tiny, name, counts):
    e = graph(spark, tiny, name).persist()
    assert cube_join(spark, pattern("q1d"), {"e": e}, mode="count").first().n == counts[0]
    assert cube_join(spark, pattern("q1d"), {"e": symmetric(e)}, mode="count").first().n == counts[1]
    assert cube_join(spark, pattern("q4"), {"e": e}, mode="count").first().n == counts[2]


def test_mixed_types_and_nulls(spark):
    a = spark.createDataFrame([(1, "p"), (2, "q"), (None, "p"), (3, None)], "k int, s string")
    b = spark.createDataFrame([(1, "p"), (2, "z"), (None, "p")], "k bigint, s string")
    query = parse_rule("Q(k, s) :- a(k, s), b(k, s)")
    assert rows_of(cube_join(spark, query, {"a": a, "b": b}), ("k", "s")) == [(1, "p")]
    with pytest.raises(ValueError):
        cube_join(spark, query, {"a": a, "b": b.select("s", "k")})
    with pytest.raises(ValueError):
        cube_join(spark, parse_rule("Q(k) :- a(k)"), {"a": spark.createDataFrame([([1],)], "k array<int>")})


def test_single_atom_product_repeats_constants(spark):
    a = spark.createDataFrame([(1, 1), (1, 2), (3, 3)], "x long, y long")
    one = parse_rule("Q(x, y) :- a(x, y)")
    assert rows_of(cube_join(spark, one, {"a": a}), "xy") == [(1, 1), (1, 2), (3, 3)]
    product = parse_rule("Q(x, y, u, v) :- a(x, y), a(u, v)")
    assert cube_join(spark, product, {"a": a}, mode="count").first().n == 9
    assert frontier_join(spark, product, {"a": a}, mode="count").first().n == 9
    assert rows_of(cube_join(spark, parse_rule("Q(x) :- a(x, x)"), {"a": a}), "x") == [(1,), (3,)]
    assert rows_of(cube_join(spark, parse_rule("Q(y) :- a(1, y)"), {"a": a}), "y") == [(1,), (2,)]


def test_empty_relation_and_big_cells(spark, edges):
    _, frame = edges
    empty = frame.limit(0)
    query = parse_rule("Q(x, y, z) :- r(x, y), s(y, z), t(x, z)")
    assert cube_join(spark, query, {"r": frame, "s": empty, "t": frame}, mode="count").first().n == 0
    assert cube_join(spark, query, {"r": frame, "s": empty, "t": frame}).count() == 0
    assert cube_join(spark, pattern("q1d"), {"e": frame}, JoinPlan(("x", "y", "z"), (64, 64, 1)), "count").first().n == len(expected("q1d", edges[0]))


def test_bag_semantics(spark):
    a = spark.createDataFrame([(1, 2), (1, 2), (3, 2)], "x long, y long")
    b = spark.createDataFrame([(2, 9), (2, 9)], "y long, z long")
    query = parse_rule("Q(x, y, z) :- a(x, y), b(y, z)")
    from dataclasses import replace

    plan = replace(quick_plan(query), semantics="bag")
    assert cube_join(spark, query, {"a": a, "b": b}, plan, "count").first().n == 6
    assert len(cube_join(spark, query, {"a": a, "b": b}, plan).collect()) == 6
    assert cube_join(spark, query, {"a": a, "b": b}, mode="count").first().n == 2


def test_filters_across_atoms(spark, edges):
    rows, frame = edges
    query = ConjunctiveQuery(("x", "y", "z"), tuple(Atom("e", v) for v in (("x", "y"), ("y", "z"), ("x", "z"))), ((("x", "z"), lambda x, z: x < z), (("x", "y"), lambda x, y: x != y)))
    want = [t for t in expected("q1d", rows) if t[0] < t[2] and t[0] != t[1]]
    assert rows_of(cube_join(spark, query, {"e": frame}), "xyz") == want
    assert rows_of(frontier_join(spark, query, {"e": frame}), "xyz") == want
    assert cube_join(spark, query, {"e": frame}, mode="count").first().n == len(want)


def test_limit_and_profile(spark, edges):
    rows, frame = edges
    assert cube_join(spark, pattern("q1d"), {"e": frame}, limit=3).count() == 3
    plan = JoinPlan(("x", "y", "z"), (2, 2, 1))
    profile = cell_profile(spark, pattern("q1d"), {"e": frame}, plan).persist()
    assert profile.agg(F.sum("rows_out")).first()[0] == len(expected("q1d", rows))
    measured = measured_communication(spark, pattern("q1d"), {"e": frame}, plan).agg(F.sum("rows")).first()[0]
    assert measured == communication_rows(pattern("q1d").scopes, [len(rows)] * 3, "xyz", (2, 2, 1))["total"]
    assert skew_summary(profile, 4).first().max_over_mean >= 1
    assert runtime_curve(profile, 2).count() == 2
    assert duplication(profile, (15, len(rows), len(expected("q1d", rows)))).count() == 3
    assert cell_work(profile).count() == 4


def test_top_variable_split_is_more_skewed(spark, tiny):
    e = symmetric(graph(spark, tiny, "words")).persist()
    skew = {}
    for shares in ((64, 1, 1), (4, 4, 4)):
        profile = cell_profile(spark, pattern("q1d"), {"e": e}, JoinPlan(("x", "y", "z"), shares))
        skew[shares] = skew_summary(profile, 64).first().max_over_mean
    assert skew[4, 4, 4] < skew[64, 1, 1]


def test_partition_layout_example(spark):
    rows = [(0, 0, 0), (0, 0, 1), (0, 1, 0), (1, 1, 0), (1, 1, 1), (1, 1, 2)]
    frame = spark.createDataFrame(rows, "a long, b long, c long")
    layout = partition_layout(frame, ("a", "b", "c"), ("a", "b", "x", "c"), (2, 2, 1, 2), "mod").collect()
    assert [(r.s_1, r.s_2, r.s_3, r.n, r.start) for r in sorted(layout)] == [(0, 0, 0, 1, 0), (0, 0, 1, 1, 1), (0, 1, 0, 1, 2), (0, 1, 1, 0, 3), (1, 0, 0, 0, 3), (1, 0, 1, 0, 3), (1, 1, 0, 2, 3), (1, 1, 1, 1, 5)]
    dealt = partition_relation(frame, ("a", "b", "c"), ("a", "b", "c"), (2, 2, 2), "mod")
    assert dealt.withColumn("p", F.spark_partition_id()).where("p <> block").count() == 0
    for strategy in ("block", "global", "auto"):
        assert sort_blocks(frame, ("a", "b", "c"), ("a", "b", "c"), (2, 2, 2), strategy).count() == 6
    with pytest.raises(ValueError):
        sort_blocks(frame, ("a", "b", "c"), ("a", "b", "c"), (2, 2, 2), "none")


def test_one_exchange_only(spark, edges):
    _, frame = edges
    routed = exchange(route_rows([frame.toDF("x", "y"), frame.toDF("y", "z"), frame.toDF("x", "z")], [("x", "y"), ("y", "z"), ("x", "z")], "xyz", (2, 2, 2)), 8)
    plan = routed._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1
    assert routed.withColumn("p", F.spark_partition_id()).where("p <> cell % 8").count() == 0


def test_dictionary_keeps_order(spark):
    frame = spark.createDataFrame([("b", "a"), ("c", "b")], "x string, y string")
    coded, dictionary = encode_domains({"r": frame}, {"r": ["x", "y"]})
    codes = {r.value: r.code for r in dictionary.collect()}
    assert sorted(codes, key=codes.get) == ["a", "b", "c"] and sorted(codes.values()) == [0, 1, 2]
    assert coded["r"].columns == ["x", "y"]


def test_factorised_counts_agree(spark, tiny):
    relations = {"e": graph(spark, tiny, "custhub").persist()}
    query = pattern("q8")
    plain = cube_join(spark, query, relations, mode="count").first().n
    assert plain == 11_910
    assert factorize.decomposed_join(spark, query, relations, "z").first().n == plain
    assert factorize.eliminate_variables(spark, query, relations, "z").first().n == plain
    assert factorize.eager_count(spark, query, relations, "z").first().n == plain


def test_binary_plan_blows_up_where_the_cube_does_not(spark):
    e = worst_case_edges(spark, 60)
    made = baselines.intermediate_rows(pattern("q1d"), {"e": e})
    visited = cell_profile(spark, pattern("q1d"), {"e": e}, JoinPlan(("x", "y", "z"), (1, 1, 1))).select(F.aggregate("visited", F.lit(0).cast("long"), lambda s, x: s + x)).first()[0]
    assert made > 3000 and visited < 600


def test_hinted_join_takes_graphs_only(spark, tiny):
    with pytest.raises(ValueError):
        baselines.hinted_join(spark, parse_rule(CT_RULE), ct_relations(spark, tiny), ("u", "x", "y", "z"))


def test_semi_reduction_keeps_results(spark, edges):
    rows, frame = edges
    query, frames = semi_reduce(pattern("q1d"), {"e": frame}, 2)
    assert frames["r0"].count() <= len(rows)
    assert cube_join(spark, query, frames, mode="count").first().n == len(expected("q1d", rows))


def test_layouts(spark):
    frame = spark.createDataFrame([(1, 5), (1, 3), (2, 9), (1, 3)], "src long, dst long")
    assert [(r.src, r.lo, r.hi, r.dsts) for r in formats.to_csr(frame).orderBy("src").collect()] == [(1, 0, 2, [3, 5]), (2, 2, 3, [9])]
    assert formats.to_csc(frame).count() == 3 and formats.to_coo(frame).count() == 3
    assert sum(r.hi - r.lo for r in formats.to_dcsr(frame).collect()) == 3
    levels = formats.trie_levels(frame)
    assert levels.where("level = 0").orderBy("pos").select("value", "lo", "hi").collect() == [(1, 0, 2), (2, 2, 3)]


def test_relational_helpers(spark):
    left = hub_edges(spark, 200).withColumnRenamed("src", "k")
    right = spark.range(200).select(F.col("id").alias("k"), (F.col("id") * 2).alias("v"))
    assert relops.salted_join(left, right, ["k"]).count() == left.join(right, "k").count()
    for how in ("inner", "left", "right", "full", "left_semi", "left_anti"):
        assert relops.equi_join(left, right, ["k"], how, "merge").count() == left.join(right, "k", how).count()
    with pytest.raises(ValueError):
        relops.equi_join(left, right, ["k"], strategy="magic")
    top = relops.top_k_per(left, ["k"], 1, F.col("dst"))
    assert top.count() == left.select("k").distinct().count()
    pairs = spark.createDataFrame([(1, 2), (2, 3), (1, 3), (3, 4)], "src long, dst long")
    assert {r.v: r.triangles for r in relops.vertex_triangles(pairs).collect()} == {1: 1, 2: 1, 3: 1}
    assert {r.v: round(r.coefficient, 3) for r in relops.clustering(pairs).collect()} == {1: 1.0, 2: 1.0, 3: 0.333, 4: 0.0}


def test_measures(spark, edges):
    _, frame = edges
    got = phase_times(spark, pattern("q1d"), {"e": frame}, JoinPlan(("x", "y", "z"), (2, 2, 1)))
    assert 0 < got["share"] < 1
    sizes = index_size(frame)
    assert sizes["index_bytes"] <= 2 * sizes["row_bytes"]
    assert bench(lambda: None)["timed_out"] is False and relative_speed(1, 2) == 2 and speedups({1: 4.0, 2: 2.0})[2] == 2
    study = share_study(spark, pattern("q1d"), {"e": frame}, [JoinPlan(("x", "y", "z"), s) for s in ((4, 1, 1), (1, 1, 4))])
    assert study[0]["rows_out"] == study[1]["rows_out"] and study[0]["total"] < study[1]["total"]


def test_all_patterns_parse():
    assert all(pattern(p).head for p in PATTERNS)


def test_heavy_values_apart(spark):
    from cubejoin.operators.heavy import heavy_split_join, residual_shares

    e = symmetric(hub_edges(spark, 300))
    plain = cube_join(spark, pattern("q1d"), {"e": e}, mode="count").first().n
    plan = JoinPlan(("x", "y", "z"), (4, 4, 1))
    assert heavy_split_join(spark, pattern("q1d"), {"e": e}, plan, threshold=40).first().n == plain
    assert residual_shares(plan, ("x",)) == (1, 4, 4) and residual_shares(plan, ("x", "y", "z")) == (1, 1, 1)


def test_sql_capture(spark, edges):
    from cubejoin.sql import query_from_sql, run_sql

    rows, frame = edges
    text = "SELECT a.src AS x, a.dst AS y, b.dst AS z FROM e a, e AS b, e c WHERE a.dst = b.src AND a.src = c.src AND c.dst = b.dst"
    assert rows_of(run_sql(spark, text, {"e": frame}), "xyz") == expected("q1d", rows)
    fixed, names = query_from_sql("select b.dst from e a, e b where a.dst = b.src and a.src = 3", {"e": frame})
    assert fixed.atoms[0].constants == {0: 3} and list(names.values()) == ["dst"]
    for bad in ("delete from e", "select a.src from f a", "select a.src from e a where a.src < 3", "select a.nope from e a", "select a.src from e a, e a"):
        with pytest.raises(ValueError):
            query_from_sql(bad, {"e": frame})


def test_studies(spark, tiny):
    from cubejoin import studies

    rewriting = {(r["query"], r["plan"]): r for r in studies.rewriting(spark, tiny)}
    assert rewriting["q6", "lifted"]["comparisons"] < rewriting["q6", "plain"]["comparisons"]
    for name in ("q1d", "lw", "ct"):
        assert rewriting[name, "lifted"]["comparisons"] == rewriting[name, "plain"]["comparisons"]
    assert len({r["comparisons"] for r in studies.searches(spark, tiny, ("succ",))}) > 1
    found = studies.factorised(spark, tiny, "custord")
    assert {r["n"] for r in found} == {4500}
    best = studies.orders(spark, tiny, "custord")
    assert len(best) == 24 and sum(r["chosen"] for r in best) == 1
    assert [r["chosen"] for r in best].index(True) < 12


def test_large_keys_and_mixed_arity(spark):
    big = 2**62 + 1
    a = spark.createDataFrame([(big, 1, 2), (big + 2, 1, 2)], "x long, y long, z long")
    b = spark.createDataFrame([(big,), (big + 4,)], "x long")
    query = parse_rule("Q(x, y, z) :- a(x, y, z), b(x)")
    assert rows_of(cube_join(spark, query, {"a": a, "b": b}), "xyz") == [(big, 1, 2)]
    assert cube_join(spark, parse_rule("Q(x) :- b(x), a(x, 1, 2)"), {"a": a, "b": b}, mode="count").first().n == 1


def test_twin_paths_are_counted_without_listing_them(spark):
    import numpy as np

    from cubejoin.operators.factorize import powers_of_paths, twin_paths

    rule = "Q(x, y, z, u) :- e(x, y), e(x, z), e(y, u), e(z, u)"
    assert twin_paths(parse_rule(rule)) == ("x", ["y", "z"], "u")
    assert not any(map(twin_paths, (pattern("q4"), pattern("q6"), pattern("q1d"), parse_rule("Q(x, y, z, u) :- e(x, y), f(x, z), e(y, u), e(z, u)"))))
    rng = np.random.default_rng(5)
    rows = [(int(a), int(b)) for a, b in rng.integers(0, 12, (70, 2))] + [(0, 1), (0, 1)]
    paths = [(a, d) for a, b in set(rows) for c, d in set(rows) if b == c]
    want = sum(paths.count(p) ** 2 for p in set(paths))
    x, y = np.array(rows).T
    for chunk in (1, 7, 1 << 20):
        assert powers_of_paths(x, y, x, y, 2, chunk) == want
    words = spark.createDataFrame([*((str(a), str(b)) for a, b in rows), (None, "1")], "src string, dst string")
    assert cube_join(spark, parse_rule(rule), {"e": words}, mode="count").first().n == want
    # 30,000 middles between two ends: 900 million results, one pair of ends.
    fan = spark.range(30_000).selectExpr("-1L as src", "id as dst").union(spark.range(30_000).selectExpr("id as src", "-2L as dst"))
    assert cube_join(spark, parse_rule(rule), {"e": fan}, mode="count").first().n == 900_000_000


@pytest.mark.parametrize("name,method", [("q1d", "topvar"), ("q6", "nolift"), ("q4", "hasheager"), ("q8", "hashlazy"), ("q1c", "hinted")])
def test_many_rows_go_to_one_store_for_all_atoms(spark, edges, monkeypatch, name, method):
    from cubejoin.operators import executor
    from cubejoin.plans import planner

    rows, frame = edges
    stored = []
    monkeypatch.setattr(executor, "GRID_ROWS", 10)
    monkeypatch.setattr(planner, "CELL_ROWS", dict.fromkeys(planner.CELL_ROWS, 60))
    write = executor.write_grid
    monkeypatch.setattr(executor, "write_grid", lambda *a: (stored.append(a), write(*a))[1])
    got = baselines.METHODS[method](spark, pattern(name), {"e": frame}, "count").first().n
    assert got == len(expected(name, rows))
    assert len(stored) == 1


def test_store_serves_tuples_limits_filters_strings_and_pivots(spark, edges, monkeypatch):
    from dataclasses import replace

    from cubejoin.operators import executor

    rows, frame = edges
    monkeypatch.setattr(executor, "GRID_ROWS", 10)
    want = expected("q1d", rows)
    assert rows_of(cube_join(spark, pattern("q1d"), {"e": frame}), "xyz") == want
    plan = quick_plan(pattern("q1d"), 16)
    assert cube_join(spark, pattern("q1d"), {"e": frame}, plan, limit=7).count() == 7
    assert cube_join(spark, pattern("q1d"), {"e": frame}, plan, "count", limit=7).first().n == 7
    ordered = replace(pattern("q1d"), filters=((("x", "y", "z"), lambda x, y, z: (x < y) & (y < z)),))
    assert cube_join(spark, ordered, {"e": frame}, plan, "count").first().n == sum(x < y < z for x, y, z in want)
    words = frame.select(*(F.concat(F.lit("w"), F.col(c).cast("string")).alias(c) for c in ("src", "dst")))
    assert rows_of(cube_join(spark, pattern("q1d"), {"e": words}), "xyz") == sorted(tuple(f"w{v}" for v in t) for t in want)
    counted = {r.y: r.c for r in executor.count_by(spark, pattern("q1d"), {"e": frame}, "y", plan).collect()}
    assert counted == {y: sum(t[1] == y for t in want) for y in {t[1] for t in want}}


def test_store_reads_parts_of_larger_sides(spark, monkeypatch):
    """A relation's two columns are dealt as finely as its finest atom; other atoms read several blocks."""
    from dataclasses import replace

    rng = random.Random(3)
    rows = sorted({(rng.randrange(-9, 40), rng.randrange(-9, 40)) for _ in range(300)})
    frame = spark.createDataFrame(rows, "src long, dst long")
    for hashing in ("xxhash64", "mod"):
        plan = JoinPlan(("x", "y", "z"), (8, 2, 1), exchange="grid", hashing=hashing)
        assert cube_join(spark, pattern("q1d"), {"e": frame}, plan, "count").first().n == len(expected("q1d", rows))
        assert cube_join(spark, pattern("q1d"), {"e": frame}, replace(plan, index="hash_eager", search="adaptive"), "count").first().n == len(expected("q1d", rows))


def test_limited_triangles_store_their_graph(spark, tiny, monkeypatch):
    """Counting, measuring and dealing out the graph read one stored table, not three derivations."""
    from cubejoin import catalog

    def derived(*_):
        raise AssertionError("derived outside the store")

    monkeypatch.setattr(catalog, "graph", derived)
    assert catalog.queries()["limited_triangles"](spark, tiny).first().n == 100


@pytest.mark.parametrize("index", ["hash_lazy", "hash_eager"])
def test_large_hash_joins_search_whole_levels(spark, edges, monkeypatch, index):
    """No Python step per binding, no dictionaries: the scalar loops are not entered over the store."""
    from dataclasses import replace

    from cubejoin.operators import executor
    from cubejoin.operators.kernel import ScalarJoin
    from cubejoin.plans.planner import fitted

    rows, frame = edges
    monkeypatch.setattr(executor, "GRID_ROWS", 10)
    plan = replace(quick_plan(pattern("q4"), 4, lift="none"), index=index, search="adaptive")
    grown = fitted(plan, pattern("q4").scopes, [len(rows)] * 5, 60)
    assert (grown.search, grown.exchange, grown.index) == ("hashed", "grid", index)
    monkeypatch.setattr(ScalarJoin, "run", None)
    assert cube_join(spark, pattern("q4"), {"e": frame}, grown, "count").first().n == len(expected("q4", rows))
    assert rows_of(cube_join(spark, pattern("q4"), {"e": frame}, grown), "xyzu") == expected("q4", rows)


def test_large_lazy_hash_counts_go_group_by_group(spark, edges, monkeypatch):
    from cubejoin.operators import executor, factorize

    rows, frame = edges
    pivots = []
    count_by = factorize.count_by
    monkeypatch.setattr(factorize, "count_by", lambda s, q, r, pivot, plan: (pivots.append((pivot, plan.index)), count_by(s, q, r, pivot, plan))[1])
    monkeypatch.setattr(executor, "GRID_ROWS", 10)
    monkeypatch.setattr(baselines, "GROUP_ROWS", 10)
    assert baselines.lazy_hash_join(spark, pattern("q8"), {"e": frame}).first().n == len(expected("q8", rows))
    assert pivots == [("z", "hash_lazy")] * 2


def test_broadcast_hint_is_for_small_relations(spark, edges, monkeypatch):
    rows, frame = edges
    plan = lambda: baselines.binary_join(pattern("q1d"), {"e": frame}, "broadcast", "tuples")._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=broadcast" in plan()
    monkeypatch.setattr(baselines, "BROADCAST_ROWS", 10)
    assert "strategy=broadcast" not in plan()
    assert baselines.binary_join(pattern("q1d"), {"e": frame}, "broadcast").first().n == len(expected("q1d", rows))


def test_large_lookups_shuffle_no_wedges(spark, edges, monkeypatch):
    from cubejoin.operators import factorize

    rows, frame = edges
    monkeypatch.setattr(factorize, "LOOKUP_ROWS", 10)
    monkeypatch.setattr(baselines, "lookup_expand_join", None)
    assert factorize.two_way_variant(pattern("q8"), {"e": frame}, "z", True, True).first().n == len(expected("q8", rows))


@pytest.mark.parametrize("name,shares", [("q1d", (4, 4, 1)), ("q1d", (1, 1, 1)), ("q4", (2, 2, 1, 1)), ("q6", (2, 2, 1, 1)), ("ct", (2, 2, 1, 1)), ("lw", (2, 2, 1, 1))])
def test_large_profiles_count_the_same_work_without_copies(spark, tiny, monkeypatch, name, shares):
    from dataclasses import replace

    from cubejoin.operators import executor, kernel
    from cubejoin.workloads import LW_RULE, lw_relations

    if name in PATTERNS:
        query, relations = pattern(name), {"e": graph(spark, tiny, "succ").persist()}
    else:
        query, relations = (parse_rule(CT_RULE), ct_relations(spark, tiny)) if name == "ct" else (parse_rule(LW_RULE), lw_relations(spark, tiny))
    base = replace(quick_plan(query, 4, lift="none"), shares=shares)
    lifted = replace(base, lifts=tuple(lift_intersections([tuple(sorted(s, key=base.order.index)) for s in query.scopes], base.order)))
    rows = lambda frame: sorted(tuple(r) for r in frame.drop("seconds").collect())
    want = [rows(cell_profile(spark, query, relations, p)) for p in (base, lifted)]
    monkeypatch.setattr(executor, "GRID_ROWS", 10)
    monkeypatch.setattr(executor, "SORTED_ROWS", 900)  # some blocks are sorted by several tasks
    monkeypatch.setattr(executor, "_routed", lambda *a: pytest.fail("rows were copied to cells"))
    got = executor.cell_profiles(spark, query, relations, [base, lifted])
    assert list(map(rows, got)) == want
    assert len(want[0]) > 1 - (base.cells == 1) and sum(r[2] for r in want[0]) > 0
    monkeypatch.setattr(executor, "STORE_BLOCKS", 1)
    assert rows(cell_profile(spark, query, relations, lifted)) == want[1]


def test_compact_cells_of_any_values_and_sizes(monkeypatch):
    import numpy as np

    from cubejoin.operators import kernel

    rng = np.random.default_rng(2)
    monkeypatch.setattr(kernel, "MAPPED_BYTES", 64)
    monkeypatch.setattr(kernel, "PART_ROWS", 7)
    monkeypatch.setattr(kernel, "MEET_ROWS", 50)
    query = pattern("q6")
    lifts = tuple((x.level, x.at_depth, x.inputs) for x in lift_intersections(query.scopes, tuple("xyzu")))
    for values in (np.arange(40), np.arange(-20, 20) * 10**6, np.arange(40) * (1 << 50)):
        columns = [values[c] for c in rng.integers(0, 40, (2, 900))]
        for plan in (kernel.KernelPlan(tuple("xyzu"), query.scopes, lifts, chunk_rows=100), kernel.KernelPlan(tuple("xyzu"), query.scopes, chunk_rows=100)):
            n, want = kernel.join_cell(plan, [columns] * 6, [None] * 6)
            parts = lambda: ([c[lo : lo + 250] for c in columns] for lo in range(0, 900, 250))  # noqa: E731, B023
            atom = kernel.StoredAtom(900, 900, [(int(c.min()), int(c.max())) for c in columns], parts)
            got = kernel.join_stored(plan, [atom] * 6)
            got.seconds = want.seconds
            assert n > 0 and got == want


def test_coded_words_are_stored_without_a_pass_for_their_ends(spark, edges, monkeypatch):
    from cubejoin.operators import executor

    rows, frame = edges
    stored = []
    write = executor.write_grid
    monkeypatch.setattr(executor, "write_grid", lambda *a: (stored.append(a[5:]), write(*a))[1])
    plan = JoinPlan(("x", "y", "z"), (2, 2, 1), exchange="grid")
    words = frame.select(*(F.concat(F.lit("w"), F.col(c).cast("string")).alias(c) for c in ("src", "dst")))
    assert cube_join(spark, pattern("q1d"), {"e": words}, plan, "count").first().n == len(expected("q1d", rows))
    assert cube_join(spark, pattern("q1d"), {"e": frame}, plan, "count").first().n == len(expected("q1d", rows))
    assert stored == [(len({v for r in rows for v in r}),), ()]
