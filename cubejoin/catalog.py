"""Driver queries of the join engine and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.register import parse_props, register_functions
from .metrics import cell_work, duplication, measured_communication, skew_summary
from .operators import baselines, factorize, formats, relops
from .operators.executor import cell_profile, count_by, cube_join
from .operators.frontier import frontier_join, semi_reduce
from .operators.heavy import heavy_split_join
from .operators.shuffle import partition_layout, partition_relation, sort_blocks
from .plans.bounds import edge_cover
from .plans.cost import communication_rows, cost_report, estimate_total_cost, exact_level_costs, replicated_cost
from .plans.planner import JoinPlan, auto_plan, best_order_dp, enumerate_orders, enumerate_shares, evenness, plan_query, prune_cost, prune_domain, quick_plan
from .plans.rewrite import lift_intersections, reduced_query
from .plans.stats import collect_stats
from .query import parse_rule, query_from_json, query_to_json
from .sources.generators import axis_sql, tensor_workload
from .sources.tables import read_edges, run_folder, table, write_result, written
from .sql import run_sql
from .streaming.incremental import IncrementalCount, windowed_edges, windowed_triangles
from .workloads import COUNT_SQL, CT_JOIN_SQL, CT_RULE, GRAPHS, LW_JOIN_SQL, LW_RULE, TRIANGLES_SQL, TRIO_JOIN_SQL, TRIO_RULE, ct_plan, ct_relations, graph, lw_relations, pattern, stored_graph, symmetric, trio_relations, with_fact, with_graph

Query = Callable[[SparkSession, str], DataFrame]
CELLS = 16


def _count(name: str, g: str, undirected: bool = False) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return cube_join(spark, pattern(name), {"e": stored_graph(spark, sf_dir, g, undirected)}, mode="count")

    return run


def _rows(name: str, g: str) -> Query:
    return lambda spark, sf_dir: cube_join(spark, pattern(name), {"e": stored_graph(spark, sf_dir, g)})


def _method(name: str, g: str, method: str, undirected: bool = False) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return baselines.METHODS[method](spark, pattern(name), {"e": stored_graph(spark, sf_dir, g, undirected)}, "count")

    return run


def _factorised(kind: str, g: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        relations = {"e": stored_graph(spark, sf_dir, g)}
        if kind in ("td", "td_lookup", "td_lookup_eager"):
            return factorize.two_way_variant(pattern("q8"), relations, "z", "lookup" in kind, "eager" in kind)
        if kind == "lazyhash":
            return baselines.lazy_hash_join(spark, pattern("q8"), relations)
        if kind == "eager":
            return factorize.eager_count(spark, pattern("q8"), relations, "z")
        if kind == "varelim":
            return factorize.eliminate_variables(spark, pattern("q8"), relations, "z")
        return factorize.decomposed_join(spark, pattern("q8"), relations, "z")

    return run


def _expand3(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = graph(spark, sf_dir, "custhub")
    return baselines.expand3(e, e, e).agg(F.count("*").alias("n"))


def _planned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Q1d under the full planner: statistics, order, lifts, shares."""
    query, relations = pattern("q1d"), {"e": graph(spark, sf_dir, "custhub")}
    plan = plan_query(query, collect_stats(query, relations), cells=64)
    return cube_join(spark, query, relations, plan, "count")


def _level_costs(field: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        query, relations = pattern("q1d"), {"e": graph(spark, sf_dir, "custord")}
        costs = exact_level_costs(spark, query, relations, ("x", "y", "z"))
        return spark.createDataFrame([(c.level, round(float(getattr(c, field)), 2)) for c in costs], "level int, cost double")

    return run


def _cost_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    query, relations = pattern("q1d"), {"e": graph(spark, sf_dir, "custord")}
    rows = cost_report(spark, query, relations, ("x", "y", "z"), collect_stats(query, relations))
    return spark.createDataFrame([(r["level"], r["variable"], r["inputs"], float(r["exact"]), float(r["bound"]), float(r["estimate"]), float(r["q_error"])) for r in rows], "level int, variable string, inputs int, exact double, bound double, estimate double, q_error double")


def _share_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All share vectors of 1,024 cells: how even they are, and the rows of the graph's triangle query that a cell gets on average."""
    n = graph(spark, sf_dir, "custord").count()
    sent = lambda s: communication_rows(pattern("q1d").scopes, [n] * 3, ("x", "y", "z"), s)["per_cell"]
    return spark.createDataFrame([(*s, round(evenness(s), 4), float(sent(s))) for s in enumerate_shares(1024, 3)], "p1 int, p2 int, p3 int, evenness double, rows_per_cell double")


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All orders of the clique's variables, each with the values of the graph that its first loop visits."""
    e = graph(spark, sf_dir, "custord")
    starts = []
    for v in "xyzu":
        sides = {("src", "dst")[s.index(v)] for s in pattern("q6").scopes if v in s}
        values = [e.select(F.col(c).alias("v")).distinct() for c in sorted(sides)]
        starts.append((v, values[0].join(values[1], "v", "left_semi").count() if len(values) > 1 else values[0].count()))
    first = dict(starts)
    return spark.createDataFrame([("".join(o), first[o[0]]) for o in enumerate_orders("xyzu")], "o string, first_values long")


def _replicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replicated cost of all 28 share vectors of 64 cells, for the optimizer's level costs of the graph's triangles."""
    query, relations = pattern("q1d"), {"e": graph(spark, sf_dir, "custord")}
    costs = estimate_total_cost(query.scopes, collect_stats(query, relations), ("x", "y", "z"))
    return spark.createDataFrame([(*s, round(float(replicated_cost(costs, s)), 2)) for s in enumerate_shares(64, 3)], "p1 int, p2 int, p3 int, cost double")


def _graph_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = []
    for g in GRAPHS:
        d = relops.degrees(graph(spark, sf_dir, g).select(F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst")))
        out.append(d.agg(F.lit(g).alias("graph"), F.sum("out_degree").alias("edges"), F.count("*").alias("nodes"), F.max("out_degree").alias("max_out"), F.max("in_degree").alias("max_in")))
    return baselines.combined(out)


def _lw(mode: str) -> Query:
    return lambda spark, sf_dir: cube_join(spark, parse_rule(LW_RULE), lw_relations(spark, sf_dir), mode=mode)


def _lw_spurious(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rebuilt (part, supplier, line, quantity) rows that no line has."""
    rebuilt = _lw("tuples")(spark, sf_dir)
    from .workloads import fact

    true = fact(spark, sf_dir).select(F.col("l_partkey").alias("x"), F.col("l_suppkey").alias("y"), F.col("l_linenumber").alias("z"), F.col("qty").alias("u")).distinct()
    return rebuilt.join(true, ["x", "y", "z", "u"], "left_anti").agg(F.count("*").alias("n"))


def _ct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cube_join(spark, parse_rule(CT_RULE), ct_relations(spark, sf_dir), mode="count")


def _trio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cube_join(spark, parse_rule(TRIO_RULE), trio_relations(spark, sf_dir), mode="count")


def _trio_by_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = cube_join(spark, parse_rule(TRIO_RULE), trio_relations(spark, sf_dir))
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("c"), "c_mktsegment")
    return found.join(customers, "c").rollup("c_mktsegment").agg(F.count("*").alias("n"))


def _layout(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition_layout(graph(spark, sf_dir, "custord"), ("src", "dst"), ("src", "dst"), (4, 2), "mod")


def _layout_hashed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition_layout(graph(spark, sf_dir, "custord"), ("src", "dst"), ("src", "dst"), (4, 2))


def _communication(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = JoinPlan(("x", "y", "z"), (4, 2, 2), hashing="mod")
    return measured_communication(spark, pattern("q1d"), {"e": graph(spark, sf_dir, "custord")}, plan)


def _profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    profile = cell_profile(spark, pattern("q1d"), {"e": stored_graph(spark, sf_dir, "hubs", True)}, JoinPlan(("x", "y", "z"), (4, 4, 1)))
    return cell_work(profile).drop("seconds")


def _skew_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Skew of cell work by share vector, 64 cells, undirected triangles of the word graph."""
    edges = symmetric(graph(spark, sf_dir, "words"))
    out = []
    for shares in ((64, 1, 1), (8, 8, 1), (4, 4, 4)):
        profile = cell_profile(spark, pattern("q1d"), {"e": edges}, JoinPlan(("x", "y", "z"), shares))
        out.append(skew_summary(profile, 64).select(F.lit("x".join(map(str, shares))).alias("shares"), "*"))
    return baselines.combined(out)


def _plan_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for g in ("custord", "custhub", "succ"):
        query, relations = pattern("q1d"), {"e": graph(spark, sf_dir, g)}
        plan = plan_query(query, collect_stats(query, relations), cells=64)
        rows.append((g, "".join(plan.order), "x".join(map(str, plan.shares)), float(plan.costs["total"]), float(plan.costs["replicated"])))
    return spark.createDataFrame(rows, "graph string, plan_order string, shares string, total double, replicated double")


def _lifts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lifted intersections of the clique in order x, y, z, u, and the values that each keeps over all bindings of its depth."""
    query, order = pattern("q6"), ("x", "y", "z", "u")
    e = stored_graph(spark, sf_dir, "custord")
    rows = []
    for x in lift_intersections(query.scopes, order):
        # Atoms of bound variables, and the projections of those that still bind one of them or give values to the lifted one.
        bound = set(order[: x.at_depth])
        seen = [v for v in order if v in bound | {order[x.level]}]
        atoms, relations = [], {}
        for j, scope in enumerate(query.scopes):
            held = [v for v in scope if v in bound or (j in x.inputs and v == order[x.level])]
            if held:
                sides = tuple(("src", "dst")[scope.index(v)] for v in held)
                relations["_".join(sides)] = e.select(*sides).distinct()
                atoms.append(f"{'_'.join(sides)}({', '.join(held)})")
        rule = f"Q({', '.join(seen)}) :- {', '.join(dict.fromkeys(atoms))}"
        kept = cube_join(spark, parse_rule(rule), relations, quick_plan(parse_rule(rule), CELLS), "count").first().n
        rows.append((x.level, x.at_depth, ",".join(map(str, x.inputs)), kept))
    return spark.createDataFrame(rows, "level int, depth int, inputs string, kept_values long")


#: Share of a dense tensor's points that rows draw, and of a sparse one's.
TENSOR_FILL = {"dense": 0.9375, "sparse": 0.001}


def _tensor(kind: str, shape: str) -> Query:
    """Tensors whose points are drawn by the keys of the parts: their domains grow with the table."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"))
        n = parts.count()
        made = tensor_workload(spark, kind, n, max(2, round((n / TENSOR_FILL[kind]) ** (1 / 3))), sparsity=TENSOR_FILL["sparse"], counters=parts)
        if shape == "lw":
            return cube_join(spark, parse_rule(LW_RULE), {f"lw{k}": made[f"t{k}"] for k in range(1, 5)}, mode="count")
        return cube_join(spark, parse_rule(CT_RULE), {f"ct{k}": made[f"t{k}"] for k in range(5, 8)}, mode="count")

    return run


def _tensor_sql(kind: str, shape: str) -> str:
    numbers = range(1, 5) if shape == "lw" else range(5, 8)
    wide = "domain" if kind == "dense" else f"greatest(2, CAST(round(sqrt(n / {10 * TENSOR_FILL[kind]} / 8)) AS BIGINT))"
    sizes = f"k AS (SELECT domain, {wide} AS wide FROM (SELECT n, greatest(2, CAST(round(pow(n / {TENSOR_FILL[kind]}, 1.0 / 3)) AS BIGINT)) AS domain FROM (SELECT CAST(count(*) AS DOUBLE) AS n FROM part) c) d)"
    dims = ("domain",) * 3 if shape == "lw" else (8, "wide", "wide")
    tables = [f"t{k} AS MATERIALIZED (SELECT DISTINCT {', '.join(f'{axis_sql("p_partkey", k, a, d)} AS x{a}' for a, d in enumerate(dims))} FROM part, k)" for k in numbers]
    joined = {
        "lw": "FROM t1 a JOIN t2 b ON a.x0 = b.x0 AND a.x1 = b.x1 JOIN t3 c ON c.x0 = a.x0 AND c.x1 = a.x2 AND c.x2 = b.x2 JOIN t4 d ON d.x0 = a.x1 AND d.x1 = a.x2 AND d.x2 = b.x2",
        "ct": "FROM t5 a JOIN t6 b ON a.x0 = b.x0 AND a.x1 = b.x1 JOIN t7 c ON c.x0 = a.x0 AND c.x1 = a.x2 AND c.x2 = b.x2",
    }[shape]
    return f"WITH {', '.join([sizes, *tables])} SELECT count(*) AS n {joined}"


def _words_by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed triangles of the word graph by their first word: string values, one row a word."""
    return count_by(spark, pattern("q1d"), {"e": stored_graph(spark, sf_dir, "words")}, "x")


def _blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks dealt without copies: rows of each and the Spark partitions it lies in."""
    dealt = partition_relation(graph(spark, sf_dir, "custord"), ("src", "dst"), ("src", "dst"), (4, 2), "mod").withColumn("p", F.spark_partition_id())
    return dealt.groupBy("block").agg(F.count("*").alias("n"), F.countDistinct("p").alias("parts"))


def _sorted_blocks(strategy: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Place of each row within its block, by the physical order of the partitions."""
        rows = sort_blocks(graph(spark, sf_dir, "custord"), ("src", "dst"), ("src", "dst"), (4, 2), strategy, hashing="mod")
        at = written(spark, rows.select("block", "src", "dst", F.monotonically_increasing_id().alias("at")), "sorted")
        return at.select("block", "src", "dst", F.row_number().over(Window.partitionBy("block").orderBy("at")).alias("place"))

    return run


def _reduced_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge-cover bounds of the clique and of its lifted plan's reduced query, over the graph's size."""
    n = graph(spark, sf_dir, "custord").count()
    query, order = pattern("q6"), ("x", "y", "z", "u")
    reduced = reduced_query(query.scopes, order, lift_intersections(query.scopes, order))
    rows = [("query", query.scopes), ("reduced", reduced)]
    return spark.createDataFrame([(name, "|".join(",".join(s) for s in scopes), round(edge_cover(scopes, [n] * 6)[0] / n**2, 6)) for name, scopes in rows], "name string, scopes string, bound_by_squares double")


def _prune_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which of the 28 share vectors of 64 cells both prunings keep: fixed level costs, the graph's domains."""
    e = graph(spark, sf_dir, "custord")
    sources, targets = e.select("src").distinct().count(), e.select("dst").distinct().count()
    domains, costs = (sources, min(sources, targets), targets), (1.0, 10.0, 100.0)
    return spark.createDataFrame([(*s, prune_cost(costs, s), prune_domain(domains, s, 30.0)) for s in enumerate_shares(64, 3)], "p1 int, p2 int, p3 int, by_cost boolean, by_domain boolean")


def _estimates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The optimizer's estimate of each level of directed triangles in order x, y, z."""
    query, relations = pattern("q1d"), {"e": graph(spark, sf_dir, "custord")}
    costs = estimate_total_cost(query.scopes, collect_stats(query, relations), ("x", "y", "z"))
    return spark.createDataFrame([(k, round(c, 2)) for k, c in enumerate(costs)], "level int, cost double")


def _plan_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The full planner on undirected triangles (all orders cost the same there): order, shares and cells of three graphs."""
    rows = []
    for g in ("custord", "custhub", "succ"):
        query, relations = pattern("q1d"), {"e": stored_graph(spark, sf_dir, g, True)}
        plan = plan_query(query, collect_stats(query, relations), cells=64)
        rows.append((g, "".join(plan.order), *plan.shares, int(plan.costs["effective_cells"])))
    return spark.createDataFrame(rows, "graph string, plan_order string, p1 int, p2 int, p3 int, cells int")


def _index_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Size of the packed indexes of one cell that holds everything, and the values visited at each level."""
    found = cell_profile(spark, pattern("q1d"), {"e": graph(spark, sf_dir, "custord")}, JoinPlan(("x", "y", "z"), (1, 1, 1)))
    return found.select("index_bytes", F.col("visited")[0].alias("level0"), F.col("visited")[1].alias("level1"), F.col("visited")[2].alias("level2"), "rows_in", "rows_out")


def _skew_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Skew of the rows that cells receive, by share vector."""
    out = []
    for shares in ((16, 1, 1), (4, 4, 1), (4, 2, 2)):
        rows = measured_communication(spark, pattern("q1d"), {"e": graph(spark, sf_dir, "custhub")}, JoinPlan(("x", "y", "z"), shares, hashing="mod"))
        summary = skew_summary(rows.withColumnRenamed("rows", "work"), 16)
        out.append(summary.select(F.lit("x".join(map(str, shares))).alias("shares"), F.round("max_over_mean", 4).alias("max_over_mean"), F.round("cv", 4).alias("cv"), F.round("top1_share", 4).alias("top1_share")))
    return baselines.combined(out)


def _duplication(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often first-level values are visited over all cells, against the distinct ones."""
    e = graph(spark, sf_dir, "custord")
    profile = cell_profile(spark, pattern("q1d"), {"e": e}, JoinPlan(("x", "y", "z"), (4, 2, 2), hashing="mod"))
    n = e.select("src").distinct().count()
    return duplication(profile, (n,)).select("level", "visited", "distinct", F.round("factor", 4).alias("factor"))


def _constants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Constants and repeated variables folded into filters: two-step paths into target 7 whose ends' lines agree."""
    return cube_join(spark, parse_rule("Q(x, y) :- e(x, y), e(y, 7)"), {"e": graph(spark, sf_dir, "custord")})


def _repeated(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem")
    return cube_join(spark, parse_rule("Q(x, y) :- r(x, x), s(x, y)"), {"r": lines.select("l_suppkey", "l_linenumber"), "s": lines.select("l_linenumber", "l_returnflag")})


def _unlifted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The clique without lifted intersections, under the planner's order and shares."""
    query, relations = pattern("q6"), {"e": stored_graph(spark, sf_dir, "custhub")}
    return cube_join(spark, query, relations, auto_plan(spark, query, relations, lift="none"), "count")


def _hinted_binary(hint: str) -> Query:
    return lambda spark, sf_dir: baselines.binary_join(pattern("q1d"), {"e": stored_graph(spark, sf_dir, "custhub", True)}, hint)


def _planned_variant(**options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        plan = replace(quick_plan(pattern("q1d"), 64), **options)
        return cube_join(spark, pattern("q1d"), {"e": stored_graph(spark, sf_dir, "custhub", True)}, plan, "count")

    return run


def _order_dp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether dynamic programming finds an order as cheap as the best of all (without lifts)."""
    rows = []
    for g in ("custord", "custhub"):
        for p in ("q1d", "q4", "q6"):
            query, relations = pattern(p), {"e": stored_graph(spark, sf_dir, g)}
            stats = collect_stats(query, relations)
            cost = lambda o: sum(estimate_total_cost(query.scopes, stats, o))  # noqa: E731, B023
            rows.append((g, p, bool(abs(cost(best_order_dp(query.scopes, stats)) - min(map(cost, enumerate_orders(query.head)))) < 1e-6 * cost(query.head))))
    return spark.createDataFrame(rows, "graph string, pattern string, as_cheap boolean")


def _intersect_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Common out-neighbours of each edge's ends by the registered SQL function, summed: the number of directed triangles."""
    register_functions(spark)
    lists = graph(spark, sf_dir, "custord").groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("dsts"))
    e = graph(spark, sf_dir, "custord")
    pairs = e.join(lists.withColumnRenamed("dsts", "a"), "src").join(lists.select(F.col("src").alias("dst"), F.col("dsts").alias("b")), "dst")
    return pairs.select(F.expr("sorted_intersect_size(a, b)").alias("c")).agg(F.sum("c").cast("long").alias("n"))


def _matched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed triangles by the registered table function over one partition."""
    register_functions(spark)
    graph(spark, sf_dir, "custord").createOrReplaceTempView("cubejoin_edges")
    found = spark.sql("SELECT * FROM match_pattern(TABLE(cubejoin_edges) WITH SINGLE PARTITION, 'Q(x, y, z) :- E(x, y), E(y, z), E(x, z)')")
    return found.select(F.col("binding")[0].alias("x"), F.col("binding")[1].alias("y"), F.col("binding")[2].alias("z"))


def _edge_files(fmt: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Edges written to a file format and read back with the given schema."""
        path = run_folder(spark, f"edges_{fmt}")
        write_result(graph(spark, sf_dir, "custord"), path, fmt)
        return read_edges(spark, path, fmt)

    return run


def _json_spec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A query from its JSON form."""
    return cube_join(spark, query_from_json(query_to_json(pattern("q1d"))), {"e": graph(spark, sf_dir, "custord")})


def _props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return parse_props(table(spark, sf_dir, "events")).groupBy("k").agg(F.count("*").alias("n"))


def _incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed triangles counted batch by batch, with a new state object for every batch."""
    path = run_folder(spark, "incremental")
    e = graph(spark, sf_dir, "custord").where("src % 4 = 0 or dst % 4 = 0")
    for batch in range(2):
        IncrementalCount(spark, pattern("q1d"), path)(e.where(f"(src + dst) % 2 = {batch}"), batch)
    return spark.createDataFrame([(IncrementalCount(spark, pattern("q1d"), path).total,)], "n long")


def _outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full outer join of customers and the orders' customers."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"), "c_mktsegment")
    o = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("k")).agg(F.count("*").alias("orders"))
    return relops.equi_join(c, o, ["k"], "full", "merge")


def _semi_reduced(spark: SparkSession, sf_dir: str) -> DataFrame:
    query = pattern("q1d")
    _, frames = semi_reduce(query, {"e": graph(spark, sf_dir, "custhub")})
    return baselines.combined([frames[f"r{j}"].agg(F.lit(j).alias("atom"), F.count("*").alias("n")) for j in range(3)])


def _set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = graph(spark, sf_dir, "custord"), graph(spark, sf_dir, "custhub")
    sizes = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}
    return baselines.combined([f.agg(F.lit(k).alias("op"), F.count("*").alias("n")) for k, f in sizes.items()])


def _as_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each purchase-like event with the value of the user's latest earlier-or-equal click-like event."""
    events = table(spark, sf_dir, "events")
    first = events.where("event_id % 2 = 0").select("event_id", "user_id", "ts")
    second = events.where("event_id % 2 = 1").groupBy("user_id", "ts").agg(F.max("event_id").alias("other"))
    return relops.as_of_join(first, second, ["user_id"], "ts", ["other"]).select("event_id", F.col("as_of_other").alias("other"))


def _range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts by size band."""
    parts = table(spark, sf_dir, "part").select("p_partkey", "p_size")
    bands = spark.createDataFrame([("small", 0, 10), ("middle", 5, 30), ("large", 30, 1000)], "band string, lo int, hi int")
    return relops.range_join(parts, bands, "p_size", "lo", "hi", 10).groupBy("band").agg(F.count("*").alias("n"))


def _windowed(kind: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        events = table(spark, sf_dir, "events")
        if kind == "sliding":
            return windowed_edges(events, "sliding", "2 days", "1 day")
        return windowed_edges(events, kind, gap="2 hours")

    return run


def _windowed_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import Window

    events = table(spark, sf_dir, "events")
    after = F.lead("user_id").over(Window.orderBy("ts", "event_id"))
    edges = events.select("ts", F.col("user_id").alias("src"), after.alias("dst")).where("src <> dst")
    return windowed_triangles(edges)


def _filtered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Undirected triangles once each: inequalities between variables, a constant-free head."""
    query = pattern("q1d")
    query = replace(query, filters=((("x", "y"), lambda x, y: x < y), (("y", "z"), lambda y, z: y < z)))
    return cube_join(spark, query, {"e": symmetric(graph(spark, sf_dir, "custhub"))}, quick_plan(query, CELLS), "count")


def _bag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bag semantics: weighted wedges over lines (part, supplier) with repeated rows."""
    query = parse_rule("Q(o, p, s) :- a(o, p), b(p, s)")
    lines = table(spark, sf_dir, "lineitem")
    relations = {"a": lines.select("l_linenumber", "l_partkey"), "b": lines.select("l_partkey", "l_suppkey")}
    return cube_join(spark, query, relations, replace(quick_plan(query, CELLS), semantics="bag"), "count")


def _limited(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = cube_join(spark, pattern("q1d"), {"e": stored_graph(spark, sf_dir, "copart")}, quick_plan(pattern("q1d"), CELLS), limit=100)
    return found.agg(F.count("*").alias("n"))


def _heavy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Undirected triangles with hub values in residual queries."""
    e = symmetric(graph(spark, sf_dir, "custhub"))
    return heavy_split_join(spark, pattern("q1d"), {"e": e}, quick_plan(pattern("q1d"), CELLS), threshold=150)


def _captured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triangles written as an ordinary three-way SQL join."""
    relations = {"e": graph(spark, sf_dir, "custord")}
    return run_sql(spark, "SELECT a.src AS x, a.dst AS y, b.dst AS z FROM e a, e b, e c WHERE a.dst = b.src AND c.src = a.src AND c.dst = b.dst", relations)


def _shared(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Undirected triangles over a block store: each cell reads its own blocks' files."""
    e = stored_graph(spark, sf_dir, "custhub", True)
    return cube_join(spark, pattern("q1d"), {"e": e}, replace(quick_plan(pattern("q1d"), 8), exchange="shared_files"), "count")


def _shared_filtered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The block store with a filter over variables of different atoms: undirected triangles once each."""
    query = replace(pattern("q1d"), filters=((("x", "y", "z"), lambda x, y, z: (x < y) & (y < z)),))
    return cube_join(spark, query, {"e": stored_graph(spark, sf_dir, "custhub", True)}, replace(quick_plan(query, 8), exchange="shared_files"), "count")


def _study(name: str, schema: str, pick: Callable[[dict], tuple]) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from . import studies

        return spark.createDataFrame([pick(r) for r in studies.STUDIES[name](spark, sf_dir)], schema)

    return run


_LAYOUT_SQL = """
, s AS (SELECT i.range AS s_1, j.range AS s_2 FROM range(4) i, range(2) j),
c AS (SELECT src % 4 AS s_1, dst % 2 AS s_2, count(*) AS n FROM e GROUP BY 1, 2),
g AS (SELECT CAST(s.s_1 AS INTEGER) AS s_1, CAST(s.s_2 AS INTEGER) AS s_2, coalesce(n, 0) AS n FROM s LEFT JOIN c ON s.s_1 = c.s_1 AND s.s_2 = c.s_2)
SELECT s_1, s_2, n, CAST(coalesce(sum(n) OVER (ORDER BY s_1, s_2 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM g
"""
_COMMUNICATION_SQL = """
, cells AS (SELECT x.range AS x, y.range AS y, z.range AS z FROM range(4) x, range(2) y, range(2) z),
r AS (
  SELECT x * 4 + y * 2 + z AS cell, count(*) AS c FROM cells JOIN e ON src % 4 = x AND dst % 2 = y GROUP BY 1
  UNION ALL SELECT x * 4 + y * 2 + z, count(*) FROM cells JOIN e ON src % 2 = y AND dst % 2 = z GROUP BY 1
  UNION ALL SELECT x * 4 + y * 2 + z, count(*) FROM cells JOIN e ON src % 4 = x AND dst % 2 = z GROUP BY 1
)
SELECT CAST(cell AS INTEGER) AS cell, CAST(sum(c) AS BIGINT) AS rows FROM r GROUP BY 1
"""
_COST_SQL = """
, d AS (SELECT src, count(*) AS d FROM e GROUP BY 1), s AS (SELECT count(*) AS s FROM d),
two AS (SELECT least(d, s) AS a, greatest(d, s) AS b FROM d, s),
three AS (SELECT least(p.d, q.d) AS a, greatest(p.d, q.d) AS b FROM e JOIN d p ON p.src = e.src JOIN d q ON q.src = e.dst)
"""
_EVENTS_NEXT = "SELECT ts, user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events"


def _plan_shares_sql() -> str:
    """Most even share vector that passes both prunings, of the largest number of cells that has one."""
    parts = []
    for g in ("custord", "custhub", "succ"):
        body = f"""
, k AS (SELECT count(*) AS e, count(DISTINCT src) AS s FROM e), m AS (SELECT max(c) AS m FROM (SELECT count(*) AS c FROM e GROUP BY src) q),
c AS (SELECT s, 2.0 * s AS c0, 2.0 * e * log2(1 + greatest(s, 1.0 * e / s) / least(s, 1.0 * e / s)) AS c1, 2.0 * least(power(e, 1.5), 1.0 * e * m) AS c2 FROM k, m),
v AS (SELECT b.range AS b, CAST(1 << i.range AS INTEGER) AS p1, CAST(1 << j.range AS INTEGER) AS p2, CAST(1 << (b.range - i.range - j.range) AS INTEGER) AS p3 FROM range(7) b, range(7) i, range(7) j WHERE i.range + j.range <= b.range),
f AS (SELECT v.*, p1 * 0.99 + p2 * 0.98 + p3 * 0.97 AS even, c0 * p2 * p3 + c1 * p3 + c2 AS cost FROM v, c
      WHERE c0 * p2 * p3 + c1 * p3 + c2 <= 2 * (c0 + c1 + c2) AND (p1 = 1 OR s >= 3 * p1 * log2(p1)) AND (p2 = 1 OR s >= 3 * p2 * log2(p2)) AND (p3 = 1 OR s >= 3 * p3 * log2(p3)))
SELECT '{g}' AS graph, 'xyz' AS plan_order, p1, p2, p3, CAST(1 << b AS INTEGER) AS cells FROM f ORDER BY b DESC, even, cost, p1, p2, p3 LIMIT 1"""
        parts.append(f"SELECT * FROM ({with_graph(g, body, True)}) AS t_{g}")
    return " UNION ALL ".join(parts)


def _skew_sql() -> str:
    parts = []
    for x, y, z in ((16, 1, 1), (4, 4, 1), (4, 2, 2)):
        parts.append(f"""SELECT '{x}x{y}x{z}' AS shares, round(max(n) / avg(n), 4) AS max_over_mean, round(stddev_pop(n) / avg(n), 4) AS cv, round(max(n) / sum(n), 4) AS top1_share FROM (
SELECT cell, sum(c) AS n FROM (
  SELECT x * {y * z} + y * {z} + z AS cell, count(src) AS c FROM (SELECT i.range AS x, j.range AS y, k.range AS z FROM range({x}) i, range({y}) j, range({z}) k) g LEFT JOIN e ON src % {x} = x AND dst % {y} = y GROUP BY 1
  UNION ALL SELECT x * {y * z} + y * {z} + z, count(src) FROM (SELECT i.range AS x, j.range AS y, k.range AS z FROM range({x}) i, range({y}) j, range({z}) k) g LEFT JOIN e ON src % {y} = y AND dst % {z} = z GROUP BY 1
  UNION ALL SELECT x * {y * z} + y * {z} + z, count(src) FROM (SELECT i.range AS x, j.range AS y, k.range AS z FROM range({x}) i, range({y}) j, range({z}) k) g LEFT JOIN e ON src % {x} = x AND dst % {z} = z GROUP BY 1
) q GROUP BY cell) w""")
    return with_graph("custhub", " UNION ALL ".join(parts))


def queries() -> dict[str, Query]:
    found: dict[str, Query] = {}
    for g in GRAPHS:
        found[f"q1d_{g}"] = _count("q1d", g)
        found[f"q1u_{g}"] = _count("q1d", g, True)
        found[f"q6_{g}"] = _count("q6", g)
        found[f"q8_{g}_eager"] = _factorised("eager", g)
        found[f"q2_{g}"] = _count("q2", g)
        found[f"q4_{g}"] = _count("q4", g)
        found[f"q1c_{g}"] = _count("q1c", g)
    found |= {"q1d_custord_rows": _rows("q1d", "custord"), "q6_custhub_rows": _rows("q6", "custhub"), "q4_custord_rows": _rows("q4", "custord"), "q8_custord_rows": _rows("q8", "custord"), "q1d_words_by_source": _words_by_source}
    for method in baselines.METHODS:
        if method != "cube":
            found[f"q1u_custhub_{method}"] = _method("q1d", "custhub", method, True)
            found[f"q4_custord_{method}"] = _method("q4", "custord", method)
    found |= {"q1d_custhub_expand3": _expand3, "q1d_custhub_planned": _planned}
    found |= {"q8_custord": _count("q8", "custord"), "q8_custhub": _count("q8", "custhub"), "q8_custhub_tree": _factorised("tree", "custhub"), "q8_custhub_varelim": _factorised("varelim", "custhub")}
    found |= {"lw_lineitem": _lw("count"), "lw_spurious": _lw_spurious, "ct_lineitem": _ct, "q1_trio": _trio, "q1_trio_by_segment": _trio_by_segment}
    found |= {
        "lw_lineitem_frontier": lambda s, d: frontier_join(s, parse_rule(LW_RULE), lw_relations(s, d), mode="count"),
        "ct_lineitem_frontier": lambda s, d: frontier_join(s, parse_rule(CT_RULE), ct_relations(s, d), ct_plan(CELLS), mode="count"),
        "lw_lineitem_binary": lambda s, d: baselines.binary_join(parse_rule(LW_RULE), lw_relations(s, d)),
        "ct_lineitem_binary": lambda s, d: baselines.binary_join(parse_rule(CT_RULE), ct_relations(s, d)),
    }
    found |= {"level_cost_exact": _level_costs("exact"), "level_cost_bound": _level_costs("bound"), "cost_report": _cost_report, "share_enumeration": _share_table, "order_enumeration": _orders, "replicated_cost_table": _replicated, "lift_clique": _lifts, "plan_choice": _plan_choice}
    found |= {"partition_layout_mod": _layout, "partition_layout": _layout_hashed, "communication_rows_mod": _communication, "cell_profile": _profile, "skew_study": _skew_study}
    found |= {
        "trie_levels_custord": lambda s, d: formats.trie_levels(graph(s, d, "custord")),
        "coo_custord": lambda s, d: formats.to_coo(graph(s, d, "custord")),
        "csr_custord": lambda s, d: formats.to_csr(graph(s, d, "custord")).select("src", "lo", "hi"),
        "csc_custord": lambda s, d: formats.to_csc(graph(s, d, "custord")).select("dst", "lo", "hi"),
        "dcsr_custord": lambda s, d: formats.to_dcsr(graph(s, d, "custord")).select("src", F.size("dsts").cast("long").alias("n")),
    }
    found |= {
        "graph_stats": _graph_stats,
        "vertex_triangles_custhub": lambda s, d: relops.vertex_triangles(graph(s, d, "custhub")),
        "clustering_top10": lambda s, d: relops.top_k(relops.clustering(graph(s, d, "custhub")).select("v", "degree", "triangles", F.round("coefficient", 6).alias("coefficient")), 10, F.desc("triangles"), F.col("v")),
        "degree_top10": lambda s, d: relops.top_k(relops.degrees(graph(s, d, "custhub")), 10, F.desc("in_degree"), F.col("v")),
        "oriented_triangles_custhub": lambda s, d: cube_join(s, pattern("q1d"), {"e": factorize.orient_by_degree(graph(s, d, "custhub"))}, mode="count"),
        "path_count_custhub": lambda s, d: factorize.degree_product_count(graph(s, d, "custhub")),
    }
    found |= {"semi_reduced_rows": _semi_reduced, "set_ops_edges": _set_ops, "asof_events": _as_of, "range_join_parts": _range, "filtered_triangles": _filtered, "bag_wedges": _bag, "limited_triangles": _limited}
    found |= {
        "q1u_custhub_heavysplit": _heavy,
        "sql_triangles_custord": _captured,
        "q1u_custhub_sharedfiles": _shared,
        "study_orders": _study("orders", "o string, estimate double, work long, chosen boolean", lambda r: (r["order"], float(r["estimate"]), int(r["work"] or 0), r["chosen"])),
        "study_rewriting": _study("rewriting", "query string, plan string, lifts int, comparisons long, index_bytes long", lambda r: (r["query"], r["plan"], r["lifts"], r["comparisons"], r["index_bytes"])),
        "study_searches": _study("searches", "graph string, search string, comparisons long", lambda r: (r["graph"], r["search"], r["comparisons"])),
    }
    for g in ("custhub", "custord"):
        for kind in ("td", "td_lookup", "td_lookup_eager", "lazyhash"):
            found[f"q8_{g}_{kind}"] = _factorised(kind, g)
    for g in ("copart", "hubs"):
        found[f"q8_{g}_td_lookup_eager"] = _factorised("td_lookup_eager", g)
        found[f"q8_{g}_varelim"] = _factorised("varelim", g)
    found |= {"blocks_mod": _blocks, "sorted_blocks_block": _sorted_blocks("block"), "sorted_blocks_global": _sorted_blocks("global"), "reduced_bound": _reduced_bound, "prune_table": _prune_table}
    found |= {"level_cost_estimate": _estimates, "plan_shares": _plan_shares, "index_bytes": _index_bytes, "skew_rows_mod": _skew_rows, "duplication_mod": _duplication, "order_dp": _order_dp}
    found |= {"constant_paths": _constants, "repeated_variable": _repeated, "intersect_sizes": _intersect_sizes, "match_pattern_triangles": _matched, "json_spec_triangles": _json_spec, "event_props": _props, "incremental_triangles": _incremental, "outer_join_customers": _outer}
    found |= {f"q1u_custhub_binary_{h}": _hinted_binary(h) for h in ("broadcast", "merge", "shuffle_hash")}
    found |= {"q6_custhub_plainlevels": _unlifted, "q1u_custhub_fewtasks": _planned_variant(tasks=4), "q1u_custhub_grouped": _planned_variant(executor="grouped"), "q1u_custhub_unfiltered": _planned_variant(search="unfiltered"), "q1u_custhub_sharedfiles_filtered": _shared_filtered}
    found |= {f"edge_files_{f}": _edge_files(f) for f in ("csv", "json", "orc", "parquet")}
    found |= {f"tensor_{kind}_{shape}": _tensor(kind, shape) for kind in ("dense", "sparse") for shape in ("lw", "ct")}
    found |= {f"windowed_edges_{k}": _windowed(k) for k in ("tumbling", "sliding", "session")}
    found |= {"windowed_triangles": _windowed_triangles}
    return found


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for g in GRAPHS:
        out[f"q1d_{g}"] = with_graph(g, COUNT_SQL["q1d"])
        out[f"q1u_{g}"] = with_graph(g, COUNT_SQL["q1d"], True)
        out[f"q6_{g}"] = with_graph(g, COUNT_SQL["q6"])
        out[f"q8_{g}_eager"] = with_graph(g, COUNT_SQL["q8"])
        out[f"q2_{g}"] = with_graph(g, COUNT_SQL["q2"])
        out[f"q4_{g}"] = with_graph(g, COUNT_SQL["q4"])
        out[f"q1c_{g}"] = with_graph(g, COUNT_SQL["q1c"])
    out["q1d_custord_rows"] = with_graph("custord", TRIANGLES_SQL)
    out["q1d_words_by_source"] = with_graph("words", f"SELECT x, count(*) AS c FROM ({TRIANGLES_SQL}) t GROUP BY 1")
    out["q6_custhub_rows"] = with_graph("custhub", f", t AS MATERIALIZED ({TRIANGLES_SQL}) SELECT a.x, a.y, a.z, b.z AS u FROM t a JOIN t b ON a.x = b.x AND a.y = b.y JOIN e c ON c.src = a.z AND c.dst = b.z")
    out["q4_custord_rows"] = with_graph("custord", f", t AS MATERIALIZED ({TRIANGLES_SQL}) SELECT a.x, a.y, a.z, b.z AS u FROM t a JOIN t b ON a.y = b.x AND a.z = b.y")
    out["q8_custord_rows"] = with_graph("custord", f", t AS MATERIALIZED ({TRIANGLES_SQL}) SELECT a.x, a.y, a.z, b.y AS u, b.z AS v FROM t a JOIN t b ON a.z = b.x")
    for method in baselines.METHODS:
        if method != "cube":
            out[f"q1u_custhub_{method}"] = out["q1u_custhub"]
            out[f"q4_custord_{method}"] = out["q4_custord"]
    out["q1u_custhub_heavysplit"] = out["q1u_custhub_sharedfiles"] = out["q1u_custhub"]
    out["sql_triangles_custord"] = out["q1d_custord_rows"]
    out["q1d_custhub_expand3"] = out["q1d_custhub_planned"] = out["q1d_custhub"]
    out["q8_custord"] = out["q8_custord_eager"]
    out["q8_custhub"] = out["q8_custhub_tree"] = out["q8_custhub_varelim"] = out["q8_custhub_eager"]
    for g in ("custhub", "custord", "copart", "hubs"):
        for kind in ("td", "td_lookup", "td_lookup_eager", "lazyhash", "varelim"):
            out[f"q8_{g}_{kind}"] = out[f"q8_{g}_eager"]
    out = {k: v for k, v in out.items() if k in queries()}
    out["blocks_mod"] = with_graph("custord", "SELECT CAST(src % 4 * 2 + dst % 2 AS INTEGER) AS block, count(*) AS n, CAST(1 AS BIGINT) AS parts FROM e GROUP BY 1")
    out["sorted_blocks_block"] = out["sorted_blocks_global"] = with_graph("custord", "SELECT CAST(src % 4 * 2 + dst % 2 AS INTEGER) AS block, src, dst, CAST(row_number() OVER (PARTITION BY src % 4, dst % 2 ORDER BY src, dst) AS INTEGER) AS place FROM e")
    out["reduced_bound"] = "SELECT * FROM (VALUES ('query', 'x,y|x,z|x,u|y,z|y,u|z,u', CAST(1.0 AS DOUBLE)), ('reduced', 'x|x,z|x,u|y|y,u|z', CAST(1.0 AS DOUBLE))) t(name, scopes, bound_by_squares)"
    six = "SELECT CAST(1 << i.range AS INTEGER) AS p1, CAST(1 << j.range AS INTEGER) AS p2, CAST(1 << (6 - i.range - j.range) AS INTEGER) AS p3 FROM range(7) i, range(7) j WHERE i.range + j.range <= 6"
    out["prune_table"] = with_graph("custord", f", d AS (SELECT count(DISTINCT src) AS s, count(DISTINCT dst) AS t FROM e) SELECT p1, p2, p3, 1.0 * p2 * p3 + 10.0 * p3 + 100.0 <= 222.0 AS by_cost, (p1 = 1 OR s >= 30 * p1 * log2(p1)) AND (p2 = 1 OR least(s, t) >= 30 * p2 * log2(p2)) AND (p3 = 1 OR t >= 30 * p3 * log2(p3)) AS by_domain FROM ({six}) v, d")
    out["level_cost_estimate"] = with_graph("custord", ", k AS (SELECT count(*) AS e, count(DISTINCT src) AS s FROM e), m AS (SELECT max(c) AS m FROM (SELECT count(*) AS c FROM e GROUP BY src) q) SELECT 0 AS level, round(2.0 * s, 2) AS cost FROM k UNION ALL SELECT 1, round(2.0 * e * log2(1 + greatest(s, 1.0 * e / s) / least(s, 1.0 * e / s)), 2) FROM k UNION ALL SELECT 2, round(2.0 * least(power(e, 1.5), 1.0 * e * m), 2) FROM k, m")
    out["plan_shares"] = _plan_shares_sql()
    out["index_bytes"] = with_graph("custord", ", k AS (SELECT count(*) AS e, count(DISTINCT src) AS s FROM e), d AS (SELECT src, count(*) AS d FROM e GROUP BY 1) SELECT CAST(3 * (16 * s + 8 * e + 8) AS BIGINT) AS index_bytes, s AS level0, (SELECT CAST(sum(least(d, s)) AS BIGINT) FROM d) AS level1, (SELECT CAST(sum(least(p.d, q.d)) AS BIGINT) FROM e JOIN d p ON p.src = e.src JOIN d q ON q.src = e.dst) AS level2, 3 * e AS rows_in, (SELECT count(*) FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst) AS rows_out FROM k")
    out["skew_rows_mod"] = _skew_sql()
    out["duplication_mod"] = with_graph("custord", ", g AS (SELECT x.range AS x, y.range AS y, z.range AS z FROM range(4) x, range(2) y, range(2) z), a AS (SELECT src % 4 AS x, dst % 2 AS t, count(DISTINCT src) AS c FROM e GROUP BY 1, 2), b AS (SELECT src % 2 AS y, dst % 2 AS z, count(*) AS c FROM e GROUP BY 1, 2), v AS (SELECT CAST(sum(least(p.c, q.c)) AS BIGINT) AS visited FROM g JOIN a p ON p.x = g.x AND p.t = g.y JOIN a q ON q.x = g.x AND q.t = g.z JOIN b ON b.y = g.y AND b.z = g.z), d AS (SELECT count(DISTINCT src) AS d FROM e) SELECT 0 AS level, visited, d AS distinct, round(visited / d, 4) AS factor FROM v, d")
    out["order_dp"] = "SELECT g AS graph, p AS pattern, true AS as_cheap FROM (VALUES ('custord'), ('custhub')) a(g), (VALUES ('q1d'), ('q4'), ('q6')) b(p)"
    out["constant_paths"] = with_graph("custord", "SELECT a.src AS x, a.dst AS y FROM e a JOIN e b ON a.dst = b.src WHERE b.dst = 7")
    out["repeated_variable"] = "SELECT DISTINCT a.l_suppkey AS x, b.l_returnflag AS y FROM lineitem a JOIN lineitem b ON a.l_suppkey = b.l_linenumber WHERE a.l_suppkey = a.l_linenumber"
    out["intersect_sizes"] = out["q1d_custord"]
    out["match_pattern_triangles"] = out["json_spec_triangles"] = out["q1d_custord_rows"]
    out["event_props"] = "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1"
    out["incremental_triangles"] = with_graph("custord", f", h AS (SELECT * FROM e WHERE src % 4 = 0 OR dst % 4 = 0) SELECT count(*) AS n FROM h a JOIN h b ON a.dst = b.src JOIN h c ON c.src = a.src AND c.dst = b.dst")
    out["outer_join_customers"] = "SELECT coalesce(c_custkey, k) AS k, c_mktsegment, orders FROM customer FULL JOIN (SELECT o_custkey AS k, count(*) AS orders FROM orders GROUP BY 1) o ON o.k = c_custkey"
    for name in ("binary_broadcast", "binary_merge", "binary_shuffle_hash", "fewtasks", "grouped", "unfiltered"):
        out[f"q1u_custhub_{name}"] = out["q1u_custhub"]
    out["q6_custhub_plainlevels"] = out["q6_custhub"]
    for f in ("csv", "json", "orc", "parquet"):
        out[f"edge_files_{f}"] = with_graph("custord", "SELECT src, dst FROM e")
    for kind in ("dense", "sparse"):
        for shape in ("lw", "ct"):
            out[f"tensor_{kind}_{shape}"] = _tensor_sql(kind, shape)
    out["semi_reduced_rows"] = with_graph("custhub", "SELECT 0 AS atom, count(*) AS n FROM e WHERE dst IN (SELECT src FROM e) AND src IN (SELECT src FROM e) UNION ALL SELECT 1, count(*) FROM e WHERE src IN (SELECT dst FROM e) AND dst IN (SELECT dst FROM e) UNION ALL SELECT 2, count(*) FROM e WHERE src IN (SELECT src FROM e) AND dst IN (SELECT dst FROM e)")
    out["lw_lineitem"] = out["lw_lineitem_frontier"] = out["lw_lineitem_binary"] = with_fact(f"SELECT count(*) AS n {LW_JOIN_SQL}")
    out["ct_lineitem"] = out["ct_lineitem_frontier"] = out["ct_lineitem_binary"] = with_fact(f"SELECT count(*) AS n {CT_JOIN_SQL}")
    out["lw_spurious"] = with_fact(f"SELECT count(*) AS n FROM (SELECT a.p, a.s, a.l, b.q {LW_JOIN_SQL} EXCEPT SELECT p, s, l, q FROM f) t")
    out["q1_trio"] = with_fact(f"SELECT count(*) AS n {TRIO_JOIN_SQL}")
    out["q1_trio_by_segment"] = with_fact(f"SELECT c_mktsegment, count(*) AS n FROM (SELECT a.c {TRIO_JOIN_SQL}) t JOIN customer ON c_custkey = t.c GROUP BY ROLLUP (c_mktsegment)")
    out["level_cost_exact"] = with_graph("custord", _COST_SQL + "SELECT 0 AS level, round(2.0 * s, 2) AS cost FROM s UNION ALL SELECT 1, round(sum(2 * a * log2(1 + b / a)), 2) FROM two UNION ALL SELECT 2, round(sum(2 * a * log2(1 + b / a)), 2) FROM three")
    out["level_cost_bound"] = with_graph("custord", _COST_SQL + "SELECT 0 AS level, round(2.0 * s, 2) AS cost FROM s UNION ALL SELECT 1, round(2 * sum(a) * log2(1 + sum(b) / sum(a)), 2) FROM two UNION ALL SELECT 2, round(2 * sum(a) * log2(1 + sum(b) / sum(a)), 2) FROM three")
    powers = "SELECT CAST(1 << i.range AS INTEGER) AS p1, CAST(1 << j.range AS INTEGER) AS p2, CAST(1 << ({b} - i.range - j.range) AS INTEGER) AS p3 FROM range({b} + 1) i, range({b} + 1) j WHERE i.range + j.range <= {b}"
    out["share_enumeration"] = with_graph("custord", f", k AS (SELECT count(*) AS e FROM e) SELECT p1, p2, p3, CAST(round(p1 * 0.99 + p2 * 0.98 + p3 * 0.97, 4) AS DOUBLE) AS evenness, e / CAST(p1 * p2 AS DOUBLE) + e / CAST(p2 * p3 AS DOUBLE) + e / CAST(p1 * p3 AS DOUBLE) AS rows_per_cell FROM ({powers.format(b=10)}) t, k")
    out["replicated_cost_table"] = with_graph("custord", f", k AS (SELECT count(*) AS e, count(DISTINCT src) AS s FROM e), m AS (SELECT max(c) AS m FROM (SELECT count(*) AS c FROM e GROUP BY src) q), c AS (SELECT 2.0 * s AS c0, 2.0 * e * log2(1 + greatest(s, 1.0 * e / s) / least(s, 1.0 * e / s)) AS c1, 2.0 * least(power(e, 1.5), 1.0 * e * m) AS c2 FROM k, m) SELECT p1, p2, p3, round(c0 * p2 * p3 + c1 * p3 + c2, 2) AS cost FROM ({powers.format(b=6)}) t, c")
    out["order_enumeration"] = with_graph("custord", ", s AS (SELECT count(DISTINCT src) AS s FROM e), d AS (SELECT count(DISTINCT dst) AS d FROM e), b AS (SELECT count(DISTINCT src) AS b FROM e WHERE src IN (SELECT dst FROM e)), v(c, n) AS (SELECT 'x', s FROM s UNION ALL SELECT 'y', b FROM b UNION ALL SELECT 'z', b FROM b UNION ALL SELECT 'u', d FROM d) SELECT a.c || b.c || d.c || e.c AS o, a.n AS first_values FROM v a, v b, v d, v e WHERE a.c <> b.c AND a.c <> d.c AND a.c <> e.c AND b.c <> d.c AND b.c <> e.c AND d.c <> e.c")
    out["lift_clique"] = with_graph("custord", f"SELECT 1 AS level, 0 AS depth, '3,4' AS inputs, count(DISTINCT src) AS kept_values FROM e UNION ALL SELECT 2, 1, '1,5', count(*) FROM e WHERE dst IN (SELECT src FROM e) UNION ALL SELECT 3, 2, '2,4', count(*) FROM ({TRIANGLES_SQL}) t")
    out["partition_layout_mod"] = with_graph("custord", _LAYOUT_SQL)
    out["communication_rows_mod"] = with_graph("custord", _COMMUNICATION_SQL)
    out["trie_levels_custord"] = with_graph("custord", ", d AS (SELECT src, count(*) AS c FROM e GROUP BY 1) SELECT 0 AS level, row_number() OVER (ORDER BY src) - 1 AS pos, src AS value, CAST(coalesce(sum(c) OVER (ORDER BY src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS lo, CAST(sum(c) OVER (ORDER BY src) AS BIGINT) AS hi FROM d UNION ALL SELECT 1, row_number() OVER (ORDER BY src, dst) - 1, dst, NULL, NULL FROM e")
    out["coo_custord"] = with_graph("custord", "SELECT src, dst FROM e")
    for name, key in (("csr", "src"), ("csc", "dst")):
        out[f"{name}_custord"] = with_graph("custord", f", d AS (SELECT {key}, count(*) AS c FROM e GROUP BY 1) SELECT {key}, CAST(sum(c) OVER (ORDER BY {key}) - c AS BIGINT) AS lo, CAST(sum(c) OVER (ORDER BY {key}) AS BIGINT) AS hi FROM d")
    out["dcsr_custord"] = with_graph("custord", "SELECT src, count(*) AS n FROM e GROUP BY 1")
    stats = []
    for g in GRAPHS:
        stats.append(f"SELECT '{g}' AS graph, (SELECT count(*) FROM {g}) AS edges, (SELECT count(*) FROM (SELECT src FROM {g} UNION SELECT dst FROM {g}) t) AS nodes, (SELECT max(c) FROM (SELECT count(*) AS c FROM {g} GROUP BY src) t) AS max_out, (SELECT max(c) FROM (SELECT count(*) AS c FROM {g} GROUP BY dst) t) AS max_in")
    from .workloads import GRAPH_SQL

    out["graph_stats"] = "WITH " + ", ".join(f"{g} AS MATERIALIZED ({GRAPH_SQL[g]})" for g in GRAPHS) + " " + " UNION ALL ".join(stats)
    corners = f", t AS MATERIALIZED (SELECT DISTINCT list_sort([x, y, z]) AS k FROM ({TRIANGLES_SQL}) q), c AS (SELECT unnest(k) AS v FROM t), k AS (SELECT v, count(*) AS triangles FROM c GROUP BY 1)"
    out["vertex_triangles_custhub"] = with_graph("custhub", f"{corners} SELECT v, triangles FROM k", True)
    out["clustering_top10"] = with_graph("custhub", f"{corners}, g AS (SELECT src AS v, count(*) AS degree FROM e GROUP BY 1) SELECT v, degree, coalesce(triangles, 0) AS triangles, round(CASE WHEN degree > 1 THEN 2.0 * coalesce(triangles, 0) / (degree * (degree - 1)) ELSE 0.0 END, 6) AS coefficient FROM g LEFT JOIN k USING (v) ORDER BY triangles DESC, v LIMIT 10", True)
    out["degree_top10"] = with_graph("custhub", ", n AS (SELECT src AS v FROM e UNION SELECT dst FROM e) SELECT v, (SELECT count(*) FROM e WHERE src = v) AS out_degree, (SELECT count(*) FROM e WHERE dst = v) AS in_degree FROM n ORDER BY in_degree DESC, v LIMIT 10")
    out["oriented_triangles_custhub"] = with_graph("custhub", f"SELECT count(*) // 6 AS n FROM ({TRIANGLES_SQL}) t", True)
    out["filtered_triangles"] = out["q1u_custhub_sharedfiles_filtered"] = out["oriented_triangles_custhub"]
    out["path_count_custhub"] = with_graph("custhub", "SELECT count(*) AS n FROM e a JOIN e b ON a.dst = b.src")
    out["set_ops_edges"] = f"WITH a AS MATERIALIZED ({GRAPH_SQL['custord']}), b AS MATERIALIZED ({GRAPH_SQL['custhub']}) SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) t UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) t UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) t"
    out["asof_events"] = "WITH l AS (SELECT event_id, user_id, ts FROM events WHERE event_id % 2 = 0), r AS (SELECT user_id, ts, max(event_id) AS other FROM events WHERE event_id % 2 = 1 GROUP BY 1, 2) SELECT event_id, other FROM l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts"
    out["range_join_parts"] = "SELECT band, count(*) AS n FROM part JOIN (VALUES ('small', 0, 10), ('middle', 5, 30), ('large', 30, 1000)) b(band, lo, hi) ON p_size >= lo AND p_size < hi GROUP BY 1"
    out["bag_wedges"] = "SELECT count(*) AS n FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey"
    out["limited_triangles"] = with_graph("copart", f"SELECT least(count(*), 100) AS n FROM ({TRIANGLES_SQL}) t")
    out["windowed_edges_tumbling"] = "SELECT date_trunc('day', ts) AS lo, date_trunc('day', ts) + INTERVAL 1 DAY AS hi, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1, 2"
    out["windowed_edges_sliding"] = "SELECT lo, lo + INTERVAL 2 DAY AS hi, count(*) AS n, count(DISTINCT user_id) AS users FROM (SELECT date_trunc('day', ts) - k.range * INTERVAL 1 DAY AS lo, user_id FROM events, range(2) k) t GROUP BY 1, 2"
    out["windowed_edges_session"] = "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS b FROM events), s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT min(ts) AS lo, max(ts) + INTERVAL 2 HOUR AS hi, user_id, count(*) AS n FROM s GROUP BY user_id, k"
    out["windowed_triangles"] = f"WITH e AS MATERIALIZED (SELECT DISTINCT date_trunc('day', ts) AS w, src, dst FROM ({_EVENTS_NEXT}) q WHERE src <> dst) SELECT a.w AS lo, count(*) AS n FROM e a JOIN e b ON a.w = b.w AND a.dst = b.src JOIN e c ON c.w = a.w AND c.src = a.src AND c.dst = b.dst GROUP BY 1"
    return out
