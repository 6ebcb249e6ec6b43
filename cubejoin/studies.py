"""The experiments as functions that return rows, and a small command line.

``python -m cubejoin.studies orders --sf /root/testdata/sf0.01``

Counters (values visited, comparisons) do not depend on the machine; seconds do.
"""

from __future__ import annotations

import argparse
import json
import os
import subprocess
import sys
import time
from dataclasses import replace

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .metrics import bench, cell_work, index_size, phase_times, share_study, skew_summary
from .operators import baselines, factorize
from .operators.executor import cell_profile, cell_profiles, cube_join
from .plans.cost import cost_report, exact_level_costs, replicated_cost
from .plans.planner import JoinPlan, enumerate_orders, enumerate_shares, plan_query, quick_plan
from .plans.rewrite import lift_intersections
from .plans.stats import collect_stats
from .query import parse_rule
from .workloads import CT_RULE, GRAPHS, LW_RULE, ct_relations, graph, lw_relations, pattern, symmetric


def _edges(spark: SparkSession, sf_dir: str, name: str):
    return {"e": graph(spark, sf_dir, name).persist()}


def methods(spark: SparkSession, sf_dir: str, graphs=("custord", "custhub", "succ"), patterns=("q1d", "q2", "q4", "q6"), repeats: int = 1) -> list[dict]:
    """Seconds of every method on every pattern and graph."""
    out = []
    for g in graphs:
        relations = _edges(spark, sf_dir, g)
        for p in patterns:
            for name, method in baselines.METHODS.items():
                got = bench(lambda m=method, q=p, r=relations: m(spark, pattern(q), r, "count").collect(), repeats, 0)
                out.append({"graph": g, "pattern": p, "method": name, "seconds": got["seconds"]})
    return out


def skew(spark: SparkSession, sf_dir: str, graphs=("words", "hubs", "copart"), vectors=((64, 1, 1), (1, 64, 1), (16, 4, 1), (8, 8, 1), (4, 4, 4))) -> list[dict]:
    """Cell skew by share vector on undirected triangles."""
    out = []
    for g in graphs:
        e = symmetric(graph(spark, sf_dir, g)).persist()
        for shares in vectors:
            profile = cell_profile(spark, pattern("q1d"), {"e": e}, JoinPlan(("x", "y", "z"), shares))
            out.append({"graph": g, "shares": shares, **skew_summary(profile, 64).first().asDict()})
    return out


def orders(spark: SparkSession, sf_dir: str, g: str = "custhub", p: str = "q4", shares_cells: int = 4) -> list[dict]:
    """Estimated, exact and measured work of all orders, and whether the planner chose it."""
    relations = _edges(spark, sf_dir, g)
    query = pattern(p)
    stats = collect_stats(query, relations)
    chosen = plan_query(query, stats, cells=shares_cells, lift="none").order
    out = []
    for o in enumerate_orders(query.head):
        plan = plan_query(query, stats, cells=shares_cells, lift="none", order_hint=o)
        work = cell_work(cell_profile(spark, query, relations, replace(plan, shares=(1,) * len(o)))).agg(F.sum("work")).first()[0]
        out.append({"order": "".join(o), "estimate": plan.costs["total"], "work": work, "chosen": o == chosen})
    return sorted(out, key=lambda r: r["work"] or 0)


def shares(spark: SparkSession, sf_dir: str, g: str = "custord", cells: int = 64) -> list[dict]:
    """Replicated cost and measured work of all share vectors of undirected triangles."""
    e = symmetric(graph(spark, sf_dir, g)).persist()
    query = pattern("q1d")
    exact = [c.exact for c in exact_level_costs(spark, query, {"e": e}, ("x", "y", "z"))]
    plans = [JoinPlan(("x", "y", "z"), s) for s in enumerate_shares(cells, 3)]
    rows = share_study(spark, query, {"e": e}, plans)
    return [{**r, "replicated_cost": replicated_cost(exact, r["shares"])} for r in rows]


def rewriting(spark: SparkSession, sf_dir: str, g: str = "succ") -> list[dict]:
    """Comparisons with and without lifting, and dictionaries against the packed index."""
    relations = _edges(spark, sf_dir, g)
    out = []
    cases = [(p, pattern(p), relations) for p in ("q1d", "q4", "q6")] + [("lw", parse_rule(LW_RULE), lw_relations(spark, sf_dir)), ("ct", parse_rule(CT_RULE), ct_relations(spark, sf_dir))]
    for name, query, rels in cases:
        base = quick_plan(query, 4, lift="none")
        lifted = replace(base, lifts=tuple(lift_intersections([tuple(sorted(s, key=base.order.index)) for s in query.scopes], base.order)))
        for label, plan, profile in zip(("plain", "lifted"), (base, lifted), cell_profiles(spark, query, rels, [base, lifted]), strict=True):
            got = profile.agg(F.sum("comparisons").alias("comparisons"), F.sum("seconds").alias("seconds"), F.sum("index_bytes").alias("index_bytes")).first()
            out.append({"query": name, "plan": label, "lifts": len(plan.lifts), **got.asDict()})
    return out


def searches(spark: SparkSession, sf_dir: str, graphs=("succ", "custhub")) -> list[dict]:
    """Comparisons of each search on directed triangles (scalar kernel)."""
    out = []
    for g in graphs:
        relations = _edges(spark, sf_dir, g)
        for search in ("linear", "stride", "gallop", "binary", "adaptive"):
            plan = replace(quick_plan(pattern("q1d"), 4, lift="none"), search=search)
            got = cell_profile(spark, pattern("q1d"), relations, plan).agg(F.sum("comparisons").alias("comparisons"), F.sum("seconds").alias("seconds")).first()
            out.append({"graph": g, "search": search, **got.asDict()})
    return out


def index(spark: SparkSession, sf_dir: str, graphs=tuple(g for g in GRAPHS if g != "words")) -> list[dict]:
    """Index size against the rows', and preprocessing's share of the time."""
    out = []
    for g in graphs:
        e = graph(spark, sf_dir, g).persist()
        times = phase_times(spark, pattern("q1d"), {"e": e}, quick_plan(pattern("q1d")))
        out.append({"graph": g, **index_size(e), **times})
    return out


def factorised(spark: SparkSession, sf_dir: str, g: str = "custhub") -> list[dict]:
    """The two-triangle query plain, decomposed, with eliminated variables, and with eager counts."""
    relations = _edges(spark, sf_dir, g)
    query = pattern("q8")
    runs = {
        "plain": lambda: cube_join(spark, query, relations, mode="count"),
        "decomposed": lambda: factorize.decomposed_join(spark, query, relations, "z"),
        "eliminated": lambda: factorize.eliminate_variables(spark, query, relations, "z"),
        "eager": lambda: factorize.eager_count(spark, query, relations, "z"),
        "lookup": lambda: baselines.lookup_expand_join(query, relations),
    }
    out = []
    for name, run in runs.items():
        began = time.perf_counter()
        n = run().first().n
        out.append({"variant": name, "n": n, "seconds": time.perf_counter() - began})
    return out


def estimator(spark: SparkSession, sf_dir: str, graphs=("custord", "custhub", "succ", "hubs", "copart")) -> list[dict]:
    """Exact cost, bound and estimate per level of directed triangles."""
    out = []
    for g in graphs:
        relations = _edges(spark, sf_dir, g)
        query = pattern("q1d")
        out += [{"graph": g, **r} for r in cost_report(spark, query, relations, ("x", "y", "z"), collect_stats(query, relations))]
    return out


def scaling_sweep(sf_dir: str, cores=(1, 2, 4, 8), queries=("q1u_copart", "q6_copart", "lw_lineitem", "ct_lineitem")) -> list[dict]:
    """Seconds and speedup by cores, each in a process of its own."""
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    found: dict[int, dict] = {}
    for c in cores:
        env = os.environ | {"BENCH_SF_DIR": sf_dir, "BENCH_CPUS": str(c)}
        done = subprocess.run([sys.executable, os.path.join(root, "bench.py"), *queries], env=env, capture_output=True, text=True, check=True)
        found[c] = json.loads(done.stdout.strip().splitlines()[-1])["queries"]
    return [{"query": q, "cores": c, "seconds": found[c][q], "speedup": found[cores[0]][q] / found[c][q]} for q in queries for c in cores]


STUDIES = {f.__name__: f for f in (methods, skew, orders, shares, rewriting, searches, index, factorised, estimator)}


def main() -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    parser.add_argument("study", choices=[*STUDIES, "scaling"])
    parser.add_argument("--sf", default="/root/testdata/sf0.01")
    parser.add_argument("--cpus", default="8")
    args = parser.parse_args()
    if args.study == "scaling":
        rows = scaling_sweep(args.sf)
    else:
        spark = SparkSession.builder.master(f"local[{args.cpus}]").config("spark.sql.shuffle.partitions", args.cpus).config("spark.ui.enabled", "false").config("spark.driver.memory", "6g").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
        spark.sparkContext.setLogLevel("ERROR")
        rows = STUDIES[args.study](spark, args.sf)
    for row in rows:
        print(json.dumps(row, default=str))


if __name__ == "__main__":
    main()
