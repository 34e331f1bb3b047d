"""The experiments on the given tables: who wins, by how much, how it scales, how good the chosen plan is, how precise
the estimates are.

``python -m huecount.experiments [--out FILE] [--sf DIR] [--cores 1,4] [--repeats 3]`` runs them, each degree of
parallelism in a process of its own, and prints the figures; ``record`` and the functions below it are what it is
made of and can be used in any session. Work is measured in seconds and, independent of the machine, in candidate rows:
those that the joins produce before their tests (the operations of the projection functions).
"""

from __future__ import annotations

import argparse
import json
import subprocess
import sys
import time
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from huecount.functions import metrics
from huecount.functions.coloring import Coloring
from huecount.operators import estimate, solve
from huecount.operators.graph import DataGraph
from huecount.operators.joins import Context
from huecount.plans.plan import Plan, enumerate_plans, plan_for
from huecount.plans.query import CATALOGUE, QueryGraph
from huecount.sources import generators
from huecount.sources.views import graph_view

ROW = "graph string, query string, strategy string, ranks int, plan int, repeat int, seconds double, cnt double, candidates long, max_load long, avg_load double, status string"


def one_run(g: DataGraph, q: QueryGraph, strategy: str, plan: Plan | None = None) -> tuple[float, float | None, str]:
    """Seconds, colourful matches, and 'ok' or the name of what went wrong."""
    got: list[float] = []

    def make() -> DataFrame:
        df = solve.count_colorful(g, q, Coloring(q.k, "affine"), strategy, plan)
        got.append(float(df.first()["cnt"]))
        return g.spark.range(0)

    seconds, status = metrics.timed(make)
    return seconds, got[0] if got else None, status


def load_of(g: DataGraph, q: QueryGraph, strategy: str, plan: Plan | None = None) -> tuple[int, int, float]:
    """Candidate rows of all partitions, of the fullest one, and in the mean."""
    row = solve.cut(metrics.load_summary(solve.load(g, q, Coloring(q.k, "affine"), strategy, plan)), "load").first()
    return int(row["candidates"] or 0), int(row["max_load"] or 0), float(row["avg_load"] or 0)


def best_by_cost(g: DataGraph, q: QueryGraph, strategy: str = "boundary", metric: str = "ops") -> tuple[Plan, list[tuple[int, float]]]:
    """The plan that costs least when every plan is run, and the cost of each. metric: ops (candidate rows) or
    seconds."""
    if metric not in ("ops", "seconds"):
        raise ValueError(f"no metric {metric!r}")
    plans, costs = enumerate_plans(q), []
    for i, p in enumerate(plans):
        costs.append((i, float(load_of(g, q, strategy, p)[0]) if metric == "ops" else one_run(g, q, strategy, p)[0]))
    return plans[min(costs, key=lambda c: (c[1], c[0]))[0]], costs


def loads(g: DataGraph, queries: Iterable[str], strategies=solve.STRATEGIES, best_base: bool = False) -> list[tuple]:
    """Rows of load per query and strategy. best_base: the boundary split gets its best plan, as the baseline of the
    experiments does; the degree order always takes the one that the heuristic chooses."""
    rows = []
    for name in queries:
        q = CATALOGUE[name]
        if solve.impossible(g, q):
            continue
        for s in strategies:
            plan = best_by_cost(g, q, s)[0] if best_base and s == "boundary" else plan_for(q)
            rows.append((g.name, name, s, *load_of(g, q, s, plan)))
    return rows


LOAD = "graph string, query string, strategy string, candidates long, max_load long, avg_load double"


def load_table(spark: SparkSession, d: str, views: Iterable[str], queries: Iterable[str], **options) -> DataFrame:
    rows = [r for v in views for r in loads(graph_view(spark, d, v), queries, **options)]
    return spark.createDataFrame(rows, LOAD)


def improvement_by_load(table: DataFrame) -> DataFrame:
    """graph, query, factor and max_factor: the boundary split's candidates over those of the degree order, in all
    and on the fullest partition."""
    wide = table.groupBy("graph", "query").pivot("strategy", ["boundary", "degree"]).agg(F.max("candidates").alias("c"), F.max("max_load").alias("m"))
    return wide.select("graph", "query", F.try_divide("boundary_c", "degree_c").alias("factor"), F.try_divide("boundary_m", "degree_m").alias("max_factor"))


def plan_loads(g: DataGraph, queries: Iterable[str], strategy: str = "degree") -> DataFrame:
    """graph, query, plan, seconds (candidate rows), heuristic: every plan of every query, for metrics.plan_error."""
    rows = []
    for name in queries:
        q = CATALOGUE[name]
        if not solve.impossible(g, q):
            chosen = plan_for(q).text()
            rows += [(g.name, name, i, float(load_of(g, q, strategy, p)[0]), p.text() == chosen) for i, p in enumerate(enumerate_plans(q))]
    return g.spark.createDataFrame(rows, "graph string, query string, plan int, seconds double, heuristic boolean")


def table_sizes(g: DataGraph, q: QueryGraph, strategy: str = "degree", coloring=None) -> DataFrame:
    """block, kind, rows (entries that are not 0) of every block's table, and the bound: vertices to the power of the
    boundary's size, times two to the power of the number of query nodes."""
    spark, plan = g.spark, plan_for(q)
    solver = solve.Solver(Context(g, coloring or Coloring(q.k, "affine")), plan, strategy)
    n, rows = g.degrees().count(), []
    for b in plan.blocks:
        made = solver.block(b)
        solver.tables[b.id] = made = solve.cut(made, f"block{b.id}")
        rows.append((q.name, g.name, b.id, b.kind, made.count(), float(n ** len(b.boundary) * 2**q.k)))
    return spark.createDataFrame(rows, "query string, graph string, block int, kind string, rows long, bound double")


def trial_counts(g: DataGraph, q: QueryGraph, trials: int, batch: int = 10) -> DataFrame:
    """graph, query, trial, cnt: colourings in batches of one job each."""
    parts = []
    for at in range(0, trials, batch):
        n = min(batch, trials - at)
        parts += [(g.name, q.name, at + r[0], float(r[1])) for r in estimate.trials_of(g, q, n, seed=1 + at).collect()]
    return g.spark.createDataFrame(parts, "graph string, query string, trial int, cnt double")


def weak_graph(spark: SparkSession, cores: int, per_core: int = 10) -> DataGraph:
    """R-MAT with 2^per_core vertices for each core."""
    return generators.rmat(spark, per_core + max(0, cores - 1).bit_length())


# --- the runs -------------------------------------------------------------------------------------------------


def record(spark: SparkSession, d: str, cells: list[tuple[str, str]], ranks: int, repeats: int = 3, strategies=("boundary", "degree"), best_base: bool = True) -> DataFrame:
    """Measurements of cells (view, query): strategies take turns, so that no one of them has the warm caches."""
    rows, graphs = [], {}
    for v, name in cells:
        g, q = graphs.setdefault(v, graph_view(spark, d, v)), CATALOGUE[name]
        g.arcs()
        plans = {s: best_by_cost(g, q, s)[0] if best_base and s == "boundary" else plan_for(q) for s in strategies}
        one_run(g, q, strategies[0], plans[strategies[0]])  # warms up
        for r in range(repeats):
            for s in strategies[:: 1 if r % 2 == 0 else -1]:
                seconds, cnt, status = one_run(g, q, s, plans[s])
                rows.append((v, name, s, ranks, 0, r, seconds, cnt, None, None, None, status))
                print(json.dumps(rows[-1][:8]), file=sys.stderr, flush=True)
    return spark.createDataFrame(rows, ROW)


def fastest(rows: DataFrame) -> DataFrame:
    """One row per cell and strategy: the median of its repeats."""
    return rows.groupBy("graph", "query", "strategy", "ranks").agg(F.median("seconds").alias("seconds"), F.max("cnt").alias("cnt"), F.max("status").alias("status"))


CELLS = [("supply_chain", "triangle"), ("part_supplier", "c4"), ("customer_part", "c4"), ("order_part", "c4"), ("user_hour", "c4"), ("succession", "c4"), ("knn8", "house")]
SMALL = "/root/testdata/sf0.01"


def _child(cores: int, d: str, repeats: int) -> None:
    from huecount.session import local_session

    spark = local_session(cores, f"experiments{cores}")
    spark.sparkContext.setLogLevel("ERROR")
    rows = fastest(record(spark, d, CELLS, cores, repeats)).collect()
    g = weak_graph(spark, cores)
    began = time.perf_counter()
    g.arcs()
    weak = [one_run(g, CATALOGUE["diamond"], "degree")[0] for _ in range(repeats + 1)][1:]
    print("RESULT " + json.dumps({"cells": [r.asDict() for r in rows], "weak": sorted(weak)[len(weak) // 2], "weak_vertices": 1 << (10 + max(0, cores - 1).bit_length()), "arcs": time.perf_counter() - began}))
    spark.stop()


def main() -> None:
    p = argparse.ArgumentParser()
    p.add_argument("--out")
    p.add_argument("--sf", default=SMALL)
    p.add_argument("--cores", default="1,4")
    p.add_argument("--repeats", type=int, default=3)
    p.add_argument("--child", type=int)
    a = p.parse_args()
    if a.child:
        return _child(a.child, a.sf, a.repeats)
    found, weak = [], {}
    cores = [int(c) for c in a.cores.split(",")]
    for c in cores:
        run = subprocess.run([sys.executable, "-m", "huecount.experiments", "--child", str(c), "--sf", a.sf, "--repeats", str(a.repeats)], stdout=subprocess.PIPE, text=True, check=True)
        one = json.loads(next(x for x in run.stdout.splitlines() if x.startswith("RESULT ")).removeprefix("RESULT "))
        found += one["cells"]
        weak[c] = {"vertices": one["weak_vertices"], "seconds": one["weak"]}
    from huecount.session import local_session

    spark = local_session(8, "experiments")
    spark.sparkContext.setLogLevel("ERROR")
    rows = spark.createDataFrame([(r["graph"], r["query"], r["strategy"], r["ranks"], r["seconds"], r["status"]) for r in found], "graph string, query string, strategy string, ranks int, seconds double, status string")
    factors = metrics.improvement(rows)
    report = {
        "sf": a.sf,
        "improvement": [r.asDict() for r in metrics.improvement_summary(factors).orderBy("ranks").collect()],
        "factors": [r.asDict() for r in factors.orderBy("graph", "query", "ranks").collect()],
        "growth": metrics.if_growth(factors, cores[0], cores[-1]).agg(F.avg("growth").alias("avg"), F.max("growth").alias("max")).first().asDict(),
        "speedup": [r.asDict() for r in metrics.speedup(rows, cores[0], cores[-1]).groupBy("strategy").agg(F.avg("speedup").alias("avg"), F.max("speedup").alias("max")).collect()],
        "strong": [r.asDict() for r in rows.where("graph = 'supply_chain' and strategy = 'degree'").groupBy("ranks").agg(F.avg("seconds").alias("seconds")).orderBy("ranks").collect()],
        "weak": weak,
        "averages": [r.asDict() for r in metrics.averages(rows.where((F.col("strategy") == "degree") & (F.col("ranks") == cores[-1]))).collect()],
    }
    text = json.dumps(report, indent=1)
    if a.out:
        with open(a.out, "w") as f:
            f.write(text + "\n")
    print(text)
    spark.stop()


if __name__ == "__main__":
    main()
