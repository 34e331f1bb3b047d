from itertools import product
from math import factorial

import pytest
from pyspark.sql import functions as F

from huecount.functions.coloring import Coloring, TableColoring
from huecount.operators import estimate, exact, paths
from huecount.operators.graph import MOST_NEAR, dense_rank, prune
from huecount.operators.joins import Context
from huecount.operators.solve import STRATEGIES, Solver, count_colorful, load, run_banded
from huecount.plans.plan import Block, Plan, enumerate_plans
from huecount.plans.query import CATALOGUE, automorphisms
from huecount.sources import generators as gen


@pytest.fixture(scope="module")
def dense(spark):
    return gen.uniform_random(spark, 14, 0.5, seed=3)


def number(df):
    return int(df.first()["cnt"])


@pytest.mark.parametrize("name", ["triangle", "c5", "paw", "house", "fan5", "k23", "bowtie", "ladder6"])
def test_strategies_equal_backtracking(dense, name):
    q = CATALOGUE[name]
    coloring = Coloring(q.k, "affine")
    want = number(exact.colorful_brute_force(dense, q, coloring))
    for s in STRATEGIES:
        assert number(count_colorful(dense, q, coloring, s)) == want
    assert want > 0 or name == "ladder6"


def test_every_plan_gives_the_same_count(dense):
    q = CATALOGUE["diamond"]
    got = {number(count_colorful(dense, q, Coloring(4, "affine"), s, p)) for p in enumerate_plans(q) for s in ("boundary", "degree")}
    assert len(got) == 1


def test_larger_queries_agree(dense):
    for name in ("satellite11", "c4_c6"):
        q = CATALOGUE[name]
        assert len({number(count_colorful(dense, q, Coloring(q.k, "affine"), s)) for s in ("boundary", "degree")}) == 1


def test_order_does_not_change_counts(dense):
    q = CATALOGUE["house"]
    assert len({number(count_colorful(dense.with_order(o), q, Coloring(5, "affine"))) for o in ("degree", "id", "random")}) == 1


def test_rewrites_change_nothing(dense):
    for name in ("c6", "paw"):
        q = CATALOGUE[name]
        want = number(count_colorful(dense, q, Coloring(q.k, "affine")))
        off = {"symmetry": False, "root_complement": False, "share": False}
        assert number(count_colorful(dense, q, Coloring(q.k, "affine"), **off)) == want
        assert run_banded(dense, q, Coloring(q.k, "affine"), 3).first()["cnt"] == want


def test_all_colourings_average_to_the_exact_count(spark):
    g = gen.complete(spark, 4)
    q = CATALOGUE["triangle"]
    every = {(t, v): c for t, colors in enumerate(product(range(3), repeat=4)) for v, c in enumerate(colors)}
    counts = count_colorful(g, q, TableColoring(3, every, 81))
    total = counts.agg(F.sum("cnt")).first()[0]
    assert total * estimate.scale(3) / 81 == number(exact.brute_force(g, q)) == 24


def test_closed_forms(spark):
    k6 = gen.complete(spark, 6)
    for name in ("c4", "paw", "star4"):
        assert number(exact.brute_force(k6, CATALOGUE[name])) == factorial(6) // factorial(2)
    assert number(exact.brute_force(gen.cycle(spark, 7), CATALOGUE["c5"])) == 0
    assert number(exact.brute_force(gen.cycle(spark, 5), CATALOGUE["c5"])) == 10
    assert number(count_colorful(gen.grid(spark, 3, 3), CATALOGUE["c5"], Coloring(5))) == 0
    assert number(exact.four_cycles(gen.grid(spark, 3, 4))) == 6
    assert number(exact.triangles(k6)) == 20 and number(exact.wedges(k6)) == 60 and number(exact.closed_walks(k6, 3)) == 120
    assert number(exact.paws(k6)) == number(exact.brute_force(k6, CATALOGUE["paw"]))
    assert number(paths.count_paths(k6, 4)) == 360 and number(paths.count_y(k6, 4)) == 90 == number(paths.count_x(k6, 4))


def test_estimate_is_near_the_truth(dense):
    q = CATALOGUE["c4"]
    true = number(exact.brute_force(dense, q))
    row = estimate.interval(estimate.count(dense, q, trials=40, kind="poly"), 4, 4.0).first()
    assert row["low"] <= true <= row["high"] and row["aut"] == automorphisms(q) == 8 and row["trials"] == 40


def test_adaptive_run_resumes(dense, tmp_path):
    folder = f"file://{tmp_path}/history"
    a = estimate.until(dense, CATALOGUE["c4"], cv=0.0, batch=2, max_trials=4, history=folder).first()
    b = estimate.until(dense, CATALOGUE["c4"], cv=0.0, batch=2, max_trials=4, history=folder).first()
    assert a == b and a["trials"] == 4


def test_counts_beyond_a_long(spark):
    g = gen.complete(spark, 5)
    out = count_colorful(g, CATALOGUE["c5"], Coloring(5, "affine"), count_type="decimal")
    assert dict(out.dtypes)["cnt"] == "decimal(38,0)"


def test_degree_order_touches_fewer_candidates(spark):
    from huecount.sources.views import graph_view

    g = graph_view(spark, "/root/testdata/sf0.001", "part_supplier")
    work = {s: load(g, CATALOGUE["c4"], Coloring(4, "affine"), s).agg(F.sum("candidates")).first()[0] for s in ("boundary", "degree")}
    assert work["degree"] < work["boundary"]


def test_dense_rank_and_prune(spark, dense):
    rows = sorted(dense_rank(dense).collect(), key=lambda r: r["rank"])
    assert [r["rank"] for r in rows] == list(range(len(rows)))
    assert [(r["deg"], r["v"]) for r in rows] == sorted((r["deg"], r["v"]) for r in rows)
    assert prune(gen.path(spark, 5), 2, 4).edges.count() == 0


def test_empty_and_disjoint_graphs(spark):
    none = gen.uniform_random(spark, 5, 0.0)
    assert number(count_colorful(none, CATALOGUE["paw"], Coloring(4))) == 0
    assert estimate.count(none, CATALOGUE["c4"], trials=2).first()["cv"] is None


def test_numbers_of_paths_without_enumerating_them(spark):
    for g in (gen.complete(spark, 7), gen.grid(spark, 3, 5), gen.star(spark, 9), gen.uniform_random(spark, 30, 0.3), gen.complete_of(spark.range(1).select(F.col("id").alias("v")))):
        for q in (3, 4, 5):
            assert number(paths.count_paths(g, q)) == paths.enumerate_paths(g, q).count()
    plan = paths.count_paths(gen.grid(spark, 3, 5), 4)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1


def test_paths_stay_at_their_start_on_flat_graphs(spark):
    from huecount.operators import joins
    from huecount.operators.joins import Context

    made = []
    for parts in (None, 0):
        g = gen.uniform_random(spark, 60, 0.2, seed=2)
        g._flat = parts
        ctx = Context(g, Coloring(4, "affine"))
        p = joins.extend_edge(ctx, joins.extend_edge(ctx, joins.seed_edge(ctx, False), False), False)
        t = joins.extend_edge(ctx, joins.seed_edge(ctx, False), False).select("trial", F.col("h").alias("u"), F.col("tail").alias("v"), "sig", "cnt")
        b = joins.extend_block(ctx, joins.seed_edge(ctx, False), t, True, False, bare=True)
        moves = p._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")  # before it has run
        made.append((sorted(p.collect()), sorted(b.collect()), moves))
    flat, plain = made
    assert flat[:2] == plain[:2] and flat[0] and flat[1]
    assert flat[2] <= 1 < plain[2]
    assert gen.star(spark, 200).flat_parts() == 0  # a hub's paths would all lie in one task


def test_a_path_meets_itself_without_a_join(spark):
    from huecount.operators.joins import Context, extend_edge, meets_itself, merge_itself, merge_paths, seed_edge

    g = gen.uniform_random(spark, 40, 0.3, seed=4)
    ctx = Context(g, Coloring(5, "affine", trials=3))
    p = extend_edge(ctx, seed_edge(ctx, False), False)
    for keep in ({}, {"u": "h"}, {"u": "h", "v": "tail"}):
        alone, joined = merge_itself(ctx, p, keep, 1), merge_paths(ctx, p, p, keep)
        plan = alone._jdf.queryExecution().executedPlan().toString()  # before it has run
        loose = merge_itself(ctx, extend_edge(ctx, seed_edge(ctx, False), False, sums=False), keep, 1)
        assert sorted(loose.collect()) == sorted(alone.collect()) == sorted(joined.select(*alone.columns).collect()) != []
        assert "SortMergeJoin" not in plan and plan.count("Exchange hashpartitioning") <= (2 if not keep else 1)
    # What a step has for candidates is told alike, by sums and by joined rows.
    told = [Context(g, Coloring(5, "affine"), load=[]) for _ in range(2)]
    for merge, c in zip((lambda c: merge_itself(c, p, {}, 1), lambda c: merge_paths(c, p, p, {})), told, strict=True):
        merge(c)
    sums = [c.load[-1].agg(F.sum("candidates"), F.sum("kept")).first() for c in told]
    assert sums[0] == sums[1] and sums[0][1] > 0
    assert meets_itself(ctx, 1) and not meets_itself(ctx, 2) and not meets_itself(Context(g, Coloring(12)), 3)  # too many sets of colours


def test_neighbours_come_in_lots(spark, monkeypatch):
    from huecount.operators import graph

    q = CATALOGUE["c4"]
    want = number(exact.colorful_brute_force(gen.uniform_random(spark, 60, 0.2, seed=2), q, Coloring(4, "affine")))
    monkeypatch.setattr(graph, "NEAR_LOT", 200)
    monkeypatch.setattr(graph, "PART_CANDIDATES", 500)
    for s in STRATEGIES:
        g = gen.uniform_random(spark, 60, 0.2, seed=2)
        assert number(count_colorful(g, q, Coloring(4, "affine"), s)) == want > 0
        assert len(g.near()) > 2 and g.flat_parts(10) > g.flat_parts()


def test_bipartite_cycles_start_on_one_side(spark):
    from huecount.operators.joins import Context
    from huecount.operators.solve import Solver
    from huecount.plans.plan import plan_for
    from huecount.sources.views import graph_view

    for v in ("part_supplier", "user_hour"):
        g = graph_view(spark, "/root/testdata/sf0.001", v)
        for name in ("c4", "c6"):
            q = CATALOGUE[name]
            ctx = Context(g, Coloring(q.k, "affine"))
            half, whole = (Solver(ctx, plan_for(q), "even", symmetry=s).run() for s in (True, False))
            assert number(half) == number(whole) > 0
            if name == "c4":
                assert "& 1) =" in half._jdf.queryExecution().toString() and "& 1) =" not in whole._jdf.queryExecution().toString()


def test_leaves_are_summed_once(dense):
    from huecount.operators.joins import Context
    from huecount.operators.solve import Solver
    from huecount.plans.plan import plan_for

    q = CATALOGUE["path4"]
    assert number(count_colorful(dense, q, Coloring(4, "affine"))) == number(exact.colorful_brute_force(dense, q, Coloring(4, "affine"))) > 0
    solver = Solver(Context(dense, Coloring(4, "affine")), plan_for(q))
    for b in solver.plan.blocks[:-1]:
        solver.tables[b.id] = solver.leaf(b).localCheckpoint()
    leaf = next(b for b in solver.plan.blocks if b.kind == "leaf" and b.on_node(b.seq[1]) is not None)
    assert "sum(cnt" in (plan := solver.leaf(leaf)._jdf.queryExecution().optimizedPlan().toString()) and plan.count("Aggregate [") == 1


def test_triangles_of_the_plain_strategies_are_closed_before_they_are_summed(spark, monkeypatch):
    g = gen.uniform_random(spark, 40, 0.3, seed=5)
    for name in ("triangle", "paw", "bull"):
        q = CATALOGUE[name]
        coloring = Coloring(q.k, "affine", trials=3)
        want = sorted(map(tuple, count_colorful(g, q, coloring, "degree").collect()))
        assert sum(c for _, c in want) > 0
        with monkeypatch.context() as m:
            m.setattr("huecount.operators.joins.extend_edge", None)  # no path of two edges is built
            for s in ("boundary", "even"):
                for kind in ("long", "decimal"):
                    assert sorted(map(tuple, count_colorful(g, q, coloring, s, count_type=kind).collect())) == want
    q = CATALOGUE["triangle"]
    assert run_banded(g, q, Coloring(3, "affine"), 3, strategy="boundary").first()["cnt"] == number(count_colorful(g, q, Coloring(3, "affine")))


def test_paths_between_the_sides_start_on_one(spark):
    from huecount.operators.joins import Context, bare_path, extend_edge, seed_edge
    from huecount.sources.views import graph_view

    for flat in (None, 0):
        g = graph_view(spark, "/root/testdata/sf0.001", "user_hour")
        g._flat = flat
        for n in (3, 4):
            ctx = Context(g, Coloring(4, "affine"))
            whole = seed_edge(ctx, False)
            for _ in range(n - 2):
                whole = extend_edge(ctx, whole, False)
            got = bare_path(ctx, n)
            assert ("& 1) =" in got._jdf.queryExecution().toString()) == (n == 4)
            assert sorted(got.select(*whole.columns).collect()) == sorted(whole.collect()) != []


def test_lists_by_colour_tell_candidates_as_joins_do(spark):
    from huecount.operators.joins import Context, extend_edge, seed_edge

    for high in (False, True):
        told = []
        for flat in (None, 0):
            g = gen.uniform_random(spark, 60, 0.2, seed=2)
            g._flat = flat
            ctx = Context(g, Coloring(4, "affine"), load=[])
            rows = sorted(extend_edge(ctx, seed_edge(ctx, high), high).collect())
            told.append((rows, ctx.load[-1].agg(F.sum("candidates"), F.sum("kept")).first()))
        assert told[0] == told[1] and told[0][0]


def test_twins_are_chosen_from_one_list(spark):
    from huecount.sources.views import graph_view

    for g in (gen.uniform_random(spark, 25, 0.4, seed=1), graph_view(spark, "/root/testdata/sf0.001", "user_hour")):
        for name in ("c4",) if g.sides else ("c4", "k23", "house"):
            q = CATALOGUE[name]
            c = Coloring(q.k, "affine")
            want = exact.matches(g, q, coloring=c).count()
            for flat in (None, 0):
                g._flat = flat
                df = exact.colorful_brute_force(g, q, c)
                assert number(df) == want
                if name == "c4" and flat is None:
                    assert "LeftSemi" not in df._jdf.queryExecution().optimizedPlan().toString()  # nothing is listed and then closed


def test_paths_with_the_highest_first_follow_from_places(spark):
    from huecount.sources.views import graph_view

    graphs = [gen.complete(spark, 6), gen.uniform_random(spark, 25, 0.3), graph_view(spark, "/root/testdata/sf0.001", "user_hour")]
    for g in graphs:
        for q in (3, 4):
            for order, count in (("degree", paths.count_x), ("id", paths.count_y)):
                assert number(count(g, q)) == paths.enumerate_paths(g, q, order).count()
    plan = paths.count_y(graphs[-1], 4)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 2  # degrees of ends, and single rows; no path is listed


def test_equal_merges_are_run_once(spark):
    from huecount.operators.joins import Context
    from huecount.operators.solve import Solver
    from huecount.plans.plan import plan_for

    g, q, told = gen.uniform_random(spark, 40, 0.25, seed=2), CATALOGUE["c4"], []
    for share in (True, False):
        ctx = Context(g, Coloring(4, "affine"), load=[])
        Solver(ctx, plan_for(q), "degree", symmetry=False, root_complement=False, share=share).run()
        merges = [x for x in ctx.load if "merge#" in x.first()["step"]]
        rows = [x.agg(F.countDistinct("step"), F.sum("candidates"), F.sum("kept")).first() for x in merges]
        told.append((len(merges), *(sum(r[i] for r in rows) for i in range(3))))
    assert told[0][0] == 1 and told[1][0] == 4
    assert told[0][1:] == told[1][1:] and told[0][1] == 4 and told[0][3] > 0


def test_measures_of_views_leave_nothing(spark):
    from huecount import catalogue, session

    since = session.made()
    rows = catalogue._on_view(spark, "/root/testdata/sf0.001", "user_hour", lambda g: [(g.arcs().count(), session.made() - since)])
    assert rows[0][0] > 0 and rows[0][1] > 0 and session.made() == since


@pytest.mark.parametrize("ends", [(), ("a",), ("a", "c"), ("a", "b")])
@pytest.mark.parametrize("strategy", STRATEGIES)
def test_cycles_in_place(spark, strategy, ends):
    """On flat graphs bare four-cycles are summed by tasks that read all lists: the same rows as by joins, without a row for a candidate."""
    block, told = Block(0, "cycle", tuple("abcd"), ends), []
    for flat in (None, 0):
        g = gen.uniform_random(spark, 90, 0.3)
        g._flat = flat
        ctx = Context(g, Coloring(5, trials=2))
        made = Solver(ctx, Plan(CATALOGUE["c4"], (block,)), strategy, root_complement=False).cycle(block)
        told.append(sorted(map(tuple, made.collect())))
        if flat is None:
            assert g.flat_parts() > 0
            taken = strategy == "boundary" or ends == ("a", "b") and strategy == "degree" or strategy == "even" and ends != ("a", "b") or not ends
            assert not taken or "explode" not in made._jdf.queryExecution().executedPlan().toString()
    assert told[0] == told[1] and len(told[0]) > 0


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_loads_in_place(spark, strategy):
    """The steps of cycles that are summed in place are told part by part as joins tell them, but no join is run for it."""
    told = []
    for lists in (True, False):
        g = gen.uniform_random(spark, 90, 0.3)
        assert g.flat_parts() > 0
        if not lists:
            g.work()["arcs"] = MOST_NEAR + 1  # too many arcs for tasks that read all of them
        made = load(g, CATALOGUE["c4"], Coloring(4), strategy)
        assert ("Join" in made._jdf.queryExecution().executedPlan().toString()) != lists
        told.append(sorted(map(tuple, made.collect())))
    assert told[0] == told[1] and len(told[0]) > 0


@pytest.mark.parametrize("k", [4, 5])
@pytest.mark.parametrize("n,p", [(60, 0.3), (400, 0.01)])
def test_edge_join_in_place(spark, k, n, p):
    """An edge and a path of three are joined where they start, on dense and on thin graphs, and nothing is exchanged for it."""
    from huecount.operators import joins

    made = []
    for flat in (None, 0):
        g = gen.uniform_random(spark, n, p, seed=5)
        g._flat = flat
        ctx = Context(g, Coloring(k))
        t = joins.bare_path(ctx, 3).select("trial", F.col("h").alias("u"), F.col("tail").alias("v"), "sig", "cnt")
        b = joins.extend_block(ctx, joins.seed_edge(ctx, False), t, True, False, bare=3)
        assert flat is not None or g.flat_parts() > 0 and "Exchange hash" not in b._jdf.queryExecution().executedPlan().toString()
        made.append(sorted(map(tuple, b.collect())))
    assert made[0] == made[1] and made[0]
