from datetime import date, datetime, timedelta

import pytest
from pyspark.sql import functions as F

from huecount import experiments
from huecount.functions import theory, udf
from huecount.functions.coloring import Coloring
from huecount.operators import direct, estimate, exact, joins
from huecount.operators.graph import DataGraph, simple_edges
from huecount.operators.joins import Context
from huecount.operators.solve import STRATEGIES, Solver, count_colorful, strategy_for
from huecount.plans.plan import enumerate_plans, plan_for
from huecount.plans.query import CATALOGUE, parse
from huecount.session import cut, fresh_dir, made, release
from huecount.sources import generators as gen
from huecount.streaming import windows


def number(df):
    return int(df.first()["cnt"])


@pytest.mark.parametrize("name", ["paw", "house"])
def test_tables_equal_their_definition(spark, name):
    g, q = gen.uniform_random(spark, 7, 0.7, seed=4), CATALOGUE[name]
    for plan in enumerate_plans(q):
        ctx = Context(g, Coloring(q.k, "affine"))
        solver, tables = Solver(ctx, plan, "degree"), {}
        for b in plan.blocks:
            solver.tables[b.id] = cut(solver.block(b), "test")
            tables[b.id] = direct.block_product(ctx, plan, b, tables)
            ours = solver.tables[b.id]
            assert sorted(map(tuple, ours.select(sorted(ours.columns)).collect())) == sorted(map(tuple, tables[b.id].select(sorted(ours.columns)).collect()))
    with pytest.raises(ValueError):
        direct.block_product(Context(gen.complete(spark, 60), Coloring(5)), plan_for(CATALOGUE["c5"]), plan_for(CATALOGUE["c5"]).root, {})


def test_names_of_nodes_do_not_matter(spark):
    g = gen.uniform_random(spark, 10, 0.5, seed=2)
    for text in ("x-y y-z z-x", "h-tail tail-x x-y y-h", "src-dst dst-cnt cnt-src src-sig"):
        q = parse(text)
        want = number(exact.colorful_brute_force(g, q, Coloring(q.k, "affine")))
        assert want > 0 and all(number(count_colorful(g, q, Coloring(q.k, "affine"), s)) == want for s in STRATEGIES)


def test_hubs_are_dealt_to_several_tasks(spark, monkeypatch):
    g = DataGraph("hub", simple_edges(spark.range(1, 40).selectExpr("0L as src", "id as dst").union(spark.range(1, 39).selectExpr("id as src", "id + 1 as dst"))))
    want = {n: number(count_colorful(g, CATALOGUE[n], Coloring(CATALOGUE[n].k, "affine"))) for n in ("c4", "house", "star4")}
    assert g.largest_order() == 39 and g.with_order("id").largest_order() == 0
    monkeypatch.setattr(joins, "HUB_DEGREE", 5)
    plan = joins.extend_edge(Context(g, Coloring(4, "affine")), joins.seed_edge(Context(g, Coloring(4, "affine")), False), False)
    assert "lot" in plan._jdf.queryExecution().toString()
    for s in STRATEGIES:
        assert {n: number(count_colorful(g, CATALOGUE[n], Coloring(CATALOGUE[n].k, "affine"), s)) for n in want} == want


def test_strategy_follows_the_skew(spark):
    hub = DataGraph("hub", simple_edges(spark.range(1, 60).selectExpr("0L as src", "id as dst").union(spark.range(1, 59).selectExpr("id as src", "id + 1 as dst"))))
    flat = gen.complete(spark, 8)
    q = CATALOGUE["house"]
    assert strategy_for(hub, q) == "degree" and strategy_for(flat, q) == "even" and strategy_for(flat, CATALOGUE["star4"]) == "degree"
    for g in (hub, flat):
        assert number(count_colorful(g, q, Coloring(5, "affine"), "auto")) == number(count_colorful(g, q, Coloring(5, "affine"), "boundary"))


def test_best_plan_is_the_cheapest(spark):
    g = gen.uniform_random(spark, 12, 0.5, seed=5)
    best, costs = experiments.best_by_cost(g, CATALOGUE["paw"], "boundary")
    assert len(costs) == 3 and experiments.load_of(g, CATALOGUE["paw"], "boundary", best)[0] == min(c for _, c in costs)
    with pytest.raises(ValueError):
        experiments.best_by_cost(g, CATALOGUE["paw"], metric="money")
    sizes = experiments.table_sizes(g, CATALOGUE["house"]).collect()
    assert len(sizes) == 2 and all(0 < r["rows"] <= r["bound"] for r in sizes)
    rows = experiments.load_table(spark, "/root/testdata/sf0.001", ["part_supplier"], ["c4"])
    factor = experiments.improvement_by_load(rows).first()
    assert factor["factor"] > 1 and factor["max_factor"] > 1


def test_measurements_of_a_cell(spark):
    rows = experiments.record(spark, "/root/testdata/sf0.001", [("user_hour", "c4")], 4, repeats=2)
    got = experiments.fastest(rows).collect()
    assert {r["strategy"] for r in got} == {"boundary", "degree"} and len({r["cnt"] for r in got}) == 1
    assert all(r["status"] == "ok" and r["seconds"] > 0 for r in got) and rows.count() == 4


def test_five_cycles_of_the_supply_chain(spark):
    from huecount.sources.views import graph_view

    g = graph_view(spark, "/root/testdata/sf0.001", "supply_chain")
    assert number(count_colorful(g, CATALOGUE["c5"], Coloring(5, "affine"))) == 31_113_070


def test_inversions_are_as_rare_as_the_bound():
    from random import Random

    rng, worse = Random(3), 0
    for _ in range(2000):
        large = sum(rng.random() < 0.2 for _ in range(200))
        small = sum(rng.random() < 0.01 for _ in range(200))
        worse += small >= large
    assert worse / 2000 <= theory.inversion_bound(40, 2) < 0.05
    with pytest.raises(ValueError):
        theory.inversion_bound(10, 9)


def test_ids_out_of_range_are_refused(spark):
    for bad in (-1, 1 << 40):
        g = DataGraph("bad", spark.createDataFrame([(bad, 3), (3, 4)], "src long, dst long"))
        with pytest.raises(Exception, match="vertex ids"):
            g.arcs().count()


def test_counts_beyond_a_long_are_kept(spark, monkeypatch, tmp_path):
    big = 10**25
    frame = spark.createDataFrame([(0, str(big)), (1, str(big + 8))], "trial int, cnt string").select("trial", F.col("cnt").cast("decimal(38,0)").alias("cnt"))
    monkeypatch.setattr(estimate, "count_colorful", lambda *a, **k: frame)
    g, folder = gen.complete(spark, 4), f"file://{tmp_path}/h"
    one = estimate.until(g, CATALOGUE["triangle"], cv=0.0, batch=2, max_trials=2, history=folder).first()
    assert one["mean_colorful"] == pytest.approx(1e25) and estimate.until(g, CATALOGUE["triangle"], cv=0.0, max_trials=2, history=folder).first() == one


def test_written_tables_are_released(spark):
    mark = made()
    a = cut(spark.range(3), "one")
    path = fresh_dir(spark, "two")
    spark.range(4).write.parquet(path)
    assert a.count() == 3 and release(spark, mark, (path,)) == 1 and spark.read.parquet(path).count() == 4
    assert release(spark, mark) == 1 and made() == mark


def events(spark, folder, n=400, files=4):
    """Events in several files, in order of time."""
    start, types = datetime(2024, 1, 1), ["a", "b", "c", None]
    for k in range(files):
        rows = [(i, start + timedelta(minutes=11 * i), i * i % 7, types[i * 7 % 4], 1.0, "{}") for i in range(k * n // files, (k + 1) * n // files)]
        spark.createDataFrame(rows, windows.EVENTS).coalesce(1).write.mode("append").parquet(f"{folder}/events.parquet")
    return spark.read.schema(windows.EVENTS).parquet(f"{folder}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def test_streams_over_several_batches(spark, tmp_path):
    folder = f"file://{tmp_path}"
    batch = events(spark, folder)
    days = batch.where("event_type is not null").select(F.to_date("ts").alias("day"), "user_id", "event_type").distinct().collect()
    common: dict = {}
    for day in {r["day"] for r in days}:
        users = {t: {r["user_id"] for r in days if r["day"] == day and r["event_type"] == t} for t in "abc"}
        common[day] = sum(len(users[a] & users[b]) * (len(users[a] & users[b]) - 1) // 2 for a, b in ("ab", "ac", "bc"))
    cycles = windows.FourCycles(spark)
    got = {r["day"]: r["cnt"] for r in cycles.drive(windows.event_stream(spark, folder, 1)).collect()}
    assert got == common and len(got) > 2
    motifs = windows.WindowedMotifs(spark, CATALOGUE["c4"], 2)
    once = sorted(map(tuple, motifs.drive(windows.event_stream(spark, folder, 2)).collect()))
    motifs(batch, 1)  # a repeated batch
    assert sorted(map(tuple, motifs.counts().collect())) == once and {r[0] for r in once} == set(common)
    day = date(2024, 1, 2)
    edges = batch.where(F.to_date("ts") == F.lit(day)).where("event_type is not null").select((F.col("user_id") * 2).alias("src"), (F.pmod(F.xxhash64("event_type"), F.lit(1 << 38)) * 2 + 1).alias("dst"))
    want = count_colorful(DataGraph("day", simple_edges(edges), bipartite=True), CATALOGUE["c4"], Coloring(4, trials=2)).collect()
    assert sorted((r["trial"], r["cnt"]) for r in want) == [x[1:] for x in once if x[0] == day]


def test_late_rows_are_counted(spark, tmp_path):
    folder = f"file://{tmp_path}"
    events(spark, folder, 400, 2)
    late = [(9000 + i, datetime(2024, 1, 1), i, "a", 1.0, "{}") for i in range(5)]
    spark.createDataFrame(late, windows.EVENTS).coalesce(1).write.mode("append").parquet(f"{folder}/events.parquet")
    rows, dropped = windows.run_and_count_late(windows.windowed_edges(windows.event_stream(spark, folder, 1), "tumbling"))
    assert dropped == 5 and rows.where("win_start < '2024-01-02'").agg(F.sum("n")).first()[0] == 131


def test_groups_in_python(spark):
    g = gen.uniform_random(spark, 12, 0.5, seed=1)
    assert udf.ego_triangles(g).agg(F.sum("triangles")).first()[0] == number(exact.triangles(g))
    a = spark.createDataFrame([(1, 5), (2, 6), (2, 7)], "k int, cnt long")
    b = spark.createDataFrame([(1, 5), (2, 7), (2, 6), (3, 1)], "k int, cnt long")
    assert udf.differences(a, b, ["k"]).first()[0] == 1 and udf.differences(a, a, ["k"]).first()[0] == 0


def test_differences_are_told_many_keys_a_call(spark):
    a = spark.range(3000).selectExpr("id div 2 as u", "id % 2 as v", "id as cnt")
    b = a.where("u <> 7").withColumn("cnt", F.expr("if(u = 9, cnt + 1, cnt)")).union(spark.sql("select 5000L, 0L, 1L")).union(a.where("u = 11"))
    assert udf.differences(a, a.orderBy(F.desc("cnt")), ["u", "v"]).first()[0] == 0
    told = udf.differences(a, b, ["u", "v"])
    assert told.first()[0] == 2 + 2 + 1 + 2
    assert "lot" in told._jdf.queryExecution().analyzed().toString()
