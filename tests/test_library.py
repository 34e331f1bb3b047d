import math

import duckdb
import pytest
from pyspark.sql import functions as F

from huecount.functions import metrics, signature, theory
from huecount.functions.coloring import Coloring, affine_sql
from huecount.operators.graph import DataGraph
from huecount.operators.solve import count_colorful
from huecount.plans.query import CATALOGUE
from huecount.sources import generators as gen
from huecount.sources import io
from huecount.streaming import windows
from tests.conftest import SF


def test_signature_algebra(spark):
    a, b = F.lit(0b0110).cast("long"), F.lit(0b0011).cast("long")
    row = spark.range(1).select(signature.disjoint_except(a, b, F.lit(0b0010)), signature.has_not(a, signature.bit(F.lit(3))), signature.size(signature.union(a, b)), F.lit(signature.full(4))).first()
    assert tuple(row) == (True, True, 3, 15)


def test_colours_agree_with_sql(spark):
    ids = [0, 1, 7, 2**31, 2**39 + 5]
    for trial in (0, 3):
        ours = [r[0] for r in spark.createDataFrame([(i,) for i in ids], "v long").select(Coloring(5, "affine").color(F.col("v"), F.lit(trial))).collect()]
        assert ours == [duckdb.sql(f"SELECT {affine_sql(f'{i}::BIGINT', 5, str(trial))}").fetchall()[0][0] for i in ids]
    for kind in ("xxhash", "poly"):
        c = Coloring(3, kind, trials=2)
        got = spark.range(3000).select(c.color(F.col("id"), F.lit(1)).alias("c")).groupBy("c").count().collect()
        assert len(got) == 3 and all(800 < r[1] < 1200 for r in got)


def test_theory(spark):
    seq = gen.power_law(spark, 1024, 1.5)
    for q in (3, 4, 5):
        left, right = theory.moment_inequality(seq, q)
        assert left <= right * (1 + 1e-9)
    assert theory.gain_exponent(1.5, 3) == pytest.approx(0.25) and theory.exponents(1.9, 3)["log_power"] == 2
    assert 0 < theory.balance(seq) < 1 and theory.power_law_lambda(10_000, 1.5) == pytest.approx(0.1)
    assert theory.path_probability([2.0, 3.0, 4.0], 10.0) == pytest.approx(2 * 9 * 4 / 100)
    assert theory.x_upper(seq, 3) > 0 and theory.y_lower(seq, 3) > 0
    law = spark.range(1, 9).select(F.explode(F.sequence(F.lit(1), F.expr("cast(pow(2, 20 - 1.5 * id) as int)"))).alias("i"), F.expr("cast(pow(2, id) as long)").alias("deg"))
    assert theory.fit_alpha(law).first()[0] == pytest.approx(1.5, abs=0.02)


def test_expected_degrees(spark):
    seq = gen.power_law(spark, 1024, 1.5)
    total = seq.agg(F.sum("d")).first()[0]
    g = gen.expected_degree(seq)
    assert abs(g.edges.count() - total / 2) < 0.12 * total / 2
    deg = {r[0]: r[1] for r in g.degrees().collect()}
    top = seq.orderBy(F.desc("d")).limit(20).collect()
    assert abs(sum(deg.get(r[0], 0) for r in top) / sum(r[1] for r in top) - 1) < 0.25


def test_trials_of_expected_degrees_are_not_sent_to_the_driver(spark):
    edges = gen.expected_degree(gen.power_law(spark, 1024, 1.5)).edges
    assert edges.collect()
    assert "BroadcastHashJoin" not in edges._jdf.queryExecution().executedPlan().toString()


def test_generators(spark):
    r = gen.rmat(spark, 7)
    assert r.edges.exceptAll(gen.rmat(spark, 7).edges).count() == 0
    assert gen.complete_bipartite(spark, 3, 4).edges.count() == 12 and gen.star(spark, 5).edges.count() == 5
    assert gen.grid(spark, 3, 4).edges.count() == 17


@pytest.mark.parametrize("kind", ["text", "csv", "json", "orc", "parquet"])
def test_edge_files_round_trip(spark, tmp_path, kind):
    g = gen.grid(spark, 3, 3)
    io.write_edges(g.edges, f"file://{tmp_path}/{kind}", kind)
    back = io.read_edges(spark, f"file://{tmp_path}/{kind}", kind)
    assert sorted(back.edges.collect()) == sorted(g.edges.collect())


def test_bucketed_arcs(spark):
    g = gen.complete(spark, 6)
    g.save_bucketed("arcs_k6", 4)
    back = DataGraph.from_bucketed(spark, "arcs_k6")
    assert count_colorful(back, CATALOGUE["c4"], Coloring(4)).collect() == count_colorful(g, CATALOGUE["c4"], Coloring(4)).collect()
    spark.sql("DROP TABLE arcs_k6")


def test_sql_surface(spark):
    from huecount.functions.udf import register

    register(spark)
    assert spark.sql("SELECT * FROM motif_plan_trees('ab bc cd da ae eb')").count() == 2
    assert spark.sql("SELECT kind FROM decompose('ab bc ca')").first()[0] == "cycle"
    assert spark.sql("SELECT query_aut('ab bc ca')").first()[0] == 6
    rows = spark.read.format("huecount_rmat").option("scale", 6).option("partitions", 3).load()
    assert rows.count() == 16 * 64


def test_timed_reports_failures(spark):
    seconds, status = metrics.timed(lambda: spark.range(10))
    assert status == "ok" and seconds > 0
    assert metrics.timed(lambda: spark.range(1).select(F.raise_error(F.lit("x"))))[1] != "ok"


def test_stream_equals_batch(spark):
    batch = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    for kind in ("tumbling", "session"):
        streamed = windows.run_to_table(windows.windowed_edges(windows.event_stream(spark, SF), kind))
        assert streamed.exceptAll(windows.windowed_edges(batch, kind)).count() == 0
        assert streamed.count() == windows.windowed_edges(batch, kind).count()


def test_stream_sinks_and_state(spark, tmp_path):
    stream = windows.event_stream(spark, SF)
    windows.run_to_parquet(windows.deduplicated(stream), f"file://{tmp_path}/out", f"file://{tmp_path}/log")
    assert spark.read.parquet(f"file://{tmp_path}/out").count() == 1000
    degrees = windows.run_to_table(windows.stateful_degrees(windows.event_stream(spark, SF)), "update").groupBy("user_id").agg(F.max("degree").alias("d"))
    want = spark.read.parquet(f"{SF}/events.parquet").groupBy("user_id").agg(F.countDistinct("event_type").alias("d"))
    assert degrees.exceptAll(want.select("user_id", F.col("d").cast("long"))).count() == 0
    pairs = windows.run_to_table(windows.active_pairs(windows.event_stream(spark, SF)), "append")
    assert pairs.where("ts_b <= ts_a").count() == 0


def test_wedges_survive_a_repeated_batch(spark):
    sink = windows.WindowedWedges(spark)
    batch = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    sink(batch, 0)
    once = sorted(sink.counts().collect())
    sink(batch, 0)
    assert sorted(sink.counts().collect()) == once and math.isfinite(once[0][1])


def test_neighbours_of_unsound_vectors(spark, tmp_path):
    from huecount.sources.views import graph_view

    rows = [(i, [1.0, i / 10, 0.5]) for i in range(12)] + [(20, None), (21, [0.0, 0.0, 0.0]), (22, [1.0, None, 1.0]), (23, [float("nan"), 1.0, 1.0]), (None, [1.0, 1.0, 1.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"file://{tmp_path}/embeddings.parquet")
    edges = graph_view(spark, f"file://{tmp_path}", "knn8").edges.collect()
    assert {v for e in edges for v in e} == set(range(12))


def test_streams_end_in_the_shared_folder(spark):
    before = {t.name for t in spark.catalog.listTables()}
    for stream, mode in ((windows.windowed_edges(windows.event_stream(spark, SF), "tumbling"), "complete"), (windows.deduplicated(windows.event_stream(spark, SF)), "append")):
        got = windows.run_to_table(stream, mode)
        assert got.count() > 0 and got.inputFiles()  # rows are in files, not on the driver
    assert {t.name for t in spark.catalog.listTables()} == before


def test_a_sink_keeps_the_last_whole_result(spark):
    stream = windows.windowed_edges(windows.event_stream(spark, SF), "tumbling")
    sink = windows._Sink(stream, "complete")
    assert sink.rows().count() == 0
    rows = spark.createDataFrame([], stream.schema)
    one = windows.windowed_edges(spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")), "tumbling")
    for number, batch in ((0, rows), (1, one), (1, one)):  # a repeated batch changes nothing
        sink(batch, number)
    assert sorted(sink.rows().collect()) == sorted(one.collect())


def test_pairs_meet_by_slot(spark):
    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    pairs = windows.active_pairs(events)
    assert "slot" in pairs._jdf.queryExecution().optimizedPlan().toString()
    sql = "SELECT count(*) FROM e a JOIN e b ON b.ts > a.ts AND b.ts <= a.ts + interval 10 minutes AND a.event_type = b.event_type AND a.user_id <> b.user_id"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW e AS SELECT * FROM read_parquet('{SF}/events.parquet')")
    assert pairs.count() == con.execute(sql).fetchone()[0] > 0


def test_tables_leave_no_shuffle_files(spark):
    from pyspark.sql import functions as F

    from huecount.session import SWEEP, cut

    def left():
        files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {name for i in range(files.size()) if (name := files.apply(i).getName()).startswith("shuffle_")}

    before, setting = left(), spark.conf.get(SWEEP)
    made = cut(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count())
    assert not left() - before and spark.conf.get(SWEEP) == setting
    assert made.count() == 7
