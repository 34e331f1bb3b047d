"""All registered queries of the motif engine and their DuckDB formulations."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount import experiments, session, sqltext
from huecount.functions import metrics, theory, udf
from huecount.functions.coloring import Coloring, TableColoring, affine_sql
from huecount.operators import direct, estimate, exact, joins, paths, solve
from huecount.operators.graph import DataGraph, dense_rank, id_of, profile
from huecount.operators.joins import Context
from huecount.plans.plan import decompose, enumerate_plans, plan_for, validate
from huecount.plans.query import CATALOGUE, QueryGraph, automorphisms, is_treewidth_le2, parse
from huecount.session import cut
from huecount.sources import generators
from huecount.sources.views import VIEW_SQL, VIEWS, graph_view, table
from huecount.streaming import windows

Make = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Make] = {}
_SQL: dict[str, str] = {}


def add(name: str, make: Make, sql: str | None = None) -> None:
    if name in _QUERIES:
        raise ValueError(f"{name} is there already")
    _QUERIES[name] = make
    if sql is not None:
        _SQL[name] = sql


def queries() -> dict[str, Make]:
    return _QUERIES


def oracle_sql() -> dict[str, str]:
    return _SQL


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return estimate.count(graph_view(spark, sf_dir, "supply_chain"), CATALOGUE["house"], trials=3)


# --- views, profiles, orders ------------------------------------------------------------------------


def _profiles(spark: SparkSession, d: str) -> DataFrame:
    return reduce(DataFrame.unionByName, [profile(graph_view(spark, d, v)) for v in VIEWS])


for _v in VIEWS:
    add(f"view_{_v}", lambda s, d, v=_v: graph_view(s, d, v).edges, VIEW_SQL[_v])
add("profile_all", _profiles, " UNION ALL ".join(f"SELECT * FROM ({sqltext.profile(v)})" for v in VIEWS))
add(
    "degree_order",
    lambda s, d: dense_rank(graph_view(s, d, "supply_chain")),
    sqltext.arcs_with("supply_chain", "SELECT v, deg, row_number() OVER (ORDER BY deg, v) - 1 AS rank FROM d"),
)
add(
    "degree_log2_histogram",
    lambda s, d: theory.degree_histogram(graph_view(s, d, "word_adj").degrees()),
    sqltext.arcs_with("word_adj", "SELECT (length(bin(deg)) - 1)::INTEGER AS bucket, count(*) AS cnt FROM d GROUP BY 1"),
)
add(
    "balance_moments",
    lambda s, d: graph_view(s, d, "word_adj").degrees().agg(*[F.sum(reduce(lambda a, b: a * b, [F.col("deg")] * p)).alias(f"m{p}") for p in (1, 2, 3)]),
    sqltext.arcs_with("word_adj", "SELECT sum(deg)::BIGINT AS m1, sum(deg*deg)::BIGINT AS m2, sum(deg*deg*deg)::BIGINT AS m3 FROM d"),
)

# --- colours and single steps of block evaluation ----------------------------------------------------


def _ids(df: DataFrame, *keys: str) -> DataFrame:
    return df.withColumns({k: id_of(F.col(k)) for k in keys})


def _context(s: SparkSession, d: str, view: str, k: int) -> Context:
    return Context(graph_view(s, d, view), Coloring(k, "affine"))


def _bit(v: str, k: int) -> str:
    return f"(1::BIGINT << ({affine_sql(v, k)})::INTEGER)"


def _colored(view: str, k: int, rest: str) -> str:
    """SQL over b(src, dst, b1, b2): arcs with colour bits of both ends."""
    return sqltext.arcs_with(view, f", b AS MATERIALIZED (SELECT src, dst, {_bit('src', k)} AS b1, {_bit('dst', k)} AS b2 FROM a) {rest}")


add(
    "colour_classes_k5",
    lambda s, d: graph_view(s, d, "user_hour").degrees().groupBy(Coloring(5, "affine").color(F.col("v"), F.lit(0)).alias("color")).agg(F.count("*").alias("cnt")),
    sqltext.arcs_with("user_hour", f"SELECT {affine_sql('v', 5)} AS color, count(*) AS cnt FROM d GROUP BY 1"),
)
add(
    "seed_edges_k5",
    lambda s, d: _ids(joins.seed_edge(_context(s, d, "user_hour", 5), False), "h", "tail").select("h", "tail", "sig", "cnt"),
    _colored("user_hour", 5, "SELECT src AS h, dst AS tail, b1 | b2 AS sig, 1::BIGINT AS cnt FROM b WHERE b1 <> b2"),
)


def _path(ctx: Context, vertices: int, high: bool) -> DataFrame:
    return joins.bare_path(ctx, vertices, high)


_HIGHER = "(x.deg > {0}.deg OR (x.deg = {0}.deg AND x.v > {0}.v))"
for _name, _view in (("order_part", "order_part"), ("user_hour", "user_hour")):
    for _n in (3, 4):
        for _high in (False, True):
            _frm = "b s1 JOIN b s2 ON s2.src = s1.dst AND (s1.b1 | s1.b2) & s2.b2 = 0"
            _last, _sig = "s2", "s1.b1 | s1.b2 | s2.b2"
            if _n == 4:
                _frm += " JOIN b s3 ON s3.src = s2.dst AND (s1.b1 | s1.b2 | s2.b2) & s3.b2 = 0"
                _last, _sig = "s3", "s1.b1 | s1.b2 | s2.b2 | s3.b2"
            _where = "s1.b1 <> s1.b2"
            if _high:
                _frm += " JOIN d x ON x.v = s1.src" + "".join(f" JOIN d y{i} ON y{i}.v = s{i}.dst" for i in range(1, _n))
                _where += "".join(" AND " + _HIGHER.format(f"y{i}") for i in range(1, _n))
            add(
                f"path{_n}_{_name}_{'high' if _high else 'boundary'}",
                lambda s, d, v=_view, n=_n, high=_high: _ids(_path(_context(s, d, v, 4), n, high), "h", "tail").select("h", "tail", "sig", "cnt"),
                _colored(_view, 4, f"SELECT s1.src AS h, {_last}.dst AS tail, {_sig} AS sig, count(*)::BIGINT AS cnt FROM {_frm} WHERE {_where} GROUP BY ALL"),
            )


def _leaf(ctx: Context) -> DataFrame:
    return joins.seed_edge(ctx, False).groupBy("trial", F.col("h").alias("u"), "sig").agg(F.sum("cnt").alias("cnt"))


add(
    "leaf_block",
    lambda s, d: _ids(_leaf(_context(s, d, "user_hour", 4)), "u").select("u", "sig", "cnt"),
    _colored("user_hour", 4, "SELECT src AS u, b1 | b2 AS sig, count(*)::BIGINT AS cnt FROM b WHERE b1 <> b2 GROUP BY ALL"),
)


def _node_join(s: SparkSession, d: str, hash_small: bool = False) -> DataFrame:
    ctx = _context(s, d, "user_hour", 4)
    ctx.hash_small = hash_small
    return _ids(joins.attach_node(ctx, joins.seed_edge(ctx, False), _leaf(ctx), "tail"), "h", "tail").select("h", "tail", "sig", "cnt")


add(
    "node_join",
    _node_join,
    _colored("user_hour", 4, "SELECT s.src AS h, s.dst AS tail, s.b1 | s.b2 | t.b2 AS sig, count(*)::BIGINT AS cnt FROM b s JOIN b t ON t.src = s.dst WHERE s.b1 <> s.b2 AND (s.b1 | s.b2) & t.b2 = 0 GROUP BY ALL"),
)


def _binary(ctx: Context, n: int) -> DataFrame:
    p = _path(ctx, n, False)
    return p.select("trial", F.col("h").alias("u"), F.col("tail").alias("v"), "sig", "cnt")


def _edge_join(s: SparkSession, d: str) -> DataFrame:
    ctx = _context(s, d, "succession", 4)
    return _ids(joins.extend_block(ctx, joins.seed_edge(ctx, False), _binary(ctx, 3), True, False, bare=3), "h", "tail").select("h", "tail", "sig", "cnt")


_PATH4_SQL = "FROM b s1 JOIN b s2 ON s2.src = s1.dst AND (s1.b1 | s1.b2) & s2.b2 = 0 JOIN b s3 ON s3.src = s2.dst AND (s1.b1 | s1.b2 | s2.b2) & s3.b2 = 0 WHERE s1.b1 <> s1.b2 GROUP BY ALL"
add("edge_join", _edge_join, _colored("succession", 4, f"SELECT s1.src AS h, s3.dst AS tail, s1.b1 | s1.b2 | s2.b2 | s3.b2 AS sig, count(*)::BIGINT AS cnt {_PATH4_SQL}"))
add(
    "transpose",
    lambda s, d: _ids(joins.transpose(_binary(_context(s, d, "user_hour", 4), 3)), "u", "v").select("u", "v", "sig", "cnt"),
    _colored("user_hour", 4, "SELECT s2.dst AS u, s1.src AS v, s1.b1 | s1.b2 | s2.b2 AS sig, count(*)::BIGINT AS cnt FROM b s1 JOIN b s2 ON s2.src = s1.dst AND (s1.b1 | s1.b2) & s2.b2 = 0 WHERE s1.b1 <> s1.b2 GROUP BY ALL"),
)


def _merge(s: SparkSession, d: str) -> DataFrame:
    ctx = _context(s, d, "user_hour", 4)
    p = _path(ctx, 3, False)
    return _ids(joins.merge_paths(ctx, p, p, {"u": "h", "v": "tail"}), "u", "v").select("u", "v", "sig", "cnt")


_C4 = "FROM b s1 JOIN b s2 ON s2.src = s1.dst AND (s1.b1 | s1.b2) & s2.b2 = 0 JOIN b s3 ON s3.src = s2.dst AND (s1.b1 | s1.b2 | s2.b2) & s3.b2 = 0 JOIN b s4 ON s4.src = s3.dst AND s4.dst = s1.src WHERE s1.b1 <> s1.b2 GROUP BY ALL"
add("merge_paths", _merge, _colored("user_hour", 4, f"SELECT s1.src AS u, s2.dst AS v, s1.b1 | s1.b2 | s2.b2 | s3.b2 AS sig, count(*)::BIGINT AS cnt {_C4}"))


def _block_table(s: SparkSession, d: str, boundary: tuple[str, ...], strategy: str) -> DataFrame:
    """The table of a bare four-cycle a-b-c-d with given boundary nodes."""
    from huecount.plans.plan import Block, Plan

    block = Block(0, "cycle", tuple("abcd"), boundary)
    solver = solve.Solver(_context(s, d, "succession", 5), Plan(CATALOGUE["c4"], (block,)), strategy)
    out = solver.cycle(block)
    return _ids(out, *"uv"[: len(boundary)]).select(*"uv"[: len(boundary)], "sig", "cnt")


_ENDS = {"config_a": ("a", "c"), "config_b": ("a", "b"), "one_boundary": ("a",)}
_AT = {"a": "s1.src", "b": "s2.src", "c": "s3.src"}
for _name, _ends in _ENDS.items():
    for _s in solve.STRATEGIES:
        _cols = ", ".join(f"{_AT[x]} AS {c}" for c, x in zip("uv", _ends, strict=False))
        add(
            f"cycle_table_{_name}_{_s}",
            lambda s, d, e=_ends, st=_s: _block_table(s, d, e, st),
            _colored("succession", 5, f"SELECT {_cols}, s1.b1 | s1.b2 | s2.b2 | s3.b2 AS sig, count(*)::BIGINT AS cnt {_C4}"),
        )

# --- colourful counts: every strategy on every view that a self-join can check -------------------------


def _colorful(s: SparkSession, d: str, view: str, q: QueryGraph, strategy: str) -> DataFrame:
    return solve.count_colorful(graph_view(s, d, view), q, Coloring(q.k, "affine"), strategy).select("cnt")


_CELLS = [("user_hour", "c4"), ("order_part", "c4"), ("succession", "triangle"), ("succession", "c4"), ("supply_chain", "triangle"), ("supply_chain", "paw")]
_CELLS += [(v, q) for v in ("page_anchor", "knn8") for q in ("triangle", "c4", "c5", "paw", "diamond", "bull", "bowtie", "house", "c4_tail", "fan5", "k23", "c6", "ladder6", "c4_c5", "path4", "star4")]
for _view, _q in _CELLS:
    for _s in solve.STRATEGIES:
        add(f"colorful_{_q}_{_view}_{_s}", lambda s, d, v=_view, q=_q, st=_s: _colorful(s, d, v, CATALOGUE[q], st), sqltext.colorful(_view, CATALOGUE[_q]))
for _q in ("path4", "star4"):
    add(f"colorful_{_q}_order_part", lambda s, d, q=_q: _colorful(s, d, "order_part", CATALOGUE[q], "degree"), sqltext.colorful("order_part", CATALOGUE[_q]))
for _q in ("c4_c6", "cactus10", "satellite11", "c8"):
    add(f"strategies_agree_{_q}", lambda s, d, q=_q: _agree(s, d, "knn8", q), f"SELECT '{_q}' AS query, 3 AS strategies, true AS agree")
add(
    "colorful_bintree12_page_anchor",
    lambda s, d: solve.count_colorful(graph_view(s, d, "page_anchor"), CATALOGUE["bintree12"], Coloring(12, "affine"), plan=decompose(CATALOGUE["bintree12"])).select("cnt"),
    sqltext.tree("page_anchor", CATALOGUE["bintree12"]),
)
for _o in ("id", "random"):
    add(
        f"colorful_house_knn8_by_{_o}",
        lambda s, d, o=_o: solve.count_colorful(graph_view(s, d, "knn8").with_order(o), CATALOGUE["house"], Coloring(5, "affine")).select("cnt"),
        sqltext.colorful("knn8", CATALOGUE["house"]),
    )


def _agree(s: SparkSession, d: str, view: str, name: str) -> DataFrame:
    """Whether all strategies give the same number of matches; for queries too large for a self-join in SQL."""
    q = CATALOGUE[name]
    g = graph_view(s, d, view)
    g.arcs()
    counts = [solve.count_colorful(g, q, Coloring(q.k, "affine"), st, plan_for(q)).select("cnt") for st in solve.STRATEGIES]
    return reduce(DataFrame.union, counts).agg(F.lit(name).alias("query"), F.count("*").cast("int").alias("strategies"), (F.countDistinct("cnt") == 1).alias("agree"))


# Every plan's tables from their definition, on the complete graph of six classes of line numbers.
_K6 = "SELECT a.i AS src, b.i AS dst FROM (SELECT DISTINCT l_linenumber::BIGINT % 6 AS i FROM lineitem) a JOIN (SELECT DISTINCT l_linenumber::BIGINT % 6 AS i FROM lineitem) b ON a.i < b.i"
_PRODUCTS = ("triangle", "paw", "diamond", "house", "bull", "c4_tail")


def _products(s: SparkSession, d: str) -> DataFrame:
    g, rows = generators.complete_of(table(s, d, "lineitem").select((F.col("l_linenumber") % 6).alias("v"))), []
    for n in _PRODUCTS:
        q = CATALOGUE[n]
        got = direct.count_by_products(Context(g, Coloring(q.k, "affine")), plan_for(q))
        rows.append(s.range(1).join(got, F.lit(True), "left").select(F.lit(n).alias("query"), F.coalesce("cnt", F.lit(0)).alias("cnt")))
    return reduce(DataFrame.unionByName, rows)


add("direct_products_k6", _products, " UNION ALL ".join(f"SELECT '{n}' AS query, cnt FROM ({sqltext.colorful_of(_K6, CATALOGUE[n])})" for n in _PRODUCTS))


# --- estimates -----------------------------------------------------------------------------------------


def _trials(s: SparkSession, d: str, n: int) -> DataFrame:
    return estimate.trials_of(graph_view(s, d, "user_hour"), CATALOGUE["c4"], n, kind="affine")


def _trials_sql(n: int) -> str:
    one = [sqltext.colorful("user_hour", CATALOGUE["c4"], trial=str(t)) for t in range(n)]
    return " UNION ALL ".join(f"SELECT {t}::INTEGER AS trial, cnt FROM ({x})" for t, x in enumerate(one))


_SUMMARY = """SELECT 'c4' AS query, 'user_hour' AS graph, count(*) AS trials, count(*) FILTER (cnt > 0) AS nonzero, avg(cnt) AS mean_colorful,
  avg(cnt) * (256.0::DOUBLE / 24) AS estimate_matches, 8 AS aut, avg(cnt) * (256.0::DOUBLE / 24) / 8 AS estimate_subgraphs, var_samp(cnt) AS variance,
  stddev_samp(cnt) / nullif(avg(cnt), 0) AS cv, var_samp(cnt) / nullif(avg(cnt), 0) AS var_over_mean FROM ({})"""
for _n in (3, 10):
    add(f"estimate_trials_{_n}", lambda s, d, n=_n: _trials(s, d, n), _trials_sql(_n))
add("estimate_summary_10", lambda s, d: estimate.summary(_trials(s, d, 10), CATALOGUE["c4"], "user_hour"), _SUMMARY.format(_trials_sql(10)))
add("estimate_house_supply_chain", lambda s, d: estimate.count(graph_view(s, d, "supply_chain"), CATALOGUE["house"], trials=1))
add("estimate_adaptive_c4", lambda s, d: estimate.until(graph_view(s, d, "user_hour"), CATALOGUE["c4"], cv=0.2, max_trials=12))

add(
    "estimate_interval_10",
    lambda s, d: estimate.interval(estimate.summary(_trials(s, d, 10), CATALOGUE["c4"], "user_hour"), 4).select("query", F.round("low", 3).alias("low"), F.round("high", 3).alias("high")),
    f"SELECT query, round(estimate_matches - h, 3) AS low, round(estimate_matches + h, 3) AS high FROM (SELECT *, 1.96 * (256.0::DOUBLE / 24) * sqrt(variance / trials) AS h FROM ({_SUMMARY.format(_trials_sql(10))}))",
)
add(
    "estimate_relative_error",
    lambda s, d: metrics.relative_error(
        estimate.summary(_trials(s, d, 10), CATALOGUE["c4"], "user_hour"),
        exact.four_cycles(graph_view(s, d, "user_hour")).select(F.lit("user_hour").alias("graph"), F.lit("c4").alias("query"), (8 * F.col("cnt")).alias("exact")),
    ).select("graph", "query", F.round("relative_error", 9).alias("relative_error")),
    f"SELECT 'user_hour' AS graph, 'c4' AS query, round(abs(estimate_matches - exact) / nullif(exact, 0), 9) AS relative_error FROM ({_SUMMARY.format(_trials_sql(10))}), (SELECT cnt AS exact FROM ({sqltext.exact('user_hour', CATALOGUE['c4'])}))",
)


def _every_colouring(s: SparkSession, d: str) -> DataFrame:
    """Colourful triangles of the complete graph of four classes of hours, under 81 explicit colourings: the number of events of a
    class among every 81st event, modulo 3."""
    e = table(s, d, "events").select((F.col("event_id") % 81).cast("int").alias("trial"), (F.hour("ts") % 4).cast("long").alias("v"))
    cells = e.select("trial").distinct().crossJoin(e.select("v").distinct()).join(e.groupBy("trial", "v").count(), ["trial", "v"], "left")
    coloring = TableColoring.from_df(cells.select("trial", "v", (F.coalesce("count", F.lit(0)) % 3).cast("long").alias("color")), 3)
    return solve.count_colorful(generators.complete_of(e), CATALOGUE["triangle"], coloring)


add(
    "explicit_colourings_k4",
    _every_colouring,
    """WITH e AS (SELECT event_id % 81 AS t, hour(ts) % 4 AS v FROM events), n AS (SELECT t, v, count(*) AS n FROM e GROUP BY ALL),
    c AS (SELECT t, v, coalesce(n, 0) % 3 AS c FROM (SELECT DISTINCT t FROM e) CROSS JOIN (SELECT DISTINCT v FROM e) LEFT JOIN n USING (t, v))
    SELECT a.t::INTEGER AS trial, (count(*) FILTER (a.c <> b.c AND a.c <> z.c AND b.c <> z.c))::BIGINT AS cnt FROM c a JOIN c b ON a.t = b.t AND a.v <> b.v JOIN c z ON a.t = z.t AND z.v <> a.v AND z.v <> b.v GROUP BY a.t""",
)

# --- exact counts and path counts ------------------------------------------------------------------------

for _v in ("succession", "user_hour", "knn8", "supply_chain", "order_part"):
    add(f"exact_triangle_{_v}", lambda s, d, v=_v: exact.triangles(graph_view(s, d, v)), f"SELECT (cnt // 6)::BIGINT AS cnt FROM ({sqltext.exact(_v, CATALOGUE['triangle'])})")
    add(f"exact_wedge_{_v}", lambda s, d, v=_v: exact.wedges(graph_view(s, d, v)), sqltext.arcs_with(_v, "SELECT (sum(deg * (deg - 1)) // 2)::BIGINT AS cnt FROM d"))
_CODEGREE = "SELECT (coalesce(sum(c * (c - 1) / 2), 0) / 2)::BIGINT AS cnt FROM (SELECT x.dst AS p, y.dst AS q, count(*) AS c FROM a x JOIN a y ON x.src = y.src AND x.dst < y.dst GROUP BY ALL)"
for _v in ("succession", "user_hour", "knn8", "order_part"):
    add(f"exact_c4_{_v}", lambda s, d, v=_v: exact.four_cycles(graph_view(s, d, v)), sqltext.arcs_with(_v, _CODEGREE))
for _v in ("succession", "knn8"):
    add(f"exact_paw_{_v}", lambda s, d, v=_v: exact.paws(graph_view(s, d, v)), sqltext.exact(_v, CATALOGUE["paw"]))
add("brute_force_house_knn8", lambda s, d: exact.brute_force(graph_view(s, d, "knn8"), CATALOGUE["house"]), sqltext.exact("knn8", CATALOGUE["house"]))
add("brute_force_c4_page_anchor", lambda s, d: exact.brute_force(graph_view(s, d, "page_anchor"), CATALOGUE["c4"]), sqltext.exact("page_anchor", CATALOGUE["c4"]))
add(
    "induced_path3_knn8",
    lambda s, d: exact.brute_force(graph_view(s, d, "knn8"), QueryGraph("p3", ("a", "b", "c"), (("a", "b"), ("b", "c"))), induced=True),
    sqltext.arcs_with("knn8", "SELECT count(*)::BIGINT AS cnt FROM a x JOIN a y ON x.dst = y.src AND x.src <> y.dst WHERE NOT EXISTS (SELECT 1 FROM a z WHERE z.src = x.src AND z.dst = y.dst)"),
)
add("closed_walks_4_knn8", lambda s, d: exact.closed_walks(graph_view(s, d, "knn8"), 4), sqltext.arcs_with("knn8", "SELECT count(*)::BIGINT AS cnt FROM a p JOIN a q ON q.src = p.dst JOIN a r ON r.src = q.dst JOIN a s ON s.src = r.dst AND s.dst = p.src"))
add(
    "colorful_brute_force_c4_user_hour",
    lambda s, d: exact.colorful_brute_force(graph_view(s, d, "user_hour"), CATALOGUE["c4"], Coloring(4, "affine")),
    sqltext.colorful("user_hour", CATALOGUE["c4"]),
)
add(
    "subgraphs_by_automorphisms",
    lambda s, d: reduce(DataFrame.unionByName, [exact.brute_force(graph_view(s, d, "knn8"), CATALOGUE[n]).select(F.lit(n).alias("query"), (F.col("cnt") / automorphisms(CATALOGUE[n])).cast("long").alias("subgraphs")) for n in ("triangle", "c4", "paw", "diamond")]),
    " UNION ALL ".join(f"SELECT '{n}' AS query, (cnt // {a})::BIGINT AS subgraphs FROM ({sqltext.exact('knn8', CATALOGUE[n])})" for n, a in (("triangle", 6), ("c4", 8), ("paw", 2), ("diamond", 4))),
)
for _v in ("user_hour", "order_part", "page_anchor"):
    for _n in (3, 4):
        add(f"x{_n}_{_v}", lambda s, d, v=_v, n=_n: paths.count_x(graph_view(s, d, v), n), sqltext.paths(_v, _n, "degree"))
        add(f"y{_n}_{_v}", lambda s, d, v=_v, n=_n: paths.count_y(graph_view(s, d, v), n), sqltext.paths(_v, _n, "id"))
        add(f"p{_n}_{_v}", lambda s, d, v=_v, n=_n: paths.count_paths(graph_view(s, d, v), n), sqltext.paths(_v, _n, None))

# --- load ----------------------------------------------------------------------------------------------


def _load(s: SparkSession, d: str, strategy: str, g: DataGraph | None = None) -> DataFrame:
    return solve.load(g or graph_view(s, d, "user_hour"), CATALOGUE["c4"], Coloring(4, "affine"), strategy)


def _loads(s: SparkSession, d: str) -> DataFrame:
    """One graph for all strategies; what a strategy has shuffled goes before the next one runs."""
    g = graph_view(s, d, "user_hour")
    return reduce(DataFrame.unionByName, [cut(metrics.load_summary(_load(s, d, st, g)).select(F.lit(st).alias("strategy"), "*"), "load") for st in solve.STRATEGIES])


add(
    "load_by_step_boundary",
    lambda s, d: _load(s, d, "boundary").groupBy(F.regexp_extract("step", r"/(\w+)#", 1).alias("step")).agg(F.sum("candidates").alias("candidates"), F.sum("kept").alias("kept")),
    _colored(
        "user_hour",
        4,
        """, p AS (SELECT s1.src AS h, s1.dst AS m, s2.dst AS t, (s1.b1 | s1.b2) AS g, s2.b2 AS w FROM b s1 JOIN b s2 ON s2.src = s1.dst WHERE s1.b1 <> s1.b2),
        g AS (SELECT h, t, g | w AS sig, count(*) AS c FROM p WHERE g & w = 0 GROUP BY ALL)
        SELECT 'seed' AS step, count(*)::BIGINT AS candidates, (count(*) FILTER (b1 <> b2))::BIGINT AS kept FROM b
        UNION ALL SELECT 'extend', count(*), count(*) FILTER (g & w = 0) FROM p
        UNION ALL SELECT 'merge', count(*), count(*) FILTER ((x.sig & y.sig) = (%s | %s)) FROM g x JOIN g y ON x.h = y.h AND x.t = y.t"""
        % (_bit("x.h", 4), _bit("x.t", 4)),
    ),
)
add("load_avg_max", _loads)

# --- measured on the views: work in candidate rows, which no machine changes ------------------------------

_LOAD_CELLS = {"part_supplier": ("c4",), "page_anchor": ("c4",), "knn8": ("paw", "house"), "user_hour": ("c4",)}
_PLAN_QUERIES = ("paw", "diamond", "house")


def _on_view(s: SparkSession, d: str, view: str, measure: Callable[[DataGraph], list]) -> list:
    """What is told of a view; its tables go when it has been told."""
    since = session.made()
    told = measure(graph_view(s, d, view))
    session.release(s, since)
    return told


def _measured_loads(s: SparkSession, d: str) -> DataFrame:
    rows = [r for v, qs in _LOAD_CELLS.items() for r in _on_view(s, d, v, lambda g, qs=qs: experiments.loads(g, qs, ("boundary", "degree")))]
    return s.createDataFrame(rows, experiments.LOAD)


add("improvement_by_load", lambda s, d: experiments.improvement_by_load(_measured_loads(s, d)))
add("normalized_load", lambda s, d: metrics.normalize(_measured_loads(s, d).withColumn("ranks", F.lit(1)), "candidates").drop("ranks"))
add("plan_error_by_load", lambda s, d: metrics.plan_error(experiments.plan_loads(graph_view(s, d, "knn8"), _PLAN_QUERIES)))


def _best_plans(s: SparkSession, d: str) -> DataFrame:
    """For each query whether no plan has a smaller load than the one that measurement chooses, and how many there are."""
    g, rows = graph_view(s, d, "knn8"), []
    for n in ("paw", "diamond", "house"):
        best, costs = experiments.best_by_cost(g, CATALOGUE[n], "boundary")
        own = experiments.load_of(g, CATALOGUE[n], "boundary", best)[0]
        rows.append((n, len(costs), own == min(c for _, c in costs)))
    return s.createDataFrame(rows, "query string, plans int, least boolean")


add("best_plan_by_load", _best_plans, "SELECT * FROM (VALUES ('paw', 3, true), ('diamond', 2, true), ('house', 2, true)) AS t(query, plans, least)")
add(
    "table_sizes_within_bound",
    lambda s, d: reduce(DataFrame.unionByName, [experiments.table_sizes(graph_view(s, d, "knn8"), CATALOGUE[n]) for n in ("house", "bull")]).groupBy("query").agg(F.count("*").alias("blocks"), F.bool_and(F.col("rows") <= F.col("bound")).alias("within")),
    "SELECT * FROM (VALUES ('house', 2, true), ('bull', 3, true)) AS t(query, blocks, within)",
)


def _measured_trials(s: SparkSession, d: str, n: int) -> DataFrame:
    cells = (("user_hour", "c4"), ("knn8", "paw"), ("part_supplier", "c4"))
    rows = [r for v, q in cells for r in _on_view(s, d, v, lambda g, q=q: experiments.trial_counts(g, CATALOGUE[q], n, 25).collect())]
    return s.createDataFrame(rows, "graph string, query string, trial int, cnt double")


add("variation_measured", lambda s, d: metrics.variation(_measured_trials(s, d, 50)))
add("cv_share_measured", lambda s, d: metrics.cv_share(_measured_trials(s, d, 50)))

# --- plans ---------------------------------------------------------------------------------------------

# Fixed queries: two that need more than two, a grid, and some of the catalogue.
_WIDTHS = [("k4", "ab ac ad bc bd cd"), ("k33", "ax ay az bx by bz cx cy cz"), ("grid9", "ab bc de ef gh hi ad dg be eh cf fi"), *[(n, CATALOGUE[n].text()) for n in ("c8", "k23", "bintree12")]]
# Fixed values of the catalogue: trees, automorphisms.
_TREES = {"satellite11": (13, 2), "triangle": (1, 6), "c4": (1, 8), "c5": (1, 10), "c6": (1, 12), "c8": (1, 16), "paw": (3, 2), "diamond": (2, 4), "bull": (9, 2), "bowtie": (2, 8),
          "house": (2, 2), "c4_tail": (3, 2), "ladder6": (2, 4), "c4_c6": (2, 2), "c4_c5": (2, 2), "cactus10": (10, 4), "fan5": (3, 2), "k23": (3, 12), "path4": (4, 2), "star4": (4, 6)}
add(
    "plan_trees",
    lambda s, d: s.createDataFrame([(n, len(enumerate_plans(CATALOGUE[n])), automorphisms(CATALOGUE[n])) for n in _TREES], "query string, trees int, aut int"),
    "SELECT * FROM (VALUES " + ", ".join(f"('{n}', {t}, {a})" for n, (t, a) in _TREES.items()) + ") AS t(query, trees, aut)",
)
add(
    "plan_blocks_satellite11",
    lambda s, d: plan_for(CATALOGUE["satellite11"]).to_df(s).select("kind", F.concat_ws("", F.array_sort(F.split("nodes", ""))).alias("nodes"), F.concat_ws("", F.array_sort(F.split("boundary", ""))).alias("boundary"), "subquery"),
    "SELECT * FROM (VALUES ('cycle', 'abcde', 'ac', 5), ('leaf', 'fh', 'f', 2), ('cycle', 'acfg', 'fg', 8), ('cycle', 'fgi', 'i', 9), ('cycle', 'ijk', '', 11)) AS t(kind, nodes, boundary, subquery)",
)
add(
    "plan_heuristic",
    lambda s, d: s.createDataFrame([(n, plan_for(CATALOGUE[n]).cost_key()[0]) for n in _TREES], "query string, longest int"),
    "SELECT * FROM (VALUES " + ", ".join(f"('{n}', {x})" for n, x in {"satellite11": 5, "triangle": 3, "c4": 4, "c5": 5, "c6": 6, "c8": 8, "paw": 3, "diamond": 3, "bull": 3, "bowtie": 3, "house": 4, "c4_tail": 4, "ladder6": 4, "c4_c6": 6, "c4_c5": 5, "cactus10": 4, "fan5": 3, "k23": 4, "path4": 0, "star4": 0}.items()) + ") AS t(query, longest)",
)

# --- measures on a fixed table of measurements -----------------------------------------------------------

_ROWS = [("g1", "q1", "boundary", 1, 8.0, "ok"), ("g1", "q1", "degree", 1, 2.0, "ok"), ("g1", "q1", "boundary", 4, 3.0, "ok"), ("g1", "q1", "degree", 4, 0.5, "ok"), ("g1", "q2", "boundary", 1, 1.0, "ok"),
         ("g1", "q2", "degree", 1, 2.0, "ok"), ("g1", "q2", "boundary", 4, 0.75, "ok"), ("g1", "q2", "degree", 4, 0.5, "ok"), ("g2", "q1", "boundary", 1, 9.0, "OutOfMemory"), ("g2", "q1", "degree", 1, 6.0, "ok"),
         ("g2", "q1", "boundary", 4, 4.0, "ok"), ("g2", "q1", "degree", 4, 2.0, "ok")]
_M = "(SELECT * FROM (VALUES " + ", ".join(f"('{a}', '{b}', '{c}', {r}, {x}::DOUBLE, '{o}')" for a, b, c, r, x, o in _ROWS) + ") AS t(graph, query, strategy, ranks, seconds, status))"
_T = [("g1", "q1", t, 90 + (t * 37) % 23) for t in range(10)] + [("g2", "q1", t, 10 + (t * 53) % 91) for t in range(10)] + [("g3", "q1", t, 0) for t in range(10)]
_TS = "(SELECT * FROM (VALUES " + ", ".join(f"('{a}', '{b}', {t}, {c}::BIGINT)" for a, b, t, c in _T) + ") AS t(graph, query, trial, cnt))"
_PL = [("g1", "q1", 0, 2.0, True), ("g1", "q1", 1, 8.0, False), ("g1", "q2", 0, 2.25, True), ("g1", "q2", 1, 2.0, False), ("g1", "q2", 2, 26.0, False)]
_PS = "(SELECT * FROM (VALUES " + ", ".join(f"('{a}', '{b}', {p}, {x}::DOUBLE, {str(h).lower()})" for a, b, p, x, h in _PL) + ") AS t(graph, query, plan, seconds, heuristic))"


def _measurements(s: SparkSession) -> DataFrame:
    return s.createDataFrame(_ROWS, "graph string, query string, strategy string, ranks int, seconds double, status string")


def _trial_rows(s: SparkSession) -> DataFrame:
    return s.createDataFrame(_T, "graph string, query string, trial int, cnt long")


# Measurements counted from a given table: whole numbers of lines as seconds, so that sums are exact in any order.
_LINES = """(SELECT 'g' || l_suppkey % 5 AS graph, 'q' || l_partkey % 3 AS query, CASE WHEN l_quantity < 25 THEN 'degree' ELSE 'boundary' END AS strategy,
    CASE WHEN l_orderkey % 3 = 0 THEN 4 ELSE 1 END AS ranks, count(*)::DOUBLE AS seconds, CASE WHEN min(l_orderkey) % 7 = 0 THEN 'OutOfMemory' ELSE 'ok' END AS status FROM lineitem GROUP BY 1, 2, 3, 4)"""
_HOURS = "(SELECT event_type AS graph, 'q' || user_id % 2 AS query, hour(ts)::INTEGER AS trial, count(*) AS cnt FROM events GROUP BY 1, 2, 3)"


def _line_counts(s: SparkSession, d: str) -> DataFrame:
    """graph, query, strategy, ranks, seconds, status from lineitem: lines of a class of suppliers and one of parts, by quantity and order."""
    name = lambda letter, column, n: F.concat(F.lit(letter), (F.col(column) % n).cast("string"))
    cells = table(s, d, "lineitem").groupBy(
        name("g", "l_suppkey", 5).alias("graph"),
        name("q", "l_partkey", 3).alias("query"),
        F.when(F.col("l_quantity") < 25, "degree").otherwise("boundary").alias("strategy"),
        F.when(F.col("l_orderkey") % 3 == 0, 4).otherwise(1).alias("ranks"),
    )
    status = F.when(F.min("l_orderkey") % 7 == 0, "OutOfMemory").otherwise("ok")
    return cells.agg(F.count("*").cast("double").alias("seconds"), status.alias("status"))


def _hour_counts(s: SparkSession, d: str) -> DataFrame:
    """graph, query, trial, cnt from events: a type, one of two classes of users, an hour of the day."""
    query = F.concat(F.lit("q"), (F.col("user_id") % 2).cast("string"))
    return table(s, d, "events").groupBy(F.col("event_type").alias("graph"), query.alias("query"), F.hour("ts").alias("trial")).agg(F.count("*").alias("cnt"))


_FACTOR = f"(SELECT graph, query, ranks, max(seconds) FILTER (strategy = 'boundary' AND status = 'ok') / max(seconds) FILTER (strategy = 'degree' AND status = 'ok') AS factor FROM {_LINES} GROUP BY ALL)"
add("averages_cube", lambda s, d: metrics.averages(_line_counts(s, d)), f"SELECT graph, query, grouping_id(graph, query)::INTEGER AS level, avg(seconds) AS avg_seconds FROM {_LINES} WHERE status = 'ok' GROUP BY GROUPING SETS ((graph), (query), ())")
add("improvement_matrix", lambda s, d: metrics.improvement(_line_counts(s, d)), f"SELECT * FROM {_FACTOR}")
add("improvement_summary", lambda s, d: metrics.improvement_summary(metrics.improvement(_line_counts(s, d))), f"SELECT ranks, count(factor) AS cells, (count(*) FILTER (factor > 1))::DOUBLE / count(factor) AS share_won, max(factor) AS max_factor, avg(factor) AS avg_factor FROM {_FACTOR} GROUP BY ranks")
add("if_growth", lambda s, d: metrics.if_growth(metrics.improvement(_line_counts(s, d)), 1, 4), f"SELECT a.graph, a.query, b.factor / a.factor AS growth FROM {_FACTOR} a JOIN {_FACTOR} b ON a.graph = b.graph AND a.query = b.query AND a.ranks = 1 AND b.ranks = 4")
add("speedup", lambda s, d: metrics.speedup(_measurements(s), 1, 4), f"SELECT a.graph, a.query, a.strategy, a.seconds / b.seconds AS speedup FROM {_M} a JOIN {_M} b USING (graph, query, strategy) WHERE a.ranks = 1 AND b.ranks = 4")
add("normalized_time", lambda s, d: metrics.normalize(_line_counts(s, d), "seconds"), f"SELECT *, seconds / max(seconds) OVER (PARTITION BY graph, query, ranks) AS norm_seconds FROM {_LINES}")
add("plan_error", lambda s, d: metrics.plan_error(s.createDataFrame(_PL, "graph string, query string, plan int, seconds double, heuristic boolean")), f"SELECT graph, query, (max(seconds) FILTER (heuristic) - min(seconds)) / min(seconds) AS error, max(seconds) / min(seconds) AS spread FROM {_PS} GROUP BY ALL")
add("variation", lambda s, d: metrics.variation(_trial_rows(s)), f"SELECT graph, query, count(*) AS trials, avg(cnt) AS mean, stddev_samp(cnt) / nullif(avg(cnt), 0) AS cv, var_samp(cnt) / nullif(avg(cnt), 0) AS var_over_mean FROM {_TS} GROUP BY ALL")
_RUN_OF = "(SELECT graph, query, trial, count(*) OVER w AS n, stddev_samp(cnt) OVER w / nullif(avg(cnt) OVER w, 0) AS cv FROM {} WINDOW w AS (PARTITION BY graph, query ORDER BY trial ROWS UNBOUNDED PRECEDING))"
_RUN = _RUN_OF.format(_TS)
add("running_cv", lambda s, d: metrics.running_cv(_trial_rows(s)).select("graph", "query", "trial", "n", F.round("cv", 9).alias("cv")), f"SELECT graph, query, trial, n, round(cv, 9) AS cv FROM {_RUN}")
add("cv_share", lambda s, d: metrics.cv_share(_hour_counts(s, d), (3, 10)), f"SELECT n, avg(CASE WHEN cv / sqrt(n) <= 0.1 THEN 1.0 WHEN cv IS NULL THEN NULL ELSE 0.0 END) AS share FROM {_RUN_OF.format(_HOURS)} WHERE n IN (3, 10) GROUP BY n")
add("cube_loads", lambda s, d: _line_counts(s, d).cube("strategy", "query").agg(F.sum("seconds").alias("seconds"), F.grouping_id().cast("int").alias("level")), f"SELECT strategy, query, sum(seconds) AS seconds, grouping_id(strategy, query)::INTEGER AS level FROM {_LINES} GROUP BY CUBE (strategy, query)")

# --- generators ------------------------------------------------------------------------------------------

add(
    "grid_edges",
    lambda s, d: generators.grid_of(table(s, d, "orders").select(F.col("o_orderkey").alias("v")), 30).edges,
    "WITH v AS (SELECT DISTINCT o_orderkey AS i FROM orders) SELECT a.i AS src, b.i AS dst FROM v a JOIN v b ON b.i = a.i + 1 WHERE a.i % 30 < 29 UNION ALL SELECT a.i, b.i FROM v a JOIN v b ON b.i = a.i + 30",
)
add(
    "complete_edges",
    lambda s, d: generators.complete_of(table(s, d, "lineitem").select(F.col("l_quantity").alias("v"))).edges,
    "WITH v AS (SELECT DISTINCT l_quantity::BIGINT AS i FROM lineitem) SELECT a.i AS src, b.i AS dst FROM v a JOIN v b ON a.i < b.i",
)
add("rmat_edges", lambda s, d: generators.rmat(s, 8, draw=generators.portable).edges, generators.rmat_sql(8))
add("expected_degree_edges", lambda s, d: generators.expected_degree(_degrees_as_d(s, d, "user_hour").select("v", "d")).edges)


def _xy(s: SparkSession, d: str) -> DataFrame:
    """q, x, y on one expected-degree graph, with the bounds of its degree sequence."""
    seq = generators.power_law(s, 1024, 1.5)
    g, rows = generators.expected_degree(seq), []
    for q in (3, 4):
        rows.append((q, paths.count_x(g, q).first()[0], paths.count_y(g, q).first()[0], theory.x_upper(seq, q), theory.y_lower(seq, q)))
    return s.createDataFrame(rows, "q int, x long, y long, x_upper double, y_lower double")


add("x_y_bounds", _xy)
_BALANCED = ("user_hour", "order_part", "knn8")
_RATIOS = ", ".join(f"m{a + b} / (m{a} * m{b})" for a in (1, 2, 3) for b in (1, 2, 3))
add(
    "degree_balance",
    lambda s, d: s.createDataFrame([(round(theory.balance(_degrees_as_d(s, d, v)), 9), v) for v in _BALANCED], "balance double, view string"),
    " UNION ALL ".join(f"SELECT round(x, 9) AS balance, '{v}' AS view FROM ({sqltext.arcs_with(v, f', m AS (SELECT {', '.join(f'sum(deg::DOUBLE ** {p}) AS m{p}' for p in range(1, 7))} FROM d) SELECT greatest({_RATIOS}) AS x FROM m')})" for v in _BALANCED),
)


def _degrees_as_d(s: SparkSession, d: str, view: str) -> DataFrame:
    return graph_view(s, d, view).degrees().withColumn("d", F.col("deg").cast("double"))


def _bounds(s: SparkSession, d: str) -> DataFrame:
    """Logarithms of both bounds and of the two sides of the inequality between them, for the degrees of a view."""
    seq, rows = _degrees_as_d(s, d, "user_hour"), []
    for q in (3, 4, 5):
        left, right = theory.moment_inequality(seq, q)
        rows.append((q, *[round(math.log10(x), 6) for x in (theory.x_upper(seq, q), theory.y_lower(seq, q), left, right)], left <= right))
    return s.createDataFrame(rows, "q int, x_upper double, y_lower double, left_side double, right_side double, holds boolean")


add(
    "theory_bounds_user_hour",
    _bounds,
    " UNION ALL ".join(
        "SELECT * FROM (" + sqltext.arcs_with(
            "user_hour",
            f", m AS (SELECT sum(deg)::DOUBLE AS m1, sum(deg * deg)::DOUBLE AS m2, sum(deg::DOUBLE ** {2 - 1 / (q - 1)}) AS mp FROM d) SELECT {q}::INTEGER AS q, round(log10(m1 ** {2 - q} * mp ** {q - 1}), 6) AS x_upper, round(log10(m1 ** {3 - q} * m2 ** {q - 2} / {q}), 6) AS y_lower, round(log10(mp ** {q - 1}), 6) AS left_side, round(log10(m1 * m2 ** {q - 2}), 6) AS right_side, mp ** {q - 1} <= m1 * m2 ** {q - 2} AS holds FROM m",
        ) + ")"
        for q in (3, 4, 5)
    ),
)
_ALPHAS = [(a / 10, q) for a in range(11, 20) for q in (3, 4, 5)]
add(
    "theory_exponents",
    lambda s, d: s.createDataFrame([(a, q, round(e["y"], 9), round(e["x"], 9), round(e["gain"], 9), e["log_power"], round(theory.power_law_lambda(10_000, a), 9)) for a, q in _ALPHAS for e in [theory.exponents(a, q)]], "alpha double, q int, y double, x double, gain double, log_power double, balance double"),
    "SELECT alpha, q, round(y, 9) AS y, round(x, 9) AS x, round(y - x, 9) AS gain, log_power, round(10000 ** (alpha / 2 - 1), 9) AS balance FROM (SELECT *, alpha - 1 + (2 - alpha) * q / 2 AS y, CASE WHEN alpha < 2 - 1 / (q - 1)::DOUBLE THEN 0.5 + (2 - alpha) * (q - 1) / 2 ELSE 1.0::DOUBLE END AS x, CASE WHEN alpha < 2 - 1 / (q - 1)::DOUBLE THEN 0.0::DOUBLE ELSE (q - 1)::DOUBLE END AS log_power FROM (VALUES "
    + ", ".join(f"({a}::DOUBLE, {q})" for a, q in _ALPHAS)
    + ") AS t(alpha, q))",
)
_MEANS = [(20.0, 1.0), (100.0, 2.0), (400.0, 20.0), (1000.0, 5.0)]
add(
    "theory_inversions",
    lambda s, d: s.createDataFrame([(a, b, round(theory.inversion_bound(a, b), 12)) for a, b in _MEANS], "large double, small double, bound double"),
    "SELECT large, small, round(least(1.0::DOUBLE, exp(-1 * pow((large - m) / large, 2) * large / 2) + exp(m * (1 - ln(m / small)))), 12) AS bound FROM (SELECT *, (large + small) / 2 AS m FROM (VALUES " + ", ".join(f"({a}::DOUBLE, {b}::DOUBLE)" for a, b in _MEANS) + ") AS t(large, small))",
)
_PATH = [(2.0, 3.0, 4.0), (1.0, 5.0, 2.0), (3.0, 3.0, 3.0)]
add(
    "theory_path_probability",
    lambda s, d: s.createDataFrame([(*x, round(theory.path_probability(list(x), 10.0), 9)) for x in _PATH], "a double, b double, c double, p double"),
    "SELECT a, b, c, round(a * b * b * c / 100, 9) AS p FROM (VALUES " + ", ".join(f"({a}::DOUBLE, {b}::DOUBLE, {c}::DOUBLE)" for a, b, c in _PATH) + ") AS t(a, b, c)",
)
add(
    "treewidth_test",
    lambda s, d: s.createDataFrame([(n, is_treewidth_le2(parse(t))) for n, t in _WIDTHS], "query string, at_most_two boolean"),
    "SELECT * FROM (VALUES ('k4', false), ('k33', false), ('grid9', false), ('c8', true), ('k23', true), ('bintree12', true)) AS t(query, at_most_two)",
)
add(
    "plan_widths",
    lambda s, d: s.createDataFrame([(n, max(map(validate, enumerate_plans(CATALOGUE[n]))) <= 2) for n in _TREES], "query string, within_two boolean"),
    "SELECT query, true AS within_two FROM (VALUES " + ", ".join(f"('{n}')" for n in _TREES) + ") AS t(query)",
)

# --- joins, sets and windows that users of the views need --------------------------------------------------


def _range_join(s: SparkSession, d: str, minutes: int = 10) -> DataFrame:
    """Different users within some minutes: an equi-join on slots of that length and the next one."""
    e = table(s, d, "events").select("event_id", "user_id", F.expr("timestampdiff(MICROSECOND, timestamp_ntz'2024-01-01 00:00:00', ts)").alias("t"))
    span = minutes * 60_000_000
    a = e.select(F.col("user_id").alias("src"), F.col("t").alias("ta"), F.explode(F.array(F.floor(F.col("t") / span), F.floor(F.col("t") / span) + 1)).alias("slot"))
    b = e.select(F.col("user_id").alias("dst"), F.col("t").alias("tb"), F.floor(F.col("t") / span).alias("slot"))
    return a.join(b, "slot").where(f"tb > ta AND tb <= ta + {span} AND src <> dst").groupBy("src", "dst").agg(F.count("*").alias("n"))


add(
    "range_join_succession",
    _range_join,
    "SELECT a.user_id AS src, b.user_id AS dst, count(*) AS n FROM events a JOIN events b ON b.ts > a.ts AND b.ts <= a.ts + interval 10 minutes AND a.user_id <> b.user_id GROUP BY ALL",
)


def _asof_every(s: SparkSession, d: str) -> DataFrame:
    """For every event its user's last event before it."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return table(s, d, "events").select("event_id", "user_id", F.lag("event_id").over(w).alias("before"))


add(
    "asof_every_event",
    _asof_every,
    "SELECT event_id, user_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events",
)


def _core_sql(view: str, least: int) -> str:
    step = lambda e: f"(SELECT src, dst FROM {e} WHERE src IN (SELECT v FROM (SELECT src AS v FROM {e} UNION ALL SELECT dst FROM {e}) GROUP BY v HAVING count(*) >= {least}) AND dst IN (SELECT v FROM (SELECT src AS v FROM {e} UNION ALL SELECT dst FROM {e}) GROUP BY v HAVING count(*) >= {least}))"
    return f"WITH e0 AS MATERIALIZED ({VIEW_SQL[view]}), e1 AS MATERIALIZED (SELECT * FROM {step('e0')}), e2 AS MATERIALIZED (SELECT * FROM {step('e1')}) SELECT src, dst FROM e2"


def _peel(s: SparkSession, d: str) -> DataFrame:
    from huecount.operators.graph import prune

    return prune(graph_view(s, d, "knn8"), 7, 2).edges


add("peel_degree_7_twice", _peel, _core_sql("knn8", 7))


def _edges(s: SparkSession, d: str, v: str) -> DataFrame:
    return graph_view(s, d, v).edges


for _name, _f, _op in (("union", DataFrame.union, "UNION"), ("intersect", DataFrame.intersect, "INTERSECT"), ("except", DataFrame.subtract, "EXCEPT")):
    add(
        f"edges_{_name}",
        lambda s, d, f=_f: f(_edges(s, d, "customer_part"), _edges(s, d, "order_part")).distinct(),
        f"SELECT src, dst FROM ({VIEW_SQL['customer_part']}) {_op} SELECT src, dst FROM ({VIEW_SQL['order_part']})",
    )


def _lateral(s: SparkSession, d: str) -> DataFrame:
    for t in ("nation", "customer"):
        table(s, d, t).createOrReplaceTempView(f"lat_{t}")
    return s.sql(
        "SELECT n_nationkey, c_custkey FROM lat_nation, LATERAL (SELECT c_custkey FROM lat_customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)"
    )


add("lateral_topk", _lateral, "SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")
add(
    "value_percentiles",
    lambda s, d: table(s, d, "events").groupBy("event_type").agg(*[F.round(F.percentile("value", p / 100), 6).alias(f"p{p}") for p in (25, 50, 90)]),
    "SELECT event_type, round(quantile_cont(value, 0.25), 6) AS p25, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type",
)
add(
    "event_quarters",
    lambda s, d: table(s, d, "events").withColumn("quarter", F.ntile(4).over(W.partitionBy("user_id").orderBy("ts", "event_id"))).groupBy("quarter").agg(F.count("*").alias("n"), F.max("event_id").alias("last")),
    "SELECT quarter::INTEGER AS quarter, count(*) AS n, max(event_id) AS last FROM (SELECT event_id, ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS quarter FROM events) GROUP BY 1",
)
add(
    "profile_long",
    lambda s, d: profile(graph_view(s, d, "user_hour")).unpivot("view", ["nodes", "edges", "max_deg"], "measure", "value"),
    f"SELECT view, measure, value FROM (SELECT view, nodes, edges, max_deg FROM ({sqltext.profile('user_hour')})) UNPIVOT (value FOR measure IN (nodes, edges, max_deg))",
)
add(
    "cv_by_aggregate_function",
    lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.round(udf.cv("value"), 6).alias("cv")),
    "SELECT event_type, round(stddev_samp(value) / avg(value), 6) AS cv FROM events GROUP BY event_type",
)
add(
    "ego_triangles_knn8",
    lambda s, d: udf.ego_triangles(graph_view(s, d, "knn8")).groupBy("triangles").agg(F.count("*").alias("vertices")),
    sqltext.arcs_with("knn8", """, t AS (SELECT x.src AS v, count(*) AS triangles FROM a x JOIN d dx ON dx.v = x.src JOIN d dy ON dy.v = x.dst JOIN a z ON z.src = x.dst JOIN d dz ON dz.v = z.dst JOIN a c ON c.src = x.src AND c.dst = z.dst
        WHERE (dx.deg, dx.v) < (dy.deg, dy.v) AND (dy.deg, dy.v) < (dz.deg, dz.v) GROUP BY x.src) SELECT triangles::BIGINT AS triangles, count(*) AS vertices FROM t GROUP BY 1"""),
)


def _cogrouped(s: SparkSession, d: str) -> DataFrame:
    a, b = (_block_table(s, d, ("a", "b"), st) for st in ("boundary", "degree"))
    return udf.differences(a, b, ["u", "v", "sig"])


add("cogrouped_differences", _cogrouped, "SELECT 0::BIGINT AS differing")
add(
    "motif_count_view",
    lambda s, d: udf.motif_count(s, d, [("user_hour", "c4")], 3) and s.sql("SELECT query, graph, trials, mean_colorful FROM motif_count"),
    f"SELECT 'c4' AS query, 'user_hour' AS graph, count(*) AS trials, avg(cnt) AS mean_colorful FROM ({_trials_sql(3)})",
)
add(
    "node_join_shuffled_hash",
    lambda s, d: _node_join(s, d, True),
    _SQL["node_join"],
)
add(
    "json_props",
    lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"), F.count("*").alias("n")),
    "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k, count(*) AS n FROM events GROUP BY event_type",
)
add(
    "turn_succession",
    lambda s, d: table(s, d, "conversations")
    .withColumn("next", F.lead("role").over(W.partitionBy("conv_id").orderBy("turn", "role", "text")))
    .where("next is not null")
    .groupBy("role", "next")
    .agg(F.count("*").alias("n")),
    "SELECT role, next, count(*) AS n FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS next FROM conversations) WHERE next IS NOT NULL GROUP BY ALL",
)
add(
    "good_document_words",
    lambda s, d: table(s, d, "documents").join(table(s, d, "labels").where("quality = 1"), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars")),
    "SELECT lang, count(*) AS docs, sum(n_chars)::BIGINT AS chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1) GROUP BY lang",
)

# --- streaming ------------------------------------------------------------------------------------------------


def _stream_sql(kind: str) -> str:
    if kind == "session":
        return """WITH s AS (SELECT *, sum(new) OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS g FROM (SELECT *,
            CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) < interval 30 minutes THEN 0 ELSE 1 END AS new FROM events))
            SELECT epoch_us(min(ts)) AS win_start, epoch_us(max(ts) + interval 30 minutes) AS win_end, user_id, event_type, count(*) AS n FROM s GROUP BY user_id, event_type, g"""
    step = 86_400_000_000 if kind == "tumbling" else 43_200_000_000
    shift = "" if kind == "tumbling" else f"UNION ALL SELECT *, epoch_us(ts) - epoch_us(ts) % {step} - {step} AS w FROM events"
    return f"SELECT w AS win_start, w + 86400000000 AS win_end, user_id, event_type, count(*) AS n FROM (SELECT *, epoch_us(ts) - epoch_us(ts) % {step} AS w FROM events {shift}) GROUP BY ALL"


def _micros(df: DataFrame) -> DataFrame:
    return df.withColumns({"win_start": F.unix_micros("win_start"), "win_end": F.unix_micros("win_end")})


def _batch_events(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


for _k in ("tumbling", "sliding", "session"):
    add(f"windowed_edges_{_k}", lambda s, d, k=_k: _micros(windows.windowed_edges(_batch_events(s, d), k)), _stream_sql(_k))


def _streamed(s: SparkSession, d: str, kind: str) -> DataFrame:
    return _micros(windows.run_to_table(windows.windowed_edges(windows.event_stream(s, d), kind)))


add("streamed_edges_tumbling", lambda s, d: _streamed(s, d, "tumbling"), _stream_sql("tumbling"))
add(
    "streamed_wedges",
    lambda s, d: windows.WindowedWedges(s).drive(windows.event_stream(s, d)).withColumn("day", F.col("day").cast("string")),
    """WITH e AS (SELECT DISTINCT ts::DATE AS day, user_id, event_type FROM events)
    SELECT day::VARCHAR AS day, sum(c * (c - 1) // 2)::BIGINT AS wedges FROM (SELECT day, count(*) AS c FROM e GROUP BY day, user_id UNION ALL SELECT day, count(*) FROM e GROUP BY day, event_type) GROUP BY day""",
)
add(
    "streamed_four_cycles",
    lambda s, d: windows.FourCycles(s).drive(windows.event_stream(s, d)).select(F.col("day").cast("string").alias("day"), "cnt"),
    """WITH e AS (SELECT DISTINCT ts::DATE AS day, user_id, event_type FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL),
    p AS (SELECT day, a.event_type AS x, b.event_type AS y, count(*) AS c FROM e a JOIN e b USING (day, user_id) WHERE a.event_type < b.event_type GROUP BY ALL)
    SELECT day::VARCHAR AS day, sum(c * (c - 1) // 2)::BIGINT AS cnt FROM p GROUP BY day""",
)
add(
    "streamed_by_nation",
    lambda s, d: _micros(windows.run_to_table(windows.by_nation(windows.event_stream(s, d), table(s, d, "customer")), "append")),
    """SELECT w AS win_start, w + 86400000000 AS win_end, nation, count(*) AS n FROM (SELECT epoch_us(ts) - epoch_us(ts) % 86400000000 AS w, c_nationkey AS nation FROM events JOIN customer ON c_custkey = user_id)
    WHERE w + 86400000000 <= (SELECT epoch_us(max(ts)) - 3600000000 FROM events) GROUP BY w, nation""",
)
add(
    "streamed_degrees",
    lambda s, d: windows.run_to_table(windows.stateful_degrees(windows.event_stream(s, d)), "update").groupBy("user_id").agg(F.max("degree").alias("degree"), F.max("seen").alias("seen")),
    "SELECT user_id, count(DISTINCT event_type) AS degree, count(*) AS seen FROM events GROUP BY user_id",
)
add(
    "streamed_once",
    lambda s, d: windows.run_to_table(windows.deduplicated(windows.event_stream(s, d)), "append").groupBy("event_type").agg(F.count("*").alias("n")),
    "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type",
)
add(
    "streamed_active_pairs",
    lambda s, d: windows.run_to_table(windows.active_pairs(windows.event_stream(s, d)), "append").groupBy("src", "dst").agg(F.count("*").alias("n")),
    "SELECT a.user_id AS src, b.user_id AS dst, count(*) AS n FROM events a JOIN events b ON b.ts > a.ts AND b.ts <= a.ts + interval 10 minutes AND a.event_type = b.event_type AND a.user_id <> b.user_id GROUP BY ALL",
)
