"""The SQL surface: table functions over queries and plans, a scalar for automorphisms, a view of estimates; an aggregate
function, and checks that group rows in Python."""

from __future__ import annotations

from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType

from huecount.operators import estimate
from huecount.operators.graph import DataGraph, id_of
from huecount.plans.plan import PLAN_SCHEMA, enumerate_plans, plan_for
from huecount.plans.query import CATALOGUE, automorphisms, parse
from huecount.session import cut
from huecount.sources.io import RmatSource
from huecount.sources.views import graph_view


@F.pandas_udf(DoubleType())
def cv(x: pd.Series) -> float:
    """Coefficient of variation of a group, as an aggregate function; null if the mean is 0. It holds a group in memory: the
    built-in form stddev_samp / avg is the one to use on large groups."""
    mean = x.mean()
    return float(x.std(ddof=1) / mean) if len(x) > 1 and mean else None


def ego_triangles(g: DataGraph) -> DataFrame:
    """v, triangles of every vertex, each counted by hand in the graph of its higher neighbours: a check of the joins."""
    up = g.arcs().where("src < dst")
    a, b = up.select(F.col("src").alias("v"), F.col("dst").alias("x")), up.select(F.col("src").alias("v"), F.col("dst").alias("y"))
    inner = up.select(F.col("src").alias("x"), F.col("dst").alias("y"))
    ego = a.join(inner, "x").join(b.withColumnRenamed("v", "w"), "y").where("v = w").select("v", "x", "y")

    def count(key, rows: pd.DataFrame) -> pd.DataFrame:
        near: dict[int, set[int]] = {}
        for x, y in zip(rows["x"], rows["y"], strict=True):
            near.setdefault(x, set()).add(y)
        return pd.DataFrame({"v": [key[0]], "triangles": [sum(map(len, near.values()))]})

    counted = ego.groupBy("v").applyInPandas(count, "v long, triangles long")
    return counted.select(id_of(F.col("v")).alias("v"), "triangles")


#: Rows of both tables that one call compares, in the mean.
COMPARED = 1 << 16


def differences(a: DataFrame, b: DataFrame, by: list[str], value: str = "cnt") -> DataFrame:
    """How many keys two tables disagree on, by grouping both together: keys that a hash puts together are compared in one call."""

    def compare(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        rows = pd.concat([left[[*by, value]].assign(more=1), right[[*by, value]].assign(more=-1)])
        more = rows.groupby([*by, value], dropna=False)["more"].sum()
        return pd.DataFrame({"differing": [len(more[more != 0].reset_index()[by].drop_duplicates())]})

    a, b = cut(a.select(*by, value), "left"), cut(b.select(*by, value), "right")
    lots = 1 + (a.count() + b.count()) // COMPARED
    a, b = (x.withColumn("lot", F.pmod(F.xxhash64(*by), F.lit(lots))) for x in (a, b))
    each = a.groupBy("lot").cogroup(b.groupBy("lot")).applyInPandas(compare, "differing long")
    return each.agg(F.coalesce(F.sum("differing"), F.lit(0)).alias("differing"))


def motif_count(spark: SparkSession, sf_dir: str, cells: list[tuple[str, str]], trials: int = 3) -> DataFrame:
    """Estimates of (view, query) cells, also as the temporary view motif_count."""
    rows = [estimate.count(graph_view(spark, sf_dir, v), CATALOGUE[q], trials, kind="affine") for v, q in cells]
    made = reduce(DataFrame.unionByName, rows)
    made.createOrReplaceTempView("motif_count")
    return made


def register(spark: SparkSession) -> None:
    """decompose(text), motif_plan_trees(text), query_aut(text), and the huecount_rmat source."""

    @F.udtf(returnType=PLAN_SCHEMA)
    class Decompose:
        def eval(self, text: str):
            yield from plan_for(parse(text)).rows()

    @F.udtf(returnType="tree int, longest int, boundary int, annotations int, chosen boolean")
    class PlanTrees:
        def eval(self, text: str):
            for i, p in enumerate(enumerate_plans(parse(text))):
                yield (i, *p.cost_key()[:3], i == 0)

    @F.pandas_udf(LongType())
    def query_aut(text: pd.Series) -> pd.Series:
        return text.map(lambda t: automorphisms(parse(t)))

    spark.udtf.register("decompose", Decompose)
    spark.udtf.register("motif_plan_trees", PlanTrees)
    spark.udf.register("query_aut", query_aut)
    spark.udf.register("cv", cv)
    spark.dataSource.register(RmatSource)
