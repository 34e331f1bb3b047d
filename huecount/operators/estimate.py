"""Unbiased estimates from colourful counts."""

from __future__ import annotations

from decimal import Decimal
from fractions import Fraction
from math import factorial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from huecount.functions.coloring import Coloring
from huecount.operators.graph import DataGraph
from huecount.operators.solve import count_colorful
from huecount.plans.plan import Plan
from huecount.plans.query import QueryGraph, automorphisms


def scale(k: int) -> Fraction:
    """One over the chance that k given vertices get k different colours."""
    return Fraction(k**k, factorial(k))


def summary(counts: DataFrame, q: QueryGraph, graph: str) -> DataFrame:
    """One row from (trial, cnt): means, estimates, spread. cv is null when the mean is 0."""
    s, x = float(scale(q.k)), F.col("cnt").cast("double")
    aut = automorphisms(q)
    return counts.agg(
        F.lit(q.name).alias("query"),
        F.lit(graph).alias("graph"),
        F.count("*").alias("trials"),
        F.count_if(F.col("cnt") > 0).alias("nonzero"),
        F.avg(x).alias("mean_colorful"),
        (F.avg(x) * s).alias("estimate_matches"),
        F.lit(aut).alias("aut"),
        (F.avg(x) * s / aut).alias("estimate_subgraphs"),
        F.var_samp(x).alias("variance"),
        F.try_divide(F.stddev_samp(x), F.avg(x)).alias("cv"),
        F.try_divide(F.var_samp(x), F.avg(x)).alias("var_over_mean"),
    )


def interval(row_summary: DataFrame, k: int, z: float = 1.96) -> DataFrame:
    """Normal interval of the estimate."""
    half = z * float(scale(k)) * F.sqrt(F.col("variance") / F.col("trials"))
    return row_summary.withColumns({"low": F.col("estimate_matches") - half, "high": F.col("estimate_matches") + half})


def trials_of(g: DataGraph, q: QueryGraph, trials: int = 10, strategy: str = "degree", kind: str = "xxhash", seed: int = 1, plan: Plan | None = None) -> DataFrame:
    """trial, cnt: all colourings in one job."""
    return count_colorful(g, q, Coloring(q.k, kind, seed, trials), strategy, plan)


def count(g: DataGraph, q: QueryGraph, trials: int = 10, **options) -> DataFrame:
    return summary(trials_of(g, q, trials, **options), q, g.name)


def until(g: DataGraph, q: QueryGraph, cv: float = 0.1, batch: int = 3, max_trials: int = 50, seed: int = 1, strategy: str = "degree", history: str | None = None) -> DataFrame:
    """Batches of colourings until the standard error over the mean is at most cv, or max_trials are done.
    history: a folder where counts are appended, and from which a stopped run goes on."""
    spark: SparkSession = g.spark
    got: list[tuple[int, int]] = []
    if history is not None:
        got = _resumed(spark, history, g.name, q.name)
    while len(got) < max_trials:
        if len(got) >= 2:
            mean = sum(c for _, c in got) / len(got)
            var = sum((c - mean) ** 2 for _, c in got) / (len(got) - 1)
            if mean > 0 and (var / len(got)) ** 0.5 / mean <= cv:
                break
        n = min(batch, max_trials - len(got))
        rows = trials_of(g, q, n, strategy, seed=seed + 1000 * len(got)).collect()  # a number a trial
        new = [(len(got) + i, int(r[1])) for i, r in enumerate(sorted(rows))]
        got += new
        if history is not None:
            frame = spark.createDataFrame([(g.name, q.name, t, Decimal(c)) for t, c in new], "graph string, query string, trial int, cnt decimal(38,0)")
            frame.write.mode("append").partitionBy("query").parquet(history)
    return summary(spark.createDataFrame([(t, Decimal(c)) for t, c in got], "trial int, cnt decimal(38,0)"), q, g.name)


def _resumed(spark: SparkSession, history: str, graph: str, query: str) -> list[tuple[int, int]]:
    try:
        old = spark.read.parquet(history).where((F.col("graph") == graph) & (F.col("query") == query))
    except Exception as e:
        if "PATH_NOT_FOUND" in str(e):
            return []
        raise
    return sorted((r["trial"], int(r["cnt"])) for r in old.collect())
