"""Measures over tables of measurements: (graph, query, strategy, ranks, seconds, ops, status) and trials."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def timed(make: Callable[[], DataFrame]) -> tuple[float, str]:
    """Seconds to produce all rows, and 'ok' or the name of what went wrong."""
    began = time.perf_counter()
    try:
        make().write.format("noop").mode("overwrite").save()
        return time.perf_counter() - began, "ok"
    except Exception as e:  # a cell of the comparison stays blank, with its reason
        return time.perf_counter() - began, type(e).__name__


def averages(df: DataFrame) -> DataFrame:
    """graph, query, level, avg_seconds: by graph, by query, over all. level: grouping_id."""
    df.createOrReplaceTempView("measurements")
    return df.sparkSession.sql(
        "SELECT graph, query, CAST(grouping_id(graph, query) AS INT) AS level, avg(seconds) AS avg_seconds FROM measurements WHERE status = 'ok' GROUP BY GROUPING SETS ((graph), (query), ())"
    )


def improvement(df: DataFrame, base: str = "boundary", ours: str = "degree") -> DataFrame:
    """graph, query, ranks, factor: base's seconds over ours; null where one of them failed."""
    ok = F.when(F.col("status") == "ok", F.col("seconds"))
    wide = df.withColumn("s", ok).groupBy("graph", "query", "ranks").pivot("strategy", [base, ours]).agg(F.max("s"))
    return wide.select("graph", "query", "ranks", F.try_divide(F.col(base), F.col(ours)).alias("factor"))


def improvement_summary(factors: DataFrame) -> DataFrame:
    return factors.groupBy("ranks").agg(
        F.count("factor").alias("cells"),
        (F.count_if(F.col("factor") > 1) / F.count("factor")).alias("share_won"),
        F.max("factor").alias("max_factor"),
        F.avg("factor").alias("avg_factor"),
    )


def if_growth(factors: DataFrame, small: int, large: int) -> DataFrame:
    """graph, query, growth of the improvement factor between two degrees of parallelism."""
    a = factors.where(F.col("ranks") == small).select("graph", "query", F.col("factor").alias("f1"))
    b = factors.where(F.col("ranks") == large).select("graph", "query", F.col("factor").alias("f2"))
    return a.join(b, ["graph", "query"]).select("graph", "query", (F.col("f2") / F.col("f1")).alias("growth"))


def speedup(df: DataFrame, small: int, large: int) -> DataFrame:
    a = df.where(F.col("ranks") == small).select("graph", "query", "strategy", F.col("seconds").alias("s1"))
    b = df.where(F.col("ranks") == large).select("graph", "query", "strategy", F.col("seconds").alias("s2"))
    return a.join(b, ["graph", "query", "strategy"]).select("graph", "query", "strategy", (F.col("s1") / F.col("s2")).alias("speedup"))


def normalize(df: DataFrame, value: str) -> DataFrame:
    """value over the larger of the strategies' values of the same query."""
    return df.withColumn(f"norm_{value}", F.col(value) / F.max(value).over(W.partitionBy("graph", "query", "ranks")))


def plan_error(df: DataFrame) -> DataFrame:
    """df(graph, query, plan, seconds, heuristic) -> graph, query, error and spread (slowest over fastest)."""
    best = F.min("seconds")
    own = F.max(F.when(F.col("heuristic"), F.col("seconds")))
    return df.groupBy("graph", "query").agg(((own - best) / best).alias("error"), (F.max("seconds") / best).alias("spread"))


def variation(trials: DataFrame) -> DataFrame:
    """df(graph, query, trial, cnt) -> cv and variance over mean; null when the mean is 0."""
    x = F.col("cnt").cast("double")
    return trials.groupBy("graph", "query").agg(
        F.count("*").alias("trials"), F.avg(x).alias("mean"), F.try_divide(F.stddev_samp(x), F.avg(x)).alias("cv"), F.try_divide(F.var_samp(x), F.avg(x)).alias("var_over_mean")
    )


def running_cv(trials: DataFrame) -> DataFrame:
    """cv over the first t trials, for every t; the mean of t trials varies by a sqrt(t)-th of it."""
    w = W.partitionBy("graph", "query").orderBy("trial").rowsBetween(W.unboundedPreceding, W.currentRow)
    x = F.col("cnt").cast("double")
    cv = F.try_divide(F.stddev_samp(x).over(w), F.avg(x).over(w))
    return trials.select("graph", "query", "trial", F.count("*").over(w).alias("n"), cv.alias("cv"), (cv / F.sqrt(F.count("*").over(w))).alias("cv_of_mean"))


def cv_share(trials: DataFrame, at: tuple[int, ...] = (3, 10, 50), limit: float = 0.1) -> DataFrame:
    """n, share of (graph, query) whose estimate from the first n trials varies by limit at most."""
    good = F.avg((F.col("cv_of_mean") <= limit).cast("double"))
    return running_cv(trials).where(F.col("n").isin(*at)).groupBy("n").agg(good.alias("share"))


def relative_error(estimates: DataFrame, exact: DataFrame) -> DataFrame:
    joined = estimates.join(exact, ["graph", "query"])
    return joined.select("graph", "query", F.try_divide(F.abs(F.col("estimate_matches") - F.col("exact")), F.col("exact")).alias("relative_error"))


def load_summary(load: DataFrame) -> DataFrame:
    """Candidate and kept rows: total, average and largest over partitions."""
    per_part = load.groupBy("part").agg(F.sum("candidates").alias("candidates"), F.sum("kept").alias("kept"))
    return per_part.agg(
        F.sum("candidates").alias("candidates"), F.sum("kept").alias("kept"), F.avg("candidates").alias("avg_load"), F.max("candidates").alias("max_load")
    )
