"""Bounds on path counts in random graphs of given expected degrees, and tests of their conditions."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def moments(degseq: DataFrame, powers: list[float]) -> dict[float, float]:
    """Sums of powers of d, in one pass."""
    row = degseq.agg(*[F.sum(F.pow("d", F.lit(float(p)))).alias(f"m{i}") for i, p in enumerate(powers)]).first()
    return {p: float(row[i] or 0.0) for i, p in enumerate(powers)}


def balance(degseq: DataFrame, max_a: int = 3, max_b: int = 3) -> float:
    """The largest ratio of the (a+b)-th moment to the product of the a-th and the b-th, over whole a, b from 1:
    the least balance parameter of the sequence. Small if no few vertices dominate the moments."""
    m = moments(degseq, [float(p) for p in range(1, max_a + max_b + 1)])
    return max(m[float(a + b)] / (m[float(a)] * m[float(b)]) for a in range(1, max_a + 1) for b in range(1, max_b + 1))


def power_law_lambda(n: int, alpha: float) -> float:
    return n ** (alpha / 2 - 1)


def degree_histogram(degrees: DataFrame) -> DataFrame:
    """bucket (power of two), cnt."""
    return degrees.groupBy((F.length(F.bin("deg")) - 1).alias("bucket")).agg(F.count("*").alias("cnt"))


def fit_alpha(degrees: DataFrame) -> DataFrame:
    """Slope of the log histogram, sign turned: about alpha for a power law of the form used here."""
    return degree_histogram(degrees).agg((-F.regr_slope(F.log2("cnt"), F.col("bucket"))).alias("alpha"))


def path_probability(ds: list[float], two_m: float) -> float:
    """Chance that given vertices form a path in this order: ends count once, inner ones twice."""
    return math.prod(ds) * math.prod(ds[1:-1]) / two_m ** (len(ds) - 1)


def y_lower(degseq: DataFrame, q: int) -> float:
    m = moments(degseq, [1.0, 2.0])
    return m[1.0] ** (3 - q) * m[2.0] ** (q - 2) / q


def x_upper(degseq: DataFrame, q: int, constant: float = 1.0) -> float:
    p = 2 - 1 / (q - 1)
    m = moments(degseq, [1.0, p])
    return constant * m[1.0] ** (2 - q) * m[p] ** (q - 1)


def moment_inequality(degseq: DataFrame, q: int) -> tuple[float, float]:
    """(left, right) with left <= right by Hoelder: the high-starting bound never exceeds the other by more
    than its constant."""
    p = 2 - 1 / (q - 1)
    m = moments(degseq, [1.0, 2.0, p])
    return m[p] ** (q - 1), m[1.0] * m[2.0] ** (q - 2)


def exponents(alpha: float, q: int) -> dict[str, float]:
    """Powers of n of both bounds for a truncated power law, and their difference. Past the threshold the
    high-starting bound is n times a power of log n."""
    y = alpha - 1 + (2 - alpha) * q / 2
    threshold = 2 - 1 / (q - 1)
    x = 0.5 + (2 - alpha) * (q - 1) / 2 if alpha < threshold else 1.0
    return {"y": y, "x": x, "gain": y - x, "log_power": 0.0 if alpha < threshold else float(q - 1)}


def upper_tail(mu: float, by: float) -> float:
    """Bound on the chance that a sum of independent 0/1 variables with mean mu reaches (1 + by) mu. The orders by
    expected and by actual degree differ for two vertices only if such a sum is far off its mean."""
    return math.exp((1 + by) * mu * (1 - math.log1p(by))) if mu > 0 else 0.0


def lower_tail(mu: float, by: float) -> float:
    """Bound on the chance that such a sum is (1 - by) mu at most, 0 < by < 1."""
    return math.exp(-by * by * mu / 2)


def inversion_bound(large: float, small: float) -> float:
    """Bound on the chance that a vertex of expected degree small ends up with a degree no less than one of expected
    degree large, for small up to a twentieth of large: one of both sums has to cross the middle between the means."""
    if 20 * small > large:
        raise ValueError("the bound holds for expected degrees that are twenty times apart")
    middle = (large + small) / 2
    return min(1.0, lower_tail(large, 1 - middle / large) + (upper_tail(small, middle / small - 1) if small > 0 else 0.0))


def gain_exponent(alpha: float, q: int) -> float:
    return exponents(alpha, q)["gain"]
