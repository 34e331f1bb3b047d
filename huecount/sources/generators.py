"""Synthetic graphs, generated by the executors from hashes: the same seed gives the same edges anywhere."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from huecount.operators.graph import DataGraph, simple_edges
from huecount.session import cut


def uniform(*parts) -> Column:
    """In [0, 1), a hash of the parts."""
    return F.pmod(F.xxhash64(*[p if isinstance(p, Column) else F.lit(p) for p in parts]), F.lit(1 << 52)) / float(1 << 52)


# Fixed values of the portable draw: a prime below 2^31 and three factors.
PRIME, FACTORS = 2147483647, (48271, 69621, 16807)


def portable(v: Column, level: int, seed: int) -> Column:
    """In [0, 1), by whole numbers that any SQL engine computes alike; slower than ``uniform`` to mix, but no hash."""
    x = (v * FACTORS[0] + (level + 1) * FACTORS[1] + seed * FACTORS[2]) % PRIME
    for _ in range(3):
        x = (x * x + v + level + 1) % PRIME
    return x / F.lit(float(PRIME))


def rmat_sql(scale: int, edge_factor: int = 16, a: float = 0.5, b: float = 0.1, c: float = 0.1, seed: int = 1) -> str:
    """The edges of ``rmat`` with the portable draw, as SQL text."""
    rounds = f"SELECT id, l, (id * {FACTORS[0]} + (l + 1) * {FACTORS[1]} + {seed * FACTORS[2]}) % {PRIME} AS x FROM range({edge_factor << scale}) t(id), range({scale}) u(l)"
    for _ in range(3):
        rounds = f"SELECT id, l, (x * x + id + l + 1) % {PRIME} AS x FROM ({rounds})"
    ends = f"SELECT id, l, CASE WHEN u >= {a + b} THEN 1 ELSE 0 END AS high, CASE WHEN u >= {a} AND u < {a + b} THEN 1 WHEN u >= {a + b + c} THEN 1 ELSE 0 END AS low FROM (SELECT id, l, x / {PRIME}::DOUBLE AS u FROM ({rounds}))"
    both = f"SELECT sum(high << ({scale - 1} - l)::INTEGER)::BIGINT AS p, sum(low << ({scale - 1} - l)::INTEGER)::BIGINT AS q FROM ({ends}) GROUP BY id"
    return f"SELECT DISTINCT least(p, q) AS src, greatest(p, q) AS dst FROM ({both}) WHERE p <> q"


def rmat(spark: SparkSession, scale: int, edge_factor: int = 16, a: float = 0.5, b: float = 0.1, c: float = 0.1, d: float = 0.3, seed: int = 1, draw=None) -> DataGraph:
    """2^scale vertices, edge_factor edges a vertex before loops and repeats go. Each bit of both ends is
    one draw among the four quadrants. draw(id, level, seed): numbers in [0, 1); by default a hash."""
    draw = draw or (lambda v, level, seed: uniform(v, seed, level))
    if abs(a + b + c + d - 1) > 1e-9:
        raise ValueError("quadrant shares add up to 1")
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        u = draw(F.col("id"), level, seed)
        low = F.when((u >= a) & (u < a + b), 1).when(u >= a + b + c, 1).otherwise(0)
        high = F.when(u >= a + b, 1).otherwise(0)
        src, dst = src * 2 + high, dst * 2 + low
    raw = spark.range(edge_factor << scale).select(src.cast("long").alias("src"), dst.cast("long").alias("dst"))
    return DataGraph(f"rmat{scale}", simple_edges(raw))


def power_law(spark: SparkSession, n: int, alpha: float) -> DataFrame:
    """v, d: about n / 2^(alpha j) vertices with degrees in [2^j, 2^(j+1)), j up to half of log2 n."""
    top = int(math.log2(n) / 2)
    sizes = [n / 2 ** (alpha * j) for j in range(top + 1)]
    edges, at = [], 0.0
    for s in sizes:
        at += s / sum(sizes) * n
        edges.append(at)
    j = F.lit(top)
    for k in range(top - 1, -1, -1):
        j = F.when(F.col("id") < math.floor(edges[k]), k).otherwise(j)
    d = F.least(F.pow(F.lit(2.0), j) * (1 + uniform(F.col("id"), "degree")), F.lit(math.sqrt(n)))
    return spark.range(n).select(F.col("id").alias("v"), d.alias("d"))


def expected_degree(degseq: DataFrame, seed: int = 1) -> DataGraph:
    """Each pair is an edge with probability d_u d_v / 2m. Vertices are classed by the power of two their
    degree lies under; for a pair of classes the number of trials is drawn as if all had the classes' upper
    bounds, ends are drawn evenly within the classes, and a trial is kept with the ratio of its true
    probability to the bound. Work is in proportion to edges, not pairs. Repeats collapse."""
    spark = degseq.sparkSession
    classed = degseq.withColumn("c", F.floor(F.log2("d")).cast("int"))
    from pyspark.sql import Window as W

    numbered = cut(classed.withColumn("i", F.row_number().over(W.partitionBy("c").orderBy("v")) - 1), "classes")
    total = numbered.agg(F.sum("d")).first()[0]
    sizes = sorted((r[0], r[1]) for r in numbered.groupBy("c").count().collect())  # one row a power of two
    jobs = []
    for x, (c1, n1) in enumerate(sizes):
        for c2, n2 in sizes[x:]:
            bound = min(1.0, 2.0 ** (c1 + 1) * 2.0 ** (c2 + 1) / total)
            pairs = n1 * n2 if c1 != c2 else n1 * (n1 - 1) // 2
            tries = round(-pairs * math.log1p(-min(bound, 0.999999))) if bound < 1 else pairs * 14
            if tries:
                jobs.append((c1, c2, n1, n2, bound, int(tries)))
    lists = spark.createDataFrame(jobs, "c1 int, c2 int, n1 long, n2 long, bound double, tries long")
    chunk = 100_000
    lots = lists.withColumn("lot", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("tries") - 1) / chunk))))
    size = F.least(F.lit(chunk).cast("long"), F.col("tries") - F.col("lot") * chunk)
    drawn = lots.repartition(max(1, min(4096, sum(-(-j[-1] // chunk) for j in jobs))), "c1", "c2", "lot").withColumn("t", F.explode(F.sequence(F.col("lot") * chunk, F.col("lot") * chunk + size - 1)))
    pick = lambda n, side: F.floor(uniform(F.col("c1"), F.col("c2"), F.col("t"), seed, side) * F.col(n)).cast("int")
    drawn = drawn.select("c1", "c2", "bound", pick("n1", 1).alias("i1"), pick("n2", 2).alias("i2"))
    end = lambda k: numbered.select(F.col("c").alias(f"c{k}"), F.col("i").alias(f"i{k}"), F.col("v").alias(f"v{k}"), F.col("d").alias(f"d{k}"))
    # Trials are made from a few small rows, by whose size a planner would send all of them to the driver and to every task.
    met = drawn.hint("merge").join(end(1), ["c1", "i1"]).hint("merge").join(end(2), ["c2", "i2"]).where("v1 <> v2")
    true = F.least(F.lit(1.0), F.col("d1") * F.col("d2") / total)
    kept = met.where(uniform(F.least("v1", "v2"), F.greatest("v1", "v2"), seed, "keep") < true / F.col("bound"))
    return DataGraph("expected_degree", simple_edges(kept.select(F.col("v1").alias("src"), F.col("v2").alias("dst"))))


def _graph(name: str, pairs: DataFrame, bipartite: bool = False) -> DataGraph:
    return DataGraph(name, simple_edges(pairs), bipartite=bipartite)


def complete(spark: SparkSession, n: int) -> DataGraph:
    ids = spark.range(n * n)
    return _graph(f"k{n}", ids.select(F.floor(F.col("id") / n).alias("src"), (F.col("id") % n).alias("dst")))


def complete_of(vertices: DataFrame, name: str = "complete") -> DataGraph:
    """Every pair of the distinct values of a column v, for columns of few values."""
    v = vertices.select(F.col("v").cast("long").alias("v")).where("v is not null").distinct()
    return _graph(name, v.select(F.col("v").alias("src")).crossJoin(v.select(F.col("v").alias("dst"))).where("src < dst"))


def cycle(spark: SparkSession, n: int) -> DataGraph:
    return _graph(f"cycle{n}", spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst")), n % 2 == 0)


def path(spark: SparkSession, n: int) -> DataGraph:
    return _graph(f"path{n}", spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst")), True)


def star(spark: SparkSession, n: int) -> DataGraph:
    return _graph(f"star{n}", spark.range(1, n + 1).select(F.lit(0).alias("src"), F.col("id").alias("dst")), True)


def grid(spark: SparkSession, rows: int, columns: int) -> DataGraph:
    ids = spark.range(rows * columns)
    right = ids.where(F.col("id") % columns < columns - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    down = ids.where(F.col("id") < (rows - 1) * columns).select(F.col("id").alias("src"), (F.col("id") + columns).alias("dst"))
    return _graph(f"grid{rows}x{columns}", right.union(down), True)


def grid_of(vertices: DataFrame, columns: int) -> DataGraph:
    """The distinct values of a column v laid out row by row; neighbours are joined if both are there."""
    v = vertices.select(F.col("v").cast("long").alias("v")).where("v is not null").distinct()
    right = v.where(F.col("v") % columns < columns - 1).select(F.col("v").alias("src"), (F.col("v") + 1).alias("dst"))
    down = v.select(F.col("v").alias("src"), (F.col("v") + columns).alias("dst"))
    return _graph(f"grid of {columns}", right.union(down).join(v.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst"), True)


def complete_bipartite(spark: SparkSession, a: int, b: int) -> DataGraph:
    ids = spark.range(a * b)
    return _graph(f"k{a}_{b}", ids.select((2 * F.floor(F.col("id") / b)).alias("src"), (2 * (F.col("id") % b) + 1).alias("dst")), True)


def uniform_random(spark: SparkSession, n: int, p: float, seed: int = 1) -> DataGraph:
    ids = spark.range(n * n).select(F.floor(F.col("id") / n).alias("src"), (F.col("id") % n).alias("dst")).where("src < dst")
    return _graph(f"random{n}", ids.where(uniform(F.col("src"), F.col("dst"), seed) < p))
