"""Numbers of simple paths, in all, with the smallest-id or the highest vertex first: the work that symmetry
breaking by id and by degree leaves for one half of a cycle."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.operators import exact
from huecount.operators.graph import DataGraph, id_of


def enumerate_paths(g: DataGraph, q: int, order: str | None = None) -> DataFrame:
    """Simple paths on q vertices as rows p1..pq of keys. order 'degree': the first vertex is the highest by
    (degree, id); 'id': it has the largest id; None: all ordered paths."""
    arcs = g.arcs() if g.order == "degree" else g.with_order("degree").arcs()

    def allowed(n: int):
        if order == "degree":
            return F.col("p1") > F.col(f"p{n}")
        return id_of(F.col("p1")) > id_of(F.col(f"p{n}")) if order == "id" else F.lit(True)

    rows = arcs.select(F.col("src").alias("p1"), F.col("dst").alias("p2")).where(allowed(2))
    for n in range(3, q + 1):
        rows = rows.join(arcs.select(F.col("src").alias(f"p{n - 1}"), F.col("dst").alias(f"p{n}")), f"p{n - 1}").where(allowed(n))
        for m in range(1, n - 1):
            rows = rows.where(F.col(f"p{m}") != F.col(f"p{n}"))
    return rows


def count_paths(g: DataGraph, q: int) -> DataFrame:
    """The number of all ordered simple paths. On three and four vertices it follows from degrees: both ends of a middle arc go on
    by any other neighbour, and the two ends meet in one vertex once for each ordered triangle."""
    if q not in (3, 4):
        return enumerate_paths(g, q).agg(F.count("*").alias("cnt"))
    arcs = g.arcs()
    deg = arcs.groupBy("src").agg(F.count("*").alias("d"))
    whole = lambda x: F.coalesce(F.sum(x), F.lit(0)).cast("long").alias("cnt")
    if q == 3:
        return deg.agg(whole(F.col("d") * (F.col("d") - 1)))
    further = arcs.join(deg.select(F.col("src").alias("dst"), (F.col("d") - 1).alias("on")), "dst")
    open_ends = further.groupBy("src").agg(F.count("*").alias("d"), F.sum("on").alias("on")).agg(whole((F.col("d") - 1) * F.col("on")))
    if g.bipartite:
        return open_ends
    return open_ends.crossJoin(exact.triangles(g).select(F.col("cnt").alias("triangles"))).select((F.col("cnt") - 6 * F.col("triangles")).alias("cnt"))


def _first_highest(g: DataGraph, q: int, order: str) -> DataFrame:
    """The number of simple paths on three or four vertices whose first one is the highest. The place of a vertex among another's
    neighbours, in the order, tells how many of these are lower. On four vertices either an end is the highest, or an inner vertex: it is
    left by two lower neighbours, one of which goes on to a lower vertex, other than the second one. All paths but the latter are asked for."""
    arcs = g.arcs() if g.order == "degree" else g.with_order("degree").arcs()
    rank = (lambda v: F.col(v)) if order == "degree" else (lambda v: id_of(F.col(v)))
    below = F.row_number().over(W.partitionBy("src").orderBy(rank("dst"))) - 1
    up = arcs.withColumn("below", below.cast("long")).where(rank("src") < rank("dst"))
    whole = lambda x: F.coalesce(F.sum(x), F.lit(0)).cast("long").alias("cnt")
    if q == 3:
        return up.agg(whole(F.col("below")))
    inner = up.groupBy("dst").agg(F.count("*").alias("low"), F.sum("below").alias("on")).agg(whole((F.col("low") - 1) * F.col("on")).alias("inner"))
    every = count_paths(g, 4).select(F.col("cnt").alias("every"))
    found = every.crossJoin(inner)
    if g.bipartite:
        return found.select((F.expr("every div 2") - F.col("inner")).alias("cnt"))
    return found.crossJoin(exact.triangles(g).select(F.col("cnt").alias("triangles"))).select((F.expr("every div 2") - F.col("inner") + 2 * F.col("triangles")).alias("cnt"))


def count_x(g: DataGraph, q: int) -> DataFrame:
    return _first_highest(g, q, "degree") if q in (3, 4) else enumerate_paths(g, q, "degree").agg(F.count("*").alias("cnt"))


def count_y(g: DataGraph, q: int) -> DataFrame:
    return _first_highest(g, q, "id") if q in (3, 4) else enumerate_paths(g, q, "id").agg(F.count("*").alias("cnt"))
