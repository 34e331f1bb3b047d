"""Exact counts, for baselines and checks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from huecount.operators.graph import DataGraph, id_of
from huecount.operators.joins import near_lists
from huecount.plans.query import QueryGraph, swaps_sides


#: Columns of an arc that closes a cycle; no query node has such a name.
CLOSING = ("closing/src", "closing/dst")


def search_order(q: QueryGraph, start: str | None = None) -> list[str]:
    """Nodes such that each but the first touches an earlier one, closing most edges first."""
    near, order = q.neighbours(), [start or max(q.nodes, key=lambda n: (len(q.neighbours()[n]), n))]
    while len(order) < q.k:
        order.append(max((n for n in q.nodes if n not in order and near[n] & set(order)), key=lambda n: (len(near[n] & set(order)), len(near[n]), n)))
    return order


def without(q: QueryGraph, node: str) -> QueryGraph:
    return QueryGraph(f"{q.name}-{node}", tuple(n for n in q.nodes if n != node), tuple(e for e in q.edges if node not in e))


def matches(g: DataGraph, q: QueryGraph, induced: bool = False, coloring=None, start: str | None = None, side: int | None = None) -> DataFrame:
    """One row per match, a column per query node (vertex keys): a self-join of arcs per node, semi-joins for
    further edges. With a colouring only colourful matches of trial 0. start: the node that is placed first, on a side of the graph
    if one is named; on a flat graph rows then stay where that node's image is, and lists of neighbours come to them."""
    arcs, near, order = g.arcs(), q.neighbours(), search_order(q, start)
    closing = arcs.select(F.col("src").alias(CLOSING[0]), F.col("dst").alias(CLOSING[1]))
    rows = arcs.select(F.col("src").alias(order[0]))
    rows = rows if side is None else rows.where(F.col(order[0]).bitwiseAND(1) == side)
    flat = g.flat_parts(1, "plain" if side is None else str(side)) if start is not None else 0
    rows = (rows.repartition(flat, order[0]) if flat else rows).distinct()
    for i, n in enumerate(order[1:], 1):
        known = sorted(near[n] & set(order[:i]))
        if flat:
            rows = near_lists(rows, known[0], g.near()).withColumn(n, F.explode("near")).drop("near")
        else:
            rows = rows.join(arcs.select(F.col("src").alias(known[0]), F.col("dst").alias(n)), known[0])
        for m in order[:i]:
            rows = rows.where(F.col(m) != F.col(n))
            if coloring is not None:
                c = [coloring.color(id_of(F.col(x)), F.lit(0)) for x in (m, n)]
                rows = rows.where(c[0] != c[1])
        for m in known[1:]:
            rows = rows.join(closing, (F.col(m) == F.col(f"`{CLOSING[0]}`")) & (F.col(n) == F.col(f"`{CLOSING[1]}`")), "left_semi")
        if induced:
            for m in [m for m in order[:i] if m not in near[n]]:
                rows = rows.join(closing, (F.col(m) == F.col(f"`{CLOSING[0]}`")) & (F.col(n) == F.col(f"`{CLOSING[1]}`")), "left_anti")
    return rows


def brute_force(g: DataGraph, q: QueryGraph, induced: bool = False) -> DataFrame:
    return matches(g, q, induced).agg(F.count("*").alias("cnt"))


def colorful_brute_force(g: DataGraph, q: QueryGraph, coloring) -> DataFrame:
    """Two query nodes with the same neighbours are chosen from the same list: where there are such twins, the images of the
    others are listed with the numbers of choices by colour, and pairs of different colours follow."""
    twins = next(((x, y) for x in q.nodes for y in q.nodes if x < y and q.neighbours()[x] == q.neighbours()[y] and len(q.neighbours()[x]) > 1), None)
    if twins is None:
        return matches(g, q, coloring=coloring).agg(F.count("*").alias("cnt"))
    x, y = twins
    rest = [n for n in q.nodes if n not in twins]
    start = max((n for n in rest if n in q.neighbours()[x]), key=lambda n: (len(q.neighbours()[n]), n))
    times, side = 1, None
    if g.sides and swaps_sides(q):
        work = g.work()  # as many matches have their first node on either side
        times, side = 2, min((0, 1), key=lambda s: work[str(s)])
    rows = matches(g, without(q, y), coloring=coloring, start=start, side=side)
    hue = coloring.color(id_of(F.col(x)), F.lit(0))
    of = rows.groupBy(*rest).agg(*[F.count_if(hue == c).alias(f"of/{c}") for c in range(coloring.k)])
    n = [F.col(f"`of/{c}`") for c in range(coloring.k)]
    pairs = sum(n[1:], n[0]) * sum(n[1:], n[0]) - sum((c * c for c in n[1:]), n[0] * n[0])
    return of.agg(F.coalesce(F.sum(pairs) * times, F.lit(0)).cast("long").alias("cnt"))


def triangles(g: DataGraph) -> DataFrame:
    """Each triangle once: from its lowest vertex, whose two higher neighbours must be adjacent."""
    up = g.arcs().where("src < dst")
    wedge = up.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(up.select(F.col("src").alias("a"), F.col("dst").alias("c")), "a").where("b < c")
    closed = wedge.join(up, (F.col("b") == up["src"]) & (F.col("c") == up["dst"]), "left_semi")
    return closed.agg(F.count("*").alias("cnt"))


def wedges(g: DataGraph) -> DataFrame:
    return g.degrees().agg(F.coalesce(F.sum(F.col("deg") * (F.col("deg") - 1) / 2), F.lit(0)).cast("long").alias("cnt"))


def four_cycles(g: DataGraph) -> DataFrame:
    """Each four-cycle at its highest vertex x: with the vertex opposite, y, it closes two wedges x-m-y, and
    both m and y are lower than x. So only wedges that leave their highest end are built (the sum over edges
    of the lower end's degree, not the sum of squared degrees), and every pair with c of them holds c(c-1)/2."""
    a = g.arcs()
    down = a.where("dst < src").select(F.col("src").alias("x"), F.col("dst").alias("m"))
    wedge = down.join(a.select(F.col("src").alias("m"), F.col("dst").alias("y")), "m").where("y < x")
    common = wedge.groupBy("x", "y").agg(F.count("*").alias("c"))
    return common.agg(F.coalesce(F.sum(F.col("c") * (F.col("c") - 1) / 2), F.lit(0)).cast("long").alias("cnt"))


def closed_walks(g: DataGraph, length: int) -> DataFrame:
    """Trace of the adjacency matrix's power: products of matrix blocks as joins with grouped sums."""
    step = g.arcs().select(F.col("src").alias("m"), F.col("dst").alias("j"), F.lit(1).cast("long").alias("b"))
    power = g.arcs().select(F.col("src").alias("i"), F.col("dst").alias("m"), F.lit(1).cast("long").alias("a"))
    for _ in range(length - 1):
        power = power.join(step, "m").groupBy("i", F.col("j").alias("m")).agg(F.sum(F.col("a") * F.col("b")).alias("a"))
    return power.where("i = m").agg(F.coalesce(F.sum("a"), F.lit(0)).alias("cnt"))


def paws(g: DataGraph) -> DataFrame:
    """Matches of a triangle with a tail, from triangles per vertex and degrees."""
    up = g.arcs().where("src < dst")
    wedge = up.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(up.select(F.col("src").alias("a"), F.col("dst").alias("c")), "a").where("b < c")
    closed = wedge.join(up, (F.col("b") == up["src"]) & (F.col("c") == up["dst"]), "left_semi")
    per = closed.select(F.explode(F.array("a", "b", "c")).alias("v")).groupBy("v").agg(F.count("*").alias("t"))
    deg = g.arcs().groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))
    return per.join(deg, "v").agg(F.coalesce(F.sum(2 * F.col("t") * (F.col("deg") - 2)), F.lit(0)).alias("cnt"))
