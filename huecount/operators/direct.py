"""Block tables straight from their definition, as a check: every placing of a block's nodes on data vertices, times
every choice of a row from each child's table. A cross join of vertices and tables, for tiny graphs only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from huecount.functions import signature as sg
from huecount.operators.joins import Context
from huecount.plans.plan import Block, Plan

#: Placings that a cross join may have: the size is checked before it is run.
MOST = 5_000_000


def block_product(ctx: Context, plan: Plan, block: Block, tables: dict[int, DataFrame]) -> DataFrame:
    """trial, the boundary's vertices u, v (as far as there are), sig, cnt of a block, given its children's tables."""
    vertices = ctx.graph.arcs().select("src").distinct()
    n = vertices.count()
    if n ** len(block.seq) > MOST:
        raise ValueError(f"{n} vertices and {len(block.seq)} nodes are too many for a cross join")
    trials = ctx.graph.spark.range(ctx.coloring.trials).select(F.col("id").cast("int").alias("trial"))
    rows = trials.withColumn("sig", F.lit(0).cast("long")).withColumn("cnt", F.lit(1).cast("long"))
    at = {node: f"at{i}" for i, node in enumerate(block.seq)}
    for node in block.seq:
        rows = rows.crossJoin(vertices.select(F.col("src").alias(at[node])))
        bit = ctx.bit(F.col(at[node]), F.col("trial"))
        rows = rows.where(sg.has_not(F.col("sig"), bit)).withColumn("sig", sg.union(F.col("sig"), bit))
    around = list(zip(block.seq, block.seq[1:], strict=False)) + ([(block.seq[-1], block.seq[0])] if block.kind == "cycle" else [])
    for a, b in around:
        if block.on_edge(a, b) is None:
            arcs = ctx.graph.arcs().select(F.col("src").alias("arc_a"), F.col("dst").alias("arc_b"))
            rows = rows.crossJoin(arcs).where((F.col(at[a]) == F.col("arc_a")) & (F.col(at[b]) == F.col("arc_b"))).drop("arc_a", "arc_b")
    for ends, child in [((x,), c) for x, c in block.node_ann] + list(block.edge_ann):
        ends = plan.blocks[child].boundary if len(ends) == 2 else ends
        named = {"trial": "t2", "sig": "s2", "cnt": "c2", "u": "u2", "v": "v2"}
        rows = rows.crossJoin(tables[child].withColumnsRenamed({k: x for k, x in named.items() if k in tables[child].columns}))
        shared = F.lit(0).cast("long")
        for x, column in zip(ends, ("u2", "v2"), strict=False):
            rows = rows.where(F.col(at[x]) == F.col(column))
            shared = sg.union(shared, ctx.bit(F.col(at[x]), F.col("trial")))
        rows = rows.where((F.col("trial") == F.col("t2")) & sg.disjoint_except(F.col("sig"), F.col("s2"), shared))
        rows = rows.withColumn("sig", sg.union(F.col("sig"), F.col("s2"))).withColumn("cnt", F.col("cnt") * F.col("c2"))
        rows = rows.drop(*[x for x in named.values() if x in rows.columns])
    keep = [F.col(at[x]).alias(c) for x, c in zip(block.boundary, "uv", strict=False)]
    by = ["trial", *"uv"[: len(keep)], "sig"]
    return rows.select("trial", *keep, "sig", "cnt").groupBy(*by).agg(F.sum("cnt").alias("cnt"))


def count_by_products(ctx: Context, plan: Plan) -> DataFrame:
    """trial, cnt by direct products all the way up."""
    tables: dict[int, DataFrame] = {}
    for b in plan.blocks:
        tables[b.id] = block_product(ctx, plan, b, tables)
    return tables[plan.root.id].groupBy("trial").agg(F.sum("cnt").alias("cnt"))
