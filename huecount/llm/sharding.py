"""Resharding by minimum-cost flow.

Given where every document lies now and how many bytes each new shard should hold, the fewest bytes
move when old shard sizes are supplies, new capacities are demands, keeping a byte costs 0 and moving
it costs 1. The flow says how many bytes go from each old shard to each new one; blocks (ranges of a
hash of doc_id within an old shard) realise it, so the driver sees block sizes only, and a file is
rewritten only if a block enters or leaves it.

Law: ``bytes``, shard sizes near equal (to a block, and to a document where blocks are documents).

Defined results: a null text has no bytes and size 1; a null doc_id hashes as '~'; repeated rows lie in
one block, in any order among themselves; an empty table gives an empty result; extra columns are
ignored by ``assign`` and written by ``reshard`` and ``rewrite``.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.llm.common import cut, fresh_dir, hash_hex

SHARDS = 16
#: Blocks of one old shard. The driver holds SHARDS x BLOCKS sizes: 65,536 numbers, whatever the input.
BLOCKS = 4096


class MinCostFlow:
    """Successive shortest paths with potentials on a small directed network of integer capacities."""

    def __init__(self, nodes: int):
        self.graph: list[list[list[int]]] = [[] for _ in range(nodes)]

    def arc(self, a: int, b: int, room: int, cost: int) -> list[int]:
        there, back = [b, room, cost, len(self.graph[b])], [a, 0, -cost, len(self.graph[a])]
        self.graph[a].append(there)
        self.graph[b].append(back)
        return back  # its room is the flow

    def run(self, s: int, t: int) -> int:
        """Send as much as fits from s to t; return its cost."""
        n, spent, height = len(self.graph), 0, [0] * len(self.graph)
        while True:
            far, via = [None] * n, [None] * n
            far[s], queue = 0, [(0, s)]
            while queue:
                d, u = heapq.heappop(queue)
                if d > far[u]:
                    continue
                for e in self.graph[u]:
                    if e[1] > 0 and (far[e[0]] is None or d + e[2] + height[u] - height[e[0]] < far[e[0]]):
                        far[e[0]], via[e[0]] = d + e[2] + height[u] - height[e[0]], (u, e)
                        heapq.heappush(queue, (far[e[0]], e[0]))
            if far[t] is None:
                return spent
            height = [h + (far[v] if far[v] is not None else 0) for v, h in enumerate(height)]
            push, v = None, t
            while v != s:
                u, e = via[v]
                push, v = e[1] if push is None else min(push, e[1]), u
            v = t
            while v != s:
                u, e = via[v]
                e[1] -= push
                self.graph[v][e[3]][1] += push
                spent, v = spent + push * e[2], u


def transfers(old: dict[int, int], capacity: dict[int, int]) -> dict[tuple[int, int], int]:
    """Bytes to send from each old shard to each new one (the same number: they stay) at the least cost.
    Capacities must hold all bytes."""
    olds, news = sorted(old), sorted(capacity)
    net = MinCostFlow(len(olds) + len(news) + 2)
    s, t = len(olds) + len(news), len(olds) + len(news) + 1
    flows = {}
    for i, a in enumerate(olds):
        net.arc(s, i, old[a], 0)
        for j, b in enumerate(news):
            flows[a, b] = net.arc(i, len(olds) + j, old[a], 0 if a == b else 1)
    for j, b in enumerate(news):
        net.arc(len(olds) + j, t, capacity[b], 0)
    net.run(s, t)
    return {k: back[1] for k, back in flows.items() if back[1] > 0}


def even_capacities(total: int, shards: int) -> dict[int, int]:
    """Capacities that add up to total and differ by one byte at most."""
    return {j: total // shards + (j < total % shards) for j in range(shards)}


def place_blocks(blocks: dict[tuple[int, str], int], capacity: dict[int, int]) -> dict[tuple[int, str], int]:
    """New shard of each block (old shard, block): the flow's bytes, rounded to blocks. Blocks go from the
    largest to the smallest, each to the target of its old shard with the most bytes still due; the
    rounding left at the end is mended by moving single blocks from the fullest to the emptiest shard."""
    old = defaultdict(int)
    for (a, _), size in blocks.items():
        old[a] += size
    due = defaultdict(dict)
    for (a, b), size in transfers(old, capacity).items():
        due[a][b] = size
    to, held = {}, dict.fromkeys(capacity, 0)
    for (a, k), size in sorted(blocks.items(), key=lambda x: (-x[1], x[0])):
        targets = due[a] or capacity
        b = max(targets, key=lambda j: (targets[j] if due[a] else capacity[j] - held[j], j == a, -j))
        to[a, k] = b
        held[b] += size
        if due[a]:
            due[a][b] -= size
    members = defaultdict(list)
    for key, b in to.items():
        members[b].append((blocks[key], key))
    for _ in range(64 * len(capacity)):
        over = {j: held[j] - capacity[j] for j in capacity}
        hi, lo = max(over, key=lambda j: (over[j], -j)), min(over, key=lambda j: (over[j], j))
        gap = over[hi] - over[lo]
        fitting = [x for x in members[hi] if 0 < x[0] < gap]
        if gap <= 1 or not fitting:
            break
        best = min(fitting, key=lambda x: (abs(gap - 2 * x[0]), x))
        members[hi].remove(best)
        members[lo].append(best)
        held[hi], held[lo], to[best[1]] = held[hi] - best[0], held[lo] + best[0], lo
    return to


def _text(docs: DataFrame) -> Column:
    return F.coalesce(docs["text"], F.lit("")).cast("binary")


def measured(docs: DataFrame, old_shard: Column, blocks: int = BLOCKS) -> DataFrame:
    """docs with the columns the plan needs; their names cannot meet columns of docs."""
    block = F.conv(F.substring(hash_hex("shard", F.col("doc_id")), 1, 8), 16, 10).cast("long") % blocks
    return docs.select(
        "*", (F.octet_length(_text(docs)) + 1).cast("long").alias("_size"), F.crc32(_text(docs)).alias("_crc"), old_shard.cast("int").alias("_old"), block.cast("int").alias("_block")
    )


def block_plan(rows: DataFrame, shards: int = SHARDS, capacity: dict[int, int] | None = None) -> list[tuple[int, int, int, int, int]]:
    """(old shard, block, new shard, first slot, bytes) of every block of measured rows."""
    per_block = {(r[0], r[1]): (r[2], r[3]) for r in rows.groupBy("_old", "_block").agg(F.sum("_size"), F.count("*")).collect()}
    capacity = capacity or even_capacities(sum(x[0] for x in per_block.values()), shards)
    to = place_blocks({k: x[0] for k, x in per_block.items()}, capacity)
    filled, plan = dict.fromkeys(capacity, 0), []
    for key in sorted(to):
        plan.append((*key, to[key], filled[to[key]], per_block[key][0]))
        filled[to[key]] += per_block[key][1]
    return plan


def placed(rows: DataFrame, plan: list[tuple[int, int, int, int, int]]) -> DataFrame:
    """Measured rows with ``shard`` and ``slot``. A row meets its block's one line of the plan and takes its
    slot by its rank in the block, so each row is placed once, however often it is repeated."""
    lines = rows.sparkSession.createDataFrame([x[:4] for x in plan], "_old int, _block int, shard int, _first long")
    in_block = W.partitionBy("_old", "_block").orderBy("doc_id", "_crc", "_size")
    ranked = rows.drop("shard", "slot").withColumn("_nth", F.row_number().over(in_block) - 1)
    return ranked.join(F.broadcast(lines), ["_old", "_block"]).withColumn("slot", (F.col("_first") + F.col("_nth")).cast("long"))  # SHARDS x BLOCKS lines at most


def assign(docs: DataFrame, old_shard: Column, shards: int = SHARDS, capacity: dict[int, int] | None = None, blocks: int = BLOCKS) -> DataFrame:
    """doc_id, size, text_crc32, old_shard, shard, slot of every document. old_shard: an int column."""
    light = cut(measured(docs, old_shard, blocks).select("doc_id", "_size", "_crc", "_old", "_block"), "shard-digests")  # some 40 bytes a document
    rows = placed(light, block_plan(light, shards, capacity))
    return rows.select("doc_id", F.col("_size").alias("size"), F.col("_crc").alias("text_crc32"), F.col("_old").alias("old_shard"), "shard", "slot")


def reshard(docs: DataFrame, old_shard: Column, path: str, shards: int = SHARDS, capacity: dict[int, int] | None = None, blocks: int = BLOCKS) -> DataFrame:
    """Plan new shards and write those that gain or lose a block as Parquet under path/shard=j. Return all
    documents with ``shard`` and ``slot``: of affected shards as the written files have them, of the others,
    which stay as they are, from docs."""
    spark, rows = docs.sparkSession, measured(docs, old_shard, blocks)
    plan = block_plan(rows, shards, capacity)
    touched = sorted({j for a, _, b, _, _ in plan if a != b for j in (a, b)})
    columns = [c for c in docs.columns if c.lower() not in ("shard", "slot")]
    shape = placed(rows, plan).select(*columns, "slot", "shard")
    # Nothing enters or leaves a shard that is not affected: the old shard tells already which rows are written.
    placed(rows.where(F.col("_old").isin(touched)), plan).select(*columns, "slot", "shard").write.mode("overwrite").partitionBy("shard").parquet(path)
    written = spark.read.schema(shape.schema).parquet(path)
    if all(a in touched for a, *_ in plan):
        return written
    return written.unionByName(placed(rows.where(~F.col("_old").isin(touched)), plan).select(*columns, "slot", "shard"))


def rewrite(docs: DataFrame, assigned: DataFrame, path: str) -> DataFrame:
    """Write the new shards of a given assignment that gain or lose a document as Parquet under path/shard=j;
    return those shards with their old and new bytes. Shards that keep exactly what they had are not touched.
    Rows of equal doc_id and text are numbered on both sides, so that each takes one of their places."""
    assigned = cut(assigned.select("doc_id", "size", "text_crc32", "old_shard", "shard", "slot"), "shards-assigned")
    out = assigned.where("old_shard <> shard").groupBy(F.col("old_shard").alias("shard")).agg(F.sum("size").alias("bytes_out"))
    into = assigned.where("old_shard <> shard").groupBy("shard").agg(F.sum("size").alias("bytes_in"))
    touched = cut(out.join(into, "shard", "full").na.fill(0), "shards-touched")
    of_equals = W.partitionBy("a_doc", "a_size", "a_crc")
    places = assigned.select(F.col("doc_id").alias("a_doc"), F.col("size").alias("a_size"), F.col("text_crc32").alias("a_crc"), "shard", "slot")
    places = places.withColumn("a_nth", F.row_number().over(of_equals.orderBy("shard", "slot")))
    moved = places.join(F.broadcast(touched.select("shard")), "shard", "left_semi")  # as many rows as shards
    full = docs.drop("shard", "slot").select("*", F.col("doc_id").alias("_doc"), (F.octet_length(_text(docs)) + 1).cast("long").alias("_size"), F.crc32(_text(docs)).alias("_crc"))
    full = full.withColumn("_nth", F.row_number().over(W.partitionBy("_doc", "_size", "_crc").orderBy(F.lit(0))))
    same = F.col("_doc").eqNullSafe(F.col("a_doc")) & (F.col("_size") == F.col("a_size")) & (F.col("_crc") == F.col("a_crc")) & (F.col("_nth") == F.col("a_nth"))
    rows = full.join(moved, same).drop("_doc", "_size", "_crc", "_nth", "a_doc", "a_size", "a_crc", "a_nth")
    rows.write.mode("overwrite").partitionBy("shard").parquet(path)
    return touched


def op2_sharding(docs: DataFrame) -> DataFrame:
    """Documents lie by source, so one old shard holds a third of them; 16 even shards are wanted. What is
    told of a document is read from the shards as written."""
    old = F.crc32(F.coalesce(F.col("source"), F.lit("")).cast("binary")) % SHARDS
    rows = reshard(docs, old, fresh_dir(docs.sparkSession, "shards"))
    return rows.select(
        "doc_id", (F.octet_length(_text(rows)) + 1).cast("long").alias("size"), F.crc32(_text(rows)).alias("text_crc32"), F.lit("bytes").alias("law"), "shard", "slot",
        F.lit(None).cast("int").alias("grown_shard"), old.cast("int").alias("old_shard"),
    )
