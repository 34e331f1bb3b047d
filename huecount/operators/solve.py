"""Evaluation of a plan: one table per block, bottom-up, under one of three cycle strategies.

``boundary`` splits a cycle at its boundary nodes, ``even`` into two halves of equal length, ``degree``
once per choice of the cycle's highest vertex, at that vertex and the one opposite, with every path vertex
below it. All three give the same tables.
"""

from __future__ import annotations

from functools import reduce

from pyspark.errors import PySparkException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from huecount.operators import inplace, joins
from huecount.operators.graph import DataGraph, order_of
from huecount.operators.joins import Context
from huecount.plans.plan import Block, Plan, plan_for
from huecount.plans.query import QueryGraph, is_bipartite
from huecount.session import cut

STRATEGIES = ("boundary", "even", "degree")


def splits(block: Block, strategy: str) -> list[tuple[int, int]]:
    """(start, end) positions of the two paths of a cycle, one pair per choice of the start."""
    n = len(block.seq)
    at = [block.seq.index(b) for b in block.boundary]
    if strategy == "degree":
        return [(i, (i + n // 2) % n) for i in range(n)]
    first = at[0] if at else 0
    if strategy == "boundary" and len(at) == 2:
        return [(at[0], at[1])]
    if strategy in ("boundary", "even"):
        return [(first, (first + n // 2) % n)]
    raise ValueError(f"no strategy {strategy!r}")


class Solver:
    def __init__(self, ctx: Context, plan: Plan, strategy: str = "degree", symmetry: bool = True, root_complement: bool = True, share: bool = True):
        self.ctx, self.plan, self.strategy = ctx, plan, strategy
        self.symmetry, self.root_complement, self.share = symmetry, root_complement, share
        self.tables: dict[int, DataFrame] = {}
        self._paths: dict[tuple, DataFrame] = {}
        self._told: dict[tuple, dict[str, DataFrame]] = {}
        self.banded = False  # the root's paths are taken band by band

    def path(self, block: Block, nodes: list[str], own_start: bool, own_end: bool, high: bool, sums: bool = True) -> DataFrame:
        """The table of a path along nodes. Boundary nodes inside it are recorded; annotations of its ends
        count only if owned. Tables of equal beginnings are one table: its grouped sum is one exchange, which all
        steps after it reuse. sums: False leaves the rows of a last step as they are joined."""
        ctx, table, made = self.ctx, self.tables, None
        for i, shape in enumerate(self._shapes(block, nodes, own_start, own_end, high), 1):
            last = i == len(nodes) - 1
            shape = shape if sums or not last else (*shape, "loose")
            if self.share and shape in self._paths:
                made = self._paths[shape]
                continue
            child = block.on_edge(nodes[i - 1], nodes[i])
            if i > 1:
                made = joins.extend_edge(ctx, made, high, sums or not last) if child is None else joins.extend_block(ctx, made, table[child], self._flip(child, nodes[i - 1]), high)
            else:
                made = joins.seed_edge(ctx, high) if child is None else joins.seed_block(ctx, table[child], self._flip(child, nodes[0]), high)
                if own_start and (c := block.on_node(nodes[0])) is not None:
                    made = joins.attach_node(ctx, made, table[c], "h")
            if (not last or own_end) and (c := block.on_node(nodes[i])) is not None:
                made = joins.attach_node(ctx, made, table[c], "tail", sums or not last)
            if not last and nodes[i] in block.boundary:
                made = joins.record(made, nodes[i])
            self._paths[shape] = made
        return made

    def _shapes(self, block, nodes, own_start, own_end, high) -> list[tuple]:
        """What the table of each beginning of a path depends on: those of equal shape are equal. A node inside
        a path and the same node at its end differ if it has something to attach or to record."""
        first = block.on_node(nodes[0]) if own_start else None
        shape, out = (high, first), []
        for i in range(1, len(nodes)):
            last = i == len(nodes) - 1
            child = block.on_edge(nodes[i - 1], nodes[i])
            step = (child, None if child is None else self._flip(child, nodes[i - 1]))
            mark = block.on_node(nodes[i]) if not last or own_end else None
            shape = (*shape, step, mark, nodes[i] if not last and nodes[i] in block.boundary else None)
            out.append(shape)
        return out

    def _flip(self, child: int, first: str) -> bool:
        """Whether a child's table has to be turned to start at first."""
        return self.plan.blocks[child].boundary[0] != first

    def triangle(self, block: Block) -> DataFrame:
        """The table of a triangle of bare edges: triangles are listed from their lowest vertex, and annotations come to them. No
        path of two edges is summed that no edge closes."""
        seq = block.seq
        if not block.boundary and not block.children and self.symmetry:
            whole = joins.triangles(self.ctx).groupBy("trial", "sig").agg((F.count("*") * 6).alias("cnt"))
            return whole.withColumn("cnt", F.col("cnt").cast("decimal(38,0)" if self.ctx.count_type == "decimal" else "long"))
        made = joins.triangle_paths(self.ctx, seq)
        place = dict(zip(seq, ("h", f"rec_{seq[1]}", "tail"), strict=True))
        for x in seq:
            if (c := block.on_node(x)) is not None:
                made = joins.attach_node(self.ctx, made, self.tables[c], place[x], sums=False)
        keep = [F.col(place[x]).alias(out) for out, x in zip("uv", block.boundary, strict=False)]
        return made.groupBy("trial", *keep, "sig").agg(F.sum("cnt").alias("cnt"))

    def _tell(self, high: bool) -> None:
        """The loads of a merge in place, and of the steps before it where no other merge has noted them. A graph keeps those of a colouring."""
        if self.ctx.load is None:
            return
        known, of = self.ctx.graph.told, (repr(self.ctx.coloring), high)
        if of not in known:
            known[of] = cut(inplace.loads(self.ctx, high), "told")
        tallied = {step: known[of].where(F.col("step") == step).drop("step") for step in inplace.STEPS}
        if of not in self._told:
            self._told[of] = tallied
            self.ctx.note_told("seed", tallied["seed"])
            self.ctx.note_told("extend", tallied["extend"])
        self.ctx.note_told("merge", self._told[of]["merge"], same=(self._told[of]["merge"],))

    def cycle(self, block: Block) -> DataFrame:
        n, seq, parts = len(block.seq), block.seq, []
        if n == 3 and self.strategy != "degree" and self.ctx.load is None and not self.banded and all(block.on_edge(seq[i - 1], seq[i]) is None for i in range(3)):
            return self.triangle(block)
        high = self.strategy == "degree"
        root = not block.boundary
        chosen = splits(block, self.strategy)
        times = 1
        if high and root and self.symmetry and not block.children:
            chosen, times = chosen[:1], n  # every rotation of a bare cycle gives the same sum
        self.ctx.side = None
        if not high and root and self.symmetry and not block.children and n % 2 == 0 and self.ctx.graph.sides:
            # Half of the rotations start on either side: the side with fewer candidates stands for both.
            work, times = self.ctx.graph.work(), 2
            self.ctx.side = min((0, 1), key=lambda s: work[str(s)])
        pairs = [([seq[(i + s) % n] for s in range((j - i) % n + 1)], [seq[(i - s) % n] for s in range((i - j) % n + 1)]) for i, j in chosen]
        for (i, j), (plus, minus) in zip(chosen, pairs, strict=True):
            same = self.share and not block.children and self._shapes(block, plus, False, True, high) == self._shapes(block, minus, True, False, high)
            place = {seq[i]: "h", seq[j]: "tail"}
            keep = {out: place.get(x, f"rec_{x}") for out, x in zip("uv", block.boundary, strict=False)}
            complement = self.plan.query.k if root and self.root_complement else None
            whole = not block.children and not self.banded and inplace.fits(self.ctx)
            if whole and same and len(plus) == 3 and not any(x in block.boundary for x in plus[1:-1]):
                self._tell(high)
                parts.append(joins.merge_in_place(self.ctx, inplace.met(self.ctx, high, "tail" in keep.values()), keep))
                continue
            if whole and self.ctx.load is None and not high and sorted(map(len, (plus, minus))) == [2, 4] and not any(x in block.boundary for x in (*plus[1:-1], *minus[1:-1])):
                parts.append(joins.merge_in_place(self.ctx, inplace.closed(self.ctx), keep))
                continue
            inner = [x for x in keep.values() if x not in ("h", "tail")]
            if whole and self.ctx.load is None and high and n == 4 and len(keep) == 2 and len(inner) == 1:
                # The arc between both boundary nodes starts at the one that is an end of the paths.
                opposite = "tail" in keep.values()
                parts.append(joins.merge_in_place(self.ctx, inplace.closed(self.ctx, "end" if opposite else True), {out: "tail" if x in inner else "h" for out, x in keep.items()}))
                continue
            if same and joins.meets_itself(self.ctx, len(plus) - 2) and not any(x in block.boundary for x in plus[1:-1]):
                parts.append(joins.merge_itself(self.ctx, self.path(block, plus, False, True, high, sums=False), keep, len(plus) - 2))
                continue
            a = self.path(block, plus, False, True, high)
            b = self.path(block, minus, True, False, high)
            parts.append(joins.merge_paths(self.ctx, a, b, keep, complement))
        self.ctx.side = None
        if len(parts) == 1 and times == 1:
            return parts[0]
        whole = reduce(DataFrame.unionByName, parts)
        by = [c for c in whole.columns if c != "cnt"]
        return whole.groupBy(*by).agg((F.sum("cnt") * times).alias("cnt"))

    def leaf(self, block: Block) -> DataFrame:
        a, b = block.seq
        p = self.path(block, [a, b], True, True, False, sums=False)  # summed once, over all tails
        return p.groupBy("trial", F.col("h").alias("u"), "sig").agg(F.sum("cnt").alias("cnt"))

    def block(self, block: Block) -> DataFrame:
        return self.leaf(block) if block.kind == "leaf" else self.cycle(block)

    def run(self, keep_tables: bool = True) -> DataFrame:
        """trial, cnt: the number of colourful matches; a trial without any has no row. A table that is read
        more than once, or by a plan that has grown long, is written out first."""
        for b in self.plan.blocks[:-1]:
            self.ctx.load_name = f"block{b.id}/"
            made = self.block(b)
            self.tables[b.id] = cut(made, f"block{b.id}", ("trial", "u")) if keep_tables else made
        self.ctx.load_name = f"block{self.plan.root.id}/"
        return self.block(self.plan.root).groupBy("trial").agg(F.sum("cnt").alias("cnt"))


def impossible(g: DataGraph, q: QueryGraph) -> bool:
    """A bipartite graph has no odd cycle."""
    return g.bipartite and not is_bipartite(q)


def strategy_for(g: DataGraph, q: QueryGraph, plan: Plan | None = None) -> str:
    """The degree order where few vertices carry the steps, the even split on flat graphs, where starting a cycle at each
    of its nodes costs more than the order saves. From one pass over the arcs, whose keys tell degrees: how many
    arcs a step finds in the mean, from any end and from the lower end of an arc."""
    plan = plan or plan_for(q)
    longest = max((b for b in plan.blocks if b.kind == "cycle"), key=lambda b: len(b.seq), default=None)
    if longest is None or g.order != "degree":
        return "degree"
    below = F.col("src") > F.col("dst")
    n, every, low, ordered = g.arcs().agg(F.count("*"), F.sum(order_of(F.col("dst"))), F.count_if(below), F.sum(F.when(below, order_of(F.col("dst"))))).first()
    if not n:
        return "degree"
    steps, bare = -(-len(longest.seq) // 2) - 1, not longest.boundary and not longest.children
    plain = n * (every / n) ** steps
    return "degree" if (1 if bare else len(longest.seq)) * low * (ordered / low) ** steps <= plain else "even"


def count_colorful(g: DataGraph, q: QueryGraph, coloring, strategy: str = "degree", plan: Plan | None = None, count_type: str = "auto", **rules) -> DataFrame:
    """trial, cnt (decimal(38,0) under count_type='decimal', else long), a row for every trial. strategy 'auto': as
    strategy_for says."""
    spark = g.spark
    if strategy == "auto":
        strategy = strategy_for(g, q, plan)
    trials = spark.range(coloring.trials).select(F.col("id").cast("int").alias("trial"))
    if impossible(g, q):
        return trials.select("trial", F.lit(0).cast("long").alias("cnt"))

    def run(kind: str) -> DataFrame:
        got = Solver(Context(g, coloring, kind), plan or plan_for(q), strategy, **rules).run()
        return trials.join(got, "trial", "left").select("trial", F.coalesce("cnt", F.lit(0)).cast("decimal(38,0)" if kind == "decimal" else "long").alias("cnt"))

    if count_type != "auto":
        return run(count_type)
    try:
        return cut(run("long"), "counts")
    except PySparkException as e:
        if "ARITHMETIC_OVERFLOW" not in str(e):
            raise
        return run("decimal")


def run_banded(g: DataGraph, q: QueryGraph, coloring, bands: int, **rules) -> DataFrame:
    """The root's count as a sum over bands of start vertices. Every strategy is linear in the start of the
    root's paths, so one band at a time bounds what is alive at once."""
    plan = plan_for(q)
    solver = Solver(Context(g, coloring), plan, **rules)
    for b in plan.blocks[:-1]:
        solver.tables[b.id] = cut(solver.block(b), f"block{b.id}", ("trial", "u"))
    parts, whole = [], solver.path
    solver.share, solver.banded = False, True  # a path of one band is not that of another
    for band in range(bands):
        in_band = F.pmod(F.xxhash64("h"), F.lit(bands)) == band
        solver.path = lambda *a, f=in_band: whole(*a).where(f)
        parts.append(cut(solver.block(plan.root).groupBy("trial").agg(F.sum("cnt").alias("cnt")), "band"))
    return reduce(DataFrame.unionByName, parts).groupBy("trial").agg(F.sum("cnt").alias("cnt"))


def load(g: DataGraph, q: QueryGraph, coloring, strategy: str, plan: Plan | None = None) -> DataFrame:
    """step, part, candidates, kept of every join of a run."""
    ctx = Context(g, coloring, load=[])
    Solver(ctx, plan or plan_for(q), strategy, symmetry=False, root_complement=False).run()  # the tables below the root; its steps are noted
    return reduce(DataFrame.unionByName, ctx.load)

