"""Decomposition of a query into leaf edges and cycles, and the choice among decompositions.

A block is contracted away step by step and leaves its projection behind as an annotation: on a node if one
boundary node remains, on a new edge if two remain. Contracting takes over the annotations that lay on the
block's nodes and edges, and those blocks become its children.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from huecount.plans.query import Pair, QueryGraph, check_tree_decomposition, is_treewidth_le2, pair


@dataclass(frozen=True)
class Block:
    id: int
    kind: str  # leaf, cycle
    seq: tuple[str, ...]  # a leaf: (boundary, leaf)
    boundary: tuple[str, ...]
    node_ann: tuple[tuple[str, int], ...] = ()
    edge_ann: tuple[tuple[Pair, int], ...] = ()

    @property
    def children(self) -> tuple[int, ...]:
        return tuple(c for _, c in self.node_ann + self.edge_ann)

    @property
    def key(self):
        return (self.kind, frozenset(self.seq), frozenset(self.boundary))

    def on_node(self, n: str) -> int | None:
        return dict(self.node_ann).get(n)

    def on_edge(self, a: str, b: str) -> int | None:
        return dict(self.edge_ann).get(pair(a, b))


@dataclass
class State:
    """What is left of a query while it is contracted."""

    near: dict[str, set[str]]
    node_ann: dict[str, int] = field(default_factory=dict)
    edge_ann: dict[Pair, int] = field(default_factory=dict)

    def shape(self):
        return frozenset((n, frozenset(x)) for n, x in self.near.items())


def start(q: QueryGraph) -> State:
    return State(q.neighbours())


def boundary(near: dict[str, set[str]], nodes) -> tuple[str, ...]:
    """Those of nodes with a neighbour outside."""
    inside = set(nodes)
    return tuple(n for n in nodes if near[n] - inside)


def leaf_edges(near: dict[str, set[str]]) -> list[tuple[str, tuple[str, ...], tuple[str, ...]]]:
    return [("leaf", (next(iter(near[n])), n), (next(iter(near[n])),)) for n in sorted(near) if len(near[n]) == 1]


def contractible_cycles(near: dict[str, set[str]]) -> list[tuple[str, tuple[str, ...], tuple[str, ...]]]:
    """Induced cycles with two boundary nodes at most, each once: from its smallest node, towards the
    smaller of that node's two neighbours on it."""
    found = []

    def grow(path: list[str]) -> None:
        for n in sorted(near[path[-1]]):
            if n <= path[0] or n in path or near[n] & set(path[1:-1]):
                continue
            if len(path) == 1 or path[0] not in near[n]:
                grow([*path, n])
            elif path[1] < n:
                ends = boundary(near, [*path, n])
                if len(ends) <= 2:
                    found.append(("cycle", (*path, n), ends))

    for n in sorted(near):
        grow([n])
    return sorted(set(found))


def moves(state: State):
    return leaf_edges(state.near) + contractible_cycles(state.near)


def contract(state: State, move, block_id: int) -> tuple[State, Block]:
    """The next state, and the block with the annotations it takes over."""
    kind, seq, ends = move
    around = list(zip(seq, seq[1:], strict=False)) + ([(seq[-1], seq[0])] if kind == "cycle" else [])
    nodes = tuple((n, state.node_ann[n]) for n in seq if n in state.node_ann)
    edges = tuple((pair(a, b), state.edge_ann[pair(a, b)]) for a, b in around if pair(a, b) in state.edge_ann)
    block = Block(block_id, kind, seq, ends, nodes, edges)
    near = {n: set(x) for n, x in state.near.items()}
    for a, b in around:
        near[a].discard(b)
        near[b].discard(a)
    gone = set(seq) - set(ends)
    near = {n: x - gone for n, x in near.items() if n not in gone}
    node_ann = {n: b for n, b in state.node_ann.items() if n not in seq}
    edge_ann = {e: b for e, b in state.edge_ann.items() if e not in {pair(*x) for x in around}}
    if len(ends) == 1:
        node_ann[ends[0]] = block_id
    elif len(ends) == 2:
        x, y = ends
        near[x].add(y)
        near[y].add(x)
        edge_ann[pair(x, y)] = block_id
    return State(near, node_ann, edge_ann), block


@dataclass(frozen=True)
class Plan:
    """Blocks in contraction order; the root is a cycle without boundary, or the node the last block left."""

    query: QueryGraph
    blocks: tuple[Block, ...]

    @property
    def root(self) -> Block:
        return self.blocks[-1]

    def subquery_nodes(self, block: Block | int) -> frozenset[str]:
        b = self.blocks[block] if isinstance(block, int) else block
        return frozenset(b.seq).union(*(self.subquery_nodes(c) for c in b.children))

    def parent(self, block: Block) -> int | None:
        return next((b.id for b in self.blocks if block.id in b.children), None)

    def cost_key(self):
        cycles = [len(b.seq) for b in self.blocks if b.kind == "cycle"]
        return (
            max(cycles, default=0),
            sum(len(b.boundary) for b in self.blocks),
            sum(len(b.children) for b in self.blocks),
            sum(n * n for n in cycles),
            self.text(),
        )

    def text(self) -> str:
        return "; ".join(f"{b.kind}({''.join(b.seq)}|{''.join(b.boundary)})" for b in self.blocks)

    def explain(self) -> str:
        def lines(b: Block, depth: int) -> list[str]:
            own = f"{'  ' * depth}{b.kind} {'-'.join(b.seq)} boundary {','.join(b.boundary) or 'none'} subquery {len(self.subquery_nodes(b))}"
            return [own] + [x for c in b.children for x in lines(self.blocks[c], depth + 1)]

        return "\n".join(lines(self.root, 0))

    def rows(self) -> list[tuple]:
        return [
            (self.query.name, b.id, b.kind, "".join(b.seq), "".join(b.boundary), len(self.subquery_nodes(b)), len(b.children), self.parent(b) if self.parent(b) is not None else -1)
            for b in self.blocks
        ]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), PLAN_SCHEMA)


PLAN_SCHEMA = "query string, block_id int, kind string, nodes string, boundary string, subquery int, children int, parent int"


def replay(q: QueryGraph, chosen) -> Plan:
    state, blocks = start(q), []
    for m in chosen:
        state, block = contract(state, m, len(blocks))
        blocks.append(block)
    return Plan(q, tuple(blocks))


def decompose(q: QueryGraph, chooser=lambda options: options[0]) -> Plan:
    """One plan, taking at each step the move that chooser picks."""
    if not is_treewidth_le2(q):
        raise ValueError("only queries of treewidth two at most can be contracted")
    state, chosen = start(q), []
    while len(state.near) > 1:
        m = chooser(moves(state))
        chosen.append(m)
        state, _ = contract(state, m, len(chosen) - 1)
    return replay(q, chosen)


def enumerate_plans(q: QueryGraph, limit: int | None = None) -> list[Plan]:
    """All plans that differ in their set of (kind, nodes, boundary). What can follow depends on the shape
    that is left alone, so shapes are visited once."""
    if not is_treewidth_le2(q):
        raise ValueError("only queries of treewidth two at most can be contracted")
    known: dict = {}

    def rest(state: State) -> dict:
        """set of block keys -> a sequence of moves"""
        if len(state.near) <= 1:
            return {frozenset(): ()}
        shape = state.shape()
        if shape not in known:
            ways: dict = {}
            for m in moves(state):
                key = (m[0], frozenset(m[1]), frozenset(m[2]))
                after, _ = contract(state, m, 0)
                for keys, seq in rest(after).items():
                    ways.setdefault(keys | {key}, (m, *seq))
            known[shape] = ways
        return known[shape]

    found = [replay(q, seq) for seq in rest(start(q)).values()]
    found.sort(key=Plan.cost_key)
    return found[:limit]


def heuristic(plans: list[Plan]) -> Plan:
    """Shortest longest cycle, then fewest boundary nodes, then fewest annotations, then squares of lengths."""
    return min(plans, key=Plan.cost_key)


def plan_for(q: QueryGraph) -> Plan:
    return heuristic(enumerate_plans(q))


def validate(plan: Plan) -> int:
    """Check a plan's invariants; return the width of the tree decomposition it stands for."""
    q, inherited = plan.query, [c for b in plan.blocks for c in b.children]
    root_left = [plan.root.id]
    if sorted(inherited + root_left) != [b.id for b in plan.blocks]:
        raise ValueError("each block but the root is inherited exactly once")
    own = []
    for b in plan.blocks:
        if len(b.boundary) > 2:
            raise ValueError("more than two boundary nodes")
        around = list(zip(b.seq, b.seq[1:], strict=False)) + ([(b.seq[-1], b.seq[0])] if b.kind == "cycle" else [])
        own += [pair(*e) for e in around if b.on_edge(*e) is None]
    if sorted(own) != sorted(q.edges):
        raise ValueError("each query edge is an own edge of exactly one block")
    if plan.subquery_nodes(plan.root) != set(q.nodes):
        raise ValueError("the root does not represent the query")
    bags, tree, last_of = [], [], {}

    def add(bag: set[str], to: int | None) -> int:
        bags.append(bag)
        if to is not None:
            tree.append((to, len(bags) - 1))
        return len(bags) - 1

    def place(b: Block, to: int | None) -> None:
        first = add(set(b.boundary) or {b.seq[0]}, to)
        if b.kind == "leaf":
            mine = [add(set(b.seq), first)]
        else:  # a fan of triangles around a boundary node
            i = b.seq.index(b.boundary[0]) if b.boundary else 0
            s, mine, at = b.seq[i:] + b.seq[:i], [], None
            for x, y in zip(s[1:], s[2:], strict=False):
                at = add({s[0], x, y}, at)
                mine.append(at)
            target = next((m for m in mine if set(b.boundary) <= bags[m]), mine[0])
            if not set(b.boundary) <= bags[target]:
                raise ValueError("boundary nodes are not in one bag")
            tree.append((first, target))
        for e, c in [((n,), c) for n, c in b.node_ann] + list(b.edge_ann):
            holder = next(m for m in mine if set(e) <= bags[m])
            place(plan.blocks[c], holder)

    place(plan.root, None)
    return check_tree_decomposition(q, bags, tree)
