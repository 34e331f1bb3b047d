"""Query graphs: small, connected, simple, of treewidth at most two."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import DataFrame

Pair = tuple[str, str]


def pair(a: str, b: str) -> Pair:
    return (a, b) if a < b else (b, a)


@dataclass(frozen=True)
class QueryGraph:
    name: str
    nodes: tuple[str, ...]
    edges: tuple[Pair, ...]

    @property
    def k(self) -> int:
        return len(self.nodes)

    def neighbours(self) -> dict[str, set[str]]:
        near: dict[str, set[str]] = {n: set() for n in self.nodes}
        for a, b in self.edges:
            near[a].add(b)
            near[b].add(a)
        return near

    def text(self) -> str:
        return " ".join(a + b for a, b in self.edges)


def build(name: str, edges: list[Pair]) -> QueryGraph:
    """Validate and normalise: at least one edge, no loop, connected. Repeated edges count once."""
    if not edges:
        raise ValueError("a query needs an edge")
    if any(a == b for a, b in edges):
        raise ValueError("a query has no self-loops")
    kept = sorted({pair(a, b) for a, b in edges})
    q = QueryGraph(name, tuple(sorted({n for e in kept for n in e})), tuple(kept))
    near, seen, todo = q.neighbours(), {q.nodes[0]}, [q.nodes[0]]
    while todo:
        for n in near[todo.pop()] - seen:
            seen.add(n)
            todo.append(n)
    if len(seen) < q.k:
        raise ValueError("a query is connected")
    return q


def parse(text: str, name: str = "query") -> QueryGraph:
    """'ab bc ca', or 'n1-n2 n2-n3' for longer node names."""
    edges = []
    for word in text.split():
        ends = word.split("-") if "-" in word else list(word)
        if len(ends) != 2 or not all(ends):
            raise ValueError(f"not an edge: {word!r}")
        edges.append((ends[0], ends[1]))
    return build(name, edges)


def from_df(df: DataFrame, name: str) -> QueryGraph:
    """From rows (query, a, b); a query has a handful of them."""
    rows = df.where(df["query"] == name).select("a", "b").collect()
    return build(name, [(r[0], r[1]) for r in rows])


def is_treewidth_le2(q: QueryGraph) -> bool:
    """Nodes of degree two or less are removed, their neighbours joined, until nothing or a core is left."""
    near = q.neighbours()
    while near:
        low = next((n for n in sorted(near) if len(near[n]) <= 2), None)
        if low is None:
            return False
        ends = near.pop(low)
        for a in ends:
            near[a] = (near[a] | ends) - {a, low}
    return True


def check_tree_decomposition(q: QueryGraph, bags: list[set[str]], tree: list[tuple[int, int]]) -> int:
    """Width of a tree decomposition; raises if a property fails."""
    if len(tree) != len(bags) - 1:
        raise ValueError("a tree has one edge less than bags")
    for a, b in q.edges:
        if not any({a, b} <= bag for bag in bags):
            raise ValueError(f"no bag holds edge {a}{b}")
    near: dict[int, set[int]] = {i: set() for i in range(len(bags))}
    for i, j in tree:
        near[i].add(j)
        near[j].add(i)
    for n in q.nodes:
        with_n = {i for i, bag in enumerate(bags) if n in bag}
        seen = todo = {next(iter(with_n))}
        while todo:
            todo = {j for i in todo for j in near[i]} & with_n - seen
            seen = seen | todo
        if seen != with_n:
            raise ValueError(f"bags of {n} are not connected")
    return max(map(len, bags)) - 1


def automorphisms(q: QueryGraph) -> int:
    """Backtracking over images of equal degree."""
    near, order = q.neighbours(), list(q.nodes)

    def count(at: int, image: dict[str, str]) -> int:
        if at == len(order):
            return 1
        n, total = order[at], 0
        for m in q.nodes:
            if m in image.values() or len(near[m]) != len(near[n]):
                continue
            if all((image[p] in near[m]) == (p in near[n]) for p in order[:at]):
                total += count(at + 1, image | {n: m})
        return total

    return count(0, {})


def sides(q: QueryGraph) -> dict[str, int] | None:
    """The side of every node of a connected query, or None if it is not bipartite."""
    near, side = q.neighbours(), {q.nodes[0]: 0}
    todo = [q.nodes[0]]
    while todo:
        n = todo.pop()
        for m in near[n]:
            if m not in side:
                side[m] = 1 - side[n]
                todo.append(m)
            elif side[m] == side[n]:
                return None
    return side


def is_bipartite(q: QueryGraph) -> bool:
    return sides(q) is not None


def swaps_sides(q: QueryGraph) -> bool:
    """Whether an automorphism takes each side of a bipartite query to the other: for bare even cycles, one step round. Only they are
    told; False says nothing of others."""
    return is_bipartite(q) and len(q.edges) == q.k and all(len(x) == 2 for x in q.neighbours().values())



def is_tree(q: QueryGraph) -> bool:
    return len(q.edges) == q.k - 1


def is_complete(q: QueryGraph) -> bool:
    return all(pair(a, b) in q.edges for a, b in combinations(q.nodes, 2))


# Fixed edge lists of the catalogue.
_CATALOGUE = {
    "satellite11": "ab bc cd de ea af fg gc fi gi fh ij jk ki",
    "triangle": "ab bc ca",
    "c4": "ab bc cd da",
    "c5": "ab bc cd de ea",
    "c6": "ab bc cd de ef fa",
    "c8": "ab bc cd de ef fg gh ha",
    "paw": "ab bc ca ad",
    "diamond": "ab bc ca ad dc",
    "bull": "ab bc ca ad be",
    "bowtie": "ab bc ca ad de ea",
    "house": "ab bc cd da ae eb",
    "c4_tail": "ab bc cd da ae",
    "ladder6": "ab bc cd af fe ed ad",
    "c4_c6": "ab bc cd da ae ef fg gh hb",
    "c4_c5": "ab bc cd da be ef fg ga",
    "cactus10": "ab bc ca cd de ef fc fg gh hi ij jg",
    "fan5": "ab ac ad ae bc cd de",
    "k23": "ax ay az bx by bz",
    "path4": "ab bc cd",
    "star4": "ab ac ad",
    "bintree12": "ab ac bd be cf cg dh di ej ek fl",
}
CATALOGUE = {name: parse(text, name) for name, text in _CATALOGUE.items()}
#: Stand-ins of the ten queries of the experiments.
EXPERIMENT_QUERIES = ("paw", "diamond", "bull", "bowtie", "house", "c4_tail", "ladder6", "c4_c6", "c4_c5", "cactus10")
