"""DuckDB formulations that are built from a query graph: plain self-joins, no dynamic programme."""

from __future__ import annotations

from huecount.functions.coloring import affine_sql
from huecount.operators.exact import search_order
from huecount.plans.query import QueryGraph
from huecount.sources.views import VIEW_SQL


def arcs_with(view: str, rest: str) -> str:
    return arcs_of(VIEW_SQL[view], rest)


def arcs_of(edges: str, rest: str) -> str:
    return f"WITH e AS MATERIALIZED ({edges}), a AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), d AS MATERIALIZED (SELECT src AS v, count(*) AS deg FROM a GROUP BY src) {rest}"


def _joined(q: QueryGraph, source: str, unlike) -> tuple[str, str]:
    """FROM and WHERE of all injective images, one arc per query edge."""
    order, near = search_order(q), q.neighbours()
    frm = []
    for i, n in enumerate(order[1:], 1):
        known = sorted(near[n] & set(order[:i]))
        if i == 1:
            frm.append(f"(SELECT src AS n_{known[0]}, c1 AS c_{known[0]}, dst AS n_{n}, c2 AS c_{n} FROM {source})")
        else:
            on = [f"n_{known[0]} = s_{n}"] + [unlike(m, n) for m in order[:i]]
            frm.append(f"JOIN (SELECT src AS s_{n}, dst AS n_{n}, c2 AS c_{n} FROM {source}) ON {' AND '.join(on)}")
        for m in known[1:]:
            frm.append(f"JOIN (SELECT src AS s_{n}_{m}, dst AS t_{n}_{m} FROM {source}) ON s_{n}_{m} = n_{m} AND t_{n}_{m} = n_{n}")
    return " ".join(frm), unlike(order[0], order[1])


def tree(view: str, q: QueryGraph, k: int | None = None) -> str:
    """Colourful matches of a tree query, level by level from the leaves: tables of (vertex, colours, number)."""
    k, near, parts = k or q.k, q.neighbours(), []

    def below(n: str, parent: str | None) -> str:
        parts.append(f"t_{n}_0 AS MATERIALIZED (SELECT v, 1::BIGINT << ({affine_sql('v', k)})::INTEGER AS s, 1::HUGEINT AS c FROM d)")
        made = f"t_{n}_0"
        for i, child in enumerate(sorted(near[n] - {parent}), 1):
            t = below(child, n)
            parts.append(f"u_{child} AS MATERIALIZED (SELECT a.src AS v, t.s, sum(t.c) AS c FROM a JOIN {t} t ON t.v = a.dst GROUP BY ALL)")
            parts.append(f"t_{n}_{i} AS MATERIALIZED (SELECT x.v, x.s | y.s AS s, sum(x.c * y.c) AS c FROM {made} x JOIN u_{child} y ON x.v = y.v AND x.s & y.s = 0 GROUP BY ALL)")
            made = f"t_{n}_{i}"
        return made

    top = below(q.nodes[0], None)
    return arcs_with(view, f", {', '.join(parts)} SELECT coalesce(sum(c), 0)::BIGINT AS cnt FROM {top}")


def colorful(view: str, q: QueryGraph, k: int | None = None, trial: str = "0") -> str:
    """SELECT of the number of colourful matches as cnt."""
    return colorful_of(VIEW_SQL[view], q, k, trial)


def colorful_of(edges: str, q: QueryGraph, k: int | None = None, trial: str = "0") -> str:
    k = k or q.k
    frm, where = _joined(q, "c", lambda m, n: f"c_{m} <> c_{n}")
    colored = f"c AS MATERIALIZED (SELECT src, dst, {affine_sql('src', k, trial)} AS c1, {affine_sql('dst', k, trial)} AS c2 FROM a)"
    return arcs_of(edges, f", {colored} SELECT count(*)::BIGINT AS cnt FROM {frm} WHERE {where}")


def exact(view: str, q: QueryGraph) -> str:
    frm, where = _joined(q, "c", lambda m, n: f"n_{m} <> n_{n}")
    return arcs_with(view, f", c AS (SELECT src, dst, 0 AS c1, 0 AS c2 FROM a) SELECT count(*)::BIGINT AS cnt FROM {frm} WHERE {where}")


def paths(view: str, q: int, order: str | None) -> str:
    """Simple paths on q vertices, all or with the first one highest (degree) or largest (id)."""
    frm = ["(SELECT x.src AS p1, x.dst AS p2 FROM a x)"]
    tests = []
    for n in range(3, q + 1):
        frm.append(f"JOIN (SELECT src AS s{n}, dst AS p{n} FROM a) ON s{n} = p{n - 1}" + "".join(f" AND p{m} <> p{n}" for m in range(1, n - 1)))
    if order == "id":
        tests = [f"p1 > p{n}" for n in range(2, q + 1)]
    elif order == "degree":
        frm += [f"JOIN (SELECT v AS v{n}, deg AS d{n} FROM d) ON v{n} = p{n}" for n in range(1, q + 1)]
        tests = [f"(d1 > d{n} OR (d1 = d{n} AND p1 > p{n}))" for n in range(2, q + 1)]
    return arcs_with(view, f"SELECT count(*)::BIGINT AS cnt FROM {' '.join(frm)}" + (f" WHERE {' AND '.join(tests)}" if tests else ""))


def profile(view: str) -> str:
    return arcs_with(view, f"SELECT '{view}' AS view, count(*)::BIGINT AS nodes, (sum(deg) // 2)::BIGINT AS edges, (sum(deg) // 2)::DOUBLE / count(*) AS avg_deg, max(deg)::BIGINT AS max_deg FROM d")
