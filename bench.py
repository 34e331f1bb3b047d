"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time


#: Runs of every cell and strategy; the fastest counts.
REPEATS = 2


def main() -> None:
    from huecount.functions.coloring import Coloring
    from huecount.operators import exact, paths
    from huecount.operators.solve import count_colorful, strategy_for
    from huecount.plans.query import CATALOGUE
    from huecount.session import local_session
    from huecount.sources.views import graph_view

    d = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(int(os.environ.get("BENCH_CPUS", "8")), "bench")
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    chosen: dict[str, str] = {}

    def timed(name, make):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
        print(name, seconds[name], file=sys.stderr, flush=True)

    graphs = {}
    for v in ("supply_chain", "user_hour", "succession", "order_part", "page_anchor", "knn8"):
        def build(v=v):
            graphs[v] = graph_view(spark, d, v)
            return graphs[v].arcs()

        timed(f"arcs_{v}", build)
    cells = [("page_anchor", "c4"), ("page_anchor", "ladder6"), ("knn8", "house"), ("knn8", "satellite11"), ("order_part", "c4"), ("user_hour", "c4"), ("succession", "triangle"), ("succession", "c4"), ("part_supplier", "c4")]
    graphs["part_supplier"] = graph_view(spark, d, "part_supplier")
    for v, q in cells:
        c, runs = Coloring(CATALOGUE[q].k, "affine"), {}
        graphs[v].arcs()
        for turn in range(REPEATS):  # strategies take turns, and the order turns round
            for s in ("boundary", "even", "degree")[:: 1 if turn % 2 else -1]:
                timed(f"{q}_{v}_{s}", lambda v=v, q=q, s=s, c=c: count_colorful(graphs[v], CATALOGUE[q], c, s, count_type="long"))
                runs.setdefault(s, []).append(seconds[f"{q}_{v}_{s}"])
        seconds.update({f"{q}_{v}_{s}": min(x) for s, x in runs.items()})
        chosen[f"{v}/{q}"] = strategy_for(graphs[v], CATALOGUE[q])
    timed("triangle_supply_chain_degree", lambda: count_colorful(graphs["supply_chain"], CATALOGUE["triangle"], Coloring(3, "affine"), count_type="long"))
    timed("trials10_c4_order_part", lambda: count_colorful(graphs["order_part"], CATALOGUE["c4"], Coloring(4, "xxhash", 1, 10), count_type="long"))
    timed("exact_triangle_supply_chain", lambda: exact.triangles(graphs["supply_chain"]))
    timed("exact_c4_user_hour", lambda: exact.four_cycles(graphs["user_hour"]))
    timed("x3_user_hour", lambda: paths.count_x(graphs["user_hour"], 3))
    timed("y3_user_hour", lambda: paths.count_y(graphs["user_hour"], 3))
    gains = [seconds[f"{q}_{v}_boundary"] / seconds[f"{q}_{v}_degree"] for v, q in cells]
    auto = [seconds[f"{q}_{v}_boundary"] / seconds[f"{q}_{v}_{chosen[f'{v}/{q}']}"] for v, q in cells]
    total = round(sum(seconds.values()), 3)
    print(json.dumps({"metric": "total_seconds", "value": total, "unit": "sec", "queries": seconds, "sf": d.rsplit("sf", 1)[-1].strip("/"),
                      "improvement_avg": round(sum(gains) / len(gains), 3), "improvement_max": round(max(gains), 3), "share_won": round(sum(g > 1 for g in gains) / len(gains), 3), "auto_avg": round(sum(auto) / len(auto), 3), "auto": chosen}))
    spark.stop()


if __name__ == "__main__":
    main()
