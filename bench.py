"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line.

Times are of whole queries into a sink that keeps nothing. For indices, build and query are timed apart; ratios beside
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from graphwin.functions.aggregates import Agg  # noqa: E402
from graphwin.model import KHop, Topological  # noqa: E402
from graphwin.operators.blockindex import block_query, build_block_index  # noqa: E402
from graphwin.operators.deltaindex import build_delta_index, delta_query  # noqa: E402
from graphwin.operators.direct import direct, propagate  # noqa: E402
from graphwin.operators.overlay import build_overlay, overlay_query  # noqa: E402
from graphwin.plans.measures import add_count, add_count_direct, break_even, index_entries, index_ratio, saving, timed  # noqa: E402
from graphwin.operators.reach import window_pairs  # noqa: E402
from graphwin.session import local_session, materialize  # noqa: E402
from graphwin.sources import graphs as G  # noqa: E402
from graphwin.model import PropertyGraph  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def kept(g: PropertyGraph) -> PropertyGraph:
    """A graph read from written tables, so that queries don't pay for deriving it."""
    return PropertyGraph(materialize(g.vertices, "bench-v"), materialize(g.edges.select("src", "dst"), "bench-e"), g.directed, g.name)


def main() -> None:
    began = time.time()
    spark = local_session(CPUS, int(CPUS), **{"spark.driver.memory": "8g"})
    spark.sparkContext.setLogLevel("ERROR")
    out: dict[str, float] = {}
    ratios: dict[str, float] = {}
    timed(lambda: spark.range(1000))

    # k-hop: direct, full and estimated clustering, overlay
    graphs = {"copurchase2": (kept(G.copurchase(spark, SF_DIR, 2)), [Agg("sum", "p_size")]), "weblinks": (kept(G.weblinks(spark, SF_DIR)), [Agg("sum", "size")]), "community": (kept(G.community(spark, SF_DIR)), [Agg("sum", "n_chars")])}
    for name, k in (("copurchase2", 1), ("copurchase2", 2), ("weblinks", 2), ("community", 1)):
        g, agg = graphs[name]
        w = KHop(k, "both")
        out[f"{name}_k{k}_direct"], _ = timed(lambda: direct(g, w, agg))  # noqa: B023
        adds = add_count_direct(window_pairs(g, w)).first()[0]
        builds = {}
        for method in ("mc", "emc"):
            if method == "emc" and k == 1:
                continue
            builds[method], ix = timed(lambda: build_block_index(g, w, method))  # noqa: B023
            out[f"{name}_k{k}_{method}_build"] = builds[method]
            out[f"{name}_k{k}_{method}_query"], _ = timed(lambda: block_query(ix, g, agg), 3)  # noqa: B023
            ratios[f"{name}_k{k}_{method}_speedup"] = out[f"{name}_k{k}_direct"] / out[f"{name}_k{k}_{method}_query"]
            ratios[f"{name}_k{k}_{method}_index_ratio"] = index_ratio(ix, g)
            ratios[f"{name}_k{k}_{method}_adds_share"] = add_count(ix) / max(1, adds)
        if len(builds) > 1:
            ratios[f"{name}_k{k}_emc_build_saving"] = saving(builds["mc"], builds["emc"])
    g, agg = graphs["community"]
    out["community_k1_overlay_build"], ov = timed(lambda: build_overlay(g, KHop(1, "both"), 2))
    out["community_k1_overlay_query"], _ = timed(lambda: overlay_query(ov, g, agg), 3)
    g, agg = graphs["copurchase2"]
    out["copurchase2_k2_propagate_max"], _ = timed(lambda: propagate(g, KHop(2), Agg("max", "p_size")))

    # topological: direct, parent delta
    dags = {"eventbranch": (kept(G.eventbranch(spark, SF_DIR)), "cents"), "synthdag_1000_10": (kept(G.synthdag(spark, 1000, 10)), "attr")}
    for name, (g, attr) in dags.items():
        agg = [Agg("sum", attr)]
        out[f"{name}_direct"], _ = timed(lambda: direct(g, Topological(), agg))  # noqa: B023
        out[f"{name}_delta_build"], dx = timed(lambda: build_delta_index(g))  # noqa: B023
        out[f"{name}_delta_query"], _ = timed(lambda: delta_query(dx, g, agg), 2)  # noqa: B023
        ratios[f"{name}_delta_speedup"] = out[f"{name}_direct"] / out[f"{name}_delta_query"]
        ratios[f"{name}_delta_entries_over_graph"] = index_entries(dx) / (g.vertices.count() + g.edges.count())
        ratios[f"{name}_delta_break_even_queries"] = break_even(out[f"{name}_delta_build"], out[f"{name}_direct"], out[f"{name}_delta_query"])
    rounded = {k: round(v, 3) for k, v in out.items()}
    clean = {k: (round(v, 4) if v != float("inf") else None) for k, v in ratios.items()}
    print(json.dumps({"metric": "window_queries_total", "value": round(sum(out.values()), 3), "unit": "sec", "queries": rounded, "ratios": clean, "sf": SF_DIR.rsplit("sf", 1)[-1], "wall": round(time.time() - began, 1)}))
    spark.stop()


if __name__ == "__main__":
    main()
