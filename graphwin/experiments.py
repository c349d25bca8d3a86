"""The experiment sweeps: each returns rows (experiment, graph, method, k, x, metric, value) as a list, x being the swept
size or degree. Every strategy's result is compared with direct evaluation before its time counts."""

from __future__ import annotations

from pyspark.sql import SparkSession

from graphwin.functions.aggregates import Agg
from graphwin.model import KHop, PropertyGraph, Topological
from graphwin.operators.blockindex import block_query, build_block_index
from graphwin.operators.deltaindex import build_delta_index, delta_query
from graphwin.operators.direct import direct
from graphwin.operators.overlay import build_overlay, overlay_query
from graphwin.plans import measures as M
from graphwin.sources import graphs as G

Row = tuple[str, str, str, int, float, str, float]


def _attr(g: PropertyGraph) -> str:
    return next(f.name for f in g.vertices.schema if f.name != "id" and f.dataType.typeName() == "long")


def _same(a, b) -> bool:
    key = lambda df: df.toPandas().sort_values("id").reset_index(drop=True)
    return key(a).equals(key(b))


def khop_methods(experiment: str, g: PropertyGraph, k: int, x: float, methods=("direct", "mc", "emc", "overlay"), check: bool = True, direction: str = "out") -> list[Row]:
    """Build time, query time, size and additions of each method for one window."""
    agg, w, rows = [Agg("sum", _attr(g))], KHop(k, direction), []
    add = lambda m, what, v: rows.append((experiment, g.name, m, k, x, what, float(v)))
    base = direct(g, w, agg)
    t0, _ = M.timed(lambda: base)
    add("direct", "query_s", t0)
    for m in methods:
        if m == "direct" or m == "emc" and k < 2:
            continue
        if m == "overlay":
            b, ov = M.timed(lambda: build_overlay(g, w))
            q, res = M.timed(lambda: overlay_query(ov, g, agg))  # noqa: B023
            add(m, "entries_ratio", M.index_ratio(ov, g))
        else:
            b, ix = M.timed(lambda: build_block_index(g, w, m, explicit_signatures=True))  # noqa: B023
            q, res = M.timed(lambda: block_query(ix, g, agg))  # noqa: B023
            add(m, "hash_s", ix.stats.hash_s), add(m, "traverse_s", ix.stats.traverse_s), add(m, "refine_s", ix.stats.refine_s)
            add(m, "entries_ratio", M.index_ratio(ix, g)), add(m, "adds", M.add_count(ix))
        if check and not _same(res, base):
            raise AssertionError(f"{m} differs from direct evaluation on {g.name}")
        add(m, "build_s", b), add(m, "query_s", q), add(m, "speedup", M.speedup(t0, q))
    return rows


def dag_methods(experiment: str, g: PropertyGraph, x: float, methods=("mc", "delta"), check: bool = True) -> list[Row]:
    agg, w, rows = [Agg("sum", _attr(g))], Topological(), []
    add = lambda m, what, v: rows.append((experiment, g.name, m, 0, x, what, float(v)))
    base = direct(g, w, agg)
    t0, _ = M.timed(lambda: base)
    add("direct", "query_s", t0)
    for m in methods:
        b, ix = M.timed(lambda: build_delta_index(g) if m == "delta" else build_block_index(g, w, "mc"))  # noqa: B023
        q, res = M.timed(lambda: delta_query(ix, g, agg) if m == "delta" else block_query(ix, g, agg))  # noqa: B023
        if check and not _same(res, base):
            raise AssertionError(f"{m} differs from direct evaluation on {g.name}")
        add(m, "build_s", b), add(m, "query_s", q), add(m, "speedup", M.speedup(t0, q))
        add(m, "entries_ratio", M.index_ratio(ix, g)), add(m, "adds", M.add_count(ix)), add(m, "break_even", M.break_even(b, t0, q))
    return rows


def hop_sweep(spark: SparkSession, sf_dir: str, ks=(1, 2, 3)) -> list[Row]:
    """Build time, index ratio and query time over the number of hops (co-purchase and relay graphs)."""
    out: list[Row] = []
    for g in (G.copurchase(spark, sf_dir, 2), G.relay(spark, sf_dir, ["1-URGENT", "2-HIGH"])):
        for k in ks:
            out += khop_methods("hops", g, k, k, ("mc", "emc"))
    return out


def against_overlay(spark: SparkSession, sf_dir: str, k: int = 1) -> list[Row]:
    """Shared blocks against overlay mining over graphs of different shape."""
    graphs = [G.copurchase(spark, sf_dir, 2), G.relay(spark, sf_dir, ["1-URGENT"]), G.trade(spark, sf_dir), G.weblinks(spark, sf_dir), G.cosupply(spark, sf_dir), G.community(spark, sf_dir)]
    return [r for g in graphs for r in khop_methods("overlay", g, k, k, ("mc", "overlay"), direction="both")]


def size_sweep(spark: SparkSession, sizes=(500, 1000, 2000), degree: int = 10, k: int = 1) -> list[Row]:
    return [r for n in sizes for r in khop_methods("size", G.synthrand(spark, n, degree), k, n, ("mc", "emc"))]


def degree_sweep(spark: SparkSession, n: int = 500, degrees=(5, 10, 20, 30), ks=(1, 2)) -> list[Row]:
    """Sparse degrees by default; pass (80, ..., 200) for dense graphs."""
    return [r for d in degrees for k in ks for r in khop_methods("degree", G.synthrand(spark, n, d), k, d, ("mc", "emc", "overlay"))]


def dag_degree_sweep(spark: SparkSession, n: int = 300, degrees=(3, 5, 10, 20)) -> list[Row]:
    return [r for d in degrees for r in dag_methods("dag_degree", G.synthdag(spark, n, d), d)]


def dag_size_sweep(spark: SparkSession, sizes=(200, 400, 800), degree: int = 10) -> list[Row]:
    return [r for n in sizes for r in dag_methods("dag_size", G.synthdag(spark, n, degree), n, ("delta",))]


def dag_ratio_grid(spark: SparkSession, sizes=(200, 400), degrees=(3, 5, 10, 20)) -> list[Row]:
    """Size of the parent-delta index over the graph's, by size and degree."""
    out: list[Row] = []
    for n in sizes:
        for d in degrees:
            g = G.synthdag(spark, n, d)
            ix = build_delta_index(g)
            out.append(("dag_ratio", g.name, "delta", 0, float(d), "entries_ratio", M.index_ratio(ix, g)))
    return out


def similarity_growth(spark: SparkSession, sf_dir: str):
    """How window similarity moves with the hops, and the expansion bound beside what is seen."""
    return M.jaccard_growth(G.copurchase(spark, sf_dir, 3), [1, 2, 3]), M.expansion_bound(G.synthrand(spark, 500, 6), 1)
