"""Running window queries: functions over one window share a pass, strategies are interchangeable."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.functions.aggregates import Agg
from graphwin.model import PropertyGraph, Topological, VertexWindowQuery
from graphwin.operators.blockindex import BlockIndex, block_query, block_query_once, refuse_holistic
from graphwin.operators.deltaindex import DeltaIndex, build_delta_index, delta_query
from graphwin.operators.direct import direct, propagate
from graphwin.operators.overlay import Overlay, build_overlay, overlay_query
from graphwin.plans.planner import choose

STRATEGIES = ("auto", "direct", "propagate", "block", "delta", "overlay")


def _evaluate(graph: PropertyGraph, window, aggs: list[Agg], strategy: str, owners: DataFrame | None, index=None, order: str = "jump", **build) -> DataFrame:
    if strategy == "auto":
        strategy = choose(graph, window, aggs, build.pop("queries", 1), isinstance(index, BlockIndex), isinstance(index, DeltaIndex)).strategy
    if strategy in ("block", "delta", "overlay"):
        refuse_holistic(aggs)
    if strategy == "direct":
        return direct(graph, window, aggs, owners)
    if strategy == "propagate":
        parts = [propagate(graph, window, a) for a in aggs]
        out = reduce(lambda a, b: a.join(b, "id"), parts)
        return out if owners is None else out.join(owners.select(F.col("owner").alias("id")), "id", "left_semi")
    if strategy == "block":
        return block_query(index, graph, aggs, owners) if isinstance(index, BlockIndex) else block_query_once(graph, window, aggs, owners, **build)
    if strategy == "delta":
        if not isinstance(window, Topological) or not window.include_self:
            raise ValueError("the parent-delta index serves topological windows that include their owner")
        g = graph if window.direction == "ancestors" else graph.reversed()
        ix = index if isinstance(index, DeltaIndex) else build_delta_index(g)
        return delta_query(ix, g, aggs, order, owners)
    if strategy == "overlay":
        ix = index if isinstance(index, Overlay) else build_overlay(graph, window, **build)
        out = overlay_query(ix, graph, aggs)
        return out if owners is None else out.join(owners.select(F.col("owner").alias("id")), "id", "left_semi")
    raise ValueError(f"unknown strategy {strategy}; one of {STRATEGIES}")


def run(query: VertexWindowQuery, strategy: str = "auto", shared: bool = True, owners: DataFrame | None = None, index=None, **options) -> DataFrame:
    """shared: functions over equal windows (and equal split attribute) are evaluated in one pass; otherwise one after the
    other and joined. Split functions can't be joined with others."""
    groups: dict = {}
    for i, f in enumerate(query.functions):
        groups.setdefault((f.window, f.agg.by) if shared else i, []).append(f)
    parts = [_evaluate(query.graph, fs[0].window, [f.agg for f in fs], strategy, owners, index, **options) for fs in groups.values()]
    if len(parts) > 1 and any(f.agg.by for f in query.functions):
        raise ValueError("functions split by an attribute run on their own")
    return reduce(lambda a, b: a.join(b, "id"), parts)


def top(result: DataFrame, n: int, col: str = "value") -> DataFrame:
    """The n vertices with the largest value (ties: least id): each task keeps n rows."""
    return result.orderBy(F.desc(col), "id").limit(n)


def explain(query: VertexWindowQuery, queries: int = 1) -> str:
    return "\n\n".join(f"{f.window} {f.agg.fn}({f.agg.attr or '*'})\n{choose(query.graph, f.window, [f.agg], queries).text()}" for f in query.functions)
