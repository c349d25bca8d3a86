"""Direct evaluation: every window is expanded and aggregated on its own, nothing shared or kept; and baselines that need
no windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphwin.functions.aggregates import Agg
from graphwin.model import KHop, PropertyGraph, Topological
from graphwin.operators.packed import sum_names
from graphwin.operators.parts import ancestor_rows
from graphwin.operators.reach import window_pairs
from graphwin.operators.whole import whole
from graphwin.session import BROADCAST_ROWS


def attributes(graph: PropertyGraph, aggs: list[Agg], key: str) -> DataFrame:
    """The vertices' id as key, and the attributes that the aggregates read, under their own names. Keys of all plans begin
    with `_gw_`, so an attribute may be called owner, member or v. A condition may read any attribute, also the id; Catalyst
    prunes what it doesn't."""
    read = list(dict.fromkeys(c for a in aggs for c in a.columns))
    return graph.vertices.select(F.col("id").alias(key), *(["*"] if any(a.where for a in aggs) else read))


def aggregate_pairs(graph: PropertyGraph, pairs: DataFrame, aggs: list[Agg], owners: DataFrame | None = None) -> DataFrame:
    """(id, [category,] values...) from window pairs; owners whose window is empty get the value of nothing."""
    joined = pairs.select(F.col("owner").alias("_gw_owner"), F.col("member").alias("_gw_member")).join(attributes(graph, aggs, "_gw_member"), "_gw_member")
    return aggregate_joined(graph, joined, aggs, owners)


def aggregate_joined(graph: PropertyGraph, joined: DataFrame, aggs: list[Agg], owners: DataFrame | None = None) -> DataFrame:
    """The same from _gw_owner with its members' attributes."""
    by = aggs[0].by
    parts = [a for a in aggs if not a.holistic]
    whole = [a for a in aggs if a.holistic]
    grouped = joined.groupBy("_gw_owner", *[by] * bool(by)).agg(*[p for a in parts for p in a.partials()], *[a.whole() for a in whole])
    out = grouped.select(F.col("_gw_owner").alias("id"), *[by] * bool(by), *[a.final() for a in parts], *[a.alias for a in whole])
    return out if by else with_all_owners(graph, out, aggs, owners)


def with_all_owners(graph: PropertyGraph, out: DataFrame, aggs: list[Agg], owners: DataFrame | None) -> DataFrame:
    """Adds owners without any member: 0 for counts, null otherwise."""
    every = graph.vertices.select("id") if owners is None else owners.select(F.col("owner").alias("id")).distinct()
    return every.join(out, "id", "left").select("id", *[F.coalesce(a.alias, F.lit(0)).cast("long").alias(a.alias) if a.fn in ("count", "count_if", "count_distinct", "approx_distinct") else F.col(a.alias) for a in aggs])


def additive(graph: PropertyGraph, aggs: list[Agg]) -> tuple[DataFrame, list[Column]] | None:
    """((id, [part,] sum_names), partials from their sums) if all aggregates are sums of whole numbers that can't overflow: for
    each its number, 0 for null, and whether it counts. None for other aggregates, and for more vertices than are sent whole."""
    numbers, partials = [], []
    for a in aggs:
        if a.by or a.fn not in ("sum", "avg", "count", "count_if"):
            return None
        x = a._x(a.attr)
        known = f"_gw_s{len(numbers)}"
        numbers.append(x.isNotNull().cast("long").alias(known))
        if a.fn in ("sum", "avg"):
            if graph.vertices.schema[a.attr].dataType.typeName() not in ("byte", "short", "integer", "long"):
                return None
            total = f"_gw_s{len(numbers)}"
            numbers.append(F.coalesce(x.cast("long"), F.lit(0)).cast("long").alias(total))
            partials.append(F.when(F.col(known) > 0, F.col(total)).alias(a.partial_names()[0]))
        if a.fn != "sum":
            partials.append(F.col(known).alias(a.partial_names()[-1]))
    values = graph.vertices.select("id", *[graph.part] * bool(graph.part), *numbers)
    names = sum_names(len(numbers))
    n, most = values.agg(F.count("*"), F.greatest(F.lit(0.0), *[F.max(F.abs(F.col(c).cast("double"))) for c in names])).first()
    return None if n > BROADCAST_ROWS or n * (most or 0) > 2.0**62 else (values, partials)


def direct(graph: PropertyGraph, window: KHop | Topological, aggs: list[Agg], owners: DataFrame | None = None) -> DataFrame:
    if isinstance(window, Topological) and owners is None:  # members come with their attributes, so pairs aren't shuffled
        names = graph.vertices.columns if any(a.where for a in aggs) else list(dict.fromkeys(c for a in aggs for c in a.columns))
        rows = ancestor_rows(graph if window.direction == "ancestors" else graph.reversed(), window.include_self, names)
        if rows is not None:
            return aggregate_joined(graph, rows.select(F.col("owner").alias("_gw_owner"), *[F.col(f"_gw_{c}").alias(c) for c in names]), aggs)
        sums = additive(graph, aggs)
        w = whole(graph if window.direction == "ancestors" else graph.reversed()) if sums is not None else None
        if w is not None:  # a window is added up in the tasks that hold its stretches
            values, partials = sums
            out = w.window_sums(values.drop(*[graph.part] * bool(graph.part)), window.include_self)
            return with_all_owners(graph, out.select("id", *partials).select("id", *[a.final() for a in aggs]), aggs, None)
    return aggregate_pairs(graph, window_pairs(graph, window, owners), aggs, owners)


def running_window(rows: DataFrame, partition: str, order: list[str], attr: str, id_col: str = "id", alias: str = "value") -> DataFrame:
    """On paths a topological window is a running sum."""
    w = Window.partitionBy(partition).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return rows.select(F.col(id_col).alias("id"), F.sum(attr).over(w).alias(alias))


def propagate(graph: PropertyGraph, window: KHop, agg: Agg) -> DataFrame:
    """k rounds of join and merge for idempotent aggregates: no windows, no index, k x (V + E) rows."""
    if not agg.idempotent or agg.by:
        raise ValueError(f"{agg.fn} isn't idempotent")
    if not window.include_self:
        raise ValueError("propagation can't leave out the owner")
    arcs = graph.arcs_with_self(window.direction).toDF("_gw_src", "_gw_dst")
    values = attributes(graph, [agg], "_gw_id").groupBy("_gw_id").agg(*agg.partials())
    for _ in range(window.k):
        values = arcs.join(values, F.col("_gw_dst") == F.col("_gw_id")).groupBy(F.col("_gw_src").alias("_gw_id")).agg(*agg.merges())
    return values.select(F.col("_gw_id").alias("id"), agg.final())
