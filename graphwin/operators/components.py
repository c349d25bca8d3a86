"""Connected components by alternating stars over edge tables.

A large star hangs every larger neighbour of a vertex on the least one around it, a small star does so for the smaller
neighbours; alternating both ends, after few rounds, in one star per component whose centre is the least vertex. All
steps are map-side combined minima and equi-joins, so a hub's edges are never gathered in one row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.session import discard, materialize

MAX_ROUNDS = 60
#: A vertex is a hub above this share of the edges, and above HUB_EDGES of them.
HUBS, HUB_EDGES = 200, 200


def _mark(edges: DataFrame):
    return edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()


def _with_least(rows: DataFrame, n_rows: int) -> tuple[DataFrame, DataFrame]:
    """(u, v, m): rows (u, v) with the least v of each u; and the written table of minima that it reads."""
    least = materialize(rows.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("_n")), "least")
    hub = F.col("_n") > max(HUB_EDGES, n_rows // HUBS)
    if least.where(hub).isEmpty():
        return rows.join(least.drop("_n"), "u").select("u", "v", "m"), least
    hubs = F.broadcast(least.where(hub).select(F.col("u").alias("_u"), "m"))
    others = rows.join(hubs, F.col("u") == F.col("_u"), "left_anti").join(least.where(~hub).drop("_n"), "u").select("u", "v", "m")
    return others.union(rows.join(hubs, F.col("u") == F.col("_u")).select("u", "v", "m")), least


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """(vertex, component) of every vertex with an edge; component is the least vertex reachable. Any orderable id type;
    direction, loops and repeated edges don't matter; no edges give no rows."""
    e = edges.select(F.col(src).alias("u"), F.col(dst).alias("v"))
    loops = e.where(F.col("u") == F.col("v")).select(F.col("u").alias("vertex")).distinct()
    now = materialize(e.where(F.col("u") != F.col("v")).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "components")
    loops = materialize(loops, "loops")
    mark = _mark(now)
    for _ in range(MAX_ROUNDS):
        both = now.union(now.select(F.col("v"), F.col("u")))
        large, of_both = _with_least(both, 2 * mark[0])
        large = large.select("u", "v", F.least("u", "m").alias("m")).where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = materialize(large, "large")
        near, of_large = _with_least(large, mark[0])
        small = near.select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).distinct()
        after = materialize(small, "components")
        discard(now, large, of_both, of_large)
        now, before, mark = after, mark, _mark(after)
        if mark == before:
            break
    else:
        raise RuntimeError(f"no fixed point after {MAX_ROUNDS} rounds")
    centres = now.select(F.col("v").alias("vertex")).distinct()
    known = now.select(F.col("u").alias("vertex"), F.col("v").alias("component")).union(centres.select("vertex", F.col("vertex").alias("component")))
    return known.union(loops.join(known, "vertex", "left_anti").select("vertex", F.col("vertex").alias("component")))
