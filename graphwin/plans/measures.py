"""Cost and quality measures of windows and indices."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.model import KHop, PropertyGraph
from graphwin.operators.blockindex import BlockIndex, jaccard_exact
from graphwin.operators.deltaindex import DeltaIndex
from graphwin.operators.overlay import Overlay
from graphwin.operators.reach import window_pairs


def timed(work: Callable[[], object], repeat: int = 1):
    """(median seconds, last result); a DataFrame is run to the end by a sink that keeps nothing."""
    took, out = [], None
    for _ in range(repeat):
        began = time.time()
        out = work()
        if isinstance(out, DataFrame):
            out.write.format("noop").mode("overwrite").save()
        took.append(time.time() - began)
    return median(took), out


def speedup(base_s: float, other_s: float) -> float:
    return base_s / other_s if other_s else math.inf


def saving(full_s: float, estimated_s: float) -> float:
    return 1 - estimated_s / full_s if full_s else 0.0


def break_even(build_s: float, direct_s: float, indexed_s: float) -> float:
    """Queries after which building has paid; infinite if the index isn't faster."""
    return build_s / (direct_s - indexed_s) if direct_s > indexed_s else math.inf


def growth(runs: list[tuple[float, float]]) -> float:
    """Least-squares exponent of y over x on logarithms."""
    pts = [(math.log(x), math.log(y)) for x, y in runs if x > 0 and y > 0]
    mx, my = sum(p[0] for p in pts) / len(pts), sum(p[1] for p in pts) / len(pts)
    return sum((a - mx) * (b - my) for a, b in pts) / (sum((a - mx) ** 2 for a, _ in pts) or 1)


def index_entries(ix: BlockIndex | DeltaIndex | Overlay) -> int:
    if isinstance(ix, BlockIndex):
        return ix.members.count() + ix.links.count()
    if isinstance(ix, DeltaIndex):
        return ix.parent.count() + ix.delta.count()
    return ix.items.count() + ix.lists.count()


def index_ratio(ix, graph: PropertyGraph, unit: str = "entries", index_bytes: int | None = None, graph_bytes: int | None = None) -> float:
    """Index size over graph size, in entries (V + E for the graph) or in bytes on disk."""
    if unit == "bytes":
        return index_bytes / graph_bytes
    return index_entries(ix) / (graph.vertices.count() + graph.edges.count())


def bytes_on_disk(spark, path: str) -> int:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).getContentSummary(where).getLength()


def add_count_direct(pairs: DataFrame) -> DataFrame:
    """(adds): one less than its size for every window."""
    return pairs.groupBy("owner").agg((F.count("*") - 1).alias("a")).agg(F.coalesce(F.sum("a"), F.lit(0)).cast("long").alias("adds"))


def add_count(ix: BlockIndex | DeltaIndex) -> int:
    """Additions of a sum query over the index."""
    if isinstance(ix, BlockIndex):
        inside = ix.members.groupBy("block_id").agg((F.count("*") - 1).alias("a")).agg(F.sum("a")).first()[0] or 0
        merged = ix.links.groupBy("owner").agg((F.count("*") - 1).alias("a")).agg(F.sum("a")).first()[0] or 0
        return inside + merged
    return ix.parent.where("pid IS NOT NULL").count() + ix.delta.count()


def block_stats(ix: BlockIndex) -> DataFrame:
    """(blocks, dense, members, links, owners): dense blocks have two members and two owners at least."""
    size = ix.members.groupBy("block_id").agg(F.count("*").alias("m"))
    use = ix.links.groupBy("block_id").agg(F.count("*").alias("o"))
    both = size.join(use, "block_id")
    return both.agg(F.count("*").alias("blocks"), F.count_if((F.col("m") > 1) & (F.col("o") > 1)).alias("dense"), F.sum("m").alias("members"), F.sum("o").alias("links"), F.avg("m").alias("mean_block"), F.avg("o").alias("mean_owners"))


def quality(full: BlockIndex, estimated: BlockIndex) -> dict[str, float]:
    """Ratios estimated / full: above 1 means that estimation cost quality."""
    a, b = block_stats(full).first(), block_stats(estimated).first()
    return {"blocks": b["blocks"] / a["blocks"], "links": b["links"] / a["links"], "members": b["members"] / a["members"], "adds": add_count(estimated) / max(1, add_count(full))}


def jaccard_growth(graph: PropertyGraph, ks: list[int], direction: str = "both") -> DataFrame:
    """(k, pairs, mean_j, share_grown): of the pairs of owners that meet at the smallest k, how similarity moves with k."""
    base, out = None, None
    for k in ks:
        j = jaccard_exact(window_pairs(graph, KHop(k, direction))).select("u", "v", (F.col("inter") / F.col("uni")).alias("j"))
        if base is None:
            base, prev = j.select("u", "v"), None
        else:
            j = j.join(base, ["u", "v"], "left_semi")
        grown = F.lit(None).cast("double")
        rows = j
        if prev is not None:
            rows = j.join(prev.withColumnRenamed("j", "before"), ["u", "v"])
            grown = F.avg((F.col("j") >= F.col("before")).cast("double"))
        row = rows.agg(F.lit(k).alias("k"), F.count("*").alias("pairs"), F.avg("j").alias("mean_j"), grown.alias("share_grown"))
        out = row if out is None else out.union(row)
        prev = j
    return out


def expansion_bound(graph: PropertyGraph, k: int, direction: str = "both") -> DataFrame:
    """(sets, mean_size, mean_new, mean_bound): how many vertices one more hop adds to the k-hop windows, beside
    s (V - s) (d - 1) / (V - 1) with d the mean degree."""
    v = graph.vertices.count()
    d = graph.arcs(direction).count() / max(v, 1)
    now = window_pairs(graph, KHop(k, direction)).groupBy("owner").agg(F.count("*").alias("s"))
    nxt = window_pairs(graph, KHop(k + 1, direction)).groupBy("owner").agg(F.count("*").alias("t"))
    bound = F.col("s") * (v - F.col("s")) * (d - 1) / max(v - 1, 1)
    return now.join(nxt, "owner").agg(F.count("*").alias("sets"), F.avg("s").alias("mean_size"), F.avg(F.col("t") - F.col("s")).alias("mean_new"), F.avg(bound).alias("mean_bound"))


def dag_stats(ix: DeltaIndex) -> DataFrame:
    """(vertices, mean_ancestors, mean_delta, depth of the longest parent path is left to delta_query)."""
    d = ix.delta.agg(F.count("*").alias("d"))
    return ix.parent.agg(F.count("*").alias("vertices"), F.avg(F.col("card") - 1).alias("mean_ancestors")).join(F.broadcast(d)).select("vertices", "mean_ancestors", (F.col("d") / F.col("vertices")).alias("mean_delta"))


def shuffle_exchanges(df: DataFrame) -> int:
    """Exchanges in the physical plan."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")
