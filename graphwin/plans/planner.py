"""Choice of a strategy from estimates."""

from __future__ import annotations

from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphwin.functions.aggregates import Agg
from graphwin.model import KHop, PropertyGraph, Topological

#: An index must save at least this share of additions to be worth building.
BREAK_EVEN = 0.95
SAMPLE_OWNERS = 400


@dataclass
class Estimate:
    vertices: int
    edges: int
    pairs: float
    strategy: str
    why: str

    def text(self) -> str:
        return "\n".join(f"{k}: {v}" for k, v in asdict(self).items())


def window_volume(graph: PropertyGraph, window: KHop | Topological, exact: bool = False) -> DataFrame:
    """(pairs): the sum of window sizes. Estimated by HLL sketches sent along the edges, k rounds and no window, or (exact,
    and topological) by counting the windows."""
    from graphwin.operators.reach import window_pairs

    if exact or isinstance(window, Topological):
        return window_pairs(graph, window).agg(F.count("*").alias("pairs"))
    arcs = graph.arcs_with_self(window.direction)
    sk = graph.vertices.groupBy("id").agg(F.hll_sketch_agg("id").alias("s"))
    for _ in range(window.k):
        sk = arcs.join(sk, arcs["dst"] == sk["id"]).groupBy(F.col("src").alias("id")).agg(F.hll_union_agg("s").alias("s"))
    return sk.agg(F.sum(F.hll_sketch_estimate("s")).alias("pairs"))


def sampled_sharing(graph: PropertyGraph, window: KHop, sample: int = SAMPLE_OWNERS) -> float:
    """Additions of a block index over those of direct evaluation, on whole clusters: those with the smallest hashes, as many
    as hold the wanted number of owners (the first one whole, however large)."""
    from graphwin.operators.blockindex import build_from_pairs, cluster_full
    from graphwin.operators.reach import window_pairs

    clusters = cluster_full(graph, window)
    sizes = clusters.groupBy("cluster").agg(F.count("*").alias("n")).orderBy(F.xxhash64("cluster"), "cluster").limit(sample)
    before = F.coalesce(F.sum("n").over(Window.orderBy(F.xxhash64("cluster"), "cluster").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    few = sizes.withColumn("_before", before).where(F.col("_before") < sample)
    own = clusters.join(few.select("cluster"), "cluster", "left_semi")
    pairs = window_pairs(graph, window, own.select("owner"))
    members, links, _ = build_from_pairs(pairs, own)
    p, k, blocks = pairs.count(), links.count(), members.select("block_id").distinct().count()
    owners, m = own.count(), members.count()
    direct = p - owners
    return 1.0 if direct <= 0 else ((m - blocks) + (k - owners)) / direct


def choose(graph: PropertyGraph, window: KHop | Topological, aggs: list[Agg], queries: int = 1, have_block: bool = False, have_delta: bool = False) -> Estimate:
    """queries: how often the window will be asked for; an index only pays over several."""
    v, e = graph.vertices.count(), graph.edges.count()
    holistic = any(a.holistic for a in aggs)
    if isinstance(window, Topological):
        if holistic:
            return Estimate(v, e, float("nan"), "direct", "holistic aggregate")
        return Estimate(v, e, float("nan"), "delta" if window.direction == "ancestors" and window.include_self else "direct", "building costs about one direct query")
    if holistic:
        return Estimate(v, e, float("nan"), "direct", "holistic aggregate")
    if have_block:
        return Estimate(v, e, float("nan"), "block", "the index is there")
    if window.include_self and all(a.idempotent and not a.by for a in aggs):
        return Estimate(v, e, float(window.k * (v + e)), "propagate", "idempotent: no windows needed")
    pairs = float(window_volume(graph, window).first()[0] or 0)
    if queries < 2 or window.k <= 1:
        return Estimate(v, e, pairs, "direct", "asked once, or adjacency is the window")
    share = sampled_sharing(graph, window)
    if share > BREAK_EVEN:
        return Estimate(v, e, pairs, "direct", f"sharing leaves {share:.2f} of the additions")
    return Estimate(v, e, pairs, "block", f"sharing leaves {share:.2f} of the additions")
