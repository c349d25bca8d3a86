"""The parent-delta index: a DAG vertex inherits the result of its closest parent and adds a small difference.

parent: (v, pid, level, card), pid the parent with the largest ancestor window (ties: least id), null for sources.
delta: (v, member), the ancestors of v that are neither v nor its parent's ancestors nor the parent.
jumps: [(v, p)], for each power r of `RADIX` the vertices 0, r, 2r, ... steps up v's parent path, short of RADIX x r.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphwin.functions.aggregates import Agg
from graphwin.model import PropertyGraph
from graphwin.operators import parts
from graphwin.operators.blockindex import BuildStats, refuse_holistic
from graphwin.operators.direct import additive, attributes, with_all_owners
from graphwin.operators.reach import ancestor_pairs, ancestor_windows_by_level, frontier_pairs, is_wide, levels_by_relaxing, topo_levels, topo_levels_by_peeling
from graphwin.operators.whole import Whole, whole
from graphwin.session import discard, materialize


#: Steps up the parent path that one round of a query gathers, times those of the rounds before.
RADIX = 4
#: Rounds that one lazy plan may chain before it is cut.
CHAIN = 4


@dataclass
class DeltaIndex:
    parent: DataFrame  # v, pid, level, card
    delta: DataFrame  # v, member
    stats: BuildStats = field(default_factory=BuildStats)
    jumps: list[DataFrame] | None = None
    rows: DataFrame | None = None  # of an index by parts, see parts.PARENT
    whole: Whole | None = None  # of a large graph that tasks hold: deltas are formed when they are read

    @classmethod
    def from_rows(cls, rows: DataFrame, stats: BuildStats) -> "DeltaIndex":
        parent = rows.where(F.col("kind") == parts.PARENT).select("v", F.when(F.col("to") != F.col("v"), F.col("to")).alias("pid"), "level", "card")
        last = rows.agg(F.max("kind")).first()[0] or 0
        own = parent.select("v", F.col("v").alias("p"))
        jumps = [own.union(rows.where(F.col("kind") == k).select("v", F.col("to").alias("p"))) for k in range(parts.JUMP, last + 1)]
        return cls(parent, rows.where(F.col("kind") == parts.DELTA).select("v", F.col("to").alias("member")), stats, jumps, rows)

    def entries(self) -> DataFrame:
        """(delta): how many rows the deltas have."""
        if self.whole is None:
            return self.delta.agg(F.count("*").alias("delta"))
        return self.whole.delta_sums().agg(F.coalesce(F.sum("n"), F.lit(0)).alias("delta"))

    def pointers(self) -> list[DataFrame]:
        """The jumps; they depend on no attribute, so they are found once and serve every query."""
        if self.jumps is None:
            self.jumps, step = [], self.parent.where("pid IS NOT NULL").select("v", F.col("pid").alias("p"))
            while not step.isEmpty():
                row = materialize(step.select("v", "p", F.lit(1).alias("n")), "jump")
                far = row
                for n in range(2, RADIX + 1):
                    far = far.join(row.select(F.col("v").alias("p"), F.col("p").alias("_to")), "p").select("v", F.col("_to").alias("p"), F.lit(n).alias("n"))
                    row_n = far if n == 2 else row_n.union(far)
                ahead = materialize(row_n, "jumps")
                self.jumps.append(self.parent.select("v", F.col("v").alias("p")).union(row.select("v", "p")).union(ahead.where(F.col("n") < RADIX).select("v", "p")))
                step = ahead.where(F.col("n") == RADIX).select("v", "p")
        return self.jumps

    def save(self, path: str, as_ranges: bool = False) -> None:
        """as_ranges: runs of consecutive members become (start, length)."""
        self.parent.write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/pd_parent")
        (delta_ranges(self.delta) if as_ranges else self.delta.sortWithinPartitions("v", "member")).write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/pd_delta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> "DeltaIndex":
        delta = spark.read.parquet(f"{path}/pd_delta")
        if "len" in delta.columns:
            delta = delta.select("v", F.explode(F.sequence("start", F.col("start") + F.col("len") - 1)).alias("member"))
        return cls(spark.read.parquet(f"{path}/pd_parent"), delta)


def delta_ranges(delta: DataFrame) -> DataFrame:
    """(v, start, len): consecutive members less their rank share a run."""
    ranked = delta.withColumn("_run", F.col("member") - F.row_number().over(Window.partitionBy("v").orderBy("member")))
    return ranked.groupBy("v", "_run").agg(F.min("member").alias("start"), F.count("*").alias("len")).drop("_run")


def closest_parent(graph: PropertyGraph, card: DataFrame) -> DataFrame:
    """(v, pid): a parent's window lies inside its child's, so the least difference is the largest parent's."""
    e = graph.edges.select("src", "dst").distinct()
    best = e.join(card.select(F.col("v").alias("src"), "card"), "src").groupBy(F.col("dst").alias("v")).agg(F.max(F.struct("card", (-F.col("src")).alias("neg"))).alias("m"))
    return best.select("v", (-F.col("m.neg")).alias("pid"))


def window_delta(closure: DataFrame, parents: DataFrame) -> DataFrame:
    """(v, member) of closure (owner, member; proper ancestors) less the parent and its ancestors."""
    mine = closure.select(F.col("owner").alias("v"), "member").join(parents.where("pid IS NOT NULL").select("v", "pid"), "v").where("member <> pid")
    theirs = closure.select(F.col("owner").alias("pid"), "member")
    return mine.join(theirs, ["pid", "member"], "left_anti").select("v", "member")


def build_delta_index(graph: PropertyGraph, method: str = "auto") -> DeltaIndex:
    """method `parts` closes every part of a parted or small graph within a task; `whole` closes stretches of members of a graph that
    each task holds; `doubling` takes log-depth rounds; `frontier` one a step of the shortest paths, for wide DAGs; `auto` one of
    these by the number of edges; `level` goes through the levels and frees spent windows."""
    stats = BuildStats()
    import time

    began = time.time()
    if method in ("auto", "parts"):
        p = parts.parted(graph)
        if p is not None:
            rows = parts.index_rows(p, RADIX)
            discard(p.rows)
            stats.traverse_s = time.time() - began
            return DeltaIndex.from_rows(rows, stats)
        if method == "parts":
            raise ValueError("the graph has no known parts that fit a task")
    if method in ("auto", "whole"):
        w = whole(graph)
        if w is not None:
            parent, jumps = w.index(RADIX)
            stats.traverse_s = time.time() - began
            return DeltaIndex(parent, w.delta_rows(), stats, jumps, whole=w)
        if method == "whole":
            raise ValueError("the graph is too large for a task")
        method = "frontier" if is_wide(graph) else "doubling"
    if method == "doubling":
        closure = ancestor_pairs(graph)
        levels = topo_levels(graph, closure)
    elif method == "frontier":
        closure = frontier_pairs(graph)
        levels = levels_by_relaxing(graph)
    elif method == "level":
        levels = materialize(topo_levels_by_peeling(graph), "levels")
        closure = materialize(ancestor_windows_by_level(graph, levels).where("owner <> member"), "closure")
    else:
        raise ValueError(f"unknown method {method}")
    stats.traverse_s = time.time() - began
    began = time.time()
    sizes = closure.groupBy(F.col("owner").alias("v")).agg((F.count("*") + 1).alias("card"))
    card = levels.select(F.col("id").alias("v"), "level").join(sizes, "v", "left").select("v", "level", F.coalesce("card", F.lit(1)).cast("long").alias("card"))
    parent = materialize(card.join(closest_parent(graph, card), "v", "left").select("v", "pid", "level", "card"), "pd_parent")
    delta = materialize(window_delta(closure, parent), "pd_delta")
    discard(closure)
    index = DeltaIndex(parent, delta, stats)
    index.pointers()
    stats.refine_s = time.time() - began
    return index


def _local(index: DeltaIndex, graph: PropertyGraph, aggs: list[Agg]) -> DataFrame:
    """(_gw_v, [category,] partials) over the vertex itself and its delta: one pass for all vertices, whatever their level."""
    by = aggs[0].by
    sums = additive(graph, aggs) if index.whole is not None else None
    if sums is not None:
        values, partials = sums
        local = index.whole.delta_sums(values.drop(*[graph.part] * bool(graph.part)))
        return local.select("*", *partials).select(F.col("v").alias("_gw_v"), *[n for a in aggs for n in a.partial_names()])
    own = index.parent.select("v", F.col("v").alias("member")).union(index.delta.select("v", "member")).toDF("_gw_v", "_gw_member")
    return own.join(attributes(graph, aggs, "_gw_member"), "_gw_member").groupBy("_gw_v", *[by] * bool(by)).agg(*[p for a in aggs for p in a.partials()])


def delta_query(index: DeltaIndex, graph: PropertyGraph, aggs: list[Agg], how: str = "jump", owners: DataFrame | None = None) -> DataFrame:
    """(id, [category,] values). `level`: children take their parents' results, one round per step of the longest parent
    path. `jump`: every vertex gathers what the vertices 0 to RADIX-1 jumps up its parent path have gathered, with jumps
    RADIX times as long in each round, so the rounds are the logarithm of that; the stretches of a path are disjoint, so sums
    stay exact. Rounds are joins with stored pointers, chained in one plan."""
    refuse_holistic(aggs)
    by = aggs[0].by
    keys = ["_gw_v"] + [by] * bool(by)
    merges = [x for a in aggs for x in a.merges()]
    names = [n for a in aggs for n in a.partial_names()]
    values = _local(index, graph, aggs)
    if how == "jump":
        for i, jumps in enumerate(index.pointers()):
            if i and i % CHAIN == 0:
                values = materialize(values, "values")
            steps = jumps.select(F.col("v").alias("_gw_to"), F.col("p").alias("_gw_v"))
            values = steps.join(values, "_gw_v").drop("_gw_v").withColumnRenamed("_gw_to", "_gw_v").groupBy(*keys).agg(*merges)
    elif how == "level":
        local = materialize(values, "local")
        pid = index.parent.select(F.col("v").alias("_gw_v"), F.col("pid").alias("_gw_pid"))
        ready = materialize(pid.where("_gw_pid IS NULL").select("_gw_v").join(local, "_gw_v", "left").select(local.columns), "ready")
        waiting = pid.where("_gw_pid IS NOT NULL")
        done, front = ready, ready
        while True:
            now = waiting.join(front.select(F.col("_gw_v").alias("_gw_pid")).distinct(), "_gw_pid", "left_semi")
            inherited = now.join(front.withColumnRenamed("_gw_v", "_gw_pid"), "_gw_pid").select(*keys, *names)
            own = local.join(now.select("_gw_v"), "_gw_v", "left_semi").select(*keys, *names)
            front = materialize(own.union(inherited).groupBy(*keys).agg(*merges), "front")
            if front.isEmpty():
                break
            done = done.union(front.select(done.columns))
        values = done
    else:
        raise ValueError(f"unknown order {how}")
    if owners is not None:
        values = values.join(owners.select(F.col("owner").alias("_gw_v")).distinct(), "_gw_v", "left_semi")
    out = values.select(F.col("_gw_v").alias("id"), *[by] * bool(by), *[a.final() for a in aggs])
    return out if by else with_all_owners(graph, out, aggs, owners)


def expand_delta(index: DeltaIndex) -> DataFrame:
    """(owner, member) with self, from the index alone: everything along the parent path."""
    path = ancestor_pairs(PropertyGraph(index.parent.select(F.col("v").alias("id")), index.parent.where("pid IS NOT NULL").select(F.col("pid").alias("src"), F.col("v").alias("dst")), True)).select("owner", "member")
    path = path.union(index.parent.select(F.col("v").alias("owner"), F.col("v").alias("member")))
    own = index.parent.select("v", F.col("v").alias("m")).union(index.delta.select("v", F.col("member").alias("m")))
    return path.join(own.withColumnRenamed("v", "member"), "member").select("owner", F.col("m").alias("member"))


def containment_violations(graph: PropertyGraph) -> DataFrame:
    """Edges whose parent's window isn't strictly inside the child's; none for a DAG."""
    closure = ancestor_pairs(graph).select("owner", "member").union(graph.vertices.select("id", "id"))
    e = graph.edges.select("src", "dst").distinct()
    up = e.join(closure.toDF("src", "member"), "src").select("src", "dst", "member")
    lost = up.join(closure.toDF("dst", "member"), ["dst", "member"], "left_anti").select("src", "dst")
    same = e.join(closure.groupBy("owner").count().toDF("src", "a"), "src").join(closure.groupBy("owner").count().toDF("dst", "b"), "dst").where("a >= b").select("src", "dst")
    return lost.union(same).distinct()
