"""Windows by traversal: (owner, member), distinct."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.model import CycleError, KHop, PropertyGraph, Topological
from graphwin.operators.parts import ancestor_rows
from graphwin.session import discard, materialize

#: Rounds that one lazy plan may chain before it is cut.
CHAIN = 3
MAX_DOUBLINGS = 40
#: From this many edges a vertex a DAG is wide: most ancestors are few steps away, over many paths, and stepping costs
#: each window its edges once, where doubling would meet it over every middle of every path.
WIDE = 3.0
RELAX_CHAIN = 6


def khop_pairs(graph: PropertyGraph, w: KHop, owners: DataFrame | None = None) -> DataFrame:
    """Each round widens every window by one step of arcs that include staying put, so the plan is one chain of
    join and distinct, without branches."""
    own = (graph.vertices.select(F.col("id").alias("owner")) if owners is None else owners.select("owner")).distinct()
    if w.k == 0:
        pairs = own.select("owner", F.col("owner").alias("member"))
    elif w.k == 1 and owners is None:  # adjacency is the window
        pairs = graph.arcs_with_self(w.direction).toDF("owner", "member").distinct()
    else:
        steps = graph.arcs_with_self(w.direction)
        if w.k > 1:
            steps = materialize(steps, "arcs")
        pairs = own.join(steps, own["owner"] == steps["src"]).select("owner", F.col("dst").alias("member")).distinct()
        for i in range(1, w.k):
            pairs = pairs.join(steps, pairs["member"] == steps["src"]).select("owner", F.col("dst").alias("member")).distinct()
            if i % CHAIN == 0 and i + 1 < w.k:
                pairs = materialize(pairs, "windows")
    return pairs if w.include_self else pairs.where("owner <> member")


def ancestor_pairs(graph: PropertyGraph, direction: str = "ancestors", owners: DataFrame | None = None) -> DataFrame:
    """(owner, member, dist) over proper ancestors, dist the longest path: paths double in length every round, so a DAG
    of h levels takes about log2(h) rounds. Written table; raises CycleError."""
    e = graph.edges.select("src", "dst").distinct()
    step = e.select(F.col("dst").alias("owner"), F.col("src").alias("member")) if direction == "ancestors" else e.select(F.col("src").alias("owner"), F.col("dst").alias("member"))
    if owners is not None:
        return _ancestors_from(step, owners)
    now = materialize(step.withColumn("dist", F.lit(1)), "closure")
    for i in range(MAX_DOUBLINGS):
        half = 1 << i
        seen = now.agg(F.count_if(F.col("owner") == F.col("member")).alias("cycles"), F.count_if(F.col("dist") == half).alias("mids")).first()
        if seen["cycles"]:
            raise CycleError("the graph has a cycle")
        if not seen["mids"]:
            return now
        # a longest path of half+1 to 2*half steps splits into longest paths of exactly half and of at most half
        a, b = now.where(F.col("dist") == half).alias("a"), now.where(F.col("dist") <= half).alias("b")
        longer = a.join(b, F.col("a.member") == F.col("b.owner")).select(F.col("a.owner"), F.col("b.member"), (F.col("a.dist") + F.col("b.dist")).alias("dist"))
        after = materialize(now.union(longer).groupBy("owner", "member").agg(F.max("dist").alias("dist")), "closure")
        discard(now)
        now = after
    raise RuntimeError("closure did not end")


def is_wide(graph: PropertyGraph) -> bool:
    return graph.edges.count() >= WIDE * max(1, graph.vertices.count())


def frontier_pairs(graph: PropertyGraph, direction: str = "ancestors") -> DataFrame:
    """(owner, member, dist) over proper ancestors, dist the shortest path: one step a round, for wide DAGs."""
    e = graph.edges.select("src", "dst").distinct()
    step = e.select(F.col("dst").alias("owner"), F.col("src").alias("member")) if direction == "ancestors" else e.select(F.col("src").alias("owner"), F.col("dst").alias("member"))
    return _ancestors_from(step, e.select(F.col("src").alias("owner")).union(e.select("dst")))


def _ancestors_from(step: DataFrame, owners: DataFrame) -> DataFrame:
    """Breadth-first from a set of owners; dist is the shortest path. Each round writes only the pairs that are new."""
    spark = step.sparkSession
    step = materialize(step.toDF("_at", "_to"), "steps")
    frontier = materialize(owners.select("owner").distinct().select("owner", F.col("owner").alias("member"), F.lit(0).alias("dist")), "reached")
    paths, depth = [frontier.shared_path], 0
    while True:
        depth += 1
        nxt = frontier.select("owner", F.col("member").alias("_at")).join(step, "_at").select("owner", F.col("_to").alias("member")).distinct()
        seen = spark.read.schema(frontier.schema).parquet(*paths)
        fresh = nxt.join(seen.where("dist > 0").select("owner", "member"), ["owner", "member"], "left_anti").withColumn("dist", F.lit(depth))
        frontier = materialize(fresh, "reached")
        some = frontier.agg(F.count("*").alias("n"), F.count_if(F.col("owner") == F.col("member")).alias("cycles")).first()
        if some["cycles"]:
            raise CycleError("the graph has a cycle")
        if not some["n"]:
            break
        paths.append(frontier.shared_path)
    return spark.read.schema(frontier.schema).parquet(*paths).where("dist > 0")


def levels_by_relaxing(graph: PropertyGraph, base: DataFrame | None = None) -> DataFrame:
    """(id, level), the longest path from a source, by rounds over vertices and edges alone, several in one plan. For an
    acyclic graph. base: (id, level) to begin with where paths come in from outside."""
    e = materialize(graph.edges.select("src", "dst").distinct(), "edges")
    now, total = materialize(graph.vertices.select("id", F.lit(0).alias("level")).distinct() if base is None else base, "levels"), -1
    while True:
        after = now
        for _ in range(RELAX_CHAIN):
            up = e.join(after, e["src"] == after["id"]).select(F.col("dst").alias("id"), (F.col("level") + 1).alias("level"))
            after = up.union(now).groupBy("id").agg(F.max("level").alias("level"))
        after = materialize(after, "levels")
        before, total = total, after.agg(F.sum(F.col("level").cast("long"))).first()[0] or 0
        discard(now)
        now = after
        if total == before:
            return now


def ancestor_windows_by_level(graph: PropertyGraph, levels: DataFrame) -> DataFrame:
    """(owner, member) with self, level after level: parents push their windows to children, and a window is dropped from
    the live set once its last child has it. For shallow DAGs; deep ones take ancestor_pairs."""
    e = graph.edges.select("src", "dst").distinct()
    lv = materialize(levels.select("id", "level"), "levels")
    last = materialize(e.join(lv.withColumnsRenamed({"id": "dst"}), "dst").groupBy(F.col("src").alias("owner")).agg(F.max("level").alias("last")), "last")
    live, done = None, []
    for level in range(lv.agg(F.max("level")).first()[0] + 1 if not lv.isEmpty() else 0):
        own = lv.where(F.col("level") == level).select(F.col("id").alias("owner"))
        made = own.select("owner", F.col("owner").alias("member"))
        if live is not None:
            into = e.join(own.withColumnsRenamed({"owner": "dst"}), "dst", "left_semi")
            made = made.union(into.join(live, F.col("src") == F.col("owner")).select(F.col("dst").alias("owner"), "member")).distinct()
        made = materialize(made, "level")
        done.append(made)
        keep = last.where(F.col("last") > level).select("owner")
        live = (made if live is None else live.union(made)).join(keep, "owner", "left_semi")
        live = materialize(live, "live")
    out = done[0] if done else None
    for d in done[1:]:
        out = out.union(d)
    return graph.vertices.select(F.col("id").alias("owner"), F.col("id").alias("member")).limit(0) if out is None else out


def topo_levels(graph: PropertyGraph, closure: DataFrame | None = None) -> DataFrame:
    """(id, level): the longest path from a source."""
    closure = ancestor_pairs(graph) if closure is None else closure
    deep = closure.groupBy(F.col("owner").alias("id")).agg(F.max("dist").alias("level"))
    return graph.vertices.select("id").join(deep, "id", "left").select("id", F.coalesce("level", F.lit(0)).cast("int").alias("level"))


def topo_levels_by_peeling(graph: PropertyGraph) -> DataFrame:
    """The same levels by removing sources round after round; raises CycleError."""
    edges, left = materialize(graph.edges.select("src", "dst").distinct(), "edges"), materialize(graph.vertices.select("id").distinct(), "left")
    done, level = None, 0
    while not left.isEmpty():
        free = materialize(left.join(edges.select(F.col("dst").alias("id")), "id", "left_anti").withColumn("level", F.lit(level)), "free")
        if free.isEmpty():
            raise CycleError("the graph has a cycle")
        done = free if done is None else done.union(free)
        edges_next = materialize(edges.join(free.select(F.col("id").alias("src")), "src", "left_anti"), "edges")
        left_next = materialize(left.join(free, "id", "left_anti"), "left")
        discard(edges, left)
        edges, left, level = edges_next, left_next, level + 1
    return graph.vertices.select("id", F.lit(0).alias("level")).limit(0) if done is None else done


def window_pairs(graph: PropertyGraph, w: KHop | Topological, owners: DataFrame | None = None) -> DataFrame:
    """(owner, member), distinct, whatever the window."""
    if isinstance(w, KHop):
        return khop_pairs(graph, w, owners)
    if owners is None:
        rows = ancestor_rows(graph if w.direction == "ancestors" else graph.reversed(), w.include_self)
        if rows is not None:
            return rows
    pairs = (frontier_pairs(graph, w.direction) if owners is None and is_wide(graph) else ancestor_pairs(graph, w.direction, owners)).select("owner", "member")
    if not w.include_self:
        return pairs
    own = graph.vertices.select(F.col("id").alias("owner")) if owners is None else owners.select("owner").distinct()
    return pairs.union(own.select("owner", F.col("owner").alias("member")))
