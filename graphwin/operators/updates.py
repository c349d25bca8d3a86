"""Upkeep of both indices under structural changes. Attribute changes touch neither index.

edge changes: (op STRING '+' or '-', src, dst).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.model import CycleError, KHop, PropertyGraph
from graphwin.operators.blockindex import BlockIndex, build_block_index, build_from_pairs, clusters_of, signature_explicit
from graphwin.operators.deltaindex import RADIX, DeltaIndex, closest_parent, window_delta
from graphwin.operators.parts import index_rows, part_of, parted
from graphwin.operators.reach import ancestor_pairs, levels_by_relaxing, window_pairs
from graphwin.session import materialize


def changed_graph(graph: PropertyGraph, changes: DataFrame) -> PropertyGraph:
    plus = changes.where("op = '+'").select("src", "dst")
    minus = changes.where("op = '-'").select("src", "dst")
    if not graph.directed:  # undirected edges are stored once, the smaller end first
        plus, minus = (x.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")) for x in (plus, minus))
    e = graph.edges.select("src", "dst")
    e = e.union(plus.where("src <> dst")).distinct().join(minus, ["src", "dst"], "left_anti")
    ids = graph.vertices.select("id").union(e.select("src")).union(e.select("dst")).distinct()
    vertices = ids.join(graph.vertices, "id", "left")
    if graph.part is not None:
        known = graph.vertices.select("id", part_of(graph).alias("_part"))
        placed = plus.where("src <> dst").join(known.toDF("src", "_part"), "src", "left").join(known.toDF("dst", "_other"), "dst", "left")
        if placed.where("_part IS NULL OR _other IS NULL OR _part <> _other").isEmpty():
            e = graph.edges.select("src", "dst", part_of(graph).alias(graph.part)).union(placed.select("src", "dst", "_part")).distinct().join(minus, ["src", "dst"], "left_anti")
            return PropertyGraph(materialize(vertices, "vertices"), materialize(e, "edges"), graph.directed, graph.name, graph.part)
    return PropertyGraph(materialize(vertices, "vertices"), materialize(e, "edges"), graph.directed, graph.name)


# -- shared blocks -----------------------------------------------------------------------------------------------------


def affected_owners(graph: PropertyGraph, changes: DataFrame, window: KHop) -> DataFrame:
    """Owners that reach an end of a changed edge, in the old or the new graph's arcs (graph must hold both): a
    superset of those whose windows change."""
    ends = changes.select("src") if graph.directed and window.direction == "out" else changes.select("dst") if graph.directed and window.direction == "in" else changes.select("src").union(changes.select("dst"))
    back = {"out": "in", "in": "out", "both": "both"}[window.direction]
    reach = KHop(max(window.k - 1, 0), back)
    return window_pairs(graph, reach, ends.toDF("owner").distinct()).select(F.col("member").alias("owner")).distinct()


def _by_text(index: BlockIndex) -> BlockIndex:
    """Blocks of a build are numbered, those of updates named by what they hold; as text they stand side by side."""
    block = F.col("block_id").cast("string").alias("block_id")
    return BlockIndex(index.nodes, index.members.select(block, "member"), index.links.select("owner", block), index.window, index.method, index.stats)


def update_block_index(index: BlockIndex, graph: PropertyGraph, changes: DataFrame, m: int = 1, seed: int = 1) -> tuple[BlockIndex, PropertyGraph]:
    """Owners that only gain members get a secondary index over what they gain; owners that lose members drop their links
    and are covered anew; blocks without links go. For k-hop windows."""
    index, after = _by_text(index), changed_graph(graph, changes)
    both = PropertyGraph(after.vertices, graph.edges.select("src", "dst").union(after.edges.select("src", "dst")).distinct(), graph.directed)
    owners = materialize(affected_owners(both, changes, index.window), "affected")
    known = owners.join(graph.vertices.select(F.col("id").alias("owner")), "owner", "left_semi")
    fresh = owners.join(known, "owner", "left_anti").union(after.vertices.select(F.col("id").alias("owner")).join(graph.vertices.select(F.col("id").alias("owner")), "owner", "left_anti")).distinct()
    owners = owners.union(fresh).distinct()
    before = materialize(index.links.join(owners, "owner", "left_semi").join(index.members, "block_id").select("owner", "member"), "before")
    now = materialize(window_pairs(after, index.window, owners), "now")
    shrunk = materialize(before.join(now, ["owner", "member"], "left_anti").select("owner").distinct(), "shrunk")
    gained = now.join(before, ["owner", "member"], "left_anti").join(shrunk, "owner", "left_anti")
    todo = materialize(gained.select("owner", "member").union(now.join(shrunk, "owner", "left_semi").select("owner", "member")), "todo")
    members, links, _ = build_from_pairs(todo, clusters_of(signature_explicit(todo, m, seed), m), m, seed)
    all_links = materialize(index.links.join(shrunk, "owner", "left_anti").select("owner", "block_id").union(links).distinct(), "sb_links")
    all_members = index.members.select("block_id", "member").union(members).distinct()
    all_members = materialize(all_members.join(all_links.select("block_id").distinct(), "block_id", "left_semi"), "sb_members")
    return BlockIndex(after.vertices.select(F.col("id").alias("owner")), all_members, all_links, index.window, index.method, index.stats), after


def update_block_vertices(index: BlockIndex, graph: PropertyGraph, added: DataFrame | None = None, removed: DataFrame | None = None) -> tuple[BlockIndex, PropertyGraph]:
    """Vertices come as isolated ones (edges follow as edge changes) and go with their edges. added: like vertices."""
    if removed is not None:
        gone = removed.select("id").distinct()
        e = graph.edges.select("src", "dst")
        cut = e.join(gone.toDF("src"), "src", "left_semi").union(e.join(gone.toDF("dst"), "dst", "left_semi")).distinct()
        index, graph = update_block_index(index, graph, cut.select(F.lit("-").alias("op"), "src", "dst"))
        keep = index.links.join(gone.toDF("owner"), "owner", "left_anti")
        graph = PropertyGraph(graph.vertices.join(gone, "id", "left_anti"), graph.edges, graph.directed, graph.name)
        members = index.members.join(keep.select("block_id").distinct(), "block_id", "left_semi")
        index = BlockIndex(graph.vertices.select(F.col("id").alias("owner")), members, keep, index.window, index.method, index.stats)
    if added is not None:
        index = _by_text(index)
        fresh = added.join(graph.vertices.select("id"), "id", "left_anti")
        graph = PropertyGraph(graph.vertices.unionByName(fresh, allowMissingColumns=True), graph.edges, graph.directed, graph.name)
        pairs = fresh.select(F.col("id").alias("owner"), F.col("id").alias("member"))
        members, links, _ = build_from_pairs(pairs, pairs.select("owner", F.col("owner").alias("cluster")))
        index = BlockIndex(graph.vertices.select(F.col("id").alias("owner")), index.members.select("block_id", "member").union(members).distinct(), index.links.select("owner", "block_id").union(links).distinct(), index.window, index.method, index.stats)
    return index, graph


def reorganize(index: BlockIndex, graph: PropertyGraph, max_ratio: float = 1.5, built_entries: int | None = None, **options) -> BlockIndex:
    """Second phase of upkeep: a full rebuild once the index has grown beyond max_ratio times what it was when built."""
    entries = index.members.count() + index.links.count()
    if built_entries is not None and entries <= max_ratio * built_entries:
        return index
    return build_block_index(graph, index.window, index.method, **options)


# -- parent delta ------------------------------------------------------------------------------------------------------


def reaches(graph: PropertyGraph, a: int, b: int) -> bool:
    """Whether b is a itself or a descendant of a."""
    if a == b:
        return True
    start = graph.vertices.sparkSession.range(1).select(F.lit(a).cast("long").alias("owner"))
    return not ancestor_pairs(graph, "descendants", start).where(F.col("member") == b).isEmpty()


def _set(graph: PropertyGraph, v: int, direction: str) -> DataFrame:
    """(member): v with its ancestors or descendants."""
    start = graph.vertices.sparkSession.range(1).select(F.lit(v).cast("long").alias("owner"))
    return materialize(ancestor_pairs(graph, direction, start).select("member").union(start.select(F.col("owner").alias("member"))), "reach")


def insert_edge(index: DeltaIndex, graph: PropertyGraph, s: int, t: int) -> tuple[DeltaIndex, PropertyGraph]:
    """W(v) grows by W(s) for t and its descendants. With parents kept: a vertex whose parent grows with it needs W(s)
    no more in its delta; one whose parent stays adds what of W(s) the parent lacks; a source t takes s as parent."""
    if reaches(graph, t, s):
        raise CycleError(f"{s} -> {t} closes a cycle")
    spark = graph.vertices.sparkSession
    below, ws = _set(graph, t, "descendants").toDF("v"), _set(graph, s, "ancestors")
    touched = materialize(index.parent.join(below, "v", "left_semi").select("v", "pid"), "touched")
    source = F.col("pid").isNull()  # only t itself can be one
    grows = materialize(touched.where(~source).join(below.toDF("pid"), "pid", "left_semi").select("v"), "grows")
    stays = materialize(touched.where(~source).join(below.toDF("pid"), "pid", "left_anti").select("v", "pid"), "stays")
    theirs = ancestor_pairs(graph, "ancestors", stays.select(F.col("pid").alias("owner"))).select(F.col("owner").alias("pid"), "member")
    theirs = theirs.union(stays.select("pid", F.col("pid").alias("member")).distinct())
    more = stays.join(_beside(ws)).join(theirs, ["pid", "member"], "left_anti").select("v", "member")
    less = grows.join(_beside(ws))
    delta = materialize(index.delta.join(less, ["v", "member"], "left_anti").select("v", "member").union(more).distinct(), "pd_delta")
    e = graph.edges.select("src", "dst").union(spark.range(1).select(F.lit(s).cast("long"), F.lit(t).cast("long"))).distinct()
    after = PropertyGraph(graph.vertices, materialize(e, "edges"), True, graph.name)
    first_parent = F.when((F.col("v") == t) & source, F.lit(s).cast("long")).otherwise(F.col("pid"))
    rows = materialize(touched.select("v", first_parent.alias("pid")), "touched")
    return _patched(index, after, rows, _sizes_along(rows, delta, index.parent), delta), after


def _beside(members: DataFrame, limit: int = 1_000_000) -> DataFrame:
    """One vertex's ancestors, to stand beside rows that all gain or lose from them: broadcast if few."""
    return F.broadcast(members) if members.limit(limit + 1).count() <= limit else members


def delete_edge(index: DeltaIndex, graph: PropertyGraph, s: int, t: int) -> tuple[DeltaIndex, PropertyGraph]:
    """W(v) loses the members of W(s) that no longer reach v, for t and its descendants; only paths between the two are
    walked. With parents kept, a delta drops what its vertex loses and takes what the parent alone loses. If the edge to t's
    own parent went, t takes the closest of the others, and its delta is formed against that."""
    known = graph.edges.select("src", "dst").where((F.col("src") == s) & (F.col("dst") == t))
    if known.isEmpty():
        return index, graph
    e = materialize(graph.edges.select("src", "dst").where(~((F.col("src") == s) & (F.col("dst") == t))), "edges")
    after = PropertyGraph(graph.vertices, e, True, graph.name)
    below, ws = _set(graph, t, "descendants"), _set(graph, s, "ancestors")
    touched = materialize(index.parent.join(below.toDF("v"), "v", "left_semi"), "touched")
    between = materialize(_reached(e, ws.toDF("id"), "descendants").join(_reached(e, below.toDF("id"), "ancestors"), "id", "left_semi"), "between")
    inner = PropertyGraph(between, materialize(e.join(between.toDF("src"), "src", "left_semi").join(between.toDF("dst"), "dst", "left_semi").select("src", "dst"), "edges"), True)
    still = ancestor_pairs(inner, "ancestors", below.toDF("owner")).select(F.col("owner").alias("v"), "member")
    lost = materialize(below.toDF("v").join(_beside(ws)).join(still, ["v", "member"], "left_anti").select("v", "member"), "lost")

    card = touched.join(lost.groupBy("v").agg(F.count("*").alias("n")), "v", "left").select("v", (F.col("card") - F.coalesce("n", F.lit(0))).alias("card"))
    dropped = index.delta.join(lost, ["v", "member"], "left_anti").select("v", "member")
    taken = touched.select("v", "pid").join(lost.toDF("pid", "member"), "pid").select("v", "member").join(lost, ["v", "member"], "left_anti")
    delta, rows = dropped.union(taken.select("v", "member")), touched.select("v", "pid")
    if not touched.where((F.col("v") == t) & (F.col("pid") == s)).isEmpty():
        again = closest_parent(PropertyGraph(graph.vertices, e.where(F.col("dst") == t), True), index.parent.select("v", "card"))
        rows = materialize(rows.join(again.withColumnRenamed("pid", "_again"), "v", "left").select("v", F.when(F.col("v") == t, F.col("_again")).otherwise(F.col("pid")).alias("pid")), "touched")
        own = materialize(rows.where(F.col("v") == t), "own")
        two = ancestor_pairs(after, "ancestors", own.select(F.col("v").alias("owner")).union(own.where("pid IS NOT NULL").select("pid")))
        delta = delta.where(F.col("v") != t).union(window_delta(two.select("owner", "member"), own))
    return _patched(index, after, rows, card, materialize(delta, "pd_delta")), after


def _sizes_along(rows: DataFrame, delta: DataFrame, parent: DataFrame) -> DataFrame:
    """(v, card) of touched rows (v, pid): |W(v)| is |W(pid)| + |delta(v)| + 1, summed along the touched part of the parent
    path; where that leaves the touched vertices, the size known there is added."""
    ids = rows.select(F.col("v").alias("id"))
    own = rows.join(delta.join(rows.select("v"), "v", "left_semi").groupBy("v").agg(F.count("*").alias("d")), "v", "left")
    outside = parent.join(rows.select("v"), "v", "left_anti").select(F.col("v").alias("pid"), "card")
    own = materialize(own.join(outside, "pid", "left").select("v", (F.coalesce("d", F.lit(0)) + 1 + F.coalesce("card", F.lit(0))).alias("d")), "sizes")
    forest = rows.join(ids.toDF("pid"), "pid", "left_semi").select(F.col("pid").alias("src"), F.col("v").alias("dst"))
    path = ancestor_pairs(PropertyGraph(ids, forest, True)).select("owner", "member").union(ids.select("id", "id"))
    return path.join(own.withColumnRenamed("v", "member"), "member").groupBy(F.col("owner").alias("v")).agg(F.sum("d").alias("card"))


def _patched(index: DeltaIndex, after: PropertyGraph, rows: DataFrame, card: DataFrame, delta: DataFrame) -> DeltaIndex:
    """The index with new parents and sizes of the touched rows, and their levels found from the levels around them."""
    here = rows.select("v")
    kept = index.parent.join(here, "v", "left_anti").select("v", "pid", "level", "card")
    into = after.edges.join(here.toDF("dst"), "dst", "left_semi")
    above = into.join(kept.select(F.col("v").alias("src"), "level"), "src").groupBy(F.col("dst").alias("v")).agg((F.max("level") + 1).alias("level"))
    base = here.join(above, "v", "left").select(F.col("v").alias("id"), F.coalesce("level", F.lit(0)).alias("level"))
    levels = levels_by_relaxing(PropertyGraph(base, into.join(here.toDF("src"), "src", "left_semi"), True), base)
    anew = rows.join(levels.withColumnRenamed("id", "v"), "v").join(card, "v").select("v", "pid", F.col("level").cast("int").alias("level"), F.col("card").cast("long").alias("card"))
    return DeltaIndex(materialize(kept.union(anew), "pd_parent"), delta, index.stats)


def update_delta_index(index: DeltaIndex, graph: PropertyGraph, changes: list[tuple[str, int, int]], repick: bool = False) -> tuple[DeltaIndex, PropertyGraph]:
    """A fold over single edge changes ('+' or '-', s, t), a bounded batch. repick: choose closest parents anew at the end."""
    for op, s, t in changes:
        index, graph = (insert_edge if op == "+" else delete_edge)(index, graph, s, t)
    if repick:
        closure = ancestor_pairs(graph).select("owner", "member")
        card = index.parent.select("v", "card")
        parent = materialize(index.parent.drop("pid").join(closest_parent(graph, card), "v", "left").select("v", "pid", "level", "card"), "pd_parent")
        index = DeltaIndex(parent, materialize(window_delta(closure, parent), "pd_delta"), index.stats)
    return index, graph


def _reached(edges: DataFrame, start: DataFrame, direction: str) -> DataFrame:
    """(id): start (id) and all its descendants or ancestors, from one vertex put beside them all."""
    beside = F.lit(-(1 << 63)).cast("long")
    both = (beside.alias("src"), F.col("id").alias("dst")) if direction == "descendants" else (F.col("id").alias("src"), beside.alias("dst"))
    e = edges.select("src", "dst").union(start.select(*both))
    return ancestor_pairs(PropertyGraph(start, e, True), direction, start.sparkSession.range(1).select(beside.alias("owner"))).select(F.col("member").alias("id"))


def update_delta_batch(index: DeltaIndex, graph: PropertyGraph, changes: DataFrame) -> tuple[DeltaIndex, PropertyGraph]:
    """Edge changes of any number at once. The windows of the changed edges' lower ends and their descendants are found
    anew, in the part of the DAG above them, or with the graph's part if it has known parts; no other window or parent's window changes. Equal to a rebuild."""
    after = changed_graph(graph, changes)
    if index.rows is not None and after.part is not None:  # parts with a change are closed anew
        ends = changes.select(F.col("dst").alias("id")).union(changes.select("src")).distinct()
        changed = materialize(after.vertices.join(ends, "id", "left_semi").select(part_of(after).alias("part")).distinct(), "changed")
        p = parted(after, changed)
        if p is not None:
            rows = index.rows.join(changed, "part", "left_anti").select(index.rows.columns).union(index_rows(p, RADIX))
            return DeltaIndex.from_rows(materialize(rows, "pd_parts"), index.stats), after
    fresh = after.vertices.select("id").join(graph.vertices.select("id"), "id", "left_anti")
    touched = materialize(_reached(graph.edges.select("src", "dst").union(after.edges.select("src", "dst")).distinct(), changes.select(F.col("dst").alias("id")).union(fresh).distinct(), "descendants"), "touched")
    inside = materialize(_reached(after.edges, touched, "ancestors"), "inside")
    closure = ancestor_pairs(PropertyGraph(inside, after.edges.join(inside.toDF("dst"), "dst", "left_semi").select("src", "dst"), True))
    sizes = closure.groupBy(F.col("owner").alias("v")).agg(F.max("dist").cast("int").alias("level"), (F.count("*") + 1).alias("card"))
    here = touched.toDF("v")
    anew = here.join(sizes, "v", "left").select("v", F.coalesce("level", F.lit(0)).alias("level"), F.coalesce("card", F.lit(1)).cast("long").alias("card"))
    kept = index.parent.join(here, "v", "left_anti").select("v", "pid", "level", "card")
    pids = closest_parent(PropertyGraph(after.vertices, after.edges.join(touched.toDF("dst"), "dst", "left_semi"), True), kept.select("v", "card").union(anew.select("v", "card")))
    again = materialize(anew.join(pids, "v", "left").select("v", "pid", "level", "card"), "again")
    delta = index.delta.join(here, "v", "left_anti").select("v", "member").union(window_delta(closure, again))
    return DeltaIndex(materialize(kept.union(again), "pd_parent"), materialize(delta, "pd_delta"), index.stats), after


def add_isolated(index: DeltaIndex, graph: PropertyGraph, vertices: DataFrame) -> tuple[DeltaIndex, PropertyGraph]:
    fresh = vertices.join(graph.vertices.select("id"), "id", "left_anti")
    rows = fresh.select(F.col("id").alias("v"), F.lit(None).cast("long").alias("pid"), F.lit(0).alias("level"), F.lit(1).cast("long").alias("card"))
    return DeltaIndex(index.parent.union(rows), index.delta, index.stats), PropertyGraph(graph.vertices.unionByName(fresh, allowMissingColumns=True), graph.edges, True, graph.name)


def remove_vertex(index: DeltaIndex, graph: PropertyGraph, v: int) -> tuple[DeltaIndex, PropertyGraph]:
    """Its edges first, as one batch, then the row."""
    own = graph.edges.where((F.col("src") == v) | (F.col("dst") == v)).select(F.lit("-").alias("op"), "src", "dst")
    index, graph = update_delta_batch(index, graph, materialize(own, "changes"))
    keep = F.col("v") != v
    return DeltaIndex(index.parent.where(keep), index.delta.where(keep), index.stats), PropertyGraph(graph.vertices.where(F.col("id") != v), graph.edges, True, graph.name)
