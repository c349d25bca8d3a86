"""The overlay-mining baseline.

In every iteration owners are ordered by their item lists, cut into chunks, and each chunk's frequent item prefixes are
mined in a prefix tree; a group of items shared by several owners becomes an overlay node that stands for them in those
owners' lists. Later iterations group overlay nodes again. All windows must be resident as lists, which is this
method's price and the reason that it fails where windows are large.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.functions.aggregates import Agg
from graphwin.model import KHop, PropertyGraph, Topological
from graphwin.operators.blockindex import BuildStats, refuse_holistic
from graphwin.operators.direct import attributes, with_all_owners
from graphwin.operators.reach import window_pairs
from graphwin.session import materialize

ITERATIONS = 10


@dataclass
class Overlay:
    items: DataFrame  # node, item, iteration: what an overlay node stands for; items below 0 are overlay nodes
    lists: DataFrame  # owner, item
    stats: BuildStats = field(default_factory=BuildStats)
    changes: int = 0
    rebuild_every: int = 1000


def mine_chunk(owners: list[int], lists: list[list[int]], first_node: int) -> tuple[list[list[int]], list[tuple[int, list[int]]]]:
    """Greedy picks from a prefix tree of the chunk: items by falling frequency, each tree path shared by several owners
    saves (owners - 1) * (items - 1) - 1 additions. Only places where the tree branches are formed, as runs of the sorted
    lists with a common prefix: of tree nodes with the same owners the deepest saves most and leaves nothing to the others."""
    n = len(lists)
    sizes = [len(x) for x in lists]
    if not sum(sizes):
        return [[] for _ in lists], []
    flat = np.concatenate([np.asarray(x, "int64") for x in lists])
    items, at, counts = np.unique(flat, return_inverse=True, return_counts=True)
    by_count = np.lexsort((items, -counts))  # an item's place: by falling frequency, then by number
    place = np.empty(len(items), "int64")
    place[by_count] = np.arange(len(items))
    key = np.sort(np.repeat(np.arange(n), sizes) * len(items) + place[at])
    ends = np.cumsum(sizes)
    rows = [key[e - k:e] - r * len(items) for r, (k, e) in enumerate(zip(sizes, ends.tolist(), strict=True))]
    often = int((counts > 1).sum())  # these come first
    prefixes = [x[:np.searchsorted(x, often)] for x in rows]
    text = [x.astype(">u4").tobytes() for x in prefixes]
    order = sorted(range(n), key=text.__getitem__)
    picks, open_runs = [], []
    for i in range(1, n + 1):
        common, left = 0, i - 1
        if i < n:
            x, y = prefixes[order[i - 1]], prefixes[order[i]]
            k = min(len(x), len(y))
            differ = x[:k] != y[:k]
            common = int(differ.argmax()) if differ.any() else k
        while open_runs and open_runs[-1][0] > common:
            depth, left = open_runs.pop()
            users = sorted(order[left:i])
            picks.append(((len(users) - 1) * (depth - 1) - 1, users[0], depth, users))
        if common and (not open_runs or open_runs[-1][0] < common):
            open_runs.append((common, left))
    taken, made = {}, []
    for _, _, depth, users in sorted(picks, key=lambda p: p[:3], reverse=True):
        left_over = [r for r in users if r not in taken]
        if (len(left_over) - 1) * (depth - 1) - 1 <= 0:
            continue
        node = first_node - len(made)
        made.append((node, np.sort(items[by_count[prefixes[users[0]][:depth]]]).tolist()))
        taken |= {r: (node, depth) for r in left_over}
    out = []
    for r, x in enumerate(rows):
        node, depth = taken.get(r, (None, 0))
        out.append([node] * (node is not None) + np.sort(items[by_count[x[depth:]]]).tolist())
        if node is not None and len(out[r]) > 1 and out[r][1] < node:
            out[r].sort()
    return out, made


def build_overlay(graph: PropertyGraph, window: KHop | Topological, iterations: int = ITERATIONS, chunk: int = 500, pairs: DataFrame | None = None) -> Overlay:
    import time

    if pairs is None and graph.by_twins(window):
        return _with_twins(build_overlay(graph.quotient(), window, iterations, chunk), graph)
    stats = BuildStats()
    began = time.time()
    pairs = window_pairs(graph, window) if pairs is None else pairs
    lists = materialize(pairs.groupBy("owner").agg(F.sort_array(F.collect_list("member")).alias("items")), "lists")
    n = lists.count()
    stats.traverse_s = time.time() - began
    began = time.time()
    chunks = max(1, -(-n // chunk))
    found = None
    for it in range(iterations):
        base = -((it + 1) << 44)

        def mine(key, pdf: pd.DataFrame) -> pd.DataFrame:
            pdf = pdf.sort_values("owner")
            out, made = mine_chunk(pdf["owner"].tolist(), list(pdf["items"]), base - (int(key[0]) << 22) - 1)  # noqa: B023
            rows = [(o, items, None) for o, items in zip(pdf["owner"], out, strict=True)] + [(None, items, node) for node, items in made]
            return pd.DataFrame(rows, columns=["owner", "items", "node"]).astype({"owner": "Int64", "node": "Int64"})

        # equal chunks of the lexicographic order
        dealt = lists.repartitionByRange(chunks, "items").withColumn("_chunk", F.spark_partition_id())
        mined = materialize(dealt.groupBy("_chunk").applyInPandas(lambda key, pdf: mine(key, pdf), "owner long, items array<long>, node long"), "mined")
        nodes = mined.where("node IS NOT NULL").select("node", F.explode("items").alias("item"), F.lit(it).alias("iteration"))
        stats.rounds += 1
        if nodes.isEmpty():
            break
        found = nodes if found is None else found.union(nodes)
        lists = mined.where("owner IS NOT NULL").select("owner", "items")
    if found is None:
        found = graph.vertices.select(F.col("id").alias("node"), F.col("id").alias("item"), F.lit(0).alias("iteration")).limit(0)
    stats.refine_s = time.time() - began
    return Overlay(materialize(found, "ov_items"), materialize(lists.select("owner", F.explode("items").alias("item")), "ov_lists"), stats)


def _with_twins(ov: Overlay, graph: PropertyGraph) -> Overlay:
    """The overlay of a quotient with every vertex: a rep's twins form a node of the first iteration, which takes the rep's
    place in the lists, and each twin has its rep's list. Nodes of twins are numbered from -1 - rep, above all mined ones."""
    twins = materialize(graph.twins, "twins")
    node = lambda c: -1 - F.col(c)
    place = lambda c: F.when(F.col(c) >= 0, node(c)).otherwise(F.col(c))
    items = twins.select(node("rep").alias("node"), F.col("id").alias("item"), F.lit(0).alias("iteration"))
    items = items.union(ov.items.select("node", place("item").alias("item"), (F.col("iteration") + 1).alias("iteration")))
    lists = ov.lists.select(F.col("owner").alias("rep"), place("item").alias("item")).join(twins, "rep").select(F.col("id").alias("owner"), "item")
    return Overlay(materialize(items, "ov_items"), materialize(lists, "ov_lists"), ov.stats)


def overlay_query(ov: Overlay, graph: PropertyGraph, aggs: list[Agg]) -> DataFrame:
    """Overlay nodes are evaluated iteration by iteration, then owners; all by joins and merges of partials."""
    refuse_holistic(aggs)
    by = aggs[0].by
    merges = [x for a in aggs for x in a.merges()]
    values = attributes(graph, aggs, "_gw_item").groupBy("_gw_item", *[by] * bool(by)).agg(*[p for a in aggs for p in a.partials()])
    items = ov.items.select(F.col("node").alias("_gw_node"), F.col("item").alias("_gw_item"), F.col("iteration").alias("_gw_at"))
    top = ov.items.agg(F.max("iteration")).first()[0]
    for it in range(0 if top is None else top + 1):
        got = items.where(F.col("_gw_at") == it).join(values, "_gw_item").groupBy("_gw_node", *[by] * bool(by)).agg(*merges)
        values = values.union(got.withColumnRenamed("_gw_node", "_gw_item").select(values.columns))
        if it % 3 == 2:
            values = materialize(values, "overlay-values")
    lists = ov.lists.select(F.col("owner").alias("_gw_owner"), F.col("item").alias("_gw_item"))
    out = lists.join(values, "_gw_item").groupBy("_gw_owner", *[by] * bool(by)).agg(*merges)
    out = out.select(F.col("_gw_owner").alias("id"), *[by] * bool(by), *[a.final() for a in aggs])
    return out if by else with_all_owners(graph, out, aggs, None)


def overlay_after_changes(ov: Overlay, graph: PropertyGraph, window: KHop | Topological, changes: int, **options) -> Overlay:
    """The baseline has no incremental upkeep: it is rebuilt after a number of structural changes, and stale before."""
    ov.changes += changes
    if ov.changes < ov.rebuild_every:
        return ov
    fresh = build_overlay(graph, window, **options)
    fresh.rebuild_every = ov.rebuild_every
    return fresh
