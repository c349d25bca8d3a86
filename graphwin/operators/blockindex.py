"""The shared-block index: windows as unions of disjoint blocks, blocks shared between windows.

Owners with alike windows are clustered by MinHash signatures. Inside a cluster, members that belong to exactly the same
owners form one class; classes of two or more members and owners are dense and become blocks. What they leave of each
window is signed and clustered anew, until a cluster has no dense class and emits what is left. All clusters advance in
the same bulk-synchronous round. A class is named by order-free hashes of its owners and a block by those of its members,
so no owner list or member list is ever gathered in a row.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphwin.functions.aggregates import Agg
from graphwin.functions.hashing import hash_columns
from graphwin.model import CycleError, HolisticAggregateError, KHop, PropertyGraph, Topological
from graphwin.operators.direct import additive as _additive, attributes, with_all_owners
from graphwin.operators.packed import CLUSTERS, LINK, MEMBER, REFINE_PAIRS, TASK_PAIRS, WINDOW_PAIRS, packed_blocks, sum_names
from graphwin.operators.parts import CYCLE, block_rows
from graphwin.operators.reach import khop_pairs, window_pairs
from graphwin.session import BROADCAST_ROWS, discard, materialize, small

#: The most paths whose ends are under way to their tasks at a time.
WAVE_PAIRS = 100_000_000
#: The most steps that every task gets whole, to walk two-hop windows from them; of graphs with more, paths are sent.
WALK_STEPS = 25_000_000

# -- signatures --------------------------------------------------------------------------------------------------------


def signature_explicit(pairs: DataFrame, m: int = 1, seed: int = 1, family: str = "affine", keys: tuple[str, ...] = ("owner",)) -> DataFrame:
    """(owner, h1..hm) from windows: map-side combined minima."""
    return pairs.groupBy(*keys).agg(*[F.min(h).alias(f"h{i + 1}") for i, h in enumerate(hash_columns(F.col("member"), m, seed, family))])


def signature_propagated(graph: PropertyGraph, window: KHop, m: int = 1, seed: int = 1, family: str = "affine", steps: DataFrame | None = None) -> DataFrame:
    """The same minima without any window: a k-hop window is the union of its neighbours' (k-1)-hop windows, so its
    minimum is the least of theirs."""
    arcs = graph.loose_steps(window.direction) if steps is None else steps
    names = [f"h{i + 1}" for i in range(m)]
    if not window.k:
        return graph.vertices.select(F.col("id").alias("owner"), *[h.alias(n) for h, n in zip(hash_columns(F.col("id"), m, seed, family), names, strict=True)])
    sig = arcs.groupBy(F.col("src").alias("id")).agg(*[F.min(h).alias(n) for h, n in zip(hash_columns(F.col("dst"), m, seed, family), names, strict=True)])
    for _ in range(window.k - 1):
        sig = small(materialize(sig, "signatures"))
        sig = arcs.join(sig, arcs["dst"] == sig["id"]).groupBy(F.col("src").alias("id")).agg(*[F.min(n).alias(n) for n in names])
    return sig.withColumnRenamed("id", "owner")


def jaccard_exact(pairs: DataFrame) -> DataFrame:
    """(u, v, inter, uni) of owners u < v whose windows meet. A join on members: for analysis, not for large windows."""
    size = pairs.groupBy("owner").agg(F.count("*").alias("n"))
    a, b = pairs.toDF("u", "member"), pairs.toDF("v", "member")
    inter = a.join(b, "member").where("u < v").groupBy("u", "v").agg(F.count("*").alias("inter"))
    return inter.join(size.toDF("u", "nu"), "u").join(size.toDF("v", "nv"), "v").select("u", "v", "inter", (F.col("nu") + F.col("nv") - F.col("inter")).alias("uni"))


def jaccard_estimate(signatures: DataFrame, candidates: DataFrame, m: int) -> DataFrame:
    """(u, v, j): the share of equal slots."""
    a = signatures.select(F.col("owner").alias("u"), *[F.col(f"h{i + 1}").alias(f"a{i}") for i in range(m)])
    b = signatures.select(F.col("owner").alias("v"), *[F.col(f"h{i + 1}").alias(f"b{i}") for i in range(m)])
    equal = sum(((F.col(f"a{i}") == F.col(f"b{i}")).cast("int") for i in range(m)), F.lit(0))
    return candidates.select("u", "v").join(a, "u").join(b, "v").select("u", "v", (equal / m).alias("j"))


# -- clusters ----------------------------------------------------------------------------------------------------------


def clusters_of(signatures: DataFrame, m: int) -> DataFrame:
    """(owner, cluster): owners whose signatures agree in all slots."""
    return signatures.select("owner", F.xxhash64(*[f"h{i + 1}" for i in range(m)]).alias("cluster"))


def cluster_full(graph: PropertyGraph, window: KHop | Topological, m: int = 1, seed: int = 1, family: str = "affine", explicit: bool = False, steps: DataFrame | None = None) -> DataFrame:
    """Clusters by signatures of the whole windows."""
    if explicit or isinstance(window, Topological):
        return clusters_of(signature_explicit(window_pairs(graph, window), m, seed, family), m)
    return clusters_of(signature_propagated(graph, window, m, seed, family, steps), m)


def cluster_estimated(graph: PropertyGraph, window: KHop, m: int = 1, k_prime: int = 1, seed: int = 1, family: str = "affine", explicit: bool = False, steps: DataFrame | None = None) -> DataFrame:
    """Clusters by signatures of windows of fewer hops: alike neighbourhoods stay alike as they grow."""
    if not isinstance(window, KHop):
        raise ValueError("estimated clustering needs a k-hop window")
    if not 1 <= k_prime < max(window.k, 2):
        raise ValueError(f"k_prime must be at least 1 and below k={window.k}")
    shorter = KHop(min(k_prime, window.k), window.direction)
    return cluster_full(graph, shorter, m, seed, family, explicit, steps)


def _sized_clusters(steps: DataFrame, k: int, method: str, m: int, seed: int, family: str) -> DataFrame:
    """(owner, cluster, n) of windows of one or two hops, n the paths to their members: sizes come with the signatures."""
    names = [f"h{i + 1}" for i in range(m)]
    sig = steps.groupBy(F.col("src").alias("owner")).agg(*[F.min(h).alias(n) for h, n in zip(hash_columns(F.col("dst"), m, seed, family), names, strict=True)], F.count("*").alias("n"))
    if k == 2:
        first = materialize(sig, "signatures")
        sig = steps.join(small(first), F.col("dst") == F.col("owner")).groupBy("src").agg(*[F.min(n).alias(n) for n in names], F.sum("n").alias("n")).withColumnRenamed("src", "owner")
        if method == "emc":
            sig = sig.select("owner", "n").join(small(first).drop("n"), "owner")
    return sig.select("owner", F.xxhash64(*names).alias("cluster"), "n")


def split_clusters(clusters: DataFrame, sizes: DataFrame | None, max_pairs: int, max_depth: int = 40) -> DataFrame:
    """Clusters whose windows hold more than max_pairs pairs fall into that many equal parts as needed, by a hash of the
    owner, and parts that still hold more fall apart again, until every part fits or is one owner: no cluster is sorted or
    gathered. sizes: (owner, n), unless clusters have n."""
    now = clusters if sizes is None else clusters.join(sizes, "owner").select("owner", "cluster", "n")
    for depth in range(max_depth):
        large = now.groupBy("cluster").agg(F.sum("n").alias("_pairs"), F.count("*").alias("_owners")).where((F.col("_pairs") > max_pairs) & (F.col("_owners") > 1))
        large = large.select("cluster", F.least(F.ceil(F.col("_pairs") / max_pairs), F.col("_owners")).alias("_parts"))
        if large.isEmpty():
            break
        part = F.pmod(F.xxhash64(F.lit(3 + depth), "owner"), F.col("_parts"))
        split = F.when(F.col("_parts").isNotNull(), F.xxhash64(F.lit(depth), "cluster", part)).otherwise(F.col("cluster"))
        now = materialize(now.join(large, "cluster", "left").select("owner", split.alias("cluster"), "n"), "split")
    return now.select("owner", "cluster")


# -- build -------------------------------------------------------------------------------------------------------------


@dataclass
class BuildStats:
    hash_s: float = 0.0
    traverse_s: float = 0.0
    refine_s: float = 0.0
    rounds: int = 0
    clusters: int = 0

    @property
    def total_s(self) -> float:
        return self.hash_s + self.traverse_s + self.refine_s


@dataclass
class BlockIndex:
    nodes: DataFrame  # owner
    members: DataFrame  # block_id, member
    links: DataFrame  # owner, block_id
    window: KHop | Topological
    method: str = "mc"
    stats: BuildStats = field(default_factory=BuildStats)

    def save(self, path: str) -> None:
        """Parquet tables and a manifest row; the index knows nothing of attributes or aggregates."""
        spark = self.nodes.sparkSession
        for name, df in (("sb_nodes", self.nodes), ("sb_members", self.members), ("sb_links", self.links)):
            df.write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/{name}")
        w = self.window
        made = [("khop", w.k, w.direction, w.include_self, self.method)] if isinstance(w, KHop) else [("topological", 0, w.direction, w.include_self, self.method)]
        spark.createDataFrame(made, "kind string, k int, direction string, include_self boolean, method string").coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest")

    def save_bucketed(self, prefix: str, buckets: int = 8) -> None:
        """Tables bucketed on the keys of the query's joins, so a query shuffles neither index table by them."""
        self.members.write.mode("overwrite").bucketBy(buckets, "block_id").sortBy("block_id").saveAsTable(f"{prefix}_members")
        self.links.write.mode("overwrite").bucketBy(buckets, "block_id").sortBy("block_id").saveAsTable(f"{prefix}_links")
        self.nodes.write.mode("overwrite").bucketBy(buckets, "owner").saveAsTable(f"{prefix}_nodes")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> "BlockIndex":
        m = spark.read.parquet(f"{path}/manifest").first()
        window = KHop(m["k"], m["direction"], m["include_self"]) if m["kind"] == "khop" else Topological(m["direction"], m["include_self"])
        return cls(*(spark.read.parquet(f"{path}/{t}") for t in ("sb_nodes", "sb_members", "sb_links")), window, m["method"])


def _fingerprint(col: str, prefix: str) -> list:
    """Two order-free 64-bit hashes and a count stand for a set of ids."""
    return [F.count("*").alias(f"{prefix}n"), F.bit_xor(F.xxhash64(F.lit(101), col)).alias(f"{prefix}x"), F.bit_xor(F.xxhash64(F.lit(202), col)).alias(f"{prefix}y")]


def _class_table(triples: DataFrame) -> DataFrame:
    """(cluster, member, owners' fingerprint on, ox, oy), one row per member of a cluster."""
    return triples.groupBy("cluster", "member").agg(*_fingerprint("owner", "o"))


def build_from_pairs(pairs: DataFrame, clusters: DataFrame, m: int = 1, seed: int = 1, family: str = "affine", max_rounds: int = 40, stats: BuildStats | None = None) -> tuple[DataFrame, DataFrame, BuildStats]:
    """(members, links) that cover exactly the given windows; clusters: (owner, cluster)."""
    stats = stats or BuildStats()
    began = time.time()
    triples = materialize(pairs.join(clusters, "owner").select("cluster", "owner", "member"), "triples")
    stats.traverse_s += time.time() - began
    began = time.time()
    names, key = [f"h{i + 1}" for i in range(m)], ["cluster", "on", "ox", "oy"]
    members, links, kept = None, None, []
    for _ in range(max_rounds):
        stats.rounds += 1
        classes = _class_table(triples)
        groups = classes.groupBy(*key).agg(*_fingerprint("member", "m")).withColumn("dense", (F.col("mn") > 1) & (F.col("on") > 1))
        has_dense = groups.groupBy("cluster").agg(F.bool_or("dense").alias("any_dense"))
        judged = groups.join(has_dense, "cluster").select(*key, (F.col("dense") | ~F.col("any_dense")).alias("emit"), F.concat_ws("-", F.col("mn"), F.hex("mx"), F.hex("my")).alias("block_id"))
        # the round's only table: which block takes each pair, or none yet
        tagged = materialize(triples.join(classes, ["cluster", "member"]).join(judged, key).select("cluster", "owner", "member", "emit", "block_id"), "tagged")
        got_members, got_links = tagged.where("emit").select("block_id", "member"), tagged.where("emit").select("owner", "block_id")
        members = got_members if members is None else members.union(got_members)
        links = got_links if links is None else links.union(got_links)
        kept.append(tagged)
        rest = tagged.where("NOT emit").select("cluster", "owner", "member")
        if rest.isEmpty():
            break
        sig = signature_explicit(rest, m, seed + stats.rounds, family, ("cluster", "owner"))
        renamed = sig.select("cluster", "owner", F.xxhash64("cluster", *names).alias("_next"))
        triples = rest.join(renamed, ["cluster", "owner"]).select(F.col("_next").alias("cluster"), "owner", "member")
    else:
        raise RuntimeError(f"windows left after {max_rounds} rounds")
    members, links = materialize(members.distinct(), "sb_members"), materialize(links.distinct(), "sb_links")
    discard(*kept)
    stats.refine_s += time.time() - began
    return members, links, stats


def _tables(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(members, links) of rows of `packed.SCHEMA`."""
    return rows.where(F.col("kind") == MEMBER).select("block_id", F.col("id").alias("member")), rows.where(F.col("kind") == LINK).select(F.col("id").alias("owner"), "block_id")


def _refuse_cycles(rows: DataFrame) -> None:
    if not rows.where(F.col("kind") == CYCLE).isEmpty():
        raise CycleError("the graph has a cycle")


def _khop_rows(graph: PropertyGraph, window: KHop, clusters: DataFrame, steps: DataFrame, m: int, seed: int, family: str, max_pairs: int, waves: int, values: DataFrame | None = None) -> list[DataFrame] | None:
    """Rows of `packed.SCHEMA`, not yet run, a frame a wave: the last step of all windows goes packed to the tasks that refine
    their clusters, each cluster in one. None if a window is too large for a task, which is measured by its paths."""
    shorter = steps.toDF("owner", "member") if window.k == 2 else None
    sizes = clusters
    if window.k > 2:
        degree = steps.groupBy(F.col("src").alias("member")).agg(F.count("*").alias("n"))
        shorter = materialize(khop_pairs(graph, KHop(window.k - 1, window.direction)), "windows")
        sizes = materialize(shorter.join(small(materialize(degree, "degrees")), "member").groupBy("owner").agg(F.sum("n").alias("n")), "sizes")
    paths, largest = sizes.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.max("n"), F.lit(0))).first()
    if largest > WINDOW_PAIRS:
        return None
    arcs = WALK_STEPS + 1 if window.k != 2 else steps.limit(WALK_STEPS + 1).count()
    if arcs <= WALK_STEPS:  # tasks hold at least half as many paths as they read steps
        walked, tasks = True, max(1, -(-paths // max(TASK_PAIRS, arcs // 2)))
    else:
        walked, waves = False, max(waves, -(-paths // WAVE_PAIRS))
        tasks = max(1, -(-paths // (TASK_PAIRS * waves)))
    own = split_clusters(clusters, sizes if window.k > 2 else None, max_pairs)
    own = materialize(own.select("owner", "cluster", F.pmod(F.xxhash64("cluster"), F.lit(tasks)).cast("int").alias("target")), "own")
    if walked:
        return [packed_blocks(None, own, tasks, 0, m, seed, family, values, steps, window.include_self)]
    rows = []
    for wave in range(waves):
        now = own if waves == 1 else own.where(F.pmod(F.xxhash64(F.lit(waves), "cluster"), F.lit(waves)) == wave)
        to = small(now.select("owner", "target"))
        if shorter is None:
            pairs = steps.toDF("owner", "member").join(to, "owner")
        else:
            pairs = shorter.join(to, "owner").join(steps, F.col("member") == F.col("src")).select("target", "owner", F.col("dst").alias("member"))
        if not window.include_self:
            pairs = pairs.where("owner <> member")
        rows.append(packed_blocks(pairs, now, tasks, wave * tasks, m, seed, family, values))
    return rows


def _task_rows(
    graph: PropertyGraph, window: KHop | Topological, method: str = "mc", m: int = 1, k_prime: int = 1, seed: int = 1, family: str = "affine",
    max_pairs_per_cluster: int = 5_000_000, waves: int = 1, explicit_signatures: bool = False, stats: BuildStats | None = None,
    values: DataFrame | None = None,
) -> tuple[list[DataFrame] | None, DataFrame | None]:
    """(rows of `packed.SCHEMA` that form the blocks within tasks, not yet run, or with values (id, sum_names) rows of their
    sums; clusters, if they were needed). No rows for graphs that go by joins."""
    read = None if values is None else [c for c in values.columns if c.startswith("_gw_s")]
    began = time.time()
    if method == "mc" and isinstance(window, Topological):
        g = graph if window.direction == "ancestors" else graph.reversed()
        if read:
            g = PropertyGraph(values, g.edges, g.directed, g.name, g.part)
        rows = block_rows(g, window.include_self, m, seed, family, read)
        if rows is not None:
            return [rows], None
    steps = None
    if isinstance(window, KHop) and window.k:
        steps = graph.loose_steps(window.direction)
        if window.k > 1:  # by their starts, so that sums over the steps of a vertex need no large shuffle
            steps = materialize(steps.repartition("src").distinct().sortWithinPartitions("src", "dst"), "arcs", "zstd")
    if steps is not None and window.k <= 2 and not explicit_signatures and (method == "mc" or k_prime == 1):
        clusters = _sized_clusters(steps, window.k, method, m, seed, family)
    elif method == "emc":
        clusters = cluster_estimated(graph, window, m, k_prime, seed, family, explicit_signatures, steps)
    else:
        clusters = cluster_full(graph, window, m, seed, family, explicit_signatures, steps)
    if steps is not None and window.k <= 2 and "n" not in clusters.columns:
        sizes = steps.groupBy(F.col("src").alias("owner")).agg(F.count("*").alias("n"))
        if window.k == 2:
            sizes = steps.join(small(materialize(sizes, "degrees")), F.col("dst") == F.col("owner")).groupBy("src").agg(F.sum("n").alias("n")).withColumnRenamed("src", "owner")
        clusters = clusters.join(sizes, "owner")
    clusters = materialize(clusters, "clusters")
    if stats is not None:
        stats.hash_s = time.time() - began
    return None if steps is None else _khop_rows(graph, window, clusters, steps, m, seed, family, min(max_pairs_per_cluster, REFINE_PAIRS), waves, None if values is None else values.select("id", *read)), clusters.select("owner", "cluster")


def build_block_index(
    graph: PropertyGraph, window: KHop | Topological, method: str = "mc", m: int = 1, k_prime: int = 1, seed: int = 1, family: str = "affine",
    max_pairs_per_cluster: int = 5_000_000, waves: int = 1, max_rounds: int = 40, explicit_signatures: bool = False, clusters: DataFrame | None = None,
) -> BlockIndex:
    """method `mc` clusters by the whole windows, `emc` by k_prime hops. Windows are traversed a second time, in `waves` of
    owners by a hash of their cluster, so only one wave's pairs exist at a time. Clusters are refined within tasks; given
    clusters, and windows too large for a task, are refined by joins, where clusters share blocks of the same members."""
    if method not in ("mc", "emc"):
        raise ValueError(f"unknown method {method}")
    if clusters is None and graph.by_twins(window):  # twins share their window and stand in the same windows
        ix = build_block_index(graph.quotient(), window, method, m, k_prime, seed, family, max_pairs_per_cluster, waves, max_rounds, explicit_signatures)
        twins = materialize(graph.twins, "twins")
        members = materialize(ix.members.join(twins.toDF("_id", "member"), "member").select("block_id", F.col("_id").alias("member")), "sb_members")
        links = materialize(ix.links.join(twins.toDF("_id", "owner"), "owner").select(F.col("_id").alias("owner"), "block_id"), "sb_links")
        return BlockIndex(graph.vertices.select(F.col("id").alias("owner")), members, links, window, method, ix.stats)
    stats = BuildStats()
    if clusters is None:
        began = time.time()
        frames, clusters = _task_rows(graph, window, method, m, k_prime, seed, family, max_pairs_per_cluster, waves, explicit_signatures, stats)
        if frames is not None:
            rows = reduce(DataFrame.union, [materialize(x, "sb_rows", "zstd") for x in frames])
            _refuse_cycles(rows)
            stats.refine_s, stats.rounds = time.time() - began - stats.hash_s, 1
            stats.clusters = rows.where(F.col("kind") == CLUSTERS).agg(F.sum("id")).first()[0] or 0 if clusters is None else clusters.select("cluster").distinct().count()
            return BlockIndex(graph.vertices.select(F.col("id").alias("owner")), *_tables(rows), window, method, stats)
    else:
        clusters = materialize(clusters, "clusters")
    members = links = None
    for wave in range(waves):
        own = clusters if waves == 1 else clusters.where(F.pmod(F.xxhash64("cluster"), F.lit(waves)) == wave)
        began = time.time()
        pairs = materialize(window_pairs(graph, window, None if waves == 1 else own.select("owner")), "pairs")
        stats.traverse_s += time.time() - began
        own = split_clusters(own, pairs.groupBy("owner").agg(F.count("*").alias("n")), max_pairs_per_cluster)
        got_members, got_links, stats = build_from_pairs(pairs, own, m, seed, family, max_rounds, stats)
        members = got_members if members is None else members.union(got_members)
        links = got_links if links is None else links.union(got_links)
        discard(pairs)
    if waves > 1:
        members = materialize(members.distinct(), "sb_members")
    stats.clusters = clusters.select("cluster").distinct().count()
    return BlockIndex(graph.vertices.select(F.col("id").alias("owner")), members, links, window, method, stats)


# -- query -------------------------------------------------------------------------------------------------------------


def refuse_holistic(aggs: list[Agg]) -> None:
    for a in aggs:
        if a.holistic:
            raise HolisticAggregateError(f"{a.fn} has no partial aggregates")


def block_partials(index: BlockIndex, graph: PropertyGraph, aggs: list[Agg]) -> DataFrame:
    """(_gw_block, [category,] partials): each block is aggregated once, however many windows hold it."""
    by = aggs[0].by
    members = index.members.select(F.col("block_id").alias("_gw_block"), F.col("member").alias("_gw_member"))
    few = graph.vertices.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    values = attributes(graph, aggs, "_gw_member")
    return members.join(F.broadcast(values) if few else values, "_gw_member").groupBy("_gw_block", *[by] * bool(by)).agg(*[p for a in aggs for p in a.partials()])


def block_query(index: BlockIndex, graph: PropertyGraph, aggs: list[Agg], owners: DataFrame | None = None) -> DataFrame:
    """(id, [category,] values): partials per block, then merged per owner."""
    refuse_holistic(aggs)
    by = aggs[0].by
    links = index.links if owners is None else index.links.join(owners.select("owner").distinct(), "owner", "left_semi")
    links = links.select(F.col("owner").alias("_gw_owner"), F.col("block_id").alias("_gw_block"))
    merged = links.join(block_partials(index, graph, aggs), "_gw_block").groupBy("_gw_owner", *[by] * bool(by)).agg(*[x for a in aggs for x in a.merges()])
    out = merged.select(F.col("_gw_owner").alias("id"), *[by] * bool(by), *[a.final() for a in aggs])
    return out if by else with_all_owners(graph, out, aggs, owners)


def block_query_once(graph: PropertyGraph, window: KHop | Topological, aggs: list[Agg], owners: DataFrame | None = None, **options) -> DataFrame:
    """`block_query` over an index for this query alone (options: those of `build_block_index`): where the aggregates are sums of
    whole numbers, a block is added up and merged into its owners in the task that forms it, and the index isn't written."""
    refuse_holistic(aggs)
    sums = None if "clusters" in options or graph.by_twins(window) else _additive(graph, aggs)
    if sums is not None:
        values, partials = sums
        frames, clusters = _task_rows(graph, window, values=values, **options)
        if frames is not None:
            names = sum_names(len([c for c in values.columns if c.startswith("_gw_s")]))
            # a wave after the other, so that one's pairs are gone before the next one's are sent
            kept = reduce(DataFrame.union, [materialize(x.groupBy("kind", "id").agg(*[F.sum(c).alias(c) for c in names]), "sums", "zstd") for x in frames])
            _refuse_cycles(kept)
            out = kept.where(F.col("kind") == LINK).select("id", *partials).select("id", *[a.final() for a in aggs])
            if owners is not None:
                out = out.join(owners.select(F.col("owner").alias("id")).distinct(), "id", "left_semi")
            return with_all_owners(graph, out, aggs, owners)
        if clusters is not None:
            options = options | {"clusters": clusters}
    return block_query(build_block_index(graph, window, **options), graph, aggs, owners)


def expand_index(index: BlockIndex) -> DataFrame:
    """(owner, member, copies): copies is 1 everywhere if the cover is exact and disjoint."""
    return index.links.join(index.members, "block_id").groupBy("owner", "member").agg(F.count("*").alias("copies"))


def check_cover(index: BlockIndex, pairs: DataFrame) -> dict[str, int]:
    """Numbers of pairs that are missing, too many, or covered more than once; all 0 for a right index."""
    got = materialize(expand_index(index), "expanded")
    flat = got.select("owner", "member")
    return {"missing": pairs.select("owner", "member").exceptAll(flat).count(), "extra": flat.exceptAll(pairs.select("owner", "member")).count(), "overlapping": got.where("copies > 1").count()}
