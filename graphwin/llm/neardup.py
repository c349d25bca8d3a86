"""Near-duplicate documents by b-bit MinHash, with links confirmed on whole shingle sets.

1. Every text becomes its set of 5-word shingle hashes (the whole sequence if it is shorter), bands of `ROWS` minima, one
   key per band, and a signature that keeps the low 8 bits of each minimum. Texts with one and the same set are one
   node from here on: groups of copies never meet as pairs.
2. Nodes that share a band key are candidates. Each hangs on the least node of its bucket (no pairs inside a bucket), and
   connected components of these stars give clusters that hold every candidate pair.
3. Inside a cluster the sets are brought together, in blocks of a bounded number of shingles if it is large (then every
   pair of blocks meets). Rarest-first prefixes and lengths bound the pairs, the collision-corrected share of equal
   signature bytes rules out what is far from the threshold, and the rest is verified on the whole sets. Pairs already
   connected need no further look, so what a task returns is a forest, never all pairs.
4. Components of the forests give each document the smallest document id that it reaches.

`plan()` takes as many bands as it needs for a pair at the threshold to miss all with a probability below `MISS`, and the
lowest number of equal signature bytes that such a pair falls short of with one below `MISS` (exact binomial tail): 24
bands at 85%, 35 at 80%. Null and empty texts have empty sets and are linked with nothing. Repeated rows, also with null
ids, are copies. Ties don't arise: a component is named by its least id. Extra columns are ignored or, in
drop_near_duplicates(), kept. An empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.llm.tokens import small_batches
from graphwin.llm.words import LOWER, UPPER
from graphwin.operators.components import connected_components
from graphwin.session import materialize

SHINGLE, ROWS, PERCENT = 5, 5, 85
#: Probability at which a pair at the threshold may miss all bands, and at which its signature may rule it out.
MISS = 1e-6
#: Shingles of a block; a task holds two blocks, 8 bytes a shingle and some copies.
BLOCK_SHINGLES = 2_000_000
MAX_SLOTS = 1_000
_UPPER, _LOWER = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz"
_LOW = bytes.maketrans(_UPPER, _LOWER)


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= 500_000:
            self.clear()
        out = xxhash.xxh3_64_intdigest(word)
        if len(word) <= 64:
            self[word] = out
        return out


_words = _WordHashes()
_rng = np.random.default_rng(20_011)
_MULTIPLY = _rng.integers(1, 1 << 63, MAX_SLOTS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(0, 1 << 63, MAX_SLOTS, dtype=np.uint64)
_MIX = _rng.integers(1, 1 << 63, max(ROWS, SHINGLE) + 1, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def plan(percent: int) -> tuple[int, int]:
    """(bands, least number of equal signature bytes) for a threshold."""
    s = percent / 100
    bands = max(1, math.ceil(math.log(MISS) / math.log1p(-(s**ROWS)))) if s < 1 else 1
    if bands * ROWS > MAX_SLOTS:
        raise ValueError(f"a threshold of {percent}% needs {bands} bands, more than {MAX_SLOTS // ROWS}")
    slots, agree = bands * ROWS, s + (1 - s) / 256
    below, floor = 0.0, 0
    while s < 1:
        below += math.comb(slots, floor) * agree**floor * (1 - agree) ** (slots - floor)
        if below >= MISS:
            return bands, floor
        floor += 1
    return bands, slots


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    return h ^ (h >> np.uint64(29))


def shingle_set(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's shingles."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOW).split()  # bytes split at 0x20 and 0x09-0x0D
    if not words:
        return np.empty(0, np.uint64)
    h = _mixed(np.fromiter(map(_words.__getitem__, words), np.uint64, len(words)))
    k = min(shingle, len(h))
    out = np.full(len(h) - k + 1, k, np.uint64)
    for j in range(k):
        out = _mixed(out + h[j : len(h) - k + 1 + j] * _MIX[j])
    return np.unique(out)


def minima(s: np.ndarray, slots: int) -> np.ndarray:
    out = np.full(slots, np.iinfo(np.uint64).max, np.uint64)
    for a in range(0, len(s), 512):
        np.minimum(out, (s[a : a + 512, None] * _MULTIPLY[:slots] + _ADD[:slots]).min(0), out=out)
    return out


def band_keys(m: np.ndarray) -> np.ndarray:
    by_band = m.reshape(-1, ROWS)
    key = np.arange(len(by_band), dtype=np.uint64)
    for j in range(ROWS):
        key = _mixed(key + by_band[:, j] * _MIX[j])
    return key.view(np.int64)


def equal_bytes(sig: np.ndarray, others: np.ndarray) -> np.ndarray:
    """Equal bytes of packed signatures."""
    return others.shape[1] - np.count_nonzero(np.bitwise_xor(others, sig), axis=1)


def estimate(sig: np.ndarray, others: np.ndarray) -> np.ndarray:
    """Similarity from equal bytes, corrected for the share of unequal minima whose low bits agree by chance."""
    chance = 1 / 256
    return (equal_bytes(sig, others) / others.shape[1] - chance) / (1 - chance)


def sketched(docs: DataFrame, bands: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_hash, n_shingles, node (16 bytes that stand for the set; null if empty), bands, sig."""
    small_batches(docs)
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.col(text_col)).alias("text_hash"), F.col(text_col).cast("string").alias("text"))

    def run(batches):
        import xxhash

        for b in batches:
            n, node, keys, sig = [], [], [], []
            for text in b.column(2).to_pylist():
                s = shingle_set(text)
                n.append(len(s))
                if not len(s):
                    node.append(None), keys.append(None), sig.append(None)
                    continue
                m = minima(s, bands * ROWS)
                node.append(xxhash.xxh3_128_digest(s.tobytes()))
                keys.append(band_keys(m))
                sig.append((m & np.uint64(255)).astype(np.uint8).tobytes())
            cols = [b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(node, pa.binary()), pa.array(keys, pa.list_(pa.int64())), pa.array(sig, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "text_hash", "n_shingles", "node", "bands", "sig"])

    return docs.mapInArrow(run, "doc_id long, text_hash long, n_shingles long, node binary, bands array<long>, sig binary")


def linked_forest(sets: list[np.ndarray], sigs: np.ndarray, percent: int = PERCENT) -> np.ndarray:
    """For each of the sets the number of the least set it is linked with, directly or over others."""
    n = np.array([len(s) for s in sets])
    label = np.arange(len(sets))
    floor = plan(percent)[1]
    members: dict[int, list[int]] = {}  # of each label that has more than its own set

    def join(a: int, b: int) -> None:
        a, b = label[a], label[b]
        mine, theirs = members.pop(a, [a]), members.pop(b, [b])
        if len(mine) < len(theirs):
            mine, theirs, a = theirs, mine, b
        label[theirs] = a  # the smaller group is renamed: n log n in all
        mine += theirs
        members[a] = mine

    if len(sets) == 2:
        if equal_bytes(sigs[0], sigs[1:])[0] >= floor:
            both = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
            if 100 * both >= percent * (n[0] + n[1] - both):
                label[1] = 0
        return label
    tokens, place, df = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    rank = np.empty(len(tokens), np.int64)
    rank[np.argsort(df, kind="stable")] = np.arange(len(tokens))
    ends = np.cumsum(n)
    ranks = rank[place]
    df_of = np.empty(len(tokens), np.int64)
    df_of[rank] = df
    own = [np.sort(r) for r in np.split(ranks, ends[:-1])]
    del tokens, place, rank, ranks
    order = np.argsort(n, kind="stable")
    # postings of prefixes, by size of the set
    prefix = [own[x][: n[x] - (-(-percent * n[x] // 100)) + 1] for x in order]
    prefix = [p[df_of[p] > 1] for p in prefix]
    who, what = np.repeat(order, [len(p) for p in prefix]), np.concatenate(prefix)
    by = np.argsort(what, kind="stable")
    who, what = who[by], what[by]
    inside = np.zeros(len(df_of), bool)
    for at, x in enumerate(order):
        mine = prefix[at]
        if not len(mine):
            continue
        lo, hi = np.searchsorted(what, mine, "left"), np.searchsorted(what, mine, "right")
        near = np.concatenate([who[a:b] for a, b in zip(lo, hi, strict=True)])
        near = near[(label[near] != label[x]) & (n[near] <= n[x]) & (100 * n[near] >= percent * n[x])]
        if not len(near):
            continue
        near = np.unique(near)
        likely = equal_bytes(sigs[x], sigs[near])
        near, likely = near[likely >= floor], likely[likely >= floor]
        near = near[np.argsort(-likely, kind="stable")]
        inside[own[x]] = True
        step = 4
        while len(near):
            now, near = near[:step], near[step:]
            both = np.add.reduceat(inside[np.concatenate([own[y] for y in now])].astype(np.int64), np.concatenate([[0], np.cumsum(n[now])[:-1]]))
            for y in now[100 * both >= percent * (n[x] + n[now] - both)]:
                if label[y] != label[x]:
                    join(x, y)
            near = near[label[near] != label[x]]
            step = min(256, step * 4)
        inside[own[x]] = False
    for group in members.values():
        label[group] = min(group)
    return label


def _forests(members: DataFrame, percent: int) -> DataFrame:
    """(src, dst) links that connect what is linked, from rows (cell, node, sig, set) dealt and sorted by cell."""

    def run(batches):
        cell, rows = None, []

        def links():
            sets = [np.frombuffer(r[2], np.uint64) for r in rows]
            label = linked_forest(sets, np.array([np.frombuffer(r[1], np.uint8) for r in rows]), percent)
            at = np.flatnonzero(label != np.arange(len(rows)))
            return pa.RecordBatch.from_arrays([pa.array([rows[i][0] for i in at], pa.binary()), pa.array([rows[label[i]][0] for i in at], pa.binary())], names=["src", "dst"])

        for b in batches:
            for c, node, sig, s in zip(*(b.column(k).to_pylist() for k in ("cell", "node", "sig", "set")), strict=True):
                if c != cell:
                    if len(rows) > 1:
                        yield links()
                    cell, rows = c, []
                rows.append((node, sig, s))
        if len(rows) > 1:
            yield links()

    dealt = members.repartition("cell").sortWithinPartitions("cell", "node")
    return dealt.mapInArrow(run, "src binary, dst binary")


def _sets_of(docs: DataFrame, wanted: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """wanted (low, text_hash, times, node, ...) with the shingle set of each node, from the texts; where a row is repeated,
    one of them is read."""
    texts = docs.select(F.col(id_col).cast("long").alias("low"), F.xxhash64(F.col(text_col)).alias("text_hash"), F.col(text_col).cast("string").alias("text"))
    joined = texts.join(wanted.withColumnsRenamed({"low": "_low", "text_hash": "_hash"}), F.col("low").eqNullSafe(F.col("_low")) & (F.col("text_hash") == F.col("_hash")))
    joined = joined.select("node", "n", "sig", "cluster", "blocks", "text", "times")
    if not wanted.where("times > 1").isEmpty():
        joined = joined.where("times = 1").unionByName(joined.where("times > 1").dropDuplicates(["node"]))

    def run(batches):
        for b in batches:
            sets = [shingle_set(t).tobytes() for t in b.column(5).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(sets, pa.large_binary()).cast(pa.binary())], names=["node", "n", "sig", "cluster", "blocks", "set"])

    return joined.mapInArrow(run, "node binary, n long, sig binary, cluster binary, blocks long, set binary")


def labelled(docs: DataFrame, percent: int = PERCENT, block_shingles: int = BLOCK_SHINGLES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_hash, n_shingles, node, component_id of every row."""
    rows = materialize(sketched(docs, plan(percent)[0], id_col, text_col), "sketches")
    filled = rows.where(F.col("node").isNotNull())
    # one row for each distinct set, and one text to read it from
    same = filled.groupBy("node", "doc_id", "text_hash").agg(F.count("*").alias("times"), F.max("n_shingles").alias("n"), F.first("bands").alias("bands"), F.first("sig").alias("sig"))
    first = F.min(F.struct("doc_id", "text_hash", "times"))
    nodes = materialize(same.groupBy("node").agg(first.alias("f"), F.max("n").alias("n"), F.first("bands").alias("bands"), F.first("sig").alias("sig")).select("node", F.col("f.doc_id").alias("low"), F.col("f.text_hash").alias("text_hash"), F.col("f.times").alias("times"), "n", "bands", "sig"), "nodes")
    in_buckets = nodes.select("node", F.explode("bands").alias("bucket"))
    buckets = in_buckets.groupBy("bucket").agg(F.min("node").alias("lead"), F.max("node").alias("last")).where(F.col("lead") < F.col("last")).select("bucket", "lead")
    stars = in_buckets.join(buckets, "bucket").where(F.col("node") != F.col("lead")).select(F.col("node").alias("src"), F.col("lead").alias("dst"))
    clusters = materialize(connected_components(stars), "clusters")
    member = nodes.drop("bands").join(clusters.select(F.col("vertex").alias("node"), F.col("component").alias("cluster")), "node")
    weight = member.groupBy("cluster").agg(F.ceil(F.sum("n") / block_shingles).alias("blocks"))
    with_sets = _sets_of(docs, member.join(weight, "cluster"), id_col, text_col)
    # a set meets every block of its cluster
    block = F.pmod(F.xxhash64("node"), F.col("blocks"))
    cells = F.when(F.col("blocks") > 1, F.transform(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1), lambda k: F.struct(F.least(block, k).alias("i"), F.greatest(block, k).alias("j")))).otherwise(F.array(F.struct(F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j"))))
    dealt = with_sets.select("cluster", "node", "sig", "set", F.explode(cells).alias("c")).select(F.concat("cluster", F.encode(F.concat_ws(",", "c.i", "c.j"), "utf-8")).alias("cell"), "node", "sig", "set")
    links = _forests(dealt, percent)
    roots = connected_components(materialize(links.where(F.col("src") != F.col("dst")), "links"))
    named = nodes.select("node", "low").join(roots.select(F.col("vertex").alias("node"), "component"), "node", "left").select("node", "low", F.coalesce("component", "node").alias("root"))
    least = named.groupBy("root").agg(F.min("low").alias("component_id"))
    labels = named.join(least, "root").select(F.col("node").alias("_node"), "root", "component_id")
    joined = rows.drop("bands", "sig").join(labels, F.col("node") == F.col("_node"), "left")
    return joined.select("doc_id", "text_hash", "n_shingles", "root", F.when(F.col("root").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def near_duplicates(docs: DataFrame, percent: int = PERCENT, **options) -> DataFrame:
    """doc_id, n_shingles, component_id, kept."""
    return labelled(docs, percent, **options).select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def drop_near_duplicates(docs: DataFrame, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs with exactly one row of each component: the one with the smallest id; rows without words all stay."""
    rows = materialize(labelled(docs, percent, id_col=id_col, text_col=text_col, **options), "labelled")
    best = rows.where(F.col("root").isNotNull()).groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("null_id"), "doc_id", "text_hash")).alias("m")).select(F.col("m.doc_id").alias("_best"), F.col("m.text_hash").alias("_best_text"))
    counts = rows.groupBy("doc_id", "text_hash").agg(F.count("*").alias("times"))
    best = best.join(counts, F.col("_best").eqNullSafe(F.col("doc_id")) & (F.col("_best_text") == F.col("text_hash"))).select("_best", "_best_text", "times")
    held = docs.select(F.struct(*docs.columns).alias("_doc"), F.col(id_col).cast("long").alias("_id"), F.xxhash64(F.col(text_col)).alias("_text"), F.coalesce(F.col(text_col).rlike(r"[^\x20\x09-\x0D]"), F.lit(False)).alias("_has_words"))
    chosen = held.where("_has_words").join(best, F.col("_id").eqNullSafe(F.col("_best")) & (F.col("_text") == F.col("_best_text")))
    once = chosen.where("times = 1").select("_doc")
    repeated = chosen.where("times > 1").dropDuplicates(["_id", "_text"]).select("_doc")
    return held.where(~F.col("_has_words")).select("_doc").union(once).union(repeated).select("_doc.*")


ORACLE = rf"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + {SHINGLE - 1}], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - {SHINGLE - 1}, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS shared FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * shared >= {PERCENT} * (x.n + y.n - shared)),
r AS (SELECT a, b FROM (SELECT a, b FROM l UNION ALL SELECT b, a FROM l) UNION SELECT r.a, z.b FROM r JOIN (SELECT a, b FROM l UNION ALL SELECT b, a FROM l) z ON r.b = z.a),
c AS (SELECT a AS doc_id, min(b) AS low FROM r GROUP BY a)
SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, least(doc_id, coalesce(low, doc_id)) AS component_id, doc_id <= coalesce(low, doc_id) AS kept
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN c USING (doc_id)
"""
