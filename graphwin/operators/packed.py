"""Blocks of windows formed within tasks: pairs travel packed, a cluster is refined where it arrives, and a round writes nothing.

Clusters of later rounds lie inside those of earlier ones, so all rounds of a cluster can run in the task that holds its
windows. Pairs reach it as a few compressed byte planes a task and batch instead of rows, and may be repeated.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.functions.hashing import PRIME, affine_constants

#: Pairs packed at a time, pairs refined at a time, pairs of a task on average.
PACK_ROWS, REFINE_PAIRS, TASK_PAIRS = 1_000_000, 1_000_000, 2_000_000
#: The largest window (with repeats) that a task takes; graphs with larger ones go by joins.
WINDOW_PAIRS = 8_000_000
#: Rows of a result: a block's member, an owner's link to a block, a number of clusters.
MEMBER, LINK, CLUSTERS = 0, 1, 2
SCHEMA = "kind int, block_id long, id long"
STEP, OWN, PAIR, VALUE = -1, 0, 1, 2


# -- refinement --------------------------------------------------------------------------------------------------------


def _mix(x, salt: int):
    """A 64-bit finalizer over an array."""
    import numpy as np

    x = x.astype("uint64") + np.uint64((salt * 0x9E3779B97F4A7C15 + 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def member_hashes(ids, m: int, seed: int, family: str):
    """m arrays of hashes, as those of `functions.hashing` for the affine family."""
    import numpy as np

    if family == "affine":
        small = np.mod(ids, PRIME)
        return [(a * small + b) % PRIME for a, b in affine_constants(m, seed)]
    return [(_mix(ids, seed * 1_000 + i) >> np.uint64(1)).astype("int64") for i in range(m)]


def _sorted_pairs(major, minor):
    """Pairs by major, from 0, and minor; as one number each where they fit."""
    import numpy as np

    if not len(major):
        return major, minor
    least = int(minor.min())
    bits = (int(minor.max()) - least).bit_length()
    if bits + int(major.max()).bit_length() > 62:
        order = np.lexsort((minor, major))
        return major[order], minor[order]
    key = np.sort((major.astype("int64") << bits) | (minor - least))
    return key >> bits, (key & ((1 << bits) - 1)) + least


def _shared(c, o, member, m: int, seed: int, family: str):
    """Pairs (o, member) without repeats and by member, o numbers owners, c: the cluster of each -> (member_block, members,
    link_block, o) of the blocks that owners share, numbered from 0, and (o, member) of what is left."""
    import numpy as np

    hx, hy = _mix(np.arange(len(c)), 101), _mix(np.arange(len(c)), 202)
    blocks, rounds = 0, 0
    none = np.zeros(0, "int64")
    in_block, in_member, of_block, of_owner, left_o, left_v = [none], [none], [none], [none], [none], [none]
    while len(o):
        rounds += 1
        _, rank = np.unique(c.view("int64"), return_inverse=True)
        clusters = int(rank.max()) + 1
        rank = rank.astype("uint16" if clusters <= 65_536 else "int64")[o]
        if (rank[1:] < rank[:-1]).any():
            order = np.argsort(rank, kind="stable")  # members stay sorted within clusters
            o, member, rank = o[order], member[order], rank[order]
        head = np.ones(len(o) + 1, bool)
        head[1:-1] = (member[1:] != member[:-1]) | (rank[1:] != rank[:-1])
        alone = head[1:] & head[:-1]  # members of one owner: no later round could share them
        left_o.append(o[alone])
        left_v.append(member[alone])
        o, member, rank = o[~alone], member[~alone], rank[~alone]
        starts = np.flatnonzero(head[:-1][~alone])
        if not len(starts):
            break
        many = np.diff(np.append(starts, len(o)))
        x, y = np.add.reduceat(hx[o], starts), np.add.reduceat(hy[o], starts)
        at = rank[starts].astype("int64")
        # equal neighbours are a class; classes that a clash of keys cuts apart are still classes
        order = np.argsort(_mix(x + at.astype("uint64"), 303))
        a, b = order[1:], order[:-1]
        first = np.concatenate([[True], (x[a] != x[b]) | (y[a] != y[b]) | (at[a] != at[b]) | (many[a] != many[b])])
        group = np.cumsum(first) - 1
        dense = np.bincount(group)[group] > 1
        rows, heads = order[dense], order[dense & first]
        if len(rows):
            in_block.append(np.cumsum(first[dense]) - 1 + blocks)
            in_member.append(member[starts[rows]])
            sizes = many[heads]
            of_block.append(np.repeat(np.arange(blocks, blocks + len(heads)), sizes))
            of_owner.append(o[np.repeat(starts[heads] - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())])
            blocks += len(heads)
        going = np.zeros(clusters, bool)
        going[at[rows]] = True
        state = np.where(going[at], 1, 2).astype("int8")  # goes on, or is left
        state[rows] = 0
        state = np.repeat(state, many)
        left_o.append(o[state == 2])
        left_v.append(member[state == 2])
        o, member = o[state == 1], member[state == 1]
        for h in member_hashes(member, m, seed + rounds, family):
            least = np.full(len(c), np.iinfo("int64").max)
            np.minimum.at(least, o, h)
            c = _mix(c ^ _mix(least, 404), rounds)
    return tuple(np.concatenate(x) for x in (in_block, in_member, of_block, of_owner, left_o, left_v))


def _numbered(got, owners):
    """(member_block, members, link_block, owners) with what is left as one block an owner."""
    import numpy as np

    in_block, in_member, of_block, of_owner, lo, lv = got
    blocks = int(of_block.max()) + 1 if len(of_block) else 0
    order = np.argsort(lo, kind="stable")
    lo, lv = lo[order], lv[order]
    head = np.ones(len(lo), bool)
    head[1:] = lo[1:] != lo[:-1]
    number = np.cumsum(head) - 1 + blocks
    return np.concatenate([in_block, number]), np.concatenate([in_member, lv]), np.concatenate([of_block, number[head]]), owners[np.concatenate([of_owner, lo[head]])]


def _factored(owner, member, cluster):
    """(owners, cluster of each, number of each pair's owner, member), pairs by member."""
    import numpy as np

    owners, first, o = np.unique(owner, return_index=True, return_inverse=True)
    order = np.argsort(member, kind="stable")
    return owners, cluster[first].astype("uint64"), o[order], member[order]


def refine(owner, member, cluster, m: int = 1, seed: int = 1, family: str = "affine"):
    """Pairs (owner, member) without repeats, with the cluster of each -> (member_block, members, link_block, owners), blocks
    numbered from 0. A class shared by two or more owners and of two or more members is a block; what a cluster without
    such a class leaves, and members of one owner alone, which no later round could share, form one block an owner."""
    owners, c, o, member = _factored(owner, member, cluster)
    return _numbered(_shared(c, o, member, m, seed, family), owners)


class Blocks:
    """A task's windows, refined some clusters at a time; blocks are numbered by task."""

    def __init__(self, first: int, m: int, seed: int, family: str):
        from pyspark import TaskContext

        self.next = (first + TaskContext.get().partitionId()) << 36
        self.options = (m, seed, family)
        self.held, self.rows = [], 0

    def add(self, owner, member, cluster):
        self.held.append((owner, member, cluster))
        self.rows += len(owner)

    def take(self, least: int = REFINE_PAIRS):
        import numpy as np

        if self.rows < max(least, 1):
            return
        owner, member, cluster = (np.concatenate(c) for c in zip(*self.held, strict=True))
        self.held, self.rows = [], 0
        yield from self.refined(*_factored(owner, member, cluster))

    def refined(self, owners, c, o, member):
        """Rows of some whole clusters; o: the number of each pair's owner, c: the cluster of each owner, pairs by member
        within clusters."""
        return self.rows_of(owners, _shared(c, o, member, *self.options))

    def rows_of(self, owners, got):
        import numpy as np
        import pyarrow as pa

        got, last = _numbered(got, owners), self.next
        for kind, block, ids in ((MEMBER, *got[:2]), (LINK, *got[2:])):
            for lo in range(0, len(ids), 200_000):
                b, i = block[lo:lo + 200_000] + self.next, ids[lo:lo + 200_000]
                last = max(last, int(b.max()) + 1)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(i), kind, "int32")), pa.array(b), pa.array(i)], names=["kind", "block_id", "id"])
        self.next = last


class Sums(Blocks):
    """Blocks that are added up where they are formed: rows (LINK, owner, sums), an owner once for each batch that it is in.
    ids: vertices in order; values: their numbers, an array a sum."""

    def __init__(self, m: int, seed: int, family: str, ids, values):
        import numpy as np

        super().__init__(0, m, seed, family)
        self.ids, self.base, self.values = ids, 0, values
        if len(ids) and ids[-1] - ids[0] < 4 * len(ids):  # read by place; vertices that aren't there count 0
            self.ids, self.base, self.values = None, int(ids[0]), []
            for v in values:
                self.values.append(np.zeros(int(ids[-1]) - self.base + 1, "int64"))
                self.values[-1][ids - self.base] = v

    def of(self, members):
        """The numbers of members, an array a sum."""
        import numpy as np

        if self.ids is None:
            at = members - self.base
            known = (at >= 0) & (at < len(self.values[0]))
        else:
            at = np.minimum(np.searchsorted(self.ids, members), max(len(self.ids) - 1, 0))
            known = self.ids[at] == members if len(self.ids) else np.zeros(len(members), bool)
        return [v[at] if known.all() else np.where(known, v[np.where(known, at, 0)], 0) if len(v) else np.zeros(len(members), "int64") for v in self.values]

    def rows_of(self, owners, got):
        import numpy as np
        import pyarrow as pa

        in_block, in_member, of_block, of_owner, lo, lv = got
        sums, n = [], int(of_block.max()) + 1 if len(of_block) else 0
        for shared, left in zip(self.of(in_member), self.of(lv), strict=True):
            block, owner = np.zeros(n, "int64"), np.zeros(len(owners), "int64")
            np.add.at(block, in_block, shared)
            np.add.at(owner, of_owner, block[of_block])
            np.add.at(owner, lo, left)
            sums.append(pa.array(owner))
        for lo in range(0, len(owners), 200_000):
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(owners[lo:lo + 200_000]), LINK, "int32")), pa.array(owners[lo:lo + 200_000]), *[x[lo:lo + 200_000] for x in sums]], names=["kind", "id", *sum_names(len(sums))])


def sum_names(n: int) -> list[str]:
    return [f"_gw_s{i}" for i in range(n)]


def sums_schema(n: int) -> str:
    return ", ".join(["kind int", "id long", *[f"{c} long" for c in sum_names(n)]])


def by_vertex(ids, values):
    """Vertices in order, numbers of rows of one vertex added up."""
    import numpy as np

    own, at = np.unique(ids, return_inverse=True)
    out = [np.zeros(len(own), "int64") for _ in values]
    for into, v in zip(out, values, strict=True):
        np.add.at(into, at, v)
    return own, out


# -- packed exchange ---------------------------------------------------------------------------------------------------


def _planes(x) -> bytes:
    """Differences of an array as compressed byte planes."""
    import numpy as np
    import pyarrow as pa

    d = np.diff(x, prepend=np.int64(0)).astype("int64")
    d = (d << 1) ^ (d >> 63)
    return pa.compress(d.view("uint8").reshape(-1, 8).T.tobytes(), "zstd", asbytes=True)


def _from_planes(b: bytes, n: int):
    import numpy as np
    import pyarrow as pa

    d = np.frombuffer(pa.decompress(b, n * 8, "zstd", asbytes=True), "uint8").reshape(8, n).T.copy().view("int64").reshape(n)
    u = d.view("uint64")
    return np.cumsum((u >> np.uint64(1)).view("int64") ^ -(d & 1))


def _pack(kind: int):
    def run(batches):
        import numpy as np
        import pyarrow as pa

        def packed(held):
            target, owner, value = (np.concatenate([b.column(c).to_numpy() for b in held]) for c in ("target", "owner", "value"))
            owners, first, o = np.unique(owner, return_index=True, return_inverse=True)
            deal = np.argsort(target[first], kind="stable")  # owners by task and id
            rank = np.empty(len(deal), "int64")
            rank[deal] = np.arange(len(deal))
            o, value = _sorted_pairs(rank[o], value)
            target = target[first][deal][o]
            cuts = np.flatnonzero(np.concatenate([[True], target[1:] != target[:-1], [True]]))
            dealt, out = owners[deal], []
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                out.append((int(target[lo]), kind, hi - lo, _planes(dealt[o[lo:hi]]), _planes(value[lo:hi])))
            t, k, n, a, b = zip(*out, strict=True)
            return pa.RecordBatch.from_arrays([pa.array(t, pa.int32()), pa.array(k, pa.int32()), pa.array(n, pa.int32()), pa.array(a, pa.binary()), pa.array(b, pa.binary())], names=["target", "kind", "n", "owners", "values"])

        held, rows = [], 0
        for b in batches:
            if b.num_rows:
                held.append(b)
                rows += b.num_rows
            if rows >= PACK_ROWS:
                yield packed(held)
                held, rows = [], 0
        if rows:
            yield packed(held)

    return run


class Steps:
    """All steps (src, dst) of a graph by their start, of packed chunks in any order: the ends of the steps from ids[i] are
    ends[at[i]:at[i + 1]] + base."""

    def __init__(self, chunks):
        import numpy as np

        starts, least, most = [], [], []
        for n, a, b in chunks:  # a chunk is sorted by its starts
            src, dst = _from_planes(a, n), _from_planes(b, n)
            first = np.flatnonzero(np.concatenate([[True], src[1:] != src[:-1]]))
            starts.append((src[first], np.diff(np.append(first, n))))
            least.append(int(dst.min()))
            most.append(int(dst.max()))
        self.ids = np.unique(np.concatenate([np.zeros(0, "int64"), *[x for x, _ in starts]]))
        degree = np.zeros(len(self.ids), "int64")
        for k, (x, c) in enumerate(starts):
            starts[k] = np.searchsorted(self.ids, x), c
            degree[starts[k][0]] += c
        self.at = np.concatenate([[0], np.cumsum(degree)])
        self.base = min(least, default=0)
        self.ends = np.empty(self.at[-1], "int32" if max(most, default=0) - self.base < 2**31 else "int64")
        free = self.at[:-1].copy()
        for (n, _, b), (x, c) in zip(chunks, starts, strict=True):
            self.ends[np.repeat(free[x] - np.cumsum(c) + c, c) + np.arange(n)] = _from_planes(b, n) - self.base
            free[x] += c

    def from_(self, who):
        """(places in who, ends) of the steps from an array of vertices."""
        import numpy as np

        i = np.minimum(np.searchsorted(self.ids, who), max(len(self.ids) - 1, 0))
        first = self.at[i]
        n = np.where(self.ids[i] == who, self.at[i + 1] - first, 0)
        return np.repeat(np.arange(len(who)), n), self.ends[np.repeat(first - np.cumsum(n) + n, n) + np.arange(n.sum())].astype("int64") + self.base

    def degree(self, who):
        import numpy as np

        i = np.minimum(np.searchsorted(self.ids, who), max(len(self.ids) - 1, 0))
        return np.where(self.ids[i] == who, self.at[i + 1] - self.at[i], 0)


def _walked(steps: Steps, who, cluster, loops: bool):
    """(owners, clusters, number of each pair's owner, members) of the windows of two steps, some whole clusters at a time, as
    `Blocks.refined` takes them; who: owners by cluster."""
    import numpy as np

    if not len(steps.ids):
        return
    o, mid = steps.from_(who)
    paths = np.bincount(o, steps.degree(mid), len(who)).astype("int64")
    cuts, total = np.searchsorted(o, np.arange(len(who) + 1)), np.concatenate([[0], np.cumsum(paths)])
    lo = 0
    for hi in (np.flatnonzero(np.append(cluster[1:] != cluster[:-1], True)) + 1).tolist():
        if total[hi] - total[lo] >= REFINE_PAIRS or hi == len(who):
            at, member = steps.from_(mid[cuts[lo]:cuts[hi]])
            yield _pairs_by_cluster(who[lo:hi], cluster[lo:hi], o[cuts[lo]:cuts[hi]][at] - lo, member, loops)
            lo = hi


def _pairs_by_cluster(who, cluster, o, member, loops: bool = True):
    """(who, cluster, o, member) without repeats of pairs, by cluster and member; who: owners by cluster."""
    import numpy as np

    base = int(member.min()) if len(member) else 0
    bits = (int(member.max()) - base).bit_length() if len(member) else 0
    rank = np.concatenate([[0], np.cumsum(cluster[1:] != cluster[:-1])])
    if bits + int(rank[-1]).bit_length() > 62:  # the first round sorts by cluster
        rank = np.zeros(len(who), "int64")
    major, o = _sorted_pairs((rank[o] << bits) | (member - base), o)
    new = np.ones(len(o), bool)
    new[1:] = (o[1:] != o[:-1]) | (major[1:] != major[:-1])
    o, member = o[new], (major[new] & ((1 << bits) - 1)) + base
    if not loops:
        o, member = o[member != who[o]], member[member != who[o]]
    return who, cluster.astype("uint64"), o, member


def _refine_packed(first: int, m: int, seed: int, family: str, sums: int = 0, loops: bool = True):
    def run(batches):
        import numpy as np

        kept = {STEP: [], OWN: [], PAIR: []} | {VALUE + i: [] for i in range(sums)}
        for b in batches:
            for kind, n, a, c in zip(*(b.column(x).to_pylist() for x in ("kind", "n", "owners", "values")), strict=True):
                if n:
                    kept[kind].append((n, a, c) if kind == STEP else (_from_planes(a, n), _from_planes(c, n)))
        if not kept[OWN]:
            return
        read = []
        for i in range(sums):
            ids, value = (np.concatenate([np.zeros(0, "int64"), *x]) for x in zip(*kept.pop(VALUE + i), strict=True))
            read.append(by_vertex(ids, [value]))
        who, cluster = (np.concatenate(x) for x in zip(*kept[OWN], strict=True))
        order = np.lexsort((who, cluster))
        who, cluster = who[order], cluster[order]
        blocks = Sums(m, seed, family, read[0][0], [v for _, (v,) in read]) if sums else Blocks(first, m, seed, family)
        if kept[STEP]:
            for pairs in _walked(Steps(kept.pop(STEP)), who, cluster, loops):
                yield from blocks.refined(*pairs)
            return
        by_id = np.argsort(who)
        sorted_ids = who[by_id]
        owner, member = (np.concatenate([np.zeros(0, "int64"), *x]) for x in zip(*kept[PAIR], strict=True)) if kept[PAIR] else (np.zeros(0, "int64"),) * 2
        kept.clear()
        owner, member = _sorted_pairs(by_id[np.searchsorted(sorted_ids, owner)], member)  # owners by cluster
        last = np.flatnonzero(np.append(cluster[1:] != cluster[:-1], True)) + 1
        ends, lo, at = np.searchsorted(owner, last), 0, 0
        for hi, to in zip(ends.tolist(), last.tolist(), strict=True):  # whole clusters, several at a time
            if hi - lo >= REFINE_PAIRS or to == len(who):
                yield from blocks.refined(*_pairs_by_cluster(who[at:to], cluster[at:to], owner[lo:hi] - at, member[lo:hi]))
                lo, at = hi, to

    return run


def packed_blocks(pairs: DataFrame | None, own: DataFrame, tasks: int, first: int, m: int, seed: int, family: str, values: DataFrame | None = None, steps: DataFrame | None = None, loops: bool = True) -> DataFrame:
    """SCHEMA rows, or with values (id, sum_names), each task's sums instead, see Sums. pairs: (target, owner, member), perhaps
    repeated; own: (target, owner, cluster). With steps (src, dst), distinct, no pairs are sent: every task gets all steps and
    walks two of them from its owners, without the way back if not loops."""
    packed = "target int, kind int, n int, owners binary, values binary"
    sent = own.select("target", "owner", F.col("cluster").alias("value")).mapInArrow(_pack(OWN), packed)
    if pairs is not None:
        sent = sent.union(pairs.select("target", "owner", F.col("member").alias("value")).mapInArrow(_pack(PAIR), packed))
    names = [c for c in values.columns if c != "id"] if values is not None else []
    whole = [(VALUE + i, values.select(F.col("id").alias("owner"), F.col(c).alias("value"))) for i, c in enumerate(names)]
    if steps is not None:
        whole.append((STEP, steps.select(F.col("src").alias("owner"), F.col("dst").alias("value"))))
    schema = sums_schema(len(names)) if names else SCHEMA
    if not whole:
        return sent.repartitionById(tasks, F.col("target")).mapInArrow(_refine_packed(first, m, seed, family), schema)
    # one row a task takes along what all tasks need, packed too
    asks = own.sparkSession.range(tasks).select(F.col("id").cast("int").alias("target"), F.lit(VALUE).alias("kind"), F.lit(0).alias("n"), F.lit(None).cast("binary").alias("owners"), F.lit(None).cast("binary").alias("values"))
    sent = sent.union(asks).repartitionById(tasks, F.col("target"))
    told = None
    for kind, df in whole:
        one = df.select(F.lit(0).alias("target"), "owner", "value").mapInArrow(_pack(kind), packed)
        told = one if told is None else told.union(one)
    told = told.select(F.lit(VALUE).alias("_ask"), F.struct("kind", "n", "owners", "values").alias("_told"))
    asked = sent.join(F.broadcast(told), (F.col("kind") == F.col("_ask")) & (F.col("n") == 0), "left")
    return asked.select("target", *[F.when(F.col("_told").isNull(), F.col(c)).otherwise(F.col(f"_told.{c}")).alias(c) for c in ("kind", "n", "owners", "values")]).mapInArrow(_refine_packed(first, m, seed, family, len(names), loops), schema)
