"""Ancestor windows of DAGs that fall into parts no edge crosses, or that are small: a part is closed within one task.

A vertex's window is a bit mask over its part, the union of its parents' masks, so a window costs its part's vertices in bits
and is never a set of rows unless rows are asked for. Masks of a large part are formed a stretch of members at a time.
Graphs with a larger part, or with no known parts and many vertices, go by the joins of `reach`.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphwin.model import CycleError, PropertyGraph
from graphwin.operators.packed import CLUSTERS, REFINE_PAIRS, SCHEMA, Blocks, Sums, _mix, by_vertex, member_hashes, sum_names, sums_schema
from graphwin.session import materialize

#: The largest part that one task takes; larger ones go by joins.
PART_VERTICES, PART_EDGES = 200_000, 3_000_000
#: Bytes of masks that a task holds at a time, rows of a task's parts, rows of a batch.
MASK_BYTES, TASK_ROWS, BATCH = 48 << 20, 150_000, 200_000
#: From this many vertices in a part its owners are dealt over several tasks when windows are asked for as rows.
DEALT, SLOTS = 4_000, 16
#: Most groups of stretches of members that slots share out; within a group slots share out owners.
GROUPS = 4
VERTEX, EDGE = 0, 1
#: The least hash of nothing.
NONE_LEAST = (1 << 63) - 1


def part_of(graph: PropertyGraph):
    """The part of a row of vertices or edges; rows without one are a part."""
    return F.coalesce(F.col(graph.part).cast("long"), F.lit(-1).cast("long"))


@dataclass
class Parted:
    rows: DataFrame  # part, kind, a, b: (VERTEX, id, null) or (EDGE, src, dst)
    tasks: int
    largest: int


def parted(graph: PropertyGraph, only: DataFrame | None = None, read: list[str] | None = None, largest: tuple[int, int] = (PART_VERTICES, PART_EDGES)) -> Parted | None:
    """The graph's rows by part, or None if its parts are unknown or too large. only: (part) that are wanted; read: vertex
    attributes to stand beside the vertices."""
    v, e = graph.vertices, graph.edges
    if graph.part is None:
        if v.limit(largest[0] + 1).count() > largest[0]:
            return None
        part = F.lit(0).cast("long")
    else:
        part = part_of(graph)
    more = [F.col(c).alias(f"_gw_{c}") for c in read or []]
    none = [F.lit(None).cast(v.schema[c].dataType).alias(f"_gw_{c}") for c in read or []]
    rows = v.select(part.alias("part"), F.lit(VERTEX).alias("kind"), F.col("id").alias("a"), F.col("id").alias("b"), *more)
    rows = rows.union(e.select(part.alias("part"), F.lit(EDGE).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), *none))
    if only is not None:
        rows = rows.join(only.select("part").distinct(), "part", "left_semi")
    rows = materialize(rows, "parts")
    sizes = rows.groupBy("part").agg(F.count_if(F.col("kind") == VERTEX).alias("v"), F.count_if(F.col("kind") == EDGE).alias("e"))
    n, v_max, e_max = sizes.agg(F.sum(F.col("v") + F.col("e")), F.max("v"), F.max("e")).first()
    if n is None:
        return Parted(rows, 1, 0)
    return None if v_max > largest[0] or e_max > largest[1] else Parted(rows, max(1, -(-n // TASK_ROWS)), v_max)


def _dealt(rows: DataFrame, tasks: int, slots: int = 1) -> DataFrame:
    """Rows of a part in one partition, or, with slots, in one partition for each of them."""
    rows = rows.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(slots - 1)))) if slots > 1 else rows.withColumn("slot", F.lit(0))
    tasks *= slots
    return rows.repartitionById(tasks, F.pmod(F.xxhash64("part") + F.col("slot"), F.lit(tasks)).cast("int"))


def _groups(batches):
    """(columns of one part and slot) of a partition's batches."""
    import numpy as np
    import pyarrow as pa

    batches = list(batches)
    if not batches:
        return
    table = pa.Table.from_batches(batches)
    part, slot = (table.column(c).to_numpy() for c in ("part", "slot"))
    order = np.lexsort((slot, part))
    part, slot = part[order], slot[order]
    cuts = np.flatnonzero((part[1:] != part[:-1]) | (slot[1:] != slot[:-1])) + 1
    kind, a, b = (table.column(c).to_numpy()[order] for c in ("kind", "a", "b"))
    lo = 0
    for hi in [*cuts.tolist(), len(part)]:
        yield part[lo], int(slot[lo]), kind[lo:hi], a[lo:hi], b[lo:hi], table, order[lo:hi]
        lo = hi


class _Part:
    """A part's vertices by number in the order of their ids, with parents and a topological order."""

    def __init__(self, kind, a, b):
        import numpy as np

        v, e = kind == VERTEX, kind == EDGE
        src, dst = a[e], b[e]
        self.ids = np.unique(np.concatenate([a[v], src, dst]))
        self.n = n = len(self.ids)
        self.own = np.unique(np.searchsorted(self.ids, a[v]))
        edges = np.unique(np.searchsorted(self.ids, src) * n + np.searchsorted(self.ids, dst)) if len(src) else np.zeros(0, "int64")
        self.up = up = [[] for _ in range(n)]
        down, wait = [[] for _ in range(n)], [0] * n
        for s, d in zip((edges // max(n, 1)).tolist(), (edges % max(n, 1)).tolist(), strict=True):
            up[d].append(s)
            down[s].append(d)
            wait[d] += 1
        self.order = order = [i for i in range(n) if not wait[i]]
        self.level = level = [0] * n
        for i in order:
            for d in down[i]:
                if level[d] <= level[i]:
                    level[d] = level[i] + 1
                wait[d] -= 1
                if not wait[d]:
                    order.append(d)
        self.cyclic = len(order) < n
        self.down = down

    def stretches(self) -> range:
        """The first members of the stretches whose masks are held at a time."""
        return range(0, self.n, max(8, MASK_BYTES * 8 // max(self.n, 1) // 8 * 8))

    def masks(self, group: int = 0, groups: int = 1):
        """(first, bits, masks): proper ancestors by number from first, a stretch of members at a time, of every groups-th one
        from group on."""
        starts = self.stretches()
        width = starts.step
        for first in starts[group::groups]:
            bits = min(width, self.n - first)
            masks = [0] * self.n
            full = [0] * self.n  # with the vertex itself
            for i in self.order:
                m = 0
                for p in self.up[i]:
                    m |= full[p]
                masks[i] = m
                full[i] = m | (1 << (i - first)) if first <= i < first + bits else m
            yield first, bits, masks, full


def _numbers(masks: list[int], bits: int, at_once: int = 4 << 20):
    """(row, number) of all set bits, some rows at a time."""
    import numpy as np

    width = (bits + 7) // 8
    some = max(1, at_once // max(bits, 1))
    for lo in range(0, len(masks), some):
        raw = b"".join(m.to_bytes(width, "little") for m in masks[lo:lo + some])
        set_bits = np.unpackbits(np.frombuffer(raw, "uint8").reshape(-1, width), axis=1, bitorder="little")
        r, c = np.nonzero(set_bits.view(bool))
        yield r + lo, c


class _Out:
    """Columns gathered into batches."""

    def __init__(self, schema):
        self.schema, self.held, self.rows = schema, [], 0

    def add(self, *columns):
        if len(columns[0]):
            self.held.append(columns)
            self.rows += len(columns[0])

    def take(self, least: int = BATCH):
        import numpy as np
        import pyarrow as pa

        if self.rows < max(least, 1):
            return
        whole = [np.concatenate(c) for c in zip(*self.held, strict=True)]
        self.held, self.rows = [], 0
        for lo in range(0, len(whole[0]), BATCH):
            yield pa.RecordBatch.from_arrays([pa.array(c[lo:lo + BATCH], f.type) for c, f in zip(whole, self.schema, strict=True)], schema=self.schema)


#: Rows of an index: a vertex with its parent (itself if it has none), level and size; a member of its delta; from JUMP on, a
#: place up its parent path for each round.
PARENT, DELTA, JUMP, CYCLE = 0, 1, 2, -1


def _index_rows(radix: int):
    def run(batches):
        import numpy as np
        import pyarrow as pa

        out = _Out(pa.schema([("part", pa.int64()), ("kind", pa.int32()), ("v", pa.int64()), ("to", pa.int64()), ("level", pa.int32()), ("card", pa.int64())]))

        def put(kind, v, to, level=None, card=None):
            zero = np.zeros(len(v), "int64")
            out.add(np.full(len(v), name, "int64"), np.full(len(v), kind, "int32"), v, to, zero.astype("int32") if level is None else level, zero if card is None else card)

        for name, _, kind, a, b, _, _ in _groups(batches):
            part = _Part(kind, a, b)
            if part.cyclic:
                put(CYCLE, part.ids[:1], part.ids[:1])
                continue
            card, kept = [1] * part.n, []
            for first, bits, masks, full in part.masks():
                card = [c + m.bit_count() for c, m in zip(card, masks, strict=True)]
                kept = [(first, bits, masks, full)]
            # ids rise with numbers, so of equal sizes the least number has the least id
            own = np.zeros(part.n, bool)
            own[part.own] = True
            known = own.tolist()
            pid = [max(((card[p], -p) for p in up if known[p]), default=(0, 1))[1] * -1 for up in part.up]
            to = np.array(pid, "int64")
            has = own & (to >= 0)
            to = np.where(has, to, -1)
            put(PARENT, part.ids[own], part.ids[np.where(has, to, np.arange(part.n))][own], np.array(part.level, "int32")[own], np.array(card, "int64")[own])
            heirs = np.flatnonzero(has).tolist()
            for first, bits, masks, full in kept if part.n <= kept[0][1] else part.masks():
                differ = [(i, masks[i] & ~full[pid[i]]) for i in heirs]
                differ = [(i, m) for i, m in differ if m]
                who = np.array([i for i, _ in differ], "int64")
                for r, c in _numbers([m for _, m in differ], bits):
                    put(DELTA, part.ids[who[r]], part.ids[c + first])
                    yield from out.take()
            far, step = JUMP, to
            while (step >= 0).any():
                at = step
                for _ in range(1, radix):
                    on = at >= 0
                    put(far, part.ids[on], part.ids[at[on]])
                    at = np.where(on, step[at], -1)
                far, step = far + 1, at
            yield from out.take()
        yield from out.take(1)

    return run


def index_rows(p: Parted, radix: int) -> DataFrame:
    """(part, kind, v, to, level, card), see PARENT; written. Raises CycleError."""
    got = materialize(_dealt(p.rows, p.tasks).mapInArrow(_index_rows(radix), "part long, kind int, v long, to long, level int, card long"), "pd_parts")
    if not got.where(F.col("kind") == CYCLE).isEmpty():
        raise CycleError("the graph has a cycle")
    return got


def _pair_rows(include_self: bool, slots: int, read: list[str]):
    def run(batches):
        import numpy as np
        import pyarrow as pa

        out = _Out(pa.schema([("owner", pa.int64()), ("member", pa.int64()), *[("_row", pa.int64())] * bool(read)]))
        for _, slot, kind, a, b, table, rows in _groups(batches):
            part = _Part(kind, a, b)
            mine = part.own[part.own % slots == slot]
            place = np.full(part.n, -1)
            vertices = kind == VERTEX
            place[np.searchsorted(part.ids, a[vertices])] = rows[vertices]
            for first, bits, masks, full in part.masks():
                sets = full if include_self else masks
                for r, c in _numbers([sets[i] for i in mine.tolist()], bits):
                    owner, member = mine[r], c + first
                    if read:  # a member without a vertex has no attributes
                        known = place[member] >= 0
                        owner, member = owner[known], member[known]
                    out.add(part.ids[owner], part.ids[member], *[place[member]] * bool(read))
                    for batch in out.take():
                        yield _with(batch, table, read)
        for batch in out.take(1):
            yield _with(batch, table, read)

    return run


def _with(batch, table, read: list[str]):
    """The batch with the members' attributes in place of their rows."""
    import pyarrow as pa

    if not read:
        return batch
    got = [table.column(f"_gw_{c}").take(batch.column(2)).combine_chunks() for c in read]
    return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *got], names=["owner", "member", *[f"_gw_{c}" for c in read]])


def _block_rows(include_self: bool, slots: int, m: int, seed: int, family: str, read: list[str] | None = None):
    def run(batches):
        import numpy as np
        import pyarrow as pa

        def note(kind, number):
            if read:
                return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), *[pa.array([number], pa.int64())] * (1 + len(read))], names=["kind", "id", *sum_names(len(read))])
            return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([0], pa.int64()), pa.array([number], pa.int64())], names=["kind", "block_id", "id"])

        blocks, clusters = Blocks(0, m, seed, family), 0
        for name, slot, kind, a, b, table, rows in _groups(batches):
            part = _Part(kind, a, b)
            if part.cyclic:
                yield note(CYCLE, int(name))
                continue
            if read:
                yield from blocks.take(1)
                of = rows[kind == VERTEX]
                blocks = Sums(m, seed, family, *by_vertex(a[kind == VERTEX], [table.column(f"_gw_{c}").take(pa.array(of)).to_numpy() for c in read]))
            key = np.full(part.n, _mix(np.array([name]), 505)[0])
            for h in member_hashes(part.ids, m, seed, family):  # a window's minimum is the least of its parents' and its own
                h = h.tolist()
                proper = [NONE_LEAST] * part.n
                for i in part.order:
                    for p in part.up[i]:
                        proper[i] = min(proper[i], proper[p], h[p])
                least = [min(x, y) for x, y in zip(proper, h, strict=True)] if include_self else proper
                key = _mix(key ^ _mix(np.array(least), 606), 707)
            place = np.empty(part.n, "int64")
            place[part.order] = np.arange(part.n)
            mine = part.own[np.lexsort((place[part.own], key[part.own]))]  # by cluster, then from sources on
            groups = min(len(part.stretches()), GROUPS, slots)
            shares, share = slots // groups, slot // groups
            if slots > 1:
                mine = mine[(np.arange(len(mine)) * (4 * shares) // max(len(mine), 1)) % shares == share]
            if slot % groups == 0:
                clusters += len(np.unique(key[mine]))
            who = mine.tolist()
            for first, bits, masks, full in part.masks(slot % groups, groups) if who else ():
                sets = full if include_self else masks
                for r, c in _numbers([sets[i] for i in who], bits, REFINE_PAIRS):
                    blocks.add(part.ids[mine[r]], part.ids[c + first], key[mine[r]])
                    yield from blocks.take()
        yield from blocks.take(1)
        yield note(CLUSTERS, clusters)

    return run


def block_rows(graph: PropertyGraph, include_self: bool, m: int, seed: int, family: str, read: list[str] | None = None) -> DataFrame | None:
    """A shared-block index of all ancestor windows as rows of `packed.SCHEMA`, not yet run; each part is clustered and refined
    where it is closed, so no pair is ever sent. A part with a cycle gives a row of kind CYCLE instead. With read, whole
    numbers of the vertices, the rows are each task's sums, see `packed.Sums`. None for graphs that go by joins."""
    p = parted(graph, read=read)
    if p is None:
        return None
    slots = SLOTS if p.largest >= DEALT else 1
    return _dealt(p.rows, p.tasks, slots).mapInArrow(_block_rows(include_self, slots, m, seed, family, read), sums_schema(len(read)) if read else SCHEMA)


def _cycles(batches):
    import pyarrow as pa

    for name, _, kind, a, b, _, _ in _groups(batches):
        if _Part(kind, a, b).cyclic:
            yield pa.RecordBatch.from_arrays([pa.array([name], pa.int64())], names=["part"])


def ancestor_rows(graph: PropertyGraph, include_self: bool = True, read: list[str] | None = None) -> DataFrame | None:
    """(owner, member), or with `read` (owner, member, the member's attributes as _gw_<name>); nothing is written or joined.
    None for graphs that go by joins. Raises CycleError."""
    read = list(read or [])
    p = parted(graph, read=read)
    if p is None:
        return None
    if not _dealt(p.rows.select("part", "kind", "a", "b"), p.tasks).mapInArrow(_cycles, "part long").isEmpty():
        raise CycleError("the graph has a cycle")
    slots = SLOTS if p.largest >= DEALT else 1
    schema = T.StructType([T.StructField("owner", T.LongType()), T.StructField("member", T.LongType()), *[T.StructField(f"_gw_{c}", graph.vertices.schema[c].dataType) for c in read]])
    return _dealt(p.rows, p.tasks, slots).mapInArrow(_pair_rows(include_self, slots, read), schema)
