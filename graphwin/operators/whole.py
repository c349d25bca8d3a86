"""Ancestor windows of a large DAG without known parts: every task holds the graph and closes its own stretches of members.

The graph is numbered once, parents before children, and sent packed (2 to 3 bytes an edge). A window is a row of bits over a
stretch of members, the union of its parents' rows; rows of a level are formed together. Windows and deltas are counted and
added up where they are formed; nothing that grows with the pairs is written or sent unless pairs are asked for as rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.model import CycleError, PropertyGraph
from graphwin.operators.packed import _from_planes, _pack, _planes, by_vertex
from graphwin.session import discard, materialize

#: The largest graph that tasks hold; larger ones go by joins.
VERTICES, EDGES = 3_000_000, 30_000_000
#: Bytes of the rows of bits that a task holds, most words of a row, rows formed at a time, tasks.
MASK_BYTES, WORDS, ROWS, TASKS = 160 << 20, 32, 4_096, 24
#: Numbers of vertices, and of edges, in a packed row.
CHUNK, EDGE_CHUNK = 1 << 16, 1 << 20
#: Parents that rows take one at a time; what a vertex has beyond is taken at once.
SINGLY = 64
#: What a packed row holds of the vertices from number `at` on, or of the edges; sums from SUM on, jumps from JUMP on.
IDS, OWN, LEVEL, DEGREE, PARENTS, CARD, PID, COUNT, VALUE, SUM, JUMP, CYCLE = 0, 1, 2, 3, 4, 5, 6, 7, 8, 1_000, 2_000, -1
EMPTY, SOME, FULL = 0, 1, 2
PACKED = "kind int, at int, n int, a binary, b binary"


def _batch(rows):
    import pyarrow as pa

    kind, at, n, a, b = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(kind, pa.int32()), pa.array(at, pa.int32()), pa.array(n, pa.int32()), pa.array(a, pa.binary()), pa.array(b, pa.binary())], names=["kind", "at", "n", "a", "b"])


def _chunks(kind: int, x, size: int = CHUNK):
    """An array as batches of packed rows."""
    for at in range(0, len(x), size):
        piece = x[at:at + size].astype("int64")
        yield _batch([(kind, at, len(piece), _planes(piece), None)])


def _rows(batches, task=lambda t: None):
    """Packed rows; task is told which task they came to, if they say so."""
    for batch in batches:
        if "task" in batch.schema.names and batch.num_rows:
            task(batch.column("task")[0].as_py())
        yield from zip(*(batch.column(c).to_pylist() for c in ("kind", "at", "n", "a", "b")), strict=True)


# -- numbering ---------------------------------------------------------------------------------------------------------


def _distinct(x):
    """An array's values in order, by sorting."""
    import numpy as np

    x = np.sort(x)
    new = np.ones(len(x), bool)
    new[1:] = x[1:] != x[:-1]
    return x[new]


def _places(ids):
    """A function from some of the ids to their places in order; by a table where that takes few places in vain."""
    import numpy as np

    if not len(ids) or int(ids[-1]) - int(ids[0]) >= 4 * len(ids):
        return lambda x: np.searchsorted(ids, x)
    table = np.zeros(int(ids[-1] - ids[0]) + 1, "int32")
    table[ids - ids[0]] = np.arange(len(ids))
    return lambda x: table[x - ids[0]].astype("int64")


def _counts(x, n: int):
    """bincount, which copies what it counts, of a stretch at a time."""
    import numpy as np

    out = np.zeros(n, "int64")
    for lo in range(0, len(x), EDGE_CHUNK):
        out += np.bincount(x[lo:lo + EDGE_CHUNK], minlength=n)
    return out


def _in_order(key):
    """(high, low) 32 bits of numbers, put in order in their place, without repeats."""
    import numpy as np

    key.sort()
    new = np.ones(len(key), bool)
    new[1:] = key[1:] != key[:-1]
    to = 0
    for lo in range(0, len(key), EDGE_CHUNK) if not new.all() else ():
        piece = key[lo:lo + EDGE_CHUNK][new[lo:lo + EDGE_CHUNK]]
        key[to:to + len(piece)] = piece
        to += len(piece)
    pairs = key[:to or len(key)].view("int32")
    return pairs[1::2].copy(), pairs[::2].copy()


def _levels(src, dst, n: int):
    """The longest path from a source for each of n vertices, and how many have one; src: in order."""
    import numpy as np

    at = np.searchsorted(src, np.arange(n + 1, dtype="int32"))
    wait, level, seen, now = _counts(dst, n), np.zeros(n, "int32"), 0, 0
    front = np.flatnonzero(wait == 0)
    while len(front):
        level[front] = now
        seen, now = seen + len(front), now + 1
        c = at[front + 1] - at[front]
        down = dst[np.repeat(at[front] - np.cumsum(c) + c, c) + np.arange(c.sum())]
        np.subtract.at(wait, down, 1)
        front = _distinct(down[wait[down] == 0])
    return level, seen


def _numbered(batches):
    """Packed vertices and edges (target, kind, n, owners, values) of the graph -> its PACKED rows, by level and falling degree."""
    import numpy as np

    vertices, edges = [np.zeros(0, "int64")], []
    for b in batches:
        for kind, n, a, c in zip(*(b.column(x).to_pylist() for x in ("kind", "n", "owners", "values")), strict=True):
            if kind == IDS:
                vertices.append(_from_planes(a, n))
            else:
                edges.append((n, a, c))
    vertices = _distinct(np.concatenate(vertices))
    ends = [_distinct(_from_planes(x, m)) for m, a, c in edges for x in (a, c)]
    ids = _distinct(np.concatenate([vertices, *ends]))
    ends.clear()
    place = _places(ids)
    n = len(ids)
    key, lo = np.empty(sum(m for m, _, _ in edges), "int64"), 0
    for m, a, c in edges:
        key[lo:lo + m] = (place(_from_planes(a, m)) << 32) | place(_from_planes(c, m))
        lo += m
    edges.clear()
    src, dst = _in_order(key)
    del key
    level, seen = _levels(src, dst, n)
    if seen < n:
        yield _batch([(CYCLE, 0, 0, None, None)])
        return
    degree = _counts(dst, n)
    order = np.lexsort((-degree, level))
    number = np.empty(n, "int64")
    number[order] = np.arange(n)
    key = np.empty(len(src), "int64")
    for lo in range(0, len(key), EDGE_CHUNK):
        key[lo:lo + EDGE_CHUNK] = (number[dst[lo:lo + EDGE_CHUNK]] << 32) | number[src[lo:lo + EDGE_CHUNK]]
    del src, dst
    _, parents = _in_order(key)
    del key
    own = np.isin(ids, vertices, assume_unique=True)
    for kind, x in ((IDS, ids), (OWN, own), (LEVEL, level), (DEGREE, degree)):
        yield from _chunks(kind, x[order])
    yield from _chunks(PARENTS, parents, EDGE_CHUNK)


# -- closing -----------------------------------------------------------------------------------------------------------


class Numbered:
    """The graph in a task."""

    def __init__(self, batches):
        import numpy as np

        held, self.values, tasks = {}, {}, [0]  # not the partition's number, which a union shifts
        for kind, at, n, a, b in _rows(batches, tasks.append):
            if VALUE <= kind < SUM:
                self.values.setdefault(kind, []).append((n, a, b))
            else:
                held.setdefault(kind, []).append((at, n, a))

        self.task = tasks[-1]

        def whole(kind, dtype):
            rows = sorted(held.pop(kind, []))
            out = np.empty(sum(n for _, n, _ in rows), dtype)
            for at, n, a in rows:
                out[at:at + n] = _from_planes(a, n)
            return out

        self.ids, self.own, self.level = whole(IDS, "int64"), whole(OWN, "bool"), whole(LEVEL, "int32")
        self.at = np.concatenate([[0], np.cumsum(whole(DEGREE, "int64"))])
        self.parents, self.card, self.pid = whole(PARENTS, "int32"), whole(CARD, "int64"), whole(PID, "int32")
        self.n = len(self.ids)
        self.cuts = np.concatenate([[0], np.cumsum(np.bincount(self.level))]) if self.n else np.zeros(1, "int64")
        self.words = max(1, min(WORDS, MASK_BYTES // (8 * max(self.n, 1)), -(-self.n // 64)))

    def numbers(self) -> list:
        """The values that came along, an array by number for each."""
        import numpy as np

        by_id = np.argsort(self.ids)
        out = []
        for _, rows in sorted(self.values.items()):
            ids, values = (np.concatenate([_from_planes(r[i], r[0]) for r in rows]) for i in (1, 2))
            ids, (values,) = by_vertex(ids, [values])
            out.append(np.zeros(self.n, "int64"))
            out[-1][by_id[np.searchsorted(self.ids, ids, sorter=by_id)]] = values
        return out

    def stretches(self, tasks: int):
        """(first, bits) of every tasks-th stretch of members, from this task's on."""
        width = self.words * 64
        for first in range(self.task * width, self.n, tasks * width):
            yield first, min(width, self.n - first)

    def closed(self, first: int, bits: int):
        """(lo, hi, masks, flag): numbers from lo to hi have their rows of bits over the members from first on, themselves among
        them. A row is only written where its flag isn't EMPTY; masks and flag hold all earlier numbers too."""
        import numpy as np

        if not hasattr(self, "masks"):
            self.masks, self.flag = np.empty((self.n, self.words), "uint64"), np.empty(self.n, "uint8")
        masks, flag = self.masks, self.flag
        flag[:] = EMPTY
        every = np.packbits(np.arange(self.words * 64) < bits, bitorder="little").view("uint64")
        start = int(self.level[first])
        for level in range(start, len(self.cuts) - 1):
            for lo in range(max(int(self.cuts[level]), first), int(self.cuts[level + 1]), ROWS):
                hi = min(lo + ROWS, int(self.cuts[level + 1]))
                if level > start:
                    self._union(lo, hi, masks, flag, every)
                if lo < first + bits:
                    own = np.arange(lo, min(hi, first + bits))
                    masks[own[flag[own] == EMPTY]] = 0
                    masks[own, (own - first) // 64] |= np.uint64(1) << ((own - first) % 64).astype("uint64")
                    flag[own] = SOME
                yield lo, hi, masks, flag

    def _union(self, lo: int, hi: int, masks, flag, every) -> None:
        """Rows of some vertices of a level from their parents'. Those with a full parent are full, empty parents give nothing."""
        import numpy as np

        e0 = self.at[lo]
        parents, heads = self.parents[e0:self.at[hi]], self.at[lo:hi] - e0
        f = flag.take(parents)
        top = np.maximum.reduceat(f, heads)
        flag[lo:hi] = top
        full = np.flatnonzero(top == FULL)
        if len(full):
            masks[lo + full] = every
        some = np.flatnonzero(top == SOME)
        if not len(some):
            return
        live = f == SOME
        if len(full):
            live &= np.repeat(top == SOME, np.diff(np.append(heads, len(parents))))
        many = np.add.reduceat(live, heads, dtype="int64")[some]
        who = parents if live.all() else parents[live]
        starts = np.cumsum(many) - many
        order = np.argsort(-many, kind="stable")
        many, starts = many[order], starts[order]
        left = np.searchsorted(-many, -np.arange(1, min(int(many[0]), SINGLY) + 1), "right")  # rows with so many parents
        got = masks.take(who[starts], axis=0)
        more = np.empty_like(got)
        for k, m in enumerate(left.tolist()[1:], 1):
            np.take(masks, who[starts[:m] + k], axis=0, out=more[:m], mode="clip")
            got[:m] |= more[:m]
        for i in np.flatnonzero(many > SINGLY).tolist():
            for at in range(starts[i] + SINGLY, starts[i] + many[i], ROWS):
                got[i] |= np.bitwise_or.reduce(masks[who[at:min(at + ROWS, starts[i] + many[i])]], axis=0)
        rows = lo + some[order]
        masks[rows] = got
        flag[rows[(got == every).all(axis=1)]] = FULL

    def deltas(self, first: int, bits: int):
        """(heirs, rows of bits): what is in their windows, and neither they themselves nor in their closest parents' windows."""
        import numpy as np

        for lo, hi, masks, flag in self.closed(first, bits):
            p = self.pid[lo:hi]
            over = flag.take(p, mode="clip")
            heirs = np.flatnonzero((p >= 0) & (flag[lo:hi] != EMPTY) & (over != FULL))
            if not len(heirs):
                continue
            theirs = masks.take(p[heirs], axis=0)
            theirs[over[heirs] == EMPTY] = 0
            mine = masks[lo + heirs] & ~theirs
            heirs += lo
            own = np.flatnonzero(heirs < first + bits)
            mine[own, (heirs[own] - first) // 64] &= ~(np.uint64(1) << ((heirs[own] - first) % 64).astype("uint64"))
            yield heirs, mine

    def windows(self, first: int, bits: int):
        """(owners, rows of bits) of windows with their owners; (owners, None) where they hold the whole stretch."""
        import numpy as np

        for lo, hi, masks, flag in self.closed(first, bits):
            f = flag[lo:hi]
            full, some = lo + np.flatnonzero(f == FULL), lo + np.flatnonzero(f == SOME)
            if len(full):
                yield full, None
            if len(some):
                yield some, masks[some]


def _tables(values, first: int, bits: int, words: int):
    """For each byte of a row of bits the sums of the members' values by the byte's 256 values, one after the other."""
    import numpy as np

    held = np.zeros(words * 64, "int64")
    held[:bits] = values[first:first + bits]
    out = np.zeros((words * 8, 256), "int64")
    for bit in range(8):
        out[:, 1 << bit:2 << bit] = out[:, :1 << bit] + held[bit::8, None]
    return out.reshape(-1)


def _add(into, rows, masks, tables) -> None:
    """The sums of the members of each row of bits are added to into, an array for each of tables."""
    import numpy as np

    flat = masks.view("uint8").reshape(-1)
    at = np.flatnonzero(flat)
    width = masks.shape[1] * 8
    row = at // width
    place = (at - row * width) * 256 + flat[at]
    heads = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]])) if len(row) else row
    for x, t in zip(into, tables, strict=True):
        if len(row):
            x[rows[row[heads]]] += np.add.reduceat(t[place], heads)


def _ones(masks):
    import numpy as np

    return np.bitwise_count(masks).sum(axis=1, dtype="int64")


def _close(what: int, tasks: int, include_self: bool = True):
    """A task's share of: CARD, window sizes with the owner; SUM, sums of windows; COUNT, sizes of deltas, and sums of them with
    the vertex itself."""

    def run(batches):
        import numpy as np

        g = Numbered(batches)
        count, values = np.zeros(g.n, "int64"), g.numbers()
        sums = [np.zeros(g.n, "int64") for _ in values]
        for first, bits in g.stretches(tasks):
            tables = [_tables(v, first, bits, g.words) for v in values]
            if what == COUNT:
                for s, v in zip(sums, values, strict=True):
                    s[first:first + bits] += v[first:first + bits]
                for heirs, masks in g.deltas(first, bits):
                    count[heirs] += _ones(masks)
                    _add(sums, heirs, masks, tables)
                continue
            for owners, masks in g.windows(first, bits):
                if what == CARD:
                    count[owners] += bits if masks is None else _ones(masks)
                elif masks is None:
                    for s, v in zip(sums, values, strict=True):
                        s[owners] += v[first:first + bits].sum()
                else:
                    _add(sums, owners, masks, tables)
            if not include_self:
                for s, v in zip(sums, values, strict=True):
                    s[first:first + bits] -= v[first:first + bits]
        if what != SUM:
            yield from _chunks(what, count)
        for i, s in enumerate(sums):
            yield from _chunks(SUM + i, s)

    return run


def _bits(masks):
    """(row, place) of all set bits."""
    import numpy as np

    return np.nonzero(np.unpackbits(masks.view("uint8").reshape(len(masks), -1), axis=1, bitorder="little").view(bool))


def _delta_rows(tasks: int):
    def run(batches):
        import pyarrow as pa

        g = Numbered(batches)
        for first, bits in g.stretches(tasks):
            for heirs, masks in g.deltas(first, bits):
                for lo in range(0, len(heirs), 256):
                    r, c = _bits(masks[lo:lo + 256])
                    if len(r):
                        yield pa.RecordBatch.from_arrays([pa.array(g.ids[heirs[lo + r]]), pa.array(g.ids[c + first])], names=["v", "member"])

    return run


def _choose(radix: int):
    """The closest parents by the sizes, -1 for none, and the places up the parent paths for each round of jumps."""

    def run(batches):
        import numpy as np

        g = Numbered(batches)
        pid = np.full(g.n, -1)
        for lo in range(int(g.cuts[1]) if g.n else 0, g.n, 1 << 18):
            hi = min(lo + (1 << 18), g.n)
            who, deg = g.parents[g.at[lo]:g.at[hi]], np.diff(g.at[lo:hi + 1])
            card = np.where(g.own[who], g.card[who], 0)
            heads = g.at[lo:hi] - g.at[lo]
            most = np.maximum.reduceat(card, heads)
            best = card == np.repeat(most, deg)
            least = np.minimum.reduceat(np.where(best, g.ids[who], np.iinfo("int64").max), heads)
            at = np.flatnonzero(best & (g.ids[who] == np.repeat(least, deg)))  # one an owner
            pid[lo:hi] = np.where((most > 0) & g.own[lo:hi], who[at], -1)
        yield from _chunks(PID, pid)
        step, far = pid, JUMP
        while (step >= 0).any():
            at = step
            for _ in range(1, radix):
                yield from _chunks(far, at)
                at, far = np.where(at >= 0, step[at], -1), far + 1
            step = at

    return run


def _added(batches):
    """Packed rows of one kind and place added up."""
    held = {}
    for kind, at, n, a, _ in _rows(batches):
        x = _from_planes(a, n)
        if (kind, at) in held:
            held[kind, at] += x
        else:
            held[kind, at] = x
    for (kind, at), x in held.items():
        yield _batch([(kind, at, len(x), _planes(x), None)])


def _unpacked(kinds: list[int]):
    """A row for every vertex of the graph: its id, then the kinds."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        held = {}
        for kind, at, n, a, _ in _rows(batches):
            held.setdefault(at, {})[kind] = _from_planes(a, n)
        for x in held.values():
            own = x[OWN].astype(bool)
            yield pa.RecordBatch.from_arrays([pa.array(c[own]) for c in (x[IDS], *(x[k] if k in x else np.zeros(len(own), "int64") for k in kinds))], names=["v", *[f"c{i}" for i in range(len(kinds))]])

    return run


def _jump_rows(batches):
    """(kind, v, to): closest parents and jumps as ids, of a task that holds all ids."""
    import numpy as np
    import pyarrow as pa

    ids, held = [], []
    for kind, at, n, a, _ in _rows(batches):
        if kind == IDS:
            ids.append((at, _from_planes(a, n)))
        else:
            held.append((kind, at, n, a))
    ids = np.concatenate([x for _, x in sorted(ids, key=lambda x: x[0])]) if ids else np.zeros(0, "int64")
    for kind, at, n, a in held:
        to = _from_planes(a, n)
        on = np.flatnonzero(to >= 0)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(on), kind, "int32")), pa.array(ids[at + on]), pa.array(ids[to[on]])], names=["kind", "v", "to"])


@dataclass
class Whole:
    rows: DataFrame  # PACKED: the numbered graph; written
    spark: object
    n: int
    chosen: DataFrame | None = None  # PACKED: the closest parents and jumps; written

    @property
    def tasks(self) -> int:
        return max(1, min(TASKS, -(-self.n // 64)))

    def _told(self, run, schema: str, tasks: int, *more: DataFrame) -> DataFrame:
        """run over the graph and more, whole in each of the tasks."""
        told = self.rows
        for df in more:
            told = told.union(df)
        return self.spark.range(0, tasks, 1, tasks).join(F.broadcast(told)).select(F.col("id").alias("task"), *told.columns).mapInArrow(run, schema)

    def _summed(self, run, *more: DataFrame) -> DataFrame:
        """The shares of all tasks, added up; written."""
        chunks = -(-self.n // CHUNK)
        shares = self._told(run, PACKED, self.tasks, *more)
        return materialize(shares.repartitionById(max(1, min(self.tasks, chunks)), (F.floor(F.col("at") / CHUNK) % max(1, min(self.tasks, chunks))).cast("int")).mapInArrow(_added, PACKED), "shares")

    def _by_vertex(self, kinds: list[int], *more: DataFrame) -> DataFrame:
        """(v, c0, ...): the kinds of every vertex."""
        told = self.rows.where(F.col("kind").isin([IDS, OWN, LEVEL]))
        for df in more:
            told = told.union(df)
        chunks = max(1, min(self.tasks, -(-self.n // CHUNK)))
        return told.repartitionById(chunks, (F.floor(F.col("at") / CHUNK) % chunks).cast("int")).mapInArrow(_unpacked(kinds), ", ".join(["v long", *[f"c{i} long" for i in range(len(kinds))]]))

    def values(self, values: DataFrame) -> tuple[list[str], list[DataFrame]]:
        """Whole numbers (id, ...) of the vertices, packed."""
        names, values = [c for c in values.columns if c != "id"], values.where("id IS NOT NULL")
        sent = [values.select(F.lit(0).alias("target"), F.col("id").alias("owner"), F.col(c).alias("value")).mapInArrow(_pack(VALUE + i), "target int, kind int, n int, owners binary, values binary") for i, c in enumerate(names)]
        return names, [x.select("kind", F.lit(0).alias("at"), "n", F.col("owners").alias("a"), F.col("values").alias("b")) for x in sent]

    def window_sums(self, values: DataFrame, include_self: bool = True) -> DataFrame:
        """(id, ...): the sums of every window, each by its own."""
        names, sent = self.values(values)
        got = self._summed(_close(SUM, self.tasks, include_self), *sent)
        out = self._by_vertex([SUM + i for i in range(len(names))], got)
        return out.toDF("id", *names)

    def index(self, radix: int) -> tuple[DataFrame, list[DataFrame]]:
        """(v, pid, level, card) and the jumps of the parent-delta index; written. Its deltas are formed when they are read."""
        cards = self._summed(_close(CARD, self.tasks))
        self.chosen = materialize(self._told(_choose(radix), PACKED, 1, cards), "chosen")
        told = self.rows.where(F.col("kind") == IDS).union(self.chosen)
        up = materialize(self.spark.range(0, 1, 1, 1).join(F.broadcast(told)).select(*told.columns).mapInArrow(_jump_rows, "kind int, v long, to long"), "jumps")
        base = self._by_vertex([LEVEL, CARD], cards).select("v", F.col("c0").cast("int").alias("level"), F.col("c1").alias("card"))
        parent = materialize(base.join(up.where(F.col("kind") == PID).select("v", F.col("to").alias("pid")), "v", "left").select("v", "pid", "level", "card"), "pd_parent")
        discard(cards)
        own, rounds = parent.select("v", F.col("v").alias("p")), ((up.agg(F.max("kind")).first()[0] or 0) - JUMP) // (radix - 1) + 1
        return parent, [own.union(up.where(F.floor((F.col("kind") - JUMP) / (radix - 1)) == k).where(F.col("kind") >= JUMP).select("v", F.col("to").alias("p"))) for k in range(rounds)]

    def _pids(self) -> DataFrame:
        return self.chosen.where(F.col("kind") == PID)

    def delta_rows(self) -> DataFrame:
        """(v, member), not written."""
        return self._told(_delta_rows(self.tasks), "v long, member long", self.tasks, self._pids())

    def delta_sums(self, values: DataFrame | None = None) -> DataFrame:
        """(v, n, ...): the size of every vertex's delta, and the sums over it and the vertex itself."""
        names, sent = self.values(values) if values is not None else ([], [])
        got = self._summed(_close(COUNT, self.tasks), self._pids(), *sent)
        return self._by_vertex([COUNT, *[SUM + i for i in range(len(names))]], got).toDF("v", "n", *names)


def whole(graph: PropertyGraph, largest: tuple[int, int] = (VERTICES, EDGES)) -> Whole | None:
    """The graph, numbered, or None if it is too large for a task. Raises CycleError."""
    packed = "target int, kind int, n int, owners binary, values binary"
    e = graph.repeated if graph.directed and graph.repeated is not None else graph.edges
    v = graph.vertices.where("id IS NOT NULL").select(F.lit(0).alias("target"), F.col("id").alias("owner"), F.col("id").alias("value")).mapInArrow(_pack(IDS), packed)
    e = e.where("src IS NOT NULL AND dst IS NOT NULL").select(F.lit(0).alias("target"), F.col("src").alias("owner"), F.col("dst").alias("value")).mapInArrow(_pack(PARENTS), packed)
    sent = materialize(v.union(e), "sent", "uncompressed")
    sizes = {r["kind"]: r["n"] for r in sent.groupBy("kind").agg(F.sum("n").alias("n")).collect()}
    if sizes.get(IDS, 0) > largest[0] or sizes.get(PARENTS, 0) > largest[1]:
        discard(sent)
        return None
    rows = materialize(sent.repartitionById(1, F.lit(0)).mapInArrow(_numbered, PACKED), "numbered", "uncompressed")
    discard(sent)
    if not rows.where(F.col("kind") == CYCLE).isEmpty():
        raise CycleError("the graph has a cycle")
    n = rows.where(F.col("kind") == IDS).agg(F.sum("n")).first()[0] or 0
    return Whole(rows, rows.sparkSession, n)
