"""Sum-of-squares packing of documents into sequences of a fixed capacity.

The rule: a piece goes where the sum, over gaps, of the squared number of open bins with that gap becomes smallest; a
bin that is full leaves the sum. Pieces of equal length are interchangeable, so the rule runs over the histogram of
lengths (at most `capacity` numbers) and not over the pieces. The pieces of a length are placed in at most `BLOCKS` blocks
of equal size, each by the rule for the block as a whole (n pieces turn n bins of one gap into n bins of another), and all
open bins stay open to every later block. So the driver's work is bounded by lengths x BLOCKS whatever the corpus, and up
to BLOCKS pieces of a length the rule is the sequential one, piece by piece. Long pieces go first, longest first; the
short ones follow interleaved, each length spread evenly, as the rule is made for mixed arrivals; of a few borders between
long and short (`SHORT`) the one with the fewest bins stays. Pieces then find their place by their number among the pieces
of their length.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphwin.functions.ranks import LOCAL, PART, PartitionRanker, partition_offsets, with_global_rank
from graphwin.llm.tokens import encoder, small_batches
from graphwin.session import materialize

#: Blocks that the pieces of one length are placed in.
BLOCKS = 64
#: Pieces below this share of the capacity are short; each share is an order, and the one that needs fewest bins is taken.
SHORT = (1 / 8, 1 / 4, 1.0)
END_ID = 0


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces; only the first of several may be shorter than the capacity."""
    if n <= capacity:
        return [(0, n)]
    first = n % capacity or capacity
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


def arrivals(histogram: dict[int, int], capacity: int, short: float, blocks: int = BLOCKS) -> list[tuple[int, int]]:
    """(length, pieces) in the order of placing, over the lengths below the capacity."""
    longs, shorts = [], []
    for length in sorted((n for n, c in histogram.items() if n < capacity and c), reverse=True):
        count = histogram[length]
        parts = min(count, blocks)
        sizes = [count * (k + 1) // parts - count * k // parts for k in range(parts)]
        if length >= capacity * short:
            longs += [(length, n) for n in sizes]
        else:
            shorts += [((k + 0.5) / parts, -length, n) for k, n in enumerate(sizes)]
    return longs + [(-neg, n) for _, neg, n in sorted(shorts)]


def sum_of_squares(order: list[tuple[int, int]], capacity: int) -> tuple[list[tuple[int, int, int, int]], int]:
    """Slots (length, first bin, offset, bins) of the blocks, and the number of bins. A block for which the chosen gap has
    too few bins fills those and goes on with what is left of it."""
    bins = np.zeros(capacity + 1)  # open bins by gap
    runs: list[list[tuple[int, int]]] = [[] for _ in range(capacity + 1)]  # (first bin, bins) of each gap
    slots, made = [], 0
    for length, left in order:
        from_gap, to_gap = bins[length:capacity], bins[: capacity - length]
        while left:
            gap, n = capacity, left
            if from_gap.size and from_gap.any():
                n_at = np.minimum(from_gap, left)
                # what n bins that change their gap add to the sum, for each bin; full bins aren't counted
                change = np.where(from_gap > 0, 2 * (to_gap - from_gap) + 2 * n_at, np.inf)
                if from_gap[0]:
                    change[0] = n_at[0] - 2 * from_gap[0]
                at = int(change.argmin())
                if change[at] <= 2 * bins[capacity - length] + n_at[at]:
                    gap, n = length + at, int(n_at[at])
            left -= n
            rest = gap - length
            if gap == capacity:
                taken, made = [(made, n)], made + n
            else:
                bins[gap] -= n
                taken = []
                while n:
                    first, many = runs[gap].pop()
                    if many > n:
                        runs[gap].append((first + n, many - n))
                    taken.append((first, min(many, n)))
                    n -= min(many, n)
            for first, many in taken:
                slots.append((length, first, capacity - gap, many))
                if rest:
                    bins[rest] += many
                    runs[rest].append((first, many))
    return slots, made


def packing_plan(histogram: dict[int, int], capacity: int, blocks: int = BLOCKS) -> pd.DataFrame:
    """Slots (length, first, sequence_id, offset, times): pieces number first .. first+times-1 of that length stand at
    offset of sequences sequence_id, sequence_id+1, ..."""
    slots, made = min((sum_of_squares(arrivals(histogram, capacity, short, blocks), capacity) for short in SHORT), key=lambda p: p[1])
    if full := histogram.get(capacity, 0):
        slots.append((capacity, made, 0, full))
    plan = pd.DataFrame(slots, columns=["length", "sequence_id", "offset", "times"]).astype("int64").sort_values(["length", "sequence_id"], kind="stable")
    plan["first"] = plan.groupby("length")["times"].cumsum() - plan["times"]
    return plan.reset_index(drop=True)[["length", "first", "sequence_id", "offset", "times"]]


def pieces(docs: DataFrame, capacity: int = 2048, id_col: str = "doc_id", text_col: str = "text", ranks_path: str | None = None, keep_ids: bool = True) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 and, if asked for, ids (binary, little-endian unsigned 32-bit) of every
    piece of every document, with the numbers that pack() needs. Null text is empty: one piece with the end id alone."""
    small_batches(docs)
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    fields = [("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())]
    fields += [("ids", pa.binary())] * keep_ids + [(PART, pa.int32()), (LOCAL, pa.int64())]
    schema = pa.schema(fields)

    def run(batches):
        enc, ranker = encoder(ranks_path), PartitionRanker()
        end = np.array([END_ID], "<u4").tobytes()
        for b in batches:
            rows: list[list] = [[] for _ in range(6)]
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                ids = enc.ids(text or "") + end
                for k, (start, length) in enumerate(cut(len(ids) // 4, capacity)):
                    part = ids[4 * start : 4 * (start + length)]
                    for col, v in zip(rows, (doc, k, start, length, zlib.crc32(part), part if keep_ids else None), strict=True):
                        col.append(v)
            local = ranker.number(pd.Series(rows[3], dtype="int64"))
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip([*rows[: 5 + keep_ids], [ranker.part] * len(local), local.to_list()], schema, strict=True)], schema=schema)

    kinds = {pa.int64(): "long", pa.int32(): "int", pa.binary(): "binary"}
    return docs.mapInArrow(run, ", ".join(f"{f.name} {kinds[f.type]}" for f in schema))


def pack(stored_pieces: DataFrame, capacity: int = 2048) -> DataFrame:
    """Adds sequence_id and offset to a written table of pieces(). Every sequence is gapless from 0."""
    offsets = partition_offsets(stored_pieces, "length")
    histogram = {int(r["length"]): int(r["n"]) for r in stored_pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most capacity rows
    plan = packing_plan(histogram, capacity)
    shift = 1 << 40
    shared = stored_pieces.sparkSession.sparkContext.broadcast((plan["length"].to_numpy() * shift + plan["first"].to_numpy(), plan["first"].to_numpy(), plan["sequence_id"].to_numpy(), plan["offset"].to_numpy()))
    ranked = with_global_rank(stored_pieces, "length", "_rank", offsets)
    names = ranked.columns
    out = T.StructType([f for f in ranked.schema.fields if f.name != "_rank"] + [T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])

    def run(batches):
        keys, first, seq, off = shared.value
        for b in batches:
            rank = b.column(names.index("_rank")).to_numpy()
            at = np.searchsorted(keys, b.column(names.index("length")).to_numpy() * shift + rank, "right") - 1
            cols = [c for c, n in zip(b.columns, names, strict=True) if n != "_rank"]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(seq[at] + rank - first[at]), pa.array(off[at])], names=[f.name for f in out.fields])

    return ranked.mapInArrow(run, out)


def pack_documents(docs: DataFrame, capacity: int = 2048, ranks_path: str | None = None, keep_ids: bool = True, **cols: str) -> DataFrame:
    """Tokenise, cut and pack. Repeated rows and ids are packed like any others; an empty table gives no rows."""
    return pack(materialize(pieces(docs, capacity, ranks_path=ranks_path, keep_ids=keep_ids, **cols), "pieces"), capacity)
