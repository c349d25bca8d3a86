"""Token ids of whole texts, and exact token counts.

The ids equal those of the `tokenizers` library with the 50k byte-level BPE file (tests compare them). A pre-token of
that vocabulary never extends over a space that a non-space character follows, so a text is cut there and each piece
is encoded once per worker and kept in a bounded table. Texts that hold the special token's string, or spaces the cut
does not cover, are encoded without the cut or with wider pieces.
"""

from __future__ import annotations

import base64

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from graphwin.session import materialize

SPECIAL = "<|endoftext|>"
CACHE_ENTRIES = 400_000
#: Rows handed to Python at once: whole texts may be long, so few of them.
BATCH_ROWS = "256"
_encoders: dict[str, "PieceEncoder"] = {}


class _Wide(Exception):
    """A piece begins with white space, so the cut before it isn't a pre-token border."""


class _Table(dict):
    def __init__(self, encode) -> None:
        super().__init__()
        self.encode = encode

    def __missing__(self, piece: str) -> bytes:
        if not piece or piece[0].isspace():
            raise _Wide
        if len(piece) > 200:
            return self.encode(" " + piece)
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        out = self[piece] = self.encode(" " + piece)
        return out


class PieceEncoder:
    """text -> little-endian unsigned 32-bit ids as bytes."""

    def __init__(self, ranks_path: str) -> None:
        import public_tokenizers
        import tiktoken

        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.model = tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={SPECIAL: len(ranks)})
        self.table = _Table(self._plain)
        self.vocabulary = len(ranks) + 1
        self.lengths = np.zeros(self.vocabulary, np.int64)  # bytes of each id
        for piece, i in [*ranks.items(), (SPECIAL.encode(), len(ranks))]:
            self.lengths[i] = len(piece)

    def _plain(self, text: str) -> bytes:
        return np.asarray(self.model.encode_ordinary(text), dtype="<u4").tobytes()

    def ids(self, text: str) -> bytes:
        if SPECIAL in text:
            return np.asarray(self.model.encode(text, allowed_special="all"), dtype="<u4").tobytes()
        pieces = text.split(" ")
        first = pieces.pop(0)
        head = self._plain(first) if first else b""
        try:
            return head + b"".join(map(self.table.__getitem__, pieces)) if first or not pieces else self._spaced(text)
        except _Wide:
            return self._spaced(text)

    def _spaced(self, text: str) -> bytes:
        """Cuts only before a space that a character other than white space follows."""
        out, at, n = [], 0, len(text)
        look = text.find(" ", 1)
        while look != -1:
            if look + 1 < n and not text[look + 1].isspace():
                out.append(self._piece(text[at:look]))
                at = look
            look = text.find(" ", look + 1)
        out.append(self._piece(text[at:]))
        return b"".join(out)

    def _piece(self, piece: str) -> bytes:
        if len(piece) > 1 and piece[0] == " " and not piece[1].isspace():
            return self.table[piece[1:]]
        return self._plain(piece) if piece else b""


def default_ranks() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.tiktoken"))


def encoder(ranks_path: str | None) -> PieceEncoder:
    """One encoder a worker process."""
    key = ranks_path or default_ranks()
    if key not in _encoders:
        _encoders[key] = PieceEncoder(key)
    return _encoders[key]


def small_batches(df: DataFrame) -> None:
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)


def with_token_count(docs: DataFrame, text_col: str = "text", out: str = "n_tokens", ranks_path: str | None = None) -> DataFrame:
    """Adds the encoded length of every whole text (null: 0). Other columns pass through; a column named like out is replaced."""
    small_batches(docs)
    docs = docs.drop(out)
    names = docs.columns

    def run(batches):
        enc = encoder(ranks_path)
        for b in batches:
            n = [len(enc.ids(t)) // 4 if t else 0 for t in b.column(names.index(text_col)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(n, pa.int64())], names=[*names, out])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(out, T.LongType())]))


def length_histogram(lengths: DataFrame, col: str = "n_tokens", block: int = 256) -> DataFrame:
    """Exact histogram of lengths with prefix and suffix sums.

    One row per length that occurs: n_tokens, n_docs, docs_at_least, tokens_at_least (sums over lengths >= it),
    truncated_total (tokens kept if every document is cut there), share_at_most (the quantile that the length is) and
    limit_to (the largest context limit for which docs_at_least, less one row, stays valid: the next length, or null).
    Sums run over blocks of lengths, then over the few block totals: no task holds all lengths. Empty input: no rows.
    """
    hist = materialize(lengths.groupBy(F.col(col).cast("long").alias("n_tokens")).agg(F.count("*").alias("n_docs")), "lengths")  # read twice
    hist = hist.withColumn("_b", F.floor(F.col("n_tokens") / block))
    blocks = hist.groupBy("_b").agg(F.sum("n_docs").alias("_d"), F.sum(F.col("n_docs") * F.col("n_tokens")).alias("_t"), F.min("n_tokens").alias("_first"))
    whole = Window.orderBy(F.desc("_b")).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.orderBy(F.desc("_b")).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    blocks = blocks.select(
        "_b", F.coalesce(F.sum("_d").over(whole), F.lit(0)).alias("_da"), F.coalesce(F.sum("_t").over(whole), F.lit(0)).alias("_ta"),
        F.sum("_d").over(everything).alias("_dall"), F.sum("_t").over(everything).alias("_tall"), F.lag("_first").over(Window.orderBy(F.desc("_b"))).alias("_next"),
    )
    inside = Window.partitionBy("_b").orderBy(F.desc("n_tokens"))
    out = hist.join(blocks, "_b").withColumn("docs_at_least", F.col("_da") + F.sum("n_docs").over(inside)).withColumn("tokens_at_least", F.col("_ta") + F.sum(F.col("n_docs") * F.col("n_tokens")).over(inside))
    return out.select(
        "n_tokens", "n_docs", "docs_at_least", "tokens_at_least",
        (F.col("_tall") - F.col("tokens_at_least") + F.col("n_tokens") * F.col("docs_at_least")).alias("truncated_total"),
        ((F.col("_dall") - F.col("docs_at_least") + F.col("n_docs")) / F.col("_dall")).alias("share_at_most"),
        F.coalesce(F.lag("n_tokens").over(inside), F.col("_next")).alias("limit_to"),
    )


def truncated_total(histogram: DataFrame, limit: int) -> DataFrame:
    """Tokens kept, documents cut and documents kept whole under one context limit."""
    kept = F.least(F.col("n_tokens"), F.lit(limit)) * F.col("n_docs")
    over = F.when(F.col("n_tokens") > limit, F.col("n_docs")).otherwise(0)
    return histogram.agg(F.coalesce(F.sum(kept), F.lit(0)).alias("tokens_kept"), F.coalesce(F.sum(over), F.lit(0)).alias("docs_cut"), F.coalesce(F.sum(F.col("n_docs") - over), F.lit(0)).alias("docs_whole"))


def quantile(histogram: DataFrame, q: float) -> DataFrame:
    """The smallest length that at least a share q of the documents don't exceed."""
    return histogram.where(F.col("share_at_most") >= q).agg(F.min("n_tokens").alias("n_tokens"))
