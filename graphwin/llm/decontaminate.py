"""Benchmark decontamination as a prefix-filtered set join, on built-in functions only.

An item's windows are its runs of `window` words (a shorter item is one window). A window is the set of its positioned
word shingles, and it occurs in a document exactly if all of them do; so one necessary token is enough to find
candidates. Tokens are ordered by how often they occur in the corpus: each window is joined by its rarest shingle only,
bounded by position and length (the window must begin and end inside the document), and the candidate is verified word
by word over a window-sized slice.

How often a shingle occurs has to be counted over all documents, so their shingles meet the whole benchmark vocabulary once;
the rarest-first prefix then decides which occurrences are looked at as candidates. Before anything is exploded, a table of
one byte per slot of hashes (bounded size) drops the shingles that no item has, so a document's cost is linear in its words.

Documents are read once. Each row gets a number when the occurrences are written, so repeated ids and repeated rows stay
apart. A null or empty text has no words and no hits; an item without words has no windows; an empty benchmark leaves
every document clean.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwin.llm.words import alnum_words
from graphwin.session import materialize

WINDOW, SHINGLE = 10, 5
#: The benchmark's distinct shingles are broadcast up to this many (16 bytes each), shuffled beyond.
BROADCAST_SHINGLES = 500_000
#: Slots of the table of known hashes: 2 ** of them at most, at least 16 a shingle while that fits.
MAX_SLOT_BITS = 22


def _hash(words: Column, at: Column, k: int) -> Column:
    """Hash of the k words from 1-based place at."""
    return F.xxhash64(F.lit(k), *[F.element_at(words, at + j) for j in range(k)])


def _shingles(words: Column, k: int) -> Column:
    """(place from 0, hash) of each run of k words."""
    n = F.size(words)
    return F.when(n >= k, F.transform(F.sequence(F.lit(1), n - (k - 1)), lambda i: F.struct((i - 1).alias("p"), _hash(words, i, k).alias("h")))).otherwise(F.array().cast("array<struct<p:int,h:bigint>>"))


def item_windows(benchmark: DataFrame, window: int = WINDOW, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """item_id, win (array of words), one row per distinct window of an item."""
    items = benchmark.select(F.col(id_col).alias("item_id"), alnum_words(F.col(text_col)).alias("_w")).where(F.size("_w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("_w") - (window - 1), F.lit(1)))
    return items.select("item_id", F.explode(starts).alias("_s"), "_w").select("item_id", F.slice("_w", F.col("_s"), F.lit(window)).alias("win")).distinct()


def hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text", keep_row: bool = False) -> DataFrame:
    """One row per document: _row, the id, the whole row as _doc if asked for, n_words, n_hit, n_items, items_sha256, contaminated."""
    windows = item_windows(benchmark, window)
    tokens = windows.select("item_id", "win", F.least(F.size("win"), F.lit(shingle)).alias("k"))
    sizes = sorted(r["k"] for r in tokens.select("k").distinct().collect())  # at most `shingle` numbers
    per_size = [tokens.where(F.col("k") == k).select("item_id", "win", F.explode(_shingles(F.col("win"), k)).alias("t")) for k in sizes]
    if not per_size:
        return _clean(docs, id_col, text_col, keep_row)
    positioned = per_size[0]
    for other in per_size[1:]:
        positioned = positioned.unionByName(other)
    positioned = materialize(positioned.select("item_id", "win", F.col("t.p").alias("off"), F.col("t.h").alias("h")), "benchmark")
    vocabulary = positioned.select("h").distinct()

    n_known = vocabulary.count()
    bits = min(MAX_SLOT_BITS, max(10, (16 * n_known).bit_length()))
    slot = lambda h: F.shiftrightunsigned(h, 64 - bits).cast("int")
    table = bytearray(1 << bits)
    for r in vocabulary.select(slot(F.col("h")).alias("s")).distinct().toLocalIterator():  # at most 2 ** MAX_SLOT_BITS small numbers
        table[r["s"]] = 1
    known = lambda h: F.substring(F.lit(bytes(table)), slot(h) + 1, F.lit(1)) == F.lit(b"\x01")

    # the first entry of every document carries its row and length; it stands for the document and joins with nothing
    words = F.col("_w")
    lead = lambda p: F.greatest(p - (window - 1), F.lit(0))
    numbered = docs.select(F.monotonically_increasing_id().alias("_row"), F.col(id_col).alias("_id"), *[F.struct(*docs.columns).alias("_doc")] * keep_row, alnum_words(F.col(text_col)).alias("_w"))
    held = F.struct("_id", *["_doc"] * keep_row, F.size("_w").alias("n_words"))
    no_near, no_doc = F.lit(None).cast("array<string>"), F.lit(None).cast(numbered.select(held.alias("x")).schema["x"].dataType)
    of_doc = F.array(F.struct(F.lit(-1).alias("p"), F.lit(0).cast("long").alias("h"), no_near.alias("near"), held.alias("held")))
    of_size = [F.transform(F.filter(_shingles(words, k), lambda t: known(t["h"])), lambda t: F.struct(t["p"].alias("p"), t["h"].alias("h"), F.slice(words, lead(t["p"]) + 1, F.lit(2 * window)).alias("near"), no_doc.alias("held"))) for k in sizes]
    found = numbered.select("_row", F.size("_w").alias("n_words"), F.explode(F.concat(of_doc, *of_size)).alias("t"))
    found = found.select("_row", "n_words", F.col("t.p").alias("p"), F.col("t.h").alias("h"), lead(F.col("t.p")).alias("_lead"), F.col("t.near").alias("_near"), F.col("t.held._id").alias("_id"), *[F.col("t.held._doc").alias("_doc")] * keep_row)
    if n_known <= BROADCAST_SHINGLES:
        exact = F.broadcast(vocabulary.select(F.col("h").alias("_known"), F.lit(False).alias("_first")).union(vocabulary.sparkSession.range(1).select(F.lit(0).cast("long"), F.lit(True))))
        stored = materialize(found.join(exact, (F.col("h") == F.col("_known")) & (F.col("_first") == (F.col("p") < 0)), "left_semi"), "occurrences")
    else:  # a benchmark too large to broadcast: what passed the table is shuffled, the documents' own rows are not
        flat = materialize(found, "shingles")
        stored = flat.where("p < 0").unionByName(flat.where("p >= 0").join(vocabulary, "h", "left_semi").select(flat.columns))
    documents, occurrences = stored.where("p < 0"), stored.where("p >= 0")

    rarity = occurrences.groupBy("h").agg(F.count("*").alias("df"))
    ranked = positioned.join(rarity, "h")  # a window with a shingle that occurs nowhere drops out below
    prefix = ranked.groupBy("item_id", "win").agg(F.count("*").alias("_present"), F.min(F.struct("df", "h", "off")).alias("m"))
    prefix = prefix.where(F.col("_present") == F.size("win") - F.least(F.size("win"), F.lit(shingle)) + 1)
    prefix = prefix.groupBy("win").agg(F.first("m").alias("m"), F.sort_array(F.collect_set("item_id")).alias("items")).select("win", F.col("m.h").alias("h"), F.col("m.off").alias("off"), "items")
    start = F.col("p") - F.col("off")
    candidates = occurrences.join(prefix, "h").where((start >= 0) & (start + F.size("win") <= F.col("n_words")))
    verified = candidates.where(F.slice("_near", start - F.col("_lead") + 1, F.size("win")) == F.col("win")).select("_row", start.alias("s"), F.size("win").alias("len"), "items").distinct()
    # of one document: its own windows only
    per_doc = verified.groupBy("_row").agg(F.sort_array(F.collect_list(F.struct("s", "len"))).alias("at"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("items"))
    reach = F.aggregate("at", F.struct(F.lit(0).alias("hit"), F.lit(0).alias("upto")), lambda a, x: F.struct((a["hit"] + F.greatest(x["s"] + x["len"] - F.greatest(a["upto"], x["s"]), F.lit(0))).alias("hit"), F.greatest(a["upto"], x["s"] + x["len"]).alias("upto")))
    names = F.array_sort(F.transform("items", lambda i: i.cast("string")))
    per_doc = per_doc.select("_row", reach["hit"].cast("long").alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.array_join(names, ",").alias("_names"))
    return _report(documents.join(per_doc, "_row", "left"), id_col, keep_row)


def _report(rows: DataFrame, id_col: str, keep_row: bool) -> DataFrame:
    n_hit = F.coalesce("n_hit", F.lit(0).cast("long"))
    return rows.select("_row", F.col("_id").alias(id_col), *["_doc"] * keep_row, F.col("n_words").cast("long").alias("n_words"), n_hit.alias("n_hit"), F.coalesce("n_items", F.lit(0).cast("long")).alias("n_items"), F.sha2(F.coalesce("_names", F.lit("")), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def _clean(docs: DataFrame, id_col: str, text_col: str, keep_row: bool) -> DataFrame:
    none = F.lit(None)
    return _report(docs.select(F.monotonically_increasing_id().alias("_row"), F.col(id_col).alias("_id"), F.struct(*docs.columns).alias("_doc"), F.size(alnum_words(F.col(text_col))).alias("n_words"), none.cast("long").alias("n_hit"), none.cast("long").alias("n_items"), none.cast("string").alias("_names")), id_col, keep_row)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the documents in which a benchmark window occurs; all columns stay."""
    out = hits(docs, benchmark, window, shingle, id_col, text_col, keep_row=True)
    return out.where(~F.col("contaminated")).select("_doc.*")


ORACLE = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
b AS (SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, array_to_string(w[s : s + 9], ' ') AS win, least(len(w), 10) AS k
       FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS s FROM b WHERE len(w) > 0)),
dw AS (SELECT doc_id, k, s, array_to_string(w[s : s + k - 1], ' ') AS win
       FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS s FROM d, (SELECT DISTINCT k FROM bw))),
m AS (SELECT doc_id, item_id, s, bw.k FROM dw JOIN bw ON dw.win = bw.win AND dw.k = bw.k),
h AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + k)) AS p FROM m) GROUP BY doc_id),
i AS (SELECT doc_id, count(*) AS n_items, string_agg(CAST(item_id AS VARCHAR), ',' ORDER BY CAST(item_id AS VARCHAR)) AS names FROM (SELECT DISTINCT doc_id, item_id FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h ON d.doc_id = h.doc_id LEFT JOIN i ON d.doc_id = i.doc_id
"""
