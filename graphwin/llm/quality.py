"""Quality rules with host-level verdicts, on built-in functions only.

Every document is measured by its own rules. Failures are then summed per host, each host's rate is shrunk with a beta
prior fitted to all hosts by moments, and hosts whose shrunk rate stays above a threshold, with enough evidence, are
rejected with all their documents.

Null and empty texts have no words and fail the rules. A null host is a host of its own. Repeated rows count each. Columns
named like a result are replaced; all others pass, whatever their names. An empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwin.session import materialize

SPACE = r"[\x20\x09-\x0D]+"
MIN_WORDS, MAX_REPEATED_PERCENT, WINDOW = 50, 50, 3


@dataclass(frozen=True)
class HostRule:
    """A host falls if its shrunk failure rate, less `deviations` standard deviations of its posterior, exceeds max_rate."""

    max_rate: float = 0.5
    deviations: float = 2.0
    default_strength: float = 10.0


def measured(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed; same-named columns are replaced."""
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    docs = docs.drop(*names)
    rows = docs.select(F.struct(*docs.columns).alias("_doc"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("_text"))
    text = F.col("_text")
    rows = rows.withColumn("_words", F.filter(F.split(text, SPACE), lambda w: w != "")).withColumn("_lines", F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    rows = rows.withColumn("_hash", _window_hashes(F.col("_words")))
    rows = rows.withColumn("_again", F.size("_hash") > F.size(F.array_distinct("_hash")))
    rows = rows.withColumn("_at", F.when(F.col("_again"), F.array_sort(F.transform("_hash", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    rows = rows.withColumn("_at", F.when(F.col("_again"), _repeated_starts(F.col("_at"), F.col("_words"))))
    n_words = F.size("_words").cast("long")
    n_repeat = F.when(F.col("_again"), _covered(F.col("_at"))).otherwise(0).cast("long")
    out = rows.select(
        "_doc", n_words.alias("n_words"), F.coalesce(F.length(F.regexp_replace(text, SPACE, "")), F.lit(0)).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"), n_repeat.alias("n_repeat_words"),
    )
    failed = (F.col("n_words") < MIN_WORDS) | (F.col("n_repeat_words") * 100 > F.col("n_words") * MAX_REPEATED_PERCENT)
    return out.select("_doc.*", *names[:-1], failed.alias("base_failed"))


def _window_hashes(words: Column) -> Column:
    """64-bit hash of each window of three words."""
    n = F.size(words)
    return F.when(n >= WINDOW, F.transform(F.sequence(F.lit(1), n - (WINDOW - 1)), lambda i: F.xxhash64(F.element_at(words, i), F.element_at(words, i + 1), F.element_at(words, i + 2)))).otherwise(F.array().cast("array<bigint>"))


def _repeated_starts(placed: Column, words: Column) -> Column:
    """Sorted numbers of the windows that occur again, from (hash, number) sorted by hash: equal hashes stand next to each
    other, and their words are compared."""

    def same(x: Column, j: Column) -> Column:
        other = F.get(placed, j)
        alike = [F.get(words, x["i"] + k) == F.get(words, other["i"] + k) for k in range(WINDOW)]
        return F.coalesce((x["h"] == other["h"]) & alike[0] & alike[1] & alike[2], F.lit(False))

    return F.array_sort(F.transform(F.filter(placed, lambda x, i: same(x, i - 1) | same(x, i + 1)), lambda x: x["i"]))


def _covered(starts: Column) -> Column:
    """Words in the union of the windows at sorted starts: each adds at most WINDOW, less what the one before covers."""
    gaps = F.transform(starts, lambda s, i: F.least(F.lit(WINDOW), F.coalesce(s - F.get(starts, i - 1), F.lit(WINDOW))))
    return F.aggregate(gaps, F.lit(0), lambda a, g: a + g)


def host_verdicts(failures: DataFrame, host_col: str, rule: HostRule = HostRule()) -> DataFrame:
    """host, n, failed, rate (shrunk), host_rejected from rows (host, base_failed).

    The prior's mean is the mean rate of hosts, its strength follows from the variance beyond sampling noise; a single
    host, or no spread, takes `default_strength`."""
    hosts = failures.groupBy(F.col(host_col).alias("_host")).agg(F.count("*").alias("n"), F.sum(F.col("base_failed").cast("long")).alias("failed"))
    r = F.col("failed") / F.col("n")
    prior = hosts.agg(F.count("*").alias("hosts"), F.avg(r).alias("m"), F.var_samp(r).alias("v"), F.avg(1 / F.col("n")).alias("inv"))
    m = F.coalesce(F.col("m"), F.lit(0.0))
    spread = F.greatest(F.coalesce(F.col("v"), F.lit(0.0)) - m * (1 - m) * F.col("inv"), F.lit(0.0))
    prior = prior.select(m.alias("m"), F.when((spread > 0) & (F.col("hosts") > 1) & (m * (1 - m) / spread > 1), m * (1 - m) / spread - 1).otherwise(rule.default_strength).alias("strength"))
    a, b = F.col("m") * F.col("strength") + F.col("failed"), (1 - F.col("m")) * F.col("strength") + F.col("n") - F.col("failed")
    rate = a / (a + b)
    sd = F.sqrt(rate * (1 - rate) / (a + b + 1))
    # the prior is one row: an aggregate without keys
    return hosts.join(F.broadcast(prior)).select("_host", "n", "failed", rate.alias("host_rate"), (rate - F.lit(rule.deviations) * sd > rule.max_rate).alias("host_rejected"))


def judged(docs: DataFrame, host_col: str = "source", text_col: str = "text", keep_text: bool = True, rule: HostRule = HostRule()) -> DataFrame:
    """docs with the measures, host_rate and kept. Texts are read and measured once, into a written table."""
    flat = measured(docs.drop("host_rate", "host_rejected", "kept"), text_col)
    stored = materialize(flat if keep_text else flat.drop(text_col), "quality")
    hosts = host_verdicts(stored, host_col, rule).select("_host", "host_rate", "host_rejected")
    joined = stored.join(hosts, stored[host_col].eqNullSafe(hosts["_host"]), "left").drop("_host")
    return joined.withColumn("kept", ~F.col("base_failed") & ~F.col("host_rejected")).drop("host_rejected")


def keep_good(docs: DataFrame, host_col: str = "source", text_col: str = "text", rule: HostRule = HostRule()) -> DataFrame:
    """The documents that both their own rules and their host pass, with the columns of docs.

    Texts that fail are not written: of them only the host and the failure go into the host's rate."""
    rows = docs.select(F.struct(*docs.columns).alias("_doc"), F.col(host_col).alias("_host_in"), F.col(text_col).cast("string").alias("_text"))
    flat = measured(rows, "_text").select("_host_in", "base_failed", F.when(~F.col("base_failed"), F.col("_doc")).alias("_doc"))
    stored = materialize(flat, "quality")
    hosts = host_verdicts(stored, "_host_in", rule).where("host_rejected").select("_host")
    passed = stored.where(~F.col("base_failed"))
    return passed.join(hosts, passed["_host_in"].eqNullSafe(hosts["_host"]), "left_anti").select("_doc.*")


ORACLE = r"""
WITH t AS (SELECT doc_id, source, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, source, text, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM t),
g AS (SELECT *, [words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] FOR i IN range(1, len(words) - 1)] AS grams FROM w),
r AS (SELECT doc_id, count(*) AS n FROM (
        SELECT DISTINCT doc_id, p + k AS at FROM (
          SELECT doc_id, p, count(*) OVER (PARTITION BY doc_id, gram) AS c FROM (
            SELECT doc_id, unnest(grams) AS gram, unnest(range(1, len(grams) + 1)) AS p FROM g)), range(0, 3) AS o(k)
        WHERE c > 1) GROUP BY doc_id),
b AS (SELECT g.doc_id, source, CAST(len(words) AS BIGINT) AS n_words,
             CAST(length(array_to_string(words, '')) AS BIGINT) AS word_chars,
             CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
             CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
             CAST(coalesce(r.n, 0) AS BIGINT) AS n_repeat_words
      FROM g LEFT JOIN r ON g.doc_id = r.doc_id),
f AS (SELECT *, (n_words < 50 OR n_repeat_words * 100 > n_words * 50) AS base_failed FROM b),
h AS (SELECT source, count(*) AS n, sum(CASE WHEN base_failed THEN 1 ELSE 0 END) AS failed FROM f GROUP BY source),
q AS (SELECT count(*) AS hosts, avg(failed / n) AS m,
             greatest(coalesce(var_samp(failed / n), 0) - avg(failed / n) * (1 - avg(failed / n)) * avg(1.0 / n), 0) AS spread FROM h),
p AS (SELECT m, CASE WHEN spread > 0 AND hosts > 1 AND m * (1 - m) / nullif(spread, 0) > 1 THEN m * (1 - m) / spread - 1 ELSE 10.0 END AS strength FROM q),
v AS (SELECT source, m * strength + failed AS a, (1 - m) * strength + n - failed AS b FROM h, p),
u AS (SELECT source, (a / (a + b) - 2.0 * sqrt(a / (a + b) * (1 - a / (a + b)) / (a + b + 1)) > 0.5) AS host_rejected FROM v)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND NOT host_rejected) AS kept
FROM f LEFT JOIN u ON f.source IS NOT DISTINCT FROM u.source
"""
