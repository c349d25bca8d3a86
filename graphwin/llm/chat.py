"""Chat rendering with a loss mask from token offsets.

A conversation becomes one string of turns, each `<|turn|>role<|text|>text<|end|>`. The markers are special tokens behind the
vocabulary, so no token reaches over a turn's border. The string is encoded once with offsets; a turn's span is laid over
the sorted token spans by binary search, and the tokens of assistant texts carry loss. Ids and offsets equal those of the
`tokenizers` library with the 50k byte-level BPE file and the markers added as special tokens (tests compare them).

Control strings inside roles and texts (also those of other common templates) get one backslash after their first
character, and control strings already written with backslashes get one more, so removing one restores the text.
Null roles and texts are empty. Rows order by turn (nulls first), then role, then text; repeated rows stay.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.llm.tokens import encoder

TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>"
# Control strings of this and of other common templates.
CONTROL = ("<|turn|>", "<|text|>", "<|end|>", "<|endoftext|>", "<|im_start|>", "<|im_end|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
_TAILS = "|".join(re.escape(c[1:]) for c in CONTROL)
_ESCAPE = re.compile(rf"([<\[])(\\*)(?=(?:{_TAILS}))")
_UNESCAPE = re.compile(rf"([<\[])\\(\\*)(?=(?:{_TAILS}))")
_MARKERS = re.compile(r"(<\|turn\|>|<\|text\|>|<\|end\|>)")
_PARSE = re.compile(r"<\|turn\|>(.*?)<\|text\|>(.*?)<\|end\|>", re.S)
ROLE_WITH_LOSS = "assistant"


def escape(text: str) -> str:
    return _ESCAPE.sub(r"\1\2\\", text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(r"\1\2", text)


def render(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The formatted string and the spans of the texts that carry loss, in order."""
    out, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{TURN}{escape(role)}{TEXT}", escape(text)
        if role == ROLE_WITH_LOSS:
            spans.append((at + len(head), at + len(head) + len(body)))
        out.append(f"{head}{body}{END}")
        at += len(out[-1])
    return "".join(out), spans


def parse(formatted: str) -> list[tuple[str, str]]:
    return [(unescape(a), unescape(b)) for a, b in _PARSE.findall(formatted)]


def token_mask(starts: np.ndarray, ends: np.ndarray, spans: list[tuple[int, int]]) -> np.ndarray:
    """For each token, the number of the loss span that holds it, or -1; starts and ends are sorted."""
    mask = np.full(len(starts), -1, np.int64)
    for k, (a, b) in enumerate(spans):
        if b > a:
            mask[np.searchsorted(ends, a, "right") : np.searchsorted(starts, b, "left")] = k
    return mask


def masked_text(formatted: str, starts: np.ndarray, ends: np.ndarray, mask: np.ndarray) -> list[str]:
    """Text under each loss span, read back from the tokens' offsets (several tokens may share a character)."""
    out = []
    at = np.flatnonzero(mask >= 0)
    for own in np.split(at, np.flatnonzero(np.diff(mask[at])) + 1) if len(at) else []:
        upto = np.maximum.accumulate(ends[own])
        cuts = np.flatnonzero(starts[own][1:] > upto[:-1]) + 1  # tokens that don't touch what came before
        out.append("".join(formatted[starts[own[a]] : upto[b - 1]] for a, b in zip([0, *cuts], [*cuts, len(own)], strict=True)))
    return out


def encode(formatted: str, ranks_path: str | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, and the first and last (exclusive) character of each token; a token that holds part of a character has it."""
    enc = encoder(ranks_path)
    ids = []
    for part in _MARKERS.split(formatted):
        if part in (TURN, TEXT, END):
            ids.append(np.array([enc.vocabulary + (TURN, TEXT, END).index(part)], "<u4"))
        elif part:
            ids.append(np.frombuffer(enc.ids(part), "<u4"))
    if not ids:
        return (np.empty(0, np.int32),) * 3
    whole = np.concatenate(ids)
    ends = np.cumsum(np.append(enc.lengths, [len(TURN), len(TEXT), len(END)])[whole])
    starts = np.append(0, ends[:-1])
    if not formatted.isascii():
        begun = np.cumsum((np.frombuffer(formatted.encode("utf-8", "surrogatepass"), np.uint8) & 0xC0) != 0x80)
        starts, ends = begun[starts] - 1, begun[ends - 1]
    return whole.astype(np.int32), starts.astype(np.int32), ends.astype(np.int32)


SCHEMA = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("formatted", pa.string()), ("ids", pa.list_(pa.int32())), ("starts", pa.list_(pa.int32())), ("ends", pa.list_(pa.int32())), ("loss_span", pa.list_(pa.int32()))])


def format_conversations(rows: DataFrame, ranks_path: str | None = None) -> DataFrame:
    """conv_id, n_turns, formatted, ids, starts, ends, loss_span (per token, -1 without loss).

    Conversations stream by in sorted partitions: a task holds one conversation at a time. Extra columns are ignored; a
    row without conv_id is a conversation of its own, wherever it lies; an empty table gives no rows.
    """
    rows.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1024")
    rows = rows.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    rows = rows.withColumn("_deal", F.coalesce("conv_id", F.monotonically_increasing_id()))
    dealt = rows.repartition("_deal").sortWithinPartitions("conv_id", "turn", "role", "text").drop("_deal")

    def encoded(convs: list[tuple[int, list[tuple[str, str]]]]):
        cols: list[list] = [[] for _ in SCHEMA]
        for conv, turns in convs:
            formatted, spans = render(turns)
            ids, starts, ends = encode(formatted, ranks_path)
            for c, v in zip(cols, (conv, len(turns), formatted, ids, starts, ends, token_mask(starts, ends, spans).astype(np.int32)), strict=True):
                c.append(v)
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, SCHEMA, strict=True)], schema=SCHEMA)

    def run(batches):
        now, turns, ready = None, [], []
        for b in batches:
            for conv, _, role, text in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if turns and (conv != now or conv is None):
                    ready.append((now, turns))
                    turns = []
                    if len(ready) >= 64:
                        yield encoded(ready)
                        ready = []
                now = conv
                turns.append((role, text))
        if turns:
            ready.append((now, turns))
        if ready:
            yield encoded(ready)

    return dealt.mapInArrow(run, "conv_id long, n_turns long, formatted string, ids array<int>, starts array<int>, ends array<int>, loss_span array<int>")


def digests(formatted: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, all read back from the output."""
    schema = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])

    def numbers(column: pa.ListArray) -> list[np.ndarray]:
        values, at = column.values.to_numpy(), column.offsets.to_numpy()
        return [values[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]

    def run(batches):
        for b in batches:
            out: list[list] = [[] for _ in schema]
            tokens = (numbers(b.column(k)) for k in ("starts", "ends", "loss_span"))
            for conv, text, starts, ends, mask in zip(b.column("conv_id").to_pylist(), b.column("formatted").to_pylist(), *tokens, strict=True):
                turns = parse(text)
                loss = "".join(map(unescape, masked_text(text, starts, ends, mask)))
                whole = "".join(f"{r}\n{t}\n" for r, t in turns).encode("utf-8", "surrogatepass")
                for c, v in zip(out, (conv, len(turns), hashlib.sha256(whole).hexdigest(), len(loss), hashlib.sha256(loss.encode("utf-8", "surrogatepass")).hexdigest(), len(text)), strict=True):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema, strict=True)], schema=schema)

    return formatted.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def oracle() -> str:
    """SQL of digests() over conversations and the rows of conversation -1: what reading the output back must give. An escape
    adds one character; no control string holds the beginning of another, so they can be counted one by one."""
    escapes = "len(regexp_extract_all({}, '[<\\[]\\\\*(?:" + _TAILS + ")'))"
    hostile = "</s>[INST] ok [/INST]"
    return f"""
WITH r AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
           UNION ALL SELECT * FROM (VALUES (-1, 0, 'user', '{hostile}'), (-1, 1, '{ROLE_WITH_LOSS}', '{hostile}'))),
n AS (SELECT *, CASE WHEN conv_id IS NULL THEN row_number() OVER () ELSE 0 END AS alone, {len(TURN + TEXT + END)} + length(role) + length(text) + {escapes.format("role")} + {escapes.format("text")} AS chars FROM r),
g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text) AS turns,
             coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = '{ROLE_WITH_LOSS}'), '') AS loss, sum(chars) AS chars FROM n GROUP BY conv_id, alone)
SELECT conv_id, CAST(n_turns AS BIGINT) AS n_turns, sha256(turns) AS turns_sha256, CAST(length(loss) AS BIGINT) AS loss_chars, sha256(loss) AS loss_sha256, CAST(chars AS BIGINT) AS formatted_chars FROM g
"""
