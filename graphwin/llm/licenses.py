"""Licence scan by a positional rare-token index, on built-in functions only.

Documents are read once: of each, the places of words that occur in licence templates are written (common function words
left out). Document frequencies of those words over the whole table give their IDF. A template is looked up in the documents
that hold its highest-IDF key word; all its postings there that agree on the relative position (place in the document
less place in the template) are counted, and the template is named if enough words agree and each of its mandatory key
phrases stands at its place. Other text in the document takes nothing away. The score is the share of a template's
words, up to `TOP` of them, at its best place.

Base phrases are looked for beside it, at every place where their words stand consecutively. Null and empty texts have
no words, no labels and score 0. Repeated rows are judged each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwin.llm.words import LOWER, UPPER, alnum_words
from graphwin.session import materialize

# Base phrases and their labels.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
# Wording of well-known licence notices; (label, wording, mandatory key phrases inside it).
TEMPLATES = (
    ("agpl-3.0", "licensed under the gnu affero general public license version 3", ("gnu affero general public license",)),
    ("apache-2.0", "licensed under the apache license version 2 0", ("apache license version 2 0",)),
    ("apache-notice", "you may not use this file except in compliance with the license", ("use", "file except")),
    ("artistic-2.0", "licensed under the artistic license 2 0", ("artistic license 2 0",)),
    ("boost-1.0", "boost software license version 1 0", ("boost software license version 1 0",)),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ("binary forms", "modification")),
    ("cc-by-4.0", "licensed under cc by 4 0", ("cc by 4 0",)),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0", ("cc by nc 4 0",)),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0", ("cc by sa 4 0",)),
    ("cc-by-4.0", "licensed under the creative commons attribution 4 0 international license", ("creative commons attribution 4 0",)),
    ("cc0-1.0", "to the extent possible under law the author has waived all copyright and related or neighboring rights", ("extent possible under law", "waived", "copyright")),
    ("epl-2.0", "made available under the terms of the eclipse public license 2 0", ("eclipse public license 2 0",)),
    ("gpl-2.0", "licensed under the gnu general public license version 2", ("gnu general public license version 2",)),
    ("gpl-3.0", "licensed under the gnu general public license version 3", ("gnu general public license version 3",)),
    ("gpl-notice", "redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", ("gnu general public license", "free software foundation")),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ("copy modify", "hereby granted")),
    ("lgpl", "licensed under the gnu lesser general public license", ("gnu lesser general public license",)),
    ("mit-notice", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ("hereby granted free", "associated documentation files")),
    ("mit-name", "released under the mit license", ("mit license",)),
    ("mpl-2.0", "subject to the terms of the mozilla public license v 2 0", ("mozilla public license v 2 0",)),
    ("unlicense", "this is free and unencumbered software released into the public domain", ("unencumbered software released",)),
    ("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages", ("implied warranty", "held liable")),
)
# Function words that carry no evidence.
COMMON = frozenset("a all and any are as be for has in is it into may no not of or the this to will with without you".split())
TOP = 8
MIN_AGREEING = 3


def _postings() -> list[tuple[int, str, int]]:
    """(template, word, place) of the words that carry evidence."""
    return [(k, w, p) for k, (_, text, _) in enumerate(TEMPLATES) for p, w in enumerate(text.split()) if w not in COMMON]


def _keys() -> list[tuple[int, str, int]]:
    """(template, word, place) that must all be there; key phrases hold no common words."""
    out = []
    for k, (_, text, phrases) in enumerate(TEMPLATES):
        words = text.split()
        for phrase in phrases:
            own = phrase.split()
            at = next(i for i in range(len(words)) if words[i : i + len(own)] == own)
            out += [(k, w, at + j) for j, w in enumerate(own)]
    return sorted(set(out))


def _vocabulary() -> list[str]:
    return sorted({w for _, w, _ in _postings()} | {w for phrase in BASE for w in phrase.split()})


def _phrase_starts(places: Column, phrase: str) -> Column:
    """Places where the words of the phrase follow each other."""
    words = phrase.split()

    def begins(x: Column, j: Column) -> Column:
        ok = x["w"] == words[0]
        for k, w in enumerate(words[1:], 1):
            after = F.get(places, j + k)
            ok = ok & F.coalesce((after["w"] == w) & (after["p"] == x["p"] + k), F.lit(False))
        return ok

    return F.transform(F.filter(places, begins), lambda x: x["p"])


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    spark = docs.sparkSession
    words = docs.select(F.monotonically_increasing_id().alias("_row"), F.col(id_col).alias("_id"), alnum_words(F.col(text_col)).alias("_w"))
    vocabulary = _vocabulary()
    places = F.array_compact(F.transform("_w", lambda w, i: F.when(w.isin(vocabulary), F.struct(i.alias("p"), w.alias("w")))))
    stored = materialize(words.select("_row", "_id", F.size("_w").cast("long").alias("n_words"), places.alias("at")), "licence-words")

    evidence = sorted({w for _, w, _ in _postings()})
    df = stored.where(F.size("at") > 0).select(F.explode(F.array_distinct(F.col("at.w"))).alias("w")).where(F.col("w").isin(evidence)).groupBy("w").agg(F.count("*").alias("df"))
    rarity = {r["w"]: r["df"] for r in df.collect()}  # at most one row per vocabulary word
    # the highest-IDF key word of a template is that with the lowest document frequency; a text without it lacks the template
    rarest = {k: min((rarity.get(w, 0), w) for t, w, _ in _keys() if t == k)[1] for k in range(len(TEMPLATES))}
    near = F.array_compact(F.array(*[F.when(F.array_contains("at.w", w), F.lit(k)) for k, w in rarest.items()]))
    looked_up = stored.where(F.size("at") > 0).select("_row", "at", near.alias("near")).where(F.size("near") > 0).select("_row", "near", F.explode("at").alias("x"))

    distinct = {k: sorted({w for t, w, _ in _postings() if t == k}) for k in range(len(TEMPLATES))}
    keys = set(_keys())
    rows = ", ".join(f"({k}, '{w}', {p}, {1 << distinct[k].index(w)}L, {int((k, w, p) in keys)})" for k, w, p in _postings())
    postings = F.broadcast(spark.sql(f"SELECT * FROM VALUES {rows} AS t(template, w, place, bit, key)"))  # fixed size
    places = looked_up.join(postings, (F.col("x.w") == F.col("w")) & F.array_contains("near", F.col("template")))
    # one word stands at one place, so a key word is counted once a shift; distinct words are bits
    at_shift = places.groupBy("_row", "template", (F.col("x.p") - F.col("place")).alias("shift")).agg(F.bit_count(F.bit_or("bit")).alias("agree"), F.sum("key").alias("present"))
    number = lambda d: F.create_map(*[F.lit(v) for k, n in d.items() for v in (k, n)])[F.col("template")]
    n_words, n_keys = number({k: len(ws) for k, ws in distinct.items()}), number({k: len([1 for t, _, _ in keys if t == k]) for k in range(len(TEMPLATES))})
    verified = at_shift.where((F.col("present") == n_keys) & (F.col("agree") >= F.least(F.lit(MIN_AGREEING), n_words)))
    # of the words that agree at one place, the `TOP` of the highest IDF count
    verified = verified.withColumn("share", F.least(F.col("agree"), F.lit(TOP)) / F.least(F.lit(TOP), n_words))
    label = F.create_map(*[F.lit(v) for k, (name, _, _) in enumerate(TEMPLATES) for v in (k, name)])[F.col("template")]
    named = verified.groupBy("_row").agg(F.collect_set(label).alias("named"), F.max("share").alias("share"))

    starts = {phrase: _phrase_starts(F.col("at"), phrase) for phrase in BASE}
    out = stored.join(named, "_row", "left").select("*", F.sort_array(F.flatten(F.array(*starts.values()))).alias("base"), F.array_compact(F.array(*[F.when(F.size(s) > 0, F.lit(BASE[phrase])) for phrase, s in starts.items()])).alias("own"))
    none = F.array().cast("array<string>")
    return out.select(
        F.col("_id").alias(id_col), "n_words", F.size("base").cast("long").alias("n_base"), F.get("base", F.lit(0)).cast("long").alias("first_word"), F.get("base", F.size("base") - 1).cast("long").alias("last_word"),
        F.array_join(F.array_sort(F.array_distinct("own")), ",").alias("base_labels"), F.array_join(F.array_sort(F.array_union("own", F.coalesce("named", none))), ",").alias("labels"),
        F.greatest(F.when(F.size("base") > 0, F.lit(1.0)).otherwise(0.0), F.least(F.coalesce("share", F.lit(0.0)), F.lit(1.0))).alias("score"),
    )


def _values(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join(f"'{v}'" if isinstance(v, str) else str(v) for v in r) + ")" for r in rows)


def oracle() -> str:
    phrases = [(label, phrase, len(phrase.split())) for phrase, label in BASE.items()]
    return rf"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS ws FROM documents),
post(template, w, place) AS (VALUES {_values(_postings())}),
keys(template, w, place) AS (VALUES {_values(_keys())}),
names(template, label) AS (VALUES {_values([(k, t[0]) for k, t in enumerate(TEMPLATES)])}),
phrases(label, phrase, n) AS (VALUES {_values(phrases)}),
o AS (SELECT doc_id, unnest(ws) AS w, unnest(range(0, len(ws))) AS p FROM d),
b AS (SELECT d.doc_id, label, s - 1 AS p FROM (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS s FROM d) AS d, phrases WHERE array_to_string(ws[s : s + n - 1], ' ') = phrase),
a AS (SELECT doc_id, template, p - place AS shift, count(DISTINCT w) AS agree FROM o JOIN post USING (w) GROUP BY ALL),
sizes AS (SELECT template, count(DISTINCT w) AS n FROM post GROUP BY template),
k AS (SELECT doc_id, template, shift FROM (SELECT DISTINCT doc_id, template, p - place AS shift, place FROM o JOIN keys USING (w))
      JOIN (SELECT template, count(*) AS need FROM keys GROUP BY template) USING (template) GROUP BY doc_id, template, shift HAVING count(*) = any_value(need)),
v AS (SELECT doc_id, label, least(agree, {TOP}) / least({TOP}, n) AS share FROM a JOIN k USING (doc_id, template, shift) JOIN sizes USING (template) JOIN names USING (template) WHERE agree >= least({MIN_AGREEING}, n)),
l AS (SELECT doc_id, string_agg(label, ',' ORDER BY label) AS labels FROM (SELECT doc_id, label FROM v UNION SELECT doc_id, label FROM b) GROUP BY doc_id),
g AS (SELECT doc_id, count(*) AS n, min(p) AS lo, max(p) AS hi, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM b GROUP BY doc_id),
s AS (SELECT doc_id, max(share) AS share FROM v GROUP BY doc_id)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(g.n, 0) AS BIGINT) AS n_base, CAST(lo AS BIGINT) AS first_word, CAST(hi AS BIGINT) AS last_word,
       coalesce(g.labels, '') AS base_labels, coalesce(l.labels, '') AS labels, CAST(greatest(CASE WHEN g.n > 0 THEN 1.0 ELSE 0.0 END, least(coalesce(share, 0.0), 1.0)) AS DOUBLE) AS score
FROM d LEFT JOIN g USING (doc_id) LEFT JOIN l USING (doc_id) LEFT JOIN s USING (doc_id)
"""
