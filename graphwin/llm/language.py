"""Language identification in two steps: the family first, then one-versus-one linear SVMs inside it.

Features are counts of hashed byte 2-, 3- and 4-grams of the whole lower-cased text, digits and ASCII signs read as
spaces; square roots, scaled to length 1. Training takes at most `per_language` labelled texts of a language, those with
the smallest hash of id and text (repeated rows count once), as sparse vectors, and fits in one task: what it holds is
bounded by languages x per_language x the features of a text, and the driver gets the weights alone.

Null texts and texts without a letter (\\p{L}) are `und` with score 0. Without any labelled row every text is `und`. Ties of
votes go to the larger sum of shares, then to the later code. Columns named like the results are replaced, others pass.
"""

from __future__ import annotations

import math
import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from graphwin.llm.tokens import small_batches
from graphwin.session import materialize

BITS = 13
DIM = 1 << BITS
#: Labels are broadcast to the texts up to this many; beyond, texts are dealt by label.
BROADCAST_LABELS = 10_000
UND = "und"
LETTER = regex.compile(r"\p{L}")
_BLANK = bytes(c if c >= 128 or chr(c).isalpha() else 32 for c in range(256))
# Families of ISO 639-1 codes. A code that isn't listed is a family of its own.
FAMILIES = {
    "germanic": ("en", "de", "nl", "af", "fy", "lb", "yi", "sv", "da", "no", "nb", "nn", "is", "fo"),
    "romance": ("fr", "es", "it", "pt", "ro", "ca", "gl", "oc"),
    "slavic": ("ru", "uk", "be", "pl", "cs", "sk", "sl", "hr", "sr", "bs", "bg", "mk"),
    "uralic": ("fi", "et", "hu"),
    "turkic": ("tr", "az", "kk", "uz", "ky", "tk"),
    "indic": ("hi", "bn", "ur", "mr", "ne", "pa", "gu"),
}
FAMILY_OF = {code: name for name, codes in FAMILIES.items() for code in codes}


def features(text: str) -> np.ndarray:
    raw = np.frombuffer(b" " + text.lower().encode("utf-8", "replace").translate(_BLANK) + b"   ", np.uint8).astype(np.uint32)
    total = np.zeros(DIM, np.float32)
    for a in range(0, max(1, len(raw) - 3), 1 << 20):  # long texts in bounded pieces
        b = raw[a : a + (1 << 20) + 3]
        two = b[:-3] | b[1:-2] << np.uint32(8)
        three = two | b[2:-1] << np.uint32(16)
        for gram, salt in ((two, 0x9E3779B1), (three, 0x85EBCA77), (three | b[3:] << np.uint32(24), 0xC2B2AE3D)):
            total += np.bincount((gram * np.uint32(salt)) >> np.uint32(32 - BITS), minlength=DIM)
    total = np.sqrt(total)
    return total / (np.linalg.norm(total) or 1.0)


#: A text as (numbers of its features, their values), the last one the constant 1.
Sparse = tuple[np.ndarray, np.ndarray]


def sparse(text: str) -> Sparse:
    v = features(text)
    at = np.flatnonzero(v)
    return np.append(at, DIM).astype(np.int32), np.append(v[at], 1).astype(np.float32)


def linear_svm(x: list[Sparse], y: np.ndarray, c: float = 10.0, epochs: int = 12, seed: int = 5) -> np.ndarray:
    """Weights of an L1-loss linear SVM by dual coordinate descent; y is -1 or 1, both sides weigh alike."""
    rng, alpha, w, norms = np.random.default_rng(seed), np.zeros(len(x)), np.zeros(DIM + 1, np.float32), [float(v @ v) for _, v in x]
    upper = np.where(y > 0, c * len(y) / (2 * max(1, (y > 0).sum())), c * len(y) / (2 * max(1, (y < 0).sum())))
    for _ in range(epochs):
        for i in rng.permutation(len(x)):
            at, v = x[i]
            new = min(max(alpha[i] - (y[i] * float(w[at] @ v) - 1) / norms[i], 0.0), upper[i])
            if new != alpha[i]:
                w[at] += np.float32((new - alpha[i]) * y[i]) * v
                alpha[i] = new
    return w


@dataclass
class LanguageModel:
    families: list[list[str]]
    family_weights: np.ndarray  # one row a family, against the others
    pairs: dict[tuple[str, str], np.ndarray]  # inside a family; positive means the first

    @classmethod
    def fit(cls, x: list[Sparse], labels: list[str]) -> "LanguageModel":
        groups: dict[str, list[str]] = {}
        for lang in sorted(set(labels)):
            groups.setdefault(FAMILY_OF.get(lang, lang), []).append(lang)
        families = [groups[k] for k in sorted(groups)]
        names = np.array(labels)
        rows = [linear_svm(x, np.where(np.isin(names, f), 1.0, -1.0)) for f in families] if len(families) > 1 else []
        pairs = {}
        for f in families:
            for i, a in enumerate(f):
                for b in f[i + 1 :]:
                    own = np.flatnonzero((names == a) | (names == b))
                    pairs[a, b] = linear_svm([x[k] for k in own], np.where(names[own] == a, 1.0, -1.0))
        return cls(families, np.array(rows, np.float32).reshape(len(rows), DIM + 1), pairs)

    def predict(self, x: np.ndarray) -> tuple[str, float]:
        squash = lambda m: 1 / (1 + math.exp(-max(-30.0, min(30.0, 4 * m))))
        at, sure = 0, 1.0
        if len(self.family_weights):
            margins = self.family_weights[:, :-1] @ x + self.family_weights[:, -1]
            at = int(margins.argmax())
            sure = squash(float(margins[at]))
        langs = self.families[at]
        votes = dict.fromkeys(langs, 0.0)
        shares = {a: [] for a in langs}
        for i, a in enumerate(langs):
            for b in langs[i + 1 :]:
                p = squash(float(self.pairs[a, b][:-1] @ x + self.pairs[a, b][-1]))
                votes[a if p >= 0.5 else b] += 1
                shares[a].append(p)
                shares[b].append(1 - p)
        best = max(langs, key=lambda lang: (votes[lang], sum(shares[lang]), lang))
        return best, sure * (sum(shares[best]) / len(shares[best]) if shares[best] else 1.0)


def held_out(id_col: Column) -> Column:
    return F.crc32(id_col.cast("string").cast("binary")) % 4 == 2


def training_texts(docs: DataFrame, trainable: Column, per_language: int = 300, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang") -> DataFrame:
    """(label, text): of each label the per_language distinct rows with the smallest hashes. A cut drawn from the label's
    estimated number of distinct hashes leaves a few times as many as needed before any row is ranked."""
    rows = docs.where(trainable & F.col(label_col).isNotNull() & F.col(text_col).rlike(r"\p{L}")).select(F.col(label_col).cast("string").alias("label"), F.col(text_col).cast("string").alias("text"), F.xxhash64(F.lit(11), id_col, text_col).alias("h"))
    share = rows.groupBy("label").agg(F.approx_count_distinct("h").alias("n")).select(F.col("label").alias("_label"), ((2.0 * per_language + 50) / F.col("n")).alias("share"))
    share = materialize(share, "label-shares")  # a row a label
    if share.count() <= BROADCAST_LABELS:
        share = F.broadcast(share)
    near = rows.join(share, F.col("label") == F.col("_label")).where(F.pmod("h", F.lit(1 << 40)) < F.col("share") * float(1 << 40)).groupBy("label", "h").agg(F.first("text").alias("text"))
    return near.withColumn("_r", F.row_number().over(Window.partitionBy("label").orderBy(F.pmod("h", F.lit(1 << 40)), "h"))).where(F.col("_r") <= per_language).select("label", "text", "h")


def fit_language_model(docs: DataFrame, trainable: Column, per_language: int = 300, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang") -> LanguageModel | None:
    """A model from a bounded sample of the labelled rows for which trainable holds, or None without such rows."""
    small_batches(docs)
    chosen = training_texts(docs, trainable, per_language, id_col, text_col, label_col)

    def vectors(batches):
        for b in batches:
            x = [sparse(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([a.tobytes() for a, _ in x], pa.binary()), pa.array([v.tobytes() for _, v in x], pa.binary()), b.column(2)], names=["label", "at", "val", "h"])

    def fit(batches):
        rows = sorted(r for b in batches for r in zip(*(b.column(c).to_pylist() for c in ("label", "h", "at", "val")), strict=True))
        if rows:
            model = LanguageModel.fit([(np.frombuffer(a, np.int32), np.frombuffer(v, np.float32)) for _, _, a, v in rows], [r[0] for r in rows])
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], names=["model"])

    made = chosen.mapInArrow(vectors, "label string, at binary, val binary, h long").repartition(1).mapInArrow(fit, "model binary").collect()
    return pickle.loads(made[0]["model"]) if made else None


def with_language(docs: DataFrame, model: LanguageModel | None, text_col: str = "text", lang_out: str = "lang_pred", score_out: str = "score") -> DataFrame:
    """Adds the predicted language and its score; columns of those names are replaced."""
    small_batches(docs)
    docs = docs.drop(lang_out, score_out)
    names = docs.columns

    def run(batches):
        for b in batches:
            langs, scores = [], []
            for t in b.column(names.index(text_col)).to_pylist():
                lang, score = model.predict(features(t)) if model and t and LETTER.search(t) else (UND, 0.0)
                langs.append(lang)
                scores.append(min(1.0, max(0.0, score)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[*names, lang_out, score_out])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(lang_out, T.StringType()), T.StructField(score_out, T.DoubleType())]))
