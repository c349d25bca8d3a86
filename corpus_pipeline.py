"""A training-data pipeline of five operators: quality rules, language, near-duplicates, benchmark passages, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each one's rows as Parquet into the shared
folder and reads them back as the next one's docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphwin.llm import decontaminate, language, neardup, packing, quality
from graphwin.session import materialize, ship

CAPACITY = 2048
SIMILAR_PERCENT = 80


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass their own rules and whose host isn't rejected. Null texts go; null sources are one host."""
    ship(spark)
    return quality.keep_good(docs)


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a language was recognised; without letters, or with nothing to learn from, that is none.

    The model is fitted to labelled rows of the stage's own input; lang stays as it was."""
    ship(spark)
    model = language.fit_language_model(docs, F.lit(True))
    rows = docs.select(F.struct(*docs.columns).alias("_doc"), F.col("text").cast("string").alias("text"))
    if model is None:  # no labelled rows: keep what has letters
        return docs.where(F.col("text").rlike(r"\p{L}"))
    return language.with_language(rows, model).where(F.col("lang_pred") != language.UND).select("_doc.*")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, linked at a similarity of 0.8 or more: that with the smallest doc_id."""
    ship(spark)
    return neardup.drop_near_duplicates(docs, SIMILAR_PERCENT)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark window occurs."""
    ship(spark)
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    ship(spark)
    return packing.pack_documents(docs, CAPACITY, keep_ids=False)


STAGES = [
    ("quality_rules", quality_rules),
    ("language_id", language_id),
    ("near_duplicates", near_duplicates),
    ("benchmark_passages", benchmark_passages),
    ("packed_sequences", packed_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; the last stage's rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return docs


#: Tokenising and near-duplicate components can't be written in SQL: tests compare run() with a brute-force version.
ORACLE_SQL = None
