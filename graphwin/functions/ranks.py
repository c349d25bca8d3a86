"""Gapless numbering inside keys without gathering a key in one task.

Rows are numbered per key inside each partition while they stream by, the per-partition counts (small) are summed up
along the partitions, and each row's number is its local one plus its partition's offset. A key that holds a third of
all rows costs no more than any other.
"""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

PART, LOCAL = "_part", "_local"


class PartitionRanker:
    """Running count per key inside one task."""

    def __init__(self) -> None:
        self.seen: dict = {}
        self.part = TaskContext.get().partitionId()

    def number(self, keys: pd.Series) -> pd.Series:
        local = keys.groupby(keys, dropna=False).cumcount()
        base = keys.map(lambda k: self.seen.get(k, 0))
        for k, n in keys.value_counts(dropna=False).items():
            self.seen[k] = self.seen.get(k, 0) + n
        return (local + base).astype("int64")


def ranked_schema(schema: T.StructType) -> T.StructType:
    return T.StructType([*schema.fields, T.StructField(PART, T.IntegerType()), T.StructField(LOCAL, T.LongType())])


def with_local_rank(df: DataFrame, key: str) -> DataFrame:
    """Adds the partition's number and the row's number inside (partition, key)."""

    def run(batches):
        ranker = PartitionRanker()
        for b in batches:
            local = ranker.number(b.column(key).to_pandas())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([ranker.part] * b.num_rows, pa.int32()), pa.array(local.to_numpy(), pa.int64())], names=[*b.schema.names, PART, LOCAL])

    return df.mapInArrow(run, ranked_schema(df.schema))


def partition_offsets(stored: DataFrame, key: str) -> DataFrame:
    """(part, key, _before, _n): how many rows of the key earlier partitions hold. stored must be a written table."""
    counts = stored.groupBy(PART, key).agg(F.count("*").alias("_n"))
    w = Window.partitionBy(key).orderBy(PART).rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn("_before", F.coalesce(F.sum("_n").over(w), F.lit(0)))


def with_global_rank(stored: DataFrame, key: str, name: str, offsets: DataFrame | None = None) -> DataFrame:
    offsets = (partition_offsets(stored, key) if offsets is None else offsets).select(PART, F.col(key).alias("_key"), "_before")
    joined = stored.join(offsets, (stored[PART] == offsets[PART]) & stored[key].eqNullSafe(offsets["_key"]), "inner").drop(offsets[PART])
    return joined.withColumn(name, F.col("_before") + F.col(LOCAL)).drop(PART, LOCAL, "_before", "_key")
