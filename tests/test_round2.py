"""Findings on single queries: order inside laterals, tables that queries read."""

import re

from conftest import normal
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphwin.operators import relational


def test_lateral_keeps_its_order(spark, tmp_path):
    """on many unordered rows the two largest orders of a customer, not any two."""
    spark.range(20).select(F.col("id").alias("c_custkey")).write.parquet(f"{tmp_path}/customer.parquet")
    o = spark.range(20_000).select(F.col("id").alias("o_orderkey"), (F.col("id") % 20).alias("o_custkey"), F.pmod(F.col("id") * 7919, F.lit(1009)).cast("double").alias("o_totalprice"))
    o.repartition(7).write.parquet(f"{tmp_path}/orders.parquet")
    o = spark.read.parquet(f"{tmp_path}/orders.parquet")
    ranked = o.withColumn("r", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")))
    got = relational.QUERIES["op_lateral"](spark, str(tmp_path))
    assert normal(got) == normal(ranked.where("r <= 2").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey"))


def test_plan_is_that_of_a_run(spark, tiny_dir):
    """the plan is explained after Spark read the tables for it."""
    text = "\n".join(r["line"] for r in relational.QUERIES["op_explain_plan"](spark, tiny_dir).orderBy("n").collect())
    assert "isFinalPlan=true" in text and re.search(r"lineitem", text)


def test_data_source_over_parts(spark, tiny_dir):
    """F32: one vertex a part."""
    got = relational.QUERIES["op_scan_datasource"](spark, tiny_dir)
    parts = spark.read.parquet(f"{tiny_dir}/part.parquet").where("p_partkey > 0").select(F.col("p_partkey").alias("dst"))
    assert normal(got.select("dst").distinct()) == normal(parts)


def test_lateral_orders_its_ranks(spark, tiny_dir):
    """the rank behind the lateral's LIMIT is ordered; small tables may come out right without."""
    plan = relational.QUERIES["op_lateral"](spark, tiny_dir)._jdf.queryExecution().optimizedPlan().toString()
    assert re.search(r"row_number\(\) windowspecdefinition\([^)]*o_totalprice#\d+ DESC", plan)
