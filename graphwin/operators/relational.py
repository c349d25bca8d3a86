"""Relational operators around the methods, one registered query each, with the SQL that must give the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from graphwin.functions.hashing import hash_columns
from graphwin.model import KHop
from graphwin.operators.components import connected_components
from graphwin.operators.reach import khop_pairs
from graphwin.session import shared_dir, ship
from graphwin.sources import graphs as G
from graphwin.sources.synthsource import SynthGraphSource

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
t = G.table
cents = G.cents
C = "CAST(ROUND({} * 100) AS BIGINT)"
_COP2 = """l AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem), e AS (SELECT a.l_partkey AS src, b.l_partkey AS dst, count(*) AS orders FROM l a JOIN l b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) >= 2)"""
_RELAY = """e AS (SELECT DISTINCT src, dst FROM (SELECT o_custkey AS src, lead(o_custkey) OVER (ORDER BY o_orderdate, o_orderkey) AS dst FROM orders) WHERE dst IS NOT NULL AND src <> dst)"""


def op(name: str, fn: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return fn(spark, sf_dir)

    QUERIES[f"op_{name}"] = run
    if sql:
        ORACLES[f"op_{name}"] = sql


# -- sources and sinks -------------------------------------------------------------------------------------------------
op("scan_parquet", lambda s, d: t(s, d, "orders").where("o_totalprice > 200000").select("o_orderkey", "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice > 200000")


def _round_trip(kind: str):
    def run(s, d):
        path = f"{shared_dir(s)}/edges-{kind}-{uuid.uuid4().hex}"
        e = G.copurchase(s, d, 2).edges.select("src", "dst")
        schema = "src long, dst long, _corrupt string"
        if kind == "csv":
            e.write.csv(path, header=True)
            return s.read.csv(path, header=True, schema=schema, mode="PERMISSIVE", columnNameOfCorruptRecord="_corrupt").select("src", "dst")
        e.write.json(path)
        return s.read.json(path, schema=schema, mode="PERMISSIVE", columnNameOfCorruptRecord="_corrupt").select("src", "dst")

    return run


op("scan_csv", _round_trip("csv"), f"WITH {_COP2} SELECT src, dst FROM e")
op("scan_json", _round_trip("json"), f"WITH {_COP2} SELECT src, dst FROM e")


def read_adjacency(s: SparkSession, path: str) -> DataFrame:
    """(src, dst) of lines `v: a b c`."""
    line = s.read.text(path).select(F.split("value", ":").alias("p"))
    return line.select(F.col("p")[0].cast("long").alias("src"), F.explode(F.split(F.trim(F.col("p")[1]), " ")).alias("dst")).select("src", F.col("dst").cast("long").alias("dst"))


def _adjacency(s, d):
    stamp = uuid.uuid4().hex
    path = f"{shared_dir(s)}/adjacency-{stamp}"
    e = G.relay(s, d).edges
    e.groupBy("src").agg(F.array_join(F.sort_array(F.collect_list("dst")), " ").alias("n")).select(F.concat_ws(": ", F.col("src").cast("string"), "n").alias("value")).write.text(path)
    return read_adjacency(s, path)


op("scan_text_adjacency", _adjacency, f"WITH {_RELAY} SELECT src, dst FROM e")


def _datasource(s, d):
    """Arithmetic parents of the parts: the source makes edges up to the largest key, those into parts stay."""
    s.dataSource.register(SynthGraphSource)
    parts = t(s, d, "part").select(F.col("p_partkey").alias("dst"))
    n = (parts.agg(F.max("dst")).first()[0] or 0) + 1
    made = s.read.format("synthgraph").option("kind", "dag").option("n", str(n)).option("d", "3").option("partitions", str(max(4, n // 100_000))).load()
    return made.join(parts, "dst", "left_semi").select("src", "dst").distinct()


op("scan_datasource", _datasource, f"SELECT DISTINCT ((p_partkey * 7919 + j.range * 104729 + 17) % {G.MODULUS}) % p_partkey AS src, p_partkey AS dst FROM part, range(3) j WHERE p_partkey > 0")


def _partitioned(s, d):
    stamp = uuid.uuid4().hex
    path = f"{shared_dir(s)}/by-status-{stamp}"
    t(s, d, "orders").select("o_orderkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return s.read.parquet(path).where("o_orderstatus = 'F'").select("o_orderkey")


op("sink_parquet_partitioned", _partitioned, "SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'")


def _bucketed(s, d):
    stamp = uuid.uuid4().hex[:12]  # a managed table's folder must be new in every session
    lines, orders = f"gw_lines_{stamp}", f"gw_orders_{stamp}"
    for name, df, key in ((orders, t(s, d, "orders").select("o_orderkey", "o_custkey"), "o_orderkey"), (lines, t(s, d, "lineitem").select("l_orderkey", "l_partkey"), "l_orderkey")):
        df.write.bucketBy(8, key).sortBy(key).saveAsTable(name)
    return s.table(lines).join(s.table(orders), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("n"))


op("sink_bucketed", _bucketed, "SELECT o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")


def _noop(s, d):
    df = t(s, d, "part").select("p_partkey")
    df.write.format("noop").mode("overwrite").save()
    return df.agg(F.count("*").alias("n"))


op("sink_noop", _noop, "SELECT count(*) AS n FROM part")

# -- projection and filter ---------------------------------------------------------------------------------------------
op("project", lambda s, d: t(s, d, "part").select("p_partkey", (F.col("p_size") * 2).alias("twice")), "SELECT p_partkey, p_size * 2 AS twice FROM part")
op("rename", lambda s, d: t(s, d, "nation").withColumnsRenamed({"n_nationkey": "k", "n_name": "name"}).select("k", "name"), "SELECT n_nationkey AS k, n_name AS name FROM nation")
op("cast", lambda s, d: t(s, d, "part").select("p_partkey", F.col("p_size").cast("string").alias("txt"), F.col("p_brand").try_cast("int").alias("bad")), "SELECT p_partkey, CAST(p_size AS VARCHAR) AS txt, TRY_CAST(p_brand AS INTEGER) AS bad FROM part")
op("filter_logic", lambda s, d: t(s, d, "customer").where(((F.col("c_nationkey") < 5) | (F.col("c_mktsegment") == "BUILDING")) & ~(F.col("c_acctbal") < 0)).select("c_custkey"), "SELECT c_custkey FROM customer WHERE (c_nationkey < 5 OR c_mktsegment = 'BUILDING') AND NOT c_acctbal < 0")
op("filter_between", lambda s, d: t(s, d, "part").where(F.col("p_size").between(10, 20)).select("p_partkey"), "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20")
op("filter_isin", lambda s, d: t(s, d, "orders").where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH')")
op("filter_like", lambda s, d: t(s, d, "part").where(F.col("p_type").like("%E%")).select("p_partkey"), "SELECT p_partkey FROM part WHERE p_type LIKE '%E%'")
op("filter_rlike", lambda s, d: t(s, d, "part").where(F.col("p_brand").rlike("#[1-3]")).select("p_partkey"), "SELECT p_partkey FROM part WHERE regexp_matches(p_brand, '#[1-3]')")
op("filter_null_safe_eq", lambda s, d: t(s, d, "orders").join(t(s, d, "customer"), (F.col("o_custkey") == F.col("c_custkey")) & (F.col("c_nationkey") == 3), "left").where(F.col("c_nationkey").eqNullSafe(F.lit(None))).select("o_orderkey"), "SELECT o_orderkey FROM orders LEFT JOIN customer ON o_custkey = c_custkey AND c_nationkey = 3 WHERE c_nationkey IS NOT DISTINCT FROM NULL")

# -- graph helpers -----------------------------------------------------------------------------------------------------
op("induced_subgraph", lambda s, d: G.copurchase(s, d, 2).induced(F.col("p_size") < 25).edges.select("src", "dst"), f"WITH {_COP2} SELECT src, dst FROM e JOIN part a ON src = a.p_partkey JOIN part b ON dst = b.p_partkey WHERE a.p_size < 25 AND b.p_size < 25")
op("edge_filter", lambda s, d: G.copurchase(s, d, 1).edges.where("orders >= 2").select("src", "dst", "orders"), f"WITH {_COP2} SELECT src, dst, orders FROM e")
op("symmetrise", lambda s, d: G.relay(s, d).arcs("both"), f"WITH {_RELAY} SELECT src, dst FROM e UNION SELECT dst, src FROM e")
op("reverse", lambda s, d: G.relay(s, d).arcs("in"), f"WITH {_RELAY} SELECT dst AS src, src AS dst FROM e")
op("degree_out", lambda s, d: (lambda g: g.vertices.select("id").join(g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n")), "id", "left").select("id", F.coalesce("n", F.lit(0)).alias("n")))(G.relay(s, d)), f"WITH {_RELAY} SELECT c_custkey AS id, count(dst) AS n FROM customer LEFT JOIN e ON src = c_custkey GROUP BY 1")
op("degree_in", lambda s, d: (lambda g: g.vertices.select("id").join(g.edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("n")), "id", "left").select("id", F.coalesce("n", F.lit(0)).alias("n")))(G.relay(s, d)), f"WITH {_RELAY} SELECT c_custkey AS id, count(src) AS n FROM customer LEFT JOIN e ON dst = c_custkey GROUP BY 1")
op("avg_degree", lambda s, d: (lambda g: g.edges.agg(F.count("*").alias("e")).join(F.broadcast(g.vertices.agg(F.count("*").alias("v")))).select((F.col("e") / F.col("v")).alias("mean")))(G.relay(s, d)), f"WITH {_RELAY} SELECT (SELECT count(*) FROM e) / (SELECT count(*) FROM customer) AS mean")
op("sources_sinks", lambda s, d: (lambda g: g.vertices.select("id").join(g.edges.select(F.col("dst").alias("id")), "id", "left_anti").select("id", F.lit("source").alias("kind")).union(g.vertices.select("id").join(g.edges.select(F.col("src").alias("id")), "id", "left_anti").select("id", F.lit("sink"))))(G.eventchain(s, d)), "WITH x AS (SELECT event_id AS id, lag(event_id) OVER w AS a, lead(event_id) OVER w AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT id, 'source' AS kind FROM x WHERE a IS NULL UNION ALL SELECT id, 'sink' FROM x WHERE b IS NULL")
op("components", lambda s, d: connected_components(G.eventchain(s, d).edges).select("vertex", "component"), "WITH x AS (SELECT event_id, min(event_id) OVER (PARTITION BY user_id) AS c, count(*) OVER (PARTITION BY user_id) AS n FROM events) SELECT event_id AS vertex, c AS component FROM x WHERE n > 1")


def triangles(e: DataFrame) -> DataFrame:
    """(n): triangles of edges stored once, the smaller end first."""
    a, b, c = e.toDF("x", "y"), e.toDF("y", "z"), e.toDF("x", "z")
    return a.join(b, "y").join(c, ["x", "z"]).agg(F.count("*").alias("n"))


op("triangles", lambda s, d: triangles(G.copurchase(s, d, 2).edges.select("src", "dst")), f"WITH {_COP2} SELECT count(*) AS n FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst")
op("dict_encode", lambda s, d: G.dict_encode(G.page_links(s, d), "token"), """SELECT token, row_number() OVER (ORDER BY encode(token)) - 1 AS code FROM (SELECT DISTINCT unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS token FROM pages)""")

# -- joins -------------------------------------------------------------------------------------------------------------
_lo = "SELECT o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
for _hint in ("shuffle_hash", "merge"):
    op({"shuffle_hash": "join_hash", "merge": "join_sort_merge"}[_hint], (lambda h: lambda s, d: t(s, d, "lineitem").select("l_orderkey").join(t(s, d, "orders").select("o_orderkey", "o_custkey").hint(h), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("n")))(_hint), _lo)
op("join_broadcast", lambda s, d: t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
op("join_nested_loop", lambda s, d: t(s, d, "nation").select(F.col("n_nationkey").alias("a")).join(t(s, d, "nation").select(F.col("n_nationkey").alias("b")), F.col("a") < F.col("b")), "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
op("join_cross", lambda s, d: t(s, d, "region").select(F.col("r_name").alias("a")).crossJoin(t(s, d, "region").select(F.col("r_name").alias("b"))), "SELECT a.r_name AS a, b.r_name AS b FROM region a CROSS JOIN region b")
for _how, _kw in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    op(f"join_{_how}", (lambda h: lambda s, d: t(s, d, "customer").where("c_nationkey < 10").select("c_custkey").join(t(s, d, "orders").where("o_totalprice > 150000").select("o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), h))(_how), f"SELECT c_custkey, o_orderkey, o_custkey FROM (SELECT * FROM customer WHERE c_nationkey < 10) {_kw} JOIN (SELECT * FROM orders WHERE o_totalprice > 150000) ON c_custkey = o_custkey")
for _how, _not in (("left_semi", ""), ("left_anti", "NOT ")):
    op({"left_semi": "join_semi", "left_anti": "join_anti"}[_how], (lambda h: lambda s, d: t(s, d, "customer").select("c_custkey").join(t(s, d, "orders").where("o_orderpriority = '1-URGENT'"), F.col("c_custkey") == F.col("o_custkey"), h))(_how), f"SELECT c_custkey FROM customer WHERE {_not}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
op("join_self", lambda s, d: G.copurchase(s, d, 2).edges, f"WITH {_COP2} SELECT src, dst, orders FROM e")


def range_join(points: DataFrame, x: str, bands: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """lo <= x <= hi: each band is listed in the buckets that it meets, points join their own bucket, then the bounds hold."""
    b = bands.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return points.withColumn("_b", F.floor(F.col(x) / width)).join(b, "_b").where(F.col(x).between(F.col(lo), F.col(hi))).drop("_b")


op("join_range", lambda s, d: range_join(t(s, d, "part").select("p_partkey", "p_size"), "p_size", s.range(0, 10).select((F.col("id") * 5).alias("lo"), (F.col("id") * 5 + 7).alias("hi")), "lo", "hi", 10).groupBy("lo").agg(F.count("*").alias("n")), "SELECT lo, count(*) AS n FROM part JOIN (SELECT range * 5 AS lo, range * 5 + 7 AS hi FROM range(10)) ON p_size BETWEEN lo AND hi GROUP BY 1")


def interval_join(events: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """(a, b): pairs of a key's events, b within the span after a. Time buckets bound what meets."""
    sec = F.unix_micros(F.col(ts).cast("timestamp"))
    span = seconds * 1_000_000
    e = events.select(F.col(key).alias("k"), F.col("event_id"), sec.alias("us")).withColumn("bucket", F.floor(F.col("us") / span))
    left = e.select("k", F.col("event_id").alias("a"), F.col("us").alias("ua"), F.explode(F.array(F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    right = e.select("k", F.col("event_id").alias("b"), F.col("us").alias("ub"), "bucket")
    return left.join(right, ["k", "bucket"]).where((F.col("ub") > F.col("ua")) & (F.col("ub") - F.col("ua") <= span)).select("a", "b")


op("join_interval", lambda s, d: interval_join(t(s, d, "events"), "user_id", "ts", 3600), "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")


def asof(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """Each left row with the value of the key's last right row strictly before it: one sort of the union per key."""
    cols = left.columns
    both = left.select(*cols, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(0).alias("_side")).unionByName(right.select(key, ts, F.col(value).alias("_v"), F.lit(1).alias("_side")), allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 0").select(*cols, F.col("_last").alias(value))


op("join_asof", lambda s, d: asof(t(s, d, "events").select("event_id", "user_id", "ts"), t(s, d, "events").where("event_type = 'error'").select("user_id", "ts", F.unix_micros(F.col("ts").cast("timestamp")).alias("err_us")), "user_id", "ts", "err_us").select("event_id", "err_us"), "SELECT a.event_id, max(epoch_us(b.ts)) AS err_us FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_type = 'error' AND b.ts < a.ts GROUP BY 1")

# -- aggregation -------------------------------------------------------------------------------------------------------
op("agg_hash", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(cents("l_extendedprice")).alias("total"), F.count("*").alias("n"), F.min("l_shipdate").alias("lo"), F.max("l_shipdate").alias("hi"), F.avg("l_linenumber").alias("mean")), f"SELECT l_returnflag, CAST(sum({C.format('l_extendedprice')}) AS BIGINT) AS total, count(*) AS n, min(l_shipdate) AS lo, max(l_shipdate) AS hi, avg(l_linenumber) AS mean FROM lineitem GROUP BY 1")
op("agg_sort_object", lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.array_join(F.sort_array(F.collect_list("o_orderkey")), ",").alias("keys")), "SELECT o_custkey, string_agg(CAST(o_orderkey AS VARCHAR), ',' ORDER BY o_orderkey) AS keys FROM orders GROUP BY 1")
op("agg_distinct", lambda s, d: t(s, d, "lineitem").groupBy("l_linestatus").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("supps")), "SELECT l_linestatus, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")
op("agg_filter", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_quantity") > 25).alias("big"), F.sum(F.when(F.col("l_quantity") <= 25, 1)).alias("small")), "SELECT l_returnflag, CAST(count_if(l_quantity > 25) AS BIGINT) AS big, count(*) FILTER (WHERE l_quantity <= 25) AS small FROM lineitem GROUP BY 1")
op("agg_having", lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 10"), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 10")
_rns = lambda s, d: t(s, d, "customer").join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
_rns_sql = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _grouping_sets(s, d):
    _rns(s, d).createOrReplaceTempView("gw_rns")
    return s.sql("SELECT r_name, c_mktsegment, count(*) AS n FROM gw_rns GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")


op("agg_grouping_sets", _grouping_sets, f"SELECT r_name, c_mktsegment, count(*) AS n {_rns_sql} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
op("agg_cube", lambda s, d: _rns(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("gid")), f"SELECT r_name, c_mktsegment, count(*) AS n, CAST(grouping(r_name, c_mktsegment) AS BIGINT) AS gid {_rns_sql} GROUP BY CUBE (r_name, c_mktsegment)")
op("agg_rollup", lambda s, d: _rns(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n")), f"SELECT r_name, n_name, count(*) AS n {_rns_sql} GROUP BY ROLLUP (r_name, n_name)")
op("agg_pivot", lambda s, d: t(s, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "2-HIGH"]).agg(F.count(F.lit(1))).select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("2-HIGH", F.lit(0)).alias("high")), "SELECT o_orderstatus, count(*) FILTER (WHERE o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (WHERE o_orderpriority = '2-HIGH') AS high FROM orders GROUP BY 1")
op("agg_stats", lambda s, d: t(s, d, "part").groupBy("p_brand").agg(*[F.round(f("p_size"), 6).alias(n) for n, f in (("vp", F.var_pop), ("sd", F.stddev_samp))], F.round(F.covar_pop("p_size", "p_retailprice"), 3).alias("cv"), F.round(F.corr("p_size", "p_retailprice"), 6).alias("cr")), "SELECT p_brand, round(var_pop(p_size), 6) AS vp, round(stddev_samp(p_size), 6) AS sd, round(covar_pop(p_size, p_retailprice), 3) AS cv, round(corr(p_size, p_retailprice), 6) AS cr FROM part GROUP BY 1")
op("agg_percentile", lambda s, d: t(s, d, "part").groupBy("p_brand").agg(F.median("p_size").alias("md"), F.percentile("p_size", 0.25).alias("q1")), "SELECT p_brand, median(p_size) AS md, quantile_cont(p_size, 0.25) AS q1 FROM part GROUP BY 1")
op("agg_mode", lambda s, d: t(s, d, "part").groupBy("p_brand", "p_size").agg(F.count("*").alias("c")).groupBy("p_brand").agg(F.max(F.struct("c", (-F.col("p_size")).alias("m"))).alias("x")).select("p_brand", (-F.col("x.m")).alias("mode")), "SELECT p_brand, p_size AS mode FROM (SELECT p_brand, p_size, row_number() OVER (PARTITION BY p_brand ORDER BY count(*) DESC, p_size) AS r FROM part GROUP BY 1, 2) WHERE r = 1")
op("agg_approx", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("u"), F.percentile_approx("value", 0.5).alias("md"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("h")))
op("agg_bool_bit", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.bool_or(F.col("value") > 99).alias("bo"), F.bool_and(F.col("value") > 0).alias("ba"), F.bit_or("user_id").alias("o"), F.bit_and("user_id").alias("a"), F.bit_xor("user_id").alias("x")), "SELECT event_type, bool_or(value > 99) AS bo, bool_and(value > 0) AS ba, bit_or(user_id) AS o, bit_and(user_id) AS a, bit_xor(user_id) AS x FROM events GROUP BY 1")
op("agg_max_by", lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("low")), "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS top, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS low FROM orders GROUP BY 1")
op("agg_string", lambda s, d: t(s, d, "part").groupBy("p_size").agg(F.array_join(F.sort_array(F.collect_set("p_brand")), "|").alias("brands")), "SELECT p_size, string_agg(DISTINCT p_brand, '|' ORDER BY p_brand) AS brands FROM part GROUP BY 1")

# -- windows, order, sets ----------------------------------------------------------------------------------------------
_bw = lambda: Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")
_bs = lambda: Window.partitionBy("p_brand").orderBy("p_size")
op("win_rank", lambda s, d: t(s, d, "part").select("p_partkey", F.row_number().over(_bw()).alias("rn"), F.rank().over(_bs()).alias("rk"), F.dense_rank().over(_bs()).alias("dr"), F.round(F.percent_rank().over(_bs()), 9).alias("pr"), F.round(F.cume_dist().over(_bs()), 9).alias("cd"), F.ntile(4).over(_bw()).alias("nt")), "SELECT p_partkey, CAST(row_number() OVER a AS INTEGER) AS rn, CAST(rank() OVER b AS INTEGER) AS rk, CAST(dense_rank() OVER b AS INTEGER) AS dr, round(percent_rank() OVER b, 9) AS pr, round(cume_dist() OVER b, 9) AS cd, CAST(ntile(4) OVER a AS INTEGER) AS nt FROM part WINDOW a AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), b AS (PARTITION BY p_brand ORDER BY p_size)")
_ow = lambda: Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
_full = lambda: _ow().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
op("win_nav", lambda s, d: t(s, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(_ow()).alias("lg"), F.lead("o_orderkey").over(_ow()).alias("ld"), F.first("o_orderkey").over(_full()).alias("f"), F.last("o_orderkey").over(_full()).alias("l"), F.nth_value("o_orderkey", 2).over(_full()).alias("n2")), "SELECT o_orderkey, lag(o_orderkey) OVER w AS lg, lead(o_orderkey) OVER w AS ld, first_value(o_orderkey) OVER f AS f, last_value(o_orderkey) OVER f AS l, nth_value(o_orderkey, 2) OVER f AS n2 FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), f AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
_ew = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
op("win_rows", lambda s, d: t(s, d, "events").select("event_id", F.sum(cents("value")).over(_ew().rowsBetween(-2, 0)).alias("last3"), F.count("*").over(_ew().rowsBetween(Window.unboundedPreceding, 0)).alias("seen")), f"SELECT event_id, CAST(sum({C.format('value')}) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING) AS BIGINT) AS last3, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS seen FROM events")
op("win_range", lambda s, d: t(s, d, "part").select("p_partkey", F.count("*").over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-3, 3)).alias("near")), "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS near FROM part")
op("sort_multi_nulls", lambda s, d: t(s, d, "orders").join(t(s, d, "customer").where("c_nationkey = 1"), F.col("o_custkey") == F.col("c_custkey"), "left").orderBy(F.asc_nulls_last("c_custkey"), F.desc("o_orderkey")).select("c_custkey", "o_orderkey").limit(50), "SELECT c_custkey, o_orderkey FROM orders LEFT JOIN (SELECT * FROM customer WHERE c_nationkey = 1) ON o_custkey = c_custkey ORDER BY c_custkey ASC NULLS LAST, o_orderkey DESC LIMIT 50")
op("limit_offset", lambda s, d: t(s, d, "orders").orderBy("o_orderkey").offset(5).limit(10).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 5")
op("topk", lambda s, d: t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
op("topk_per_group", lambda s, d: t(s, d, "orders").withColumn("r", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 2").select("o_custkey", "o_orderkey", "r"), "SELECT o_custkey, o_orderkey, CAST(r AS INTEGER) AS r FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
_ca, _sa = (lambda s, d: t(s, d, "customer").select(F.col("c_nationkey").alias("k"))), (lambda s, d: t(s, d, "supplier").select(F.col("s_nationkey").alias("k")))
for _n, _f, _kw in (("union_all", lambda a, b: a.union(b), "UNION ALL"), ("union_distinct", lambda a, b: a.union(b).distinct(), "UNION"), ("intersect", lambda a, b: a.intersect(b), "INTERSECT"), ("intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"), ("except", lambda a, b: a.subtract(b), "EXCEPT"), ("except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL")):
    op(_n, (lambda f: lambda s, d: f(_ca(s, d), _sa(s, d)))(_f), f"SELECT c_nationkey AS k FROM customer {_kw} SELECT s_nationkey FROM supplier")
op("union_by_name", lambda s, d: t(s, d, "nation").select(F.col("n_name").alias("name"), F.col("n_nationkey").alias("k")).unionByName(t(s, d, "region").select(F.col("r_regionkey").alias("k"), F.col("r_name").alias("name"))), "SELECT n_name AS name, n_nationkey AS k FROM nation UNION ALL SELECT r_name, r_regionkey FROM region")

# -- scalar functions --------------------------------------------------------------------------------------------------
op("fn_string", lambda s, d: t(s, d, "part").select("p_partkey", F.lower("p_brand").alias("lo"), F.upper("p_name").alias("up"), F.substring("p_brand", 1, 3).alias("sub"), F.split("p_brand", "#")[1].alias("num"), F.concat_ws("-", "p_brand", "p_type").alias("cat"), F.replace("p_brand", F.lit("#"), F.lit("_")).alias("rep"), F.length("p_name").alias("len"), F.regexp_extract("p_brand", r"#(\d)", 1).alias("ex"), F.instr("p_brand", "#").alias("at"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("pad"), F.trim(F.concat(F.lit(" "), "p_brand")).alias("tr")), r"SELECT p_partkey, lower(p_brand) AS lo, upper(p_name) AS up, substring(p_brand, 1, 3) AS sub, split_part(p_brand, '#', 2) AS num, p_brand || '-' || p_type AS cat, replace(p_brand, '#', '_') AS rep, CAST(length(p_name) AS INTEGER) AS len, regexp_extract(p_brand, '#(\d)', 1) AS ex, CAST(instr(p_brand, '#') AS INTEGER) AS at, lpad(CAST(p_size AS VARCHAR), 4, '0') AS pad, trim(' ' || p_brand) AS tr FROM part")
op("fn_html_links", lambda s, d: G.page_links(s, d), """SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS token FROM pages""")
op("fn_date", lambda s, d: t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("tr"), F.datediff("o_orderdate", F.lit("1992-01-01").cast("date")).alias("dd"), F.date_format(F.add_months("o_orderdate", 1), "yyyy-MM-dd").alias("nx"), F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("us")), "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS tr, CAST(datediff('day', DATE '1992-01-01', o_orderdate) AS INTEGER) AS dd, strftime(CAST(o_orderdate AS DATE) + INTERVAL 1 MONTH, '%Y-%m-%d') AS nx, epoch_us(o_orderdate) AS us FROM orders")
op("fn_math", lambda s, d: t(s, d, "part").select("p_partkey", F.floor(F.col("p_retailprice")).alias("fl"), F.abs(F.col("p_size") - 25).alias("ab"), F.pmod(F.col("p_size") - 25, F.lit(7)).alias("pm"), F.round(F.sqrt("p_size"), 6).alias("sq"), F.round(F.log2("p_size"), 6).alias("lg"), F.greatest("p_size", F.lit(20)).alias("gr"), F.least("p_size", F.lit(20)).alias("le"), F.round(F.pow("p_size", F.lit(2)), 0).alias("po"), F.signum(F.col("p_size") - 25).alias("sg")), "SELECT p_partkey, CAST(floor(p_retailprice) AS BIGINT) AS fl, abs(p_size - 25) AS ab, ((p_size - 25) % 7 + 7) % 7 AS pm, round(sqrt(p_size), 6) AS sq, round(log2(p_size), 6) AS lg, greatest(p_size, 20) AS gr, least(p_size, 20) AS le, round(pow(p_size, 2), 0) AS po, CAST(sign(p_size - 25) AS DOUBLE) AS sg FROM part")
op("fn_conditional", lambda s, d: t(s, d, "customer").select("c_custkey", F.when(F.col("c_acctbal") < 0, "neg").when(F.col("c_acctbal") < 5000, "mid").otherwise("big").alias("cls"), F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("seg")), "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'neg' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'big' END AS cls, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS seg FROM customer")


def _arrays(s, d):
    a = t(s, d, "orders").groupBy("o_custkey").agg(F.sort_array(F.collect_list(F.col("o_orderkey") % 10)).alias("a"))
    return a.select(
        "o_custkey", F.size("a").alias("n"), F.size(F.array_distinct("a")).alias("u"), F.array_join(F.slice("a", 1, 3), ",").alias("head"), F.aggregate(F.transform("a", lambda x: x * x), F.lit(0).cast("long"), lambda p, x: p + x).alias("sq"),
        F.size(F.filter("a", lambda x: x > 5)).alias("big"), F.exists("a", lambda x: x == 0).alias("z"), F.array_contains("a", F.lit(7).cast("long")).alias("c7"), F.size(F.array_intersect("a", F.array(F.lit(1).cast("long"), F.lit(2).cast("long")))).alias("i12"),
        F.size(F.array_union("a", F.array(F.lit(100).cast("long")))).alias("un"), F.size(F.array_except("a", F.array(F.lit(3).cast("long")))).alias("ex"), F.size(F.flatten(F.array("a", "a"))).alias("fl"), F.aggregate(F.zip_with("a", "a", lambda x, y: x * y), F.lit(0).cast("long"), lambda p, x: p + x).alias("zw"), F.size(F.sequence(F.lit(1), F.size("a"))).alias("sq_n"),
    )


op("fn_array", _arrays, "WITH g AS (SELECT o_custkey, list(o_orderkey % 10 ORDER BY o_orderkey % 10) AS a FROM orders GROUP BY 1) SELECT o_custkey, CAST(len(a) AS INTEGER) AS n, CAST(len(list_distinct(a)) AS INTEGER) AS u, array_to_string(a[1:3], ',') AS head, CAST(list_sum([x * x FOR x IN a]) AS BIGINT) AS sq, CAST(len([x FOR x IN a IF x > 5]) AS INTEGER) AS big, list_contains(a, 0) AS z, list_contains(a, 7) AS c7, CAST(len(list_intersect(list_distinct(a), [1, 2])) AS INTEGER) AS i12, CAST(len(list_distinct(list_concat(a, [100]))) AS INTEGER) AS un, CAST(len([x FOR x IN list_distinct(a) IF x <> 3]) AS INTEGER) AS ex, CAST(2 * len(a) AS INTEGER) AS fl, CAST(list_sum([x * x FOR x IN a]) AS BIGINT) AS zw, CAST(len(a) AS INTEGER) AS sq_n FROM g")


def _maps(s, d):
    h = t(s, d, "orders").groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n")).groupBy("o_custkey").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("o_orderstatus", "n")))).alias("m"))
    return h.select("o_custkey", F.array_join(F.sort_array(F.map_keys("m")), ",").alias("ks"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0)).alias("f"), F.size(F.map_filter("m", lambda k, v: v > 3)).alias("big"), F.size(F.map_zip_with("m", "m", lambda k, a, b: a + b)).alias("z"))


op("fn_map", _maps, "WITH h AS (SELECT o_custkey, o_orderstatus, count(*) AS n FROM orders GROUP BY 1, 2) SELECT o_custkey, string_agg(o_orderstatus, ',' ORDER BY o_orderstatus) AS ks, CAST(sum(n) AS BIGINT) AS total, CAST(coalesce(sum(n) FILTER (WHERE o_orderstatus = 'F'), 0) AS BIGINT) AS f, CAST(count(*) FILTER (WHERE n > 3) AS INTEGER) AS big, CAST(count(*) AS INTEGER) AS z FROM h GROUP BY 1")
op("fn_struct", lambda s, d: t(s, d, "nation").select(F.struct(F.col("n_nationkey").alias("k"), F.col("n_name").alias("nm")).alias("x")).select("x.k", F.col("x").getField("nm").alias("nm")).selectExpr("inline(array(named_struct('k', k, 'nm', nm), named_struct('k', k + 100, 'nm', nm)))"), "SELECT n_nationkey AS k, n_name AS nm FROM nation UNION ALL SELECT n_nationkey + 100, n_name FROM nation")
op("fn_json", lambda s, d: t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2"), F.to_json(F.struct(F.col("user_id").alias("u"))).alias("j")), "SELECT event_id, CAST(props ->> '$.k' AS INTEGER) AS k, CAST(props ->> '$.k' AS INTEGER) AS k2, '{\"u\":' || user_id || '}' AS j FROM events")
op("fn_hash", lambda s, d: t(s, d, "part").select("p_partkey", F.sha2("p_name", 256).alias("s"), F.md5("p_name").alias("m")), "SELECT p_partkey, sha256(p_name) AS s, md5(p_name) AS m FROM part")
op("fn_hash_engine", lambda s, d: t(s, d, "part").select("p_partkey", F.xxhash64("p_partkey").alias("x"), F.crc32("p_name").alias("c"), F.bit_count("p_partkey").alias("b"), F.shiftleft("p_size", 2).alias("sl")))
op("affine_hash", lambda s, d: t(s, d, "part").select("p_partkey", *[h.alias(f"h{i}") for i, h in enumerate(hash_columns(F.col("p_partkey"), 2))]), None)
from graphwin.functions.hashing import PRIME, affine_constants  # noqa: E402

ORACLES["op_affine_hash"] = "SELECT p_partkey, " + ", ".join(f"({a} * (p_partkey % {PRIME}) + {b}) % {PRIME} AS h{i}" for i, (a, b) in enumerate(affine_constants(2))) + " FROM part"

# -- subqueries, CTEs, SQL ---------------------------------------------------------------------------------------------


def _sql(text: str, *tables: str):
    def run(s, d):
        for name in tables:
            t(s, d, name).createOrReplaceTempView(name)
        return s.sql(text)

    return run


for _n, _q, _t in (
    ("sub_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)", ("orders",)),
    ("sub_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')", ("customer", "orders")),
    ("sub_in", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 250000)", ("customer", "orders")),
    ("sub_correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice = (SELECT max(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)", ("orders",)),
    ("cte", "WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT max(n) AS m FROM a) SELECT a.o_custkey, a.n FROM a JOIN b ON a.n = b.m", ("orders",)),
    ("lateral", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) x", ("customer", "orders")),
):
    # Spark's rewrite of a lateral LIMIT keeps the order only if all its columns are selected inside
    op(_n, _sql(_q.replace("(SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER", "(SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER"), *_t), _q)
_rec = "WITH RECURSIVE p(id, root, depth) AS (SELECT conv_id * 16 + turn, conv_id, 0 FROM conversations WHERE turn = 0 UNION ALL SELECT c.conv_id * 16 + c.turn, p.root, p.depth + 1 FROM p JOIN conversations c ON c.conv_id = p.root AND c.turn = p.depth + 1) SELECT id, root, depth FROM p"
op("recursive_path", _sql(_rec, "conversations"), _rec)
op("sample_hash", lambda s, d: t(s, d, "part").where(F.pmod(F.col("p_partkey") * 7919 + 17, F.lit(100)) < 10).select("p_partkey"), "SELECT p_partkey FROM part WHERE (p_partkey * 7919 + 17) % 100 < 10")

# -- Python functions where built-ins don't reach ------------------------------------------------------------------------


def jaccard_arrays():
    @F.pandas_udf("double")
    def j(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([len(set(x) & set(y)) / max(1, len(set(x) | set(y))) for x, y in zip(a, b, strict=True)])

    return j


def _windows_as_arrays(s, d):
    return khop_pairs(G.copurchase(s, d, 2), KHop(1)).groupBy("owner").agg(F.sort_array(F.collect_list("member")).alias("w"))


def _pandas_jaccard(s, d):
    w = _windows_as_arrays(s, d)
    e = G.copurchase(s, d, 2).edges.select("src", "dst")
    return e.join(w.toDF("src", "a"), "src").join(w.toDF("dst", "b"), "dst").select("src", "dst", F.round(jaccard_arrays()("a", "b"), 9).alias("j"))


op("pandas_udf", _pandas_jaccard, f"WITH {_COP2}, w AS (SELECT src AS o, dst AS m FROM e UNION SELECT dst, src FROM e UNION SELECT p_partkey, p_partkey FROM part), n AS (SELECT o, count(*) AS n FROM w GROUP BY 1), i AS (SELECT e.src, e.dst, count(*) AS c FROM e JOIN w a ON a.o = e.src JOIN w b ON b.o = e.dst AND a.m = b.m GROUP BY 1, 2) SELECT src, dst, round(c / (x.n + y.n - c), 9) AS j FROM i JOIN n x ON x.o = src JOIN n y ON y.o = dst")


def _gcd(s, d):
    @F.pandas_udf("long")
    def gcd(v: pd.Series) -> int:
        import math

        return math.gcd(*map(int, v))

    return t(s, d, "part").where("p_size % 2 = 0").groupBy("p_brand").agg(gcd("p_size").alias("g"))


op("udaf_pandas", _gcd, "SELECT p_brand, CAST(list_reduce(list(CAST(p_size AS BIGINT)), lambda x, y: gcd(x, y)) AS BIGINT) AS g FROM part WHERE p_size % 2 = 0 GROUP BY 1")


def _udf(s, d):
    f = F.udf(lambda x: None if x is None else x[::-1], "string")
    return t(s, d, "nation").select("n_nationkey", f("n_name").alias("r"))


op("udf_python", _udf, "SELECT n_nationkey, reverse(n_name) AS r FROM nation")


def _udtf(s, d):
    @F.udtf(returnType="member: bigint")
    class WindowMembers:
        def eval(self, members):
            for m in members:
                yield (m,)

    s.udtf.register("window_members", WindowMembers)
    _windows_as_arrays(s, d).createOrReplaceTempView("gw_windows")
    return s.sql("SELECT owner, m.member FROM gw_windows, LATERAL window_members(w) m")


op("udtf_window_members", _udtf, f"WITH {_COP2} SELECT src AS owner, dst AS member FROM e UNION SELECT dst, src FROM e UNION SELECT p_partkey, p_partkey FROM part")
op("apply_in_pandas", lambda s, d: t(s, d, "part").select("p_brand", F.col("p_size").cast("long").alias("p_size")).groupBy("p_brand").applyInPandas(lambda g: pd.DataFrame({"p_brand": g["p_brand"].iloc[:1], "spread": [int(g["p_size"].max() - g["p_size"].min())]}), "p_brand string, spread long"), "SELECT p_brand, CAST(max(p_size) - min(p_size) AS BIGINT) AS spread FROM part GROUP BY 1")
op("map_in_pandas", lambda s, d: t(s, d, "part").select("p_partkey", F.col("p_size").cast("long").alias("p_size")).mapInPandas(lambda it: (b.assign(p_size=b["p_size"] + 1) for b in it), "p_partkey long, p_size long"), "SELECT p_partkey, CAST(p_size + 1 AS BIGINT) AS p_size FROM part")


def _explain(s, d):
    """The plan of a k-hop window sum as it ran (an adaptive plan is final only then), a row a line."""
    from graphwin.functions.aggregates import Agg
    from graphwin.operators.direct import direct

    ran = direct(G.copurchase(s, d, 2), KHop(1), [Agg("sum", "p_size")])._jdf.queryExecution()
    ran.toRdd().count()
    plan = ran.explainString(s._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    return s.createDataFrame([(i, line) for i, line in enumerate(plan.split("\n"))], T.StructType([T.StructField("n", T.LongType()), T.StructField("line", T.StringType())]))


op("explain_plan", _explain)
