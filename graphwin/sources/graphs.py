"""Graphs over the given tables, arithmetic graphs, and literal ones."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphwin.model import PropertyGraph

#: Offsets that keep ids of different kinds apart.
KIND = 10**12
MODULUS = 1_000_003
#: Vectors of a cell, of which two meet in a group.
CELL = 16_384


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(c: str | Column) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    return F.round(c * 100).cast("long")


def _upper(df: DataFrame, a: str, b: str) -> DataFrame:
    return df.where(F.col(a) < F.col(b)).select(F.col(a).alias("src"), F.col(b).alias("dst"))


def copurchase(spark: SparkSession, sf_dir: str, t: int = 1) -> PropertyGraph:
    """Parts that share at least t orders. One order's lines are few, so the self-join stays linear in the lines."""
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").cast("long").alias("p_size"), "p_brand")
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    both = line.join(line.withColumnRenamed("l_partkey", "_other"), "l_orderkey").where("l_partkey < _other")
    e = both.groupBy(F.col("l_partkey").alias("src"), F.col("_other").alias("dst")).agg(F.count("*").alias("orders")).where(F.col("orders") >= t)
    if t > 1:
        return PropertyGraph(parts, e, False, f"copurchase{t}")
    dealt = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").repartition("l_orderkey")
    met = dealt.select("l_orderkey", F.col("l_partkey").alias("src")).join(dealt.select("l_orderkey", F.col("l_partkey").alias("dst")), "l_orderkey").where("src <> dst").select("src", "dst")
    return PropertyGraph(parts, e, False, "copurchase1", repeated=met)


def relay(spark: SparkSession, sf_dir: str, priorities: list[str] | None = None) -> PropertyGraph:
    """Customer of an order to the customer of the next one in time. The order of all orders comes from day buckets:
    within a day by lead(), across days by the first order of the next day, so no task sorts them all."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    if priorities:
        o = o.where(F.col("o_orderpriority").isin(priorities))
    o = o.withColumn("_day", F.to_date("o_orderdate"))
    key = F.struct("o_orderdate", "o_orderkey")
    in_day = Window.partitionBy("_day").orderBy("o_orderdate", "o_orderkey")
    days = o.groupBy("_day").agg(F.min(F.struct(key.alias("k"), F.col("o_custkey").alias("c"))).alias("first"))
    days = days.select("_day", F.lead("first.c").over(Window.orderBy("_day")).alias("_next_day"))  # one row a day
    nxt = F.coalesce(F.lead("o_custkey").over(in_day), F.col("_next_day"))
    e = o.join(days, "_day").select(F.col("o_custkey").alias("src"), nxt.alias("dst")).where("dst IS NOT NULL AND src <> dst")
    v = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), cents("c_acctbal").alias("cents"), "c_mktsegment")
    return PropertyGraph(v, e.distinct(), True, "relay", repeated=e)


def trade(spark: SparkSession, sf_dir: str, lo: str = "1997-01-01", hi: str = "1997-07-01") -> PropertyGraph:
    """Customers and the suppliers they bought from in a span; only vertices with an edge."""
    line = table(spark, sf_dir, "lineitem").where((F.col("l_shipdate") >= F.lit(lo).cast("timestamp_ntz")) & (F.col("l_shipdate") < F.lit(hi).cast("timestamp_ntz"))).select("l_orderkey", "l_suppkey")
    e = line.join(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    e = e.select((F.col("o_custkey") + KIND).alias("src"), (F.col("l_suppkey") + 2 * KIND).alias("dst")).distinct()
    v = table(spark, sf_dir, "customer").select((F.col("c_custkey") + KIND).alias("id"), cents("c_acctbal").alias("cents"), F.lit("customer").alias("kind"))
    v = v.union(table(spark, sf_dir, "supplier").select(F.col("s_suppkey") + 2 * KIND, cents("s_acctbal"), F.lit("supplier")))
    ends = e.select(F.col("src").alias("id")).union(e.select("dst"))
    return PropertyGraph(v.join(ends, "id", "left_semi"), e, False, "trade")


def cosupply(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Suppliers that share an order."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").distinct()
    e = line.join(line.withColumnRenamed("l_suppkey", "_other"), "l_orderkey").where("l_suppkey < _other").select(F.col("l_suppkey").alias("src"), F.col("_other").alias("dst")).distinct()
    v = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), cents("s_acctbal").alias("cents"), F.col("s_nationkey").alias("nation"))
    return PropertyGraph(v, e, False, "cosupply")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, token): distinct site-relative hrefs."""
    p = table(spark, sf_dir, "pages")
    return p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1))).alias("token")).distinct()


def weblinks(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Pages and the tokens they link to; token ids are a dense rank by name."""
    links = page_links(spark, sf_dir)
    ids = dict_encode(links, "token").select("token", (F.col("code") + KIND).alias("dst"))
    e = links.join(ids, "token").select(F.col("page_id").alias("src"), "dst")
    v = table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), F.length("html").cast("long").alias("size"), F.lit("page").alias("kind"))
    return PropertyGraph(v.union(ids.select(F.col("dst"), F.lit(0).cast("long"), F.lit("token"))), e, True, "weblinks")


def dict_encode(df: DataFrame, col: str) -> DataFrame:
    """(col, code): the value's rank from 0 in order, found in hash-free range partitions: each is ranked by itself and
    shifted by the counts of those before it."""
    values = df.select(col).distinct()
    parts = values.repartitionByRange(F.col(col)).withColumn("_part", F.spark_partition_id())
    from graphwin.session import materialize

    parts = materialize(parts, "codes")
    before = parts.groupBy("_part").agg(F.count("*").alias("_n"))
    before = before.select("_part", F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(col)) - 1
    return parts.withColumn("_r", inside).join(before, "_part").select(col, (F.col("_r") + F.col("_before")).cast("long").alias("code"))


def community(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Documents of one source and language: cliques."""
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("n_chars").cast("long").alias("n_chars"), "lang", "source")
    e = d.select(F.col("id").alias("src"), "lang", "source").join(d.select(F.col("id").alias("dst"), "lang", "source"), ["lang", "source"]).where("src < dst").select("src", "dst")
    known = F.col("lang").isNotNull() & F.col("source").isNotNull()
    twins = d.select("id", F.when(known, F.min("id").over(Window.partitionBy("lang", "source"))).otherwise(F.col("id")).alias("rep"))
    none = d.select(F.col("id").alias("src"), F.col("id").alias("dst")).where(F.lit(False))
    return PropertyGraph(d.select("id", "n_chars", "lang"), e, False, "community", twins=twins, between=none)


def similar(spark: SparkSession, sf_dir: str, threshold: float = 0.3) -> PropertyGraph:
    """Embeddings with a cosine of at least the threshold. All pairs are compared, as products of matrices of two cells of
    the vectors, a cell pair a group."""
    v = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("label").cast("long").alias("label"), F.col("embedding").alias("e"))
    known = v.where("e IS NOT NULL").select("id", "e")
    cells = max(1, -(-known.count() // CELL))
    mine = F.pmod(F.xxhash64("id"), F.lit(cells)).cast("int")
    met = known.withColumn("cell", mine).withColumn("_o", F.explode(F.sequence(F.lit(0), F.lit(cells - 1))))
    met = met.select("id", "e", "cell", F.least("cell", "_o").alias("i"), F.greatest("cell", "_o").alias("j"))
    return PropertyGraph(v.select("id", "label"), met.groupBy("i", "j").applyInArrow(_similar_pairs(threshold), "src long, dst long"), False, "similar")


def _similar_pairs(threshold: float):
    def run(key, table):
        import math

        import numpy as np
        import pyarrow as pa

        ids, cell = table.column("id").to_numpy(), table.column("cell").to_numpy()
        x = table.column("e").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype("float64").reshape(len(ids), -1)
        with np.errstate(invalid="ignore", divide="ignore"):
            x = x / np.sqrt((x * x).sum(axis=1))[:, None]
        i, j = key[0].as_py(), key[1].as_py()
        left, right = np.flatnonzero(cell == i), np.flatnonzero(cell == j)
        src, dst = [], []
        for lo in range(0, len(left), 256):
            rows = left[lo:lo + 256]
            c = x[rows] @ x[right].T
            a, b = np.nonzero(c >= threshold - 1e-9)
            sure = c[a, b] >= threshold + 1e-9
            for k in np.flatnonzero(~sure).tolist():  # too near for sums in any order
                sure[k] = math.fsum((x[rows[a[k]]] * x[right[b[k]]]).tolist()) >= threshold
            a, b = ids[rows[a[sure]]], ids[right[b[sure]]]
            if i == j:
                a, b = a[a < b], b[a < b]
            src.append(np.minimum(a, b))
            dst.append(np.maximum(a, b))
        none = np.zeros(0, "int64")
        return pa.table({"src": np.concatenate([none, *src]), "dst": np.concatenate([none, *dst])})

    return run


def catalog(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Region, nation, customer and supplier, part, order: a shallow DAG with many parents."""
    r, n, c, s, p, o, l = (table(spark, sf_dir, t) for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"))
    at = lambda k, col: (F.col(col).cast("long") + k * KIND)
    one = F.lit(1).cast("long")
    v = (
        r.select(at(1, "r_regionkey").alias("id"), one.alias("cents"), F.lit("region").alias("kind"))
        .union(n.select(at(2, "n_nationkey"), one, F.lit("nation")))
        .union(c.select(at(3, "c_custkey"), cents("c_acctbal"), F.lit("customer")))
        .union(s.select(at(4, "s_suppkey"), cents("s_acctbal"), F.lit("supplier")))
        .union(p.select(at(5, "p_partkey"), cents("p_retailprice"), F.lit("part")))
        .union(o.select(at(6, "o_orderkey"), cents("o_totalprice"), F.lit("orders")))
    )
    e = (
        n.select(at(1, "n_regionkey").alias("src"), at(2, "n_nationkey").alias("dst"))
        .union(c.select(at(2, "c_nationkey"), at(3, "c_custkey")))
        .union(s.select(at(2, "s_nationkey"), at(4, "s_suppkey")))
        .union(o.select(at(3, "o_custkey"), at(6, "o_orderkey")))
        .union(l.select(at(5, "l_partkey"), at(6, "l_orderkey")).distinct())
        .union(l.select(at(4, "l_suppkey"), at(6, "l_orderkey")).distinct())
    )
    return PropertyGraph(v, e, True, "catalog")


def _event_vertices(ev: DataFrame) -> DataFrame:
    return ev.select(F.col("event_id").alias("id"), cents("value").alias("cents"), "event_type", "user_id")


def eventchain(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """An event to the user's next one: paths."""
    ev = table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = ev.select(F.lag("event_id").over(w).alias("src"), F.col("event_id").alias("dst"), "user_id").where("src IS NOT NULL")
    return PropertyGraph(_event_vertices(ev), e, True, "eventchain", "user_id")


def eventbranch(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """An event to the next of the same user and type, and to the user's third next: at most two parents."""
    ev = table(spark, sf_dir, "events")
    a, b = Window.partitionBy("user_id", "event_type").orderBy("ts", "event_id"), Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = ev.select(F.lag("event_id").over(a).alias("src"), F.col("event_id").alias("dst"), "user_id").union(ev.select(F.lag("event_id", 3).over(b), "event_id", "user_id"))
    return PropertyGraph(_event_vertices(ev), e.where("src IS NOT NULL").distinct(), True, "eventbranch", "user_id")


def dialogue(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """A conversation's turns one after the other."""
    c = table(spark, sf_dir, "conversations")
    node = F.col("conv_id") * 16 + F.col("turn")
    w = Window.partitionBy("conv_id").orderBy("turn")
    e = c.select(F.lag(node).over(w).alias("src"), node.alias("dst")).where("src IS NOT NULL")
    return PropertyGraph(c.select(node.alias("id"), F.length("text").cast("long").alias("chars"), "role"), e, True, "dialogue")


def lineage(spark: SparkSession, sf_dir: str, priority: str | None = None, status: str | None = None, each_priority: bool = False) -> PropertyGraph:
    """An order to the customer's next, and to the next with the same part, of all orders or those of one priority or
    status: deep, with windows that grow with the square of the orders kept. each_priority: all orders, each in the lineage of
    its own priority, so the graph is that of every priority side by side."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_totalprice", "o_orderstatus", "o_orderpriority")
    if priority:
        o = o.where(F.col("o_orderpriority") == priority)
    if status:
        o = o.where(F.col("o_orderstatus") == status)
    parts = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct().join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    side = ["o_orderpriority"] * each_priority
    a, b = Window.partitionBy("o_custkey", *side).orderBy("o_orderdate", "o_orderkey"), Window.partitionBy("l_partkey", *side).orderBy("o_orderdate", "o_orderkey")
    e = o.select(F.lag("o_orderkey").over(a).alias("src"), F.col("o_orderkey").alias("dst")).union(parts.select(F.lag("o_orderkey").over(b), "o_orderkey")).where("src IS NOT NULL")
    return PropertyGraph(o.select(F.col("o_orderkey").alias("id"), cents("o_totalprice").alias("cents"), "o_orderstatus"), e.distinct(), True, "lineage", repeated=e)


def _arithmetic(v: Column, j: Column) -> Column:
    return F.pmod(v * 7919 + j * 104_729 + 17, F.lit(MODULUS))


def synthdag(spark: SparkSession, n: int, d: int) -> PropertyGraph:
    """d arithmetic parents for each of n vertices, equal in any engine; attr is the id itself."""
    v = spark.range(n)
    e = spark.range(1, n).select(F.col("id").alias("dst"), F.explode(F.sequence(F.lit(0), F.lit(d - 1)).cast("array<bigint>")).alias("j"))
    e = e.select(F.pmod(_arithmetic(F.col("dst"), F.col("j")), F.col("dst")).alias("src"), "dst")
    return PropertyGraph(v.select("id", (F.col("id") % 97).alias("attr")), e.distinct(), True, f"synthdag_{n}_{d}", repeated=e)


def synthrand(spark: SparkSession, n: int, d: int) -> PropertyGraph:
    """An undirected graph of mean degree about d, close to a random one."""
    e = spark.range(n).select(F.col("id").alias("a"), F.explode(F.sequence(F.lit(0), F.lit(max(d // 2, 1) - 1)).cast("array<bigint>")).alias("j"))
    x = _arithmetic(F.col("a"), F.col("j"))
    e = e.select("a", x.alias("x")).select("a", F.pmod(F.pmod(F.col("x") * F.col("x") + 31 * F.col("x") + 7, F.lit(MODULUS)), F.lit(n)).alias("b")).where("a <> b")
    met = e.select("a", "b").union(e.select("b", "a")).toDF("src", "dst")
    e = e.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()
    return PropertyGraph(spark.range(n).select("id", (F.col("id") % 97).alias("attr")), e, False, f"synthrand_{n}_{d}", repeated=met)


def literal(spark: SparkSession, edges: list[tuple[int, int]], vertices: list[int] | None = None, directed: bool = False, attrs: dict[int, int] | None = None, name: str = "literal") -> PropertyGraph:
    ids = sorted(set(vertices or []) | {x for e in edges for x in e})
    v = spark.createDataFrame([(i, (attrs or {}).get(i, i)) for i in ids], "id long, attr long")
    return PropertyGraph(v, spark.createDataFrame(edges, "src long, dst long"), directed, name)


# The two worked examples; letters A, B, ... are vertices 0, 1, ...
TINY_SOCIAL = "AB AC AD AE AF BD BF CD CE CF".split()
TINY_PATH = "AD BD DE CE DH".split()


def tinysocial(spark: SparkSession) -> PropertyGraph:
    return literal(spark, [(ord(e[0]) - 65, ord(e[1]) - 65) for e in TINY_SOCIAL], name="tinysocial")


def tinypath(spark: SparkSession) -> PropertyGraph:
    return literal(spark, [(ord(e[0]) - 65, ord(e[1]) - 65) for e in TINY_PATH], directed=True, name="tinypath")
