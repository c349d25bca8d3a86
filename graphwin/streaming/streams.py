"""Streaming operators over replayed events, each ending in the table it has built, so batch SQL can check it."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphwin.functions.aggregates import Agg
from graphwin.model import KHop
from graphwin.operators import blockindex as sb
from graphwin.operators import updates
from graphwin.session import materialize, shared_dir, ship
from graphwin.sources import graphs as G

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, fn, sql: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return fn(spark, sf_dir)

    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def replay(spark: SparkSession, rows: DataFrame, files: int = 1) -> DataFrame:
    """A file stream over rows written to the shared folder, `files` of them in the rows' own split, one a trigger."""
    stored = materialize(rows.repartition(files), "replay")
    return spark.readStream.schema(stored.schema).option("maxFilesPerTrigger", 1).parquet(stored.shared_path)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", G.cents("value").alias("cents"))


def run_to_end(stream: DataFrame, mode: str, checkpoint: str | None = None) -> DataFrame:
    """Everything that is there, then stop; the rows go to the shared folder by foreachBatch in complete and update mode,
    by a file sink in append mode."""
    spark = stream.sparkSession
    out = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    ck = checkpoint or f"{out}-ck"
    w = stream.writeStream.outputMode(mode).option("checkpointLocation", ck).trigger(availableNow=True)
    if mode == "append":
        q = w.format("parquet").option("path", out).start()
    else:
        q = w.foreachBatch(lambda df, n: df.withColumn("_batch", F.lit(n)).write.mode("overwrite").parquet(f"{out}/_b={n:06d}")).start()
    q.awaitTermination()
    if mode == "append":
        return spark.read.schema(stream.schema).parquet(out)
    return spark.read.option("basePath", out).parquet(out).drop("_b")


def last_batch(df: DataFrame) -> DataFrame:
    return df.join(F.broadcast(df.agg(F.max("_batch").alias("_batch"))), "_batch", "left_semi").drop("_batch")


def _us(c: str):
    return F.unix_micros(c)


def _tumbling(s, d):
    w = replay(s, events(s, d)).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    return last_batch(run_to_end(w.select(_us("window.start").alias("start_us"), "event_type", "n", "cents"), "complete"))


_add("st_tumbling", _tumbling, "SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01')) AS start_us, event_type, count(*) AS n, CAST(sum(CAST(ROUND(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1, 2")


def _sliding(s, d):
    w = replay(s, events(s, d)).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return last_batch(run_to_end(w.select(_us("window.start").alias("start_us"), "n"), "complete"))


_add("st_sliding", _sliding, "SELECT epoch_us(b) - o * 86400000000 AS start_us, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS b FROM events), (VALUES (0), (1)) x(o) GROUP BY 1")


def _session(s, d):
    w = replay(s, events(s, d)).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n"))
    return last_batch(run_to_end(w.select("user_id", _us("session_window.start").alias("start_us"), "n"), "complete"))


_add("st_session", _session, "WITH x AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM x) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM y GROUP BY user_id, g")


def _late(s, d):
    """Newest first, so what comes after the watermark is late and dropped; rows only."""
    ev = events(s, d)
    w = replay(s, ev, 4).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return run_to_end(w.select(_us("window.start").alias("start_us"), "n"), "append")


_add("st_watermark_late", _late)


def _dedup(s, d):
    ev = events(s, d)
    twice = replay(s, ev.union(ev)).withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"])
    return run_to_end(twice.select("event_id", "user_id"), "append")


_add("st_dedup", _dedup, "SELECT event_id, user_id FROM events")


def _static_join(s, d):
    """Attribute changes meet the index's members: how many changes each block gets. The index itself stays."""
    g = G.relay(s, d, ["1-URGENT"])
    ix = sb.build_block_index(g, KHop(1))
    changes = replay(s, events(s, d)).join(ix.members, F.col("user_id") == F.col("member"))
    return last_batch(run_to_end(changes.groupBy("member").agg(F.count("*").alias("n"), F.sum("cents").alias("delta")), "complete")).join(ix.members.groupBy("member").agg(F.count("*").alias("blocks")), "member").select("member", (F.col("n") / F.col("blocks")).cast("long").alias("n"), (F.col("delta") / F.col("blocks")).cast("long").alias("delta"))


_add("st_static_join", _static_join, "SELECT user_id AS member, count(*) AS n, CAST(sum(CAST(ROUND(value * 100) AS BIGINT)) AS BIGINT) AS delta FROM events WHERE user_id IN (SELECT c_custkey FROM customer) GROUP BY 1")


def _stream_join(s, d):
    ev = events(s, d)
    a = replay(s, ev.where("event_type = 'error'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))).withWatermark("ta", "1 hour")
    b = replay(s, ev.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))).withWatermark("tb", "1 hour")
    return run_to_end(a.join(b, F.expr("ua = ub AND tb > ta AND tb <= ta + INTERVAL 12 HOURS")).select("a", "b"), "append")


_add("st_stream_join", _stream_join, "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 12 HOUR WHERE x.event_type = 'error' AND y.event_type = 'purchase'")


def _stateful(s, d):
    """Running partials per user in keyed state."""

    def update(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0)
        for r in rows:
            n, total = n + len(r), total + int(r["cents"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "cents": [total]})

    out = replay(s, events(s, d), 3).groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, cents long", "n long, cents long", "update", GroupStateTimeout.NoTimeout)
    return run_to_end(out, "update").groupBy("user_id").agg(F.max_by("n", "_batch").alias("n"), F.max_by("cents", "_batch").alias("cents"))


_add("st_stateful", _stateful, "SELECT user_id, count(*) AS n, CAST(sum(CAST(ROUND(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1")


def _foreach_batch(s, d):
    """Edge insertions arrive in batches; each updates the block index. A batch number is applied once."""
    g = G.copurchase(s, d, 3)
    change = materialize(g.edges.where((F.col("src") + F.col("dst")) % 5 == 0).select(F.lit("+").alias("op"), "src", "dst"), "changes")
    start = updates.changed_graph(g, change.withColumn("op", F.lit("-")))
    state = {"index": sb.build_block_index(start, KHop(1)), "graph": start, "done": set()}

    def apply(df: DataFrame, n: int) -> None:
        if n in state["done"] or df.isEmpty():
            return
        state["index"], state["graph"] = updates.update_block_index(state["index"], state["graph"], materialize(df, "batch"))
        state["done"].add(n)

    ck = f"{shared_dir(s)}/ck-{uuid.uuid4().hex}"
    replay(s, change).writeStream.foreachBatch(apply).option("checkpointLocation", ck).trigger(availableNow=True).start().awaitTermination()
    return sb.block_query(state["index"], state["graph"], [Agg("sum", "p_size", "sum_size")])


_add("st_foreach_batch", _foreach_batch, "WITH l AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem), e AS (SELECT a.l_partkey AS src, b.l_partkey AS dst FROM l a JOIN l b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) >= 3), w AS (SELECT src AS o, dst AS m FROM e UNION SELECT dst, src FROM e UNION SELECT p_partkey, p_partkey FROM part) SELECT o AS id, CAST(sum(p_size) AS BIGINT) AS sum_size FROM w JOIN part ON m = p_partkey GROUP BY 1")


def _restart(s, d):
    """Half of the events, stop, the rest with the same checkpoint: each is counted once."""
    ev = events(s, d)
    half = materialize(ev.where("event_id % 2 = 0"), "half")
    stream = s.readStream.schema(half.schema).parquet(half.shared_path).groupBy("event_type").agg(F.count("*").alias("n"))
    ck = f"{shared_dir(s)}/ck-{uuid.uuid4().hex}"
    run_to_end(stream, "complete", ck)
    ev.where("event_id % 2 = 1").write.mode("append").parquet(half.shared_path)
    return last_batch(run_to_end(stream, "complete", ck))


_add("st_modes", _restart, "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
