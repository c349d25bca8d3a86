"""Registered window queries with their SQL equivalents.

Every strategy of a workload shares one SQL text: the result may not depend on the index."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphwin.functions.aggregates import Agg
from graphwin.functions.hashing import PRIME, affine_constants
from graphwin.model import KHop, PropertyGraph, Topological, VertexWindowFunction, VertexWindowQuery
from graphwin.operators import blockindex as sb
from graphwin.operators import deltaindex as pd
from graphwin.operators import updates
from graphwin.operators.direct import direct, propagate, running_window
from graphwin.operators.overlay import build_overlay, overlay_query
from graphwin.operators.reach import ancestor_windows_by_level, topo_levels, topo_levels_by_peeling, window_pairs
from graphwin.plans import measures
from graphwin.plans.planner import window_volume
from graphwin.plans.query import top
from graphwin.plans.sqltext import graph_window_sql
from graphwin.session import ship
from graphwin.sources import graphs as G

Build = Callable[[SparkSession, str], PropertyGraph]
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

# -- SQL of the graphs: e(src, dst) and v(id, ...) ----------------------------------------------------------------------

K = G.KIND
_CENTS = "CAST(ROUND({} * 100) AS BIGINT)"


def _copurchase_sql(t: int) -> str:
    return f"""v AS (SELECT p_partkey AS id, CAST(p_size AS BIGINT) AS p_size, p_brand FROM part),
l AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem),
e AS (SELECT a.l_partkey AS src, b.l_partkey AS dst, count(*) AS orders FROM l a JOIN l b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) >= {t})"""


_RELAY_SQL = f"""v AS (SELECT c_custkey AS id, {_CENTS.format('c_acctbal')} AS cents, c_mktsegment FROM customer),
e AS (SELECT DISTINCT src, dst FROM (SELECT o_custkey AS src, lead(o_custkey) OVER (ORDER BY o_orderdate, o_orderkey) AS dst FROM orders WHERE TRUE {{filter}}) WHERE dst IS NOT NULL AND src <> dst)"""
_TRADE_SQL = f"""e AS (SELECT DISTINCT o_custkey + {K} AS src, l_suppkey + {2 * K} AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1997-07-01'),
v AS (SELECT * FROM (SELECT c_custkey + {K} AS id, {_CENTS.format('c_acctbal')} AS cents, 'customer' AS kind FROM customer UNION ALL SELECT s_suppkey + {2 * K}, {_CENTS.format('s_acctbal')}, 'supplier' FROM supplier) WHERE id IN (SELECT src FROM e UNION SELECT dst FROM e))"""
_COSUPPLY_SQL = f"""v AS (SELECT s_suppkey AS id, {_CENTS.format('s_acctbal')} AS cents FROM supplier), l AS (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem),
e AS (SELECT DISTINCT a.l_suppkey AS src, b.l_suppkey AS dst FROM l a JOIN l b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey)"""
_WEBLINKS_SQL = f"""pl AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS token FROM pages),
ids AS (SELECT token, {K} + row_number() OVER (ORDER BY encode(token)) - 1 AS tid FROM (SELECT DISTINCT token FROM pl)),
e AS (SELECT page_id AS src, tid AS dst FROM pl JOIN ids USING (token)),
v AS (SELECT page_id AS id, CAST(length(html) AS BIGINT) AS size FROM pages UNION ALL SELECT tid, 0 FROM ids)"""
_COMMUNITY_SQL = """v AS (SELECT doc_id AS id, CAST(n_chars AS BIGINT) AS n_chars, lang FROM documents),
e AS (SELECT a.doc_id AS src, b.doc_id AS dst FROM documents a JOIN documents b ON a.lang = b.lang AND a.source = b.source AND a.doc_id < b.doc_id)"""
_CATALOG_SQL = f"""v AS (SELECT r_regionkey + {K} AS id, CAST(1 AS BIGINT) AS cents, 'region' AS kind FROM region UNION ALL SELECT n_nationkey + {2 * K}, 1, 'nation' FROM nation
UNION ALL SELECT c_custkey + {3 * K}, {_CENTS.format('c_acctbal')}, 'customer' FROM customer UNION ALL SELECT s_suppkey + {4 * K}, {_CENTS.format('s_acctbal')}, 'supplier' FROM supplier
UNION ALL SELECT p_partkey + {5 * K}, {_CENTS.format('p_retailprice')}, 'part' FROM part UNION ALL SELECT o_orderkey + {6 * K}, {_CENTS.format('o_totalprice')}, 'orders' FROM orders),
e AS (SELECT n_regionkey + {K} AS src, n_nationkey + {2 * K} AS dst FROM nation UNION ALL SELECT c_nationkey + {2 * K}, c_custkey + {3 * K} FROM customer UNION ALL SELECT s_nationkey + {2 * K}, s_suppkey + {4 * K} FROM supplier
UNION ALL SELECT o_custkey + {3 * K}, o_orderkey + {6 * K} FROM orders UNION ALL SELECT DISTINCT l_partkey + {5 * K}, l_orderkey + {6 * K} FROM lineitem UNION ALL SELECT DISTINCT l_suppkey + {4 * K}, l_orderkey + {6 * K} FROM lineitem)"""
_EVENTS_V = f"v AS (SELECT event_id AS id, {_CENTS.format('value')} AS cents, event_type FROM events)"
_CHAIN_SQL = f"{_EVENTS_V}, e AS (SELECT * FROM (SELECT lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src, event_id AS dst FROM events) WHERE src IS NOT NULL)"
_BRANCH_SQL = f"""{_EVENTS_V}, e AS (SELECT DISTINCT * FROM (SELECT lag(event_id) OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS src, event_id AS dst FROM events
UNION ALL SELECT lag(event_id, 3) OVER (PARTITION BY user_id ORDER BY ts, event_id), event_id FROM events) WHERE src IS NOT NULL)"""
_DIALOGUE_SQL = """v AS (SELECT conv_id * 16 + turn AS id, CAST(length(text) AS BIGINT) AS chars, role FROM conversations),
e AS (SELECT * FROM (SELECT lag(conv_id * 16 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS src, conv_id * 16 + turn AS dst FROM conversations) WHERE src IS NOT NULL)"""
_LINEAGE_SQL = f"""o AS (SELECT * FROM orders WHERE o_orderpriority = '1-URGENT'), v AS (SELECT o_orderkey AS id, {_CENTS.format('o_totalprice')} AS cents FROM o),
e AS (SELECT DISTINCT * FROM (SELECT lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS src, o_orderkey AS dst FROM o
UNION ALL SELECT lag(o_orderkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey), o_orderkey FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) JOIN o ON l_orderkey = o_orderkey) WHERE src IS NOT NULL)"""


# as many vertices as there are parts
_PARTS_SQL = "v AS (SELECT i AS id, i % 97 AS attr FROM (SELECT unnest(range((SELECT count(*) FROM part))) AS i))"


def _synthdag_sql(d: int) -> str:
    return f"{_PARTS_SQL}, e AS (SELECT DISTINCT ((v.id * 7919 + j.range * 104729 + 17) % {G.MODULUS}) % v.id AS src, v.id AS dst FROM v, range({d}) j WHERE v.id > 0)"


def _synthrand_sql(d: int) -> str:
    x = f"((a.id * 7919 + j.range * 104729 + 17) % {G.MODULUS})"
    return f"{_PARTS_SQL}, p AS (SELECT a.id AS a, (({x} * {x} + 31 * {x} + 7) % {G.MODULUS}) % (SELECT count(*) FROM part) AS b FROM v a, range({max(d // 2, 1)}) j), e AS (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM p WHERE a <> b)"


def _synthdag(d: int) -> Build:
    return lambda spark, sf_dir: G.synthdag(spark, G.table(spark, sf_dir, "part").count(), d)


def _synthrand(d: int) -> Build:
    return lambda spark, sf_dir: G.synthrand(spark, G.table(spark, sf_dir, "part").count(), d)


def _windows_sql(k: int, undirected: bool, direction: str = "out", include_self: bool = True) -> str:
    if undirected or direction == "both":
        arcs = "SELECT src, dst FROM e UNION SELECT dst, src FROM e"
    else:
        arcs = "SELECT src, dst FROM e" if direction == "out" else "SELECT dst AS src, src AS dst FROM e"
    out = f"arcs AS ({arcs} UNION SELECT id, id FROM v), w0 AS (SELECT id AS owner, id AS member FROM v)"
    for i in range(1, k + 1):
        out += f", w{i} AS (SELECT DISTINCT w.owner, a.dst AS member FROM w{i - 1} w JOIN arcs a ON w.member = a.src)"
    return out + f", w AS (SELECT owner, member FROM w{k}{'' if include_self else ' WHERE owner <> member'})"


_CLOSURE = "c(owner, member) AS (SELECT dst, src FROM e UNION SELECT e.dst, c.member FROM e JOIN c ON e.src = c.owner), w AS (SELECT owner, member FROM c UNION ALL SELECT id, id FROM v)"


def _khop(graph_sql: str, k: int, undirected: bool, body: str, direction: str = "out", include_self: bool = True) -> str:
    return f"WITH {graph_sql}, {_windows_sql(k, undirected, direction, include_self)} {body}"


def _topo(graph_sql: str, body: str) -> str:
    return f"WITH RECURSIVE {graph_sql}, {_CLOSURE} {body}"


def _sum_body(attr: str, alias: str) -> str:
    return f"SELECT owner AS id, CAST(sum({attr}) AS BIGINT) AS {alias} FROM w JOIN v ON member = v.id GROUP BY owner"


def _add(name: str, fn: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return fn(spark, sf_dir)

    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


# -- k-hop -------------------------------------------------------------------------------------------------------------


def _by_strategy(build: Build, window, aggs: list[Agg], strategy: str, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = build(spark, sf_dir)
        if strategy == "direct":
            return direct(g, window, aggs)
        if strategy in ("mc", "emc"):
            return sb.block_query_once(g, window, aggs, method=strategy, **options)
        if strategy == "overlay":
            return overlay_query(build_overlay(g, window, **options), g, aggs)
        if strategy == "propagate":
            return propagate(g, window, aggs[0])
        if strategy in ("level", "jump"):
            return pd.delta_query(pd.build_delta_index(g), g, aggs, strategy)
        raise ValueError(strategy)

    return run


_cop = lambda t: lambda s, d: G.copurchase(s, d, t)
_size = [Agg("sum", "p_size", "sum_size")]
for _k in (1, 2, 3, 4):
    for _s in ("direct", "mc", "emc", "overlay"):
        if (_s == "emc" and _k == 1) or (_s == "overlay" and _k > 2):
            continue
        _add(f"khop_{_s}_sum_copurchase_k{_k}", _by_strategy(_cop(2), KHop(_k), _size, _s, **({"iterations": 10} if _s == "overlay" else {})), _khop(_copurchase_sql(2), _k, True, _sum_body("p_size", "sum_size")))
_add("khop_direct_sum_copurchase_all_k1", _by_strategy(_cop(1), KHop(1), _size, "direct"), _khop(_copurchase_sql(1), 1, True, _sum_body("p_size", "sum_size")))
_add("khop_mc_sum_copurchase_all_k1", _by_strategy(_cop(1), KHop(1), _size, "mc"), _khop(_copurchase_sql(1), 1, True, _sum_body("p_size", "sum_size")))
_cents = [Agg("sum", "cents", "sum_cents")]
for _dir in ("out", "in", "both"):
    for _k in (1, 2):
        _add(f"khop_direct_sum_relay_{_dir}_k{_k}", _by_strategy(G.relay, KHop(_k, _dir), _cents, "direct"), _khop(_RELAY_SQL.format(filter=""), _k, False, _sum_body("cents", "sum_cents"), _dir))
for _dir in ("out", "in", "both"):
    for _k in (1, 2):
        for _s in ("mc", "emc")[:_k]:
            _add(f"khop_{_s}_sum_relay_{_dir}_k{_k}", _by_strategy(G.relay, KHop(_k, _dir), _cents, _s), ORACLES[f"khop_direct_sum_relay_{_dir}_k{_k}"])
_add("khop_mc_waves_sum_copurchase_k2", _by_strategy(_cop(2), KHop(2), _size, "mc", waves=2), ORACLES["khop_mc_sum_copurchase_k2"])
_add("khop_mc_split_sum_copurchase_k2", _by_strategy(_cop(2), KHop(2), _size, "mc", max_pairs_per_cluster=500), ORACLES["khop_mc_sum_copurchase_k2"])
for _fn, _sql in (("count", "count(*)"), ("avg", "avg(p_size)"), ("min", "min(p_size)"), ("max", "max(p_size)"), ("var_pop", "var_pop(p_size)")):
    _agg = Agg(_fn, None if _fn == "count" else "p_size", "value")
    _round = f"round({_sql}, 6)" if _fn in ("avg", "var_pop") else f"CAST({_sql} AS BIGINT)"
    _of = lambda run, r: (lambda s, d: run(s, d).select("id", F.round("value", 6).alias("value")) if r else run(s, d))
    _add(f"khop_mc_{_fn}_copurchase_k2", _of(_by_strategy(_cop(2), KHop(2), [_agg], "mc"), _fn in ("avg", "var_pop")), _khop(_copurchase_sql(2), 2, True, f"SELECT owner AS id, {_round} AS value FROM w JOIN v ON member = v.id GROUP BY owner"))
    if _fn in ("min", "max"):
        _add(f"khop_propagate_{_fn}_copurchase_k3", _by_strategy(_cop(2), KHop(3), [_agg], "propagate"), _khop(_copurchase_sql(2), 3, True, f"SELECT owner AS id, {_round} AS value FROM w JOIN v ON member = v.id GROUP BY owner"))


def _derived(s, d):
    g = G.copurchase(s, d, 2)
    return PropertyGraph(g.vertices.withColumn("few", F.col("p_size") % 3).withColumn("tiny", F.col("p_size") * F.lit(1e-5)), g.edges, False, g.name)


_add("khop_mc_product_copurchase_k1", _by_strategy(_derived, KHop(1), [Agg("product", "few", "value")], "mc"), _khop(_copurchase_sql(2), 1, True, "SELECT owner AS id, product(p_size % 3) AS value FROM w JOIN v ON member = v.id GROUP BY 1"))
_add("khop_mc_var_double_copurchase_k2", lambda s, d: _by_strategy(_derived, KHop(2), [Agg("var_pop", "tiny", "value"), Agg("corr", "tiny", "r", attr2="few"), Agg("covar_pop", "tiny", "c", attr2="few")], "mc")(s, d).select("id", F.round(F.col("value") * 1e10, 4).alias("value"), F.round("r", 6).alias("r"), F.round(F.col("c") * 1e5, 4).alias("c")), _khop(_copurchase_sql(2), 2, True, "SELECT owner AS id, round(var_pop(p_size * 1e-5::DOUBLE) * 1e10::DOUBLE, 4) AS value, round(CASE WHEN var_pop(p_size) > 0 AND var_pop(p_size % 3) > 0 THEN corr(p_size * 1e-5::DOUBLE, (p_size % 3)::DOUBLE) END, 6) AS r, round(covar_pop(p_size * 1e-5::DOUBLE, (p_size % 3)::DOUBLE) * 1e5::DOUBLE, 4) AS c FROM w JOIN v ON member = v.id GROUP BY 1"))
_many = [Agg("sum", "p_size", "total"), Agg("count", None, "n"), Agg("stddev_pop", "p_size", "sd"), Agg("bit_or", "p_size", "bits"), Agg("count_if", None, "big", where="p_size > 25"), Agg("bool_or", "small", "any_small")]
_many_sql = "SELECT owner AS id, CAST(sum(p_size) AS BIGINT) AS total, count(*) AS n, round(stddev_pop(p_size), 6) AS sd, bit_or(p_size) AS bits, CAST(count_if(p_size > 25) AS BIGINT) AS big, bool_or(p_size < 3) AS any_small FROM w JOIN v ON member = v.id GROUP BY owner"


def _with_small(s, d):
    g = G.copurchase(s, d, 2)
    return PropertyGraph(g.vertices.withColumn("small", F.col("p_size") < 3), g.edges, False, g.name)


def _many_run(strategy, shared):
    def run(s, d):
        g = _with_small(s, d)
        q = VertexWindowQuery(g, [VertexWindowFunction(KHop(2), a) for a in _many])
        return q.run(strategy, shared=shared).withColumn("sd", F.round("sd", 6)).withColumn("big", F.col("big").cast("long"))

    return run


_add("multi_function_copurchase_shared", _many_run("direct", True), _khop(_copurchase_sql(2), 2, True, _many_sql))
_add("multi_function_copurchase_seq", _many_run("direct", False), _khop(_copurchase_sql(2), 2, True, _many_sql))
_add("multi_function_copurchase_block", _many_run("block", True), _khop(_copurchase_sql(2), 2, True, _many_sql))
_hist_sql = _khop(_copurchase_sql(2), 2, True, "SELECT owner AS id, p_brand, count(*) AS n FROM w JOIN v ON member = v.id GROUP BY 1, 2")
_add("khop_hist_brand_copurchase_k2", _by_strategy(_cop(2), KHop(2), [Agg("count", None, "n", by="p_brand")], "direct"), _hist_sql)
_add("khop_hist_brand_copurchase_k2_block", _by_strategy(_cop(2), KHop(2), [Agg("count", None, "n", by="p_brand")], "mc"), _hist_sql)
_add("khop_countif_copurchase_k2", _by_strategy(_cop(2), KHop(2), [Agg("count_if", None, "n", where="p_size > 25")], "mc"), _khop(_copurchase_sql(2), 2, True, "SELECT owner AS id, CAST(count_if(p_size > 25) AS BIGINT) AS n FROM w JOIN v ON member = v.id GROUP BY 1"))
_add("khop_median_copurchase_k2_direct", _by_strategy(_cop(2), KHop(2), [Agg("median", "p_size", "m")], "direct"), _khop(_copurchase_sql(2), 2, True, "SELECT owner AS id, median(p_size) AS m FROM w JOIN v ON member = v.id GROUP BY 1"))
_add("khop_noself_count_copurchase_k2", _by_strategy(_cop(2), KHop(2, include_self=False), [Agg("count", None, "n")], "direct"), _khop(_copurchase_sql(2), 2, True, "SELECT v.id, count(member) AS n FROM v LEFT JOIN w ON owner = v.id GROUP BY 1", include_self=False))
_add("khop_zero_sum_copurchase", _by_strategy(_cop(2), KHop(0), _size, "direct"), "SELECT p_partkey AS id, CAST(p_size AS BIGINT) AS sum_size FROM part")


def _topk(build: Build):
    return lambda s, d: top(direct(build(s, d), KHop(2), [Agg("count", None, "n")]), 10, "n")


_add("khop_topk_relay_k2", _topk(G.relay), _khop(_RELAY_SQL.format(filter=""), 2, False, "SELECT owner AS id, count(*) AS n FROM w GROUP BY 1 ORDER BY n DESC, id LIMIT 10"))


def _subset(s, d):
    g = G.copurchase(s, d, 2)
    return direct(g, KHop(2), _size, g.vertices.where("p_brand = 'Brand#11'").select(F.col("id").alias("owner")))


_add("khop_owner_subset_copurchase_k2", _subset, _khop(_copurchase_sql(2), 2, True, "SELECT owner AS id, CAST(sum(m.p_size) AS BIGINT) AS sum_size FROM w JOIN v m ON member = m.id JOIN v o ON owner = o.id WHERE o.p_brand = 'Brand#11' GROUP BY 1"))


def _subset_block(s, d):
    g = G.copurchase(s, d, 2)
    return sb.block_query(sb.build_block_index(g, KHop(2)), g, _size, g.vertices.where("p_brand = 'Brand#11'").select(F.col("id").alias("owner")))


def _subset_delta(s, d):
    g = G.eventbranch(s, d)
    return pd.delta_query(pd.build_delta_index(g), g, _cents, owners=g.vertices.where("event_type = 'error'").select(F.col("id").alias("owner")))


_add("khop_owner_subset_block_copurchase_k2", _subset_block, ORACLES["khop_owner_subset_copurchase_k2"])
_add("topo_owner_subset_delta_eventbranch", _subset_delta, _topo(_BRANCH_SQL, "SELECT owner AS id, CAST(sum(m.cents) AS BIGINT) AS sum_cents FROM w JOIN v m ON member = m.id JOIN v o ON owner = o.id WHERE o.event_type = 'error' GROUP BY 1"))
_add("khop_weblinks_k1", _by_strategy(G.weblinks, KHop(1), [Agg("sum", "size", "total")], "direct"), _khop(_WEBLINKS_SQL, 1, False, _sum_body("size", "total")))
_add("khop_weblinks_k2_both", _by_strategy(G.weblinks, KHop(2, "both"), [Agg("sum", "size", "total")], "mc"), _khop(_WEBLINKS_SQL, 2, False, _sum_body("size", "total"), "both"))
_add("khop_trade_k2", _by_strategy(G.trade, KHop(2), _cents, "direct"), _khop(_TRADE_SQL, 2, True, _sum_body("cents", "sum_cents")))
_add("khop_trade_k2_block", _by_strategy(G.trade, KHop(2), _cents, "mc"), _khop(_TRADE_SQL, 2, True, _sum_body("cents", "sum_cents")))
_add("khop_cosupply_k1", _by_strategy(G.cosupply, KHop(1), _cents, "mc"), _khop(_COSUPPLY_SQL, 1, True, _sum_body("cents", "sum_cents")))
_add("khop_community_k2", _by_strategy(G.community, KHop(2), [Agg("sum", "n_chars", "total")], "mc"), _khop(_COMMUNITY_SQL, 2, True, _sum_body("n_chars", "total")))
_add("khop_community_k1_overlay", _by_strategy(G.community, KHop(1), [Agg("sum", "n_chars", "total")], "overlay", iterations=10), _khop(_COMMUNITY_SQL, 1, True, _sum_body("n_chars", "total")))
# the published sweeps: degrees 5 to 30 over two hops, dense graphs, and the overlay baseline with 10 iterations beside them
_attr_total = [Agg("sum", "attr", "total")]
for _d, _k, _s in ((10, 2, "direct"), (5, 2, "mc"), (10, 2, "mc"), (10, 2, "emc"), (20, 1, "mc"), (30, 1, "mc"), (10, 1, "overlay"), (80, 1, "mc"), (200, 1, "mc"), (80, 1, "overlay")):
    _add(f"khop_{_s}_sum_synthrand_d{_d}_k{_k}", _by_strategy(_synthrand(_d), KHop(_k), _attr_total, _s, **({"iterations": 10} if _s == "overlay" else {})), _khop(_synthrand_sql(_d), _k, True, _sum_body("attr", "total")))
for _name, _build, _window, _gsql, _und, _agg, _alias in (
    ("relay_out", G.relay, KHop(1), _RELAY_SQL.format(filter=""), False, "cents", "sum_cents"), ("trade", G.trade, KHop(1), _TRADE_SQL, True, "cents", "sum_cents"),
    ("weblinks_both", G.weblinks, KHop(1, "both"), _WEBLINKS_SQL, False, "size", "total"), ("cosupply", G.cosupply, KHop(1), _COSUPPLY_SQL, True, "cents", "sum_cents"),
):
    _add(f"khop_overlay_sum_{_name}_k1", _by_strategy(_build, _window, [Agg("sum", _agg, _alias)], "overlay", iterations=10), _khop(_gsql, 1, _und, _sum_body(_agg, _alias), _window.direction))
_SIMILAR_SQL = """v AS (SELECT vec_id AS id, CAST(label AS BIGINT) AS label, CAST(embedding AS DOUBLE[]) AS x FROM embeddings),
e AS (SELECT a.id AS src, b.id AS dst FROM v a JOIN v b ON a.id < b.id WHERE list_cosine_similarity(a.x, b.x) >= 0.3)"""
_add("khop_similar_k1", lambda s, d: direct(G.similar(s, d), KHop(1), [Agg("sum", "label", "total")]), _khop(_SIMILAR_SQL, 1, True, _sum_body("label", "total")))

_urgent = lambda s, d: G.lineage(s, d, "1-URGENT")  # noqa: E731  the graph is defined by a priority

# -- topological -------------------------------------------------------------------------------------------------------

for _name, _build, _gsql, _attr in (("eventbranch", G.eventbranch, _BRANCH_SQL, "cents"), ("catalog", G.catalog, _CATALOG_SQL, "cents"), ("dialogue", G.dialogue, _DIALOGUE_SQL, "chars")):
    _body = _topo(_gsql, _sum_body(_attr, "total"))
    for _s in ("direct", "mc", "level", "jump"):
        if (_name, _s) in (("eventbranch", "level"), ("catalog", "mc")):
            continue
        _add(f"topo_{ {'mc': 'block', 'level': 'delta_level', 'jump': 'delta_jump'}.get(_s, _s) }_sum_{_name}", _by_strategy(_build, Topological(), [Agg("sum", _attr, "total")], _s), _body)
_add("topo_delta_sum_lineage", lambda s, d: (lambda g: pd.delta_query(pd.build_delta_index(g), g, [Agg("sum", "cents", "total")]))(_urgent(s, d)), _topo(_LINEAGE_SQL, _sum_body("cents", "total")))
for _d in (3, 5, 10, 20):
    _add(f"topo_delta_sum_synthdag_d{_d}", _by_strategy(_synthdag(_d), Topological(), _attr_total, "jump"), _topo(_synthdag_sql(_d), _sum_body("attr", "total")))
_add("topo_direct_sum_synthdag_d10", _by_strategy(_synthdag(10), Topological(), _attr_total, "direct"), ORACLES["topo_delta_sum_synthdag_d10"])
_add("topo_block_sum_synthdag_d3", _by_strategy(_synthdag(3), Topological(), _attr_total, "mc"), ORACLES["topo_delta_sum_synthdag_d3"])


def _clashing(s, d):
    g = G.eventbranch(s, d)
    named = g.vertices.select("id", g.part, *[F.col("cents").alias(c) for c in ("member", "v", "owner", "block_id", "p")])
    g = PropertyGraph(named, g.edges, True, g.name, g.part)
    return pd.delta_query(pd.build_delta_index(g), g, [Agg("sum", "member", "member"), Agg("sum", "v", "v"), Agg("sum", "owner", "owner", where="p > 5000")])


_add("topo_delta_clashing_names", _clashing, _topo(_BRANCH_SQL, "SELECT owner AS id, CAST(sum(cents) AS BIGINT) AS member, CAST(sum(cents) AS BIGINT) AS v, CAST(sum(CASE WHEN cents > 5000 THEN cents END) AS BIGINT) AS owner FROM w JOIN v ON member = v.id GROUP BY 1"))
_add("topo_running_eventchain", lambda s, d: running_window(G.table(s, d, "events").select(F.col("event_id").alias("id"), "user_id", "ts", "event_id", G.cents("value").alias("cents")), "user_id", ["ts", "event_id"], "cents"), f"SELECT event_id AS id, CAST(sum({_CENTS.format('value')}) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS value FROM events")
_add("topo_delta_jump_sum_eventchain", _by_strategy(G.eventchain, Topological(), [Agg("sum", "cents", "value")], "jump"), ORACLES["topo_running_eventchain"])
_add("topo_kinds_catalog", _by_strategy(G.catalog, Topological(), [Agg("count", None, "n", by="kind")], "jump"), _topo(_CATALOG_SQL, "SELECT owner AS id, kind, count(*) AS n FROM w JOIN v ON member = v.id GROUP BY 1, 2"))
_add("topo_types_eventbranch", _by_strategy(G.eventbranch, Topological(), [Agg("count", None, "n", by="event_type")], "jump"), _topo(_BRANCH_SQL, "SELECT owner AS id, event_type, count(*) AS n FROM w JOIN v ON member = v.id GROUP BY 1, 2"))
_add("topo_countif_eventbranch", _by_strategy(G.eventbranch, Topological(), [Agg("count_if", None, "n", where="event_type = 'error'")], "jump"), _topo(_BRANCH_SQL, "SELECT owner AS id, CAST(count_if(event_type = 'error') AS BIGINT) AS n FROM w JOIN v ON member = v.id GROUP BY 1"))
_add("topo_impact_lineage", lambda s, d: direct(_urgent(s, d), Topological(include_self=False), [Agg("count", None, "n")]), _topo(_LINEAGE_SQL, "SELECT v.id, count(c.member) AS n FROM v LEFT JOIN c ON c.owner = v.id GROUP BY 1"))
_add("topo_descendants_catalog", lambda s, d: direct(G.catalog(s, d), Topological("descendants"), [Agg("count", None, "n")]), _topo(_CATALOG_SQL, "SELECT member AS id, count(*) AS n FROM w GROUP BY 1"))
_add("topo_levels_eventbranch", lambda s, d: topo_levels(G.eventbranch(s, d)), None)
_level_sql = "WITH RECURSIVE {}, q(id, level) AS (SELECT id, 0 FROM v UNION SELECT e.dst, q.level + 1 FROM q JOIN e ON e.src = q.id) SELECT id, CAST(max(level) AS INTEGER) AS level FROM q GROUP BY 1"
ORACLES["topo_levels_eventbranch"] = _level_sql.format(_BRANCH_SQL)
_add("topo_levels_catalog_peeling", lambda s, d: topo_levels_by_peeling(G.catalog(s, d)), _level_sql.format(_CATALOG_SQL))
_add("topo_windows_by_level_catalog", lambda s, d: (lambda g: ancestor_windows_by_level(g, topo_levels(g)))(G.catalog(s, d)), _topo(_CATALOG_SQL, "SELECT owner, member FROM w"))
_add("topo_containment_eventbranch", lambda s, d: pd.containment_violations(G.eventbranch(s, d)), "SELECT event_id AS src, event_id AS dst FROM events WHERE FALSE")

# -- indices, signatures, measures -------------------------------------------------------------------------------------

_pairs_sql = _khop(_copurchase_sql(2), 2, True, "SELECT owner, member, CAST(1 AS BIGINT) AS copies FROM w")
for _s in ("mc", "emc"):
    _add(f"index_cover_{_s}_copurchase_k2", (lambda m: lambda s, d: sb.expand_index(sb.build_block_index(G.copurchase(s, d, 2), KHop(2), m)))(_s), _pairs_sql)
_add("index_cover_delta_eventbranch", lambda s, d: pd.expand_delta(pd.build_delta_index(G.eventbranch(s, d))), _topo(_BRANCH_SQL, "SELECT owner, member FROM w"))
_pid_sql = ", card AS (SELECT owner AS id, count(*) AS card FROM w GROUP BY 1), p AS (SELECT dst AS v, src AS pid, row_number() OVER (PARTITION BY dst ORDER BY card DESC, src) AS r FROM e JOIN card ON src = card.id), pp AS (SELECT v, pid FROM p WHERE r = 1) "
_add("delta_parent_eventbranch", lambda s, d: pd.build_delta_index(G.eventbranch(s, d)).parent.select("v", "pid", "card"), f"WITH RECURSIVE {_BRANCH_SQL}, {_CLOSURE}{_pid_sql} SELECT card.id AS v, pid, card FROM card LEFT JOIN pp ON v = card.id")
_add("delta_diff_catalog", lambda s, d: pd.build_delta_index(G.catalog(s, d)).delta, f"WITH RECURSIVE {_CATALOG_SQL}, {_CLOSURE}{_pid_sql} SELECT pp.v, w.member FROM pp JOIN w ON w.owner = pp.v WHERE w.member <> pp.v AND NOT EXISTS (SELECT 1 FROM w x WHERE x.owner = pp.pid AND x.member = w.member)")
_add("delta_ranges_catalog", lambda s, d: pd.delta_ranges(pd.build_delta_index(G.catalog(s, d)).delta).select("v", "start", "len"), f"WITH RECURSIVE {_CATALOG_SQL}, {_CLOSURE}{_pid_sql}, dd AS (SELECT pp.v, w.member, w.member - row_number() OVER (PARTITION BY pp.v ORDER BY w.member) AS run FROM pp JOIN w ON w.owner = pp.v WHERE w.member <> pp.v AND NOT EXISTS (SELECT 1 FROM w x WHERE x.owner = pp.pid AND x.member = w.member)) SELECT v, min(member) AS start, count(*) AS len FROM dd GROUP BY v, run")
_h = ", ".join(f"CAST(min(({a} * (member % {PRIME}) + {b}) % {PRIME}) AS BIGINT) AS h{i + 1}" for i, (a, b) in enumerate(affine_constants(2)))
_minhash_all_sql = _khop(_RELAY_SQL.format(filter=""), 2, False, f"SELECT owner, {_h} FROM w GROUP BY 1")
_add("minhash_explicit_relay_k2", lambda s, d: sb.signature_explicit(window_pairs(G.relay(s, d), KHop(2)), 2), _minhash_all_sql)
_add("minhash_propagated_relay_k2", lambda s, d: sb.signature_propagated(G.relay(s, d), KHop(2), 2), _minhash_all_sql)
for _k in (1, 2):
    _add(f"jaccard_exact_copurchase_k{_k}", (lambda k: lambda s, d: sb.jaccard_exact(window_pairs(G.copurchase(s, d, 2), KHop(k))))(_k), _khop(_copurchase_sql(2), _k, True, "SELECT a.owner AS u, b.owner AS v, count(*) AS inter, any_value(na.n) + any_value(nb.n) - count(*) AS uni FROM w a JOIN w b ON a.member = b.member AND a.owner < b.owner JOIN (SELECT owner, count(*) AS n FROM w GROUP BY 1) na ON na.owner = a.owner JOIN (SELECT owner, count(*) AS n FROM w GROUP BY 1) nb ON nb.owner = b.owner GROUP BY 1, 2"))


def _estimate(s, d):
    g = G.relay(s, d)
    sig = sb.signature_propagated(g, KHop(2), 16, family="xx")
    return sb.jaccard_estimate(sig, g.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")), 16)


_add("jaccard_estimate_relay_k2", _estimate)


def _named_by_least(clusters: DataFrame) -> DataFrame:
    """(owner, least): clusters by their least owner, as the engine's hash has no counterpart in SQL."""
    least = clusters.groupBy("cluster").agg(F.min("owner").alias("least"))
    return clusters.join(least, "cluster").select("owner", "least")


def _cluster_sql(k: int) -> str:
    (a, b), = affine_constants(1)
    return _khop(_RELAY_SQL.format(filter=""), k, False, f"SELECT owner, min(owner) OVER (PARTITION BY h) AS least FROM (SELECT owner, min(({a} * (member % {PRIME}) + {b}) % {PRIME}) AS h FROM w GROUP BY 1)")


_add("cluster_full_relay_k2", lambda s, d: _named_by_least(sb.cluster_full(G.relay(s, d), KHop(2))), _cluster_sql(2))
_add("cluster_estimated_relay_k2", lambda s, d: _named_by_least(sb.cluster_estimated(G.relay(s, d), KHop(2))), _cluster_sql(1))
_add("block_stats_copurchase_k2", lambda s, d: measures.block_stats(sb.build_block_index(G.copurchase(s, d, 2), KHop(2))))
_add("window_volume_copurchase_k2", lambda s, d: window_volume(G.copurchase(s, d, 2), KHop(2), exact=True), _khop(_copurchase_sql(2), 2, True, "SELECT count(*) AS pairs FROM w"))
_add("window_volume_estimated_copurchase_k2", lambda s, d: window_volume(G.copurchase(s, d, 2), KHop(2)))
_add("add_count_direct_copurchase_k2", lambda s, d: measures.add_count_direct(window_pairs(G.copurchase(s, d, 2), KHop(2))), _khop(_copurchase_sql(2), 2, True, "SELECT CAST(sum(n - 1) AS BIGINT) AS adds FROM (SELECT count(*) AS n FROM w GROUP BY owner)"))


def _growth_sql(ks: tuple[int, ...]) -> str:
    out = _windows_sql(max(ks), True)
    for k in ks:
        base = "" if k == ks[0] else f" JOIN j{ks[0]} z ON z.u = a.owner AND z.v = b.owner"
        out += f", n{k} AS (SELECT owner, count(*) AS n FROM w{k} GROUP BY 1), j{k} AS (SELECT a.owner AS u, b.owner AS v, count(*) / (any_value(x.n) + any_value(y.n) - count(*)) AS j FROM w{k} a JOIN w{k} b ON a.member = b.member AND a.owner < b.owner JOIN n{k} x ON x.owner = a.owner JOIN n{k} y ON y.owner = b.owner{base} GROUP BY 1, 2)"
    rows = [f"SELECT CAST({k} AS INTEGER) AS k, count(*) AS pairs, round(avg(j{k}.j), 6) AS mean_j, " + ("CAST(NULL AS DOUBLE)" if i == 0 else f"round(avg(CASE WHEN j{k}.j >= j{ks[i - 1]}.j THEN 1.0 ELSE 0.0 END), 6)") + f" AS share_grown FROM j{k}" + ("" if i == 0 else f" JOIN j{ks[i - 1]} USING (u, v)") for i, k in enumerate(ks)]
    return f"WITH {_copurchase_sql(2)}, {out} " + " UNION ALL ".join(rows)


_add("jaccard_growth_copurchase", lambda s, d: measures.jaccard_growth(G.copurchase(s, d, 2), [1, 2, 3]).withColumn("mean_j", F.round("mean_j", 6)).withColumn("share_grown", F.round("share_grown", 6)), _growth_sql((1, 2, 3)))
_add("expansion_bound_synthrand", lambda s, d: measures.expansion_bound(_synthrand(6)(s, d), 1).select("sets", *[F.round(c, 6).alias(c) for c in ("mean_size", "mean_new", "mean_bound")]), _khop(_synthrand_sql(6), 2, True, "SELECT count(*) AS sets, round(avg(s), 6) AS mean_size, round(avg(t - s), 6) AS mean_new, round(avg(s * (nv - s) * (d - 1) / (nv - 1)), 6) AS mean_bound FROM (SELECT owner, count(*) AS s FROM w1 GROUP BY 1) JOIN (SELECT owner, count(*) AS t FROM w2 GROUP BY 1) USING (owner), (SELECT count(*) AS nv, 2.0::DOUBLE * (SELECT count(*) FROM e) / count(*) AS d FROM v)"))
_sizes_sql = ", card AS (SELECT owner AS id, count(*) AS card FROM w GROUP BY 1), up AS (SELECT dst AS id, max(card) AS card FROM e JOIN card ON src = card.id GROUP BY 1), s AS (SELECT card.card, CASE WHEN up.card IS NULL THEN 0 ELSE card.card - 1 - up.card END AS delta FROM card LEFT JOIN up USING (id)) "
_stats_body = "SELECT count(*) AS vertices, round(avg(card - 1), 6) AS mean_ancestors, round(sum(delta) / count(*), 6) AS mean_delta FROM s"
_rounded = lambda df: df.select("vertices", F.round("mean_ancestors", 6).alias("mean_ancestors"), F.round("mean_delta", 6).alias("mean_delta"))
_add("dag_stats_eventbranch", lambda s, d: _rounded(measures.dag_stats(pd.build_delta_index(G.eventbranch(s, d)))), f"WITH RECURSIVE {_BRANCH_SQL}, {_CLOSURE}{_sizes_sql}{_stats_body}")


def _delta_size(build: Build):
    """Entries of the parent-delta index beside the graph's, and the additions of a sum query."""

    def run(s, d):
        g = build(s, d)
        ix = pd.build_delta_index(g)
        sizes = ix.parent.agg(F.count("*").alias("vertices"), F.count("pid").alias("inherit")).join(ix.entries()).join(g.edges.select("src", "dst").distinct().agg(F.count("*").alias("edges")))
        return sizes.select("vertices", "edges", "delta", F.round((F.col("vertices") + F.col("delta")) / (F.col("vertices") + F.col("edges")), 6).alias("ratio"), (F.col("inherit") + F.col("delta")).alias("adds"))

    return run


_size_body = "SELECT n AS vertices, m AS edges, CAST(delta AS BIGINT) AS delta, round((n + delta) / (n + m), 6) AS ratio, CAST(inherit + delta AS BIGINT) AS adds FROM (SELECT count(*) AS n, sum(delta) AS delta FROM s), (SELECT count(*) AS m, count(DISTINCT dst) AS inherit FROM e)"
for _name, _build, _gsql in (("eventbranch", G.eventbranch, _BRANCH_SQL), ("synthdag_d3", _synthdag(3), _synthdag_sql(3)), ("synthdag_d20", _synthdag(20), _synthdag_sql(20))):
    _add(f"delta_size_{_name}", _delta_size(_build), f"WITH RECURSIVE {_gsql}, {_CLOSURE}{_sizes_sql}{_size_body}")
_add("graph_validate_catalog", lambda s, d: G.catalog(s, d).validate(), f"WITH {_CATALOG_SQL} SELECT 'loops' AS \"check\", count(*) AS n FROM e WHERE src = dst UNION ALL SELECT 'repeated_edges', count(*) - (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM e)) FROM e UNION ALL SELECT 'repeated_vertices', count(*) - count(DISTINCT id) FROM v UNION ALL SELECT 'dangling_ends', count(*) FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) WHERE id NOT IN (SELECT id FROM v) UNION ALL SELECT 'null_ids', count(*) FROM v WHERE id IS NULL")

# -- updates -----------------------------------------------------------------------------------------------------------


def _edge_changes(g: PropertyGraph, op: str, share: int = 100, low: bool = True) -> DataFrame:
    """Edges with ends whose ids sum up to 0 modulo share (or, not low, to 1) as changes: about 1 in `share`."""
    return g.edges.where((F.col("src") + F.col("dst")) % share == (0 if low else 1)).select(F.lit(op).alias("op"), "src", "dst")


def _block_update(op: str):
    def run(s, d):
        g = G.copurchase(s, d, 2)
        changes = _edge_changes(g, op)
        start = g if op == "-" else updates.changed_graph(g, changes.withColumn("op", F.lit("-")))
        ix, after = updates.update_block_index(sb.build_block_index(start, KHop(2)), start, changes)
        return sb.block_query(ix, after, _size)

    return run


_less = "e AS (SELECT * FROM e0 WHERE (src + dst) % 100 <> 0)"
_add("update_insert_block_copurchase_k2", _block_update("+"), ORACLES["khop_mc_sum_copurchase_k2"])
_add("update_delete_block_copurchase_k2", _block_update("-"), _khop(_copurchase_sql(2).replace("e AS (", "e0 AS (", 1) + ", " + _less, 2, True, _sum_body("p_size", "sum_size")))

def _delta_batch(op: str):
    """All edges of the 1% change set at once."""

    def run(s, d):
        g = G.eventbranch(s, d)
        changes = _edge_changes(g, op)
        start = g if op == "-" else updates.changed_graph(g, changes.withColumn("op", F.lit("-")))
        ix, after = updates.update_delta_batch(pd.build_delta_index(start), start, changes)
        return pd.delta_query(ix, after, [Agg("sum", "cents", "total")])

    return run


_add("update_insert_delta_eventbranch", _delta_batch("+"), ORACLES["topo_direct_sum_eventbranch"])
_add("update_delete_delta_eventbranch", _delta_batch("-"), _topo(_BRANCH_SQL.replace("e AS (", "e0 AS (", 1) + ", " + _less, _sum_body("cents", "total")))

# -- SQL surface -------------------------------------------------------------------------------------------------------

_add("sql_surface_khop", lambda s, d: graph_window_sql(s, "SELECT id, SUM(p_size) AS total, COUNT(*) AS n OVER KHOP(2, both) FROM parts USING direct ORDER BY total DESC LIMIT 20", {"parts": G.copurchase(s, d, 2)}), _khop(_copurchase_sql(2), 2, True, "SELECT owner AS id, CAST(sum(p_size) AS BIGINT) AS total, count(*) AS n FROM w JOIN v ON member = v.id GROUP BY 1 ORDER BY total DESC, id LIMIT 20"))
_add("sql_surface_topo", lambda s, d: graph_window_sql(s, "SELECT id, COUNT(*) FILTER (WHERE cents > 5000) AS n OVER TOPO FROM events USING delta", {"events": G.eventbranch(s, d)}), _topo(_BRANCH_SQL, "SELECT owner AS id, CAST(count_if(cents > 5000) AS BIGINT) AS n FROM w JOIN v ON member = v.id GROUP BY 1"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sum of sizes over 1-hop windows of the co-purchase graph, through a shared-block index."""
    return _by_strategy(_cop(1), KHop(1), _size, "mc")(spark, sf_dir)
