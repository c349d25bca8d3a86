"""Lineage over every order, against brute force on a small fixture; the registered queries, of one priority, against SQL."""

from datetime import datetime

import pytest
from conftest import normal

from graphwin import workloads
from graphwin.functions.aggregates import Agg
from graphwin.model import Topological
from graphwin.operators.deltaindex import build_delta_index, delta_query
from graphwin.operators.direct import direct
from graphwin.operators.reach import topo_levels
from graphwin.sources import graphs as G

PRIORITIES, STATUS = ["1-URGENT", "2-HIGH", "5-LOW"], ["P", "O", "F"]
# order: (key, customer, day, priced in whole units), parts of its lines
ORDERS = [(k, k % 4, 1 + (k * 7) % 25, 10 * k + 1) for k in range(1, 25)]
LINES = [(k, (k * j) % 11) for k in range(1, 25) for j in (1, 3)]


@pytest.fixture(scope="module")
def orders_dir(spark, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("lineage"))
    rows = [(k, c, datetime(1997, 1, d), float(p), STATUS[k % 3], PRIORITIES[k // 3 % 3]) for k, c, d, p in ORDERS]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz, o_totalprice double, o_orderstatus string, o_orderpriority string").write.parquet(f"{at}/orders.parquet")
    spark.createDataFrame(LINES, "l_orderkey long, l_partkey long").write.parquet(f"{at}/lineitem.parquet")
    return at


def ancestors():
    groups: dict = {}
    for k, c, d, _ in ORDERS:
        groups.setdefault(("customer", c), set()).add((d, k))
    day = {k: d for k, _, d, _ in ORDERS}
    for k, part in LINES:
        groups.setdefault(("part", part), set()).add((day[k], k))
    parents: dict = {k: set() for k, _, _, _ in ORDERS}
    for members in groups.values():
        line = [k for _, k in sorted(members)]
        for a, b in zip(line, line[1:], strict=False):
            parents[b].add(a)
    out: dict = {}
    for _, k in sorted((d, k) for k, d in day.items()):
        out[k] = set().union(*({p} | out[p] for p in parents[k]))
    return out


def test_impact_counts_every_order(spark, orders_dir):
    got = {r["id"]: r["n"] for r in direct(G.lineage(spark, orders_dir), Topological(include_self=False), [Agg("count", None, "n")]).collect()}
    assert got == {k: len(a) for k, a in ancestors().items()}


@pytest.mark.parametrize("method", ["doubling", "frontier", "level"])
def test_delta_sums_every_order(spark, orders_dir, method):
    price = {k: 100 * p for k, _, _, p in ORDERS}
    g = G.lineage(spark, orders_dir)
    ix = build_delta_index(g, method)
    got = {r["id"]: r["total"] for r in delta_query(ix, g, [Agg("sum", "cents", "total")]).collect()}
    assert got == {k: price[k] + sum(price[x] for x in a) for k, a in ancestors().items()}
    assert {r["v"]: r["level"] for r in ix.parent.collect()} == {r["id"]: r["level"] for r in topo_levels(g).collect()}


@pytest.mark.parametrize("name", ["topo_impact_lineage", "topo_delta_sum_lineage"])
def test_registered_lineage(spark, duck, tiny_dir, name):
    assert normal(workloads.QUERIES[name](spark, tiny_dir)) == normal(duck.execute(workloads.ORACLES[name]))
