"""Ancestor windows of large graphs without known parts: closed by stretches in tasks that hold the graph, equal to joins."""

import numpy as np
import pyarrow as pa
import pytest
from conftest import normal

from graphwin import workloads
from graphwin.functions.aggregates import Agg
from graphwin.model import CycleError, PropertyGraph, Topological
from graphwin.operators import parts, reach
from graphwin.operators import whole as W
from graphwin.operators.deltaindex import build_delta_index, delta_query
from graphwin.operators.direct import direct
from graphwin.operators.packed import _pack
from graphwin.operators.whole import whole
from graphwin.sources import graphs as G

NAMES = ["delta_size_synthdag_d20", "topo_delta_sum_synthdag_d10", "topo_delta_sum_synthdag_d20", "topo_direct_sum_synthdag_d10", "topo_delta_sum_lineage"]
NAMES += ["delta_size_synthdag_d3", "topo_delta_sum_synthdag_d3", "topo_delta_sum_synthdag_d5"]


@pytest.fixture
def large(monkeypatch):
    """Graphs count as too large for a part, and no closure may be written by joins."""
    def refused(*a, **k):
        raise AssertionError("a closure by joins")

    monkeypatch.setattr(parts.parted, "__defaults__", (None, None, (20, 20)))
    monkeypatch.setattr(reach, "ancestor_pairs", refused)
    monkeypatch.setattr(reach, "frontier_pairs", refused)
    monkeypatch.setattr("graphwin.operators.deltaindex.ancestor_pairs", refused)
    monkeypatch.setattr("graphwin.operators.deltaindex.frontier_pairs", refused)


@pytest.mark.parametrize("name", NAMES)
def test_no_closure_of_a_large_graph_is_joined(spark, duck, tiny_dir, large, name):
    assert normal(workloads.QUERIES[name](spark, tiny_dir)) == normal(duck.execute(workloads.ORACLES[name]))


@pytest.mark.parametrize("d", [2, 9])
def test_index_equals_that_by_joins(spark, d):
    g = G.synthdag(spark, 700, d)
    v = g.vertices.where("id <> 3").selectExpr("5 - id * 1000000007 AS id", "IF(id % 5 = 0, NULL, attr - 40) AS attr")
    e = g.edges.selectExpr("5 - src * 1000000007 AS src", "5 - dst * 1000000007 AS dst")
    g = PropertyGraph(v, e.union(e.limit(50)), True, "spread")  # some edges twice, one vertex with edges only
    a, b = build_delta_index(g, "whole"), build_delta_index(g, "parts")
    assert normal(a.parent) == normal(b.parent.select("v", "pid", "level", "card"))
    assert normal(a.delta) == normal(b.delta) and a.entries().first()[0] == b.entries().first()[0]
    assert len(a.jumps) == len(b.jumps) and all(normal(x) == normal(y) for x, y in zip(a.jumps, b.jumps, strict=True))
    for aggs in ([Agg("sum", "attr", "total"), Agg("count", None, "n")], [Agg("sum", "attr", "total", where="id % 2 = 0"), Agg("avg", "attr", "mean")], [Agg("max", "attr", "most")]):
        assert normal(delta_query(a, g, aggs)) == normal(delta_query(b, g, aggs))


def test_direct_sums(spark, monkeypatch):
    g = G.synthdag(spark, 700, 4)
    aggs = [Agg("sum", "attr", "total"), Agg("count", None, "n")]
    for w in (Topological(), Topological(include_self=False), Topological("descendants")):
        expected = normal(direct(g, w, aggs))
        with monkeypatch.context() as m:
            m.setattr(parts.parted, "__defaults__", (None, None, (20, 20)))
            assert normal(direct(g, w, aggs)) == expected


def test_hubs_full_rows_and_short_stretches(spark, monkeypatch):
    """A vertex with many parents, windows that hold whole stretches, stretches of one word, rows of few vertices."""
    edges = [(i, i + 1) for i in range(100)] + [(i, 500) for i in range(100, 400)] + [(500, 501), (100, 501), (399, 501)]
    g = G.literal(spark, edges, directed=True)
    a, b = build_delta_index(g, "whole"), build_delta_index(g, "parts")
    assert normal(a.parent) == normal(b.parent.select("v", "pid", "level", "card")) and normal(a.delta) == normal(b.delta)
    columns = np.zeros(len(edges), "int32"), np.array([s for s, _ in edges]), np.array([d for _, d in edges])
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["target", "owner", "value"])
    rows = list(W._numbered(_pack(W.PARENTS)([batch])))
    anc = {}
    for s, d in sorted(edges, key=lambda e: e[1]):
        anc.setdefault(d, {d}).update(anc.setdefault(s, {s}))
    for words, size in ((1, 3), (2, 4096)):
        monkeypatch.setattr(W, "WORDS", words)
        monkeypatch.setattr(W, "ROWS", size)
        n = W.Numbered(rows)
        sizes = np.zeros(n.n, "int64")
        full = 0
        for first, bits in n.stretches(1):
            for owners, masks in n.windows(first, bits):
                sizes[owners] += bits if masks is None else W._ones(masks)
                full += masks is None
        assert full and dict(zip(n.ids.tolist(), sizes.tolist(), strict=True)) == {k: len(x) for k, x in anc.items()}


def test_cycles_and_limits(spark):
    with pytest.raises(CycleError):
        build_delta_index(G.literal(spark, [(1, 2), (2, 3), (3, 1), (3, 4)], directed=True), "whole")
    g = G.synthdag(spark, 50, 3)
    assert whole(g, (49, 1000)) is None and whole(g, (50, 10)) is None
    none = PropertyGraph(g.vertices.limit(0), g.edges.limit(0), True, "none")
    assert build_delta_index(none, "whole").parent.count() == 0
    assert whole(g).n == 50
