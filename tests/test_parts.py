"""Ancestor windows by parts: equal to those by joins, and no closure is ever written."""

import pytest
from conftest import normal

from graphwin import workloads
from graphwin.functions.aggregates import Agg
from graphwin.model import CycleError, PropertyGraph, Topological
from graphwin.operators import parts, reach
from graphwin.operators.deltaindex import build_delta_index, delta_query
from graphwin.operators.direct import direct
from graphwin.operators.updates import changed_graph, update_delta_batch
from graphwin.sources import graphs as G


@pytest.fixture
def no_closure(monkeypatch):
    """The joins' closures are written tables; with parts there must be none."""
    def refused(*a, **k):
        raise AssertionError("a closure by joins")

    monkeypatch.setattr(reach, "ancestor_pairs", refused)
    monkeypatch.setattr(reach, "frontier_pairs", refused)
    for module in ("deltaindex", "updates"):
        monkeypatch.setattr(f"graphwin.operators.{module}.ancestor_pairs", refused)


DIRECT = ["topo_direct_sum_eventbranch", "topo_direct_sum_synthdag_d10"]  # F1, F24
INDEX = ["delta_parent_eventbranch", "topo_delta_jump_sum_eventbranch", "topo_owner_subset_delta_eventbranch", "delta_size_synthdag_d20", "delta_size_synthdag_d3", "topo_delta_sum_lineage"]  # F2, F9, F10, F13, F14, F19
INDEX += [f"topo_delta_sum_synthdag_d{d}" for d in (3, 5, 10, 20)]  # F20 to F23
UPDATES = ["update_delete_delta_eventbranch", "update_insert_delta_eventbranch"]  # F11, F12


@pytest.mark.parametrize("name", [*DIRECT, *INDEX, *UPDATES])
def test_no_closure_is_joined(spark, duck, tiny_dir, no_closure, name):
    assert normal(workloads.QUERIES[name](spark, tiny_dir)) == normal(duck.execute(workloads.ORACLES[name]))


def test_index_equals_that_by_joins(spark):
    g = G.synthdag(spark, 400, 3)
    a, b = build_delta_index(g, "parts"), build_delta_index(g, "doubling")
    assert normal(a.parent.select("v", "pid", "level", "card")) == normal(b.parent.select("v", "pid", "level", "card"))
    assert normal(a.delta) == normal(b.delta)
    assert len(a.jumps) == len(b.jumps) and all(normal(x) == normal(y) for x, y in zip(a.jumps, b.jumps, strict=True))


def test_masks_in_stretches(monkeypatch):
    """A part whose masks don't fit at once gives the same rows."""
    import pyarrow as pa

    edges = [((v * 7919 + j * 104729 + 17) % 1_000_003 % v, v) for v in range(1, 300) for j in range(3)]
    kind, a, b = [0] * 300 + [1] * len(edges), [*range(300), *(s for s, _ in edges)], [*range(300), *(d for _, d in edges)]
    batch = pa.RecordBatch.from_arrays([pa.array(x) for x in ([5] * len(kind), [0] * len(kind), kind, a, b)], names=["part", "slot", "kind", "a", "b"])
    whole = [r for t in parts._index_rows(4)([batch]) for r in t.to_pylist()]
    monkeypatch.setattr(parts, "MASK_BYTES", 1000)
    cut = [r for t in parts._index_rows(4)([batch]) for r in t.to_pylist()]
    assert sorted(map(str, whole)) == sorted(map(str, cut)) and any(r["kind"] == parts.DELTA for r in whole)


def test_large_parts_go_by_joins(spark):
    g = G.synthdag(spark, 50, 3)
    assert parts.parted(g, largest=(49, 1000)) is None and parts.parted(g, largest=(50, 10)) is None
    assert parts.parted(g, largest=(50, 1000)).largest == 50


def test_descendants_conditions_and_names(spark, tiny_dir):
    g = G.eventbranch(spark, tiny_dir)
    bare = PropertyGraph(g.vertices, g.edges, True, g.name)
    aggs = [Agg("sum", "cents", "total", where="event_type = 'error' AND id % 2 = 0"), Agg("count", None, "n")]
    for w in (Topological("descendants"), Topological(include_self=False)):
        pairs = reach.ancestor_pairs(bare, w.direction).select("owner", "member")
        from graphwin.operators.direct import aggregate_pairs

        if w.include_self:
            pairs = pairs.union(g.vertices.select("id", "id"))
        assert normal(direct(g, w, aggs)) == normal(aggregate_pairs(bare, pairs, aggs))


def test_cycles(spark):
    g = G.literal(spark, [(1, 2), (2, 3), (3, 1)], directed=True)
    for run in (lambda: build_delta_index(g), lambda: direct(g, Topological(), [Agg("sum", "attr")])):
        with pytest.raises(CycleError):
            run()


def test_updates_across_parts(spark):
    """An edge between two parts ends the partition, within one it stays; both equal a rebuild."""
    v = spark.createDataFrame([(i, i, i // 5) for i in range(10)], "id long, attr long, place long")
    e = spark.createDataFrame([(i, i + 1, i // 5) for i in (0, 1, 2, 5, 6, 7)], "src long, dst long, place long")
    g = PropertyGraph(v, e, True, "two", "place")
    for new, kept in (((3, 4), "place"), ((3, 9), None)):
        changes = spark.createDataFrame([("+", *new), ("-", 0, 1)], "op string, src long, dst long")
        ix, after = update_delta_batch(build_delta_index(g), g, changes)
        assert after.part == kept == changed_graph(g, changes).part
        sums = [Agg("sum", "attr", "total")]
        assert normal(delta_query(ix, after, sums)) == normal(delta_query(build_delta_index(after, "doubling"), after, sums))
