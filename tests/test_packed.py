"""Blocks formed within tasks: exact, disjoint covers, and no pair is written or sent as a row."""

import numpy as np
import pytest
from conftest import normal
from pyspark.sql import functions as F

from graphwin import workloads
from graphwin.functions.aggregates import Agg
from graphwin.model import CycleError, KHop, PropertyGraph, Topological
from graphwin.operators import blockindex as sb
from graphwin.operators import packed
from graphwin.operators.direct import direct
from graphwin.operators.reach import window_pairs
from graphwin.sources import graphs as G


def cover(owner, member, cluster, m=1, family="affine"):
    mb, mm, lb, lo = (x.tolist() for x in packed.refine(np.array(owner, "int64"), np.array(member, "int64"), np.array(cluster, "int64"), m, 1, family))
    held = {}
    for b, v in zip(mb, mm, strict=True):
        held.setdefault(b, []).append(v)
    return held, sorted((o, v) for b, o in zip(lb, lo, strict=True) for v in held[b])


@pytest.mark.parametrize("m, family", [(1, "affine"), (2, "xx")])
def test_refine_covers_each_pair_once(m, family):
    rng = np.random.default_rng(5)
    pairs = sorted({(int(o) * 10**11, int(v) - 60) for o, v in zip(rng.integers(0, 60, 2_500), rng.integers(0, 150, 2_500), strict=True)} | {(o * 10**11, v) for o in range(20, 40) for v in range(200, 230)})
    owner, member = zip(*pairs, strict=True)
    held, got = cover(owner, member, [o // 10**11 % 3 for o in owner], m, family)
    assert got == pairs
    assert len(held) < len(pairs) and sum(map(len, held.values())) < len(pairs) - 30 * 10  # the planted square is shared


def test_planes_return_any_numbers():
    for x in ([], [5], [-(2**62), 2**62, 0, -1], list(range(1000))):
        a = np.array(x, "int64")
        assert packed._from_planes(packed._planes(a), len(a)).tolist() == x


def no_rows_of_pairs(monkeypatch):
    monkeypatch.setattr(sb, "build_from_pairs", lambda *a, **k: pytest.fail("pairs went by joins"))


@pytest.mark.parametrize("name", ["khop_emc_sum_relay_both_k2", "khop_mc_sum_copurchase_all_k1", "khop_mc_sum_synthrand_d200_k1", "topo_block_sum_eventbranch", "khop_mc_sum_relay_both_k2", "topo_block_sum_synthdag_d3"])
def test_near_random_windows(spark, duck, tiny_dir, monkeypatch, name):
    """F4, F5, F6, F8, F16, F18."""
    no_rows_of_pairs(monkeypatch)
    assert normal(workloads.QUERIES[name](spark, tiny_dir)) == normal(duck.execute(workloads.ORACLES[name]))


@pytest.mark.parametrize("window", [KHop(1), KHop(2, "in", False), KHop(3, "both")])
def test_cover_over_several_tasks(spark, monkeypatch, window):
    no_rows_of_pairs(monkeypatch)
    monkeypatch.setattr(sb, "TASK_PAIRS", 300)
    monkeypatch.setattr(packed, "PACK_ROWS", 170)
    rng = np.random.default_rng(3)
    e = sorted({(int(a), int(b)) for a, b in rng.integers(0, 90, (260, 2)) if a < b})
    g = G.literal(spark, e, list(range(95)), directed=window.direction != "out")
    for waves in (1, 2):
        ix = sb.build_block_index(g, window, waves=waves, max_pairs_per_cluster=200)
        assert sb.check_cover(ix, window_pairs(g, window)) == {"missing": 0, "extra": 0, "overlapping": 0}
    sums = [Agg("sum", "attr", "total"), Agg("count", None, "n")]
    assert normal(sb.block_query(ix, g, sums)) == normal(direct(g, window, sums))


@pytest.mark.parametrize("window", [KHop(2, "both"), KHop(2, "out", False)])
def test_two_hops_are_walked_within_tasks(spark, monkeypatch, window):
    """F4, F16: no path is sent, unless a graph has too many steps to send whole."""
    no_rows_of_pairs(monkeypatch)
    monkeypatch.setattr(sb, "TASK_PAIRS", 300)
    monkeypatch.setattr(packed, "REFINE_PAIRS", 150)
    sent, run = [], sb.packed_blocks
    monkeypatch.setattr(sb, "packed_blocks", lambda pairs, *a: sent.append(pairs is not None) or run(pairs, *a))
    g = G.literal(spark, [(a * 10**11, b * 10**11) for a in range(40) for b in (a * 7 % 41, a * a % 37) if a != b], directed=True)
    for steps, paths in ((sb.WALK_STEPS, False), (10, True)):
        monkeypatch.setattr(sb, "WALK_STEPS", steps)
        ix = sb.build_block_index(g, window, "emc")
        assert sb.check_cover(ix, window_pairs(g, window)) == {"missing": 0, "extra": 0, "overlapping": 0}
        assert sent.pop() is paths


def test_steps_of_chunks_in_any_order():
    """F4, F16."""
    rng = np.random.default_rng(6)
    for far in (1, 10**13):
        e = np.unique(rng.integers(-50, 50, (700, 2)) * far, axis=0)
        steps = packed.Steps([(len(x), packed._planes(x[:, 0]), packed._planes(x[:, 1])) for x in (e[0::3], e[1::3], e[2::3])])
        ask = np.array([7, -50, 49, 10**15, 7, 0]) * far
        at, to = steps.from_(ask)
        assert sorted(zip(at.tolist(), to.tolist(), strict=True)) == sorted((i, int(d)) for i, a in enumerate(ask) for s, d in e if s == a)
        assert steps.degree(ask).tolist() == np.bincount(at, minlength=6).tolist()


def test_large_windows_go_by_joins(spark, monkeypatch):
    monkeypatch.setattr(sb, "WINDOW_PAIRS", 3)
    g = G.literal(spark, [(0, 1), (0, 2), (0, 3), (3, 4)])
    ix = sb.build_block_index(g, KHop(2))
    assert sb.check_cover(ix, window_pairs(g, KHop(2))) == {"missing": 0, "extra": 0, "overlapping": 0}


@pytest.mark.parametrize("window", [Topological(), Topological("descendants", False)])
def test_parts_are_dealt_over_slots(spark, monkeypatch, window):
    from graphwin.operators import parts

    no_rows_of_pairs(monkeypatch)
    monkeypatch.setattr(parts, "DEALT", 10)
    rng = np.random.default_rng(4)
    e = sorted({(int(a), int(b)) for a, b in rng.integers(0, 80, (200, 2)) if a < b})
    g = G.literal(spark, e, list(range(85)), directed=True)
    ix = sb.build_block_index(g, window)
    assert sb.check_cover(ix, window_pairs(g, window)) == {"missing": 0, "extra": 0, "overlapping": 0}
    with pytest.raises(CycleError):
        sb.build_block_index(G.literal(spark, [(1, 2), (2, 1)], directed=True), window)


def test_loose_steps_are_the_arcs(spark, tiny_dir):
    for g in (G.copurchase(spark, tiny_dir, 1), G.synthrand(spark, 300, 20)):
        assert normal(g.loose_steps().distinct()) == normal(g.arcs_with_self())
    g = G.literal(spark, [(1, 2), (2, 3)], directed=True)
    assert normal(g.loose_steps("both").distinct()) == normal(g.arcs_with_self("both"))


def test_loose_steps_of_directed_edges(spark, tiny_dir):
    """F4, F16."""
    g = G.relay(spark, tiny_dir)
    assert normal(g.loose_steps("both").distinct()) == normal(g.arcs_with_self("both")) and normal(g.loose_steps("in")) == normal(g.arcs_with_self("in"))


@pytest.mark.parametrize("name", ["topo_block_sum_synthdag_d3", "khop_mc_sum_synthrand_d200_k1", "khop_mc_sum_copurchase_all_k1", "khop_mc_sum_relay_both_k2", "khop_emc_sum_relay_both_k2"])
def test_one_query_writes_no_members_of_blocks(spark, tiny_dir, monkeypatch, name):
    """F4, F5, F6, F16, F18: an index for one query is added up where it is formed."""
    labels, write = [], sb.materialize
    monkeypatch.setattr(sb, "materialize", lambda df, label, *a: labels.append(label) or write(df, label, *a))
    workloads.QUERIES[name](spark, tiny_dir)
    assert "sums" in labels and not {"sb_rows", "sb_members", "triples"} & set(labels)


@pytest.mark.parametrize("window", [Topological(), Topological("descendants", False), KHop(2, "both"), KHop(1, "out", False)])
def test_sums_where_blocks_are_formed(spark, monkeypatch, window):
    from graphwin.operators import parts

    monkeypatch.setattr(parts, "DEALT", 10)
    monkeypatch.setattr(parts, "MASK_BYTES", 64)  # several stretches of members
    monkeypatch.setattr(sb, "WAVE_PAIRS", 2_500)
    g = G.synthdag(spark, 90, 3)
    v = g.vertices.withColumn("attr", F.expr("IF(id % 4 = 0, NULL, CAST(attr - 40 AS INT))"))
    g = PropertyGraph(v, g.edges, True)
    sums = [Agg("sum", "attr", "total"), Agg("sum", "attr", "part", where="id % 8 = 0"), Agg("count", "attr", "n"), Agg("count_if", None, "odd", where="id % 2 = 1"), Agg("avg", "attr", "mean")]
    some = g.vertices.where("id % 3 = 0").select(F.col("id").alias("owner"))
    for owners in (None, some):
        got = sb.block_query_once(g, window, sums, owners)
        assert normal(got) == normal(direct(g, window, sums, owners))
    others = [Agg("sum", "big", "total"), Agg("max", "big", "most")]  # sums that may overflow, and what isn't a sum, go by a stored index
    h = PropertyGraph(v.withColumn("big", F.expr("IF(id = 0, 1L << 58, id)")), g.edges, True)
    assert sb._additive(h, others) is None and sb._additive(h, others[:1]) is None
    assert normal(sb.block_query_once(h, window, others)) == normal(direct(h, window, others))
