"""Cliques of twins: no edge of theirs is formed, the windows are those of the whole graph."""

import pytest
from conftest import normal
from pyspark.sql import functions as F

from graphwin import workloads
from graphwin.functions.aggregates import Agg
from graphwin.model import KHop, PropertyGraph
from graphwin.operators.blockindex import block_query, build_block_index, expand_index
from graphwin.operators.direct import direct
from graphwin.operators.overlay import build_overlay, overlay_query
from graphwin.operators.reach import window_pairs
from graphwin.sources import graphs as G


@pytest.mark.parametrize("name", ["khop_community_k2", "khop_community_k1_overlay"])  # F15, F3
def test_no_edge_of_a_clique(spark, duck, tiny_dir, name, monkeypatch):
    whole = G.community

    def bare(s, d):
        g = whole(s, d)
        return PropertyGraph(g.vertices, g.edges.withColumn("src", F.raise_error(F.lit("an edge")).cast("long")), False, g.name, twins=g.twins, between=g.between)

    run = workloads._by_strategy(bare, KHop(2), [Agg("sum", "n_chars", "total")], "mc") if name == "khop_community_k2" else workloads._by_strategy(bare, KHop(1), [Agg("sum", "n_chars", "total")], "overlay", iterations=10)
    assert normal(run(spark, tiny_dir)) == normal(duck.execute(workloads.ORACLES[name]))


def test_twins_with_other_neighbours(spark):
    """Cliques {1, 2, 3} and {4, 5} all linked, {5...} to 6 through both, 7 alone."""
    e = [(1, 2), (1, 3), (2, 3), (4, 5), *[(a, b) for a in (1, 2, 3) for b in (4, 5)], (4, 6), (5, 6), (6, 8)]
    g = G.literal(spark, e, [7])
    reps = {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 6: 6, 7: 7, 8: 8}
    t = PropertyGraph(g.vertices, g.edges, False, "t", twins=spark.createDataFrame(list(reps.items()), "id long, rep long"), between=spark.createDataFrame([(1, 4), (4, 6), (6, 8)], "src long, dst long"))
    sums = [Agg("sum", "attr", "total")]
    for k in (1, 2, 3):
        want = normal(direct(g, KHop(k), sums))
        ix = build_block_index(t, KHop(k))
        assert normal(block_query(ix, t, sums)) == want == normal(overlay_query(build_overlay(t, KHop(k), 2), t, sums))
        assert normal(expand_index(ix)) == normal(window_pairs(g, KHop(k)).withColumn("copies", F.lit(1)))


def test_similar_in_cells(spark, duck, tiny_dir, monkeypatch):
    """vectors meet as matrices, cell by cell; no expression compares two vectors. Any number of cells gives the same."""
    sql = f"WITH {workloads._SIMILAR_SQL} SELECT src, dst FROM e"
    for cell in (17, 16_384):
        monkeypatch.setattr(G, "CELL", cell)
        e = G.similar(spark, tiny_dir).edges
        assert normal(e) == normal(duck.execute(sql))
        assert "zip_with" not in e._jdf.queryExecution().optimizedPlan().toString()
