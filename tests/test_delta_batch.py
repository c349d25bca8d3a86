"""A batch of changes to the parent-delta index: equal to a rebuild, and a 1% change set of a DAG over the tables."""

import random

import pytest
from conftest import normal

from graphwin import workloads
from graphwin.model import CycleError
from graphwin.operators import deltaindex as pd
from graphwin.operators import updates
from graphwin.sources import graphs as G


def changes_of(spark, rows):
    return spark.createDataFrame(rows, "op string, src long, dst long")


def test_batch_equals_rebuild(spark):
    rnd = random.Random(3)
    edges = sorted({(a, b) for b in range(1, 30) for a in rnd.sample(range(b), min(b, 2))})
    g = G.literal(spark, edges, list(range(32)), directed=True)
    gone = rnd.sample(edges, 6)
    more = [(2, 31), (31, 40), (5, 29), (0, 17), (30, 12)]  # 40 is new, 30 and 31 had no edge
    ix, after = updates.update_delta_batch(pd.build_delta_index(g), g, changes_of(spark, [("-", *e) for e in gone] + [("+", *e) for e in more]))
    assert {tuple(e) for e in after.edges.select("src", "dst").collect()} == set(edges) - set(gone) | set(more)
    whole = pd.build_delta_index(after)
    for a, b in ((ix.parent, whole.parent), (ix.delta, whole.delta)):
        assert normal(a) == normal(b)


def test_batch_refuses_a_cycle(spark):
    g = G.literal(spark, [(0, 1), (1, 2)], directed=True)
    with pytest.raises(CycleError):
        updates.update_delta_batch(pd.build_delta_index(g), g, changes_of(spark, [("+", 2, 0)]))


@pytest.mark.parametrize("op", ["insert", "delete"])
def test_change_set_of_the_tables(spark, duck, tiny_dir, op):
    name = f"update_{op}_delta_eventbranch"
    assert workloads._edge_changes(G.eventbranch(spark, tiny_dir), "+").count() > 2
    assert normal(workloads.QUERIES[name](spark, tiny_dir)) == normal(duck.execute(workloads.ORACLES[name]))
