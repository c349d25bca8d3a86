"""Index, signature, cluster and top-k queries over the relay graph of all orders."""

import pytest
from conftest import normal

from graphwin import workloads

SUMS = [f"khop_{s}_sum_relay_{d}_k{k}" for d in ("out", "in", "both") for s, k in (("mc", 1), ("mc", 2), ("emc", 2))]


@pytest.mark.parametrize("name", [*SUMS, "khop_topk_relay_k2", "minhash_explicit_relay_k2", "minhash_propagated_relay_k2"])
def test_whole_relay(spark, duck, tiny_dir, name):
    assert normal(workloads.QUERIES[name](spark, tiny_dir)) == normal(duck.execute(workloads.ORACLES[name]))


@pytest.mark.parametrize("name", ["cluster_full_relay_k2", "cluster_estimated_relay_k2"])
def test_clusters_hold_every_owner(spark, tiny_dir, name):
    got = [r["owner"] for r in workloads.QUERIES[name](spark, tiny_dir).collect()]
    assert len(got) == len(set(got)) == spark.read.parquet(f"{tiny_dir}/customer.parquet").count()
