"""Shards are built, refreshed and walked in tasks of their own, and their nodes are pruned in step."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from sidecar_ann.functions import graph as G
from sidecar_ann.operators import index as I
from sidecar_ann.workloads import core, registry, streams  # noqa: F401

SF = "/root/testdata/sf0.001"

#: Query -> how often its index is dealt out: built, refreshed, walked.
DEALT = {
    "ann_exhaustive_centroid_shards": 1,
    "hybrid_exhaustive": 1,
    "ann_exhaustive_file_shards": 1,
    "hnsw_exhaustive": 2,
    "stream_knn": 2,
    "w_knn_label_vote": 2,
    "ann_exhaustive_topk": 2,
    "cow_delete_exhaustive": 3,
    "filtered_knn_post": 2,
    "refresh_append_exhaustive": 3,
    "refresh_delete_exhaustive": 3,
    "w_knn_group": 2,
}


@pytest.mark.parametrize("name", DEALT)
def test_each_shard_has_a_task(spark, name, monkeypatch):
    found, deal = [], I.a_task_each

    def spy(rows, shards):
        out = deal(rows, shards)
        got = out.select(F.spark_partition_id().alias("p"), "shard").distinct().collect()
        found.append((len(shards), len({r["shard"] for r in got}), len({r["p"] for r in got}), len(got)))
        return out

    monkeypatch.setattr(I, "a_task_each", spy)
    monkeypatch.setattr(registry, "_built", {})
    registry.QUERIES[name](spark, SF)
    assert len(found) >= DEALT[name]
    assert all(f == (f[0],) * 4 and f[0] > 1 for f in found)


@pytest.mark.parametrize("saturate", [False, True])
@pytest.mark.parametrize("metric", ["l2", "ip"])
def test_pruning_in_step_keeps_what_pruning_alone_keeps(metric, saturate):
    """Candidates of very different numbers, none, repeated ones, the node itself, equal vectors, and one crowd."""
    rng = np.random.default_rng(0)
    x = rng.integers(-2, 3, size=(2000, 4)).astype(float)
    nodes = rng.permutation(2000)[:60]
    cand = [rng.integers(-1, 2000, size=n) for n in rng.integers(0, 90, size=58)] + [np.arange(2000), np.full(5, nodes[59])]
    got = G.prune_many(x, nodes, cand, 1.2, 7, metric, saturate)
    for k, p in enumerate(nodes):
        want = G.robust_prune(x, int(p), cand[k], 1.2, 7, metric, saturate)
        assert got[k].tolist() == want.tolist() + [-1] * (7 - len(want))


def test_a_build_prunes_no_node_alone(monkeypatch):
    """Nor the nodes that many edges meet in."""
    alone, prune = [], G.robust_prune
    monkeypatch.setattr(G, "robust_prune", lambda *a, **b: alone.append(a[1]) or prune(*a, **b))
    x = np.concatenate([np.random.default_rng(0).normal(size=(300, 8)), np.zeros((60, 8))])
    table, entries = G.build_graph(x, G.GraphParams(R=6, L=12, n_entries=3))
    assert G.reachable(table, entries).all()
    assert all(len(set(r[r >= 0])) == (r >= 0).sum() and i not in r for i, r in enumerate(table))
    G.insert(x, table, entries, x[:40] + 0.01, G.GraphParams(R=6, L=12, n_entries=3))
    assert not alone
