"""Searches whose options cut nothing, against SQL: the candidates are found once, not once a query."""

import duckdb
import numpy as np
import pytest
from sidecar_ann.functions import distance as D
from sidecar_ann.operators.exact import exact_batch_topk
from sidecar_ann.operators.index import IndexManager
from sidecar_ann.workloads import core, streams  # noqa: F401
from sidecar_ann.workloads.registry import QUERIES, SQL

SF = "/root/testdata/sf0.001"
ROWS = 500


def answers(spark, name, monkeypatch):
    """(rows, rows by SQL, rows of the largest table that a search kept of its candidates)."""
    kept, put = [0], IndexManager._kept

    def spy(self, df):
        out = put(self, df)
        if "row_offset" in out.columns:
            kept.append(out.count())
        return out

    monkeypatch.setattr(IndexManager, "_kept", spy)
    got = sorted(tuple(r) for r in QUERIES[name](spark, SF).collect())
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{SF}/embeddings.parquet')")
    return got, sorted(con.execute(SQL[name]).fetchall()), max(kept)


ONCE = [
    "ann_batch_exhaustive",
    "ann_exhaustive_centroid_shards",
    "hybrid_exhaustive",
    "ann_exhaustive_file_shards",
    "hnsw_exhaustive",
    "stream_knn",
    "w_knn_label_vote",
    "filtered_knn_post",
    "refresh_append_exhaustive",
    "ann_exhaustive_topk",
    "cow_delete_exhaustive",
    "refresh_delete_exhaustive",
    "w_knn_group",
]


@pytest.mark.parametrize("name", ONCE)
def test_candidates_do_not_grow_with_the_queries(spark, name, monkeypatch):
    got, want, kept = answers(spark, name, monkeypatch)
    assert got == want
    assert 0 < kept <= ROWS


@pytest.mark.parametrize("metric", D.METRICS)
def test_all_rows_as_near_as_the_last_place_are_measured(spark, metric):
    """Far more equal rows than places, the smaller ids in the later rows."""
    rng = np.random.default_rng(0)
    common = [0.6, 0.8, 0.0]
    rows = [(i, common) for i in range(400, 100, -1)] + [(i, rng.normal(size=3).tolist()) for i in range(100)]
    e = spark.createDataFrame(rows, "vec_id long, v array<double>").repartition(2)
    qs = spark.createDataFrame([(0, common), (1, [0.59, 0.8, 0.01])], "qid long, qv array<double>")
    got = sorted((r["qid"], r["rank"], r["vec_id"]) for r in exact_batch_topk(e, qs, 5, metric=metric).collect())
    want = []
    for qid, q in ((0, common), (1, [0.59, 0.8, 0.01])):
        d = sorted((float(D.exact_distances(np.array([v]), np.array(q), metric)[0]), i) for i, v in rows)
        want += [(qid, k + 1, i) for k, (_, i) in enumerate(d[:5])]
    assert got == want


def test_centroid_batches_pair_no_rows_with_queries(spark):
    """The rows of a file meet its queries in a kernel, not in a join."""
    from sidecar_ann.workloads.registry import queries_of, shared, uniform

    got = shared(spark, SF)[1].search_centroid_batch("ix", queries_of(uniform(spark, SF)), 10, 5)
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()
