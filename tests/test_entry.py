"""Driver contract: the entry, the keys, and a few keys against their SQL."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_entry(spark):
    assert entry.entry(spark).count() == 50


def test_keys():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 120


@pytest.mark.parametrize("name", ["dist_l2", "exact_topk", "file_radius", "centroid_topk", "kmeans_one_step", "pq_encode", "graph_reachable", "ann_exhaustive_topk", "snapshot_diff", "rel_cube", "rel_asof_join_whole", "stream_session"])
def test_against_sql(spark, sf, name):
    got = entry.queries()[name](spark, sf).toPandas()
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    want = con.sql(entry.oracle_sql()[name]).df()
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    rows = lambda d: sorted(map(tuple, d[columns].astype(str).values.tolist()))
    assert rows(got) == rows(want)
