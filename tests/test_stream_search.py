"""A stream of queries: what all its batches look at is found and read once a version."""

from pyspark.sql import functions as F
from sidecar_ann.operators.exact import exact_batch_topk
from sidecar_ann.operators.index import IndexManager
from sidecar_ann.streaming import streams as S
from sidecar_ann.workloads.registry import EXHAUSTIVE, SMALL, per_file, queries_of, table_of, uniform

SF = "/root/testdata/sf0.001"


def rows_of(df):
    return sorted((r["qid"], r["rank"], r["vec_id"], round(r["distance"], 9)) for r in df.collect())


def counted(monkeypatch):
    calls = {"reached": 0, "rows_at": 0}
    for name in calls:

        def spy(self, *a, f=getattr(IndexManager, name), name=name, **b):
            calls[name] += 1
            return f(self, *a, **b)

        monkeypatch.setattr(IndexManager, name, spy)
    return calls


def test_batches_share_the_walk_and_the_rows(spark, tmp_path, monkeypatch):
    table = table_of(spark, SF, per_file=per_file(spark, SF))
    m = IndexManager(table)
    m.create("ix", "v", **SMALL)
    qs = queries_of(uniform(spark, SF))
    qs.repartition(5, "qid").write.parquet(f"{tmp_path}/q")
    calls, batches = counted(monkeypatch), []
    stream = spark.readStream.schema(qs.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/q")
    S.search_stream(stream, m, "ix", 3, lambda df, i: batches.append(df.count()) or df.write.parquet(f"{tmp_path}/out/b{i}"), f"{tmp_path}/cp", **EXHAUSTIVE).awaitTermination()
    assert len(batches) > 2
    assert calls == {"reached": 1, "rows_at": 1}
    assert rows_of(spark.read.option("recursiveFileLookup", "true").parquet(f"{tmp_path}/out")) == rows_of(exact_batch_topk(uniform(spark, SF), qs, 3))


def test_a_new_version_is_not_answered_from_held_rows(spark):
    """Rows that come or go between two batches count from the next batch on; filters see their own rows."""
    each = per_file(spark, SF)
    e, qs = uniform(spark, SF), queries_of(uniform(spark, SF))
    table = table_of(spark, SF, f"vec_id < {18 * each}", per_file=each)
    m = IndexManager(table)
    m.create("ix", "v", **SMALL)
    ask = lambda **o: rows_of(m.search("ix", qs, 5, hold=True, **EXHAUSTIVE, **o))
    want = lambda where: rows_of(exact_batch_topk(e.filter(where), qs, 5))
    old = table.log.current().version
    assert ask() == want(f"vec_id < {18 * each}")
    table.remove_files([0, 1])
    assert ask() == want(f"vec_id >= {2 * each} AND vec_id < {18 * each}")
    table.append(e.filter(f"vec_id >= {18 * each}"), 1)
    assert ask() == want(f"vec_id >= {2 * each}")
    assert ask(where=F.col("label") == 3, filter_mode="post") == want(f"vec_id >= {2 * each} AND label = 3")
    m.refresh("ix")
    assert ask(stale="error") == want(f"vec_id >= {2 * each}")
    assert ask(version=old) == want(f"vec_id < {18 * each}")
