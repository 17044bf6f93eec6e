"""Engine: worked examples, invariants, and the arithmetic that the published figures rest on."""

import threading

import numpy as np
import pytest
from pyspark.sql import functions as F

from sidecar_ann.errors import BadParameter, CommitConflict, CorruptContainer, StaleIndex, UnknownIndex
from sidecar_ann.functions import distance as D
from sidecar_ann.functions import graph as G
from sidecar_ann.functions import quantize as Q
from sidecar_ann.operators.centroids import CentroidProbe, centroids_of
from sidecar_ann.operators.exact import exact_batch_topk, exact_topk
from sidecar_ann.operators.index import IndexManager, IndexOptions, plan_shards
from sidecar_ann.plans import cost
from sidecar_ann.plans.detect import detect
from sidecar_ann.plans.session import AnnSession
from sidecar_ann.sources import blobs, coding, store
from sidecar_ann.sources.catalog import Change, Table
from sidecar_ann.sources.container import GRAPH, Blob, read_footer, write_container
from sidecar_ann.workloads.core import benchmark_overlap
from sidecar_ann.workloads.registry import QUERIES


# ---- kernels
def test_line_topk_ties_and_bounds(spark):
    rows = spark.createDataFrame([(i, [float(i)]) for i in range(10)] + [(77, None)], "vec_id long, v array<double>")
    assert [r["vec_id"] for r in exact_topk(rows, [4.5], 4).collect()] == [4, 5, 3, 6]
    qs = spark.createDataFrame([(1, [4.5])], "qid long, qv array<double>")
    assert [r["vec_id"] for r in exact_batch_topk(rows, qs, 4).orderBy("rank").collect()] == [4, 5, 3, 6]
    assert exact_batch_topk(rows, qs, 100).count() == 10
    assert exact_batch_topk(rows, qs.limit(0), 3).count() == 0


def test_cosine_of_zero_is_null_and_validity(spark):
    bad = spark.createDataFrame([(0, [0.0, 0.0]), (1, None), (2, [1.0]), (3, [float("nan"), 1.0]), (4, [3.0, 4.0])], "i int, v array<double>")
    got = {r["i"]: (r["ok"], r["c"]) for r in bad.select("i", D.is_valid_vector(F.col("v"), 2).alias("ok"), D.cosine(F.col("v"), D.literal([3.0, 4.0])).alias("c")).collect()}
    assert [got[i][0] for i in range(5)] == [True, False, False, False, True]
    assert got[0][1] is None and got[4][1] == pytest.approx(0)


def test_prune_on_hand_placed_points():
    x = np.array([[0, 0], [1, 0], [2, 0], [0, 1.5], [2.2, 0.1], [0, 3.2]], float)
    assert G.robust_prune(x, 0, np.arange(6), 1.0, 5).tolist() == [1, 3]
    assert G.robust_prune(x, 0, np.arange(6), 1.0, 1).tolist() == [1]
    assert set(G.robust_prune(x, 0, np.arange(6), 1.0, 4, saturate=True).tolist()) == {1, 3, 2, 4}
    assert len(G.robust_prune(x, 0, np.arange(6), 3.0, 5)) >= 3


@pytest.mark.parametrize("seed", range(5))
def test_graph_invariants_and_exhaustive_search(seed):
    rng = np.random.default_rng(seed)
    x = np.concatenate([rng.normal(size=(60, 8)), rng.normal(size=(40, 8)) * 0.1 + 20])
    p = G.GraphParams(R=6, L=16, n_entries=1, seed=seed)
    table, entries = G.build_graph(x, p)
    assert G.reachable(table, entries).all()
    for i, row in enumerate(table):
        own = row[row >= 0]
        assert i not in own and len(set(own.tolist())) == len(own) <= 6 and (own < 100).all()
    got = G.beam_search(x, table, entries, x[::7], 100)
    assert (np.sort(got.ids, 1) == np.arange(100)).all()
    assert (np.diff(got.distance, axis=1) >= 0).all() and (got.visited <= 100).all()
    keep, small, e = G.consolidate(x, table, np.arange(100) % 4 == 0, p)
    assert G.reachable(small, e).all() and len(keep) == 75


def test_small_and_degenerate_graphs():
    for n in (0, 1, 2, 3):
        table, entries = G.build_graph(np.ones((n, 4)), G.GraphParams(R=4, L=4))
        assert len(table) == n and G.reachable(table, entries).all()
    assert (G.beam_search(np.zeros((0, 4)), np.zeros((0, 4), int), np.zeros(0, int), np.ones((2, 4)), 3).ids == -1).all()


def test_tiny_codebook():
    x = np.array([[0, 0, 0, 0], [1, 1, 1, 1], [0, 0, 1, 1], [1, 1, 0, 0]], float)
    book = np.array([[[0, 0], [1, 1]], [[0, 0], [1, 1]]], float)
    assert Q.pq_encode(x, book).tolist() == [[0, 0], [1, 1], [0, 1], [1, 0]]
    assert Q.adc_scores(Q.pq_encode(x, book), Q.adc_table(x[1], book)).tolist() == [4, 0, 2, 2]
    assert Q.pq_mse(x, book) == 0
    with pytest.raises(BadParameter):
        Q.train_pq(x, 3, 2)
    with pytest.raises(BadParameter):
        IndexOptions(metric="l1")


def test_recall_rises_with_beam():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(800, 32))
    table, entries = G.build_graph(x, G.GraphParams(R=12, L=32))
    q = x[::40] + 0.05 * rng.normal(size=(20, 32))
    true = ((x[None] - q[:, None]) ** 2).sum(-1).argsort(1)[:, :10]
    r = [np.mean([len(set(a[:10]) & set(b)) / 10 for a, b in zip(G.beam_search(x, table, entries, q, L).ids, true)]) for L in (10, 40, 160, 800)]
    assert r == sorted(r) and r[-1] == 1 and r[2] > 0.9


# ---- storage
def test_codings_and_corruption(tmp_path):
    x = np.array([0, 1, 127, 128, 1 << 40, (1 << 63) - 1], np.uint64)
    assert (coding.varint_decode(coding.varint_encode(x)) == x).all()
    assert len(coding.varint_decode(b"")) == 0 and len(coding.delta_decode(coding.delta_encode(np.zeros(0)))) == 0
    store.put(str(tmp_path / "x"), b"not a container at all, much too plain")
    with pytest.raises(CorruptContainer):
        read_footer(str(tmp_path / "x"))
    with pytest.raises(CorruptContainer):
        blobs.decode_shard(b"abcd" * 10)
    write_container(str(tmp_path / "y"), [Blob(GRAPH, b"1")])
    with pytest.raises(FileExistsError):
        write_container(str(tmp_path / "y"), [Blob(GRAPH, b"2")])


@pytest.fixture(scope="module")
def rows(spark, sf):
    return spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", F.col("embedding").alias("v"), "label").filter("vec_id < 160").cache()


def make(spark, rows, tmp_path, files=8):
    return Table.create(spark, str(tmp_path / "t"), rows, "vec_id", files, file_no=(F.col("vec_id") / 20).cast("int"))


def test_snapshots(spark, rows, tmp_path):
    t = make(spark, rows.filter("vec_id < 100"), tmp_path)
    t.append(rows.filter("vec_id >= 140"))
    t.remove_files([0])
    t.delete_where(F.col("label") == 1)
    assert [t.df(v).count() for v in (1, 2, 3)] == [100, 120, 100]
    assert t.df().filter("label = 1").count() == 0 and t.df().count() == rows.filter("(vec_id BETWEEN 20 AND 99 OR vec_id >= 140) AND label <> 1").count()
    assert {s for s, in t.diff(1, 2).select("status").distinct().collect()} == {"EXISTING", "ADDED"}
    assert t.log.at(timestamp_ms=t.log.snapshot(2).ts_ms).version == 2


def test_racing_commits(spark, rows, tmp_path):
    t = make(spark, rows.filter("vec_id < 100"), tmp_path)
    base = t.log.current()
    more = [t._write(rows.filter(f"vec_id = {100 + k}"), "vec_id", 1, None, None, 50 + k) for k in range(4)]
    work = [threading.Thread(target=t.log.commit, args=(base, Change("append", add=m))) for m in more]
    for w in work:
        w.start()
    for w in work:
        w.join()
    assert t.log.versions() == [1, 2, 3, 4, 5] and t.df().count() == 104
    gone = {f.path for f in t.log.files(base) if f.file_no == 0}
    t.log.commit(base, Change("delete", remove=gone))
    with pytest.raises(CommitConflict):
        t.log.commit(base, Change("delete", remove=gone))


# ---- index
def found(df):
    return {(r["qid"], r["vec_id"]) for r in df.collect()}


def test_index_through_its_life(spark, rows, tmp_path):
    t = make(spark, rows.filter("vec_id < 120"), tmp_path)
    m = IndexManager(t)
    m.create("ix", "v", R=8, L=16, num_shards=3, pq_nbits=3, cells=4)
    qs = rows.filter("vec_id % 30 = 0").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    wide = {"L": 10_000, "shard_oversample": 10_000, "rerank_oversample": 10_000}
    truth = lambda cond: found(exact_batch_topk(rows.filter(cond), qs, 5))
    assert found(m.search("ix", qs, 5, **wide)) == truth("vec_id < 120")
    t.append(rows.filter("vec_id >= 120"))
    with pytest.raises(StaleIndex):
        m.search("ix", qs, 5, stale="error")
    assert found(m.search("ix", qs, 5, **wide)) == found(m.search("ix", qs, 5, stale="exact")) == truth("true")
    m.refresh("ix")
    t.remove_files([0])
    assert found(m.search("ix", qs, 5, **wide)) == truth("vec_id >= 20")
    m.refresh("ix")
    assert {r["dead"] for r in m.tombstones("ix").collect()} <= {6, 7}
    assert found(m.search("ix", qs, 5, stale="error", **wide)) == truth("vec_id >= 20")
    t.remove_files([1, 2])
    m.refresh("ix")
    assert all(r["rebuilt"] for r in m.last_results) and m.describe("ix")["rows"] == 100
    assert found(m.search("ix", qs, 5, version=2, **wide)) == truth("vec_id < 120")
    m.drop("ix")
    with pytest.raises(UnknownIndex):
        m.open("ix")
    assert found(m.search("ix", qs, 5, version=2, **wide)) == truth("vec_id < 120")
    before = t.log.referenced()
    assert not set(t.log.orphans()) & before


def test_upkeep_reads_only_what_changed(spark, rows, tmp_path):
    t = make(spark, rows.filter("vec_id < 120"), tmp_path)
    m = IndexManager(t)
    m.create("ix", "v", R=8, L=16, num_shards=3, pq_nbits=3, cells=4)
    assert m.last_centroid_files == [f.file_no for f in t.log.files(t.log.current())]
    before = m.centroids("ix")
    t.remove_files([1])
    new = {f.file_no for f in t.log.files(t.append(rows.filter("vec_id >= 120")))} - set(before.file_no.tolist())
    m.refresh("ix")
    assert set(m.last_centroid_files) == new
    after, snap = m.centroids("ix"), t.log.current()
    whole = {c["file_no"]: c for c in centroids_of(t, snap, "v", after.centroid.shape[1])}
    assert after.file_no.tolist() == sorted(whole)
    for n, c, r in zip(after.file_no, after.centroid, after.radius):
        assert np.allclose(c, whole[n]["centroid"], atol=1e-6) and whole[n]["radius"] <= r < whole[n]["radius"] + 1e-5
    kept = np.isin(before.file_no, after.file_no)
    assert (before.radius[kept] == after.radius[np.isin(after.file_no, before.file_no)]).all()  # taken over, not widened


def test_rebuild_of_one_shard(spark, rows, tmp_path):
    t = make(spark, rows, tmp_path)
    m = IndexManager(t)
    m.create("ix", "v", R=8, L=16, num_shards=3, pq_nbits=3, cells=4)
    t.remove_files([0])
    m.refresh("ix")
    dead = {s["shard"]: s["dead"] for s in m.open("ix").shards}
    paths = {s["shard"]: s["path"] for s in m.open("ix").shards}
    assert all(dead.values())
    m.rebuild_shard("ix", 1)
    now = {s["shard"]: s for s in m.open("ix").shards}
    assert now[1]["dead"] == 0 and all(now[s]["path"] == paths[s] and now[s]["dead"] == dead[s] for s in (0, 2))
    m.maintain("ix", 0.0)
    assert sum(s["dead"] for s in m.open("ix").shards) == 0 and m.describe("ix")["rows"] == rows.filter("vec_id >= 20").count()
    qs = rows.filter("vec_id % 30 = 0").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    wide = {"L": 10_000, "shard_oversample": 10_000, "rerank_oversample": 10_000}
    assert found(m.search("ix", qs, 5, stale="error", **wide)) == found(exact_batch_topk(rows.filter("vec_id >= 20"), qs, 5))
    with pytest.raises(BadParameter):
        m.rebuild_shard("ix", 9)


def test_orphans_are_removed_after_the_grace_age(spark, rows, tmp_path):
    t = make(spark, rows, tmp_path)
    m = IndexManager(t)
    m.create("ix", "v", R=8, L=16, num_shards=3, pq_nbits=3, cells=4)
    t.overwrite(rows.filter("vec_id % 2 = 0"), 2)
    m.refresh("ix", rebuild_all=True)
    assert t.log.unreferenced(0) == []  # every version is kept still
    t.log.expire(1)
    assert t.log.remove_orphans(dry_run=False) == []  # too young
    found_now = t.log.remove_orphans(0)
    assert {n.split("/")[0] for n in found_now} == {"data", "index", "manifests"}
    assert t.log.remove_orphans(0, dry_run=False) == found_now and t.log.unreferenced(0) == []
    assert t.df().count() == rows.filter("vec_id % 2 = 0").count()
    qs = rows.filter("vec_id = 60").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    assert m.search("ix", qs, 3, stale="error").count() == 3


def test_statement_rebuilds_a_shard(spark, rows, tmp_path):
    s = AnnSession(spark, str(tmp_path))
    s.create_table("t", rows, "vec_id", files=8)
    s.sql("CREATE INDEX a ON TABLE t USING vamana (v) OPTIONS (R='6', L='12', num_shards='2', pq_nbits='3')")
    s.table("t").remove_files([0])
    assert s.sql("REBUILD INDEX a ON t SHARD 1").first()["state"] == "rebuilt"
    assert [x["dead"] > 0 for x in s.indexes("t").open("a").shards] == [True, False]


@pytest.mark.parametrize("metric", ["cosine", "ip", "l2sq"])
def test_other_metrics(spark, rows, tmp_path, metric):
    t = make(spark, rows, tmp_path)
    m = IndexManager(t)
    m.create("ix", "v", R=8, L=16, num_shards=2, pq_nbits=3, cells=4, metric=metric)
    qs = rows.filter("vec_id % 40 = 0").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    got = m.search("ix", qs, 5, L=10_000, shard_oversample=10_000, rerank_oversample=10_000)
    assert found(got) == found(exact_batch_topk(rows, qs, 5, metric=metric))


def test_bounds_hold_for_every_metric():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 6))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    groups = np.arange(300) % 10
    c = np.stack([x[groups == g].mean(0) for g in range(10)])
    r = np.array([np.sqrt(((x[groups == g] - c[g]) ** 2).sum(1)).max() for g in range(10)])
    for metric in D.METRICS:
        p = CentroidProbe(np.arange(10), c, r, metric)
        for q in rng.normal(size=(20, 6)):
            d = D.exact_distances(x, q[None], metric)
            assert all(p.bounds(q)[g] <= d[groups == g].min() + 1e-9 for g in range(10)), metric


def test_plan_shards_splits_large_cells():
    got = plan_shards([1000, 1, 1, 1], 4, 250)
    assert got[0] == [0, 1, 2, 3] and all(len(g) == 1 for g in got[1:])


# ---- planning
def test_patterns(spark):
    a = "array(1.0, -2, 3.5D)"
    p = detect(spark, f"SELECT id, l2_distance(v, {a}) AS d FROM t WHERE x = 3 ORDER BY d LIMIT 5 OFFSET 2")
    assert (p.table, p.column, p.metric, p.vector, p.k, p.offset, p.alias) == ("t", "v", "l2", (1.0, -2.0, 3.5), 5, 2, "d") and "x" in p.where
    p = detect(spark, f"SELECT * FROM t VERSION AS OF 4 ORDER BY cosine_distance({a}, v) LIMIT 3")
    assert (p.metric, p.k, p.version) == ("cosine", 3, 4)
    p = detect(spark, f"SELECT id FROM t WHERE 0.5 >= l2_distance(v, {a}) AND y < 2")
    assert (p.threshold, p.strict) == (0.5, False)
    for text in (f"SELECT id FROM t ORDER BY l2_distance(v, {a}) DESC LIMIT 5", f"SELECT id FROM t ORDER BY l2_distance(v, {a})", "SELECT id FROM t ORDER BY l2_distance(v, w) LIMIT 5", f"SELECT id FROM t WHERE l2_distance(v, {a}) < 1 OR x = 2", f"SELECT id FROM t WHERE l2_distance(v, {a}) > 1", "SELECT 1"):
        assert detect(spark, text) is None, text


def test_statements(spark, rows, tmp_path):
    s = AnnSession(spark, str(tmp_path))
    s.create_table("t", rows, "vec_id", files=4)
    s.sql("CREATE INDEX a ON TABLE t USING vamana (v) OPTIONS (R='6', L='12', num_shards='2', pq_nbits='3')")
    q = [float(x) for x in rows.filter("vec_id = 7").first()["v"]]
    text = "SELECT vec_id, l2_distance(v, array(" + ",".join(map(repr, q)) + ")) AS d FROM t WHERE label < 8 ORDER BY d LIMIT 4"
    assert [r["vec_id"] for r in s.sql(text).collect()] == [r["vec_id"] for r in s.compare(text).collect()]
    assert s.last_plan["index"] == "a" and s.explain(text)["tier"] == "driver"
    assert [r[0] for r in s.sql("SHOW INDEXES ON t").collect()] == ["a"]
    with pytest.raises(BadParameter):
        s.sql("CREATE INDEX b ON TABLE t USING btree (v)")


def test_centroid_search_of_a_stale_index(spark, tmp_path):
    near = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(40, 80)], "vec_id long, v array<double>")
    t = Table.create(spark, str(tmp_path / "t"), near, "vec_id", 4, cluster_by=["vec_id"])
    m = IndexManager(t)
    m.create("ix", "v", kind="centroid", pq_m=1, pq_nbits=2, cells=2)
    t.append(spark.createDataFrame([(i, [float(i), 0.0]) for i in range(3)], "vec_id long, v array<double>"))
    t.delete_where(F.col("vec_id") == 41)
    ids = lambda **how: [r["vec_id"] for r in m.search_centroid("ix", [0.0, 0.0], 5, **how).collect()]
    assert ids() == [0, 1, 2, 40, 42]
    assert ids(nprobe=1) == [0, 1, 2, 40, 42]
    assert ids(where=F.col("vec_id") > 1) == [2, 40, 42, 43, 44]
    assert ids(version=t.log.current().version - 2) == [40, 41, 42, 43, 44]


def test_sql_topk_of_a_centroid_index(spark, tmp_path):
    s = AnnSession(spark, str(tmp_path))
    s.create_table("t", spark.createDataFrame([(i, [float(i), 0.0], i % 2) for i in range(40)], "vec_id long, v array<double>, label int"), "vec_id", files=4)
    s.sql("CREATE INDEX cx ON TABLE t USING centroid (v) OPTIONS (pq_m='1', pq_nbits='2', cells='2')")
    got = s.sql("SELECT vec_id FROM t WHERE label = 1 ORDER BY l2_distance(v, array(9.8D, 0.0D)) LIMIT 3 OFFSET 1").collect()
    assert [r["vec_id"] for r in got] == [11, 7, 13] and s.last_plan["probe"] == "centroids"
    qs = spark.createDataFrame([(1, [9.8, 0.0])], "qid long, qv array<double>")
    assert [r["vec_id"] for r in s.indexes("t").search("cx", qs, 2).orderBy("rank").collect()] == [10, 9]


def test_asof_join_keeps_every_order(spark, tmp_path):
    from sidecar_ann.workloads import relational  # noqa: F401

    spark.createDataFrame([(i, i % 7) for i in (1, 2000, 2001, 9000)], "o_orderkey long, o_custkey long").write.parquet(str(tmp_path / "orders.parquet"))
    spark.sql("SELECT CAST(u AS LONG) AS user_id, TIMESTAMP_NTZ '2024-01-09 12:00:00' AS ts FROM VALUES (0), (1), (5), (6) t(u)").write.parquet(str(tmp_path / "events.parquet"))
    got = {r["o_orderkey"]: r["ts"] is not None for r in QUERIES["rel_asof_join_whole"](spark, str(tmp_path)).collect()}
    assert got == {1: True, 2000: True, 2001: True, 9000: True}


def test_long_texts_are_retrieved(spark, tmp_path):
    long = " ".join(f"w{i % 900}" for i in range(4000))
    rows = [(50, long), (51, long + " more"), (52, "other words here"), (100, "other words here"), (97, "alone")]
    spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_chars", F.length("text").cast("long")).write.parquet(str(tmp_path / "documents.parquet"))
    assert sorted(map(tuple, QUERIES["w_doc_retrieval_whole"](spark, str(tmp_path)).select("qid", "near").collect())) == [(50, 2), (100, 2)]


def test_benchmark_overlap_of_whole_items(spark):
    w = [f"w{i}" for i in range(40)]
    items = spark.createDataFrame([(1, " ".join(w)), (2, "short item here"), (3, ""), (4, None)], "item_id long, text string")
    edited = ["W0", *w[1:]]
    texts = ["x " + " ".join(w[10:]), " ".join(edited), " ".join(w[:12]) + " y z", "a short  item\nhere b", "short item", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert sorted(map(tuple, benchmark_overlap(items, docs).collect())) == [(1, 2), (2, 1)]


def test_published_arithmetic():
    m = cost.size_model(cost.Scale())
    assert m["raw_vectors"] == pytest.approx(3.072e12) and m["file_centroids"] == pytest.approx(30.8e6, rel=0.01)
    assert m["vamana_links"] == pytest.approx(256e9) and m["shard_vectors"] == pytest.approx(768e9) and m["pq_codes"] == 48e9 and m["shard_codes"] == 12e9
    assert m["pq_codebook"] < 1e6
    plans = cost.project_query(cost.Scale())
    assert [p["files"] for p in plans] == [10_000, 400, 50]
    assert plans[0]["warm_s"] > plans[1]["warm_s"] > plans[2]["warm_s"]
    assert cost.choose_tier(30_800_032) == "driver" and cost.choose_tier(16e9) == "executors"


def test_scan_reads_only_what_it_needs(spark, sf):
    plan = spark.read.parquet(f"{sf}/embeddings.parquet").filter("vec_id < 5").select("embedding")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(vec_id), LessThan(vec_id,5)]" in plan and "label" not in plan.split("ReadSchema")[1]


def test_row_group_masks_and_fetch(spark, tmp_path):
    """Masks of places in files of several row groups; places beyond the end and removed files are in none."""
    rows = spark.range(100).select(F.col("id").alias("vec_id"), F.array(*[(F.col("id") + i).cast("float") for i in range(4)]).alias("v"))
    table = Table.create(spark, str(tmp_path / "t"), rows, "vec_id", 4, file_no=(F.col("vec_id") / 25).cast("int"), rows_per_group=10)
    m, snap = IndexManager(table), table.log.current()
    index = m.create("ix", "v", pq_m=4, pq_nbits=2, R=4, L=8)
    places = [(0, 3), (0, 9), (0, 10), (1, 24), (3, 99), (7, 0)]
    cand = spark.createDataFrame(places, "file_no int, row_offset long")
    got = {(r["file_no"], r["row_group"]): r["rows"] for r in m.row_group_masks(snap, cand).collect()}
    assert got == {(0, 0): [3, 9], (0, 1): [0], (1, 2): [4]}
    fetched = sorted((r["vec_id"], r["file_no"], r["row_offset"], r["v"][0]) for r in m.fetch(index, snap, cand).collect())
    assert fetched == [(3, 0, 3, 3.0), (9, 0, 9, 9.0), (10, 0, 10, 10.0), (49, 1, 24, 49.0)]
    assert m.row_group_masks(snap, cand.limit(0)).count() == 0


def test_centroid_batch_sees_files_the_index_lacks(spark, tmp_path):
    rows = spark.range(100).select(F.col("id").alias("vec_id"), F.array(*[(F.col("id") + i).cast("float") for i in range(4)]).alias("v"))
    table = Table.create(spark, str(tmp_path / "t"), rows.filter("vec_id < 75"), "vec_id", 3, file_no=(F.col("vec_id") / 25).cast("int"))
    m = IndexManager(table)
    m.create("ix", "v", pq_m=4, pq_nbits=2, R=4, L=8)
    table.append(rows.filter("vec_id >= 75"))
    qs = rows.filter("vec_id in (5, 90)").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    got = {r["qid"]: r["vec_id"] for r in m.search_centroid_batch("ix", qs, 1, 1).collect()}
    assert got == {5: 5, 90: 90}
