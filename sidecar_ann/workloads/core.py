"""Queries for the methods: distances, containers, snapshots, centroids, build, graph, quantizer, probe, refresh, SQL."""

from __future__ import annotations

import threading

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..errors import CommitConflict
from ..functions import distance as D
from ..functions import graph as G
from ..functions import quantize as Q
from ..operators import baselines as X
from ..operators import measures as A
from ..operators.centroids import CentroidProbe, file_centroids, file_radii
from ..operators.exact import exact_batch_topk, exact_range, exact_topk, top_per_query
from ..operators.index import HITS, IndexManager, cached_shard, plan_shards, sample_rows
from ..plans import cost
from ..plans.session import AnnSession
from ..sources import blobs, coding, store
from ..sources.catalog import Change, Table
from ..sources.container import CENTROIDS, GRAPH, ROUTING, Blob, read_blob, read_footer, write_container
from .registry import EXHAUSTIVE, SMALL, U, UQ, clustered, matrix, no_violations, out_topk, per_file, queries_of, query, read, shared, table_of, topk_sql, uniform, violations, warehouse

# ---------------------------------------------------------------- distances
_PAIRS = f"WITH {U}, n AS (SELECT max(vec_id) + 1 AS n FROM u), p AS (SELECT a.vec_id, a.v AS x, b.v AS y FROM u a JOIN u b ON b.vec_id = (a.vec_id + 1) % (SELECT n FROM n))"


def _pairs(spark, sf):
    e = uniform(spark, sf)
    n = e.agg(F.max("vec_id")).first()[0] + 1
    return e.select("vec_id", F.col("v").alias("x")).join(e.select(F.pmod(F.col("vec_id") - 1, F.lit(n)).alias("vec_id"), F.col("v").alias("y")), "vec_id")


for _name, _sql in {"l2": "list_distance(x, y)", "l2sq": "list_distance(x, y) ** 2", "cosine": "list_cosine_distance(x, y)", "ip": "-list_inner_product(x, y)"}.items():

    @query(f"dist_{_name}", f"{_PAIRS} SELECT vec_id, round({_sql}, 6) AS d FROM p")
    def _distance(spark, sf, metric=_name):
        return _pairs(spark, sf).select("vec_id", F.round(D.metric(metric)(F.col("x"), F.col("y")), 6).alias("d"))


@query("vec_norm", f"WITH {U} SELECT vec_id, round(sqrt(list_inner_product(v, v)), 6) AS norm FROM u")
def vec_norm(spark, sf):
    return uniform(spark, sf).select("vec_id", F.round(D.l2_norm(F.col("v")), 6).alias("norm"))


@query("vec_normalize", f"WITH {U} SELECT vec_id, round(v[1] / sqrt(list_inner_product(v, v)), 6) AS first, round(v[64] / sqrt(list_inner_product(v, v)), 6) AS last FROM u")
def vec_normalize(spark, sf):
    n = D.normalize(F.col("v"))
    return uniform(spark, sf).select("vec_id", n.alias("n")).select("vec_id", F.round(F.element_at("n", 1), 6).alias("first"), F.round(F.element_at("n", 64), 6).alias("last"))


@query("vec_validate", "SELECT vec_id, len(embedding) = 64 AND label < 5 AS valid FROM embeddings")
def vec_validate(spark, sf):
    bad = F.when(F.col("label") < 5, F.col("v")).otherwise(F.concat(F.slice("v", 1, 63), F.array(F.lit(float("nan")).cast("float"))))
    return uniform(spark, sf).select("vec_id", D.is_valid_vector(bad, 64).alias("valid"))


@query("knn_block", topk_sql())
def knn_block(spark, sf):
    e = uniform(spark, sf)
    return out_topk(exact_batch_topk(e, queries_of(e), 10))


QUERIES_SMALL = "vec_id % 25 = 0"


@query("exact_batch_topk", topk_sql(5))
def exact_batch(spark, sf):
    e = uniform(spark, sf)
    return out_topk(exact_batch_topk(e, queries_of(e), 5))


_ONE = f"WITH {U}, one AS (SELECT v AS qv FROM u WHERE vec_id = 7), d AS (SELECT vec_id, label, list_distance(v, qv) AS distance FROM u, one)"


def _seven(spark, sf):
    return [float(x) for x in uniform(spark, sf).filter("vec_id = 7").first()["v"]]


@query("exact_topk", f"{_ONE} SELECT vec_id, round(distance, 6) AS distance FROM d ORDER BY d.distance, vec_id LIMIT 10")
def exact_top(spark, sf):
    return exact_topk(uniform(spark, sf), _seven(spark, sf), 10).select("vec_id", F.round("distance", 6).alias("distance"))


@query("exact_range", f"{_ONE} SELECT vec_id, round(distance, 6) AS distance FROM d WHERE distance <= 1.3")
def exact_rng(spark, sf):
    return exact_range(uniform(spark, sf), _seven(spark, sf), 1.3).select("vec_id", F.round("distance", 6).alias("distance"))


@query("sql_distance_fn", f"{_ONE} SELECT label, count(*) AS n FROM d WHERE distance < 1.35 GROUP BY label")
def sql_distance_fn(spark, sf):
    D.register_functions(spark)
    uniform(spark, sf).createOrReplaceTempView("sidecar_fn_rows")
    arr = "array(" + ",".join(f"{x!r}D" for x in _seven(spark, sf)) + ")"
    return spark.sql(f"SELECT label, count(*) AS n FROM (SELECT label, l2_distance(v, {arr}) AS d FROM sidecar_fn_rows) WHERE d < 1.35 GROUP BY label")


# ---------------------------------------------------------------- container
@query("container_roundtrip", no_violations("blob bytes", "footer properties", "absent names are refused"))
def container_roundtrip(spark, sf):
    path = f"{warehouse(spark)}/c.side"
    made = [Blob(ROUTING, bytes(range(256)) * 9, [1], 3, {"a": "b"}, c) for c in ("none", "zstd")] + [Blob(CENTROIDS, b"", [1], 3)]
    write_container(path, made, {"p": "q"})
    foot = read_footer(path)
    refused = 0
    try:
        write_container(path, made)
        refused = 1
    except FileExistsError:
        pass
    return violations(spark, **{"blob bytes": sum(read_blob(path, m) != b.data for m, b in zip(foot.blobs, made)), "footer properties": foot.properties != {"p": "q"}, "absent names are refused": refused})


@query("container_footer", no_violations("known types", "one blob a shard at most", "footer is small"))
def container_footer(spark, sf):
    table, m = shared(spark, sf)
    index = m.open("ix")
    foot = read_footer(f"{index.root}/{index.path}")
    return violations(spark, **{"known types": len(foot.blobs) - len(foot.known()), "one blob a shard at most": sum(len(read_footer(f"{index.root}/{s['path']}").blobs) != 1 for s in index.shards), "footer is small": foot.footer_bytes > 64_000})


@query("blob_range_read", no_violations("ranges"))
def blob_range_read(spark, sf):
    path = f"{warehouse(spark)}/c.side"
    parts = [bytes([k]) * (100 + k) for k in range(5)]
    write_container(path, [Blob(GRAPH, p) for p in parts])
    return violations(spark, ranges=sum(store.get(path, b.offset, b.length) != p for b, p in zip(read_footer(path).blobs, parts)))


@query("unknown_blob_ignored", no_violations("known"))
def unknown_blob_ignored(spark, sf):
    path = f"{warehouse(spark)}/c.side"
    write_container(path, [Blob("someone-elses-v9", b"x"), Blob(ROUTING, b"y")])
    return violations(spark, known=[b.type for b in read_footer(path).known()] != [ROUTING])


@query("blob_codec", no_violations("zstd is smaller", "zstd reads the same"))
def blob_codec(spark, sf):
    w = warehouse(spark)
    write_container(f"{w}/a", [Blob(GRAPH, b"abcd" * 5000)])
    write_container(f"{w}/b", [Blob(GRAPH, b"abcd" * 5000, codec="zstd")])
    a, b = read_footer(f"{w}/a").blobs[0], read_footer(f"{w}/b").blobs[0]
    return violations(spark, **{"zstd is smaller": b.length >= a.length, "zstd reads the same": read_blob(f"{w}/a", a) != read_blob(f"{w}/b", b)})


@query("varint_roundtrip", no_violations("varint", "delta"))
def varint_roundtrip(spark, sf):
    x = np.random.default_rng(1).integers(0, 1 << 62, 5000) >> np.random.default_rng(2).integers(0, 62, 5000)
    return violations(spark, varint=int((coding.varint_decode(coding.varint_encode(x)) != x).sum()), delta=int((coding.delta_decode(coding.delta_encode(x - 9)) != x - 9).sum()))


@query("shard_roundtrip", no_violations("arrays", "bytes"))
def shard_roundtrip(spark, sf):
    _, m = shared(spark, sf)
    index = m.open("ix")
    arrays = bytes_ = 0
    for s in index.shards:
        a = cached_shard(f"{index.root}/{s['path']}", s["blob"])
        b = blobs.decode_shard(blobs.encode_shard(a))
        arrays += sum((x != y).any() for x, y in zip(a.neighbours, b.neighbours)) + (a.ids != b.ids).any() + (a.codes != b.codes).any()
        bytes_ += blobs.encode_shard(a) != blobs.encode_shard(b)
    return violations(spark, arrays=arrays, bytes=bytes_)


@query("routing_roundtrip", no_violations("head", "codebook"))
def routing_roundtrip(spark, sf):
    book = np.arange(24, dtype=np.float32).reshape(3, 8)
    head, back = blobs.decode_routing(blobs.encode_routing({"shards": [1], "covered": {"a": 2}}, book))
    return violations(spark, head=head != {"shards": [1], "covered": {"a": 2}}, codebook=(back != book).any())


@query("centroid_blob_roundtrip", no_violations("paths", "centroids", "radius covers"))
def centroid_blob_roundtrip(spark, sf):
    c, r = np.random.default_rng(0).normal(size=(5, 64)), np.linspace(0.5, 1.5, 5)
    d = blobs.decode_centroids(blobs.encode_centroids(list("abcde"), np.arange(5), c, r, "l2"))
    return violations(spark, paths=d["paths"] != list("abcde"), centroids=(d["centroid"] != c.astype(np.float32)).any(), **{"radius covers": (d["radius"] < r).any()})


@query("centroid_blob_size", "SELECT CAST(f AS BIGINT) AS files, CAST(d AS BIGINT) AS dim, CAST(f * (4 * d + 8) + 32 AS BIGINT) AS bytes FROM (VALUES (20, 64), (10000, 768), (200000, 768)) x(f, d)")
def centroid_blob_size(spark, sf):
    return spark.createDataFrame([(f, d, blobs.centroid_blob_bytes(f, d)) for f, d in ((20, 64), (10000, 768), (200000, 768))], "files long, dim long, bytes long")


@query("locator_bijection", no_violations("ids", "locators", "files"))
def locator_bijection(spark, sf):
    table, m = shared(spark, sf)
    index = m.open("ix")
    got = [(int(i), int(f), int(o)) for s in index.shards for i, f, o in zip(*(getattr(cached_shard(f"{index.root}/{s['path']}", s["blob"]), c) for c in ("ids", "files", "offsets")))]
    true = {(r["vec_id"], r["file_no"], r["row_offset"]) for r in m._rows(table.log.at(1), "v", [f.path for f in table.log.files(table.log.at(1))]).select("vec_id", "file_no", "row_offset").collect()}
    return violations(spark, ids=len(got) - len({g[0] for g in got}), locators=len(got) - len({g[1:] for g in got}), files=len(set(got) ^ true))


# ---------------------------------------------------------------- snapshots
def _history(spark, sf):
    """Version 1 holds files below 18 of 20, 2 binds an index, 3 appends the rest, 4 drops files 0 and 1."""
    each = per_file(spark, sf)
    table = table_of(spark, sf, f"vec_id < {18 * each}", 18, each)
    m = IndexManager(table)
    m.create("ix", "v", **SMALL)
    rest = uniform(spark, sf).filter(f"vec_id >= {18 * each}")
    table.append(rest, 2, file_no=(F.col("vec_id") / each).cast("int"))
    return table, m, each


_EACH = "e AS (SELECT CAST(ceil(count(*) / 20.0) AS BIGINT) AS each FROM embeddings)"


@query("table_scan", "SELECT count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS ids, CAST(sum(label) AS BIGINT) AS labels FROM embeddings")
def table_scan(spark, sf):
    table, _ = shared(spark, sf)
    return table.df().agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"), F.sum("label").cast("long").alias("labels"))


@query("after_append", f"WITH {_EACH} SELECT count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS ids FROM embeddings")
def after_append(spark, sf):
    table, _, _ = _history(spark, sf)
    return table.df().agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


@query("after_delete", f"WITH {_EACH} SELECT count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS ids FROM embeddings, e WHERE vec_id >= 2 * each")
def after_delete(spark, sf):
    table, _, _ = _history(spark, sf)
    table.remove_files([0, 1])
    return table.df().agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


@query("after_overwrite", "SELECT count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS ids FROM embeddings WHERE label = 3")
def after_overwrite(spark, sf):
    table = table_of(spark, sf)
    table.overwrite(uniform(spark, sf).filter("label = 3"), 2)
    return table.df().agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


@query("commit_race", no_violations("lost rows", "versions"))
def commit_race(spark, sf):
    table = table_of(spark, sf, "vec_id < 100")
    base = table.log.current()
    added = [table._write(uniform(spark, sf).filter(f"vec_id % 5 = {k} AND vec_id BETWEEN 100 AND 199"), "vec_id", 1, None, None, 100 + k) for k in range(2)]
    threads = [threading.Thread(target=table.log.commit, args=(base, Change("append", add=a))) for a in added]
    for t in threads:
        t.start()
    for t in threads:
        t.join()
    return violations(spark, **{"lost rows": 140 - table.df().count(), "versions": table.log.versions() != [1, 2, 3]})


@query("index_race", no_violations("a second binding of one name", "the first stands"))
def index_race(spark, sf):
    table = table_of(spark, sf, "vec_id < 100")
    base = table.log.current()
    table.log.commit(base, Change("replace", bind={"ix": {"path": "index/a", "base": 1}}))
    lost = 0
    try:
        table.log.commit(base, Change("replace", bind={"ix": {"path": "index/b", "base": 1}}))
        lost = 1
    except CommitConflict:
        pass
    return violations(spark, **{"a second binding of one name": lost, "the first stands": table.log.current().indexes["ix"]["path"] != "index/a"})


@query("bind_is_metadata_only", "SELECT 'EXISTING' AS status, CAST(20 AS BIGINT) AS n")
def bind_is_metadata_only(spark, sf):
    table, _ = shared(spark, sf)
    return table.diff(1, 2).groupBy("status").agg(F.count("*").alias("n"))


@query("snapshot_diff", "SELECT CAST(range AS INTEGER) AS file_no, CASE WHEN range < 2 THEN 'DELETED' WHEN range >= 18 THEN 'ADDED' ELSE 'EXISTING' END AS status FROM range(20)")
def snapshot_diff(spark, sf):
    table, _, _ = _history(spark, sf)
    table.remove_files([0, 1])
    return table.diff(2, 4).select("file_no", "status")


@query("time_travel_scan", f"WITH {_EACH} SELECT version, count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS ids FROM embeddings, e, (VALUES (1), (3), (4)) x(version) WHERE (version >= 3 OR vec_id < 18 * each) AND (version < 4 OR vec_id >= 2 * each) GROUP BY version")
def time_travel_scan(spark, sf):
    table, _, _ = _history(spark, sf)
    table.remove_files([0, 1])
    parts = [table.df(v).agg(F.lit(v).alias("version"), F.count("*").alias("n"), F.sum("vec_id").alias("ids")) for v in (1, 3, 4)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("time_travel_knn", f"WITH {UQ}, {_EACH}, d AS (SELECT version, qid, vec_id, list_distance(v, qv) AS distance FROM q, u, e, (VALUES (2), (3)) x(version) WHERE version = 3 OR vec_id < 18 * each), r AS (SELECT *, row_number() OVER (PARTITION BY version, qid ORDER BY distance, vec_id) AS rank FROM d) SELECT version, qid, vec_id, round(distance, 6) AS distance FROM r WHERE rank <= 5")
def time_travel_knn(spark, sf):
    table, m, _ = _history(spark, sf)
    qs = queries_of(uniform(spark, sf))
    parts = [m.search("ix", qs, 5, version=v, **EXHAUSTIVE).select(F.lit(v).alias("version"), "qid", "vec_id", F.round("distance", 6).alias("distance")) for v in (2, 3)]
    return parts[0].unionByName(parts[1])


@query("orphans", "SELECT CAST(5 AS BIGINT) AS orphans, CAST(0 AS BIGINT) AS live_among_them")
def orphans(spark, sf):
    table, m, _ = _history(spark, sf)
    old = table.log.snapshot(2).indexes["ix"]
    m.refresh("ix", rebuild_all=True)
    named = table.log.referenced()
    table.log.expire(1)
    found = set(table.log.orphans())
    now = table.log.referenced()
    expected = ({old["path"], *old["objects"]} & named) - now
    return spark.createDataFrame([(len(found & expected), len(found & now))], "orphans long, live_among_them long")


@query("foreign_reader", "SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def foreign_reader(spark, sf):
    table, _ = shared(spark, sf)
    return spark.read.parquet(*[f.path for f in table.log.files(table.log.current())]).groupBy("label").agg(F.count("*").alias("n"))


@query("meta_history", "SELECT * FROM (VALUES (1, 'create'), (2, 'replace'), (3, 'append')) x(version, operation)")
def meta_history(spark, sf):
    return _history(spark, sf)[0].metadata("history").select(F.col("version").cast("int").alias("version"), "operation")


@query("meta_files", f"WITH {_EACH} SELECT CAST(vec_id // each AS INTEGER) AS file_no, count(*) AS records, min(vec_id) AS low, max(vec_id) AS high FROM embeddings, e GROUP BY 1")
def meta_files(spark, sf):
    return shared(spark, sf)[0].metadata("files").filter("version = 1").select("file_no", "records", "low", "high")


@query("meta_indexes", "SELECT 2 AS version, 'ix' AS name, 1 AS base UNION ALL SELECT 3, 'ix', 1")
def meta_indexes(spark, sf):
    return _history(spark, sf)[0].metadata("indexes").select(F.col("version").cast("int").alias("version"), "name", F.col("base").cast("int").alias("base"))


@query("zone_prune", f"WITH {_EACH}, f AS (SELECT vec_id // each AS f, min(vec_id) AS lo, max(vec_id) AS hi FROM embeddings, e GROUP BY 1) SELECT CAST(f AS INTEGER) AS file_no FROM f WHERE hi >= 60 AND lo <= 140")
def zone_prune(spark, sf):
    return spark.createDataFrame([(f.file_no,) for f in shared(spark, sf)[0].prune_files(60, 140)], "file_no int")


# ---------------------------------------------------------------- file centroids
_FILES = f"{U}, {_EACH}, f AS (SELECT vec_id // each AS file_no, vec_id, v FROM u, e), pos AS (SELECT file_no, i, avg(v[i]) AS m FROM f, range(1, 65) t(i) GROUP BY file_no, i), c AS (SELECT file_no, list(m ORDER BY i) AS centroid FROM pos GROUP BY file_no), rad AS (SELECT file_no, max(list_distance(v, centroid)) AS radius, count(*) AS n FROM f JOIN c USING (file_no) GROUP BY file_no)"


def _filed(spark, sf):
    each = per_file(spark, sf)
    return uniform(spark, sf).select("vec_id", "v", (F.col("vec_id") / each).cast("int").alias("file_no"))


@query("file_centroids", f"WITH {_FILES} SELECT CAST(file_no AS INTEGER) AS file_no, round(centroid[1], 6) AS first, round(centroid[64], 6) AS last, round(list_sum(centroid), 6) AS total FROM c")
def q_file_centroids(spark, sf):
    c = file_centroids(_filed(spark, sf), 64)
    return c.select("file_no", F.round(F.element_at("centroid", 1), 6).alias("first"), F.round(F.element_at("centroid", 64), 6).alias("last"), F.round(F.aggregate("centroid", F.lit(0.0), lambda s, x: s + x), 6).alias("total"))


@query("file_radius", f"WITH {_FILES} SELECT CAST(file_no AS INTEGER) AS file_no, n, round(radius, 6) AS radius FROM rad")
def q_file_radius(spark, sf):
    rows = _filed(spark, sf)
    return file_radii(rows, file_centroids(rows, 64), 20, 64).select("file_no", "n", F.round("radius", 6).alias("radius"))


def _probe(spark, sf):
    rows = _filed(spark, sf)
    got = sorted(file_radii(rows, file_centroids(rows, 64), 20, 64).collect(), key=lambda r: r["file_no"])
    return CentroidProbe(np.array([r["file_no"] for r in got]), np.array([r["centroid"] for r in got]), np.array([r["radius"] for r in got]))


@query("threshold_pruned_files", f"WITH {_FILES}, q AS (SELECT v AS qv FROM u WHERE vec_id = 7) SELECT CAST(file_no AS INTEGER) AS file_no FROM c JOIN rad USING (file_no), q WHERE greatest(list_distance(centroid, qv) - radius, 0) <= 0.05")
def threshold_pruned_files(spark, sf):
    return spark.createDataFrame([(int(f),) for f in _probe(spark, sf).within(_seven(spark, sf), 0.05)], "file_no int")


@query("threshold_search", f"{_ONE} SELECT vec_id, round(distance, 6) AS distance FROM d WHERE distance <= 1.25")
def threshold_search(spark, sf):
    return shared(spark, sf)[1].search_range("ix", _seven(spark, sf), 1.25).select("vec_id", F.round("distance", 6).alias("distance"))


_CENTROID_TOP = f"WITH {_FILES}, q AS (SELECT v AS qv FROM u WHERE vec_id = 7), near AS (SELECT file_no FROM c, q ORDER BY list_distance(centroid, qv), file_no LIMIT 5), d AS (SELECT vec_id, list_distance(v, qv) AS distance FROM f JOIN near USING (file_no), q)"


@query("centroid_topk", f"{_CENTROID_TOP} SELECT vec_id, round(distance, 6) AS distance FROM d ORDER BY d.distance, vec_id LIMIT 10")
def centroid_topk(spark, sf):
    return shared(spark, sf)[1].search_centroid("ix", _seven(spark, sf), 10, 5).select("vec_id", F.round("distance", 6).alias("distance"))


@query("recall_centroid", f"{_CENTROID_TOP}, got AS (SELECT vec_id FROM d ORDER BY distance, vec_id LIMIT 10), best AS (SELECT vec_id FROM u, q ORDER BY list_distance(v, qv), vec_id LIMIT 10) SELECT round(count(*) / 10.0, 6)::DOUBLE AS recall FROM got JOIN best USING (vec_id)")
def recall_centroid(spark, sf):
    q = _seven(spark, sf)
    got = shared(spark, sf)[1].search_centroid("ix", q, 10, 5).withColumn("qid", F.lit(7))
    return A.recall_at_k(got, exact_topk(uniform(spark, sf), q, 10).withColumn("qid", F.lit(7)), 10).select(F.round("recall", 6).alias("recall"))


@query("files_scanned_centroid", "SELECT CAST(5 AS BIGINT) AS files, CAST(20 AS BIGINT) AS of_files")
def files_scanned_centroid(spark, sf):
    table, m = shared(spark, sf)
    m.search_centroid("ix", _seven(spark, sf), 10, 5)
    return spark.createDataFrame([(m.last_metrics["files"], len(table.log.files(table.log.current())))], "files long, of_files long")


@query("centroid_exact_topk", f"{_ONE} SELECT vec_id, round(distance, 6) AS distance FROM d ORDER BY d.distance, vec_id LIMIT 10")
def centroid_exact_topk(spark, sf):
    return shared(spark, sf)[1].search_centroid("ix", _seven(spark, sf), 10).select("vec_id", F.round("distance", 6).alias("distance"))


@query("centroid_exact_topk_stale", f"{_ONE} SELECT vec_id, round(distance, 6) AS distance FROM d ORDER BY d.distance, vec_id LIMIT 10")
def centroid_exact_topk_stale(spark, sf):
    """The index covers a part of the table only: the rest is appended after the build."""
    _, m, _ = _history(spark, sf)
    return m.search_centroid("ix", _seven(spark, sf), 10).select("vec_id", F.round("distance", 6).alias("distance"))


@query("bound_safety", no_violations("l2", "l2sq", "cosine", "ip"))
def bound_safety(spark, sf):
    ids, x = matrix(uniform(spark, sf))
    out = {}
    c = np.stack([x[s::20].mean(0) for s in range(20)])
    r = np.array([np.sqrt(((x[s::20] - c[s]) ** 2).sum(1)).max() for s in range(20)])
    for metric in ("l2", "l2sq", "cosine", "ip"):
        p, bad = CentroidProbe(np.arange(20), c, r, metric), 0
        for q in x[::25]:
            b, d = p.bounds(q), D.exact_distances(x, q[None], metric)
            bad += sum(b[s] > d[s::20].min() + 1e-9 for s in range(20))
        out[metric] = bad
    return violations(spark, **out)


@query("centroids_after_refresh", f"WITH {_FILES} SELECT CAST(file_no AS INTEGER) AS file_no, round(radius, 2) AS radius FROM rad")
def centroids_after_refresh(spark, sf):
    _, m, _ = _history(spark, sf)
    m.refresh("ix")
    p = m.centroids("ix")
    return spark.createDataFrame([(int(f), float(r)) for f, r in zip(p.file_no, p.radius)], "file_no int, radius double").select("file_no", F.round("radius", 2).alias("radius"))


# ---------------------------------------------------------------- build
@query("sample_fraction", no_violations("repeatable", "capped", "near the fraction"))
def sample_fraction(spark, sf):
    e = uniform(spark, sf)
    a, b = (sorted(r[0] for r in sample_rows(e, 0.3, 10_000).select("vec_id").collect()) for _ in range(2))
    n = e.count()
    return violations(spark, repeatable=a != b, capped=sample_rows(e, 1.0, 7).count() != 7, **{"near the fraction": abs(len(a) / n - 0.3) > 0.1})


_CELLS = f"{U}, k AS (SELECT vec_id AS cell, v AS c FROM u WHERE vec_id < 8), a AS (SELECT u.vec_id, u.v, arg_min(cell, (list_distance(v, c) ** 2, cell)) AS cell FROM u, k GROUP BY u.vec_id, u.v)"


def _first8(spark, sf):
    return matrix(uniform(spark, sf).filter("vec_id < 8"))[1]


@query("assign_nearest", f"WITH {_CELLS} SELECT vec_id, CAST(cell AS INTEGER) AS cell FROM a")
def assign_nearest(spark, sf):
    return uniform(spark, sf).select("vec_id", X.cell_of(F.col("v"), _first8(spark, sf)).alias("cell"))


@query("kmeans_one_step", f"WITH {_CELLS} SELECT CAST(cell AS INTEGER) AS cell, count(*) AS n, round(avg(v[1]), 6) AS first, round(avg(v[64]), 6) AS last FROM a GROUP BY cell")
def kmeans_one_step(spark, sf):
    return X.lloyd_step(uniform(spark, sf), _first8(spark, sf), 64).select("cell", "n", F.round(F.element_at("centre", 1), 6).alias("first"), F.round(F.element_at("centre", 64), 6).alias("last"))


@query("kmeans_inertia_monotone", no_violations("uniform", "clustered"))
def kmeans_inertia_monotone(spark, sf):
    return violations(spark, **{n: sum(b > a + 1e-9 for a, b in zip(h, h[1:])) for n, h in (("uniform", Q.kmeans(matrix(uniform(spark, sf))[1], 10)[1]), ("clustered", Q.kmeans(matrix(clustered(spark, sf))[1], 10)[1]))})


@query("build_results", "SELECT CAST(vec_id % 4 AS INTEGER) AS shard, count(*) AS n FROM embeddings GROUP BY 1")
def build_results(spark, sf):
    return shared(spark, sf)[1].tombstones("ix").select("shard", "n")


@query("shard_balance", "SELECT CAST(count(*) AS BIGINT) AS shards, max(n) AS most, min(n) AS least, round(max(n) / avg(n), 6) AS balance FROM (SELECT vec_id % 4, count(*) AS n FROM embeddings GROUP BY 1)")
def shard_balance(spark, sf):
    return A.shard_balance(uniform(spark, sf).withColumn("shard", F.col("vec_id") % 4)).withColumn("balance", F.round("balance", 6))


@query("plan_shards", no_violations("every cell placed", "large cells split", "balanced"))
def q_plan_shards(spark, sf):
    cells = [1000, 10, 20, 30, 40, 50, 60, 70, 80, 90]
    got = plan_shards(cells, 4, 300)
    load = [sum(cells[c] / len(s) for c, s in enumerate(got) if k in s) for k in range(4)]
    return violations(spark, **{"every cell placed": sum(not s for s in got), "large cells split": len(got[0]) < 4, "balanced": max(load) > 1.5 * sum(load) / 4})


@query("partition_stats", no_violations("rows", "inertia"))
def partition_stats(spark, sf):
    _, m = shared(spark, sf)
    n = uniform(spark, sf).count()
    return violations(spark, rows=n - sum(r["n"] for r in m.last_results), inertia=sum(not r["inertia"] > 0 for r in m.last_results))


@query("assemble_modes_equal", no_violations("inline and by reference"))
def assemble_modes_equal(spark, sf):
    qs = queries_of(uniform(spark, sf), 100)
    got = [{(r["qid"], r["vec_id"]) for r in shared(spark, sf, **o)[1].search("ix", qs, 5).collect()} for o in ({}, {"mode": "inline", "compression": "zstd"})]
    return violations(spark, **{"inline and by reference": len(got[0] ^ got[1])})


@query("index_lifecycle", "SELECT * FROM (VALUES (1, 'created', 1), (2, 'refreshed', 1), (3, 'dropped', 0)) x(step, state, indexes)")
def index_lifecycle(spark, sf):
    table, m, _ = _history(spark, sf)
    out = [(1, "created", len(m.list()))]
    m.refresh("ix")
    out.append((2, "refreshed", len(m.list())))
    m.drop("ix")
    out.append((3, "dropped", len(m.list())))
    return spark.createDataFrame(out, "step int, state string, indexes int")


# ---------------------------------------------------------------- graph and quantizer
@query("shard_medoid", f"WITH {U}, s AS (SELECT vec_id % 4 AS shard, vec_id, v FROM u), m AS (SELECT shard, i, avg(v[i]) AS a FROM s, range(1, 65) t(i) GROUP BY shard, i), c AS (SELECT shard, list(a ORDER BY i) AS mean FROM m GROUP BY shard) SELECT CAST(shard AS INTEGER) AS shard, arg_min(vec_id, (list_distance(v, mean), vec_id)) AS medoid FROM s JOIN c USING (shard) GROUP BY shard")
def shard_medoid(spark, sf):
    index = shared(spark, sf)[1].open("ix")
    out = []
    for s in index.shards:
        shard = cached_shard(f"{index.root}/{s['path']}", s["blob"])
        out.append((s["shard"], int(shard.ids[shard.entries[0]])))
    return spark.createDataFrame(out, "shard int, medoid long")


def _all_edges(m):
    return m.edges("ix")


@query("graph_degree_bound", no_violations("above R", "without edges"))
def graph_degree_bound(spark, sf):
    _, m = shared(spark, sf)
    degree = m.edges("ix").groupBy("src").agg(F.count("*").alias("d"))
    n = uniform(spark, sf).count()
    return violations(spark, **{"above R": degree.filter(F.col("d") > SMALL["R"]).count(), "without edges": n - degree.count()})


@query("graph_no_self_loops", no_violations("self loops", "repeated", "across shards"))
def graph_no_self_loops(spark, sf):
    e = shared(spark, sf)[1].edges("ix")
    return violations(spark, **{"self loops": e.filter("src = dst").count(), "repeated": e.count() - e.distinct().count(), "across shards": e.filter("src % 4 <> dst % 4").count()})


@query("graph_reachable", no_violations("uniform", "clustered", "hub"))
def graph_reachable(spark, sf):
    out = {}
    for name, rows in (("uniform", uniform(spark, sf)), ("clustered", clustered(spark, sf)), ("hub", clustered(spark, sf, True))):
        x = matrix(rows.filter("vec_id % 4 = 1"))[1]
        table, entries = G.build_graph(x, G.GraphParams(R=8, L=20, n_entries=4))
        out[name] = int((~G.reachable(table, entries)).sum())
    return violations(spark, **out)


@query("prune_rule", no_violations("rule", "bound"))
def prune_rule(spark, sf):
    """Every tenth row, with all rows as candidates: tasks of points, a broadcast of the vectors."""
    _, x = matrix(uniform(spark, sf))
    held = spark.sparkContext.broadcast(x)

    def run(batches):
        x = held.value
        for b in batches:
            bad = over = 0
            for p in b.column(0).to_pylist():
                kept = G.robust_prune(x, p, np.arange(len(x)), 1.2, 12)
                over += len(kept) > 12
                d = np.sqrt(((x[kept] - x[p]) ** 2).sum(1))
                for i in range(len(kept)):
                    for j in range(i + 1, len(kept)):
                        bad += bool(1.2 * np.sqrt(((x[kept[i]] - x[kept[j]]) ** 2).sum()) <= d[j])
            yield pa.RecordBatch.from_pydict({"bad": [bad], "over": [over]})

    # 64 points a task, so that a task's work grows with the rows and not with their square
    got = spark.range(0, len(x), 10, max(1, -(-len(x) // 640))).mapInArrow(run, "bad long, over long").agg(F.sum("bad").alias("bad"), F.sum("over").alias("over")).first()
    return violations(spark, rule=got["bad"] or 0, bound=got["over"] or 0)


@query("beam_full_width_exact", topk_sql(5, "vec_id % 4 = 2"))
def beam_full_width_exact(spark, sf):
    ids, x = matrix(uniform(spark, sf).filter("vec_id % 4 = 2"))
    qid, q = matrix(uniform(spark, sf).filter("vec_id % 25 = 0"))
    table, entries = G.build_graph(x, G.GraphParams(R=8, L=20))
    got = G.beam_search(x, table, entries, q, len(x))
    rows = []
    for i, row in zip(qid, got.ids):
        d = D.exact_distances(x[row], q[qid == i], "l2")
        best = np.lexsort((ids[row], d))[:5]
        rows += [(int(i), int(ids[row[b]]), float(d[b]), k + 1) for k, b in enumerate(best)]
    return out_topk(spark.createDataFrame(rows, "qid long, vec_id long, distance double, rank int"))


@query("insert_then_find", no_violations("found", "degree", "reachable"))
def insert_then_find(spark, sf):
    _, x = matrix(uniform(spark, sf).filter("vec_id < 200"))
    p = G.GraphParams(R=10, L=24)
    table, entries = G.build_graph(x[:150], p)
    y, table, info = G.insert(x[:150], table, entries, x[150:], p)
    got = G.beam_search(y, table, info["entries"], x[150:], 24)
    return violations(spark, found=int((got.ids[:, 0] != np.arange(150, 200)).sum()), degree=int(((table >= 0).sum(1) > 10).sum()), reachable=int((~G.reachable(table, info["entries"])).sum()))


@query("hard_delete_exhaustive", topk_sql(5, "vec_id % 4 = 2 AND vec_id % 3 <> 0"))
def hard_delete_exhaustive(spark, sf):
    ids, x = matrix(uniform(spark, sf).filter("vec_id % 4 = 2"))
    qid, q = matrix(uniform(spark, sf).filter("vec_id % 25 = 0"))
    p = G.GraphParams(R=8, L=20)
    table, _ = G.build_graph(x, p)
    keep, small, entries = G.consolidate(x, table, ids % 3 == 0, p)
    x, ids = x[keep], ids[keep]
    got = G.beam_search(x, small, entries, q, len(x))
    rows = []
    for i, row in zip(qid, got.ids):
        d = D.exact_distances(x[row], q[qid == i], "l2")
        best = np.lexsort((ids[row], d))[:5]
        rows += [(int(i), int(ids[row[b]]), float(d[b]), k + 1) for k, b in enumerate(best)]
    return out_topk(spark.createDataFrame(rows, "qid long, vec_id long, distance double, rank int"))


_BOOK = f"{U}, b AS (SELECT s, vec_id AS code, v[s * 16 + 1 : s * 16 + 16] AS w FROM u, range(4) t(s) WHERE vec_id < 16), x AS (SELECT s, vec_id, v[s * 16 + 1 : s * 16 + 16] AS p FROM u, range(4) t(s)), e AS (SELECT vec_id, s, arg_min(code, (list_distance(p, w) ** 2, code)) AS code, min(list_distance(p, w) ** 2) AS err FROM x JOIN b USING (s) GROUP BY vec_id, s)"


def _book(spark, sf):
    x = matrix(uniform(spark, sf).filter("vec_id < 16"))[1]
    return x.reshape(16, 4, 16).transpose(1, 0, 2)


@query("pq_encode", f"WITH {_BOOK} SELECT vec_id, CAST(s AS INTEGER) AS s, CAST(code AS INTEGER) AS code FROM e")
def pq_encode(spark, sf):
    coded = uniform(spark, sf).select("vec_id", X.pq_codes(F.col("v"), _book(spark, sf)).alias("c"))
    return coded.select("vec_id", F.posexplode("c").alias("s", "code"))


@query("pq_mse", f"WITH {_BOOK} SELECT round(sum(err) / count(DISTINCT vec_id), 6) AS mse FROM e")
def pq_mse(spark, sf):
    return spark.createDataFrame([(round(Q.pq_mse(matrix(uniform(spark, sf))[1], _book(spark, sf)), 6),)], "mse double")


@query("pq_adc", f"WITH {_BOOK}, q AS (SELECT vec_id AS qid, s, p AS qp FROM x WHERE vec_id % 100 = 0) SELECT qid, e.vec_id, round(sum(list_distance(qp, w) ** 2), 6) AS score FROM q JOIN e USING (s) JOIN b USING (s, code) GROUP BY qid, e.vec_id")
def pq_adc(spark, sf):
    ids, x = matrix(uniform(spark, sf))
    book = _book(spark, sf)
    codes = Q.pq_encode(x, book)
    rows = [(int(i), int(j), float(s)) for i in ids[ids % 100 == 0] for j, s in zip(ids, Q.adc_scores(codes, Q.adc_table(x[ids == i][0], book)))]
    return spark.createDataFrame(rows, "qid long, vec_id long, score double").withColumn("score", F.round("score", 6))


@query("pq_train_error_monotone", no_violations("m=8", "m=16"))
def pq_train_error_monotone(spark, sf):
    x = matrix(uniform(spark, sf))[1]
    return violations(spark, **{f"m={m}": sum(b > a + 1e-9 for a, b in zip(e, e[1:])) for m in (8, 16) for e in [Q.train_pq(x, m, 4)[1]]})


# ---------------------------------------------------------------- probe
@query("probe_stage_a", no_violations("at most k * c a shard", "live ids only", "visits within n"))
def probe_stage_a(spark, sf):
    _, m = shared(spark, sf)
    index = m.open("ix")
    got = m.stage_a(index, queries_of(uniform(spark, sf)), 5, 24, 4)
    per = got.groupBy("qid", "shard").agg(F.count("*").alias("n"), F.max("visited").alias("v"))
    n = uniform(spark, sf).count()
    return violations(spark, **{"at most k * c a shard": per.filter("n > 20").count(), "live ids only": got.filter((F.col("vec_id") % 4 != F.col("shard")) | (F.col("vec_id") >= n)).count(), "visits within n": per.filter(F.col("v") > n).count()})


for _key, _k, _o in (("ann_exhaustive_topk", 10, {}), ("ann_batch_exhaustive", 3, {}), ("ann_exhaustive_centroid_shards", 5, {"sharding": "centroid"}), ("ann_exhaustive_file_shards", 5, {"sharding": "file"}), ("rerank_from_blob", 5, {"keep_vectors": True}), ("hnsw_exhaustive", 5, {"kind": "hnsw", "keep_vectors": True})):

    @query(_key, topk_sql(_k))
    def _exhaustive(spark, sf, k=_k, options=_o):
        return out_topk(shared(spark, sf, **options)[1].search("ix", queries_of(uniform(spark, sf)), k, distance="full" if options.get("keep_vectors") else "pq", **EXHAUSTIVE))


@query("ann_default", no_violations("recall under 0.9", "distances are exact", "k rows a query"))
def ann_default(spark, sf):
    e = uniform(spark, sf)
    qs = queries_of(e)
    got = shared(spark, sf, keep_vectors=True)[1].search("ix", qs, 10, L=60, distance="full").cache()
    truth = exact_batch_topk(e, qs, 10)
    recall = A.recall_at_k(got, truth, 10).first()[0]
    wrong = got.join(truth.select("qid", "vec_id", F.col("distance").alias("t")), ["qid", "vec_id"]).filter(F.abs(F.col("distance") - F.col("t")) > 1e-9).count()
    return violations(spark, **{"recall under 0.9": recall < 0.9, "distances are exact": wrong, "k rows a query": got.groupBy("qid").count().filter("count <> 10").count()})


@query("filtered_knn", topk_sql(5, "label = 3"))
def filtered_knn(spark, sf):
    return out_topk(shared(spark, sf)[1].search("ix", queries_of(uniform(spark, sf)), 5, where=F.col("label") == 3))


@query("filtered_knn_post", topk_sql(5, "label IN (1, 2, 3)"))
def filtered_knn_post(spark, sf):
    return out_topk(shared(spark, sf)[1].search("ix", queries_of(uniform(spark, sf)), 5, where=F.col("label").isin(1, 2, 3), filter_mode="post", **EXHAUSTIVE))


@query("filtered_knn_post_default", no_violations("queries with less than five rows", "rows outside the filter"))
def filtered_knn_post_default(spark, sf):
    """A filter after the search, with a narrow beam: no query ends with less rows than there are."""
    e = uniform(spark, sf)
    got = shared(spark, sf)[1].search("ix", queries_of(e), 5, where=F.col("label") == 3, filter_mode="post").cache()
    short = queries_of(e).join(got.groupBy("qid").agg(F.count("*").alias("n")), "qid", "left").filter("coalesce(n, 0) <> 5").count()
    return violations(spark, **{"queries with less than five rows": short, "rows outside the filter": got.join(e.filter("label = 3"), "vec_id", "left_anti").count()})


@query("hybrid_after_delete_default", no_violations("queries with less than ten rows", "removed rows"))
def hybrid_after_delete_default(spark, sf):
    """A stale index after files were removed: their rows neither show nor take the places of others."""
    each = per_file(spark, sf)
    table = table_of(spark, sf, per_file=each)
    m = IndexManager(table)
    m.create("ix", "v", **SMALL)
    table.remove_files(list(range(8)))
    e = uniform(spark, sf)
    got = m.search("ix", queries_of(e), 10, shard_oversample=1, rerank_oversample=1).cache()
    short = queries_of(e).join(got.groupBy("qid").agg(F.count("*").alias("n")), "qid", "left").filter("coalesce(n, 0) <> 10").count()
    return violations(spark, **{"queries with less than ten rows": short, "removed rows": got.filter(F.col("vec_id") < 8 * each).count()})


@query("concurrent_append_range", "SELECT vec_id FROM embeddings")
def concurrent_append_range(spark, sf):
    """Two writers append at the same time; a range search over everything finds every row of both."""
    e = uniform(spark, sf)
    table = table_of(spark, sf, "vec_id % 10 < 8", 20, per_file(spark, sf))
    m = IndexManager(table)
    m.create("ix", "v", **SMALL)
    threads = [threading.Thread(target=table.append, args=(e.filter(F.col("vec_id") % 10 == k),)) for k in (8, 9)]
    for t in threads:
        t.start()
    for t in threads:
        t.join()
    return m.search_range("ix", _seven(spark, sf), 100.0).select("vec_id")


@query("ann_default_pq", no_violations("recall under 0.9", "k rows a query"))
def ann_default_pq(spark, sf):
    """Options of the index and of the search as they come."""
    e = uniform(spark, sf)
    table = table_of(spark, sf, per_file=per_file(spark, sf))
    m = IndexManager(table)
    m.create("ix", "v")
    got = m.search("ix", queries_of(e), 10).cache()
    recall = A.recall_at_k(got, exact_batch_topk(e, queries_of(e), 10), 10).first()[0]
    return violations(spark, **{"recall under 0.9": recall < 0.9, "k rows a query": got.groupBy("qid").count().filter("count <> 10").count()})


@query("merge_topk", topk_sql(8, select="qid, vec_id"))
def merge_topk(spark, sf):
    e = uniform(spark, sf)
    cand = e.join(F.broadcast(queries_of(e)), F.lit(True)).select("qid", "vec_id", D.l2(F.col("v"), F.col("qv")).alias("approx"))
    return shared(spark, sf)[1].merge(cand, 4, 2).select("qid", "vec_id")


@query("exact_rerank", topk_sql(6, "vec_id % 3 = 1"))
def exact_rerank(spark, sf):
    table, m = shared(spark, sf)
    e = uniform(spark, sf)
    each = per_file(spark, sf)
    cand = e.filter("vec_id % 3 = 1").join(F.broadcast(queries_of(e)), F.lit(True)).select("qid", "vec_id", (F.col("vec_id") / each).cast("int").alias("file_no"))
    return out_topk(top_per_query(m.rerank(m.open("ix"), table.log.current(), cand, queries_of(e)), 6))


@query("row_group_masks", f"WITH {UQ}, s AS (SELECT CAST(ceil(count(*) / 20.0) AS BIGINT) AS e FROM embeddings), d AS (SELECT vec_id, row_number() OVER (PARTITION BY qid ORDER BY list_distance(v, qv), vec_id) AS rank FROM q, u), c AS (SELECT DISTINCT vec_id FROM d WHERE rank <= 10) SELECT CAST(vec_id // e AS INTEGER) AS file_no, CAST(vec_id % e // 10 AS INTEGER) AS row_group, list(vec_id % e % 10 ORDER BY vec_id)::VARCHAR AS rows FROM c, s GROUP BY 1, 2")
def row_group_masks(spark, sf):
    """Masks of the ten nearest rows of each query, over files with row groups of ten rows."""
    e = uniform(spark, sf)
    table = Table.create(spark, f"{warehouse(spark)}/t", e, "vec_id", 20, file_no=(F.col("vec_id") / per_file(spark, sf)).cast("int"), rows_per_group=10)
    m, snap = IndexManager(table), table.log.current()
    rows = m._rows(snap, "v", [f.path for f in table.log.files(snap)])
    near = exact_batch_topk(e, queries_of(e), 10).select("vec_id").distinct()
    return m.row_group_masks(snap, rows.join(near, "vec_id", "left_semi")).select("file_no", "row_group", F.col("rows").cast("string").alias("rows"))


@query("rerank_from_table", topk_sql(6))
def rerank_from_table(spark, sf):
    """Exact distances through row-group masks, over files of several row groups."""
    e = uniform(spark, sf)
    table = Table.create(spark, f"{warehouse(spark)}/t", e, "vec_id", 20, file_no=(F.col("vec_id") / per_file(spark, sf)).cast("int"), rows_per_group=10)
    m = IndexManager(table)
    index, snap = m.create("ix", "v", **SMALL), table.log.current()
    qs = queries_of(e)
    places = m._rows(snap, "v", [f.path for f in table.log.files(snap)]).drop("v")
    cand = exact_batch_topk(e, qs, 30).select("qid", "vec_id").join(places, "vec_id")
    return out_topk(top_per_query(m.rerank(index, snap, cand, qs), 6))


@query("ann_range_exhaustive", f"{_ONE} SELECT vec_id FROM d WHERE distance <= 1.2")
def ann_range_exhaustive(spark, sf):
    q = spark.createDataFrame([(7, _seven(spark, sf))], "qid long, qv array<double>")
    n = uniform(spark, sf).count()
    return shared(spark, sf)[1].search("ix", q, n, **{**EXHAUSTIVE, "shard_oversample": 1, "rerank_oversample": 1}).filter("distance <= 1.2").select("vec_id")


# ---------------------------------------------------------------- refresh
@query("refresh_changes", "SELECT status, count(*) AS n FROM (SELECT CASE WHEN range < 2 THEN 'DELETED' WHEN range >= 18 THEN 'ADDED' ELSE 'EXISTING' END AS status FROM range(20)) GROUP BY status")
def refresh_changes(spark, sf):
    table, m, _ = _history(spark, sf)
    table.remove_files([0, 1])
    return spark.createDataFrame(m.changes("ix"), "status string, file_no int").groupBy("status").agg(F.count("*").alias("n"))


@query("refresh_append_exhaustive", topk_sql(5))
def refresh_append_exhaustive(spark, sf):
    _, m, _ = _history(spark, sf)
    m.refresh("ix")
    return out_topk(m.search("ix", queries_of(uniform(spark, sf)), 5, stale="error", **EXHAUSTIVE))


@query("hybrid_exhaustive", topk_sql(5))
def hybrid_exhaustive(spark, sf):
    _, m, _ = _history(spark, sf)
    return out_topk(m.search("ix", queries_of(uniform(spark, sf)), 5, stale="hybrid", **EXHAUSTIVE))


_LIVE = "vec_id >= 2 * (SELECT CAST(ceil(count(*) / 20.0) AS BIGINT) FROM embeddings)"


def _deleted(spark, sf, drop=(0, 1)):
    table = table_of(spark, sf, per_file=per_file(spark, sf))
    m = IndexManager(table)
    m.create("ix", "v", **SMALL)
    table.remove_files(list(drop))
    m.refresh("ix")
    return table, m


@query("refresh_delete_exhaustive", topk_sql(5, _LIVE))
def refresh_delete_exhaustive(spark, sf):
    return out_topk(_deleted(spark, sf)[1].search("ix", queries_of(uniform(spark, sf)), 5, **EXHAUSTIVE))


@query("tombstone_hidden", "SELECT CAST(0 AS BIGINT) AS dead_ids, CAST(4 AS BIGINT) AS shards_with_tombstones")
def tombstone_hidden(spark, sf):
    _, m = _deleted(spark, sf)
    each = per_file(spark, sf)
    got = m.stage_a(m.open("ix"), queries_of(uniform(spark, sf)), 10, 24, 4)
    return spark.createDataFrame([(got.filter(F.col("vec_id") < 2 * each).count(), m.tombstones("ix").filter("dead > 0").count())], "dead_ids long, shards_with_tombstones long")


@query("tombstone_ratio", f"SELECT CAST(vec_id % 4 AS INTEGER) AS shard, count(*) AS n, count(*) FILTER (NOT ({_LIVE})) AS dead, round(count(*) FILTER (NOT ({_LIVE})) / count(*), 6) AS ratio FROM embeddings GROUP BY 1")
def tombstone_ratio(spark, sf):
    return _deleted(spark, sf)[1].tombstones("ix").withColumn("ratio", F.round("ratio", 6))


_SIX = "vec_id >= 6 * (SELECT CAST(ceil(count(*) / 20.0) AS BIGINT) FROM embeddings)"


@query("rebuild_trigger", f"SELECT CAST(vec_id % 4 AS INTEGER) AS shard, count(*) FILTER ({_SIX}) AS n, CAST(0 AS BIGINT) AS dead, true AS rebuilt FROM embeddings GROUP BY 1")
def rebuild_trigger(spark, sf):
    _, m = _deleted(spark, sf, range(6))
    return spark.createDataFrame([(r["shard"], r["n"], r["dead"], r["rebuilt"]) for r in m.last_results], "shard int, n long, dead long, rebuilt boolean")


@query("rebuild_exhaustive", topk_sql(5, _SIX))
def rebuild_exhaustive(spark, sf):
    return out_topk(_deleted(spark, sf, range(6))[1].search("ix", queries_of(uniform(spark, sf)), 5, **EXHAUSTIVE))


@query("refresh_vs_rebuild_equal", topk_sql(5, _LIVE))
def refresh_vs_rebuild_equal(spark, sf):
    _, m = _deleted(spark, sf)
    m.refresh("ix", rebuild_all=True)
    return out_topk(m.search("ix", queries_of(uniform(spark, sf)), 5, **EXHAUSTIVE))


@query("untouched_bytes_equal", no_violations("untouched shards", "touched shards"))
def untouched_bytes_equal(spark, sf):
    table = table_of(spark, sf, per_file=per_file(spark, sf))
    m = IndexManager(table)
    old = {s["shard"]: s["path"] for s in m.create("ix", "v", **{**SMALL, "sharding": "file"}).shards}
    table.remove_files([1])
    new = {s["shard"]: s["path"] for s in m.refresh("ix").shards}
    return violations(spark, **{"untouched shards": sum(old[s] != new[s] for s in (0, 2, 3)), "touched shards": old[1] == new[1]})


@query("cow_delete_exhaustive", topk_sql(5, "label <> 4"))
def cow_delete_exhaustive(spark, sf):
    table = table_of(spark, sf, per_file=per_file(spark, sf))
    m = IndexManager(table)
    m.create("ix", "v", **SMALL)
    table.delete_where(F.col("label") == 4)
    m.refresh("ix")
    return out_topk(m.search("ix", queries_of(uniform(spark, sf)), 5, **EXHAUSTIVE))


# ---------------------------------------------------------------- planning and statements
def _session(spark, sf):
    s = AnnSession(spark, warehouse(spark))
    table, _ = shared(spark, sf)
    s.tables["t"] = table
    return s


def _literal(spark, sf):
    return "array(" + ",".join(f"{x!r}" for x in _seven(spark, sf)) + ")"


@query("sql_threshold", f"{_ONE} SELECT vec_id, round(distance, 6) AS d FROM d WHERE distance < 1.3 AND label <> 4")
def sql_threshold(spark, sf):
    a = _literal(spark, sf)
    return _session(spark, sf).sql(f"SELECT vec_id, l2_distance(v, {a}) AS d FROM t WHERE 1.3 > l2_distance(v, {a}) AND label <> 4").withColumn("d", F.round("d", 6))


@query("sql_order_by_limit", f"{_ONE} SELECT vec_id, label, round(distance, 6) AS d FROM d WHERE label < 5 ORDER BY distance, vec_id LIMIT 6 OFFSET 2")
def sql_order_by_limit(spark, sf):
    a = _literal(spark, sf)
    return _session(spark, sf).sql(f"SELECT vec_id, label, l2_distance(v, {a}) AS d FROM t WHERE label < 5 ORDER BY d LIMIT 6 OFFSET 2").withColumn("d", F.round("d", 6))


@query("sql_order_by_limit_centroid", f"{_ONE} SELECT vec_id, label, round(distance, 6) AS d FROM d WHERE label < 5 ORDER BY distance, vec_id LIMIT 6 OFFSET 2")
def sql_order_by_limit_centroid(spark, sf):
    """Top-k through an index of file centroids only."""
    s, a = AnnSession(spark, warehouse(spark)), _literal(spark, sf)
    s.tables["t"] = table_of(spark, sf, per_file=per_file(spark, sf))
    s.sql("CREATE INDEX cx ON TABLE t USING centroid (v) OPTIONS (cells='8', pq_nbits='4')")
    return s.sql(f"SELECT vec_id, label, l2_distance(v, {a}) AS d FROM t WHERE label < 5 ORDER BY d LIMIT 6 OFFSET 2").withColumn("d", F.round("d", 6))


@query("sql_fallback_exact", f"{_ONE} SELECT label, count(*) AS n FROM d WHERE distance < 1.2 OR label = 3 GROUP BY label")
def sql_fallback_exact(spark, sf):
    s = _session(spark, sf)
    s.register_functions()
    return s.sql(f"SELECT label, count(*) AS n FROM t WHERE l2_distance(v, {_literal(spark, sf)}) < 1.2 OR label = 3 GROUP BY label")


@query("tier_choice", "SELECT kind, CAST(bytes AS BIGINT) AS bytes, CASE WHEN bytes < 104857600 THEN 'driver' ELSE 'executors' END AS tier FROM (VALUES ('file_centroids', 30800032), ('ivf_pq', 56012582912), ('hnsw_links', 128000000000), ('vamana_links', 256000000000)) x(kind, bytes)")
def tier_choice(spark, sf):
    m = cost.size_model(cost.Scale())
    return spark.createDataFrame([(k, int(m[k]), cost.choose_tier(m[k])) for k in ("file_centroids", "ivf_pq", "hnsw_links", "vamana_links")], "kind string, bytes long, tier string")


@query("size_model_table", "SELECT n, d, n * d * 4 AS raw_vectors, CAST(10000 * (4 * d + 8) + 32 AS BIGINT) AS file_centroids, n * 48 AS pq_codes, n * 256 AS vamana_links, (n // 4) * 256 AS shard_links FROM (VALUES (CAST(1000000000 AS BIGINT), CAST(768 AS BIGINT)), (CAST(1000000 AS BIGINT), CAST(64 AS BIGINT))) x(n, d)")
def size_model_table(spark, sf):
    out = []
    for n, d in ((10**9, 768), (10**6, 64)):
        m = cost.size_model(cost.Scale(rows=n, dim=d))
        out.append((n, d, *(int(m[k]) for k in ("raw_vectors", "file_centroids", "pq_codes", "vamana_links", "shard_links"))))
    return spark.createDataFrame(out, "n long, d long, raw_vectors long, file_centroids long, pq_codes long, vamana_links long, shard_links long")


@query("projection_table", "SELECT * FROM (VALUES ('no_index', CAST(10000 AS BIGINT)), ('file_centroids', 400), ('sharded_graph', 50)) x(plan, files)")
def projection_table(spark, sf):
    return spark.createDataFrame([(r["plan"], r["files"]) for r in cost.project_query(cost.Scale())], "plan string, files long")


@query("strategy_choice", no_violations("small tables", "large tables", "selective filters", "full recall"))
def strategy_choice(spark, sf):
    c = cost.choose_strategy
    return violations(spark, **{"small tables": c(2000, 10) != "exact", "large tables": c(10**9, 100) != "graph", "selective filters": c(10**9, 10, 0.001) != "exact", "full recall": c(10**9, 10, 1.0, 1.0) != "exact"})


@query("ddl_create_drop", "SELECT * FROM (VALUES (1, 'created'), (2, 'exists'), (3, 'dropped'), (4, 'absent')) x(step, state)")
def ddl_create_drop(spark, sf):
    s = AnnSession(spark, warehouse(spark))
    s.tables["t"] = table_of(spark, sf, "vec_id < 100", 4)
    said = [s.sql(x).first()["state"] for x in ("CREATE INDEX a ON TABLE t USING vamana (v) OPTIONS (R='6', L='12', pq_nbits='3', num_shards='2')", "CREATE INDEX IF NOT EXISTS a ON TABLE t USING vamana (v)", "DROP INDEX a ON TABLE t", "DROP INDEX IF EXISTS a ON TABLE t")]
    return spark.createDataFrame([(i + 1, x) for i, x in enumerate(said)], "step int, state string")


@query("ddl_refresh", "SELECT * FROM (VALUES (1, 'refreshed', 120), (2, 'rebuilt', 120)) x(step, state, n)")
def ddl_refresh(spark, sf):
    s = AnnSession(spark, warehouse(spark))
    s.tables["t"] = table_of(spark, sf, "vec_id < 100", 4)
    s.sql("CREATE INDEX a ON TABLE t USING graph (v) OPTIONS (R='6', L='12', pq_nbits='3', num_shards='2')").first()
    s.tables["t"].append(uniform(spark, sf).filter("vec_id BETWEEN 100 AND 119"))
    out = []
    for i, x in enumerate(("REFRESH INDEX a ON t", "REBUILD INDEX a ON t")):
        state = s.sql(x).first()["state"]
        out.append((i + 1, state, s.indexes("t").describe("a")["rows"]))
    return spark.createDataFrame(out, "step int, state string, n int")


# ---------------------------------------------------------------- baselines
@query("ivf_flat", f"WITH {_CELLS}, q AS (SELECT vec_id AS qid, v AS qv FROM u WHERE vec_id % 25 = 0), pr AS (SELECT * FROM (SELECT qid, qv, cell, row_number() OVER (PARTITION BY qid ORDER BY list_distance(qv, c) ** 2, cell) AS r FROM q, k) WHERE r <= 3), d AS (SELECT qid, vec_id, list_distance(v, qv) AS distance FROM a JOIN pr USING (cell)), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY distance, vec_id) AS rank FROM d) SELECT qid, vec_id, round(distance, 6) AS distance, CAST(rank AS INTEGER) AS rank FROM r WHERE rank <= 5")
def ivf_flat(spark, sf):
    e = uniform(spark, sf)
    return out_topk(X.ivf_flat(e, queries_of(e), _first8(spark, sf), 5, 3))


@query("ivfpq_full_probe_reranked", topk_sql(5))
def ivfpq_full(spark, sf):
    e = uniform(spark, sf)
    return out_topk(X.ivfpq_search(e, queries_of(e), _first8(spark, sf), _book(spark, sf), 5, 8, 1 << 16))


@query("lsh_candidates")
def lsh(spark, sf):
    e = uniform(spark, sf)
    return X.lsh_candidates(e, queries_of(e, 50))


@query("recall_exact_is_one", "SELECT 1.0::DOUBLE AS recall, 1.0::DOUBLE AS ratio")
def recall_exact(spark, sf):
    e = uniform(spark, sf)
    t = exact_batch_topk(e, queries_of(e), 10)
    return A.recall_at_k(t, t, 10).join(A.distance_ratio(t, t), F.lit(True))


@query("global_vs_sharded_recall")
def global_vs_sharded(spark, sf):
    e = uniform(spark, sf)
    qs, truth = queries_of(e), None
    truth = exact_batch_topk(e, qs, 10)
    out = None
    for n in (1, 4):
        r = A.recall_at_k(shared(spark, sf, num_shards=n, keep_vectors=True)[1].search("ix", qs, 10, distance="full"), truth, 10).select(F.lit(n).alias("shards"), "recall")
        out = r if out is None else out.unionByName(r)
    return out


# ---------------------------------------------------------------- workloads
@query("w_truth", topk_sql(100, select="qid, vec_id, round(distance, 6) AS distance"))
def w_truth(spark, sf):
    e = uniform(spark, sf)
    return exact_batch_topk(e, queries_of(e), 100).select("qid", "vec_id", F.round("distance", 6).alias("distance"))


def _table2(spark, rows):
    """Recall, files and bytes a query at K = 10 and 100: all files, nearest files, sharded graph as it comes. Every fifth
    row, perturbed, is a query."""
    t = Table.create(spark, f"{warehouse(spark)}/t", rows.withColumn("a", F.col("vec_id") % 32), "vec_id", 20, cluster_by=["a", "vec_id"])
    m = IndexManager(t)
    index = m.create("ix", "v")
    qs = m._kept(queries_of(rows, 5).withColumn("qv", F.zip_with("qv", F.reverse("qv"), lambda x, y: x.cast("double") + 0.1 * y.cast("double"))))
    size = {f.file_no: f.bytes for f in t.log.files(t.log.current())}
    sizes = spark.createDataFrame(list(size.items()), "file_no int, bytes long")
    n, out = qs.count(), []
    # the first ten of the hundred nearest are the ten nearest
    truths = m._kept(exact_batch_topk(rows, qs, 100))
    probed = m._kept(m.search_centroid_batch("ix", qs, 100, 4))
    read_ = m.probed_files("ix", qs, 4).join(sizes, "file_no").agg(F.count("*"), F.sum("bytes")).first()
    for k in (10, 100):
        truth = truths.filter(F.col("rank") <= k)
        out.append((k, "no_index", 1.0, float(len(size)), float(sum(size.values()))))
        recall = A.recall_at_k(probed.filter(F.col("rank") <= k), truth, k).first()[0]
        out.append((k, "file_centroids", recall, read_[0] / n, read_[1] / n))
        recall = A.recall_at_k(m.search("ix", qs, k), truth, k).first()[0]
        cand = m.last_candidates
        files = cand.select("qid", "file_no").distinct().count()
        # codes and links of the shards, whole, and the vectors of the candidates
        out.append((k, "sharded_graph", recall, files / n, sum(s["bytes"] for s in index.shards) + cand.count() * 4.0 * index.dim / n))
    return spark.createDataFrame(out, "k int, plan string, recall double, files double, bytes double")


@query("w_table2_uniform")
def w_table2_uniform(spark, sf):
    return _table2(spark, uniform(spark, sf))


@query("w_table2_clustered")
def w_table2_clustered(spark, sf):
    return _table2(spark, clustered(spark, sf, True))


@query("centroid_topk_batch", f"WITH {_FILES}, q AS (SELECT vec_id AS qid, v AS qv FROM u WHERE vec_id % 25 = 0), near AS (SELECT * FROM (SELECT qid, qv, file_no, row_number() OVER (PARTITION BY qid ORDER BY list_distance(centroid, qv), file_no) AS p FROM c, q) WHERE p <= 5), d AS (SELECT qid, vec_id, list_distance(v, qv) AS distance FROM f JOIN near USING (file_no)), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY distance, vec_id) AS rank FROM d) SELECT qid, vec_id, round(distance, 6) AS distance, CAST(rank AS INTEGER) AS rank FROM r WHERE rank <= 10")
def centroid_topk_batch(spark, sf):
    return out_topk(shared(spark, sf)[1].search_centroid_batch("ix", queries_of(uniform(spark, sf)), 10, 5))


@query("w_threshold_files", f"WITH {_FILES}, q AS (SELECT v AS qv FROM u WHERE vec_id = 7) SELECT t, count(*) FILTER (WHERE greatest(list_distance(centroid, qv) - radius, 0) <= t + 1e-7) AS files FROM c JOIN rad USING (file_no), q, (VALUES (0.05::DOUBLE), (0.2), (1.2)) x(t) GROUP BY t")
def w_threshold_files(spark, sf):
    m, q = shared(spark, sf)[1], _seven(spark, sf)
    return spark.createDataFrame([(t, len(m.centroids("ix").within(q, t))) for t in (0.05, 0.2, 1.2)], "t double, files long")


@query("w_knn_group", f"WITH {UQ}, d AS (SELECT qid, vec_id, label, list_distance(v, qv) AS distance FROM q, u), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY distance, vec_id) AS rank FROM d) SELECT label, count(*) AS n, round(avg(distance), 6) AS mean, round(min(distance), 6) AS least FROM r WHERE rank <= 10 GROUP BY label")
def w_knn_group(spark, sf):
    near = _top(spark, sf).join(uniform(spark, sf).select("vec_id", "label"), "vec_id")
    return near.groupBy("label").agg(F.count("*").alias("n"), F.round(F.avg("distance"), 6).alias("mean"), F.round(F.min("distance"), 6).alias("least"))


@query("w_centroid_blob", no_violations("raw size by the formula", "compressed is smaller", "centroids come back"))
def w_centroid_blob(spark, sf):
    """The centroid blob of ten thousand files of the paper's width: raw and compressed size, and a round trip."""
    n, d = 10_000, 768
    centre = np.random.default_rng(0).standard_normal((n, d)).astype(np.float32)
    raw = blobs.encode_centroids([f"data/f{i}.parquet" for i in range(n)], np.arange(n), centre, np.ones(n), "l2")
    path = f"{warehouse(spark)}/centroids.side"
    write_container(path, [Blob(CENTROIDS, raw, [1], 1, {}, "zstd")], {})
    meta = read_footer(path).first(CENTROIDS)
    back = blobs.decode_centroids(read_blob(path, meta))
    least = int(cost.size_model(cost.Scale())["file_centroids"])
    return violations(spark, **{"raw size by the formula": not least <= len(raw) <= least + 64 * n, "compressed is smaller": meta.length >= meta.raw_length, "centroids come back": not np.array_equal(back["centroid"].astype(np.float32), centre)})


@query("insert_recall", no_violations("recall after inserts under 0.9", "refresh takes over what is there"))
def insert_recall(spark, sf):
    """A tenth of the files is appended and taken in by a refresh; recall by the options as they come."""
    each, e = per_file(spark, sf), uniform(spark, sf)
    table = table_of(spark, sf, f"vec_id < {18 * each}", 18, each)
    m = IndexManager(table)
    m.create("ix", "v")
    table.append(e.filter(f"vec_id >= {18 * each}"), 2, file_no=(F.col("vec_id") / each).cast("int"))
    m.refresh("ix")
    recall = A.recall_at_k(m.search("ix", queries_of(e), 10, stale="error"), exact_batch_topk(e, queries_of(e), 10), 10).first()[0]
    return violations(spark, **{"recall after inserts under 0.9": recall < 0.9, "refresh takes over what is there": any(r["rebuilt"] for r in m.last_results)})


@query("recall_vs_tombstones", no_violations("recall under 0.9 at one file", "recall under 0.9 at two", "recall under 0.9 at three"))
def recall_vs_tombstones(spark, sf):
    """Recall as tombstones grow to 15 %, below the limit of a rebuild: the beam widens with them."""
    each, e = per_file(spark, sf), uniform(spark, sf)
    table = table_of(spark, sf, per_file=each)
    m = IndexManager(table)
    m.create("ix", "v")
    low = []
    for i in range(3):
        table.remove_files([i])
        m.refresh("ix")
        live = e.filter(F.col("vec_id") >= (i + 1) * each)
        low.append(A.recall_at_k(m.search("ix", queries_of(e), 10), exact_batch_topk(live, queries_of(e), 10), 10).first()[0] < 0.9)
    return violations(spark, **dict(zip(("recall under 0.9 at one file", "recall under 0.9 at two", "recall under 0.9 at three"), low)))


@query("refresh_commit", "SELECT * FROM (VALUES (1, 'create', 0), (2, 'replace', 1), (3, 'append', 1), (4, 'replace', 2)) x(version, operation, containers)")
def refresh_commit(spark, sf):
    """A refresh writes a new root container under a metadata-only commit; the version before keeps its own."""
    table, m, _ = _history(spark, sf)
    m.refresh("ix")
    seen, out = set(), []
    for v in table.log.versions():
        snap = table.log.snapshot(v)
        seen |= {x["path"] for x in snap.indexes.values()}
        out.append((v, snap.operation, len(seen)))
    return spark.createDataFrame(out, "version int, operation string, containers int")


@query("blob_properties", "SELECT 'vector-centroids-v1' AS type, '64' AS dim, 'l2' AS metric, count(*)::VARCHAR AS n, CAST(1 AS BIGINT) AS snapshot FROM embeddings UNION ALL SELECT 'vector-routing-v1', '64', 'l2', count(*)::VARCHAR, 1 FROM embeddings")
def blob_properties(spark, sf):
    index = shared(spark, sf)[1].open("ix")
    found = read_footer(f"{index.root}/{index.path}").blobs
    return spark.createDataFrame([(b.type, b.properties["dim"], b.properties["metric"], b.properties["n"], b.snapshot_id) for b in found], "type string, dim string, metric string, n string, snapshot long")


@query("cache_hits", no_violations("second read misses", "another object"))
def cache_hits(spark, sf):
    """A shard is decoded once a process: the second look-up gives the same object."""
    index = shared(spark, sf)[1].open("ix")
    first = index.shards[0]
    one = cached_shard(f"{index.root}/{first['path']}", first["blob"])
    before = dict(HITS)
    two = cached_shard(f"{index.root}/{first['path']}", first["blob"])
    return violations(spark, **{"second read misses": HITS["miss"] != before["miss"] or HITS["hit"] != before["hit"] + 1, "another object": one is not two})


@query("visits_bound", no_violations("visits beyond the shard", "distances beyond the degree"))
def visits_bound(spark, sf):
    """Nodes visited are at most a shard's, and each visit measures at most the widest degree, besides the entries."""
    m = shared(spark, sf)[1]
    index = m.open("ix")
    got = m.stage_a(index, queries_of(uniform(spark, sf)), 10, 24, 4).cache()
    wide = max(max(len(v) for v in cached_shard(f"{index.root}/{s['path']}", s["blob"]).neighbours) for s in index.shards)
    n = max(s["n"] for s in index.shards)
    return violations(spark, **{"visits beyond the shard": got.filter(F.col("visited") > n).count(), "distances beyond the degree": got.filter(F.col("distances") > F.col("visited") * wide + 64).count()})


@query("range_subset_of_exact", no_violations("rows beyond the threshold", "rows of the graph that exact search lacks"))
def range_subset_of_exact(spark, sf):
    """A range answered through the graph, by the options as they come, is a part of the exact one."""
    q = _seven(spark, sf)
    got = shared(spark, sf)[1].search("ix", spark.createDataFrame([(7, q)], "qid long, qv array<double>"), 50).filter("distance <= 1.2")
    exact = exact_range(uniform(spark, sf), q, 1.2).select("vec_id")
    return violations(spark, **{"rows beyond the threshold": got.filter("distance > 1.2").count(), "rows of the graph that exact search lacks": got.join(exact, "vec_id", "left_anti").count()})


@query("w_oversample", no_violations("recall falls as oversampling grows"))
def w_oversample(spark, sf):
    e = uniform(spark, sf)
    qs, m = queries_of(e), shared(spark, sf)[1]
    truth = exact_batch_topk(e, qs, 10)
    r = [A.recall_at_k(m.search("ix", qs, 10, L=500, shard_oversample=50, rerank_oversample=c), truth, 10).first()[0] for c in (1, 2, 4, 8)]
    return violations(spark, **{"recall falls as oversampling grows": sum(b < a for a, b in zip(r, r[1:]))})


@query("w_threshold", f"{_ONE} SELECT t, count(*) AS n FROM d, (VALUES (1.2::DOUBLE), (1.3)) x(t) WHERE distance <= t GROUP BY t")
def w_threshold(spark, sf):
    m, q = shared(spark, sf)[1], _seven(spark, sf)
    parts = [m.search_range("ix", q, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("t"), "n") for t in (1.2, 1.3)]
    return parts[0].unionByName(parts[1])


@query("w_shard_spread", f"WITH {UQ}, d AS (SELECT qid, vec_id, row_number() OVER (PARTITION BY qid ORDER BY list_distance(v, qv), vec_id) AS rank FROM q, u) SELECT qid, count(DISTINCT vec_id % 4) AS hash_shards, count(DISTINCT (vec_id // 25) % 4) AS file_shards FROM d WHERE rank <= 10 GROUP BY qid")
def w_shard_spread(spark, sf):
    e = uniform(spark, sf)
    t = exact_batch_topk(e, queries_of(e), 10)
    return t.groupBy("qid").agg(F.countDistinct(F.col("vec_id") % 4).alias("hash_shards"), F.countDistinct(F.floor(F.col("vec_id") / 25) % 4).alias("file_shards"))


_KNN_CTE = f"WITH {UQ}, d AS (SELECT qid, vec_id, label, list_distance(v, qv) AS distance FROM q, u), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY distance, vec_id) AS rank FROM d), top AS (SELECT * FROM r WHERE rank <= 10)"


def _top(spark, sf):
    return shared(spark, sf)[1].search("ix", queries_of(uniform(spark, sf)), 10, **EXHAUSTIVE)


@query("w_knn_join_docs", f"{_KNN_CTE} SELECT qid, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM top JOIN documents ON doc_id = vec_id GROUP BY qid, source")
def w_knn_join_docs(spark, sf):
    return _top(spark, sf).join(read(spark, sf, "documents"), F.col("doc_id") == F.col("vec_id")).groupBy("qid", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("w_knn_label_vote", f"{_KNN_CTE}, v AS (SELECT qid, label, count(*) AS n FROM top GROUP BY qid, label) SELECT qid, CAST(arg_min(label, (-n, label)) AS INTEGER) AS vote, max(n) AS n FROM v GROUP BY qid")
def w_knn_label_vote(spark, sf):
    v = _top(spark, sf).join(uniform(spark, sf).select("vec_id", "label"), "vec_id").groupBy("qid", "label").agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("n"), "label"))
    return v.withColumn("r", rank).filter("r = 1").select("qid", F.col("label").cast("int").alias("vote"), "n")


@query("w_event_queries", f"WITH {U}, n AS (SELECT max(vec_id) + 1 AS n FROM u), q AS (SELECT DISTINCT user_id % 20 AS qid FROM events), d AS (SELECT qid, b.vec_id, row_number() OVER (PARTITION BY qid ORDER BY list_distance(a.v, b.v), b.vec_id) AS rank FROM q JOIN u a ON a.vec_id = qid, u b), t AS (SELECT * FROM d WHERE rank <= 3) SELECT date_trunc('day', ts) AS day, t.vec_id, count(*) AS n FROM events JOIN t ON t.qid = user_id % 20 GROUP BY 1, 2")
def w_event_queries(spark, sf):
    e = uniform(spark, sf)
    ev = read(spark, sf, "events").select("ts", (F.col("user_id") % 20).alias("qid"))
    qs = ev.select("qid").distinct().join(e, F.col("vec_id") == F.col("qid")).select("qid", F.col("v").alias("qv"))
    top = shared(spark, sf)[1].search("ix", qs, 3, **EXHAUSTIVE)
    return ev.join(top, "qid").groupBy(F.date_trunc("day", "ts").alias("day"), "vec_id").agg(F.count("*").alias("n")).withColumn("day", F.col("day").cast("timestamp_ntz"))


# ---------------------------------------------------------------- sources and functions for users
@query("container_source", "SELECT 'vector-graph-v1' AS type, CAST(4 AS BIGINT) AS blobs, true AS sized UNION ALL SELECT 'vector-routing-v1', 1, true UNION ALL SELECT 'vector-centroids-v1', 1, true")
def container_source(spark, sf):
    from ..sources.reader import register

    register(spark)
    index = shared(spark, sf)[1].open("ix")
    paths = ",".join(f"{index.root}/{p}" for p in [index.path, *(s["path"] for s in index.shards)])
    return spark.read.format("ann_container").load(paths).groupBy("type").agg(F.count("*").alias("blobs"), (F.min("length") > 0).alias("sized"))


@query("udtf_graph_edges", no_violations("edges that differ"))
def udtf_graph_edges(spark, sf):
    from ..functions.udfs import register as functions
    from ..sources.reader import register

    register(spark)
    functions(spark)
    m = shared(spark, sf)[1]
    index = m.open("ix")
    spark.read.format("ann_container").option("payload", "true").load(",".join(f"{index.root}/{s['path']}" for s in index.shards)).createOrReplaceTempView("sidecar_blobs")
    got = spark.sql("SELECT e.src, e.dst FROM sidecar_blobs b, LATERAL decode_graph_edges(b.payload) e")
    want = m.edges("ix").select("src", "dst")
    return violations(spark, **{"edges that differ": got.exceptAll(want).count() + want.exceptAll(got).count()})


@query("udf_nearest_centroid", f"WITH {_CELLS} SELECT CAST(cell AS INTEGER) AS cell, count(*) AS n FROM a GROUP BY cell")
def udf_nearest_centroid(spark, sf):
    from ..functions.udfs import nearest_centroid_udf

    return uniform(spark, sf).groupBy(nearest_centroid_udf(_first8(spark, sf))("v").alias("cell")).agg(F.count("*").alias("n"))


@query("udf_pq_encode", f"WITH {_BOOK} SELECT vec_id, list(CAST(code AS INTEGER) ORDER BY s)::VARCHAR AS codes FROM e GROUP BY vec_id")
def udf_pq_encode(spark, sf):
    from ..functions.udfs import pq_encode_udf

    coded = uniform(spark, sf).select("vec_id", F.hex(pq_encode_udf(_book(spark, sf))("v")).alias("h"))
    codes = F.transform(F.sequence(F.lit(0), F.lit(3)), lambda i: F.conv(F.substring("h", 2 * i + 1, 2), 16, 10).cast("int"))
    return coded.select("vec_id", codes.cast("string").alias("codes"))


@query("udaf_vector_avg", f"WITH {U} SELECT label, count(*) AS n, round(avg(v[1]), 6) AS first, round(avg(v[64]), 6) AS last FROM u GROUP BY label")
def udaf_vector_avg(spark, sf):
    from ..functions.udfs import vector_avg

    return vector_avg(uniform(spark, sf), "v", 64, "label").select("label", "n", F.round(F.element_at("mean", 1), 6).alias("first"), F.round(F.element_at("mean", 64), 6).alias("last"))


_TEXT_VEC = """w AS (SELECT doc_id, unnest(list_filter(regexp_split_to_array(lower(text), '\\s+'), lambda x: x <> '')) AS w FROM docs), s AS (SELECT doc_id, CAST(('0x' || substr(md5(w), 1, 7)) AS BIGINT) AS h FROM w),
 c AS (SELECT doc_id, h % 64 AS i, sum(CASE WHEN (h // 64) % 2 = 0 THEN 1 ELSE -1 END)::DOUBLE AS x FROM s GROUP BY 1, 2), n AS (SELECT doc_id, sqrt(sum(x * x)) AS n FROM c GROUP BY doc_id)"""


@query("w_doc_retrieval_whole", f"WITH docs AS (SELECT doc_id, text FROM documents), {_TEXT_VEC}, q AS (SELECT * FROM c WHERE doc_id % 50 = 0), p AS (SELECT q.doc_id AS qid, c.doc_id AS vec_id, sum(q.x * c.x) AS ip FROM q JOIN c ON c.i = q.i GROUP BY 1, 2), d AS (SELECT qid, vec_id, 1 - ip / (a.n * b.n) AS distance FROM p JOIN n a ON a.doc_id = qid JOIN n b ON b.doc_id = vec_id) SELECT qid, count(*) FILTER (WHERE distance < 0.05) AS near FROM d GROUP BY qid")
def w_doc_retrieval_whole(spark, sf):
    """Near copies of every fiftieth text among texts of any length; only counts leave a task."""
    from ..functions.udfs import hash_text_vector
    from ..operators.exact import exact_batch_count

    docs = read(spark, sf, "documents").select(F.col("doc_id").alias("vec_id"), hash_text_vector(F.col("text")).alias("v"))
    qs = docs.filter("vec_id % 50 = 0").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    return exact_batch_count(docs, qs, 0.05, metric="cosine")


_GRAM = 5
_WORDS = "list_filter(regexp_split_to_array(text, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')"


def _grams(words: str, n) -> F.Column:
    """Distinct runs of n words."""
    n = F.lit(n) if isinstance(n, int) else n
    runs = F.transform(F.sequence(F.lit(1), F.size(words) - n + 1), lambda i: F.concat_ws(" ", F.slice(words, i, n)))
    return F.when((n > 0) & (F.size(words) >= n), F.array_distinct(runs)).otherwise(F.array().cast("array<string>"))


@query("w_benchmark_overlap_whole", f"WITH b AS (SELECT item_id, {_WORDS} AS w, least({_GRAM}, len(w)) AS n FROM benchmark), bg AS (SELECT DISTINCT item_id, unnest(list_transform(range(1, len(w) - n + 2), lambda i: array_to_string(w[i : i + n - 1], ' '))) AS g FROM b WHERE n > 0), s AS (SELECT item_id, count(*) AS size FROM bg GROUP BY item_id), d AS (SELECT doc_id, {_WORDS} AS w FROM documents), dg AS (SELECT DISTINCT doc_id, unnest(list_transform(range(1, len(w) - n + 2), lambda i: array_to_string(w[i : i + n - 1], ' '))) AS g FROM d, (SELECT DISTINCT n FROM b WHERE n > 0) WHERE len(w) >= n), m AS (SELECT item_id, doc_id, count(*) AS held FROM bg JOIN dg USING (g) GROUP BY 1, 2) SELECT item_id, count(*) AS documents FROM m JOIN s USING (item_id) WHERE 2 * held >= size GROUP BY item_id")
def w_benchmark_overlap_whole(spark, sf):
    """Documents that hold at least half of an item's runs of five words, wherever they stand; shorter items as a whole."""
    return benchmark_overlap(read(spark, sf, "benchmark"), read(spark, sf, "documents"))


def benchmark_overlap(items, docs):
    words = F.filter(F.split(F.coalesce(F.col("text"), F.lit("")), r"[\x20\x09-\x0D]+"), lambda x: x != "")
    b = items.select("item_id", words.alias("w")).withColumn("n", F.least(F.lit(_GRAM), F.size("w"))).filter("n > 0")
    lengths = sorted(r[0] for r in b.select("n").distinct().collect())
    own = b.select("item_id", _grams("w", F.col("n")).alias("g")).select("item_id", F.size("g").alias("size"), F.explode("g").alias("g"))
    each = F.concat(*[_grams("w", n) for n in lengths]) if lengths else F.array().cast("array<string>")
    held = docs.select("doc_id", words.alias("w")).select("doc_id", F.explode(each).alias("g"))
    pairs = held.join(F.broadcast(own), "g").groupBy("item_id", "doc_id", "size").agg(F.count("*").alias("held"))
    return pairs.filter(F.col("held") * 2 >= F.col("size")).groupBy("item_id").agg(F.count("*").alias("documents"))


@query("derived_quantile_model", no_violations("outside the tolerance"))
def derived_quantile_model(spark, sf):
    """Quantiles of a column as derived data, checked against exact ranks."""
    li = read(spark, sf, "lineitem").select("l_extendedprice")
    n = li.count()
    ps = [0.1, 0.25, 0.5, 0.75, 0.9]
    q = li.agg(F.percentile_approx("l_extendedprice", ps, 1000).alias("q")).first()["q"]
    rank = li.agg(*[F.count(F.when(F.col("l_extendedprice") <= v, 1)).alias(f"r{i}") for i, v in enumerate(q)]).first()
    return violations(spark, **{"outside the tolerance": sum(abs(rank[i] / n - p) > 0.01 for i, p in enumerate(ps))})


@query("w_filtered_region", f"WITH {U}, one AS (SELECT v AS qv FROM u WHERE vec_id = 7), d AS (SELECT vec_id, list_distance(v, qv) AS distance FROM u, one) SELECT p_partkey, p_brand, round(distance, 6) AS distance FROM d JOIN part ON p_partkey = vec_id WHERE p_size < 25 ORDER BY d.distance, p_partkey LIMIT 10")
def w_filtered_region(spark, sf):
    """Feature search over parts under an attribute filter."""
    parts = read(spark, sf, "part").filter("p_size < 25").join(uniform(spark, sf), F.col("vec_id") == F.col("p_partkey"))
    return exact_topk(parts, _seven(spark, sf), 10, key="p_partkey").select("p_partkey", "p_brand", F.round("distance", 6).alias("distance"))
