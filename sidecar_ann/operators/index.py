"""Sharded graph indexes bound to table snapshots: distributed build, three-stage probe, incremental refresh.

Build: a hashed sample trains the codebooks; every row's shard follows from its id, file or nearest cell; each shard is
built by one task, which writes its own object and returns one row; the root container holds routing and file centroids
and is bound by a metadata-only commit. Probe: every (shard, block of queries) is a task that emits at most K times the
oversampling; candidates are merged by approximate distance, reranked exactly on the row groups that hold them, and cut to K. Refresh: the manifest difference since the base snapshot names added and removed files; only shards that they
touch are rewritten; removed rows become tombstones; a shard with too many is rebuilt. File centroids of unchanged files are
taken over from the index before."""

from __future__ import annotations

import json
import time
import uuid
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..errors import BadParameter, StaleIndex, UnknownIndex
from ..functions import distance as D
from ..functions import graph as G
from ..functions import quantize as Q
from ..sources import blobs, store
from ..sources.catalog import Change, Snapshot, Table, diff, file_number
from ..sources.container import CENTROIDS, GRAPH, ROUTING, Blob, pack, read_blob, read_footer, write_container
from .centroids import CentroidProbe, centroids_of
from .exact import exact_batch_topk, files_batch_topk, top_per_query, vectors_of


@dataclass
class IndexOptions:
    metric: str = "l2"
    sharding: str = "hash"  # hash (of the id), file, centroid
    num_shards: int = 4
    R: int = 16
    L: int = 100
    alpha: float = 1.2
    saturate: bool = True
    n_entries: int = 16
    repair: bool = True
    pq_m: int = 16
    pq_nbits: int = 8
    pq_scope: str = "global"  # or shard
    keep_vectors: bool = False
    compression: str = "none"
    mode: str = "by_ref"  # or inline
    kind: str = "graph"  # or hnsw, centroid
    sample_fraction: float = 1.0
    sample_cap: int = 20_000
    cells: int = 8
    seed: int = 0
    tombstone_limit: float = 0.20
    shard_rows: int = 1_000_000

    def __post_init__(self) -> None:
        if self.metric not in D.METRICS:
            raise BadParameter(f"unknown metric {self.metric}")
        if self.sharding not in ("hash", "file", "centroid") or self.num_shards < 1:
            raise BadParameter("sharding is hash, file or centroid, with at least one shard")
        self.graph()

    def graph(self) -> G.GraphParams:
        return G.GraphParams(self.R, self.L, self.alpha, "ip" if self.metric == "ip" else "l2", self.saturate, self.n_entries, self.repair, self.seed)


@dataclass
class Index:
    """A decoded routing blob and where it came from."""

    name: str
    path: str
    base: int
    column: str
    dim: int
    options: IndexOptions
    shards: list[dict]
    codebook: np.ndarray
    cell_shards: list[list[int]]
    covered: dict[str, int]  # path -> file number
    root: str

    def shard_of(self, vector: Column, key: Column, file_no: Column) -> Column:
        """Shard of a row, natively: id, file, or nearest cell and, where a cell is split, the id's hash."""
        o = self.options
        if o.sharding == "hash":
            return F.pmod(key.cast("long"), F.lit(o.num_shards)).cast("int")
        if o.sharding == "file":
            return F.pmod(file_no, F.lit(o.num_shards)).cast("int")
        d = F.array(*[D.l2sq(vector, D.literal(c)) for c in self.codebook])
        cell = F.array_position(d, F.array_min(d)).cast("int")
        places = F.array(*[F.array(*[F.lit(int(s)) for s in c]) for c in self.cell_shards])
        own = F.element_at(places, cell)
        return F.element_at(own, F.pmod(F.xxhash64(key), F.size(own)).cast("int") + 1)


def a_task_each(rows: DataFrame, shards: list[int]) -> DataFrame:
    """rows (shard, ...) with those of each of the shards in a partition of its own. A hash of the number would put several
    shards in one partition and leave others empty, and their work would be done one after another."""
    place = F.array_position(F.array(*[F.lit(int(s)) for s in shards]).cast("array<int>"), F.col("shard")) - 1
    return rows.repartitionById(max(1, len(shards)), place.cast("int"))


def each_shard(rows: DataFrame, shards: list[int], run: Callable[[pa.Table], pa.Table], schema: str) -> DataFrame:
    """run's rows for the rows of each of the shards that has any, a task each."""

    def tables(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if got := [b for b in batches if b.num_rows]:
            yield from run(pa.Table.from_batches(got).combine_chunks()).to_batches()

    return a_task_each(rows, shards).mapInArrow(tables, schema)


def sample_rows(rows: DataFrame, fraction: float, cap: int, key: str = "vec_id") -> DataFrame:
    """A deterministic sample by the hash of the id, at most cap rows."""
    own = rows if fraction >= 1 else rows.filter(F.pmod(F.xxhash64(key), F.lit(1 << 20)) < int(fraction * (1 << 20)))
    return own.orderBy(F.xxhash64(key), key).limit(cap)


def plan_shards(cell_rows: list[int], shards: int, most: int) -> list[list[int]]:
    """Shards of each cell: cells above `most` rows or above twice a fair share are split, the rest packed greedily, the
    largest first, into the least loaded shard."""
    fair = max(1, sum(cell_rows) // shards)
    load = [0] * shards
    out: list[list[int]] = [[0]] * len(cell_rows)
    for c in sorted(range(len(cell_rows)), key=lambda c: (-cell_rows[c], c)):
        parts = min(shards, max(1, -(-cell_rows[c] // min(most, 2 * fair))))
        chosen = sorted(sorted(range(shards), key=lambda s: (load[s], s))[:parts])
        for s in chosen:
            load[s] += cell_rows[c] // parts
        out[c] = chosen
    return out


def _prepared(x: np.ndarray, metric: str) -> np.ndarray:
    if metric != "cosine":
        return x
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(n > 0, n, 1)


def _build_shard(ids, files, rows, x, o: IndexOptions, book: np.ndarray | None, seed: int) -> blobs.Shard:
    x = _prepared(x, o.metric)
    if book is None:
        book, _ = Q.train_pq(x[: o.sample_cap], o.pq_m, o.pq_nbits, 6, seed) if len(x) else (np.zeros((o.pq_m, 1 << o.pq_nbits, 1), np.float32), [])
    table, entries = G.build_graph(x, replace(o.graph(), seed=seed))
    codes = Q.pq_encode(x, book) if len(x) else np.zeros((0, o.pq_m), np.uint8)
    return blobs.Shard(ids, files, rows, G.as_lists(table), entries, o.metric, {"R": o.R, "L": o.L, "alpha": o.alpha, "seed": seed}, book, codes, np.zeros(len(ids), bool), x.astype(np.float32) if o.keep_vectors else None, x.shape[1])


def _put_shard(root: str, shard: blobs.Shard, o: IndexOptions, base: int, number: int) -> tuple[str, int]:
    """Writes one shard as a container of its own, under a name of this attempt; (name, bytes)."""
    name = f"index/{base}-shard{number}-{uuid.uuid4().hex}.side"
    data = pack([Blob(GRAPH, blobs.encode_shard(shard, o.keep_vectors), [1], base, {"dim": str(shard.dim), "metric": o.metric, "n": str(shard.n), "shard": str(number)}, o.compression)])
    store.put(f"{root}/{name}", data)
    return name, len(data)


_RESULT = "shard int, path string, n long, dead long, bytes long, seconds double, inertia double, rebuilt boolean, visits long, distances long"


def _result(shard: int, path: str, n: int, dead: int, size: int, seconds: float, inertia: float, rebuilt: bool = False, visits: int = 0, distances: int = 0) -> pa.Table:
    return pa.table({"shard": pa.array([shard], pa.int32()), "path": [path], "n": [n], "dead": [dead], "bytes": [size], "seconds": [seconds], "inertia": [inertia], "rebuilt": [rebuilt], "visits": [visits], "distances": [distances]})


class IndexManager:
    def __init__(self, table: Table):
        self.table, self.spark = table, table.spark
        self.last_results: list[dict] = []
        self.last_metrics: dict = {}
        self.last_centroid_files: list[int] = []
        self.last_candidates: DataFrame | None = None
        self._held: tuple[tuple, DataFrame, DataFrame | None] | None = None

    # ------------------------------------------------------------ build
    def _rows(self, snap: Snapshot, column: str, paths: list[str]) -> DataFrame:
        return self.table.read_files(snap, paths).select(
            F.col(snap.id_column).cast("long").alias("vec_id"), F.col(column).alias("v"), file_number().alias("file_no"), F.col("_metadata.row_index").alias("row_offset")
        )

    def create(self, name: str, column: str, **options) -> Index:
        o = IndexOptions(**options)
        log = self.table.log
        snap = log.current()
        if name in snap.indexes:
            raise BadParameter(f"index {name} exists")
        return self._build(name, column, o, snap)

    def _build(self, name: str, column: str, o: IndexOptions, snap: Snapshot) -> Index:
        files = self.table.log.files(snap)
        rows = self._rows(snap, column, [f.path for f in files])
        first = rows.filter(F.col("v").isNotNull()).select(F.size("v").alias("d")).first()
        dim = first["d"] if first else 1
        rows = rows.filter(D.is_valid_vector(F.col("v"), dim))
        got = sample_rows(rows.select("vec_id", "v"), o.sample_fraction, o.sample_cap).collect()
        sample = _prepared(np.array([r["v"] for r in got], np.float64).reshape(-1, dim), o.metric)
        if o.pq_m > dim or dim % o.pq_m:
            raise BadParameter(f"{o.pq_m} subspaces do not divide {dim} dimensions")
        codebook, _ = Q.kmeans(sample, o.cells, 8, o.seed) if len(sample) else (np.zeros((1, dim)), [])
        book = Q.train_pq(sample, o.pq_m, o.pq_nbits, 6, o.seed)[0] if len(sample) and o.pq_scope == "global" else None
        index = Index(name, "", snap.version, column, dim, o, [], codebook, [[0]] * len(codebook), {f.path: f.file_no for f in files}, self.table.log.root)
        if o.kind != "centroid":
            if o.sharding == "centroid":
                flat = replace(index, cell_shards=[[c] for c in range(len(codebook))])
                counts = {r["c"]: r["n"] for r in rows.groupBy(flat.shard_of(F.col("v"), F.col("vec_id"), F.col("file_no")).alias("c")).agg(F.count("*").alias("n")).collect()}
                index.cell_shards = plan_shards([counts.get(c, 0) for c in range(len(codebook))], o.num_shards, o.shard_rows)
            placed = rows.withColumn("shard", index.shard_of(F.col("v"), F.col("vec_id"), F.col("file_no")))
            root, base = self.table.log.root, snap.version

            def build(table: pa.Table) -> pa.Table:
                begun = time.time()
                number = table.column("shard")[0].as_py()
                table = table.sort_by("vec_id")
                x = vectors_of(table.column("v").combine_chunks())
                shard = _build_shard(*(np.asarray(table.column(c)) for c in ("vec_id", "file_no", "row_offset")), x, o, book, o.seed + number)
                path, size = _put_shard(root, shard, o, base, number)
                return _result(number, path, shard.n, 0, size, time.time() - begun, float(Q.nearest(x, codebook)[1].sum()))

            self.last_results = [r.asDict() for r in each_shard(placed, list(range(o.num_shards)), build, _RESULT).collect()]
            index.shards = [{"shard": r["shard"], "path": r["path"], "n": r["n"], "dead": 0, "bytes": r["bytes"], "blob": 0} for r in sorted(self.last_results, key=lambda r: r["shard"])]
        return self._commit(index, snap)

    def _centroid_blob(self, index: Index, snap: Snapshot, known: dict[str, int]) -> bytes:
        """Centroids of the snapshot's files. Those of `known`, the files of the container that the index was read from, are
        taken over unless a file of the same number came or went; only the other files are read."""
        own = self.table.log.files(snap)
        there = {f.path for f in own}
        moved = {n for p, n in known.items() if p not in there} | {f.file_no for f in own if f.path not in known}
        self.last_centroid_files = sorted(f.file_no for f in own if f.file_no in moved or not known)
        cent = centroids_of(self.table, snap, index.column, index.dim, [f for f in own if f.file_no in moved or not known])
        number = np.array([c["file_no"] for c in cent], np.int64)
        centre = np.array([c["centroid"] for c in cent]).reshape(-1, index.dim)
        radius = np.array([c["radius"] for c in cent], np.float64)
        if known:
            old = cached_centroids(f"{index.root}/{index.path}")
            keep = np.isin(old["file_no"], [f.file_no for f in own]) & ~np.isin(old["file_no"], sorted(moved))
            # one float down, as encoding goes one up again
            radius = np.concatenate([np.nextafter(old["radius"][keep], np.float32(-np.inf)), radius])
            number, centre = np.concatenate([old["file_no"][keep], number]), np.concatenate([old["centroid"][keep], centre])
        order = np.argsort(number, kind="stable")
        return blobs.encode_centroids([f.path for f in own], number[order], centre[order], radius[order], index.options.metric)

    def _commit(self, index: Index, snap: Snapshot, known: dict[str, int] | None = None) -> Index:
        o, log = index.options, self.table.log
        name = f"index/{snap.version}-{index.name}-{uuid.uuid4().hex}.side"
        graphs = []
        if o.mode == "inline" and index.shards:
            graphs = [self._raw_blob(index, s) for s in index.shards]
            index.shards = [{**s, "path": name, "blob": 2 + k} for k, s in enumerate(index.shards)]
        head = {"name": index.name, "base": snap.version, "column": index.column, "dim": index.dim, "options": asdict(o), "shards": index.shards, "cells": index.cell_shards, "covered": index.covered}
        props = {"dim": str(index.dim), "metric": o.metric, "base": str(snap.version), "n": str(sum(s["n"] for s in index.shards))}
        pieces = [
            Blob(ROUTING, blobs.encode_routing(head, index.codebook), [1], snap.version, props),
            Blob(CENTROIDS, self._centroid_blob(index, snap, known or {}), [1], snap.version, props, "zstd"),
            *graphs,
        ]
        write_container(f"{log.root}/{name}", pieces, {"index": index.name})
        objects = sorted({s["path"] for s in index.shards} - {name})
        log.commit(snap, Change("replace", bind={index.name: {"path": name, "base": snap.version, "objects": objects}}))
        index.path, index.base = name, snap.version
        return index

    def _raw_blob(self, index: Index, s: dict) -> Blob:
        path = f"{index.root}/{s['path']}"
        meta = [b for b in read_footer(path).blobs if b.type == GRAPH][0]
        return Blob(GRAPH, read_blob(path, meta), meta.fields, meta.snapshot_id, meta.properties, meta.codec)

    # ------------------------------------------------------------ look-up
    def open(self, name: str, version: int | None = None) -> Index:
        snap = self.table.log.at(version)
        if name not in snap.indexes:
            raise UnknownIndex(name)
        path = snap.indexes[name]["path"]
        full = f"{self.table.log.root}/{path}"
        head, codebook = blobs.decode_routing(read_blob(full, read_footer(full).first(ROUTING)))
        return Index(name, path, head["base"], head["column"], head["dim"], IndexOptions(**head["options"]), head["shards"], codebook.astype(np.float64), head["cells"], head["covered"], self.table.log.root)

    def centroids(self, name: str, version: int | None = None) -> CentroidProbe:
        index = self.open(name, version)
        c = cached_centroids(f"{index.root}/{index.path}")
        return CentroidProbe(c["file_no"], c["centroid"], c["radius"], c["metric"])

    def list(self) -> list[str]:
        return sorted(self.table.log.current().indexes)

    def describe(self, name: str) -> dict:
        i = self.open(name)
        return {"name": i.name, "base": i.base, "column": i.column, "dim": i.dim, "shards": len(i.shards), "rows": sum(s["n"] for s in i.shards), "dead": sum(s["dead"] for s in i.shards), "bytes": sum(s["bytes"] for s in i.shards), **asdict(i.options)}

    def drop(self, name: str) -> Snapshot:
        snap = self.table.log.current()
        if name not in snap.indexes:
            raise UnknownIndex(name)
        return self.table.log.commit(snap, Change("replace", bind={name: None}))

    # ------------------------------------------------------------ probe
    def stage_a(self, index: Index, queries: DataFrame, k: int, L: int, oversample: int, nprobe_shards: int | None = None, distance: str = "pq", removed: list[int] | None = None) -> DataFrame:
        """qid, vec_id, file_no, row_offset, approx, shard, visited, distances: at most k * oversample rows for each
        query and shard, live rows only. Rows of `removed` files count as dead, so the beam is widened for them, too."""
        gone = np.array(sorted(removed or []), np.int64)
        root, want = index.root, k * oversample
        there = self.spark.createDataFrame([(s["shard"], s["path"], s["blob"], s["n"], s["dead"]) for s in index.shards], "shard int, path string, blob int, n long, dead long")
        blocks = queries.select("qid", "qv").withColumn("block", F.pmod(F.col("qid"), F.lit(16)).cast("int"))
        spread = blocks.join(F.broadcast(there.filter("n > 0")), F.lit(True))
        if nprobe_shards is not None and index.options.sharding == "centroid":
            near = F.array(*[D.l2sq(F.col("qv"), D.literal(c)) for c in index.codebook])
            of = {s["shard"]: [c for c, own in enumerate(index.cell_shards) if s["shard"] in own] for s in index.shards}
            reach = F.array(*[F.array_min(F.array(*[F.element_at(F.col("_near"), c + 1) for c in of[s["shard"]]])) if of[s["shard"]] else F.lit(float("inf")) for s in index.shards])
            order = F.create_map(*[F.lit(x) for i, s in enumerate(index.shards) for x in (s["shard"], i + 1)])
            spread = spread.withColumn("_near", near).withColumn("_reach", reach).withColumn("_own", F.element_at("_reach", order[F.col("shard")]))
            spread = spread.withColumn("_rank", F.row_number().over(Window.partitionBy("qid").orderBy("_own", "shard"))).filter(F.col("_rank") <= nprobe_shards)
        spread = spread.select("shard", "path", "blob", "block", "qid", "qv")
        metric, kind = index.options.metric, index.options.kind
        schema = "qid long, vec_id long, file_no int, row_offset long, approx double, shard int, visited long, distances long"

        def run(table: pa.Table) -> pa.Table:
            number = table.column("shard")[0].as_py()
            shard = cached_shard(f"{root}/{table.column('path')[0].as_py()}", table.column("blob")[0].as_py())
            qid = np.asarray(table.column("qid"))
            q = _prepared(vectors_of(table.column("qv").combine_chunks()), metric)
            live = shard.live & ~np.isin(shard.files, gone) if len(gone) else shard.live
            ratio = 1 - live.mean() if shard.n else 0.0
            wide = shard.n if ratio >= 1 else min(shard.n, int(np.ceil(max(L, want) / (1 - ratio))))
            full = distance == "full" and shard.vectors is not None
            table_ = neighbour_table(shard)
            kind_ = "ip" if metric == "ip" else "l2"
            if kind == "hnsw" and shard.vectors is not None:
                got = G.search_hnsw(shard.vectors, layers_of(shard, index.options), q, wide, kind_)
            elif full:
                got = G.beam_search(shard.vectors, table_, shard.entries, q, wide, kind_)
            else:
                got = G.beam_search(None, table_, shard.entries, q, wide, kind_, shard.codes, shard.codebook)
            ok = (got.ids >= 0) & live[np.maximum(got.ids, 0)]
            rank = np.cumsum(ok, 1)
            r, c = np.nonzero(ok & (rank <= want))
            node = got.ids[r, c]
            return pa.table({"qid": qid[r], "vec_id": shard.ids[node], "file_no": pa.array(shard.files[node], pa.int32()), "row_offset": shard.offsets[node], "approx": got.distance[r, c], "shard": pa.array(np.full(len(r), number), pa.int32()), "visited": got.visited[r], "distances": got.distances[r]})

        return spread.groupBy("shard", "path", "blob", "block").applyInArrow(run, schema)

    def cuts_nothing(self, index: Index, k: int, L: int, shard_oversample: int, rerank_oversample: int, nprobe_shards: int | None = None) -> bool:
        """Whether no shard's beam, no shard's share of candidates and no share of the rerank is smaller than what there is.
        Then all queries have the same candidates, those of `reached`."""
        most, total = max(s["n"] for s in index.shards), sum(s["n"] for s in index.shards)
        every = nprobe_shards is None or index.options.sharding != "centroid" or nprobe_shards >= sum(s["n"] > 0 for s in index.shards)
        return every and k * shard_oversample >= most and max(L, k * shard_oversample) >= most and k * rerank_oversample >= total

    def reached(self, index: Index, removed: list[int] | None = None) -> DataFrame:
        """vec_id, file_no, row_offset of the live rows that the shards' graphs reach from their entries: the candidates of
        any query under a beam as wide as the shard, found once a shard instead of once a query."""
        gone = np.array(sorted(removed or []), np.int64)
        root, o = index.root, index.options
        full = [s for s in index.shards if s["n"]]
        there = a_task_each(self.spark.createDataFrame([(s["shard"], s["path"], s["blob"]) for s in full], "shard int, path string, blob int"), [s["shard"] for s in full]).select("path", "blob")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for path, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                    shard = cached_shard(f"{root}/{path}", blob)
                    if o.kind == "hnsw" and shard.vectors is not None:
                        ok = G.reachable_hnsw(shard.vectors, layers_of(shard, o))
                    else:
                        ok = G.reachable(neighbour_table(shard), shard.entries)
                    ok &= shard.live & ~np.isin(shard.files, gone)
                    yield pa.RecordBatch.from_arrays([pa.array(shard.ids[ok], pa.int64()), pa.array(shard.files[ok], pa.int32()), pa.array(shard.offsets[ok], pa.int64())], ["vec_id", "file_no", "row_offset"])

        return there.mapInArrow(run, "vec_id long, file_no int, row_offset long")

    def rows_at(self, index: Index, snap: Snapshot, places: DataFrame, where: Column | None = None) -> DataFrame:
        """vec_id, v of rows given by vec_id, file_no, row_offset; places in files that the snapshot no longer has fall away."""
        if where is None:
            place = ["file_no", "row_offset", "vec_id"]
            return places.select(*place).join(self.fetch(index, snap, places), place).select("vec_id", "v")
        rows = self._rows_where(snap, index.column, [f for f in self.table.log.files(snap) if f.path in index.covered], where)
        return rows.join(places.select("vec_id"), "vec_id", "left_semi")

    def merge(self, candidates: DataFrame, k: int, oversample: int) -> DataFrame:
        rank = F.row_number().over(Window.partitionBy("qid").orderBy("approx", "vec_id"))
        return candidates.withColumn("_r", rank).filter(F.col("_r") <= k * oversample).drop("_r")

    def _touched(self, snap: Snapshot, candidates: DataFrame) -> DataFrame:
        """path, rows: the places of candidates in each file that the snapshot has; one row a file, dealt by file."""
        live = self.spark.createDataFrame([(f.file_no, f.path) for f in self.table.log.files(snap)], "file_no int, path string")
        rows = candidates.groupBy("file_no").agg(F.sort_array(F.collect_set("row_offset")).alias("rows"))
        # a width of its own, which adaptive execution does not coalesce: the rows are small, the reads behind them are not
        return rows.join(live, "file_no").repartition(int(self.spark.conf.get("spark.sql.shuffle.partitions")), "file_no").select("file_no", "path", "rows")

    def row_group_masks(self, snap: Snapshot, candidates: DataFrame) -> DataFrame:
        """file_no, row_group, rows (places within the group) that hold candidates (file_no, row_offset); only footers are
        read. Places beyond a file's end are in no mask."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for number, path, rows in zip(*(b.column(i).to_pylist() for i in range(3))):
                    with store.opened(path) as f:
                        found = group_masks(pq.ParquetFile(f).metadata, np.array(rows, np.int64))
                    yield pa.RecordBatch.from_arrays([pa.array([number] * len(found), pa.int32()), pa.array([g for g, _ in found], pa.int32()), pa.array([at for _, at in found], pa.list_(pa.int64()))], ["file_no", "row_group", "rows"])

        return self._touched(snap, candidates).mapInArrow(run, "file_no int, row_group int, rows array<long>")

    def fetch(self, index: Index, snap: Snapshot, candidates: DataFrame) -> DataFrame:
        """file_no, row_offset, vec_id, v of the candidates: of the touched files only the row groups with a mask are read,
        two columns of them, one group at a time."""
        key, column = snap.id_column, index.column

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for number, path, rows in zip(*(b.column(i).to_pylist() for i in range(3))):
                    with store.opened(path) as f:
                        file = pq.ParquetFile(f)
                        starts = group_starts(file.metadata)
                        for g, at in group_masks(file.metadata, np.array(rows, np.int64)):
                            got = file.read_row_group(g, columns=[key, column]).take(pa.array(at)).combine_chunks()
                            ids, v = (got.column(c).combine_chunks() for c in (key, column))
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), number), pa.int32()), pa.array(at + starts[g]), ids.cast(pa.int64()), v.cast(pa.list_(pa.float64()))], ["file_no", "row_offset", "vec_id", "v"])

        return self._touched(snap, candidates).mapInArrow(run, "file_no int, row_offset long, vec_id long, v array<double>")

    def rerank(self, index: Index, snap: Snapshot, candidates: DataFrame, queries: DataFrame, where: Column | None = None) -> DataFrame:
        """qid, vec_id, distance: exact. Candidates with a row_offset are read by row-group masks; under a filter, which may
        need any column, and without offsets whole files are scanned. Candidates in files that the snapshot no longer has
        fall away in the join."""
        d = D.metric(index.options.metric)(F.col("v"), F.col("qv"))
        asked = queries.select("qid", "qv")
        if where is None and "row_offset" in candidates.columns:
            # with the id, as two files of one number would share offsets
            place = ["file_no", "row_offset", "vec_id"]
            found = candidates.select("qid", *place).join(self.fetch(index, snap, candidates), place)
            return found.join(asked, "qid").select("qid", "vec_id", d.alias("distance"))
        numbers = {r[0] for r in candidates.select("file_no").distinct().collect()}
        live = [f for f in self.table.log.files(snap) if f.file_no in numbers]
        own = self.table.read_files(snap, [f.path for f in live])
        own = own if where is None else own.filter(where)
        rows = own.select(F.col(snap.id_column).cast("long").alias("vec_id"), F.col(index.column).alias("v"))
        return candidates.select("qid", "vec_id").join(rows, "vec_id").join(asked, "qid").select("qid", "vec_id", d.alias("distance"))

    def search(self, name: str, queries: DataFrame, k: int, L: int | None = None, shard_oversample: int = 4, rerank_oversample: int = 4, nprobe_shards: int | None = None, stale: str = "hybrid", where: Column | None = None, filter_mode: str = "pre", version: int | None = None, distance: str = "pq", hold: bool = False) -> DataFrame:
        """qid, vec_id, distance, rank. Distances are exact; ids are the true ones up to recall, and exact for an
        index without shards, where all files are scanned. hold: more searches of this version follow, as for a stream."""
        snap = self.table.log.at(version)
        index = self.open(name, version)
        now, base = {f.path: f for f in self.table.log.files(snap)}, index.covered
        added = [f for p, f in now.items() if p not in base]
        removed = [n for p, n in base.items() if p not in now]
        if stale == "error" and (added or removed):
            raise StaleIndex(name)
        rows = lambda files: self._rows_where(snap, index.column, files, where)
        if not index.shards or (stale == "exact" and (added or removed)) or (where is not None and filter_mode == "pre"):
            return exact_batch_topk(rows(list(now.values())), queries, k, metric=index.options.metric).select("qid", "vec_id", "distance", "rank")
        L = L or index.options.L
        if self.cuts_nothing(index, k, L, shard_oversample, rerank_oversample, nprobe_shards):
            places, held = self._whole(index, snap, removed, where, hold)
            self.last_candidates = queries.select("qid").join(F.broadcast(places), F.lit(True))
            own = held if held is not None else self.rows_at(index, snap, places, where)
            exact = exact_batch_topk(own, queries, k, metric=index.options.metric).select("qid", "vec_id", "distance")
        else:
            cand = self.stage_a(index, queries, k, L, shard_oversample, nprobe_shards, distance, removed)
            # stage A runs once: the rerank reads its candidates from a table
            merged = self._kept(self.merge(cand, k, rerank_oversample).select("qid", "vec_id", "file_no", "row_offset"))
            self.last_candidates = merged
            exact = self.rerank(index, snap, merged, queries, where)
        if added:
            exact = exact.unionByName(exact_batch_topk(rows(added), queries, k, metric=index.options.metric).select("qid", "vec_id", "distance"))
        found = top_per_query(exact, k).select("qid", "vec_id", "distance", "rank")
        if where is None:
            return found
        # after a filter a query may have less than k rows left: those queries are answered exactly
        found = self._kept(found)
        full = found.groupBy("qid").agg(F.count("*").alias("n")).filter(F.col("n") >= k).select("qid")
        rest = queries.join(full, "qid", "left_anti")
        again = exact_batch_topk(rows(list(now.values())), rest, k, metric=index.options.metric).select("qid", "vec_id", "distance", "rank")
        return found.join(full, "qid", "left_semi").unionByName(again)

    def _whole(self, index: Index, snap: Snapshot, removed: list[int], where: Column | None, hold: bool) -> tuple[DataFrame, DataFrame | None]:
        """(places, rows) of all that the shards reach. With hold they are found and read once for an index and version;
        without, and under a filter, there are no rows."""
        key = (index.path, snap.version, where is None)
        if not hold or self._held is None or self._held[0] != key:
            places = self._kept(self.reached(index, removed))
            if not hold:
                return places, None
            self._held = key, places, self._kept(self.rows_at(index, snap, places)) if where is None else None
        return self._held[1:]

    def _kept(self, df: DataFrame) -> DataFrame:
        """df written beside the table, where every executor sees it, and read again; gone when the process ends."""
        path = f"{self.table.log.root}/scratch/{uuid.uuid4().hex}"
        df.write.parquet(path)
        store.delete_at_exit(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def _rows_where(self, snap: Snapshot, column: str, files: list, where: Column | None) -> DataFrame:
        rows = self.table.read_files(snap, [f.path for f in files])
        rows = rows if where is None else rows.filter(where)
        return rows.select(F.col(snap.id_column).cast("long").alias("vec_id"), F.col(column).alias("v"))

    # ------------------------------------------------------------ centroid tier
    def search_centroid(self, name: str, q, k: int, nprobe: int | None = None, version: int | None = None, where: Column | None = None) -> DataFrame:
        """vec_id, distance of one query: the nprobe nearest files are scanned; without nprobe, files in order of their
        bound until no bound is below the kth distance (exact), in batches that double. Files that the index does not
        cover have no bound and are scanned in either case."""
        snap, index = self.table.log.at(version), self.open(name, version)
        files = {f.file_no: f for f in self.table.log.files(snap)}
        added = [n for n, f in files.items() if f.path not in index.covered]
        probe = self.centroids(name, version)
        rows = lambda numbers: self._rows_where(snap, index.column, [files[n] for n in numbers], where)
        from .exact import exact_topk

        if nprobe is not None:
            chosen = [n for n in probe.closest(q, len(probe.file_no)) if n in files][:nprobe] + added
            self.last_metrics = {"files": len(chosen), "bytes": sum(files[n].bytes for n in chosen)}
            return exact_topk(rows(chosen), q, k, metric=index.options.metric).select("vec_id", "distance")
        order, done, step, worst = [(b, n) for b, n in probe.by_bound(q) if n in files], 0, 1, float("inf")
        best: list[tuple[float, int]] = []
        if added:
            best = [(r["distance"], r["vec_id"]) for r in exact_topk(rows(added), q, k, metric=index.options.metric).collect()]
            worst = best[-1][0] if best else worst
        while done < len(order) and (len(best) < k or order[done][0] <= worst):
            batch = [n for b, n in order[done : done + step] if len(best) < k or b <= worst]
            best = sorted(best + [(r["distance"], r["vec_id"]) for r in exact_topk(rows(batch), q, k, metric=index.options.metric).collect()])[:k]
            worst = best[-1][0] if best else worst
            done, step = done + step, step * 2
        self.last_metrics = {"files": min(done, len(order)) + len(added)}
        return self.spark.createDataFrame([(i, d) for d, i in best], "vec_id long, distance double")

    def search_centroid_batch(self, name: str, queries: DataFrame, k: int, nprobe: int, version: int | None = None) -> DataFrame:
        """qid, vec_id, distance, rank of a set of queries: each looks at the rows of its nprobe nearest files and of the
        files that the index does not cover. One pass over the files that any query needs."""
        snap, index = self.table.log.at(version), self.open(name, version)
        files = {f.file_no: f for f in self.table.log.files(snap)}
        pairs = self.probed_files(name, queries, nprobe, version).select("qid", "file_no").toArrow()
        wanted = set(pairs.column("file_no").unique().to_pylist())
        rows = self._rows(snap, index.column, [f.path for n, f in sorted(files.items()) if n in wanted])
        return files_batch_topk(rows, queries, pairs, k, index.options.metric).select("qid", "vec_id", "distance", "rank")

    def probed_files(self, name: str, queries: DataFrame, nprobe: int, version: int | None = None) -> DataFrame:
        """qid, qv, file_no: the files that `search_centroid_batch` scans for each query."""
        snap, index = self.table.log.at(version), self.open(name, version)
        there = {f.file_no: f for f in self.table.log.files(snap)}
        added = [n for n, f in there.items() if f.path not in index.covered]
        probe = self.centroids(name, version)
        near = np.isin(probe.file_no, list(there))
        number, centre, metric = probe.file_no[near], probe.centroid[near], index.options.metric

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                far = D.block_distances(centre, vectors_of(b.column(1)).astype(np.float64), metric)
                order = np.argsort(far, axis=1, kind="stable")[:, :nprobe]
                chosen = np.concatenate([number[order], np.tile(np.array(added, np.int64), (b.num_rows, 1))], 1)
                at = np.repeat(np.arange(b.num_rows), chosen.shape[1])
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)).cast(pa.list_(pa.float64())), pa.array(chosen.ravel(), pa.int32())], ["qid", "qv", "file_no"])

        return queries.select(F.col("qid").cast("long"), F.col("qv").cast("array<double>")).mapInArrow(run, "qid long, qv array<double>, file_no int")

    def search_range(self, name: str, q, threshold: float, version: int | None = None) -> DataFrame:
        """All rows at most `threshold` away: files pruned by centroid and radius, the rest scanned."""
        from .exact import exact_range

        snap, index = self.table.log.at(version), self.open(name, version)
        files = {f.file_no: f for f in self.table.log.files(snap)}
        covered = set(index.covered)
        chosen = [files[n] for n in self.centroids(name, version).within(q, threshold) if n in files]
        chosen += [f for f in files.values() if f.path not in covered]
        self.last_metrics = {"files": len(chosen), "bytes": sum(f.bytes for f in chosen)}
        return exact_range(self._rows_where(snap, index.column, chosen, None), q, threshold, metric=index.options.metric).select("vec_id", "distance")

    # ------------------------------------------------------------ refresh
    def changes(self, name: str) -> list[tuple[str, int]]:
        index, snap = self.open(name), self.table.log.current()
        now = {f.path: f.file_no for f in self.table.log.files(snap)}
        out = [("EXISTING" if p in now else "DELETED", n) for p, n in index.covered.items()]
        return out + [("ADDED", n) for p, n in now.items() if p not in index.covered]

    def rebuild_shard(self, name: str, number: int) -> Index:
        """Brings the index to the current snapshot and builds one shard anew from its live rows, without tombstones."""
        return self.refresh(name, rebuild=frozenset([number]))

    def maintain(self, name: str, limit: float) -> Index:
        """Rebuilds the shards whose share of dead rows is above the limit."""
        return self.refresh(name, rebuild=frozenset(s["shard"] for s in self.open(name).shards if s["dead"] > limit * s["n"]))

    def refresh(self, name: str, rebuild_all: bool = False, rebuild: frozenset[int] = frozenset()) -> Index:
        """Brings the index to the current snapshot; only shards that the change touches, and those of `rebuild`, are
        rewritten. Which shards gain rows is found from the added files alone."""
        index, snap = self.open(name), self.table.log.current()
        now = {f.path: f for f in self.table.log.files(snap)}
        if rebuild_all or not index.shards:
            fresh = self._build(name, index.column, index.options, snap)
            return fresh
        added = {f.file_no for p, f in now.items() if p not in index.covered}
        removed = sorted(n for p, n in index.covered.items() if p not in now)
        if unknown := rebuild - {s["shard"] for s in index.shards}:
            raise BadParameter(f"no shards {sorted(unknown)}")
        if not added and not removed and not rebuild:
            return index

        def rows_of(paths: list[str]) -> DataFrame:
            rows = self._rows(snap, index.column, paths).filter(D.is_valid_vector(F.col("v"), index.dim))
            return rows.withColumn("shard", index.shard_of(F.col("v"), F.col("vec_id"), F.col("file_no")))

        old = {s["shard"]: s for s in index.shards}
        gets = {r[0] for r in rows_of([p for p in now if p not in index.covered]).select("shard").distinct().collect()} if added else set()
        loses = {s["shard"] for s in index.shards if removed and np.isin(cached_shard(f"{index.root}/{s['path']}", s["blob"]).files, removed).any()} if len(index.shards) <= 64 else self._losing(index, removed)
        touched = sorted(gets | loses | rebuild)
        o, root, base = index.options, index.root, snap.version
        where = {s: (old[s]["path"], old[s]["blob"]) for s in touched if s in old}

        def patch(number: int, table: pa.Table | None) -> pa.Table:
            begun = time.time()
            x = vectors_of(table.column("v").combine_chunks()) if table is not None and table.num_rows else np.zeros((0, index.dim))
            ids, files, offs, fresh = (np.asarray(table.column(c)) if table is not None else np.zeros(0, np.int64) for c in ("vec_id", "file_no", "row_offset", "fresh"))
            if number in where:
                shard = cached_shard(f"{root}/{where[number][0]}", where[number][1])
                shard = replace(shard, dead=(shard.dead if len(shard.dead) else np.zeros(shard.n, bool)) | np.isin(shard.files, removed))
                visits = dists = 0
                if fresh.any() and number not in rebuild:
                    own = Q.pq_decode(shard.codes, shard.codebook).astype(np.float64) if shard.n else np.zeros((0, index.dim))
                    order = np.argsort(ids[~fresh])
                    at = np.searchsorted(ids[~fresh][order], shard.ids)
                    known = (at < len(order)) & ~shard.dead
                    known[known] = ids[~fresh][order][at[known]] == shard.ids[known]
                    own[known] = _prepared(x[~fresh], o.metric)[order][at[known]]
                    pick = np.flatnonzero(fresh)[np.argsort(ids[fresh])]
                    new = _prepared(x[pick], o.metric)
                    full, tbl, info = G.insert(own, neighbour_table(shard), shard.entries, new, o.graph())
                    visits, dists = info["visits"], info["distances"]
                    shard = replace(shard, ids=np.concatenate([shard.ids, ids[pick]]), files=np.concatenate([shard.files, files[pick]]), offsets=np.concatenate([shard.offsets, offs[pick]]), neighbours=G.as_lists(tbl), entries=info["entries"], codes=np.concatenate([shard.codes, Q.pq_encode(new, shard.codebook)]), dead=np.concatenate([shard.dead, np.zeros(len(pick), bool)]), vectors=full.astype(np.float32) if o.keep_vectors else None)
                if number not in rebuild and (shard.n == 0 or shard.dead.mean() <= o.tombstone_limit):
                    path, size = _put_shard(root, shard, o, base, number)
                    return _result(number, path, shard.n, int(shard.dead.sum()), size, time.time() - begun, 0.0, False, visits, dists)
                book = shard.codebook
            else:
                book = None
            order = np.argsort(ids)
            shard = _build_shard(ids[order], files[order], offs[order], x[order], o, book, o.seed + number)
            path, size = _put_shard(root, shard, o, base, number)
            return _result(number, path, shard.n, 0, size, time.time() - begun, 0.0, True)

        # a row without a file for each touched shard, as one may only lose rows
        keys = self.spark.createDataFrame([(t,) for t in touched], "shard int")

        def run(table: pa.Table) -> pa.Table:
            own = table.filter(table.column("file_no").is_valid())
            return patch(table.column("shard")[0].as_py(), own if own.num_rows else None)

        # under file sharding the other files hold no row of these shards
        paths = [p for p, f in now.items() if touched and (o.sharding != "file" or f.file_no % o.num_shards in touched)]
        data = rows_of(paths).filter(F.col("shard").isin(touched)).withColumn("fresh", F.col("file_no").isin(sorted(added)) if added else F.lit(False))
        self.last_results = [r.asDict() for r in each_shard(data.unionByName(keys, allowMissingColumns=True), touched, run, _RESULT).collect()]
        new = {r["shard"]: {"shard": r["shard"], "path": r["path"], "n": r["n"], "dead": r["dead"], "bytes": r["bytes"], "blob": 0} for r in self.last_results}
        index.shards = [{**old, **new}[s] for s in sorted({**old, **new})]
        known, index.covered = index.covered, {p: f.file_no for p, f in now.items()}
        return self._commit(index, snap, known)

    def _losing(self, index: Index, removed: list[int]) -> set[int]:
        if not removed:
            return set()
        root = index.root
        there = self.spark.createDataFrame([(s["shard"], s["path"], s["blob"]) for s in index.shards], "shard int, path string, blob int").repartition(len(index.shards))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                hit = [s for s, p, k in zip(*(b.column(i).to_pylist() for i in range(3))) if np.isin(cached_shard(f"{root}/{p}", k).files, removed).any()]
                yield pa.RecordBatch.from_pydict({"shard": pa.array(hit, pa.int32())})

        return {r[0] for r in there.mapInArrow(run, "shard int").collect()}

    def tombstones(self, name: str) -> DataFrame:
        """shard, n, dead, ratio by the routing blob."""
        return self.spark.createDataFrame([(s["shard"], s["n"], s["dead"], s["dead"] / s["n"] if s["n"] else 0.0) for s in self.open(name).shards], "shard int, n long, dead long, ratio double")

    def edges(self, name: str) -> DataFrame:
        """shard, src, dst of every edge, by id."""
        index = self.open(name)
        root = index.root
        there = self.spark.createDataFrame([(s["shard"], s["path"], s["blob"]) for s in index.shards], "shard int, path string, blob int")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for s, p, k in zip(*(b.column(i).to_pylist() for i in range(3))):
                    shard = cached_shard(f"{root}/{p}", k)
                    src = np.repeat(shard.ids, [len(v) for v in shard.neighbours])
                    dst = shard.ids[np.concatenate(shard.neighbours)] if len(src) else src
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(src), s), pa.int32()), pa.array(src), pa.array(dst)], ["shard", "src", "dst"])

        return there.mapInArrow(run, "shard int, src long, dst long")


def group_starts(meta: pq.FileMetaData) -> np.ndarray:
    """First row of each row group, and the number of rows at the end."""
    return np.concatenate([[0], np.cumsum([meta.row_group(g).num_rows for g in range(meta.num_row_groups)])]).astype(np.int64)


def group_masks(meta: pq.FileMetaData, rows: np.ndarray) -> list[tuple[int, np.ndarray]]:
    """(row group, places within it) of rows, given by their place in the file in ascending order."""
    starts = group_starts(meta)
    rows = rows[rows < starts[-1]]
    group = np.searchsorted(starts, rows, "right") - 1
    return [(int(g), rows[group == g] - starts[g]) for g in np.unique(group)]


# ---------------------------------------------------------------- shards held by a worker
_HELD: dict[tuple[str, int], blobs.Shard] = {}
_TABLES: dict[int, np.ndarray] = {}
HELD_BYTES = 1 << 30
HITS = {"hit": 0, "miss": 0}


def cached_shard(path: str, blob: int) -> blobs.Shard:
    """Objects never change, so the path is the key; the oldest go when the sum of blob bytes passes HELD_BYTES."""
    key = (path, blob)
    if key in _HELD:
        HITS["hit"] += 1
        return _HELD[key]
    HITS["miss"] += 1
    meta = read_footer(path).blobs[blob]
    shard = blobs.decode_shard(read_blob(path, meta))
    shard.params["_bytes"] = meta.raw_length
    while _HELD and sum(s.params["_bytes"] for s in _HELD.values()) + meta.raw_length > HELD_BYTES:
        _HELD.pop(next(iter(_HELD)))
    _HELD[key] = shard
    return shard


def layers_of(shard: blobs.Shard, o: IndexOptions) -> list[tuple[np.ndarray, np.ndarray]]:
    """The layered graph over a shard's vectors, made once for a held shard."""
    if not hasattr(shard, "layers"):
        shard.layers = G.build_hnsw(shard.vectors, o.R // 2 or 1, o.L)
    return shard.layers


_CENTROIDS: dict[str, dict] = {}
CENTROID_BYTES = 256 << 20


def cached_centroids(path: str) -> dict:
    """Decoded file centroids of a root container, by its path as containers never change; the oldest go when the sum of
    vector bytes passes CENTROID_BYTES."""
    if path in _CENTROIDS:
        HITS["hit"] += 1
        return _CENTROIDS[path]
    HITS["miss"] += 1
    c = blobs.decode_centroids(read_blob(path, read_footer(path).first(CENTROIDS)))
    while _CENTROIDS and sum(x["centroid"].nbytes for x in _CENTROIDS.values()) + c["centroid"].nbytes > CENTROID_BYTES:
        _CENTROIDS.pop(next(iter(_CENTROIDS)))
    _CENTROIDS[path] = c
    return c


def neighbour_table(shard: blobs.Shard) -> np.ndarray:
    return G._as_table(shard.neighbours, max([shard.params.get("R", 1), *(len(v) for v in shard.neighbours)]) if shard.n else 1)


def manifest_diff(table: Table, old: int, new: int) -> list[tuple[str, int]]:
    log = table.log
    return [(s, f.file_no) for s, f in diff(log.files(log.snapshot(old)), log.files(log.snapshot(new)))]


def routing_json(index: Index) -> str:
    return json.dumps({"shards": index.shards, "covered": index.covered}, sort_keys=True)
