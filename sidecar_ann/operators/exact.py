"""Exact search: the baseline without an index, and the distances of every rerank."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import distance as D

#: Bytes of query vectors that one pass over the rows carries along.
QUERY_BYTES = 32 << 20


def exact_topk(rows: DataFrame, q, k: int, vector: str = "v", key: str = "vec_id", metric: str = "l2") -> DataFrame:
    """The k nearest rows to one literal vector; native, ends in a top-k operator. Null and zero-norm (cosine) vectors
    have no distance and are left out; ties go to the smaller id."""
    d = rows.withColumn("distance", D.metric(metric)(F.col(vector), D.literal(q))).filter(F.col("distance").isNotNull())
    return d.orderBy("distance", key).limit(k)


def exact_range(rows: DataFrame, q, threshold: float, vector: str = "v", metric: str = "l2", strict: bool = False) -> DataFrame:
    d = rows.withColumn("distance", D.metric(metric)(F.col(vector), D.literal(q)))
    return d.filter(F.col("distance") < threshold if strict else F.col("distance") <= threshold)


def collect_queries(queries: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(qid, vectors) of a stated query set (qid, qv), in qid order."""
    got = sorted((r["qid"], r["qv"]) for r in queries.select("qid", "qv").collect())
    vectors = np.array([g[1] for g in got], np.float64) if got else np.zeros((0, 1))
    return np.array([g[0] for g in got], np.int64), vectors.reshape(len(got), -1) if got else vectors


def exact_batch_topk(rows: DataFrame, queries: DataFrame, k: int, vector: str = "v", key: str = "vec_id", metric: str = "l2") -> DataFrame:
    """qid, key, distance, rank for a set of queries: block kernel over batches of rows; a task keeps k rows a query, so
    what is shuffled does not grow with the rows. Queries go along in blocks of QUERY_BYTES, with the rows kept for them.
    Of equal distances the smaller ids come first, however many there are."""
    qid, qs = collect_queries(queries)
    each = max(1, QUERY_BYTES // max(1, 8 * qs.shape[1], 16 * k))
    parts = [_scan(rows, qid[s : s + each], qs[s : s + each], k, vector, key, metric) for s in range(0, max(1, len(qid)), each)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return top_per_query(out, k, key)


def top_per_query(candidates: DataFrame, k: int, key: str = "vec_id") -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("qid").orderBy("distance", key))
    return candidates.withColumn("rank", rank).filter(F.col("rank") <= k)


def files_batch_topk(rows: DataFrame, queries: DataFrame, wanted: pa.Table, k: int, metric: str = "l2") -> DataFrame:
    """qid, vec_id, distance, rank among the rows (vec_id, v, file_no) of each query's own files, which wanted (qid, file_no)
    names: the block kernel, with the queries of a file for its rows."""
    qid, qs = collect_queries(queries)
    asked, number = np.asarray(wanted.column("qid")), np.asarray(wanted.column("file_no"))
    each = max(1, QUERY_BYTES // max(1, 8 * qs.shape[1], 16 * k))
    out = None
    for s in range(0, max(1, len(qid)), each):
        own = qid[s : s + each]
        mine = np.isin(asked, own)
        place, file = np.searchsorted(own, asked[mine]), number[mine]
        part = _scan(rows, own, qs[s : s + each], k, "v", "vec_id", metric, {int(f): np.sort(place[file == f]) for f in np.unique(file)})
        out = part if out is None else out.unionByName(part)
    return top_per_query(out, k)


def _scan(rows: DataFrame, qid: np.ndarray, qs: np.ndarray, k: int, vector: str, key: str, metric: str, files: dict[int, np.ndarray] | None = None) -> DataFrame:
    """files: places of the queries that look at each file_no; without, all look at all rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = np.full((len(qid), k), np.iinfo(np.int64).max)
        far = np.full((len(qid), k), np.inf)
        for batch in batches:
            for s in range(0, batch.num_rows, 4096):
                part = batch.slice(s, 4096)
                x, own = vectors_of(part.column(1)), np.asarray(part.column(0))
                if not len(x) or not k:
                    continue
                for at, who in _looks(part, files, len(qid)):
                    for b in range(0, len(who), 256):
                        to = who[b : b + 256]
                        ids[to], far[to] = _nearer(x[at], own[at], qs[to], ids[to], far[to], metric)
        keep = np.isfinite(far).ravel()
        if keep.any():
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(qid, k)[keep]), pa.array(ids.ravel()[keep]), pa.array(far.ravel()[keep])], ["qid", key, "distance"])

    columns = [F.col(key).cast("long"), vector] + ([] if files is None else ["file_no"])
    return rows.select(*columns).filter(F.col(vector).isNotNull()).mapInArrow(run, f"qid long, {key} long, distance double")


def _looks(part: pa.RecordBatch, files: dict[int, np.ndarray] | None, queries: int) -> list[tuple[slice | np.ndarray, np.ndarray]]:
    """(rows, places of the queries that look at them)."""
    if files is None:
        return [(slice(None), np.arange(queries))]
    number = np.asarray(part.column(2))
    return [(number == f, files[int(f)]) for f in np.unique(number) if int(f) in files]


def _nearer(x: np.ndarray, own: np.ndarray, q: np.ndarray, ids: np.ndarray, far: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray]:
    """The k places (ids, far) of each query after the rows (own, x). The product form only picks the rows that can get a
    place, with all that are as near as the last one up to its rounding; these are measured exactly."""
    k = ids.shape[1]
    form = "l2sq" if metric == "l2" else metric
    coarse = D.block_distances(x, q, form)
    coarse[np.isnan(coarse)] = np.inf
    size = float(np.nanmax((x * x).sum(1), initial=0)) + (q * q).sum(1)
    slack = 1e-12 * (np.ones(len(q)) if form == "cosine" else size)
    worst = far[:, -1] ** 2 if metric == "l2" else far[:, -1]
    if k < len(own):
        worst = np.minimum(worst, np.partition(coarse, k - 1, axis=1)[:, k - 1])
    r, c = np.nonzero((coarse <= (worst + slack)[:, None]) & np.isfinite(coarse))
    if not len(r):
        return ids, far
    d = np.concatenate([D.exact_distances(x[c[s : s + 32768]], q[r[s : s + 32768]], metric) for s in range(0, len(r), 32768)])
    r, i, d = np.concatenate([r, np.repeat(np.arange(len(q)), k)]), np.concatenate([own[c], ids.ravel()]), np.concatenate([d, far.ravel()])
    order = np.lexsort((i, np.where(np.isnan(d), np.inf, d), r))
    r = r[order]
    first = order[np.arange(len(r)) - np.searchsorted(r, r) < k]
    return i[first].reshape(len(q), k), np.where(np.isnan(d[first]), np.inf, d[first]).reshape(len(q), k)


def exact_batch_count(rows: DataFrame, queries: DataFrame, threshold: float, vector: str = "v", metric: str = "l2") -> DataFrame:
    """qid, near: rows nearer than `threshold` to each query that has one. A task sends on a count a query, no pairs; the
    block kernel only picks what is then measured exactly."""
    qid, qs = collect_queries(queries)
    each = max(1, QUERY_BYTES // max(1, 8 * qs.shape[1]))

    def scan(ids: np.ndarray, own: np.ndarray) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            n = np.zeros(len(ids), np.int64)
            for batch in batches:
                for s in range(0, batch.num_rows, 4096):
                    x = vectors_of(batch.slice(s, 4096).column(0))
                    for b in range(0, len(ids), 1024):
                        r, c = np.nonzero(D.block_distances(x, own[b : b + 1024], metric) < threshold + 1e-6)
                        hit = D.exact_distances(x[c], own[b + r], metric) < threshold
                        n[b : b + 1024] += np.bincount(r[hit], minlength=len(own[b : b + 1024]))
            yield pa.RecordBatch.from_arrays([pa.array(ids[n > 0]), pa.array(n[n > 0])], ["qid", "near"])

        return rows.select(vector).filter(F.col(vector).isNotNull()).mapInArrow(run, "qid long, near long")

    out = scan(qid[:each], qs[:each])
    for s in range(each, len(qid), each):
        out = out.unionByName(scan(qid[s : s + each], qs[s : s + each]))
    return out.groupBy("qid").agg(F.sum("near").alias("near"))


def vectors_of(column: pa.Array) -> np.ndarray:
    """A list column of equal lengths as a matrix."""
    flat = column.flatten()
    return np.asarray(flat, dtype=np.float64).reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def similarity_join(left: DataFrame, right: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """k nearest right rows (vec_id, v) of each left row (qid, qv)."""
    return exact_batch_topk(right, left, k, metric=metric)


def where_of(condition: Column | None, df: DataFrame) -> DataFrame:
    return df if condition is None else df.filter(condition)
