"""Quality classifier: random-indexing word vectors pooled per document, and a two-layer network with a calibrated
temperature.

Every word, hashed to one of SLOTS slots, and every word shape ("Aa", "A!", "a%": character classes, runs collapsed) has
a sparse random index vector, which only its hash decides. Its word vector is the sum of the index vectors of its
neighbours (two to each side) over all documents: sums of integers, so any order of tasks gives the same. A document is
the mean and spread of the vectors of its words and of its shapes, with its length and its shares of distinct words and
shapes. The network (one hidden layer, numpy) is fitted on at most LABELLED rows with labels, drawn in hash order from
the rows that may be learned from; a fifth of them sets the temperature and when to stop.

Null and empty texts have vectors of zeros and still get a score. Repeated rows repeat; of repeated labels the smallest
counts. Without labels to learn from (none, or of one class), every score is the share of label 1 (0.5 if none).
Columns other than doc_id and text are not read."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import MIX, crc32_of_text, give_back, mix64, own_worker, per_batch, pieces, span_hashes, text_bytes, words

SLOTS, DIMS, NONZERO, WINDOW = 1 << 13, 32, 4, 2
#: Most labelled rows that a network is fitted on.
LABELLED = 20_000
HIDDEN, ROUNDS = 32, 400
#: Tables of sums that are added up in one group on the first level, as tasks over FAN; on the second, at most FAN.
FAN = 256

#: Character classes of bytes: digits 9, capitals A, small letters and bytes of longer characters a, others themselves.
_CLASS = np.arange(256, dtype=np.uint8)
_CLASS[48:58] = 57
_CLASS[65:91] = 65
_CLASS[97:123] = 97
_CLASS[128:] = 97


def index_vectors() -> tuple[np.ndarray, np.ndarray]:
    """(dimension, sign) of the NONZERO entries of each slot's index vector."""
    draw = mix64(np.arange(SLOTS * NONZERO, dtype=np.uint64) * MIX + np.uint64(7)).reshape(SLOTS, NONZERO)
    return (draw >> np.uint64(8)) % np.uint64(DIMS), np.where(draw & np.uint64(1), 1, -1)


def units(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, word slot and shape slot of each word."""
    start, end, row = words(data, off)
    if not len(start):
        return row, row, row
    kind = _CLASS[data]
    new = np.ones(len(kind), bool)
    new[1:] = kind[1:] != kind[:-1]
    new[start] = True
    at = np.cumsum(new)  # collapsed characters up to each place
    shape = span_hashes(kind[new], at[start] - 1, at[end - 1])
    word = span_hashes(data, start, end)
    return row, (word % np.uint64(SLOTS)).astype(np.int64), (mix64(shape + np.uint64(1)) % np.uint64(SLOTS)).astype(np.int64)


def _context_sums(row: np.ndarray, slot: np.ndarray, table: np.ndarray, dims: np.ndarray, signs: np.ndarray) -> None:
    for step in range(1, WINDOW + 1):
        near = np.flatnonzero(row[step:] == row[:-step])
        for a, b in ((near, near + step), (near + step, near)):
            base, other = slot[a] * DIMS, slot[b]
            for k in range(NONZERO):
                table += np.bincount(base + dims[other, k], signs[other, k], SLOTS * DIMS).astype(np.int64)


def word_vectors(docs: DataFrame, blocks: int = 16) -> np.ndarray:
    """(SLOTS, DIMS) unit vectors, from all documents. What a task sends on is bounded by the table of sums."""
    each = SLOTS * DIMS // blocks
    schema = "part int, block int, data binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_worker(__name__)
        dims, signs = index_vectors()
        dims = dims.astype(np.int64)
        signs = signs.astype(float)
        table = np.zeros(SLOTS * DIMS, np.int64)
        for batch in batches:
            for part in pieces(batch, most=512 << 10):
                row, word, shape = units(*text_bytes(part.column("text")))
                for slot in (word, shape):
                    _context_sums(row, slot, table, dims, signs)
        part = TaskContext.get().partitionId() % FAN
        yield pa.RecordBatch.from_pydict({"part": pa.array([part] * blocks, pa.int32()), "block": pa.array(range(blocks), pa.int32()), "data": pa.array([zlib.compress(table[i * each : (i + 1) * each].tobytes(), 1) for i in range(blocks)], pa.binary())})

    def total(table: pa.Table) -> pa.Table:
        data = np.zeros(each, np.int64)
        for x in table.column("data"):
            data += np.frombuffer(zlib.decompress(x.as_py()), np.int64)
        return pa.table({"part": pa.array([0], pa.int32()), "block": table.column("block")[:1], "data": pa.array([zlib.compress(data.tobytes(), 1)], pa.binary())})

    sums = docs.select("text").mapInArrow(run, schema)
    for keys in (["part", "block"], ["block"]):  # a tree: no group holds a table of every task
        sums = sums.groupBy(*keys).applyInArrow(total, schema)
    table = np.zeros(SLOTS * DIMS)
    for r in sums.collect():
        table[r["block"] * each : (r["block"] + 1) * each] = np.frombuffer(zlib.decompress(bytes(r["data"])), np.int64)
    table = table.reshape(SLOTS, DIMS)
    table -= table.sum(0) / max(1.0, np.abs(table).sum()) * np.abs(table).sum(1, keepdims=True)  # the common direction
    norm = np.linalg.norm(table, axis=1, keepdims=True)
    return (table / np.where(norm > 0, norm, 1)).astype(np.float32)


FEATURES = 4 * DIMS + 4


def features(data: np.ndarray, off: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """(documents, FEATURES)."""
    n = len(off) - 1
    out = np.zeros((n, FEATURES), np.float32)
    row, word, shape = units(data, off)
    count = np.bincount(row, minlength=n)
    have = np.flatnonzero(count)
    if len(have):
        first = np.cumsum(count)[have] - count[have]
        for k, slot in enumerate((word, shape)):
            held = vectors[slot]
            mean = np.add.reduceat(held, first, axis=0) / count[have, None]
            out[have, 2 * k * DIMS : (2 * k + 1) * DIMS] = mean
            np.multiply(held, held, out=held)
            square = np.add.reduceat(held, first, axis=0) / count[have, None]
            out[have, (2 * k + 1) * DIMS : (2 * k + 2) * DIMS] = np.sqrt(np.maximum(square - mean**2, 0))
            distinct = np.bincount(np.unique(row * SLOTS + slot) // SLOTS, minlength=n)
            out[have, 4 * DIMS + 2 + k] = np.log(distinct[have] / count[have])
    out[:, 4 * DIMS] = np.log1p(count)
    out[:, 4 * DIMS + 1] = np.log1p(np.diff(off)) - np.log1p(count)
    return out


class Network:
    """Two layers; `scores` are probabilities at the calibrated temperature."""

    def __init__(self, seed: int = 5):
        self.seed, self.share = seed, 0.5
        self.weights: list[np.ndarray] | None = None

    def _logits(self, x: np.ndarray) -> np.ndarray:
        w1, b1, w2, b2 = self.weights
        return np.tanh((x - self.center) / self.scale @ w1 + b1) @ w2 + b2

    def fit(self, x: np.ndarray, y: np.ndarray, check: np.ndarray) -> Network:
        """check: rows kept from the gradient, for stopping and temperature."""
        if len(y):
            self.share = float(y.mean())
        if len(y) < 4 or len(set(y.tolist())) < 2:
            return self
        x = x.astype(np.float64)
        if check.all() or not check.any() or len(set(y[~check].tolist())) < 2:
            check = np.zeros(len(y), bool)
        train = ~check
        self.center, self.scale = x[train].mean(0), x[train].std(0) + 1e-3
        rng = np.random.default_rng(self.seed)
        d = x.shape[1]
        w = [rng.normal(0, d**-0.5, (d, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, HIDDEN), np.zeros(1)]
        z, t = (x[train] - self.center) / self.scale, y[train].astype(float)
        held = check if check.any() else train
        m, v = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w]
        best, kept = np.inf, [a.copy() for a in w]
        step = 0
        size = min(len(t), 512)
        for _ in range(max(30, min(ROUNDS, 60_000 * 20 // len(t)))):
            order = rng.permutation(len(t))
            for s in range(0, len(t) - size + 1, size):
                b = order[s : s + size]
                h = np.tanh(z[b] @ w[0] + w[1])
                p = 1 / (1 + np.exp(-(h @ w[2] + w[3])))
                g = (p - t[b]) / len(b)
                back = g[:, None] * w[2] * (1 - h * h)
                grads = [z[b].T @ back + 1e-3 * w[0], back.sum(0), h.T @ g + 1e-3 * w[2], np.array([g.sum()])]
                step += 1
                for i, q in enumerate(grads):
                    m[i] = 0.9 * m[i] + 0.1 * q
                    v[i] = 0.999 * v[i] + 0.001 * q * q
                    w[i] -= 0.005 * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
            self.weights = w
            loss = _loss(self._logits(x[held]), y[held], 1.0)
            if loss < best:
                best, kept = loss, [a.copy() for a in w]
        self.weights = kept
        logits = self._logits(x[held])
        grid = np.exp(np.linspace(np.log(0.25), np.log(8), 200))
        self.temperature = float(grid[np.argmin([_loss(logits, y[held], g) for g in grid])])
        return self

    def scores(self, x: np.ndarray) -> np.ndarray:
        if self.weights is None:
            return np.full(len(x), self.share)
        return 1 / (1 + np.exp(-np.clip(self._logits(x.astype(np.float64)) / self.temperature, -60, 60)))


def _loss(logits: np.ndarray, y: np.ndarray, temperature: float) -> float:
    z = np.where(y == 1, logits, -logits) / temperature
    return float(np.mean(np.logaddexp(0, -z)))


def held_out(column) -> F.Column:
    """Rows that are never learned from: crc32 of the id as text, modulo 4, is 2."""
    return F.coalesce(crc32_of_text(column) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, vectors: np.ndarray, limit: int = LABELLED) -> Network:
    """Labels: doc_id, quality."""
    own = (
        labels.select("doc_id", F.col("quality").cast("int").alias("_y")).filter(F.col("doc_id").isNotNull() & F.col("_y").isin(0, 1) & ~held_out(F.col("doc_id")))
        .groupBy("doc_id").agg(F.min("_y").alias("_y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit)
    )
    rows = docs.select("doc_id", "text").join(F.broadcast(own), "doc_id")

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for part in pieces(batch, most=512 << 10):
            x = features(*text_bytes(part.column("text")), vectors)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("_y"), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "_y", "x"])

    one = per_batch(rows, work, "doc_id long, _y int, x binary").groupBy("doc_id").agg(F.min(F.struct("x", "_y")).alias("r"))  # of repeated ids one row
    got = sorted((r["doc_id"], bytes(r["r"]["x"]), r["r"]["_y"]) for r in one.collect())
    x = np.frombuffer(b"".join(g[1] for g in got), np.float32).reshape(-1, FEATURES)
    y = np.array([g[2] for g in got], np.int64)
    check = mix64(np.array([g[0] for g in got], np.int64).astype(np.uint64)) % np.uint64(5) == 0 if got else np.zeros(0, bool)
    del got
    network = Network().fit(x, y, check)
    give_back()
    return network


def score(docs: DataFrame, network: Network, vectors: np.ndarray, name: str = "score") -> DataFrame:
    """docs with a column of scores, which may not have the name of another column; every other column stays."""
    kept = docs.columns
    if name in kept:
        raise ValueError(f"{name} is a column of the documents; give another name for the scores")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for part in pieces(batch, most=512 << 10):
            s = network.scores(features(*text_bytes(part.column("text")), vectors))
            yield pa.RecordBatch.from_arrays([*(part.column(n) for n in kept), pa.array(s)], [*kept, name])

    return per_batch(docs, work, f"{schema}, `{name}` double")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    vectors = word_vectors(docs)
    return score(docs.select("doc_id", "text"), fit(docs, labels, vectors), vectors)
