"""What the text operators share: scratch tables, Arrow batches as numpy views, hashing, ordered parts."""

from __future__ import annotations

import atexit
import ctypes
import functools
import sys
import tempfile
import types
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_left: list = []


# ---------------------------------------------------------------- tables
def documents(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions(spark: SparkSession) -> int:
    """Shuffle width of the session; the unit in which every operator sizes its parts and buckets."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def scratch_root(spark: SparkSession) -> str:
    """The shared folder named by spark.checkpoint.dir. Where none is named, a session on one machine gets a temporary
    folder; a cluster, whose executors would not see it, is refused."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = _own_root()
    return root.rstrip("/")


@functools.cache
def _own_root() -> str:
    return tempfile.mkdtemp(prefix="scratch-")


def stage(df: DataFrame, label: str) -> DataFrame:
    """Writes df as Parquet in the shared scratch folder and rereads it: lineage ends here, and a lost executor
    costs no more than the reader's own task. The folder goes when the process ends."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _left.append((spark, path))
    give_back()
    return spark.read.schema(df.schema).parquet(path)


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _clean() -> None:
    for spark, path in _left:
        try:
            _remove(spark, path)
        except Exception:  # the session is over: the folder belongs to the cluster's own clean-up
            return


def worker_cache(name: str) -> dict:
    """A dict that lives in the Python worker until a task of another operator begins there (`own_worker`)."""
    return _holder().__dict__.setdefault("caches", {}).setdefault(name, {})


def _holder() -> types.ModuleType:
    return sys.modules.setdefault("_sidecar_worker_cache", types.ModuleType("_sidecar_worker_cache"))


def own_worker(owner: str) -> None:
    """Workers are reused: what another operator's tasks left in this one goes before a task of `owner` begins."""
    held = _holder().__dict__
    if held.get("owner") != owner:
        held.update(owner=owner, caches={})
        give_back()


def give_back() -> None:
    """Memory that is free in this process goes back to the machine; the allocators keep it otherwise."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # only some C libraries have it
    if trim is not None:
        trim(0)


def per_batch(df: DataFrame, work: Callable, schema: str) -> DataFrame:
    """mapInArrow with work(batch) -> RecordBatch, an iterator of them, or None."""

    owner = work.__module__

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_worker(owner)
        for batch in batches:
            out = work(batch)
            if out is None:
                continue
            if isinstance(out, pa.RecordBatch):
                yield out
            else:
                yield from out
        give_back()

    return df.mapInArrow(run, schema)


# ---------------------------------------------------------------- texts as bytes
def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of all texts joined, offsets). A null text is empty."""
    if column.null_count:
        column = pc.fill_null(column, pa.scalar("", column.type) if not pa.types.is_binary(column.type) else b"")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offs, data = column.buffers()
    off = np.frombuffer(offs, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if data is None:
        return np.zeros(0, np.uint8), off - off[0]
    return np.frombuffer(data, np.uint8)[off[0] : off[-1]], off - off[0]


def pieces(batch: pa.RecordBatch, column: str = "text", most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of about `most` bytes of text each, whole rows only: what bounds a worker's memory."""
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0))
    ends = np.cumsum(sizes)
    at = 0
    while at < len(sizes):
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + most, "right")))
        yield batch.slice(at, to - at)
        at = to


MIX = np.uint64(0x9E3779B97F4A7C15)
MIX2 = np.uint64(0xC2B2AE3D27D4EB4F)


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalising bijection of 64 bits (splitmix constants are public)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: One random odd-ish word for each byte value.
BYTE_CODES = mix64(np.arange(1, 257, dtype=np.uint64) * MIX)

_POWER = np.uint64(0x5851F42D4C957F2D)  # odd, so that it has an inverse modulo 2**64
_INVERSE = np.uint64(pow(int(_POWER), -1, 1 << 64))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    held = worker_cache("powers")
    if held.get("n", 0) < n:
        m = max(n, 1 << 16)
        up, down = np.full(m, _POWER), np.full(m, _INVERSE)
        up[0] = down[0] = 1
        with np.errstate(over="ignore"):
            held.update(n=m, up=np.multiply.accumulate(up), down=np.multiply.accumulate(down))
    return held["up"][:n], held["down"][:n]


def span_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit content hash of each byte span, equal for equal spans wherever they stand."""
    up, down = _powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(BYTE_CODES[data] * up[: len(data)], out=total[1:])
    return mix64((total[end] - total[start]) * down[start] + (end - start).astype(np.uint64) * MIX2)


_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True


def words(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and row of each maximal run of bytes other than space and \\t..\\r; runs never cross rows."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, none
    solid = ~_SPACE[data]
    begins = solid.copy()
    begins[1:] &= ~solid[:-1]
    inner = off[1:-1]
    inner = inner[inner < len(data)]
    begins[inner] = solid[inner]
    ends = solid.copy()
    ends[:-1] &= ~solid[1:]
    cut = off[1:-1]
    cut = cut[cut > 0] - 1
    ends[cut] = solid[cut]
    start, end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    return start, end, np.searchsorted(off, start, "right") - 1


def crc32_of_text(column: Column) -> Column:
    return F.crc32(column.cast("string").cast("binary"))
