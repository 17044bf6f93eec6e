"""Files of token ids in the fewest bits that hold the vocabulary, with block offsets for random access.

A file is a run of blocks of `block` ids, each id `bits` wide (least significant bit first, the last block short and
padded to a byte), then the index: offset of each block (u8), end of each document in ids (u8), doc_id of each document
(i8) and a flag for each null doc_id (u1), then a trailer of fixed size. Ids are written as they are made, so a writer
holds one block and the index only. Files are put under names of their own for each attempt and count only once their
row of the manifest is returned: a lost task leaves a file that nobody reads.

Ascending doc_id order: a range shuffle, then one file for each range; null ids come first, rows of equal id in text
order. Null and empty texts are documents of the end id alone. An empty table gives no files and no rows."""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import own_worker, partitions, pieces, scratch_root
from .tokens import ChunkEncoder, tokenizer_path

_TRAILER = struct.Struct("<4sHHIQQQ")  # magic, version, bits, ids a block, ids, documents, start of the index
_MAGIC = b"FWID"
BLOCK = 8192


def bits_for(vocabulary: int) -> int:
    return max(1, int(vocabulary - 1).bit_length())


def pack_bits(ids: np.ndarray, bits: int) -> bytes:
    if bits in (8, 16, 32):
        return ids.astype(f"<u{bits // 8}").tobytes()
    raw = np.ascontiguousarray(ids, "<u4").view(np.uint8).reshape(-1, 4)
    return np.packbits(np.unpackbits(raw, axis=1, bitorder="little")[:, :bits].reshape(-1), bitorder="little").tobytes()


def unpack_bits(data, n: int, bits: int) -> np.ndarray:
    if bits in (8, 16, 32):
        return np.frombuffer(data, f"<u{bits // 8}", n).astype("<u4")
    flat = np.unpackbits(np.frombuffer(data, np.uint8), count=n * bits, bitorder="little").reshape(n, bits)
    wide = np.zeros((n, 32), np.uint8)
    wide[:, :bits] = flat
    return np.packbits(wide, axis=1, bitorder="little").view("<u4").reshape(-1)


class IdWriter:
    def __init__(self, out, vocabulary: int, block: int = BLOCK):
        self.out, self.bits, self.block = out, bits_for(vocabulary), block
        self.held: list[bytes] = []
        self.held_ids = self.ids = self.at = 0
        self.offsets: list[int] = []
        self.ends: list[int] = []
        self.docs: list[int | None] = []

    def add(self, docs: list[int | None], ids: np.ndarray, ends: np.ndarray) -> None:
        """Documents with their ids joined; ends: where each document ends in them."""
        if len(ids) and int(ids.max()) >> self.bits:
            raise ValueError(f"an id needs more than {self.bits} bits")
        self.held.append(np.ascontiguousarray(ids, "<u4").tobytes())
        self.held_ids += len(ids)
        self.ends += (ends + self.ids).tolist()
        self.ids += len(ids)
        self.docs += docs
        if self.held_ids >= self.block * 16:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        ids = np.frombuffer(b"".join(self.held), "<u4")
        whole = len(ids) if last else len(ids) // self.block * self.block
        for s in range(0, whole, self.block):
            self.offsets.append(self.at)
            self.at += self.out.write(packed := pack_bits(ids[s : min(s + self.block, whole)], self.bits)) or len(packed)
        self.held, self.held_ids = [ids[whole:].tobytes()], len(ids) - whole

    def close(self) -> None:
        self._flush(True)
        index = np.array(self.offsets, "<u8").tobytes() + np.array(self.ends, "<u8").tobytes()
        index += np.array([d or 0 for d in self.docs], "<i8").tobytes() + np.array([d is None for d in self.docs], np.uint8).tobytes()
        self.out.write(index + _TRAILER.pack(_MAGIC, 1, self.bits, self.block, self.ids, len(self.docs), self.at))


class IdReader:
    """Random access to the ids of a file: only the blocks that a range touches are read."""

    def __init__(self, source):
        self.f = source
        size = source.size()
        magic, version, self.bits, self.block, self.n_ids, self.n_docs, index = _TRAILER.unpack(source.read_at(_TRAILER.size, size - _TRAILER.size))
        if magic != _MAGIC or version != 1:
            raise ValueError("not a file of packed ids")
        raw = source.read_at(size - _TRAILER.size - index, index)
        blocks = -(-self.n_ids // self.block)
        self.offsets = np.append(np.frombuffer(raw, "<u8", blocks), np.uint64(index)).astype(np.int64)
        self.ends = np.frombuffer(raw, "<u8", self.n_docs, 8 * blocks).astype(np.int64)
        self.doc_ids = np.frombuffer(raw, "<i8", self.n_docs, 8 * (blocks + self.n_docs))
        self.no_id = np.frombuffer(raw, np.uint8, self.n_docs, 8 * (blocks + 2 * self.n_docs)).astype(bool)

    def ids(self, start: int, stop: int) -> np.ndarray:
        if stop <= start:
            return np.zeros(0, "<u4")
        b0, b1 = start // self.block, (stop - 1) // self.block + 1
        raw = self.f.read_at(int(self.offsets[b1] - self.offsets[b0]), int(self.offsets[b0]))
        n = min(self.n_ids, b1 * self.block) - b0 * self.block
        if self.block * self.bits % 8 == 0:
            return unpack_bits(raw, n, self.bits)[start - b0 * self.block : stop - b0 * self.block]
        parts = [unpack_bits(raw[self.offsets[b] - self.offsets[b0] : self.offsets[b + 1] - self.offsets[b0]], min(self.block, self.n_ids - b * self.block), self.bits) for b in range(b0, b1)]
        return np.concatenate(parts)[start - b0 * self.block : stop - b0 * self.block]

    def documents(self, span: int = 1 << 20) -> Iterator[tuple[int | None, int, np.ndarray]]:
        """(doc_id, start in the file, ids) in order, about `span` ids in memory at a time."""
        k = 0
        while k < self.n_docs:
            base = int(self.ends[k - 1]) if k else 0
            to = max(k + 1, int(np.searchsorted(self.ends, base + span, "right")))
            held = self.ids(base, int(self.ends[to - 1]))
            for d in range(k, to):
                s = int(self.ends[d - 1]) if d else 0
                yield None if self.no_id[d] else int(self.doc_ids[d]), s, held[s - base : int(self.ends[d]) - base]
            k = to


def _at(folder: str):
    """File system and path of a folder; a path without a scheme is local."""
    return pafs.FileSystem.from_uri(folder.replace("s3a://", "s3://", 1)) if "://" in folder or folder.startswith("file:") else (pafs.LocalFileSystem(), folder)


def write_token_files(docs: DataFrame, folder: str, tokenizer: str, vocabulary: int | None = None) -> list[dict]:
    """Writes one file for each range of ids; returns the manifest (path, first id, ids, documents) in id order, one
    small row for each file. The width of an id follows the tokenizer's vocabulary unless another is given."""
    spark = docs.sparkSession
    parts = partitions(spark)
    ordered = docs.select("doc_id", "text").repartitionByRange(parts, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    fs, base = _at(folder)
    fs.create_dir(base, recursive=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_worker(__name__)
        encoder, writer = None, None
        for batch in batches:
            for part in pieces(batch, most=512 << 10):
                if writer is None:
                    encoder = ChunkEncoder.of(tokenizer)
                    store, root = _at(folder)
                    path = f"{root}/{uuid.uuid4().hex}.fwid"
                    out = store.open_output_stream(path)
                    writer = IdWriter(out, vocabulary or encoder.vocabulary)
                ids, off = encoder.encode_documents(part.column("text"))
                writer.add(part.column("doc_id").to_pylist(), ids, off[1:])
        if writer is not None:
            writer.close()
            out.close()
            yield pa.RecordBatch.from_pydict({"path": [path.rsplit("/", 1)[1]], "first_id": pa.array([writer.docs[0]], pa.int64()), "ids": [writer.ids], "docs": [len(writer.docs)]})

    found = ordered.mapInArrow(run, "path string, first_id long, ids long, docs long").collect()
    out, start = [], 0
    for r in sorted(found, key=lambda r: (r["first_id"] is not None, r["first_id"] or 0)):
        out.append({"path": r["path"], "start": start, "ids": r["ids"], "docs": r["docs"]})
        start += r["ids"]
    return out


def read_token_files(spark, folder: str, manifest: list[dict]) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files."""
    rows = spark.createDataFrame([(m["path"], m["start"]) for m in manifest], "path string, start long")
    if manifest:
        rows = rows.repartition(len(manifest))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = _at(folder)
        for batch in batches:
            for path, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                with store.open_input_file(f"{root}/{path}") as f:
                    cols: list[list] = [[], [], [], []]
                    for doc, start, ids in IdReader(f).documents():
                        for c, v in zip(cols, (doc, base + start, len(ids), zlib.crc32(ids.tobytes()))):
                            c.append(v)
                        if len(cols[0]) >= 20_000:
                            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["doc_id", "start", "n_tokens", "ids_crc32"])
                            cols = [[], [], [], []]
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return rows.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_files(docs: DataFrame, tokenizer: str | None = None, vocabulary: int | None = None, folder: str | None = None) -> DataFrame:
    spark = docs.sparkSession
    folder = folder or f"{scratch_root(spark)}/token-files-{uuid.uuid4().hex}"
    manifest = write_token_files(docs, folder, tokenizer or tokenizer_path("word_bpe_49k.json"), vocabulary)
    return read_token_files(spark, folder, manifest)
