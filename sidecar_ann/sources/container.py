"""Typed blobs in one object: blobs, a JSON footer that lists them, and a fixed trailer, so that two small ranged reads
find any blob. Readers skip types that they do not know. A blob may be compressed whole by zstd."""

from __future__ import annotations

import json
import struct
from collections.abc import Iterable
from dataclasses import asdict, dataclass, field

import pyarrow as pa

from ..errors import CorruptContainer
from . import store

MAGIC = b"SIDE"
_TRAILER = struct.Struct("<IIQ4s")  # version, reserved, footer length, magic

CENTROIDS, ROUTING, GRAPH, DERIVED = "vector-centroids-v1", "vector-routing-v1", "vector-graph-v1", "derived-data-v1"
BLOB_TYPES = (CENTROIDS, ROUTING, GRAPH, DERIVED)


@dataclass
class Blob:
    type: str
    data: bytes
    fields: list[int] = field(default_factory=list)
    snapshot_id: int = -1
    properties: dict[str, str] = field(default_factory=dict)
    codec: str = "none"


@dataclass
class BlobMeta:
    type: str
    offset: int
    length: int
    raw_length: int
    fields: list[int]
    snapshot_id: int
    codec: str
    properties: dict[str, str]


@dataclass
class Footer:
    blobs: list[BlobMeta]
    properties: dict[str, str]
    footer_bytes: int

    def known(self) -> list[BlobMeta]:
        return [b for b in self.blobs if b.type in BLOB_TYPES]

    def first(self, kind: str) -> BlobMeta:
        for b in self.blobs:
            if b.type == kind:
                return b
        raise CorruptContainer(f"no blob of type {kind}")


def pack(blobs: Iterable[Blob], properties: dict[str, str] | None = None) -> bytes:
    parts, metas, at = [MAGIC], [], len(MAGIC)
    for b in blobs:
        if b.codec not in ("none", "zstd"):
            raise ValueError(f"unknown codec {b.codec}")
        data = bytes(pa.Codec("zstd").compress(b.data, asbytes=True)) if b.codec == "zstd" else b.data
        metas.append(BlobMeta(b.type, at, len(data), len(b.data), list(b.fields), b.snapshot_id, b.codec, dict(b.properties)))
        parts.append(data)
        at += len(data)
    foot = json.dumps({"blobs": [asdict(m) for m in metas], "properties": properties or {}}, sort_keys=True).encode()
    return b"".join([*parts, foot, _TRAILER.pack(1, 0, len(foot), MAGIC)])


def write_container(path: str, blobs: Iterable[Blob], properties: dict[str, str] | None = None) -> int:
    data = pack(blobs, properties)
    if not store.put_if_absent(path, data):
        raise FileExistsError(path)
    return len(data)


def read_footer(path: str) -> Footer:
    n = store.size(path)
    if n < _TRAILER.size + len(MAGIC):
        raise CorruptContainer(f"{path} is too short")
    version, _, length, magic = _TRAILER.unpack(store.get(path, n - _TRAILER.size, _TRAILER.size))
    if magic != MAGIC or version != 1 or length > n:
        raise CorruptContainer(f"{path} has no trailer")
    foot = json.loads(store.get(path, n - _TRAILER.size - length, length))
    return Footer([BlobMeta(**b) for b in foot["blobs"]], foot["properties"], length + _TRAILER.size)


def read_blob(path: str, meta: BlobMeta) -> bytes:
    raw = store.get(path, meta.offset, meta.length)
    return bytes(pa.Codec("zstd").decompress(raw, meta.raw_length, asbytes=True)) if meta.codec == "zstd" else raw
