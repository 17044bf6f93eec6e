"""Integer codings of blob sections, vectorised."""

from __future__ import annotations

import numpy as np


def zigzag(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.int64)
    return ((x << 1) ^ (x >> 63)).astype(np.uint64)


def unzigzag(x: np.ndarray) -> np.ndarray:
    return (x >> np.uint64(1)).astype(np.int64) ^ -(x & np.uint64(1)).astype(np.int64)


def varint_encode(x: np.ndarray) -> bytes:
    """Seven bits a byte, low bits first."""
    x = np.asarray(x, np.uint64)
    if not len(x):
        return b""
    n = np.ones(len(x), np.int64)
    for k in range(1, 10):
        n += x >= np.uint64(1) << np.uint64(7 * k)
    ends = np.cumsum(n)
    out = np.zeros(ends[-1], np.uint8)
    for k in range(int(n.max())):
        rows = n > k
        part = (x[rows] >> np.uint64(7 * k)) & np.uint64(127)
        out[ends[rows] - n[rows] + k] = part.astype(np.uint8) | ((n[rows] > k + 1).astype(np.uint8) << 7)
    return out.tobytes()


def varint_decode(data: bytes) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8)
    if not len(raw):
        return np.zeros(0, np.uint64)
    last = np.flatnonzero(raw < 128)
    first = np.concatenate([[0], last[:-1] + 1])
    place = np.arange(len(raw)) - np.repeat(first, last - first + 1)
    part = (raw & 127).astype(np.uint64) << (7 * place).astype(np.uint64)
    return np.add.reduceat(part, first)


def delta_encode(x: np.ndarray) -> bytes:
    x = np.asarray(x, np.int64)
    return varint_encode(zigzag(np.diff(x, prepend=0))) if len(x) else b""


def delta_decode(data: bytes) -> np.ndarray:
    return np.cumsum(unzigzag(varint_decode(data)))
