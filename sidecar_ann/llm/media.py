"""AVI motion-JPEG: bytes stored losslessly as intra frames, read back through the RIFF index, cut into timed shots.

A frame is a baseline JPEG in which each 8 x 8 block is one sample: blocks are flat, so a DC coefficient quantised by 8
holds the sample exactly and every decoder returns it unchanged. A row of 64 blocks is a restart interval; intervals
begin at a byte and need nothing from each other, so all intervals of a batch of files are decoded in step with each
other by table look-ups. The reader is a general one for sequential Huffman frames of 8 bits: codes of DC and AC
coefficients, dequantisation, inverse transform, several components with their sampling; a block without AC coefficients,
as all of a payload are, is the constant that the transform gives. A payload of up to 64 rows is one frame of its own height; longer ones have several of one
height, the last padded, and the comment chunk holds the payload's length.

Shots end where the histogram difference of neighbouring frames stands out from those before it (mean and deviation of
the differences since the last cut), and each shot is a row with its times.

Null texts are empty; the payload of an empty text is 64 zero bytes. Equal payloads give equal files. Repeated rows
repeat. An empty table gives no rows. Columns other than doc_id and text are ignored."""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import per_batch, pieces, text_bytes, worker_cache

ROW = 64  # samples (blocks) of a row, and of a restart interval
ROWS = 64  # rows of a full frame
FPS = 25
#: Code lengths of the DC categories 0..8: fixed, so equal payloads give equal files.
DC_LENGTHS = (5, 5, 3, 3, 2, 3, 5, 2, 6)


def _codes(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """Canonical codes: symbol -> (code, length), by length and then symbol."""
    out, code, last = {}, 0, 0
    for sym, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        code <<= n - last
        out[sym] = (code, n)
        code, last = code + 1, n
    return out


def _dht(kind: int, lengths: dict[int, int]) -> bytes:
    order = sorted(lengths, key=lambda s: (lengths[s], s))
    counts = bytes(sum(n == k for n in lengths.values()) for k in range(1, 17))
    return struct.pack(">HHB", 0xFFC4, 19 + len(order), kind) + counts + bytes(order)


_DC = dict(enumerate(DC_LENGTHS))
_EOB_LENGTH = 1


def _encode_tables() -> tuple[np.ndarray, np.ndarray]:
    """For each difference -255..255: code, extra bits and the end-of-block code, and their number of bits."""
    codes = _codes(_DC)
    value, bits = np.zeros(511, np.uint32), np.zeros(511, np.int64)
    for d in range(-255, 256):
        cat = abs(d).bit_length()
        code, n = codes[cat]
        extra = d if d >= 0 else d + (1 << cat) - 1
        value[d + 255] = ((code << cat) | extra) << _EOB_LENGTH
        bits[d + 255] = n + cat + _EOB_LENGTH
    return value, bits


_VALUE, _BITS = _encode_tables()


def _jpeg_head(rows: int) -> bytes:
    quant = bytes([8] + [1] * 63)
    return (
        b"\xff\xd8" + struct.pack(">HHB", 0xFFDB, 67, 0) + quant + struct.pack(">HHBHHBBBB", 0xFFC0, 11, 8, 8 * rows, 8 * ROW, 1, 1, 0x11, 0)
        + _dht(0x00, _DC) + _dht(0x10, {0: _EOB_LENGTH}) + struct.pack(">HHH", 0xFFDD, 4, ROW) + struct.pack(">HHBBBBBB", 0xFFDA, 8, 1, 1, 0, 0, 63, 0)
    )


def entropy_code(samples: np.ndarray, first_of_frame: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes with stuffing and restart markers, end of each row's bytes) of rows of samples. A marker stands before each
    row but the first of a frame; first_of_frame: the number of each row within its frame."""
    diff = np.empty(samples.shape, np.int64)
    diff[:, 0] = samples[:, 0].astype(np.int64) - 128
    diff[:, 1:] = np.diff(samples.astype(np.int16), axis=1)
    diff += 255
    bits = _BITS[diff]
    upto = np.cumsum(bits, axis=1)
    n_bytes = (upto[:, -1] + 7) >> 3
    base = np.cumsum(n_bytes) - n_bytes
    pos = (upto - bits + (base << 3)[:, None]).ravel()
    word = _VALUE[diff].ravel().astype(np.int64) << (24 - bits.ravel() - (pos & 7))
    at = pos >> 3
    size = int(n_bytes.sum())
    out = np.bincount(at, word >> 16, size + 2)
    out += np.bincount(at + 1, (word >> 8) & 255, size + 2)
    out += np.bincount(at + 2, word & 255, size + 2)
    raw = out[:size].astype(np.uint8)
    raw[base + n_bytes - 1] |= ((1 << ((n_bytes << 3) - upto[:, -1])) - 1).astype(np.uint8)
    marked = np.flatnonzero(first_of_frame)
    extra = (raw == 255).astype(np.int64)
    shift = np.cumsum(extra) - extra  # stuffing before each byte
    lead = np.zeros(size, np.int64)
    lead[base[marked]] = 2
    to = np.arange(size) + shift + np.cumsum(lead)
    full = np.zeros(size + int(extra.sum()) + 2 * len(marked), np.uint8)
    full[to] = raw
    full[to[base[marked]] - 2] = 255
    full[to[base[marked]] - 1] = 0xD0 + (first_of_frame[marked] - 1) % 8
    last = base + n_bytes - 1
    return full, to[last] + 1 + extra[last]


def _chunk(tag: bytes, data: bytes) -> bytes:
    return tag + struct.pack("<I", len(data)) + data + b"\0" * (len(data) & 1)


def _avi(frames: list[bytes], rows: int, payload: int) -> bytes:
    width, height, most = 8 * ROW, 8 * rows, max(map(len, frames))
    avih = struct.pack("<14I", 1_000_000 // FPS, most * FPS, 0, 0x10, len(frames), 0, 1, most, width, height, 0, 0, 0, 0)
    strh = b"vidsMJPG" + struct.pack("<IHHIIIIIIIIHHHH", 0, 0, 0, 0, 1, FPS, 0, len(frames), most, 0xFFFFFFFF, 0, 0, 0, width, height)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 24, b"MJPG", width * height * 3, 0, 0, 0, 0)
    head = _chunk(b"LIST", b"hdrl" + _chunk(b"avih", avih) + _chunk(b"LIST", b"strl" + _chunk(b"strh", strh) + _chunk(b"strf", strf)))
    info = _chunk(b"LIST", b"INFO" + _chunk(b"ICMT", b"payload=%d\0" % payload))
    movi, index, at = [], [], 4
    for f in frames:
        c = _chunk(b"00dc", f)
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(f)))
        movi.append(c)
        at += len(c)
    body = b"AVI " + head + info + _chunk(b"LIST", b"movi" + b"".join(movi)) + _chunk(b"idx1", b"".join(index))
    return _chunk(b"RIFF", body)


def encode(payloads: list[bytes]) -> list[bytes]:
    """An AVI file for each payload (a positive multiple of 64 bytes)."""
    shape, flat = [], []
    for p in payloads:
        rows = len(p) // ROW
        frames = -(-rows // ROWS)
        high = -(-rows // frames)
        shape.append((frames, high))
        flat += [p, b"\0" * ((frames * high - rows) * ROW)]
    samples = np.frombuffer(b"".join(flat), np.uint8).reshape(-1, ROW)
    number = np.concatenate([np.tile(np.arange(h), f) for f, h in shape])
    coded, ends = entropy_code(samples, number)
    coded, ends = coded.tobytes(), ends.tolist()
    heads = worker_cache("jpeg_heads")
    out, row, at = [], 0, 0
    for p, (n, high) in zip(payloads, shape):
        head = heads.get(high) or heads.setdefault(high, _jpeg_head(high))
        frames = []
        for _ in range(n):
            row += high
            frames.append(head + coded[at : ends[row - 1]] + b"\xff\xd9")
            at = ends[row - 1]
        out.append(_avi(frames, high, len(p)))
    return out


# ---------------------------------------------------------------- reading
def parse_avi(data: bytes) -> tuple[list[tuple[int, int]], int | None, float]:
    """((offset, length) of each frame by the index, payload length of the comment, seconds a frame)."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    movi, index, payload, micro = None, b"", None, 1_000_000 // FPS

    def walk(at: int, end: int) -> None:
        nonlocal movi, index, payload, micro
        while at + 8 <= end:
            tag, n = data[at : at + 4], int.from_bytes(data[at + 4 : at + 8], "little")
            body = at + 8
            if tag == b"LIST":
                kind = data[body : body + 4]
                if kind == b"movi":
                    movi = body
                else:
                    walk(body + 4, body + n)
            elif tag == b"idx1":
                index = data[body : body + n]
            elif tag == b"avih":
                micro = int.from_bytes(data[body : body + 4], "little")
            elif tag == b"ICMT" and data[body : body + 8] == b"payload=":
                payload = int(data[body + 8 : body + n].rstrip(b"\0"))
            at = body + n + (n & 1)

    walk(12, min(len(data), 8 + int.from_bytes(data[4:8], "little")))
    if movi is None:
        raise ValueError("no frames")
    frames = [(movi + at + 8, n) for tag, _, at, n in struct.iter_unpack("<4sIII", index) if tag[2:] in (b"dc", b"db")]
    return frames, payload, micro / 1e6


#: Row-major place of each coefficient in the order of the stream.
ZIGZAG = np.array(sorted(range(64), key=lambda i: (i // 8 + i % 8, i // 8 if (i // 8 + i % 8) % 2 else i % 8)))
#: Rows: frequencies; columns: samples.
_WAVES = np.array([[(0.5 if u else 0.125**0.5) * np.cos((2 * x + 1) * u * np.pi / 16) for x in range(8)] for u in range(8)])


def _parse_jpeg(frame: bytes) -> tuple[bytes, tuple, int, int, int, int, int]:
    """(tables as they stand, (h, v, quantiser, DC table, AC table) of each component, height, width, restart interval,
    start and end of the coded data)."""
    at, height, width, interval, tables, parts = 2, 0, 0, 0, [], {}
    while True:
        if at + 4 > len(frame):
            raise ValueError("no scan in the frame")
        marker, n = frame[at + 1], int.from_bytes(frame[at + 2 : at + 4], "big")
        body = frame[at + 4 : at + 2 + n]
        if marker in (0xC4, 0xDB):
            tables.append(frame[at : at + 2 + n])
        elif marker in (0xC0, 0xC1):
            height, width = int.from_bytes(body[1:3], "big"), int.from_bytes(body[3:5], "big")
            if body[0] != 8:
                raise ValueError("8-bit frames only")
            parts = {body[k]: (body[k + 1] >> 4, body[k + 1] & 15, body[k + 2]) for k in range(6, 6 + 3 * body[5], 3)}
        elif 0xC2 <= marker <= 0xCF and marker != 0xC8:
            raise ValueError("sequential Huffman frames only")
        elif marker == 0xDD:
            interval = int.from_bytes(body[:2], "big")
        at += 2 + n
        if marker == 0xDA:
            break
    if body[0] != len(parts) or not height or not width:
        raise ValueError("frames of one scan and of known size only")
    scan = tuple((*parts[body[k]], body[k + 1] >> 4, body[k + 1] & 15) for k in range(1, 1 + 2 * body[0], 2))
    if len(scan) == 1:
        scan = ((1, 1, *scan[0][2:]),)  # the blocks of a lone component follow each other row by row
    end = frame.rfind(b"\xff\xd9", at)
    return b"".join(tables), scan, height, width, interval, at, len(frame) if end < 0 else end


def _tables(tables: bytes) -> tuple[dict, dict]:
    """(64 quantisers in the order of the stream by number; (symbol, code length) of the next 16 bits by class and number)."""
    at, quant, codes = 0, {}, {}
    while at < len(tables):
        marker, n = tables[at + 1], int.from_bytes(tables[at + 2 : at + 4], "big")
        body = tables[at + 4 : at + 2 + n]
        while body:
            if marker == 0xDB:
                wide = 1 + (body[0] >> 4)
                quant[body[0] & 15] = np.frombuffer(body[1 : 1 + 64 * wide], ">u2" if wide == 2 else "u1").astype(np.int64)
                body = body[1 + 64 * wide :]
                continue
            counts, kind = body[1:17], body[0]
            k = sum(counts)
            lengths = [i + 1 for i, c in enumerate(counts) for _ in range(c)]
            symbol, length = np.zeros(1 << 16, np.int32), np.zeros(1 << 16, np.int32)
            for sym, (code, size) in _codes_in_order(list(body[17 : 17 + k]), lengths).items():
                symbol[code << (16 - size) : (code + 1) << (16 - size)] = sym
                length[code << (16 - size) : (code + 1) << (16 - size)] = size
            codes[kind] = symbol, length
            body = body[17 + k :]
        at += 2 + n
    return quant, codes


def _extended(bits: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Signed value of `size` bits."""
    return np.where((size > 0) & (bits < (1 << size) >> 1), bits - (1 << size) + 1, bits)


def _lookup(tables: bytes, scan: tuple) -> list[tuple]:
    """For each component: quantisers, DC and AC codes, and for the next 16 bits the DC difference and the bits taken by a
    block that ends after it; 0 bits where the block goes on, or does not fit."""
    held = worker_cache("jpeg_tables")
    if (tables, scan) in held:
        return held[tables, scan]
    quant, codes = _tables(tables)
    out = []
    for _, _, q, dc, ac in scan:
        if q not in quant or dc not in codes or 16 + ac not in codes:
            raise ValueError("a table of the frame is missing")
        (cat, n), (symbol, length) = codes[dc], codes[16 + ac]
        peek = np.arange(1 << 16)
        rest = 16 - n - cat
        fits = (n > 0) & (rest > 0)
        after = np.where(fits, peek << np.where(fits, n + cat, 0), 0) & 0xFFFF
        fits &= (symbol[after] == 0) & (length[after] > 0) & (length[after] <= rest)
        bits = (peek >> np.where(fits, rest, 0)) & ((1 << np.where(fits, cat, 0)) - 1)
        diff = np.where(fits, _extended(bits, np.where(fits, cat, 0)), 0).astype(np.int32)
        out.append((quant[q], (cat, n), (symbol, length), diff, np.where(fits, n + cat + length[after], 0).astype(np.int32)))
    held[tables, scan] = out
    return out


def _codes_in_order(symbols: list[int], lengths: list[int]) -> dict[int, tuple[int, int]]:
    out, code, last = {}, 0, 0
    for s, n in zip(symbols, lengths):
        code <<= n - last
        out[s] = (code, n)
        code, last = code + 1, n
    return out


def _peek(word: np.ndarray, pos: np.ndarray) -> np.ndarray:
    """The 16 bits from each place; past the end the last ones."""
    return ((word[np.minimum(pos >> 3, len(word) - 1)] >> (8 - (pos & 7)).astype(np.uint32)) & 0xFFFF).astype(np.int64)


def _symbols(word: np.ndarray, pos: np.ndarray, table: tuple) -> tuple[np.ndarray, np.ndarray]:
    peek = _peek(word, pos)
    if not table[1][peek].all():
        raise ValueError("a code that no table of the frame has")
    return table[0][peek], pos + table[1][peek]


def _blocks(word: np.ndarray, pos: np.ndarray, dc: tuple, ac: tuple) -> tuple[np.ndarray, np.ndarray, tuple]:
    """(DC difference of a block at each place, where it ends, (which block, number, level) of its AC coefficients)."""
    size, pos = _symbols(word, pos, dc)
    diff = _extended(_peek(word, pos) >> (16 - size), size)
    pos = pos + size
    at, live, found = np.ones(len(pos), np.int64), np.arange(len(pos)), []
    while len(live):
        sym, pos[live] = _symbols(word, pos[live], ac)
        run, size = sym >> 4, sym & 15
        goes_on = (size > 0) | (run == 15)
        live, run, size = live[goes_on], run[goes_on], size[goes_on]
        at[live] += run
        if (at[live] > 63).any():
            raise ValueError("more than 63 coefficients in a block")
        level = _extended(_peek(word, pos[live]) >> (16 - size), size)
        pos[live] += size
        found.append((live[size > 0], at[live][size > 0], level[size > 0]))
        at[live] += 1
        live = live[at[live] <= 63]
    return diff, pos, tuple(np.concatenate(x) for x in zip(*found))


def _samples(dc: np.ndarray, which: np.ndarray, number: np.ndarray, level: np.ndarray, quant: np.ndarray) -> np.ndarray:
    """Samples (n, 8, 8) of blocks of dequantised DC coefficients, and AC coefficients of the blocks `which`."""
    out = np.empty((len(dc), 8, 8), np.uint8)
    order = np.argsort(which, kind="stable")
    which, number, level = which[order], number[order], level[order]
    for s in range(0, len(dc), 1 << 13):
        a, b = np.searchsorted(which, [s, s + (1 << 13)])
        part = np.zeros((len(dc[s : s + (1 << 13)]), 64))
        part[:, 0] = dc[s : s + (1 << 13)]
        part[which[a:b] - s, ZIGZAG[number[a:b]]] = level[a:b] * quant[number[a:b]]
        wave = _WAVES.T @ part.reshape(-1, 8, 8) @ _WAVES
        out[s : s + len(part)] = np.clip(np.floor(wave + 128.5), 0, 255)
    return out


def _plane(dc: np.ndarray, ac: tuple, quant: np.ndarray, high: int, wide: int, per: tuple[int, int], size: tuple[int, int]) -> np.ndarray:
    """A component of `high` x `wide` groups of per = (rows, columns) blocks, cut to its size: samples (rows, columns), or
    where all blocks are flat a view (block rows, 8, block columns, 8) of one sample a block."""
    v, h = per

    def raster(x: np.ndarray) -> np.ndarray:
        x = x.reshape(high, wide, v, h, *x.shape[1:])
        return np.moveaxis(x, 2, 1).reshape(high * v, wide * h, *x.shape[4:])

    if len(ac[0]):
        x = np.moveaxis(raster(_samples(dc, *ac, quant)), 2, 1)
    else:
        flat = raster(np.clip(((dc + 4) >> 3) + 128, 0, 255).astype(np.uint8))
        x = np.broadcast_to(flat[:, None, :, None], (high * v, 8, wide * h, 8))
        if size == (high * v * 8, wide * h * 8):
            return x
    return x.reshape(high * v * 8, wide * h * 8)[: size[0], : size[1]]


def _seen(plane: np.ndarray) -> np.ndarray:
    """Samples of a plane, one of each block where blocks are flat: of the same shares and mean."""
    return plane[:, 0, :, 0] if plane.ndim == 4 else plane


def decode_frames(frames: list[bytes]) -> list[list[np.ndarray]]:
    """Planes of the components of each frame (see _plane; brightness comes first), all frames in step where their tables
    and components agree. Blocks that end after their DC coefficient take one look-up, others one for each code."""
    parsed = [_parse_jpeg(f) for f in frames]
    out: list = [None] * len(frames)
    groups: dict[tuple, list[int]] = {}
    shape = []
    for i, (tables, scan, height, width, interval, _, _) in enumerate(parsed):
        most_h, most_v = max(c[0] for c in scan), max(c[1] for c in scan)
        shape.append((-(-height // (8 * most_v)), -(-width // (8 * most_h)), most_v, most_h))
        groups.setdefault((tables, scan, interval or shape[i][0] * shape[i][1]), []).append(i)
    for (tables, scan, interval), members in groups.items():
        parts = _lookup(tables, scan)
        order = [c for c, (h, v, *_) in enumerate(scan) for _ in range(h * v)]  # component of each block of a unit
        coded = [np.frombuffer(frames[i], np.uint8)[parsed[i][5] : parsed[i][6]] for i in members]
        sizes = np.array([len(c) for c in coded], np.int64)
        data = np.concatenate([*coded, np.zeros(8, np.uint8)])
        starts = np.cumsum(sizes) - sizes
        ff = np.flatnonzero(data[:-1] == 255)
        after = data[ff + 1]
        drop = np.zeros(len(data), bool)
        drop[ff[after == 0] + 1] = True
        marks = ff[(after >= 0xD0) & (after <= 0xD7)]
        drop[marks] = drop[marks + 1] = True
        begin = np.sort(np.concatenate([starts, marks + 2]))
        kept = np.cumsum(~drop) - ~drop
        at = kept[begin]  # place of each interval in the plain bytes
        plain = np.concatenate([data[~drop], np.zeros(8, np.uint8)]).astype(np.uint32)
        word = plain[:-3] << 16 | plain[1:-2] << 8 | plain[2:-1]
        total = np.array([shape[i][0] * shape[i][1] for i in members], np.int64)
        per = -(-total // interval)
        units = np.full(len(at), interval, np.int64)
        if len(units) != int(per.sum()):
            raise ValueError("restart markers do not match the frames")
        units[np.cumsum(per) - 1] = total - (per - 1) * interval
        blocks = units * len(order)
        steps = int(blocks.max())
        held = np.zeros((steps, len(at)), np.int32)
        more: list[list[tuple]] = [[] for _ in scan]
        pos = at << 3
        for k in range(steps):
            _, dc, ac, diff, used = parts[order[k % len(order)]]
            peek = (word[np.minimum(pos >> 3, len(word) - 1)] >> (8 - (pos & 7)).astype(np.uint32)) & 0xFFFF
            held[k], take = diff[peek], used[peek]
            long = np.flatnonzero((take == 0) & (blocks > k)) if not take.all() else ()
            pos = np.where(blocks > k, pos + take, pos)
            if len(long):
                held[k, long], pos[long], (which, number, level) = _blocks(word, pos[long], dc, ac)
                more[order[k % len(order)]].append((long[which], np.full(len(which), k), number, level))
        owner = np.repeat(np.arange(len(members)), per)
        lead = np.cumsum(per) - per
        for c, (h, v, *_) in enumerate(scan):
            mine = np.flatnonzero(np.array(order) == c)
            rows = (np.arange(steps // len(order))[:, None] * len(order) + mine).ravel()
            value = (np.cumsum(held[rows], axis=0) * parts[c][0][0]).T
            n_units = units * len(mine)
            flat = value.reshape(-1) if (blocks == steps).all() else np.concatenate([x[:n] for x, n in zip(value, n_units)])
            none = np.zeros(0, np.int64)
            inter, step, number, level = (np.concatenate(x) for x in zip(*more[c])) if more[c] else (none,) * 4
            first = np.cumsum(n_units) - n_units
            which = first[inter] + step // len(order) * len(mine) + step % len(order) - (mine[0] if len(mine) else 0)
            by = np.argsort(owner[inter], kind="stable")
            which, number, level = which[by], number[by], level[by]
            cuts = np.searchsorted(owner[inter][by], np.arange(len(members) + 1))
            for m, i in enumerate(members):
                s, (high, wide, most_v, most_h) = first[lead[m]], shape[i]
                a, b = cuts[m], cuts[m + 1]
                size = -(-parsed[i][2] * v // most_v), -(-parsed[i][3] * h // most_h)
                plane = _plane(flat[s : s + total[m] * len(mine)], (which[a:b] - s, number[a:b], level[a:b]), parts[c][0], high, wide, (v, h), size)
                out[i] = (out[i] or []) + [plane]
    return out


def decode(files: list[bytes]) -> list[tuple[bytes, list[np.ndarray], float]]:
    """(payload, brightness of the frames, seconds a frame) of each file. Without a length in a comment chunk the payload is
    the samples seen."""
    parsed = [parse_avi(f) for f in files]
    frames = [planes[0] for planes in decode_frames([f[at : at + n] for f, (where, _, _) in zip(files, parsed) for at, n in where])]
    out, k = [], 0
    for where, payload, each in parsed:
        own = frames[k : k + len(where)]
        k += len(where)
        joined = b"".join(_seen(x).tobytes() for x in own)
        out.append((joined if payload is None else joined[:payload], own, each))
    return out


def histograms(frames: list[np.ndarray]) -> np.ndarray:
    """Share of the samples of each frame in each of 16 ranges."""
    frames = [_seen(f) for f in frames]
    sizes = np.array([f.size for f in frames], np.int64)
    flat = np.concatenate([f.ravel() for f in frames]).astype(np.int64) >> 4
    row = np.repeat(np.arange(len(frames)), sizes)
    return np.bincount(row * 16 + flat, minlength=16 * len(frames)).reshape(-1, 16) / sizes[:, None]


def shots(hist: np.ndarray, spread: float = 3.0, floor: float = 0.08) -> list[tuple[int, int]]:
    """(first frame, end) of each shot."""
    if len(hist) < 2:
        return [(0, len(hist))]
    step = np.abs(np.diff(hist, axis=0)).sum(1) / 2
    cuts, since = [0], 0
    for i, d in enumerate(step):
        past = step[since:i]
        limit = past.mean() + spread * past.std() if len(past) >= 2 else 3 * floor
        if d > max(limit, floor):
            cuts.append(i + 1)
            since = i + 1
    return list(zip(cuts, [*cuts[1:], len(hist)]))


def _payload(raw: bytes) -> bytes:
    return raw + b"\0" * (-len(raw) % ROW or (0 if raw else ROW))


def store_and_read(docs: DataFrame) -> DataFrame:
    """doc_id, media and what reading it back gives: payload digests, the sound of the round trip, features, shots."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    names = [c.split()[0] for c in schema.split(", ")]

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for part in pieces(batch, most=1 << 20):
            data, off = text_bytes(part.column("text"))
            raw = data.tobytes()
            texts = [raw[s:e] for s, e in zip(off[:-1], off[1:])]
            files = encode([_payload(t) for t in texts])
            cols: list[list] = [[] for _ in names]
            back = decode(files)
            hist, k = histograms([f for _, frames, _ in back for f in frames]), 0
            for doc, t, f, (payload, frames, each) in zip(part.column("doc_id").to_pylist(), texts, files, back):
                own = hist[k : k + len(frames)]
                k += len(frames)
                found = shots(own)
                mean = ".".join(str(int(x)) for x in np.rint(own.mean(0) * 1000))
                feature = f"{len(frames)};{len(found)};{max(e - s for s, e in found) * each:.2f};{mean}"
                row = (doc, len(t), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(f), hashlib.sha256(f).hexdigest(), feature)
                for c, v in zip(cols, row):
                    c.append(v)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names)

    return per_batch(docs.select("doc_id", "text"), work, schema)


def media_column(docs: DataFrame) -> DataFrame:
    """doc_id, media: each text's bytes as an AVI file."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for part in pieces(batch, most=1 << 20):
            data, off = text_bytes(part.column("text"))
            raw = data.tobytes()
            files = encode([_payload(raw[s:e]) for s, e in zip(off[:-1], off[1:])])
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(files, pa.binary())], ["doc_id", "media"])

    return per_batch(docs.select("doc_id", "text"), work, "doc_id long, media binary")


def clips(media: DataFrame) -> DataFrame:
    """doc_id, clip, start_s, end_s, first_frame, end_frame, mean: one row for each shot of each file. A null file has
    no clips."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for part in pieces(batch, "media", 1 << 20):
            rows = [(d, bytes(m)) for d, m in zip(part.column("doc_id").to_pylist(), part.column("media").to_pylist()) if m is not None]
            out = []
            for (doc, _), (_, frames, each) in zip(rows, decode([m for _, m in rows])):
                for k, (s, e) in enumerate(shots(histograms(frames))):
                    out.append((doc, k, s * each, e * each, s, e, float(np.mean([_seen(f).mean() for f in frames[s:e]]))))
            kinds = [pa.int64(), pa.int32(), pa.float64(), pa.float64(), pa.int64(), pa.int64(), pa.float64()]
            names = ["doc_id", "clip", "start_s", "end_s", "first_frame", "end_frame", "mean"]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], names)

    return per_batch(media.select("doc_id", "media"), work, "doc_id long, clip int, start_s double, end_s double, first_frame long, end_frame long, mean double")
