"""Whole-text encoding with public tokenizer files: texts are cut where the tokenizer's own pattern cuts them anyway, and
the ids of the chunks come from a memo of fixed size.

`cut_points` marks only places at which the pattern of the file must begin a new piece whatever stands around: between
ASCII characters (and letters of Latin, Greek and Cyrillic blocks) of different kinds, never after an apostrophe, never
beside a character that it does not know. So the joined ids of the chunks are the ids of the whole text; texts that hold
the string of an added token, and files with a pattern that is not known here, are encoded whole.

The memo is a direct-mapped table of numpy arrays: a chunk of up to KEY_BYTES bytes is its own key (no hash is trusted),
a slot holds up to WIDTH values, and a newer chunk takes the slot of an older one. Its size is fixed, under 40 MB for a
worker, whatever the corpus; what does not fit is encoded each time."""

from __future__ import annotations

import json
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import MIX, MIX2, text_bytes, worker_cache

END_ID = 2
KEY_BYTES = 23
WIDTH = 6

#: The splitting pattern of the files whose words are kept apart from white space; a fixed value of the format.
_WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

_UNKNOWN, _BLANK, _WHITE, _LETTER, _DIGIT, _OTHER = range(6)


def _kinds() -> np.ndarray:
    out = np.full(256, _UNKNOWN, np.uint8)
    out[:128] = _OTHER
    out[28:32] = _UNKNOWN  # separators that some patterns count as white space
    out[9:14] = _WHITE
    out[32] = _BLANK
    for first, last, kind in (("0", "9", _DIGIT), ("a", "z", _LETTER), ("A", "Z", _LETTER)):
        out[ord(first) : ord(last) + 1] = kind
    return out


_KIND = _kinds()
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def _byte_chars() -> dict[int, int]:
    """Characters that stand for bytes in byte-level models: printable ones for themselves, others from 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in shown]
    return {b: 256 + k for k, b in enumerate(others)}


_BYTE_CHARS = _byte_chars()
_BLANK_CHAR = chr(_BYTE_CHARS[32])


def _letter_pairs() -> np.ndarray:
    """Two-byte characters that are letters, and stay one letter in lower case: by code point."""
    import unicodedata

    out = np.zeros(0x800, bool)
    for a, b in ((0xC0, 0x240), (0x391, 0x3CF), (0x400, 0x480)):
        for c in range(a, b):
            ch = chr(c)
            out[c] = unicodedata.category(ch)[0] == "L" and len(ch.lower()) == 1 and unicodedata.normalize("NFC", ch) == ch
    return out


_PAIRS = _letter_pairs()


def byte_kinds(data: np.ndarray) -> np.ndarray:
    kind = _KIND[data]
    lead = np.flatnonzero((data[:-1] >= 0xC3) & (data[:-1] <= 0xD1)) if len(data) > 1 else np.zeros(0, np.int64)
    if len(lead):
        code = ((data[lead].astype(np.int64) & 0x1F) << 6) | (data[lead + 1] & 0x3F)
        known = lead[_PAIRS[code]]
        kind[known] = _LETTER
        kind[known + 1] = _LETTER
    return kind


def cut_points(data: np.ndarray, off: np.ndarray, glued: bool, opaque_rows: np.ndarray | None = None) -> np.ndarray:
    """Starts of the chunks: safe cuts and the start of each text that has bytes. glued: one blank belongs to the word
    after it; else white space is dropped and digits stand alone."""
    if not len(data):
        return np.zeros(0, np.int64)
    kind = byte_kinds(data)
    if opaque_rows is not None:
        for r in np.flatnonzero(opaque_rows):
            kind[off[r] : off[r + 1]] = _UNKNOWN
    row = np.zeros(len(data) + 1, bool)
    row[off] = True
    left, right = kind[:-1], kind[1:]
    cut = np.zeros(len(data), bool)
    cut[1:] = (left != right) & (left != _UNKNOWN) & (right != _UNKNOWN) & (data[:-1] != 39)
    white = kind <= _WHITE
    white &= kind != _UNKNOWN
    if glued:
        # after white space only where that is one character, not a blank, behind a known solid character or at the start
        after = np.zeros(len(data), bool)
        after[1:] = white[:-1]
        lone = np.zeros(len(data), bool)
        lone[1:] = (left == _WHITE) & row[:-2]
        lone[2:] |= (left[1:] == _WHITE) & (kind[:-2] > _WHITE)
        cut &= ~after | (lone & ~white)
    else:
        cut[1:] |= (left == _DIGIT) & (right == _DIGIT)
    cut |= row[:-1]
    return np.flatnonzero(cut)


class ChunkEncoder:
    """encode(column) -> (values of all texts joined, offsets of the texts); the values are token ids."""

    name = "encoders"
    #: Slots of the memo as a power of two, and the type of the values outside it.
    slot_bits, value_type = 20, np.uint32

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = [t["content"] for t in spec.get("added_tokens") or []]
        self.rule = self._rule(spec)
        self.model = self.tokenizer.model
        self.vocabulary = max(self.tokenizer.get_vocab(with_added_tokens=True).values()) + 1
        slots = 1 << self.slot_bits
        self.keys = tuple(np.zeros(slots, np.uint64) for _ in range(3))
        self.values = np.zeros((slots, WIDTH), self._stored())
        self.sizes = np.zeros(slots, np.uint8)

    @classmethod
    def of(cls, path: str) -> ChunkEncoder:
        held = worker_cache(cls.name)
        if path not in held:
            held[path] = cls(path)
        return held[path]

    def _stored(self) -> type:
        return np.uint16 if self.vocabulary <= 1 << 16 else np.uint32

    @staticmethod
    def _rule(spec: dict) -> str | None:
        pre, norm = spec.get("pre_tokenizer") or {}, spec.get("normalizer")
        if norm is None and pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space"):
            return "glued"
        steps = pre.get("pretokenizers") or [{}]
        kinds = [n.get("type") for n in (norm or {}).get("normalizers", [])]
        if steps[0].get("type") == "Split" and steps[0].get("pattern") == {"Regex": _WORD_PATTERN} and steps[0].get("invert") and kinds == ["NFC", "Replace", "Lowercase"]:
            return "apart"
        return None

    # ------------------------------------------------------------ the tokenizer itself
    def _whole(self, texts: list[str]) -> list[list[int]]:
        """Values of chunks as the whole pipeline of the tokenizer gives them."""
        return [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _values(self, chunk: bytes) -> list[int]:
        """Values of a chunk that the pattern leaves in one piece, from the tokenizer's model."""
        return [t.id for t in self.model.tokenize(self._chars(chunk))]

    def _chars(self, chunk: bytes) -> str:
        """The chunk's bytes as the characters that the model knows them by."""
        if not chunk.isascii():
            if self.rule == "apart":  # character by character: no rule for the ends of words
                chunk = "".join(c.lower() for c in chunk.decode()).encode()
            return chunk.decode("latin-1").translate(_BYTE_CHARS)
        text = chunk.decode().lower() if self.rule == "apart" else chunk.decode()
        if not text.isprintable():
            return text.translate(_BYTE_CHARS)
        return _BLANK_CHAR + text[1:] if text[0] == " " else text

    def _encode_chunks(self, chunks: list[bytes], single: np.ndarray) -> list[list[int]]:
        values = self._values
        out = [values(c) if one else None for c, one in zip(chunks, single.tolist())]
        rest = np.flatnonzero(~single).tolist()
        for i, v in zip(rest, self._whole([chunks[i].decode("utf-8", "replace") for i in rest]) if rest else ()):
            out[i] = v
        return out

    # ------------------------------------------------------------ memo
    def _keys(self, data: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, ...]:
        """Three words of chunks of at most KEY_BYTES bytes: their bytes, zeros after, and the size in the last byte."""
        padded = np.concatenate([data, np.zeros(24, np.uint8)])
        raw = np.lib.stride_tricks.sliding_window_view(padded, 24)[start].view(np.uint64)
        raw &= _MASKS[size]
        raw[:, 2] |= size.astype(np.uint64) << np.uint64(56)
        return tuple(np.ascontiguousarray(raw[:, i]) for i in range(3))

    def _slots(self, key: tuple[np.ndarray, ...]) -> np.ndarray:
        mixed = key[0] * MIX + key[1] * MIX2 + key[2]
        mixed ^= mixed >> np.uint64(32)
        mixed *= MIX2
        return (mixed >> np.uint64(64 - self.slot_bits)).astype(np.int64)

    def _holds(self, slot: np.ndarray, key: tuple[np.ndarray, ...]) -> np.ndarray:
        same = self.keys[0][slot] == key[0]
        same &= self.keys[1][slot] == key[1]
        same &= self.keys[2][slot] == key[2]
        return same

    def lookup(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(values of all chunks joined, number of values of each)."""
        size = ends - starts
        n = np.zeros(len(starts), np.int64)
        short = np.flatnonzero(size <= KEY_BYTES)
        key = self._keys(data, starts[short], size[short])
        slot = self._slots(key)
        hit = self._holds(slot, key)
        found, at = short[hit], slot[hit]
        sizes = self.sizes[at]
        n[found] = sizes
        todo = np.ones(len(starts), bool)
        todo[found] = False
        todo = np.flatnonzero(todo)
        if len(todo):
            raw = data.tobytes()
            missing = [raw[s:e] for s, e in zip(starts[todo].tolist(), ends[todo].tolist())]
            known = {c: k for k, c in enumerate(dict.fromkeys(missing))}
            which = np.array([known[c] for c in missing], np.int64)
            first = np.empty(len(known), np.int64)
            first[which[::-1]] = todo[::-1]
            lists = self._encode_chunks(list(known), self._single(data, starts[first], ends[first]))
            each = np.array([len(v) for v in lists], np.int64)
            flat = np.array([x for v in lists for x in v], self.value_type)
            head = np.cumsum(each) - each
            n[todo] = each[which]
        base = np.cumsum(n) - n
        out = np.empty(int(n.sum()), self.value_type)
        to = base[found]
        for j in range(int(sizes.max()) if len(sizes) else 0):
            if j:
                more = np.flatnonzero(sizes > j)
                to, at, sizes = to[more], at[more], sizes[more]
            some = sizes > 0 if not j else slice(None)
            out[to[some] + j] = self.values[at[some], j]
        if len(todo):
            count = n[todo]
            step = np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
            out[np.repeat(base[todo], count) + step] = flat[np.repeat(head[which], count) + step]
            self._learn(data, starts[first], size[first], flat, head, each)
        return out, n

    def _learn(self, data: np.ndarray, start: np.ndarray, size: np.ndarray, flat: np.ndarray, head: np.ndarray, each: np.ndarray) -> None:
        keep = np.flatnonzero((size <= KEY_BYTES) & (each <= WIDTH))
        key = self._keys(data, start[keep], size[keep])
        slot = self._slots(key)
        for table, word in zip(self.keys, key):
            table[slot] = word
        mine = self._holds(slot, key)  # of two chunks for one slot, the one written last
        slot, keep = slot[mine], keep[mine]
        self.sizes[slot] = each[keep]
        for j in range(WIDTH):
            more = np.flatnonzero(each[keep] > j)
            self.values[slot[more], j] = flat[head[keep[more]] + j]

    def _single(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Which chunks the pattern surely leaves in one piece: one kind of known solid characters without an apostrophe,
        after one blank at most where blanks are kept."""
        if self.rule is None:
            return np.zeros(len(start), bool)
        kind = byte_kinds(data)
        new = np.zeros(len(kind), bool)
        new[1:] = kind[1:] != kind[:-1]
        new |= data == 39
        upto = np.concatenate([[0], np.cumsum(new)])
        first = start + ((kind[start] == _BLANK) if self.rule == "glued" else 0)
        solid = (first < end) & (kind[np.minimum(first, end - 1)] >= _LETTER) & (data[np.minimum(first, end - 1)] != 39)
        return solid & (upto[end] == upto[np.minimum(first + 1, end)])

    # ------------------------------------------------------------ texts
    def chunks(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(bytes, offsets of the texts, starts of the chunks, offsets of the texts in chunks)."""
        data, off = text_bytes(column)
        if self.rule is None:
            odd = np.ones(len(column), bool)
        else:
            odd = np.zeros(len(column), bool)
            for s in self.special:
                odd |= np.asarray(pc.fill_null(pc.match_substring(column, s), False))
        if self.rule == "apart" and not odd.any():
            data = _LOWER[data]
        starts = cut_points(data, off, self.rule == "glued", odd if odd.any() else None)
        return data, off, starts, np.searchsorted(starts, off)

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        data, _, starts, row = self.chunks(column)
        flat, n = self.lookup(data, starts, np.append(starts[1:], len(data)) if len(starts) else starts)
        return flat, np.concatenate([[0], np.cumsum(n)])[row]

    def encode_documents(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """As encode, with the end id after each text."""
        flat, off = self.encode(column)
        return np.insert(flat, off[1:], END_ID), off + np.arange(len(off))


def _masks() -> np.ndarray:
    """By size: which bytes of three words belong to the chunk."""
    on = (np.arange(24)[None, :] < np.arange(KEY_BYTES + 1)[:, None]).astype(np.uint8) * 255
    return on.view(np.uint64)


_MASKS = _masks()


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


