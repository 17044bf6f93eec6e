"""Token counts by section or field: each whole text is encoded once (chunk by chunk from a memo, with the spans of a
whole encoding), and its tokens attributed to sections by character spans.

`attribute` joins sorted token spans with sorted section spans by binary search (an interval join; texts are joined end to
end, and no token crosses texts) and gives a token that crosses a boundary by one of three rules: "start" (the section of
its first character, the default), "majority" (the section with most of its characters, the earlier on a tie),
"proportional" (shares of its length, so counts are fractions). Sections are lines by default, where a line end belongs to
the line that it ends; any function of the text may be given, or several columns rendered as one text.

Null and empty texts are one section of no tokens. Repeated rows repeat. An empty table gives no rows. Columns other
than doc_id and text are ignored."""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import per_batch, pieces, text_bytes
from .tokens import ChunkEncoder, tokenizer_path

RULES = ("start", "majority", "proportional")


def line_sections(text: str) -> np.ndarray:
    """Starts of the lines and the end of the text."""
    cut = [0]
    at = text.find("\n")
    while at >= 0 and at + 1 < len(text):
        cut.append(at + 1)
        at = text.find("\n", at + 1)
    return np.array([*cut, len(text)], np.int64)


def attribute(start: np.ndarray, end: np.ndarray, bounds: np.ndarray, rule: str = "start") -> tuple[np.ndarray, np.ndarray]:
    """(tokens, crossing tokens) of each section; a crossing token is noted at the section of its first character."""
    n = len(bounds) - 1
    first = np.clip(np.searchsorted(bounds, start, "right") - 1, 0, n - 1)
    last = np.clip(np.searchsorted(bounds, np.maximum(end - 1, start), "right") - 1, 0, n - 1)
    crossing = first != last
    cross = np.bincount(first[crossing], minlength=n)
    if rule == "start" or not crossing.any():
        return np.bincount(first, minlength=n).astype(float), cross
    got = np.bincount(first[~crossing], minlength=n).astype(float)
    for s, e, a, b in zip(start[crossing], end[crossing], first[crossing], last[crossing]):
        inside = np.minimum(bounds[a + 1 : b + 2], e) - np.maximum(bounds[a : b + 1], s)
        if rule == "majority":
            got[a + int(np.argmax(inside))] += 1
        else:
            got[a : b + 1] += inside / (e - s)
    return got, cross


class SpanEncoder(ChunkEncoder):
    """The same memo of chunks with character spans as values: start and end within the chunk in one word."""

    name = "span_encoders"
    slot_bits, value_type = 19, np.uint64

    def _stored(self) -> type:
        return np.uint64

    def _whole(self, texts: list[str]) -> list[list[int]]:
        return [[s << 32 | e for s, e in x.offsets] for x in self.tokenizer.encode_batch(texts, add_special_tokens=False)]

    def _values(self, chunk: bytes) -> list[int]:
        chars = self._chars(chunk)
        sizes = [len(t.value) for t in self.model.tokenize(chars)]  # a character of the model is a byte
        ends = list(itertools.accumulate(sizes))
        ends[-1] = len(chars)  # without the mark of a word's end
        starts = [0, *ends[:-1]]
        if len(chars) == len(chunk) and not chunk.isascii():
            at = list(itertools.accumulate((b & 0xC0) != 0x80 for b in chunk))  # a span covers each character it touches
            starts, ends = [at[s] - 1 for s in starts], [at[e - 1] for e in ends]
        return [s << 32 | e for s, e in zip(starts, ends)]

    def spans(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(starts, ends, offsets of the texts in tokens, offsets of the texts in characters); positions are characters
        of all texts joined."""
        data, off, begin, row = self.chunks(column)
        flat, n = self.lookup(data, begin, np.append(begin[1:], len(data)) if len(begin) else begin)
        at = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
        base = np.repeat(at[begin], n)
        low = np.uint64(0xFFFFFFFF)
        return (flat >> np.uint64(32)).astype(np.int64) + base, (flat & low).astype(np.int64) + base, np.concatenate([[0], np.cumsum(n)])[row], at[off]


def _line_bounds(column: pa.Array, chars: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(starts of the lines of all texts in characters of all texts joined, text of each)."""
    data, off = text_bytes(column)
    at = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
    after = np.flatnonzero(data == 10) + 1
    owner = np.searchsorted(off, after - 1, "right") - 1
    after, owner = (x[after < off[owner + 1]] for x in (after, owner))  # the last line end opens no line
    start = np.concatenate([chars[:-1], at[after]])
    text = np.concatenate([np.arange(len(column)), owner])
    order = np.lexsort((start, text))
    return start[order], text[order]


def _given_bounds(texts: list[str], chars: np.ndarray, sections) -> tuple[np.ndarray, np.ndarray]:
    own = [np.asarray(sections(t), np.int64)[:-1] for t in texts]
    text = np.repeat(np.arange(len(texts)), [len(b) for b in own])
    return np.concatenate([*own, np.zeros(0, np.int64)]) + chars[text], text


def _counted(column: pa.Array, held: SpanEncoder, rule: str, sections) -> tuple[np.ndarray, ...]:
    """(text, section, start, characters, tokens, crossing tokens) of all sections of the texts."""
    start, end, _, chars = held.spans(column)
    begin, text = _line_bounds(column, chars) if sections is line_sections else _given_bounds([t or "" for t in column.to_pylist()], chars, sections)
    got, cross = attribute(start, end, np.append(begin, chars[-1]), rule)
    size = np.where(np.append(text[1:], -1) == text, np.append(begin[1:], 0), chars[text + 1]) - begin
    first = np.searchsorted(text, text)
    return text, np.arange(len(text)) - first, begin - chars[text], size, got, cross


def section_token_counts(docs: DataFrame, tokenizer: str | None = None, rule: str = "start", sections=line_sections) -> DataFrame:
    """doc_id, section, start, n_chars, n_tokens, n_crossing: one row for each section of each document. `sections` maps
    a text to the starts of its sections (the first is 0) and its length; lines by default."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    path = tokenizer or tokenizer_path("byte_bpe_50k.json")

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        held = SpanEncoder.of(path)
        for part in pieces(batch, most=512 << 10):
            text, section, at, size, n, x = _counted(part.column("text"), held, rule, sections)
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id").take(pa.array(text)), pa.array(section), pa.array(at), pa.array(size), pa.array(n), pa.array(x)],
                ["doc_id", "section", "start", "n_chars", "n_tokens", "n_crossing"],
            )

    return per_batch(docs.select(F.col("doc_id").cast("long"), "text"), work, "doc_id long, section long, start long, n_chars long, n_tokens double, n_crossing long")


def field_token_counts(docs: DataFrame, fields: list[str], tokenizer: str | None = None, rule: str = "start", separator: str = "\n") -> DataFrame:
    """doc_id, field, n_chars, n_tokens, n_crossing: string columns rendered as one text, encoded once, and its tokens
    attributed to the columns. A separator belongs to the field that it ends; a null field is empty."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    path = tokenizer or tokenizer_path("byte_bpe_50k.json")
    names = pa.array(fields)

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        held = SpanEncoder.of(path)
        for part in pieces(batch, most=512 << 10, column="_text"):
            own = np.stack([np.asarray(part.column(f"_n{i}")) for i in range(len(fields))], axis=1)
            start, end, _, chars = held.spans(part.column("_text"))
            size = own + len(separator) * (np.arange(len(fields)) < len(fields) - 1)
            begin = chars[:-1, None] + np.cumsum(size, axis=1) - size
            got, cross = attribute(start, end, np.append(begin.reshape(-1), chars[-1]), rule)
            rows = part.num_rows
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id").take(pa.array(np.repeat(np.arange(rows), len(fields)))), names.take(pa.array(np.tile(np.arange(len(fields)), rows))), pa.array(own.reshape(-1).astype(np.int64)), pa.array(got), pa.array(cross)],
                ["doc_id", "field", "n_chars", "n_tokens", "n_crossing"],
            )

    whole = [F.coalesce(F.col(f).cast("string"), F.lit("")) for f in fields]
    rendered = docs.select(F.col("doc_id").cast("long"), F.concat_ws(separator, *whole).alias("_text"), *[F.char_length(c).cast("long").alias(f"_n{i}") for i, c in enumerate(whole)])
    return per_batch(rendered, work, "doc_id long, field string, n_chars long, n_tokens double, n_crossing long")
