"""Best-fit packing of tokenised documents into sequences of a fixed capacity, by large-item matching.

A document is its ids and an end id. One longer than the capacity is cut into full pieces, the remainder standing first.
What decides the packing is how many pieces there are of each length: at most `capacity` numbers, whatever the corpus.
From them `plan_bins` pairs the items above a third of the capacity (at most two of these fit a bin: the largest left
takes the largest partner that still fits), then places smaller items, longest first, into the tightest gap, and opens
bins for the rest. Pieces get their places by their rank among the pieces of their length, which a hash spreads over
many groups, so that no length is ranked by one task.

Nulls and empty texts are documents of one token (the end id). Repeated rows are packed once each. An empty table gives
no rows. Columns other than doc_id and text are ignored."""

from __future__ import annotations

import bisect
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import per_batch, pieces, stage
from .tokens import ChunkEncoder, tokenizer_path

CAPACITY = 1024
#: Pieces of one length that are ranked together, about: a frequent length has many groups.
RANK_GROUP = 4_000


def token_pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every document."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        encoder = ChunkEncoder.of(tokenizer)
        for part in pieces(batch, most=512 << 10):
            flat, off = encoder.encode_documents(part.column("text"))
            size = np.diff(off)
            head = size % capacity
            count = -(-size // capacity)
            doc = np.repeat(np.arange(len(size)), count)
            piece = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
            short = head[doc] > 0
            start = np.where(short & (piece > 0), head[doc] - capacity, 0) + piece * capacity
            length = np.where(short & (piece == 0), head[doc], capacity)
            raw = flat.astype("<u4").view(np.uint8).data
            at = 4 * (off[doc] + start)
            crc = [zlib.crc32(raw[a:b]) for a, b in zip(at.tolist(), (at + 4 * length).tolist())]
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id").take(pa.array(doc)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc, pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return per_batch(docs.select(F.col("doc_id").cast("long"), "text"), work, "doc_id long, piece int, start long, length long, ids_crc32 long")


def plan_bins(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, list[int]]]:
    """[(number of bins, lengths in each)]: every length as often as it is counted, no bin above the capacity."""
    left = {n: c for n, c in counts.items() if c > 0}
    third = capacity // 3
    large = sorted(n for n in left if n > third)
    bins: list[tuple[int, list[int]]] = []
    while large:
        a = large[-1]
        at = bisect.bisect_right(large, capacity - a) - 1
        if at >= 0 and large[at] == a and left[a] < 2:
            at -= 1
        if at < 0:
            bins.append((left.pop(a), [a]))
            large.pop()
            continue
        b = large[at]
        k = left[a] // 2 if a == b else min(left[a], left[b])
        bins.append((k, [a, b]))
        for n in (a, b):
            left[n] -= k
        for n in {a, b}:
            if not left[n]:
                del left[n]
                large.remove(n)
    gaps: dict[int, list[tuple[int, list[int]]]] = defaultdict(list)
    for k, held in bins:
        gaps[capacity - sum(held)].append((k, held))
    sizes = sorted(gaps)
    for n in sorted((n for n in left if n <= third), reverse=True):
        todo = left[n]
        while todo:
            at = bisect.bisect_left(sizes, n)
            if at == len(sizes):  # new bins
                each = capacity // n
                k = todo // each or 1
                held = [n] * min(each, todo)
            else:
                g = sizes[at]
                k, held = gaps[g].pop()
                if not gaps[g]:
                    del gaps[g]
                    sizes.pop(at)
                each = min(g // n, todo)  # the gap that the first leaves is tighter still
                take = min(k, todo // each)
                if take < k:
                    _put(gaps, sizes, g, (k - take, held))
                k, held = take, held + [n] * each
                todo -= take * each
                _put(gaps, sizes, capacity - sum(held), (k, held))
                continue
            todo -= k * len(held)
            _put(gaps, sizes, capacity - sum(held), (k, held))
    return [x for g in sorted(gaps) for x in gaps[g]]


def _put(gaps: dict, sizes: list[int], gap: int, group: tuple[int, list[int]]) -> None:
    if gap not in gaps:
        bisect.insort(sizes, gap)
    gaps[gap].append(group)


def slots(bins: list[tuple[int, list[int]]], capacity: int = CAPACITY) -> dict[int, tuple[np.ndarray, ...]]:
    """By length: first rank of each run of places, its first sequence, its offset in the sequence."""
    runs: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
    seen: dict[int, int] = defaultdict(int)
    base = 0
    for k, held in bins:
        at = 0
        for n in held:
            runs[n].append((seen[n], base, at))
            seen[n] += k
            at += n
        base += k
    return {n: tuple(np.array(x, np.int64) for x in zip(*r)) for n, r in runs.items()}


def pack(cut_pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """cut_pieces (doc_id, piece, length, ...) with sequence_id and offset added. Read several times: stage it first."""
    counts = {r["length"]: r["n"] for r in cut_pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    place = slots(plan_bins(counts, capacity), capacity)
    groups = F.create_map(*[F.lit(x) for n, c in sorted(counts.items()) for x in (n, c // RANK_GROUP + 1)]) if counts else F.create_map(F.lit(0), F.lit(1))
    spread = cut_pieces.withColumn("_group", F.pmod(F.xxhash64("doc_id", "piece"), groups[F.col("length")]))
    before = (
        spread.groupBy("length", "_group").agg(F.count("*").alias("_n"))
        .withColumn("_before", F.sum("_n").over(Window.partitionBy("length").orderBy("_group").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n"))
        .drop("_n")
    )
    in_group = F.row_number().over(Window.partitionBy("length", "_group").orderBy("doc_id", "piece"))
    ranked = spread.withColumn("_rank", in_group - 1).join(before, ["length", "_group"]).withColumn("_rank", F.col("_rank") + F.col("_before"))
    kept = [f.name for f in cut_pieces.schema.fields]

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        length, rank = np.asarray(batch.column("length")), np.asarray(batch.column("_rank"))
        seq, off = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
        for n in np.unique(length):
            rows = np.flatnonzero(length == n)
            first, base, at = place[int(n)]
            run = np.searchsorted(first, rank[rows], "right") - 1
            seq[rows], off[rows] = base[run] + rank[rows] - first[run], at[run]
        return pa.RecordBatch.from_arrays([batch.column(c) for c in kept] + [pa.array(seq), pa.array(off)], [*kept, "sequence_id", "offset"])

    out = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cut_pieces.schema.fields)
    return per_batch(ranked.select(*kept, "_rank"), work, f"{out}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    path = tokenizer or tokenizer_path("byte_bpe_50k.json")
    return pack(stage(token_pieces(docs, path, capacity), "pieces"), capacity)
