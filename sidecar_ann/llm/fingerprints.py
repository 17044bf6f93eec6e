"""I-Match fingerprints over several randomised lexicons.

The lexicon is the band of terms whose document frequency lies between two shares of the corpus (so between two inverse
document frequencies). Documents are counted once for each group of equal or near-equal texts: a sketch of KEYS keys
stands for each text, and a text counts by one over the number of texts that share its commonest key, so that a group
adds up to about one, however large; keys that fewer than a quarter of the lower share of texts have count as single. A
term is a run of bytes between white space. At most (mean distinct terms of a group) / LOW terms can reach the lower
share, so the lexicon that every task holds is bounded whatever the corpus; frequencies are counted by hash range.

A fingerprint keeps a document's distinct terms of the lexicon and hashes SUBSETS random part-lexicons: a part-lexicon of
level l takes a term with chance 2**-l. The level follows the number of terms kept so that about one of them falls into
each part, and the next level is hashed too, because a text with small edits may be one level off. (Whole lexicons, level
0, would tell only whether all terms are equal.) A part's hash is the sum of the mixed distinct terms that fell in, which
is the same for the same set without another sort, cut to 32 bits: two sets are taken for equal with a chance of 2**-32.
`likeness` is the share of parts with equal hashes at a common level, counting parts in which either text has a term.

A text with less than a quarter of its distinct terms (or than LEAST of them) in the band fills up to that number: first
with its terms below the band, in the order of their hashes, then with those above it, the rarest first. So small edits
change few of the terms kept, also in a rare language or in a text of frequent words only.

Null texts are empty. A text without any term hashes its content instead (level x). Equal texts always have equal
fingerprints. Repeated rows repeat. An empty table gives no rows. Columns other than doc_id and text are ignored."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import MIX, MIX2, mix64, own_worker, partitions, per_batch, pieces, span_hashes, stage, text_bytes, words

SUBSETS = 32
#: Band of document frequency, as shares of all groups of near-equal texts.
LOW, HIGH = 1 / 2000, 1 / 20
#: Keys of a text's sketch, each of two min-hashes over runs of three words: at a likeness of 0.6, 97 % share one or more.
KEYS = 8
#: Terms that a text keeps at least, if it has so many, and the least share of its distinct terms.
LEAST, SHARE = 8, 0.25
#: Weight of a single document in weighted counts, which are whole numbers so that their order does not matter.
UNIT = 1 << 24
_ROUND = np.uint64(16)


def distinct_terms(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, term hash) of the distinct terms of each text, ordered."""
    start, end, row = words(data, off)
    term = span_hashes(data, start, end)
    order = np.lexsort((term, row))
    row, term = row[order], term[order]
    keep = np.ones(len(row), bool)
    keep[1:] = (row[1:] != row[:-1]) | (term[1:] != term[:-1])
    return row[keep], term[keep]


def sketches(data: np.ndarray, off: np.ndarray) -> np.ndarray:
    """(texts, KEYS) keys; near-equal texts share some, equal ones all, and texts without words have the same."""
    start, end, row = words(data, off)
    out = np.zeros((len(off) - 1, KEYS), np.uint64)
    if len(row):
        h = span_hashes(data, start, end)
        run = h * np.uint64(3)
        for ahead, code in ((1, MIX), (2, MIX2)):
            run[:-ahead] += np.where(row[ahead:] == row[:-ahead], h[ahead:], np.uint64(0)) * code
        run = mix64(run)
        first = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]]))
        odd = mix64(np.arange(1, 2 * KEYS + 1, dtype=np.uint64)) | np.uint64(1)
        least = [np.minimum.reduceat(run * c, first) for c in odd]
        for k in range(KEYS):
            out[row[first], k] = mix64(least[2 * k] + mix64(least[2 * k + 1]))
    return mix64(out + np.arange(KEYS, dtype=np.uint64) * MIX)


def weights(keys: np.ndarray, heavy: np.ndarray) -> np.ndarray:
    """UNIT over the number of texts that share a text's commonest key."""
    at = np.minimum(np.searchsorted(heavy["key"], keys), max(0, len(heavy) - 1))
    n = np.where(heavy["key"][at] == keys, heavy["n"][at], 1).max(1) if len(heavy) else np.ones(len(keys))
    return np.maximum(1, UNIT // n.astype(np.int64)).astype(np.uint64)


def heavy_keys(docs: DataFrame, low: float = LOW) -> tuple[np.ndarray, int]:
    """(key, n) of the keys that many texts share, ordered, at most 4 * KEYS / low of them; and the documents' weight."""
    kind = np.dtype([("key", "<u8"), ("n", "<u8")])
    buckets = partitions(docs.sparkSession)

    def sketch(batch: pa.RecordBatch) -> pa.RecordBatch:
        got = [sketches(*text_bytes(part.column("text"))) for part in pieces(batch)]
        return pa.RecordBatch.from_pydict({"n": [sum(map(len, got))], "data": pa.array([b"".join(x.tobytes() for x in got)], pa.binary())})

    held = stage(per_batch(docs.select("text"), sketch, "n long, data binary"), "sketches")
    n = held.agg(F.sum("n")).first()[0] or 0
    least = max(2, n * low / 4)

    def deal(batch: pa.RecordBatch) -> pa.RecordBatch:
        key, count = np.unique(np.frombuffer(b"".join(batch.column("data").to_pylist()), "<u8"), return_counts=True)
        rows = np.zeros(len(key), kind)
        rows["key"], rows["n"] = key, count
        bucket = (key % np.uint64(buckets)).astype(np.int32)
        there = np.unique(bucket)
        return pa.RecordBatch.from_pydict({"bucket": pa.array(there), "data": pa.array([rows[bucket == b].tobytes() for b in there], pa.binary())})

    def many(table: pa.Table) -> pa.Table:
        rows = np.frombuffer(b"".join(table.column("data").to_pylist()), kind)
        key, inverse = np.unique(rows["key"], return_inverse=True)
        out = np.zeros(len(key), kind)
        out["key"], out["n"] = key, np.bincount(inverse, rows["n"], len(key))
        return pa.table({"data": pa.array([out[out["n"] >= least].tobytes()], pa.binary())})

    got = per_batch(held, deal, "bucket int, data binary").groupBy("bucket").applyInArrow(many, "data binary").collect()
    heavy = np.sort(np.frombuffer(b"".join(bytes(r[0]) for r in got), kind), order="key")

    def weigh(batch: pa.RecordBatch) -> pa.RecordBatch:
        keys = np.frombuffer(b"".join(batch.column("data").to_pylist()), "<u8").reshape(-1, KEYS)
        return pa.RecordBatch.from_pydict({"w": [int(weights(keys, heavy).sum())]})

    return heavy, int(per_batch(held, weigh, "w long").agg(F.sum(F.col("w").cast("decimal(38,0)"))).first()[0] or 0)


FREQUENCY = np.dtype([("term", "<u8"), ("n", "<u8")])


def document_frequencies(docs: DataFrame, heavy: np.ndarray | None = None, low: float = 0.0, high: float = math.inf) -> DataFrame:
    """Blobs of (term hash, document frequency), exact: each task counts its batch, hash ranges add up the counts. With
    the heavy keys, documents count by their weights, otherwise by 1. data: frequencies from low to high, above: higher
    ones; lower ones are left out."""
    buckets = 4 * partitions(docs.sparkSession)

    def count(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        term, n = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
        held: list[tuple] = []
        for part in pieces(batch, most=1 << 20):
            data, off = text_bytes(part.column("text"))
            row, own = distinct_terms(data, off)
            w = np.ones(len(off) - 1, np.uint64) if heavy is None else weights(sketches(data, off), heavy)
            held.append(_added(own, w[row]))
            if sum(len(t) for t, _ in held) > len(term):  # as in merging runs: each entry is moved a few times only
                term, n = _added(*(np.concatenate(x) for x in zip((term, n), *held)))
                held = []
        term, n = _added(*(np.concatenate(x) for x in zip((term, n), *held)))
        bucket = (term >> np.uint64(32)) % np.uint64(buckets)
        order = np.argsort(bucket, kind="stable")
        term, n, bucket = term[order], n[order], bucket[order]
        cuts = np.flatnonzero(np.diff(bucket)) + 1
        lead = bucket[np.concatenate([[0], cuts])] if len(bucket) else bucket
        split = lambda x: pa.array([y.tobytes() for y in np.split(x, cuts)] if len(x) else [], pa.binary())
        yield pa.RecordBatch.from_pydict({"bucket": pa.array(lead.astype(np.int32)), "terms": split(term), "sums": split(n)})

    def total(table: pa.Table) -> pa.Table:
        own_worker(__name__)
        term, n = _added(*(np.frombuffer(b"".join(table.column(c).to_pylist()), "<u8") for c in ("terms", "sums")))
        out = np.zeros(len(term), FREQUENCY)
        out["term"], out["n"] = term, n
        return pa.table({"data": pa.array([out[(n >= low) & (n <= high)].tobytes()], pa.binary()), "above": pa.array([out[n > high].tobytes()], pa.binary())})

    return per_batch(docs.select("text"), count, "bucket int, terms binary, sums binary").groupBy("bucket").applyInArrow(total, "data binary, above binary")


def _added(term: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(term):
        return term, n
    order = np.argsort(term, kind="stable")
    term, n = term[order], n[order]
    lead = np.flatnonzero(np.concatenate([[True], term[1:] != term[:-1]]))
    return term[lead], np.add.reduceat(n, lead)


def lexicon(docs: DataFrame, low: float = LOW, high: float = HIGH) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted hashes of the terms within the band; those of the terms above it, and the places of these by frequency."""
    heavy, whole = heavy_keys(docs, low)
    got = document_frequencies(docs, heavy, whole * low, whole * high).collect()
    inside, above = (np.sort(np.frombuffer(b"".join(bytes(r[i]) for r in got), FREQUENCY), order="term") for i in (0, 1))
    place = np.zeros(len(above), np.uint64)
    place[np.lexsort((above["term"], above["n"]))] = np.arange(len(above), dtype=np.uint64)
    return inside["term"].copy(), above["term"].copy(), place


def part_hashes(row: np.ndarray, term: np.ndarray, level: np.ndarray, n: int) -> np.ndarray:
    """(n, SUBSETS) hashes at each row's level, 0 where no term falls into the part. Terms come sorted in each row, and
    each part sums the mixed terms, which is the same for the same set."""
    out = np.zeros((n, SUBSETS), np.uint64)
    if not len(row):
        return out
    limit = np.left_shift(np.uint64(1), np.uint64(64) - level.astype(np.uint64)) - np.uint64(1)
    limit = np.where(level == 0, np.uint64(0xFFFFFFFFFFFFFFFF), limit)[row]
    first = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]]))
    for k in range(SUBSETS):
        draw = mix64(term + np.uint64((k + 1) * int(MIX) & 0xFFFFFFFFFFFFFFFF))
        value = np.where(draw <= limit, mix64(term ^ np.uint64(0xA5A5A5A5 + k)), np.uint64(0))
        out[row[first], k] = np.add.reduceat(value, first)
    return out


def _among(sorted_terms: np.ndarray, term: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(sorted_terms):
        return np.zeros(len(term), np.int64), np.zeros(len(term), bool)
    at = np.minimum(np.searchsorted(sorted_terms, term), len(sorted_terms) - 1)
    return at, sorted_terms[at] == term


def kept_terms(row: np.ndarray, term: np.ndarray, n: int, terms: tuple[np.ndarray, np.ndarray, np.ndarray]) -> np.ndarray:
    """Which of the distinct terms of n texts stay: those in the band, and where they are few, the terms nearest to it."""
    inside, above, place = terms
    keep = _among(inside, term)[1]
    held, distinct = np.bincount(row[keep], minlength=n), np.bincount(row, minlength=n)
    short = np.maximum(LEAST, np.ceil(SHARE * distinct)).astype(np.int64) - held
    spare = np.flatnonzero(~keep & (short[row] > 0))
    if len(spare):
        at, frequent = _among(above, term[spare])
        turn = mix64(term[spare]) >> np.uint64(1)
        turn[frequent] = place[at[frequent]] + np.uint64(1 << 63)
        spare = spare[np.lexsort((turn, row[spare]))]
        own = row[spare]
        rank = np.arange(len(own)) - np.searchsorted(own, own)
        keep[spare[rank < short[own]]] = True
    return keep


def fingerprints(texts: list[bytes], terms: tuple[np.ndarray, np.ndarray, np.ndarray]) -> list[str]:
    data = np.frombuffer(b"".join(texts), np.uint8)
    off = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
    row, term = distinct_terms(data, off)
    keep = kept_terms(row, term, len(texts), terms)
    row, term = row[keep], term[keep]
    held = np.bincount(row, minlength=len(texts))
    level = np.floor(np.log2(np.maximum(held, 1))).astype(np.int64)
    low, high = part_hashes(row, term, level, len(texts)), part_hashes(row, term, level + 1, len(texts))
    short = lambda h: "".join(f"{int(x) >> 32 or 1:08x}" if x else "00000000" for x in h)
    return [f"{lv}:{short(a)}|{lv + 1}:{short(b)}" if n else f"x:{hashlib.md5(t).hexdigest()}" for t, n, lv, a, b in zip(texts, held, level, low, high)]


def likeness(a: str, b: str) -> float:
    if a == b:
        return 1.0
    x, y = (dict(p.split(":") for p in f.split("|")) for f in (a, b))
    best = 0.0
    for level in x.keys() & y.keys():
        if level == "x":
            continue
        u, v = x[level], y[level]
        pairs = [(u[i : i + 8], v[i : i + 8]) for i in range(0, 8 * SUBSETS, 8)]
        live = [p for p in pairs if p != ("00000000", "00000000")]
        if live:
            best = max(best, sum(p == q for p, q in live) / len(live))
    return best


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id, size, body (the text's bytes, compressed), _ahead in sorted parts: each part ends with a copy (_ahead = 1)
    of the first row of the part that follows, the last with the first row of all. One copied row a part; ids and not
    texts decide the cut points. Texts are compressed before they are sent: this is the only shuffle of whole texts."""
    spark = docs.sparkSession
    base = docs.select(F.col("doc_id").cast("long"), "text")
    ids = base.select("doc_id")
    bounds = np.array(_bounds(ids, partitions(spark)), np.int64)
    parts = len(bounds) + 1

    def part_of(doc: pa.Array) -> np.ndarray:
        found = np.searchsorted(bounds, np.asarray(pc.fill_null(doc, 0)), "right")
        found[np.asarray(doc.is_null())] = 0
        return found

    def firsts(batch: pa.RecordBatch) -> pa.RecordBatch:
        part = part_of(batch.column("doc_id"))
        return pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), batch.column("doc_id")], ["part", "doc_id"])

    least = per_batch(ids, firsts, "part int, doc_id long").groupBy("part").agg(F.min(F.struct(F.col("doc_id").isNotNull().alias("known"), "doc_id")).alias("x"))
    first = {r["part"]: r["x"]["doc_id"] for r in least.collect()}
    there = sorted(first)
    before = {first[p]: there[i - 1] for i, p in enumerate(there)}  # id of a first row -> the part that it follows

    def send(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        codec = pa.Codec("zstd", compression_level=1)
        for some in pieces(batch):
            doc = some.column("doc_id")
            part = part_of(doc)
            ahead = np.array([before.get(d, -1) for d in doc.to_pylist()], np.int64) if some.num_rows else np.zeros(0, np.int64)
            copied = np.flatnonzero(ahead >= 0)
            raw = [(t or "").encode() for t in some.column("text").to_pylist()]
            size, body = [len(r) for r in raw], [codec.compress(r, asbytes=True) for r in raw]
            pick = np.concatenate([np.arange(some.num_rows), copied])
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.concatenate([part, ahead[copied]]), pa.int32()), pa.array(np.concatenate([np.zeros(some.num_rows), np.ones(len(copied))]), pa.int32()),
                 doc.take(pa.array(pick)), pa.array([size[i] for i in pick], pa.int64()), pa.array([body[i] for i in pick], pa.binary())],
                ["part", "_ahead", "doc_id", "size", "body"],
            )

    rows = per_batch(base, send, "part int, _ahead int, doc_id long, size long, body binary")
    return rows.repartitionById(parts, "part").sortWithinPartitions("part", "_ahead", F.col("doc_id").asc_nulls_first(), "body")


def _bounds(ids: DataFrame, parts: int) -> list:
    if parts < 2:
        return []
    got = ids.agg(F.percentile_approx("doc_id", [i / parts for i in range(1, parts)], 100 * parts).alias("q")).first()["q"]
    return sorted(set(got or []))


def edited_fingerprints(docs: DataFrame, low: float = LOW, high: float = HIGH) -> DataFrame:
    """One row a document: its fingerprint, that of its text with the last quarter replaced by the head of the next
    document (ascending doc_id, after the last the first; a single document follows itself), and their likeness."""
    terms = lexicon(docs, low, high)
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    names = [c.split()[0] for c in schema.split(", ")]

    def digest(rows: list[tuple], nexts: list[str]) -> pa.RecordBatch:
        texts = [t for _, t in rows]
        edited = [t[: len(t) - len(t) // 4] + n[: len(t) // 4] for t, n in zip(texts, nexts)]
        own = fingerprints([t.encode() for t in texts] + [nexts[-1].encode()], terms)
        cut = [e.encode() for e in edited]
        other = fingerprints(cut, terms)
        cols = [[d for d, _ in rows], [len(t) for t in texts], [hashlib.sha256(e).hexdigest() for e in cut], own[:-1], other]
        cols += [[likeness(a, b) for a, b in zip(own, other)], [likeness(a, b) for a, b in zip(own, own[1:])]]
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_worker(__name__)
        held: list[tuple] = []  # rows whose next is not seen yet come last
        size, at = 0, None
        codec = pa.Codec("zstd", compression_level=1)
        for batch in batches:
            rows = zip(*(batch.column(c).to_pylist() for c in ("part", "doc_id", "_ahead", "size")), batch.column("body"))
            for part, doc, ahead, n, body in rows:
                text = codec.decompress(body.as_py(), n, asbytes=True).decode() if n else ""
                if ahead:
                    if held and part == at:
                        yield digest(held, [t for _, t in held[1:]] + [text])
                    held, size = [], 0
                    continue
                if size > 1 << 20:
                    yield digest(held, [t for _, t in held[1:]] + [text])
                    held, size = [], 0
                at = part
                held.append((doc, text))
                size += len(text)
        if held:
            raise ValueError("a part without its next row")

    return with_next(docs).mapInArrow(run, schema)
