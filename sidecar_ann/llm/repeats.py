"""Long repeated passages by a run-length index: which bytes of a text stand in a string of LENGTH bytes that starts
earlier, in a document of smaller id or further up in the same one.

How one index over all text is dealt out. Every window of LENGTH bytes has a minimiser, its least hashed GRAM-byte
substring; neighbouring windows that share it form a phrase. Equal windows have equal minimisers, so phrases of one
minimiser can be looked at apart from all others. As in prefix-free parsing, equal phrases are one entry of a dictionary
with a weight (the number of places where they stand) and the first place; a task lets go of all but its first place
before anything is sent, so a passage that stands in a third of all documents costs a bucket one row a task.

Minimisers with two or more different phrases, and phrases that repeat a window within themselves, go to buckets. Each
bucket is indexed: suffixes sorted by doubling, Burrows-Wheeler transform kept as runs, suffix samples at both ends of
each run, and the places where neighbouring suffixes agree in fewer than LENGTH bytes. Every phrase is then streamed
through the runs from its end to its start; the row of each window among those places gives its matching statistic
capped at LENGTH (does it stand elsewhere, too?) and a name for the string, under which the earliest place is found. All
other places are marked. For a phrase with no rival, all places but the first are marked at once, since the index of a
single phrase would say no more. The phrases of a minimiser inside a line that very many documents share, with other
text around it, are split once more before they are dealt out (`split_crowded`).

Texts are UTF-8 bytes, null is empty. Rows of equal doc_id are ordered by text, so of repeated rows one keeps its
bytes. A null doc_id comes first. Texts shorter than LENGTH have no
windows. An empty table gives no rows. Columns other than doc_id and text are ignored."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BYTE_CODES, MIX, MIX2, give_back, mix64, own_worker, partitions, per_batch, pieces, span_hashes, stage, text_bytes

LENGTH, GRAM = 100, 32
#: Most windows of a phrase; longer runs of one minimiser (periodic text) are cut.
PHRASE = 128
#: Places that a task gathers before it deals them out (31 bytes each, about three times that while they are sorted).
HELD = 1 << 19
#: Phrases that one minimiser may bring to one bucket whole (about 0.3 MB); of more, each is split and dealt out anew.
CROWD = 2000
STEP = 18

#: A place of a phrase: minimiser, content, document, start, number of windows, whether it repeats a window itself
#: (1; CROWDED is added where its minimiser has very many phrases).
PLACE = np.dtype([("gram", "<u8"), ("text", "<u8"), ("doc", "<i8"), ("start", "<u4"), ("n", "<u2"), ("self", "u1")])
CROWDED = 2
MARK = np.dtype([("doc", "<i8"), ("start", "<u4"), ("n", "<u2")])


# ---------------------------------------------------------------- phrases
def gram_hashes(data: np.ndarray, block: int = 1 << 16) -> np.ndarray:
    """Hash of the GRAM bytes at each place (GRAM a power of two), by doubling."""
    n = len(data) - GRAM + 1
    out = np.empty(max(n, 0), np.uint64)
    for s in range(0, max(n, 0), block):
        h = BYTE_CODES[data[s : min(s + block, n) + GRAM - 1]]
        w = 1
        while w < GRAM:
            h = h[:-w] * MIX + (h[w:] ^ (h[w:] >> np.uint64(29)))
            h ^= h >> np.uint64(32)
            h *= MIX2
            w *= 2
        out[s : s + len(h)] = h
    return out


def _least(h: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
    """Least of each `span` neighbours and whether it stands there twice, from disjoint blocks of powers of two."""
    size, low, tie = 1, h, np.zeros(len(h), bool)
    done, got, twice = 0, None, None
    while True:
        if span & size:
            m = len(h) - span + 1
            a, t = low[done : done + m], tie[done : done + m]
            if got is None:
                got, twice = a, t
            else:
                twice = np.where(got == a, True, np.where(got < a, twice, t))
                got = np.minimum(got, a)
            done += size
        if size * 2 > span:
            return got, twice
        tie = np.where(low[:-size] == low[size:], True, np.where(low[:-size] < low[size:], tie[:-size], tie[size:]))
        low = np.minimum(low[:-size], low[size:])
        size *= 2


def phrases(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, ...]:
    """(row, start in the row, windows, minimiser, content hash, repeats itself) of each phrase, in text order."""
    none = np.zeros(0, np.int64)
    empty = (none, none, none, none.astype(np.uint64), none.astype(np.uint64), none.astype(bool))
    if len(data) < LENGTH:
        return empty
    grams = gram_hashes(data)
    least, twice = _least(grams, LENGTH - GRAM + 1)
    last = off[1:] - LENGTH  # last window of each text
    whole = np.flatnonzero(last >= off[:-1])
    if not len(whole):
        return empty
    edge = np.zeros(len(least) + 1, np.int32)
    edge[off[whole]] += 1
    edge[last[whole] + 1] -= 1
    inside = np.cumsum(edge[:-1]) > 0
    begin = inside.copy()
    begin[1:] &= (least[1:] != least[:-1]) | ~inside[:-1]
    begin[off[whole]] = True
    start = np.flatnonzero(begin)
    row = np.searchsorted(off, start, "right") - 1
    upto = np.minimum(np.append(start[1:], len(least)), last[row] + 1)
    n = upto - start
    cuts = -(-n // PHRASE)
    if (cuts > 1).any():
        k = np.repeat(np.arange(len(start)), cuts)
        at = np.arange(len(k)) - np.repeat(np.cumsum(cuts) - cuts, cuts)
        long = n > PHRASE
        start, n, row, periodic = start[k] + at * PHRASE, np.minimum(n[k] - at * PHRASE, PHRASE), row[k], long[k]
    else:
        periodic = np.zeros(len(start), bool)
    ties = np.concatenate([[0], np.cumsum(twice)])
    own = periodic | (n > LENGTH - GRAM + 1) | (ties[start + n] > ties[start])
    size = n + LENGTH - 1
    text = mix64(size.astype(np.uint64) * MIX)
    for k in range(0, PHRASE + LENGTH, GRAM):
        text = mix64(text ^ grams[start + np.minimum(k, size - GRAM)])
    return row, start - off[row], n, least[start], text, own


def _first_places(p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places sorted by minimiser, content and place; whether each is the first of its phrase."""
    p = p[np.lexsort((p["start"], p["doc"], p["text"], p["gram"]))]
    first = np.ones(len(p), bool)
    first[1:] = (p["gram"][1:] != p["gram"][:-1]) | (p["text"][1:] != p["text"][:-1])
    return p, first


def _marks(p: np.ndarray) -> np.ndarray:
    out = np.zeros(len(p), MARK)
    for c in MARK.names:
        out[c] = p[c]
    return out


def _cuts(bucket: np.ndarray) -> np.ndarray:
    """Where each run of equal buckets begins, and the end."""
    return np.concatenate([np.flatnonzero(np.diff(bucket, prepend=-1)), [len(bucket)]])


def _binary(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    """Bytes cut at `ends` (the first is 0), as they lie in memory: blobs grow in number with the square of the table, so
    none may cost a step of Python."""
    return pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(data)])


def _joined(column: pa.ChunkedArray, kind: np.dtype) -> np.ndarray:
    """The rows in all blobs of a column, in order."""
    parts = [text_bytes(c)[0] for c in column.chunks if len(c)]
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint8)).view(kind)


def _blobs(kind: int, bucket: np.ndarray, rows: np.ndarray) -> pa.RecordBatch:
    """One blob for each bucket."""
    order = np.argsort(bucket, kind="stable")
    rows, bucket = rows[order], bucket[order]
    cuts = _cuts(bucket)
    lead = bucket[cuts[:-1]].astype(np.int32)
    columns = [np.full(len(lead), kind, np.int32), lead, _binary(rows.view(np.uint8), cuts * rows.itemsize)]
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["kind", "bucket", "data"])


def _doc_bucket(doc: np.ndarray, buckets: int) -> np.ndarray:
    return (mix64(doc.astype(np.uint64)) % np.uint64(buckets)).astype(np.int64)


def _gram_bucket(gram: np.ndarray, buckets: int) -> np.ndarray:
    return (mix64(gram) % np.uint64(buckets)).astype(np.int64)


SCHEMA = "kind int, bucket int, data binary"


#: Kinds of blobs: places by bucket of the minimiser, marks and phrases wanted by bucket of the document, their texts.
PLACES, MARKS, WANTED = 0, 1, 2


def phrase_places(docs: DataFrame, buckets: int) -> DataFrame:
    """Blobs of the first place of each phrase, and marks for its other places. A task gathers up to HELD places before
    it deals them out, so that blobs hold as much as its share of the table allows."""

    def deal(held: list) -> Iterator[pa.RecordBatch]:
        p, first = _first_places(np.concatenate(held))
        again, p = _marks(p[~first]), p[first]
        yield _blobs(PLACES, _gram_bucket(p["gram"], buckets), p)
        yield _blobs(MARKS, _doc_bucket(again["doc"], buckets), again)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_worker(__name__)
        held, n_held = [], 0
        for batch in batches:
            for part in pieces(batch):
                data, off = text_bytes(part.column("text"))
                row, start, n, gram, text, own = phrases(data, off)
                p = np.zeros(len(row), PLACE)
                p["gram"], p["text"], p["doc"], p["start"], p["n"], p["self"] = gram, text, np.asarray(part.column("_doc"))[row], start, n, own
                held.append(p)
                n_held += len(p)
                if n_held >= HELD:
                    yield from deal(held)
                    held, n_held = [], 0
        if n_held:
            yield from deal(held)
        give_back()

    return docs.select("_doc", "text").mapInArrow(run, SCHEMA)


def rivals(places: DataFrame, buckets: int, crowd: int) -> DataFrame:
    """For each bucket of minimisers: marks for all but the first place of each phrase, and the phrases wanted for an
    index (minimisers with several phrases, phrases that repeat themselves; CROWDED is set where there are more than
    `crowd` of them). Out: blobs by bucket of the document."""

    def settle(table: pa.Table) -> pa.Table:
        p, first = _first_places(_joined(table.filter(pc.field("kind") == PLACES).column("data"), PLACE))
        again = np.concatenate([_joined(table.filter(pc.field("kind") == MARKS).column("data"), MARK), _marks(p[~first])])
        p = p[first]
        _, n = np.unique(p["gram"], return_counts=True)
        n = np.repeat(n, n)  # phrases of the minimiser of each
        wanted = (n > 1) | (p["self"] > 0)
        p["self"][n > crowd] |= CROWDED
        want = p[wanted]
        return pa.Table.from_batches([_blobs(MARKS, _doc_bucket(again["doc"], buckets), again), _blobs(WANTED, _doc_bucket(want["doc"], buckets), want)])

    return places.groupBy("bucket").applyInArrow(settle, SCHEMA)


def split_crowded(want: np.ndarray, at: np.ndarray, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(parts, their places in data) of phrases at `at`. Windows are dealt by where their minimiser first stands in them,
    in steps of STEP bytes, and by the LENGTH - STEP + 1 bytes that all windows of such a step share; these and the
    minimiser name the part. Equal windows have their minimiser at the same place and share those bytes, so their parts
    have one name, and parts of other surroundings have other names."""
    n = want["n"].astype(np.int64)
    size = n + LENGTH - 1
    off = np.cumsum(size) - size
    body = data[np.repeat(at - off, size) + np.arange(int(size.sum()))]
    grams = gram_hashes(body)
    hit = np.where(grams == np.repeat(want["gram"], size)[: len(grams)], np.arange(len(grams)), len(grams))
    following = np.minimum.accumulate(hit[::-1])[::-1]
    phrase = np.repeat(np.arange(len(want)), n)
    inside = np.arange(len(phrase)) - np.repeat(np.cumsum(n) - n, n)
    place = following[off[phrase] + inside]
    step = (place - off[phrase] - inside) // STEP
    begin = np.ones(len(phrase), bool)
    begin[1:] = (phrase[1:] != phrase[:-1]) | (place[1:] != place[:-1]) | (step[1:] != step[:-1])
    first = np.flatnonzero(begin)
    parts = want[phrase[first]]
    parts["start"] += inside[first].astype(np.uint32)
    parts["n"] = np.diff(np.append(first, len(phrase)))
    core = place[first] - STEP * step[first]
    parts["gram"] = mix64(parts["gram"] ^ span_hashes(body, core, core + LENGTH - STEP + 1))
    return parts, at[phrase[first]] + inside[first]


def phrase_texts(docs: DataFrame, wanted: DataFrame, buckets: int) -> DataFrame:
    """Blobs by bucket of the minimiser (for parts of crowded ones: of the name of the part): the wanted phrases and
    their bytes."""

    def fetch(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        want = _joined(right.column("data"), PLACE)
        if not len(want):
            return pa.table({"bucket": pa.array([], pa.int32()), "places": pa.array([], pa.binary()), "data": pa.array([], pa.binary())})
        ids = np.asarray(left.column("_doc"))
        order = np.argsort(ids, kind="stable")
        row = order[np.searchsorted(ids[order], want["doc"])]
        text = left.column("text").combine_chunks()
        data, off = text_bytes(text.chunk(0) if isinstance(text, pa.ChunkedArray) else text)
        raw = data.tobytes()
        at = off[row] + want["start"]
        crowded = want["self"] & CROWDED > 0
        if crowded.any():
            parts, places = split_crowded(want[crowded], at[crowded], data)
            want, at = np.concatenate([want[~crowded], parts]), np.concatenate([at[~crowded], places])
        bucket = _gram_bucket(want["gram"], buckets)
        by = np.argsort(bucket, kind="stable")
        want, at, bucket = want[by], at[by], bucket[by]
        size = want["n"].astype(np.int64) + LENGTH - 1
        cuts = _cuts(bucket)
        bodies = b"".join([raw[s : s + n] for s, n in zip(at.tolist(), size.tolist())])
        ends = np.concatenate([[0], np.cumsum(size)])[cuts]
        return pa.table({"bucket": pa.array(bucket[cuts[:-1]], pa.int32()), "places": _binary(want.view(np.uint8), cuts * PLACE.itemsize), "data": _binary(bodies, ends)})

    return _by_doc(docs, buckets).cogroup(wanted.groupBy("bucket")).applyInArrow(fetch, "bucket int, places binary, data binary")


# ---------------------------------------------------------------- the index
class RunLengthIndex:
    """Burrows-Wheeler transform of a set of texts as runs, with suffix samples at the ends of runs.

    Texts are bytes; each ends with a mark of its own, smaller than any byte and ordered by text number. `starts` of a
    symbol's runs answer rank queries by binary search; `breaks` are the rows whose suffix agrees with the one before it
    in fewer than `depth` bytes."""

    def __init__(self, data: np.ndarray, off: np.ndarray, depth: int = LENGTH):
        self.depth, self.texts = depth, len(off) - 1
        size = np.diff(off)
        self.end = off[1:] + np.arange(self.texts)  # place of each mark
        self.n = len(data) + self.texts
        symbols = np.zeros(self.n, np.int64)
        symbols[np.arange(len(data)) + np.repeat(np.arange(self.texts), size)] = data.astype(np.int64) + 1
        self.symbols = symbols
        rank = self._sort(symbols)
        order = np.empty(self.n, np.int64)
        order[rank] = np.arange(self.n)  # suffix array
        before = np.where(order > 0, symbols[order - 1], 0)
        change = np.ones(self.n, bool)
        change[1:] = before[1:] != before[:-1]
        self.run_start = np.flatnonzero(change)
        self.run_symbol = before[self.run_start]
        run_end = np.append(self.run_start[1:], self.n)
        self.sample_first, self.sample_last = order[self.run_start], order[run_end - 1]
        by = np.lexsort((self.run_start, self.run_symbol))
        self.key = self.run_symbol[by] * (self.n + 1) + self.run_start[by]
        length = (run_end - self.run_start)[by]
        # rows of smaller symbols and of earlier runs of the symbol: where a run's rows go when read backwards
        self.target = np.cumsum(length) - length
        self.key_start = self.run_start[by]
        self._breaks(order)

    def _sort(self, symbols: np.ndarray) -> np.ndarray:
        """Rank of each suffix: as many symbols at once as a word holds, then doubling among those not yet told apart."""
        n, texts = self.n, self.texts
        stop = np.repeat(self.end, np.diff(np.concatenate([[-1], self.end])))  # the mark that ends each place's text
        code = np.zeros(257, np.uint64)
        used = np.flatnonzero(np.bincount(symbols, minlength=257)[1:]) + 1
        code[used] = np.arange(1, len(used) + 1)
        bits = len(used).bit_length()
        width = 63 // max(bits, 1)
        padded = np.concatenate([code[symbols], np.zeros(width, np.uint64)])
        key, live = np.zeros(n, np.uint64), np.ones(n, bool)
        for k in range(width):
            key = key << np.uint64(bits) | np.where(live, padded[k : k + n], np.uint64(0))
            live &= padded[k : k + n] > 0
        del live, padded
        by = np.argsort(key)
        key = key[by]
        group = np.ones(n, bool)
        group[1:] = key[1:] != key[:-1]
        del key
        rank = np.empty(n, np.int64)
        rank[by] = np.maximum.accumulate(np.where(group, np.arange(n), 0))
        rank[self.end] = np.arange(texts)  # marks are the least suffixes, each of its own
        alone = group & np.append(group[1:], True)
        alone[:texts] = True
        open_ = by[~alone]
        while len(open_):
            r, o = rank[open_], rank[np.minimum(open_ + width, stop[open_])]
            by = np.argsort(r * n + o)
            open_, r, o = open_[by], r[by], o[by]
            group = np.ones(len(by), bool)
            group[1:] = r[1:] != r[:-1]
            at = np.arange(len(by))
            inside = at - np.maximum.accumulate(np.where(group, at, 0))
            group[1:] |= o[1:] != o[:-1]
            rank[open_] = np.maximum.accumulate(np.where(group, r + inside, 0))
            open_ = open_[~(group & np.append(group[1:], True))]
            width *= 2
        return rank

    def _breaks(self, order: np.ndarray) -> None:
        """Rows at which the first `depth` bytes differ from those of the row before."""
        text = np.searchsorted(self.end, order)
        room = self.end[text] - order >= self.depth
        same = np.zeros(self.n, bool)
        pair = np.flatnonzero(room[1:] & room[:-1]) + 1
        a, b = order[pair - 1], order[pair]
        words = np.concatenate([self.symbols, np.zeros(8, np.int64)])
        alive = np.arange(len(pair))
        # eight bytes at a time, only for pairs that agree so far
        packed = np.zeros(self.n, np.uint64)
        for k in range(7):
            packed = packed << np.uint64(9) | words[k : k + self.n].astype(np.uint64)
        for k in [*range(0, self.depth - 7, 7), self.depth - 7]:
            alive = alive[packed[a[alive] + k] == packed[b[alive] + k]]
        same[pair[alive]] = True
        self.breaks = np.flatnonzero(~same)

    def back(self, row: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """Row of the suffix one symbol longer, for rows that the symbol stands before."""
        run = np.searchsorted(self.key, symbol * (self.n + 1) + row, "right") - 1
        return self.target[run] + row - self.key_start[run]

    def stream(self) -> np.ndarray:
        """Row of each place, all texts read backwards in step from their marks."""
        out = np.empty(self.n, np.int64)
        row = np.arange(self.texts)  # the marks' rows
        out[self.end] = row
        at = self.end.copy()
        first = np.concatenate([[0], self.end[:-1] + 1])
        live = np.flatnonzero(at > first)
        while len(live):
            at[live] -= 1
            row[live] = self.back(row[live], self.symbols[at[live]])
            out[at[live]] = row[live]
            live = live[at[live] > first[live]]
        return out

    def string_of(self, row: np.ndarray) -> np.ndarray:
        """A name for the `depth` bytes at each row: equal for equal strings."""
        return np.searchsorted(self.breaks, row, "right")

    def matching(self, data: bytes) -> np.ndarray:
        """Matching statistics of a foreign text, capped at `depth`: how many bytes from each place stand in the index.
        Read backwards; where the text leaves the run, the nearest run of its symbol is entered by the sample at its
        end and the length cut to what the two suffixes share."""
        out = np.zeros(len(data), np.int64)
        row, length = 0, 0
        for i in range(len(data) - 1, -1, -1):
            c = data[i] + 1
            at = int(np.searchsorted(self.run_start, row, "right")) - 1
            if self.run_symbol[at] != c:
                run = int(np.searchsorted(self.key, c * (self.n + 1) + row, "right")) - 1
                options = []
                if run >= 0 and self.key[run] // (self.n + 1) == c:
                    k = int(np.searchsorted(self.run_start, self.key_start[run]))
                    end = (self.run_start[k + 1] if k + 1 < len(self.run_start) else self.n) - 1
                    options.append((self._share(int(self.sample_last[k]), data, i + 1, length), end))
                if run + 1 < len(self.key) and self.key[run + 1] // (self.n + 1) == c:
                    k = int(np.searchsorted(self.run_start, self.key_start[run + 1]))
                    options.append((self._share(int(self.sample_first[k]), data, i + 1, length), self.key_start[run + 1]))
                if not options:
                    row, length = 0, 0
                    continue
                length, row = max(options)
            row = int(self.back(np.array([row]), np.array([c]))[0])
            length = min(length + 1, self.depth)
            out[i] = length
        return out

    def _share(self, place: int, data: bytes, at: int, most: int) -> int:
        n = 0
        while n < most and place + n < self.n and self.symbols[place + n] == data[at + n] + 1:
            n += 1
        return n


def repeated_windows(places: np.ndarray, data: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Marks for the windows of the phrases (with their first places) that stand earlier in another place."""
    if not len(places):
        return np.zeros(0, MARK)
    index = RunLengthIndex(data, off)
    rows = index.stream()
    n = places["n"].astype(np.int64)
    phrase = np.repeat(np.arange(len(places)), n)
    inside = np.arange(len(phrase)) - np.repeat(np.cumsum(n) - n, n)
    name = index.string_of(rows[off[:-1][phrase] + phrase + inside])
    start = places["start"][phrase].astype(np.int64) + inside
    order = np.lexsort((start, places["doc"][phrase], name))
    later = np.zeros(len(order), bool)
    later[order[1:]] = name[order][1:] == name[order][:-1]
    # neighbouring windows of a phrase as one mark
    begin = later.copy()
    begin[1:] &= ~(later[:-1] & (phrase[1:] == phrase[:-1]))
    which = np.flatnonzero(begin)
    if not len(which):
        return np.zeros(0, MARK)
    out = np.zeros(len(which), MARK)
    out["doc"], out["start"] = places["doc"][phrase[which]], start[which]
    out["n"] = np.add.reduceat(later, which)
    return out


def thinned(places: np.ndarray, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(places, their bytes, offsets, marks) without what a bucket holds of crowded minimisers needlessly: windows of
    them that hash as no other does are cut out, and of equal remains the first is kept and the others are marked, as
    for whole phrases. A long line that very many documents share would fill the index with its surroundings otherwise."""
    n = places["n"].astype(np.int64)
    ends = np.concatenate([[0], np.cumsum(n)])
    name = np.empty(ends[-1], np.uint64)
    cuts = np.unique(np.searchsorted(off, np.arange(0, off[-1] + (1 << 20), 1 << 20)).clip(0, len(places)))
    for a, b in zip(cuts[:-1], cuts[1:]):
        at = np.repeat(off[a:b] - off[a] - (ends[a:b] - ends[a]), n[a:b]) + np.arange(ends[b] - ends[a])
        name[ends[a] : ends[b]] = span_hashes(data[off[a] : off[b]], at, at + LENGTH)
    phrase = np.repeat(np.arange(len(places)), n)
    order = np.argsort(name)
    same = name[order][1:] == name[order][:-1]
    keep = places["self"][phrase] & CROWDED == 0
    keep[order[1:][same]] = keep[order[:-1][same]] = True
    begin = keep.copy()
    begin[1:] &= ~keep[:-1] | (phrase[1:] != phrase[:-1])
    stop = keep.copy()
    stop[:-1] &= ~keep[1:] | (phrase[1:] != phrase[:-1])
    first, last = np.flatnonzero(begin), np.flatnonzero(stop)
    lead = phrase[first]
    parts = places[lead]
    parts["start"] += (first - ends[lead]).astype(np.uint32)
    parts["n"] = last - first + 1
    at = off[lead] + first - ends[lead]
    text = mix64(parts["n"].astype(np.uint64) * MIX)
    for k in range(int(parts["n"].max(initial=0))):
        inside = parts["n"] > k
        text[inside] = mix64(text[inside] ^ name[first[inside] + k])
    parts["text"] = text
    order = np.lexsort((parts["start"], parts["doc"], text))
    again = np.zeros(len(parts), bool)
    again[order[1:]] = text[order][1:] == text[order][:-1]
    marks, parts, at = _marks(parts[again]), parts[~again], at[~again]
    size = parts["n"].astype(np.int64) + LENGTH - 1
    raw = data.tobytes()
    body = b"".join([raw[s : s + k] for s, k in zip(at.tolist(), size.tolist())])
    return parts, np.frombuffer(body, np.uint8), np.concatenate([[0], np.cumsum(size)]), marks


def index_buckets(texts: DataFrame, buckets: int) -> DataFrame:
    """Marks (blobs by bucket of the document) from an index of each bucket's phrases."""

    def build(table: pa.Table) -> pa.Table:
        p = _joined(table.column("places"), PLACE)
        off = np.concatenate([[0], np.cumsum(p["n"].astype(np.int64) + LENGTH - 1)])
        data, marks = _joined(table.column("data"), np.dtype(np.uint8)), np.zeros(0, MARK)
        if (p["self"] & CROWDED).any():
            p, data, off, marks = thinned(p, data, off)
        got = np.concatenate([marks, repeated_windows(p, data, off)])
        return pa.Table.from_batches([_blobs(MARKS, _doc_bucket(got["doc"], buckets), got)])

    return texts.groupBy("bucket").applyInArrow(build, SCHEMA)


# ---------------------------------------------------------------- what is left
def _by_doc(docs: DataFrame, buckets: int):
    """docs grouped by the bucket of the document, computed as _doc_bucket does."""
    names = docs.columns

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        bucket = _doc_bucket(np.asarray(batch.column("_doc")), buckets).astype(np.int32)
        return pa.RecordBatch.from_arrays([*batch.columns, pa.array(bucket)], [*names, "bucket"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return per_batch(docs, work, f"{fields}, bucket int").groupBy("bucket")


def covered(marks: np.ndarray, size: int) -> list[tuple[int, int]]:
    """Maximal runs of bytes covered by marked windows."""
    if not len(marks):
        return []
    order = np.argsort(marks["start"], kind="stable")
    start = marks["start"][order].astype(np.int64)
    end = np.maximum.accumulate(start + marks["n"][order] + LENGTH - 1)
    new = np.concatenate([[True], start[1:] > end[:-1]])
    first = np.flatnonzero(new)
    return list(zip(start[first].tolist(), end[np.append(first[1:], len(start)) - 1].tolist()))


def numbered(docs: DataFrame) -> DataFrame:
    """doc_id, text and _doc, a long of its own for each row that orders rows by doc_id (null first) and text. Where ids
    are distinct it is the id; else rows are counted in the order of a range shuffle, so that no id and no task holds
    many rows (equal rows are parted by where they were read)."""
    base = docs.select("doc_id", "text")
    ids = base.groupBy("doc_id").agg(F.count("*").alias("n")).agg(F.max("n").alias("most"), F.min("doc_id").alias("low")).first()
    if (ids["most"] or 1) == 1:
        return base.withColumn("_doc", F.coalesce(F.col("doc_id"), F.lit((ids["low"] or 0) - 1)).cast("long"))
    order = (F.col("doc_id").asc_nulls_first(), F.col("text").asc_nulls_first(), F.col("_m").asc())
    dealt = base.withColumn("_m", F.monotonically_increasing_id()).repartitionByRange(partitions(docs.sparkSession), *order).sortWithinPartitions(*order)
    held = stage(dealt.select("doc_id", "text", F.monotonically_increasing_id().alias("_at")), "numbered")
    part = F.shiftright("_at", 33)  # the function puts the partition there
    counts = held.groupBy(part.alias("p")).agg(F.count("*").alias("n")).orderBy("p").collect()  # one row a partition
    start, at = [], 0
    for r in counts:
        start += [F.lit(r["p"]), F.lit(at)]
        at += r["n"]
    base_of = F.element_at(F.create_map(*start), part).cast("long")
    return held.select("doc_id", "text", (base_of + F.col("_at").bitwiseAND((1 << 33) - 1)).alias("_doc"))


def removals(docs: DataFrame, crowd: int = CROWD) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept (the text left), spans ("start:end,...")."""
    spark = docs.sparkSession
    buckets = 4 * partitions(spark)
    base = numbered(docs)
    settled = stage(rivals(phrase_places(base, buckets), buckets, crowd), "phrases")
    texts = phrase_texts(base, settled.filter(F.col("kind") == WANTED), buckets)
    found = stage(index_buckets(texts, buckets), "repeats")
    marks = settled.filter(F.col("kind") == MARKS).unionByName(found)
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary, spans string"
    names = [c.split()[0] for c in schema.split(", ")]

    def cut(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        marks = _joined(right.column("data"), MARK)
        marks = marks[np.argsort(marks["doc"], kind="stable")]
        cols: list[list] = [[] for _ in names]
        ids = np.asarray(left.column("_doc")) if left.num_rows else np.zeros(0, np.int64)
        lo, hi = np.searchsorted(marks["doc"], ids), np.searchsorted(marks["doc"], ids, "right")
        for doc, text, a, b in zip(left.column("doc_id").to_pylist(), left.column("text").to_pylist(), lo, hi):
            raw = (text or "").encode()
            runs = covered(marks[a:b], len(raw))
            kept, at = [], 0
            for s, e in runs:
                kept.append(raw[at:s])
                at = e
            kept.append(raw[at:])
            left_over = b"".join(kept)
            row = (doc, len(raw), len(raw) - len(left_over), len(runs), hashlib.sha256(left_over).hexdigest(), left_over, ",".join(f"{s}:{e}" for s, e in runs))
            for c, v in zip(cols, row):
                c.append(v)
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.string()]
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    return _by_doc(base, buckets).cogroup(marks.groupBy("bucket")).applyInArrow(cut, schema)
