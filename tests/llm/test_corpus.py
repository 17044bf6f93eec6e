"""Repeats, near duplicates, fingerprints, quality, media, pipeline: against brute force on small fixtures."""

import hashlib
import random
import re
import zlib
from collections import defaultdict

import numpy as np
import pytest

from sidecar_ann.llm import fingerprints, media, neardup, quality, repeats


def brute_removals(rows):
    seen, out = set(), {}
    for d, t in sorted(rows):
        b = (t or "").encode()
        edge = np.zeros(len(b) + 1, int)
        for i in range(len(b) - 99):
            w = b[i : i + 100]
            if w in seen:
                edge[i] += 1
                edge[min(i + 100, len(b))] -= 1
            else:
                seen.add(w)
        gone = np.cumsum(edge)[:-1] > 0
        kept = bytes(np.frombuffer(b, np.uint8)[~gone]) if b else b""
        out[d] = (len(b), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest())
    return out


def test_repeats(spark):
    rng = random.Random(3)
    base = "".join(rng.choice("abcdefg ") for _ in range(600))
    rows = [(5, "ab" * 400), (1, "x" * 99), (2, "x" * 100), (3, "x" * 101), (4, "x" * 350), (9, base), (7, base[:300] + "ZZ" + base[310:]), (8, base[50:149]), (10, base[50:150])]
    rows += [(11, None), (12, ""), (13, "lorem ipsum " * 30 + base[100:400] + "lorem ipsum " * 30), (14, "é" * 300), (6, "0123456789" * 13), (20, ("0123456789" * 13)[3:])] + [(100 + i, base[i : i + 250] * 2) for i in range(40)]
    docs = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, spans string").repartition(5)
    got = {r[0]: tuple(r[1:5]) for r in repeats.removals(docs).collect()}
    assert got == brute_removals(rows)


def test_repeats_of_repeated_rows_and_empty(spark):
    docs = spark.createDataFrame([(1, "y" * 10 + "abc" * 60)] * 3 + [(None, "z" * 120)] * 2, "doc_id long, text string")
    removed = sorted(r["n_removed"] for r in repeats.removals(docs).collect() if r["doc_id"] == 1)
    assert removed[1:] == [190, 190] and removed[0] < 190
    assert repeats.removals(docs.filter("doc_id = 77")).count() == 0


def test_repeats_of_crowded_minimisers(spark):
    """Minimisers with more than a few phrases are split and dealt out anew, and no equal windows are parted."""
    rng = random.Random(11)
    text = lambda n: "".join(rng.choice("abcdef") for _ in range(n))
    lines, tails = [text(k) for k in (40, 60, 85, 97, 99, 100, 140)], [text(70) for _ in range(5)]
    rows = [(i, rng.choice(tails)[rng.randrange(60) :] + lines[i % 7] + rng.choice(tails)[: rng.randrange(70)] + (lines[i % 7] if i % 5 == 0 else "")) for i in range(400)]
    rows += [(500, "ab" * 300), (501, "x" + "ab" * 120), (502, lines[0] * 9), (503, "q" + lines[0] * 4), (504, "0123456789" * 30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert {r[0]: tuple(r[1:5]) for r in repeats.removals(docs, crowd=0).collect()} == brute_removals(rows)
    assert {r[0]: tuple(r[1:5]) for r in repeats.removals(docs, crowd=3).collect()} == brute_removals(rows)


def test_a_line_in_very_many_documents_is_dealt_out():
    """One line of 60 bytes amid other texts: no name of a part gathers the phrases of all documents."""
    rng = np.random.default_rng(4)
    line = rng.integers(97, 123, 60).astype(np.uint8)
    texts = [np.concatenate([rng.integers(97, 123, 120).astype(np.uint8), line, rng.integers(97, 123, 120).astype(np.uint8)]) for _ in range(300)]
    data, off = np.concatenate(texts), np.arange(301) * 300
    row, start, n, gram, _, _ = repeats.phrases(data, off)
    p = np.zeros(len(row), repeats.PLACE)
    p["gram"], p["doc"], p["start"], p["n"] = gram, row, start, n
    assert np.unique(p["gram"], return_counts=True)[1].max() >= 150
    parts, at = repeats.split_crowded(p, off[row] + start, data)
    assert np.unique(parts["gram"], return_counts=True)[1].max() <= 2
    assert parts["n"].sum() == n.sum() and parts["n"].max() <= repeats.STEP and (at == off[parts["doc"]] + parts["start"]).all()


def test_surroundings_of_a_long_common_line_do_not_fill_an_index():
    rng = np.random.default_rng(6)
    line = rng.integers(97, 123, 160).astype(np.uint8)
    texts = [np.concatenate([rng.integers(97, 123, 120).astype(np.uint8), line, rng.integers(97, 123, 120).astype(np.uint8)]) for _ in range(2000)]
    data, off = np.concatenate(texts), np.arange(2001) * 400
    row, start, n, gram, text, _ = repeats.phrases(data, off)
    p = np.zeros(len(row), repeats.PLACE)
    p["gram"], p["text"], p["doc"], p["start"], p["n"], p["self"] = gram, text, row, start, n, repeats.CROWDED
    parts, at = repeats.split_crowded(p, off[row] + start, data)
    size = parts["n"].astype(np.int64) + repeats.LENGTH - 1
    held = np.concatenate([data[a : a + k] for a, k in zip(at, size)])
    left, body, ends, marks = repeats.thinned(parts, held, np.concatenate([[0], np.cumsum(size)]))
    assert len(body) == ends[-1] and len(body) < len(held) / 20
    found = np.concatenate([marks, repeats.repeated_windows(left, body, ends)])
    seen, want = set(), set()
    for d, t in enumerate(texts):
        for i in range(301):
            w = t[i : i + 100].tobytes()
            want |= {(d, i)} if w in seen else set()
            seen.add(w)
    assert {(int(d), int(s) + k) for d, s, c in found.tolist() for k in range(c)} == want


def test_places_of_a_task_are_dealt_out_together(spark):
    """Blobs of many pieces of text: one for each bucket and task, not one for each bucket and piece."""
    rng = random.Random(2)
    rows = [(i, "".join(rng.choice("abcdefgh ") for _ in range(400_000))) for i in range(8)]  # some pieces of 1 MB
    docs = spark.createDataFrame(rows, "_doc long, text string").coalesce(1)
    assert repeats.phrase_places(docs, 16).filter("kind = 0").count() == 16


def test_index_matching_statistics():
    data = b"banana bandana" + b"anagram"
    index = repeats.RunLengthIndex(np.frombuffer(data, np.uint8), np.array([0, 14, 21]), 5)
    texts = [b"banana bandana", b"anagram"]
    q = b"xbananagrabanx"
    want = [max([n for n in range(6) if i + n <= len(q) and any(q[i : i + n] in t for t in texts)]) for i in range(len(q))]
    got = index.matching(q).tolist()
    assert all(g <= w for g, w in zip(got, want)) and got[0] == 0 and got[1] == 5
    assert (index.stream() == index._sort(index.symbols)).all()
    assert len(index.run_start) < index.n


def brute_classes(rows, threshold=0.8):
    sets = {}
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        sets[d] = frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([(*w, "#")] if w else [("##", t or "")])
    root, links = {d: d for d in sets}, defaultdict(int)

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            k = len(sets[a] & sets[b])
            if k >= threshold * (len(sets[a]) + len(sets[b]) - k) - 1e-9:
                links[a] += 1
                links[b] += 1
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {d: (find(d), links[d]) for d in sets}


def test_near_duplicates(spark):
    rng = random.Random(5)
    word = lambda: f"w{rng.randrange(5000)}"
    base, rows = [word() for _ in range(150)], []
    for i in range(200):
        x = list(base)
        for _ in range(rng.randrange(4)):
            x[rng.randrange(150)] = f"e{rng.randrange(10**6)}"
        rows.append((i, "  ".join(x)))
    rows += [(1000, None), (1001, ""), (1002, "a b"), (1003, "a  b"), (1004, " ".join(base)), (1005, "a b c d e")] + [(2000 + i, " ".join(word() for _ in range(60))) for i in range(30)]
    docs = spark.createDataFrame([(d, t, 7) for d, t in rows], "doc_id long, text string, rep long").repartition(4)
    assert {r["doc_id"]: (r["class_id"], r["n_links"]) for r in neardup.classes(docs).collect()} == brute_classes(rows)
    kept = sorted(r["doc_id"] for r in neardup.keep_one(docs).collect())
    assert kept == sorted({c for c, _ in brute_classes(rows).values()})


def test_near_duplicates_blocks_and_edges(spark, monkeypatch):
    monkeypatch.setattr(neardup, "SMALL", 4)
    monkeypatch.setattr(neardup, "BLOCK", 8)
    base = [f"w{i}" for i in range(80)]
    rows = [(i, " ".join(base[: 80 - i % 3] + [f"x{i}"])) for i in range(30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r["doc_id"]: (r["class_id"], r["n_links"]) for r in neardup.classes(docs).collect()} == brute_classes(rows)
    again = spark.createDataFrame(rows[:2] * 2 + [(None, None)], "doc_id long, text string")
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["n_links"]) for r in neardup.classes(again).collect()) == [(-1, 0), (0, 3), (0, 3), (1, 3), (1, 3)]
    assert neardup.classes(docs.filter("doc_id < 0")).count() == 0


def test_least_depth():
    d = neardup.least_depth()
    assert 1 - (1 - 0.8**d) ** neardup.TREES >= neardup.RECALL > 1 - (1 - 0.8 ** (d + 1)) ** neardup.TREES


def test_keys_are_tries():
    rng = np.random.default_rng(2)
    h, first = rng.integers(0, 1 << 63, 400).astype(np.uint64), np.arange(0, 400, 10)
    least, full = neardup.least_depth(), neardup.FULL_DEPTH
    alone = neardup.trie_keys(h[:10], np.array([0]), 3, least)
    other = neardup.trie_keys(np.concatenate([h, h[:10]]), np.append(first, 400), 3, least)
    assert (other[0] == alone[0]).all() and (other[-1] == alone[0]).all() and len(np.unique(other[:-1] >> np.uint64(8 * (full - least)))) == 120


def _nodes(spark, rows, trees):
    keyed = spark.createDataFrame(rows, "key long, rep long")
    narrow, wide = neardup.forest_nodes(keyed, trees, 0.8, neardup.RECALL, small=4)
    groups = defaultdict(set)
    for r in narrow.collect():
        groups[r["node"]].add(r["rep"])
    return sorted(map(sorted, groups.values())), sorted((r["rep"], r["low"]) for r in wide.collect())


def test_prefixes_are_shortened_only_as_far_as_needed(spark):
    """Ten documents meet in one crowded node of one tree; in the others they stand alone, so the deeper prefixes do.
    Where they meet in every tree, the target is out of reach without the crowded nodes, and these become wide."""
    deeper = neardup.FULL_DEPTH - neardup.least_depth()
    node = 5 << 8 * deeper
    one = [(node | (i % 5) << 8 * (deeper - 1) | i << 8, i) for i in range(10)]
    lone = [((1000 + 50 * t + i) << 8 * deeper, i) for t in range(1, 32) for i in range(10)]
    narrow, wide = _nodes(spark, one + lone, 32)
    assert narrow and all(len(g) <= 4 for g in narrow) and not wide
    assert [g for g in narrow if len(g) == 2] == [[i, i + 5] for i in range(5)]
    every = [((7 + t) << 8 * deeper | i, i) for t in range(32) for i in range(10)]
    narrow, wide = _nodes(spark, every, 32)
    assert {r for r, _ in wide} == set(range(10)) and {low for _, low in wide} == {0}


@pytest.mark.parametrize("edges", [[], [(3, 1), (7, 1), (9, 8)], [(i, i + 1) for i in range(40)], [(5, 9), (9, 2), (2, 5), (4, 4), (11, 30), (30, 12)]])
def test_components_are_those_of_union_find(spark, edges):
    root: dict[int, int] = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for u, v in edges:
        a, b = find(u), find(v)
        root[max(a, b)] = min(a, b)
    want = {x: find(x) for x in root if find(x) != x}
    got = neardup.components(spark.createDataFrame(edges, "u long, v long")).collect()
    assert {r["node"]: r["root"] for r in got} == want and len(got) == len(want)


def test_near_duplicates_of_repeated_ids(spark):
    text = " ".join(f"w{i}" for i in range(60))
    rows = [(1 << 60, text, 1), (1 << 60, text, 2), (None, text + " x", 3), (None, "other words stand here alone now", 4), (None, None, 5), (-(1 << 61), "", 6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, _doc int")
    kept = sorted(r["_doc"] for r in neardup.keep_one(docs).collect())
    assert kept == [3, 4, 5, 6] or kept == [3, 4, 5] or kept == [3, 4, 6]
    got = [r for r in neardup.classes(docs).collect()]
    assert len(got) == 6 and sorted(r["n_links"] for r in got) == [0, 1, 1, 2, 2, 2]


def test_fingerprints(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = sorted((r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect())
    got = {r["doc_id"]: r for r in fingerprints.edited_fingerprints(docs).collect()}
    assert len(got) == len(rows)
    near = []
    for k, (d, t) in enumerate(rows):
        n = rows[(k + 1) % len(rows)][1]
        e = t[: len(t) - len(t) // 4] + n[: len(t) // 4]
        assert got[d]["edited_sha256"] == hashlib.sha256(e.encode()).hexdigest() and got[d]["n_chars"] == len(t)
        assert got[d]["near_edited"] == fingerprints.likeness(got[d]["fingerprint"], got[d]["edited_fingerprint"])
        near.append(got[d]["near_edited"] > got[d]["near_next"])
    assert np.mean(near) > 0.9
    same = defaultdict(set)
    for d, t in rows:
        same[t].add(got[d]["fingerprint"])
    assert all(len(v) == 1 for v in same.values())


def test_fingerprint_edges(spark):
    one = spark.createDataFrame([(1, None, "s")], "doc_id long, text string, part string")
    r = fingerprints.edited_fingerprints(one).first()
    assert r["n_chars"] == 0 and r["near_edited"] == 1.0 and r["near_next"] == 1.0
    assert fingerprints.edited_fingerprints(one.filter("doc_id > 1")).count() == 0


def test_fingerprints_of_large_groups_and_rare_sources(spark):
    rng = random.Random(3)
    text = lambda kind, n=80, many=3000: [f"{kind}{rng.randrange(many)}" for _ in range(n)]
    base, rows = text("g"), []
    for i in range(900):
        x = list(base)
        for _ in range(3):
            x[rng.randrange(80)] = f"g{rng.randrange(3000)}"
        rows.append((3 * i, " ".join(x)))
    rows += [(3 * i + 1, " ".join(text("w"))) for i in range(1990)]
    rare = [text("r", 80, 10**9) for _ in range(10)]
    rows += [(10**6 + i, " ".join(x)) for i, x in enumerate(rare)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    heavy, whole = fingerprints.heavy_keys(docs)
    assert 2000 <= whole / fingerprints.UNIT < 2020
    terms = fingerprints.lexicon(docs)
    alike = lambda a, b: fingerprints.likeness(*fingerprints.fingerprints([a.encode(), b.encode()], terms))
    group = [t for d, t in rows if d < 10**6 and d % 3 == 0]
    assert np.mean([alike(a, b) for a, b in zip(group, group[1:100])]) > 0.5
    other = [t for d, t in rows if d < 10**6 and d % 3 == 1]
    assert np.mean([alike(a, b) for a, b in zip(other, other[1:100])]) < 0.1
    for x in rare:
        assert alike(" ".join(x), " ".join([*x[:70], *text("r", 10, 10**9)])) > 0.4
    assert max(alike(" ".join(a), " ".join(b)) for a, b in zip(rare, rare[1:])) < 0.1


def test_document_frequencies_are_exact(spark):
    docs = spark.createDataFrame([(i, f"common w{i % 3} w{i % 3} only{i}") for i in range(30)], "doc_id long, text string").repartition(4)
    n = np.concatenate([np.frombuffer(bytes(r[0]), [("t", "<u8"), ("n", "<u8")])["n"] for r in fingerprints.document_frequencies(docs).collect()])
    assert sorted(n.tolist()) == [1] * 30 + [10] * 3 + [30]


def test_quality(spark, sf):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = {r["doc_id"]: r["score"] for r in quality.classify(docs.select("doc_id", "text"), labels).collect()}
    held = [(got[r["doc_id"]], r["quality"]) for r in labels.collect() if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    good, bad = [s for s, y in held if y], [s for s, y in held if not y]
    assert np.mean([g > b for g in good for b in bad]) > 0.97
    assert all(0 <= s <= 1 for s in got.values())


def test_quality_without_labels(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "some words")], "doc_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, quality int")
    assert {r["score"] for r in quality.classify(docs, labels).collect()} == {0.5}
    assert quality.classify(docs.filter("doc_id > 9"), labels).count() == 0


def test_media_round_trip(spark):
    rng = random.Random(1)
    payloads = [media._payload(x) for x in [b"", b"abc", rng.randbytes(64), rng.randbytes(64 * 64), rng.randbytes(64 * 64 * 3 + 100), "Ünï ".encode() * 5000]]
    assert [p for p, _, _ in media.decode(media.encode(payloads))] == payloads
    docs = spark.createDataFrame([(1, None, "a"), (2, "", "a"), (3, "é" * 3000, "a"), (3, "é" * 3000, "a")], "doc_id long, text string, media string")
    got = sorted(media.store_and_read(docs).collect())
    assert [r["payload_bytes"] for r in got] == [64, 64, 6016, 6016] and got[2] == got[3]
    assert got[0]["payload_sha256"] == hashlib.sha256(b"\0" * 64).hexdigest() and got[0]["media_sha256"] == got[1]["media_sha256"]


def coded_picture(rng, height, width, sampling, interval):
    """A baseline frame of random coefficients, code by code, and its planes by the transform's definition."""
    zigzag, x, y, up = [], 0, 0, True
    for _ in range(64):  # walk the diagonals
        zigzag.append(8 * y + x)
        if up:
            x, y, up = (x, y + 1, False) if x == 7 else (x + 1, y, False) if y == 0 else (x + 1, y - 1, True)
        else:
            x, y, up = (x + 1, y, True) if y == 7 else (x, y + 1, True) if x == 0 else (x - 1, y + 1, False)
    dc_len, ac_len = {c: 4 for c in range(12)}, {r << 4 | s: 9 for r in range(16) for s in range(1, 11)} | {0: 3, 0xF0: 8}
    dc_codes, ac_codes = media._codes(dc_len), media._codes(ac_len)
    quant = [1 + rng.randrange(12) for _ in range(64)]
    hm, vm = max(h for h, _ in sampling), max(v for _, v in sampling)
    high, wide = -(-height // (8 * vm)), -(-width // (8 * hm))
    planes = [np.zeros((high * v * 8, wide * h * 8)) for h, v in sampling]
    wave = np.array([[(0.5 if u else 8**-0.5) * np.cos((2 * i + 1) * u * np.pi / 16) for i in range(8)] for u in range(8)])
    coded, bits, last, units, marks = b"", "", [0] * len(sampling), 0, 0

    def put(code, value=0):
        s = abs(value).bit_length()
        return f"{code[0]:0{code[1]}b}" + (f"{value if value > 0 else value + (1 << s) - 1:0{s}b}" if s else "")

    def flush():
        whole = bits + "1" * (-len(bits) % 8)
        return b"".join(bytes([b]) + (b"\0" if b == 255 else b"") for b in (int(whole[i : i + 8], 2) for i in range(0, len(whole), 8)))

    for my in range(high):
        for mx in range(wide):
            if interval and units and units % interval == 0:
                coded, bits, last = coded + flush() + bytes([255, 0xD0 + marks % 8]), "", [0] * len(sampling)
                marks += 1
            units += 1
            for c, (h, v) in enumerate(sampling):
                for by in range(v):
                    for bx in range(h):
                        z = [rng.randrange(-40, 40)] + [0] * 63
                        for k in rng.sample(range(1, 64), rng.choice([0, 0, 1, 5, 63])):
                            z[k] = rng.randrange(-9, 10)
                        d, last[c] = z[0] - last[c], z[0]
                        bits += put(dc_codes[abs(d).bit_length()], d)
                        run = 0
                        end = max([k for k in range(64) if z[k]] + [0])
                        for k in range(1, end + 1):
                            if not z[k]:
                                run += 1
                                continue
                            bits += put(ac_codes[0xF0]) * (run // 16) + put(ac_codes[run % 16 << 4 | abs(z[k]).bit_length()], z[k])
                            run = 0
                        bits += put(ac_codes[0]) if end < 63 else ""
                        f = np.zeros(64)
                        for k in range(64):
                            f[zigzag[k]] = z[k] * quant[k]
                        r, q = (my * v + by) * 8, (mx * h + bx) * 8
                        planes[c][r : r + 8, q : q + 8] = wave.T @ f.reshape(8, 8) @ wave + 128
    n = len(sampling)
    head = b"\xff\xd8\xff\xdb\x00\x43\x00" + bytes(quant) + b"\xff\xc0" + (8 + 3 * n).to_bytes(2, "big") + b"\x08" + height.to_bytes(2, "big") + width.to_bytes(2, "big") + bytes([n])
    head += b"".join(bytes([c + 1, h << 4 | v, 0]) for c, (h, v) in enumerate(sampling)) + media._dht(0, dc_len) + media._dht(16, ac_len)
    head += b"\xff\xdd\x00\x04" + interval.to_bytes(2, "big") if interval else b""
    head += b"\xff\xda" + (6 + 2 * n).to_bytes(2, "big") + bytes([n]) + b"".join(bytes([c + 1, 0]) for c in range(n)) + b"\x00\x3f\x00"
    cut = [p[: -(-height * v // vm), : -(-width * h // hm)] for p, (h, v) in zip(planes, sampling)]
    return head + coded + flush() + b"\xff\xd9", cut


def test_frames_with_ac_coefficients_and_colours(spark):
    rng = random.Random(8)
    cases = [(16, 24, [(1, 1)], 0), (21, 35, [(1, 1)], 2), (40, 50, [(2, 2), (1, 1), (1, 1)], 3), (33, 17, [(2, 1), (1, 1), (1, 1)], 0), (21, 40, [(1, 1)], 2)]
    made = [coded_picture(rng, *c) for c in cases]
    flat = media.encode([bytes(range(64)) * 2])[0]
    where = media.parse_avi(flat)[0][0]
    got = media.decode_frames([f for f, _ in made] + [flat[where[0] : where[0] + where[1]]])
    for planes, (_, want) in zip(got, made):
        assert [p.shape for p in planes] == [w.shape for w in want]
        assert all(np.abs(p - np.clip(w, 0, 255)).max() <= 0.51 for p, w in zip(planes, want))
    assert got[-1][0].shape == (2, 8, 64, 8) and got[-1][0][1, :, 9, :].tolist() == [[9] * 8] * 8
    file = media._avi([made[2][0]] * 3, 5, 0).replace(b"payload=", b"comment=")
    rows = spark.createDataFrame([(1, bytearray(file))], "doc_id long, media binary")
    clip = media.clips(rows).collect()
    assert [(r["first_frame"], r["end_frame"]) for r in clip] == [(0, 3)] and abs(clip[0]["mean"] - np.clip(made[2][1][0], 0, 255).mean()) < 0.3
    with pytest.raises(ValueError):
        media.decode_frames([made[0][0].replace(b"\xff\xc0", b"\xff\xc2")])


def test_shots_become_clips(spark):
    scenes = b"".join(bytes([v]) * (media.ROW * media.ROWS * 6) for v in (20, 200, 90))
    docs = spark.createDataFrame([(1, bytes(scenes).decode("latin-1"))], "doc_id long, text string")
    file = media.encode([scenes])[0]
    rows = spark.createDataFrame([(1, bytearray(file)), (2, None)], "doc_id long, media binary")
    got = sorted(media.clips(rows).collect())
    assert [(r["first_frame"], r["end_frame"]) for r in got] == [(0, 6), (6, 12), (12, 18)]
    assert got[1]["start_s"] == pytest.approx(6 / 25) and got[1]["mean"] == 200
    assert docs.count() == 1


def test_pipeline(spark, sf):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = docs.columns
    assert [n for n, _ in p.STAGES] == ["quality", "near_duplicates", "personal_data", "mixing", "packing"]
    held = docs
    for name, f in p.STAGES[:-1]:
        out = f(spark, held, sf)
        assert out.columns == names, name
        rows = [tuple(r) for r in out.collect()]
        if name in ("quality", "near_duplicates"):
            assert set(rows) <= {tuple(r) for r in held.collect()}
        if name == "near_duplicates":
            before = [(r["doc_id"], r["text"]) for r in held.select("doc_id", "text").collect()]
            assert {r[0] for r in rows} == {c for c, _ in brute_classes(before).values()}
        if name == "personal_data":
            assert len(rows) == held.count() and not any("@mail" in (r[1] or "") for r in rows)
        held = spark.createDataFrame(rows, out.schema)
    packed = p.STAGES[-1][1](spark, held, sf)
    assert packed.agg({"length": "sum"}).first()[0] > 0
    assert packed.groupBy("sequence_id").agg({"length": "sum"}).filter("`sum(length)` > 1024").count() == 0
