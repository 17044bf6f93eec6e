"""Personal data, mixing, packing, tokens: against brute force on small fixtures."""

import hashlib
import re
import json
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from sidecar_ann.llm import mixing, packing, pii, token_counts, token_files
from sidecar_ann.llm.tokens import ChunkEncoder, tokenizer_path

TEXTS = [
    None, "", "plain words only.", "two  blanks\n\nand lines\n", "tab\there and   odd space", "é\U0001f642 café It's a test's end 12 345\nNext line!!", "x" * 3000, "word " * 2500,
    "a@b.c_d@e.f.g, x.y@z a@b.c._x@d.e 1.2.3.4.5.6.7.8 999.1.1.1 007.1.2.003 +1 (017) 555-7713 4111 1111 1111 1111", "é\U0001f642 a@b.co \U0001f642 +12345678901 token = \"abcd1234abcd1234abcd\" 12-34 56 7890123456-7",
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "ab"[i % 2] if i % 5 else None, "clash") for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, size string").repartition(3)


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (1 + i % 2)
        total += v - 9 if v > 9 else v
    return total % 10 == 0


def base_spans(t):
    out = []
    out += [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m.group())
        if 14 <= len(d) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 10 <= len(re.sub("[^0-9]", "", m.group())) <= 15]
    return sorted(out)


def test_base_spans(docs):
    got = {r["doc_id"]: r for r in pii.digest(pii.find(docs)).collect()}
    for i, t in enumerate(TEXTS):
        spans = base_spans(t or "")
        said = ",".join(f"{pii.KINDS[k]}:{s}:{e}" for s, k, e in spans)
        assert got[i]["base_sha256"] == hashlib.sha256(said.encode()).hexdigest(), (i, said, got[i]["spans"])
        assert set(said.split(",")) - {""} <= set(got[i]["spans"].split(","))
        assert [got[i][f"n_{k}"] for k in pii.KINDS[:4]] == [sum(x[1] == j for x in spans) for j in range(4)]


def test_base_spans_of_random_texts(spark):
    rnd = random.Random(11)
    some = ["1", "23", "4111 1111 1111 1111", "4242-4242-4242-4242", " ", " ", "-", "--", "+", "+1", "(", ")", ".", "@", "a", "b.c", "@x.org", "1.2.3.4", "256.1.1.1", "é", "\U0001f600", "\n", "0", "00"]
    texts = ["".join(rnd.choice(some) for _ in range(rnd.choice([3, 8, 20, 60]))) for _ in range(3000)] + [" ".join(f"word{i} {i}" for i in range(20_000)), "1" * 30_000, "a@b.c " * 3000]
    got = {r["doc_id"]: r for r in pii.digest(pii.find(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4))).collect()}
    for i, t in enumerate(texts):
        said = ",".join(f"{pii.KINDS[k]}:{s}:{e}" for s, k, e in base_spans(t))
        assert got[i]["base_sha256"] == hashlib.sha256(said.encode()).hexdigest(), (i, said[:300], got[i]["spans"][:300])


def test_added_spans_and_redaction(spark):
    texts = ['export token = "' + c * 4 + '0123456789abcdef0123456789abcdef0123"' for c in "abcd"] + ["call (212) 555-0199 now", "version 9807915762804491 of the book"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    left = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    assert all(left[i] == 'export token = "[SECRET]"' for i in range(4))
    assert left[5] == texts[5]


def test_secrets_of_any_length_are_whole(spark):
    values = ["0123456789abcdef" * n for n in (2, 12, 13, 20, 400)]
    texts = [f"export token = {v} end" for v in values]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["spans"] for r in pii.digest(pii.find(docs)).collect()}
    left = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    for i, v in enumerate(values):
        assert got[i] == f"secret:15:{15 + len(v)}"
        assert left[i] == "export token = [SECRET] end"


def test_reliabilities_follow_agreement():
    counts = {(3, 26, 9): 50, (3, 4, 9): 400, (3, 23, 9): 30, (3, 1, 9): 300}
    post, rel = pii.estimate(counts)
    assert post[3, 26] > 0.9 > 0.2 > post[3, 4]
    code = lambda k, v, h: (k * 27 + v) * pii.SHAPES + h
    assert code(3, 26, 9) in pii.accepted(pii.train(counts, post))


def test_span_classifier_sees_more_than_the_votes():
    """Where no labeler decides, the shape that goes with the doubtful spans' sure relatives does."""
    counts = {(4, 26, 17): 200, (4, 4, 0): 200, (4, 13, 17): 5, (4, 13, 0): 5}
    post, _ = pii.estimate(counts)
    weights = pii.train(counts, post)
    near = lambda h: sum(a * b for a, b in zip(weights, pii._features(4, 13, h)))
    assert near(17) > near(0)


CLASHES = ["size", "target", "taken", "source_size", "_key", "_range", "_n", "_ss", "_t", "_cands", "_s", "_h_email", "_l_ip", "_row", "_doc", "rep", "score", "part", "_ahead", "key", "block", "n_chars"]


def test_columns_of_any_name_keep_their_values(spark):
    from sidecar_ann.llm import neardup, quality

    rows = [(i, t, "ab"[i % 2], *[f"{c}{i}" for c in CLASHES]) for i, t in enumerate(["mail a.b@c.org now please and then", "plain words here and there again", None, "token = 'abcd1234abcd1234abcd'"])]
    docs = spark.createDataFrame(rows, ", ".join(["doc_id long", "text string", "source string", *[f"`{c}` string" for c in CLASHES]]))
    labels = spark.createDataFrame([(0, 1), (1, 0)], "doc_id long, quality int")
    vectors = quality.word_vectors(docs)
    for out in (pii.redact(docs), mixing.repeat_documents(docs), neardup.keep_one(docs), quality.score(docs, quality.fit(docs, labels, vectors), vectors, "quality_score").select(*docs.columns)):
        assert out.columns == docs.columns
        got = out.collect()
        assert got
        for r in got:
            assert all(r[c] == f"{c}{r['doc_id']}" for c in CLASHES)
    assert {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}[0] == "mail [EMAIL] now please and then"


def test_pipeline_stages_on_edge_rows(spark, tmp_path):
    import corpus_pipeline as p

    schema = "doc_id long, text string, lang string, source string, n_chars long"
    long_text = " ".join(f"word{i % 977}" for i in range(20_000))
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, long_text, "en", "a", len(long_text)), (3, long_text, "en", "a", len(long_text)), (None, "one two three four five six", None, "b", 1), (5, "write to x.y@z.org today", "de", "b", 24)]
    spark.createDataFrame([(1, 1, 0), (3, 1, 0), (5, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    for held in (spark.createDataFrame(rows, schema), spark.createDataFrame([], schema)):
        for name, f in p.STAGES:
            out = f(spark, held, str(tmp_path))
            got = out.collect()
            if name == "packing":
                assert sum(r["length"] for r in got) > 0 or not held.count()
                break
            assert out.columns == held.columns and (got or not held.count()), name
            if name == "near_duplicates":
                assert sum(r["text"] == long_text for r in got) <= 1
            if name == "mixing":
                assert all((r["text"] or "").split() for r in got)
            held = spark.createDataFrame([tuple(r) for r in got], schema)


def test_empty_tables(spark, docs):
    none = docs.filter("doc_id < 0")
    assert pii.find(none).count() == 0
    assert mixing.mix(none).count() == 0
    assert packing.pack_documents(none).count() == 0
    assert token_files.token_files(none).count() == 0
    assert token_counts.section_token_counts(none).count() == 0


def test_mixing_meets_targets(spark):
    rows = [(i, "w " * (1 + i * 7 % 40), s) for i, s in enumerate(["a"] * 300 + ["b"] * 20 + ["c"] * 10 + [None] * 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(docs).collect()
    sizes = {}
    for _, t, s in rows:
        sizes[s] = sizes.get(s, 0) + t.count("w")
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: 1 + k % 3 for k, s in enumerate(order)}
    target, free, left = {}, set(order), sum(sizes.values())
    while True:
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        full = {s for s in free if share[s] >= 3 * sizes[s]}
        if not full:
            target |= share
            break
        for s in full:
            target[s] = 3.0 * sizes[s]
            left -= 3 * sizes[s]
        free -= full
    by = {}
    for r in got:
        by[r["source"]] = by.get(r["source"], 0) + r["taken"]
        assert r["target"] == pytest.approx(target[r["source"]]) and r["taken"] <= 3 * r["size"] and r["source_size"] == sizes[r["source"]]
    assert all(abs(by[s] - target[s]) <= 1 for s in order)
    assert sorted(map(tuple, got), key=str) == sorted(map(tuple, mixing.mix(docs.repartition(5)).collect()), key=str)


#: Pieces of odd texts: letters of many kinds, marks, blanks of many kinds, apostrophes, strings of added tokens.
ODD = [
    "a", "b", "The", "the", "é", "É", "ñ", "İ", "ß", "ж", "Ж", "α", "Σ", "ς", "中", "文", "。", "\U0001f600", "—", "\u0301", "\u00a0", "\u3000", "\x1c", "\x85", "\x01", "\x00",
    " ", " ", " ", "\n", "\n", "\t", "\r", "  ", "'", "'s", "'t", "'LL", "'re", "1", "23", "½", "²", ".", ",", "!", "&&&", "<|", "endoftext", "|>", "<|endoftext|>", "<|startoftext|>",
    "|", "_", "-", "ÿ", "×", "÷", "µ", "ª", "ŉ", "ǅ", "\u200b", "\u2028", "\x7f", "longwordlongwordlongword", "....",
]


def odd_texts(seed: int, n: int) -> list:
    rnd = random.Random(seed)
    out = []
    for _ in range(n // 100):
        some = rnd.sample(ODD, rnd.choice([5, 20, len(ODD)]))
        out += ["".join(rnd.choice(some) for _ in range(rnd.choice([0, 1, 2, 3, 5, 8, 20, 60]))) for _ in range(100)]
    return out


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_chunked_ids_and_spans_are_those_of_whole_texts(name):
    texts = TEXTS + odd_texts(3, 6000) + ["word " * 20_000, "x" * 5000]
    want = Tokenizer.from_file(tokenizer_path(name)).encode_batch([t or "" for t in texts], add_special_tokens=False)
    ids = ChunkEncoder(tokenizer_path(name))
    spans = token_counts.SpanEncoder(tokenizer_path(name))
    for _ in range(2):  # the second time from the memo
        flat, off = ids.encode(pa.array(texts, pa.string()))
        start, end, row, chars = spans.spans(pa.array(texts, pa.string()))
        for i, w in enumerate(want):
            assert flat[off[i] : off[i + 1]].tolist() == w.ids
            assert list(zip((start[row[i] : row[i + 1]] - chars[i]).tolist(), (end[row[i] : row[i + 1]] - chars[i]).tolist())) == w.offsets


def test_an_unknown_pattern_is_encoded_whole(tmp_path):
    spec = json.load(open(tokenizer_path("byte_bpe_50k.json"), encoding="utf-8"))
    spec["pre_tokenizer"]["add_prefix_space"] = True
    path = str(tmp_path / "t.json")
    json.dump(spec, open(path, "w", encoding="utf-8"))
    texts = odd_texts(5, 300)
    flat, off = ChunkEncoder(path).encode(pa.array(texts))
    for i, w in enumerate(Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)):
        assert flat[off[i] : off[i + 1]].tolist() == w.ids


def test_packing(docs):
    whole = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    ids = {i: np.array(whole.encode(t or "", add_special_tokens=False).ids + [2], "<u4") for i, t in enumerate(TEXTS)}
    rows = packing.pack_documents(docs).collect()
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_seq.setdefault(r["sequence_id"], []).append(r)
    for doc, got in by_doc.items():
        at = 0
        for k, r in enumerate(sorted(got, key=lambda r: r["piece"])):
            assert (r["piece"], r["start"]) == (k, at) and (k == 0 or r["length"] == 1024)
            assert zlib.crc32(ids[doc][at : at + r["length"]].tobytes()) == r["ids_crc32"]
            at += r["length"]
        assert at == len(ids[doc])
    for got in by_seq.values():
        at = 0
        for r in sorted(got, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 1024


def test_bins_near_the_bound():
    rng = np.random.default_rng(0)
    n = np.clip((rng.lognormal(5, 1.2, 20_000)).astype(int), 1, 1024)
    counts = dict(zip(*(x.tolist() for x in np.unique(n, return_counts=True))))
    bins = packing.plan_bins(counts)
    used = {}
    for k, held in bins:
        assert sum(held) <= 1024 and sum(h > 341 for h in held) <= 2
        for h in held:
            used[h] = used.get(h, 0) + k
    assert used == counts
    assert sum(k for k, _ in bins) <= 1.02 * -(-int(n.sum()) // 1024)


def test_token_files(docs):
    whole = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    got, at = sorted(token_files.token_files(docs).collect()), 0
    for i, t in enumerate(TEXTS):
        ids = np.array(whole.encode(t or "", add_special_tokens=False).ids + [2], "<u4")
        assert tuple(got[i]) == (i, at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)


@pytest.mark.parametrize("vocabulary", [2, 300, 5000, 49_408, 1 << 17])
def test_bit_packing_and_random_access(tmp_path, vocabulary):
    import pyarrow.fs as pafs

    rng = np.random.default_rng(1)
    docs = [(k if k % 3 else None, rng.integers(0, vocabulary, rng.integers(0, 40)).astype("<u4")) for k in range(50)]
    with open(tmp_path / "f", "wb") as f:
        w = token_files.IdWriter(f, vocabulary, block=24)
        for d, ids in docs:
            w.add([d], ids, np.array([len(ids)]))
        w.close()
    r = token_files.IdReader(pafs.LocalFileSystem().open_input_file(str(tmp_path / "f")))
    assert [(d, i.tolist()) for d, _, i in r.documents(span=30)] == [(d, i.tolist()) for d, i in docs]
    flat = np.concatenate([i for _, i in docs])
    for a, b in ((0, 1), (23, 25), (5, 90), (len(flat) - 3, len(flat))):
        assert r.ids(a, b).tolist() == flat[a:b].tolist()


def _shares(offsets: list, bounds: list, rule: str) -> tuple[list, list]:
    """Tokens and crossing tokens of each section, token by token."""
    n = len(bounds) - 1
    got, cross = [0.0] * n, [0] * n
    for s, e in offsets:
        inside = [max(0, min(e, bounds[i + 1]) - max(s, bounds[i])) for i in range(n)]
        first = next(i for i in range(n) if inside[i])
        cross[first] += sum(map(bool, inside)) > 1
        if rule == "start":
            got[first] += 1
        elif rule == "majority":
            got[inside.index(max(inside))] += 1
        else:
            for i in range(n):
                got[i] += inside[i] / (e - s)
    return got, cross


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_token_counts_by_section(spark, rule):
    texts = TEXTS + odd_texts(7, 300) + ["a\n\nb\n", "\n", "\n\n"]
    whole = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)

    def fifths(text):
        return [0, *range(5, len(text), 5), len(text)]

    for sections in (token_counts.line_sections, fifths):
        got = {}
        for r in token_counts.section_token_counts(docs, rule=rule, sections=sections).collect():
            got.setdefault(r["doc_id"], []).append(r)
        for i, t in enumerate(texts):
            t = t or ""
            if sections is fifths:
                bounds = fifths(t)
            else:
                cuts = [0, *(k + 1 for k, c in enumerate(t) if c == "\n" and k + 1 < len(t)), len(t)]
                bounds = cuts
            rows = sorted(got[i], key=lambda r: r["section"])
            assert [(r["section"], r["start"], r["n_chars"]) for r in rows] == [(k, bounds[k], bounds[k + 1] - bounds[k]) for k in range(len(bounds) - 1)]
            want, cross = _shares(whole.encode(t, add_special_tokens=False).offsets, bounds, rule) if t else ([0.0], [0])
            assert [r["n_tokens"] for r in rows] == pytest.approx(want) and [r["n_crossing"] for r in rows] == cross


def test_token_counts_by_field(spark):
    docs = spark.createDataFrame([(1, "A title", "body text, longer", None), (2, None, "", "x"), (3, "é ü", "zwei\nZeilen", "tag")], "doc_id long, title string, text string, tag string")
    whole = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    got = {(r["doc_id"], r["field"]): r for r in token_counts.field_token_counts(docs, ["title", "text", "tag"]).collect()}
    for r in docs.collect():
        fields = [r["title"] or "", r["text"] or "", r["tag"] or ""]
        bounds = [0, len(fields[0]) + 1, len(fields[0]) + len(fields[1]) + 2, sum(map(len, fields)) + 2]
        want, cross = _shares(whole.encode("\n".join(fields), add_special_tokens=False).offsets, bounds, "start")
        for f, w, c, t in zip(("title", "text", "tag"), want, cross, fields):
            assert (got[r["doc_id"], f]["n_tokens"], got[r["doc_id"], f]["n_crossing"], got[r["doc_id"], f]["n_chars"]) == (w, c, len(t))


def test_token_counts_rules():
    start, end, bounds = np.array([0, 2, 5]), np.array([2, 5, 6]), np.array([0, 4, 6])
    assert token_counts.attribute(start, end, bounds, "start")[0].tolist() == [2, 1]
    assert token_counts.attribute(start, end, bounds, "majority")[0].tolist() == [2, 1]
    assert token_counts.attribute(start, end, bounds, "proportional")[0].tolist() == pytest.approx([1 + 2 / 3, 1 + 1 / 3])
