"""Personal data by weak supervision; DataFrame functions only.

Candidates are what loose patterns find: everything that a base pattern matches (also what its check then refuses), local
phone numbers, and values assigned to names of secrets (the whole run, however long). Three labelers vote on each for, against or not at all: the
format check (digit counts, Luhn, octets), a gazetteer (domain endings, card issuers, country codes, special networks,
names of secrets) and the words before it. How often each pattern of votes occurs is counted over all documents, a table
of fixed size; expectation-maximisation on it estimates how reliable each labeler is for each kind. The final classifier
of spans (logistic, fitted to the posteriors weighted by the candidates' numbers) sees, besides kind and votes, what no
labeler looks at: the span's length, its share of digits and whether it stands alone between blanks, quotes or brackets.
A candidate is personal data if the classifier says so or if it is a base span; where an added span overlaps a base span, only the base span stays.

Positions are code points, ends exclusive. Null texts are empty. Repeated rows repeat. An empty table gives no rows (and
the classifier falls back to the labelers' prior reliability). Columns other than doc_id and text are not read by
`find`; `redact` keeps every column of its input."""

from __future__ import annotations

import math
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stage

#: Kinds in the order in which spans of one start are listed; the first four have base patterns.
KINDS = ("email", "ip", "card", "phone", "secret")

# Patterns: the base ones, anchored at the starts of runs so that a long run is tried once (\G: just after a match).
_LOCAL = r"[A-Za-z0-9._%+-]"
PATTERNS = {
    "email": rf"(?:\G|(?<!{_LOCAL})){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"(?<![0-9])[0-9](?:[\x20-]?[0-9]){13,}+",  # a run of fewer digits never passes its check
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "secret": r"(?i)(?<![a-z0-9])(?:[a-z0-9]{1,20}[_-])?(?:token|secret|password|passwd|pwd|api[_-]?key|access[_-]?key)[\"']?\x20{0,3}[:=]\x20{0,3}[\"']?[^\s\"']{8,}+",
    "local_phone": r"(?<![0-9+])\(?[0-9]{3}\)?[\x20.-][0-9]{3}[\x20.-][0-9]{4}(?![0-9])",
}
_SECRET_HEAD = r"(?i)^[a-z0-9_-]+[\"']?\x20{0,3}[:=]\x20{0,3}[\"']?"

# Fixed words of the gazetteers and context labelers.
#: Generic endings; every ending of two letters is a country's.
DOMAIN_ENDINGS = (
    "com", "org", "net", "edu", "gov", "mil", "int", "info", "biz", "name", "pro", "aero", "coop", "museum", "jobs", "mobi", "travel", "cat", "tel", "asia", "post",
    "app", "dev", "cloud", "online", "site", "shop", "store", "blog", "tech", "agency", "email", "live", "media", "news", "studio", "systems", "world", "xyz", "top",
)
SPECIAL_NETWORKS = r"^(?:0|10|127|169\.254|192\.168|172\.(?:1[6-9]|2[0-9]|3[01])|22[4-9]|2[34][0-9]|25[0-5])\."
CARD_ISSUERS = r"^(?:4|5[1-5]|2[2-7]|3[47]|3[068]|6011|65|35)"
COUNTRY_CODES = r"^\+(?:1|7|20|27|3[0-69]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58])"
FOR = {
    "email": r"mail|contact|write|correo|courriel|schreib|kontakt",
    "ip": r"\bip\b|address|adresse|server|host|direcci",
    "card": r"card|visa|master|amex|karte|carte|tarjeta|credit",
    "phone": r"phone|tel|call|fax|mobile|ruf|appel|llam|m[oó]vil",
    "secret": r"config|export|env|auth|login|header",
}
AGAINST = {
    "email": r"example only|noreply",
    "ip": r"version|release|\bv$|section|abschnitt",
    "card": r"isbn|order|serial|invoice|bestell|num[eé]ro de s",
    "phone": r"version|isbn|order|serial",
    "secret": r"placeholder|example",
}
CONTEXT_CHARS = 32


def _text() -> Column:
    return F.coalesce(F.col("text"), F.lit(""))


def _hits(text: Column, kind: str) -> Column:
    guard = {"email": text.contains("@"), "phone": text.contains("+"), "secret": text.contains("=") | text.contains(":")}.get(kind)
    found = F.regexp_extract_all(text, F.lit(PATTERNS[kind]), F.lit(0))
    return found if guard is None else F.when(guard, found).otherwise(F.array().cast("array<string>"))


def _located(text: Column, hits: Column, kind: str) -> Column:
    """array<struct<s, e, t>> of the hits, from the lengths of what stands between them."""
    gaps = F.when(F.size(hits) > 0, F.transform(F.split(text, PATTERNS[kind], -1), F.char_length))
    lengths = F.transform(hits, F.char_length)
    begin = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out"))

    def step(state: Column, x: Column) -> Column:
        start = state["at"] + x["gap"]
        return F.struct((start + F.coalesce(x["n"], F.lit(0))).alias("at"), F.array_append(state["out"], start).alias("out"))

    starts = F.aggregate(F.arrays_zip(gaps.alias("gap"), lengths.alias("n")), begin, step, lambda state: F.slice(state["out"], F.lit(1), F.size(hits)))
    return F.when(F.size(hits) > 0, F.transform(F.arrays_zip(hits.alias("t"), starts.alias("s")), lambda x: F.struct(x["s"].alias("s"), F.char_length(x["t"]).alias("n"), x["t"].alias("t")))).otherwise(
        F.array().cast("array<struct<s:int,n:int,t:string>>")
    )


def _digits(t: Column) -> Column:
    return F.regexp_replace(t, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    back = F.split(F.reverse(digits), "")
    value = F.transform(F.filter(back, lambda c: c != ""), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise((c.cast("int") * 2) % 10 + F.floor(c.cast("int") * 2 / 10).cast("int")))
    return F.aggregate(value, F.lit(0), lambda x, y: x + y) % 10 == 0


def _passes(kind: str, t: Column) -> Column:
    n = F.char_length(_digits(t))
    if kind == "ip":
        return F.forall(F.split(t, r"\."), lambda p: F.regexp_replace(p, "^0+(?=.)", "").rlike("^(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$"))
    if kind == "card":
        return (n >= 14) & (n <= 19) & F.when((n >= 14) & (n <= 19), luhn(_digits(t))).otherwise(False)
    if kind == "phone":
        return (n >= 10) & (n <= 15)
    if kind == "secret":
        return t.rlike("[0-9]") & t.rlike("[A-Za-z]") & (F.char_length(t) >= 16)
    return F.lit(True)


def _gazetteer(kind: str, t: Column) -> Column:
    if kind == "email":
        ending = F.lower(F.regexp_extract(t, r"\.([A-Za-z0-9-]+)$", 1))
        return F.when(ending.isin(*DOMAIN_ENDINGS) | ending.rlike("^[a-z]{2}$"), 1).when(ending.rlike("^[0-9]+$"), -1).otherwise(0)
    if kind == "ip":
        return F.when(t.rlike(SPECIAL_NETWORKS), -1).otherwise(1)
    if kind == "card":
        return F.when(_digits(t).rlike(CARD_ISSUERS), 1).otherwise(0)
    if kind == "phone":
        return F.when(t.rlike(COUNTRY_CODES), 1).otherwise(0)
    return F.when(t.rlike("^[0-9a-fA-F]{32,}$|^(?:sk|pk|ghp|xox)[-_]"), 1).otherwise(0)


def _context(kind: str, before: Column) -> Column:
    low = F.lower(before)
    return F.when(low.rlike(AGAINST[kind]), -1).when(low.rlike(FOR[kind]), 1).otherwise(0)


def _voted(text: Column, located: Column, kind: str, as_kind: str | None = None, base: bool = True) -> Column:
    name = as_kind or kind
    number = KINDS.index(name)
    edge = r"^[\s\"'()\[\]<>{},;:.!?]?$"

    def shape(t: Column, around: Column) -> Column:
        n = F.char_length(t)
        length = F.when(n < 16, 0).when(n < 32, 1).otherwise(2)
        digits = F.char_length(_digits(t)) * 3
        return length * 6 + F.when(digits < n, 0).when(digits < 2 * n, 1).otherwise(2) * 2 + F.when(around, 1).otherwise(0)

    def one(x: Column) -> Column:
        head = F.char_length(F.regexp_extract(x["t"], _SECRET_HEAD, 0)) if kind == "secret" else F.lit(0)
        t = F.regexp_replace(x["t"], _SECRET_HEAD, "") if kind == "secret" else x["t"]
        start = x["s"] + head
        at = F.greatest(F.lit(0), start - CONTEXT_CHARS)
        passed = _passes(name, t)
        end = x["s"] + x["n"]
        alone = F.when(start > 0, text.substr(start, F.lit(1)).rlike(edge)).otherwise(True) & text.substr(end + 1, F.lit(1)).rlike(edge)
        return F.struct(
            start.alias("s"), end.alias("e"), F.lit(number).alias("k"), shape(t, alone).cast("int").alias("shape"),
            (passed if base else F.lit(False)).alias("base"),
            ((F.when(passed, 2).otherwise(0)) * 9 + (_gazetteer(name, t) + 1) * 3 + _context(name, text.substr(at + 1, start - at)) + 1).cast("int").alias("votes"),
        )

    return F.transform(located, one)


def candidates(docs: DataFrame) -> DataFrame:
    """docs with _cands: array<struct<s, e, k, shape, base, votes>>, where votes = 9 * format + 3 * gazetteer + context,
    each 0 (against), 1 (none) or 2 (for), and shape = 6 * length + 2 * share of digits + alone. docs is a frame of the
    operator's own: text and columns that begin with no underscore, or _row."""
    names = docs.columns
    step = docs.select(*names, _text().alias("_t"))
    step = step.select("*", *[_hits(F.col("_t"), k).alias(f"_h_{k}") for k in PATTERNS])
    step = step.select("*", *[_located(F.col("_t"), F.col(f"_h_{k}"), k).alias(f"_l_{k}") for k in PATTERNS])
    parts = [_voted(F.col("_t"), F.col(f"_l_{k}"), k) for k in KINDS[:4]]
    parts.append(_voted(F.col("_t"), F.col("_l_secret"), "secret", base=False))
    parts.append(_voted(F.col("_t"), F.col("_l_local_phone"), "local_phone", "phone", base=False))
    return step.select(*names, F.concat(*parts).alias("_cands"))


# ---------------------------------------------------------------- reliabilities and classifier, on the table of counts
Seen = tuple[int, int, int]  # kind, votes, shape

#: Shapes of a span.
SHAPES = 18


def vote_counts(cands: DataFrame) -> dict[Seen, int]:
    """(kind, votes, shape) -> number of candidates; at most 5 * 27 * 18 rows."""
    rows = cands.select(F.explode("_cands").alias("c")).groupBy(F.col("c.k").alias("k"), F.col("c.votes").alias("v"), F.col("c.shape").alias("h")).agg(F.count("*").alias("n"))
    return {(r["k"], r["v"], r["h"]): r["n"] for r in rows.collect()}


def _split(votes: int) -> tuple[int, int, int]:
    return votes // 9, votes // 3 % 3, votes % 3


#: How a labeler is taken to vote before any data: rows by truth (no, yes), columns by vote (against, none, for).
PRIOR = (((0.80, 0.15, 0.05), (0.05, 0.15, 0.80)), ((0.35, 0.45, 0.20), (0.10, 0.30, 0.60)), ((0.15, 0.80, 0.05), (0.02, 0.78, 0.20)))
STRENGTH = 20.0


def estimate(counts: dict[Seen, int], rounds: int = 50) -> tuple[dict, dict]:
    """(posterior of each (kind, votes), reliabilities of each kind) by expectation-maximisation with the prior's weight
    of STRENGTH candidates."""
    post: dict[tuple[int, int], float] = {}
    reliability: dict[int, tuple] = {}
    for kind in sorted({k for k, _, _ in counts}):
        own: dict[int, int] = {}
        for (k, v, _), n in counts.items():
            if k == kind:
                own[v] = own.get(v, 0) + n
        rate, table = 0.5, PRIOR
        p: dict[int, float] = {}
        for _ in range(rounds):
            for v in own:
                yes, no = math.log(rate), math.log(1 - rate)
                for lab, vote in enumerate(_split(v)):
                    no += math.log(table[lab][0][vote])
                    yes += math.log(table[lab][1][vote])
                p[v] = 1 / (1 + math.exp(min(60.0, no - yes)))
            total = sum(own.values())
            rate = (sum(p[v] * n for v, n in own.items()) + STRENGTH / 2) / (total + STRENGTH)
            new = []
            for lab in range(3):
                rows = []
                for truth in (0, 1):
                    w = [STRENGTH * PRIOR[lab][truth][vote] + sum((p[v] if truth else 1 - p[v]) * n for v, n in own.items() if _split(v)[lab] == vote) for vote in range(3)]
                    rows.append(tuple(x / sum(w) for x in w))
                new.append(tuple(rows))
            table = tuple(new)
        reliability[kind] = (rate, table)
        post |= {(kind, v): q for v, q in p.items()}
    return post, reliability


def _features(kind: int, votes: int, shape: int) -> list[float]:
    f, g, c = _split(votes)
    length, digits, alone = shape // 6, shape // 2 % 3, shape % 2
    return [float(kind == k) for k in range(len(KINDS))] + [float(f == 0), float(f == 2), float(g == 0), float(g == 2), float(c == 0), float(c == 2)] + [
        float(length == 1), float(length == 2), float(digits == 1), float(digits == 2), float(alone)
    ]


def train(counts: dict[Seen, int], post: dict, rounds: int = 400) -> list[float]:
    """Weights of the logistic classifier of spans, fitted to the posteriors weighted by the candidates' numbers."""
    w = [0.0] * len(_features(0, 0, 0))
    if not counts:
        return [-1.0] * len(KINDS) + [-2.0, 2.0, -1.0, 1.0, -2.0, 1.0] + [0.0] * 5
    total = sum(counts.values())
    rows = [(_features(k, v, h), post[k, v], n / total) for (k, v, h), n in sorted(counts.items())]
    for _ in range(rounds):
        grad = [1e-4 * x for x in w]
        for x, y, n in rows:
            q = 1 / (1 + math.exp(-max(-60.0, min(60.0, sum(a * b for a, b in zip(w, x))))))
            for i, a in enumerate(x):
                grad[i] += n * (q - y) * a
        w = [a - 2.0 * g for a, g in zip(w, grad)]
    return w


def accepted(weights: list[float]) -> list[int]:
    """The codes (kind, votes and shape as one number) that the classifier takes."""
    every = ((k, v, h) for k in range(len(KINDS)) for v in range(27) for h in range(SHAPES))
    return [(k * 27 + v) * SHAPES + h for k, v, h in every if sum(a * b for a, b in zip(weights, _features(k, v, h))) > 0]


def decide(cands: DataFrame) -> list[int]:
    """The codes of candidates that the classifier takes for personal data."""
    counts = vote_counts(cands)
    return accepted(train(counts, estimate(counts)[0]))


def chosen(cands: Column, yes: Iterable[int]) -> Column:
    """Base spans and the added ones that overlap none of them, nor an added one before, by start and kind."""
    base = F.filter(cands, lambda c: c["base"])
    wanted = F.split(F.lit(",".join(map(str, [-1, *yes]))), ",").cast("array<int>")  # a literal once folded
    extra = F.filter(cands, lambda c: ~c["base"] & F.array_contains(wanted, (c["k"] * 27 + c["votes"]) * SHAPES + c["shape"]))
    free = F.filter(extra, lambda c: ~F.exists(base, lambda b: (b["s"] < c["e"]) & (c["s"] < b["e"])))
    free = F.filter(free, lambda c: ~F.exists(free, lambda b: (b["s"] < c["e"]) & (c["s"] < b["e"]) & ((b["s"] < c["s"]) | ((b["s"] == c["s"]) & (b["k"] < c["k"])))))
    return F.array_sort(F.transform(F.concat(base, free), lambda c: F.struct(c["s"].alias("s"), c["k"].alias("k"), c["e"].alias("e"), c["base"].alias("base"))))


def _joined(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda c: F.concat_ws(":", F.element_at(names, c["k"] + 1), c["s"].cast("string"), c["e"].cast("string"))), ",")


def find(docs: DataFrame) -> DataFrame:
    """doc_id, spans (array<struct<s, k, e, base>>), one row a document."""
    held = stage(candidates(docs.select("doc_id", "text")).select("doc_id", "_cands"), "candidates")
    return held.select("doc_id", chosen(F.col("_cands"), decide(held)).alias("spans"))


def digest(found: DataFrame) -> DataFrame:
    base = F.filter("spans", lambda c: c["base"])
    count = lambda k: F.size(F.filter("spans", lambda c: c["base"] & (c["k"] == k))).cast("long")
    return found.select(
        "doc_id", *[count(i).alias(f"n_{k}") for i, k in enumerate(KINDS[:4])],
        F.sha2(_joined(base).cast("binary"), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"),
    )


def redact(docs: DataFrame) -> DataFrame:
    """docs with each span of personal data replaced by its kind in brackets; spans that overlap are replaced as one, by
    the kind of the first. Reads docs twice: once for the votes, once for the texts."""
    yes = decide(candidates(docs.select("text")))
    names = docs.columns
    rows = docs.select("text", F.struct(*[F.col(f"`{n}`") for n in names]).alias("_row"))
    step = candidates(rows).withColumn("_s", chosen(F.col("_cands"), yes))
    tags = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])
    text = F.col("text")

    def put(state: Column, c: Column) -> Column:
        kept = text.substr(state["at"] + 1, c["s"] - state["at"])
        piece = F.when(c["s"] >= state["at"], F.concat(state["out"], kept, F.element_at(tags, c["k"] + 1))).otherwise(state["out"])
        return F.struct(F.greatest(state["at"], c["e"]).alias("at"), piece.alias("out"))

    whole = F.aggregate(F.col("_s"), F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), put, lambda s: F.concat(s["out"], text.substr(s["at"] + 1, F.char_length(text))))
    new = F.when(F.size("_s") > 0, whole).otherwise(text)
    return step.select(*[new.alias(n) if n == "text" else F.col("_row").getField(n).alias(n) for n in names])
