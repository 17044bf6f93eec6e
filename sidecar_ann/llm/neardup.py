"""N-gram Jaccard join by a MinHash LSH forest, and exact verification.

A document is the set of its five-word shingles (words stand between white space; a text of fewer words is one shingle;
a text of no word is its bytes). Documents of equal sets are copies: one represents them, with their number as weight,
and copies are never expanded. Each representative has a sequence of FULL_DEPTH min-hashes in each of TREES trees. A
sequence is packed into one sortable number (the prefix that is never cut first, then a byte for each deeper level), so
that the numbers of a tree in order are its trie, and a prefix is a shift.

Prefixes are shortened as far as each document needs. A pair at the threshold t shares a prefix of d levels with chance
t**d, so looking at depths d1, d2, ... in the trees misses it with the product of (1 - t**di). In a tree where the node
at the least depth (5 for 32 trees at 0.8: there the product over all trees reaches the target recall of 0.99999) has up
to SMALL members, a document looks at that node. Where it has more, the document first looks at the shortest deeper
prefix with up to SMALL members (or at none). If its product then misses the target, it shortens prefixes to the least
depth, the smallest nodes first, until the target is reached; the node of a prefix shortened so is "wide". Members of
nodes are counted by sums with map-side combining, never by gathering them.

Documents in one narrow node pair with each other; a pair is looked at once, whatever the number of nodes it shares, and
verified on whole sets. Wide nodes join their documents into families (connected components over such nodes only). A
family is cut into blocks by hash, and each pair of blocks is one task that counts the links of its members exactly, by
products of incidence matrices, and hands on counts and a spanning forest: as many rows as members, not as links. (Sets
of a family of F members are sent F / BLOCK times.) Pairs within a family are left to it. So no link between different
texts is lost to a limit, and no step lists all pairs of a group.

Classes are the connected components of the links (stars contracted in rounds, each round a written table).

Texts are whole; null is empty. Of rows with equal ids each counts as a document of its own. Ties go to the smaller id.
An empty table gives no rows. Columns other than doc_id and text are kept by `keep_one`, whatever their names, and not
read by `classes`."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import MIX, mix64, per_batch, pieces, span_hashes, stage, text_bytes, words
from .repeats import numbered

WORDS, THRESHOLD = 5, 0.8
TREES, FULL_DEPTH, RECALL = 32, 8, 0.99999
#: Members of a node up to which pairs are listed.
SMALL = 32
#: Members of a block of a family, about.
BLOCK = 512


def least_depth(trees: int = TREES, threshold: float = THRESHOLD, recall: float = RECALL, full: int = FULL_DEPTH) -> int:
    """The longest prefix at which, looked at in all trees, a pair at the threshold is found with the wanted chance."""
    depth = full
    while depth > 1 and 1 - (1 - threshold**depth) ** trees < recall:
        depth -= 1
    return depth


def shingles(data: np.ndarray, off: np.ndarray, size: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of the distinct shingles of each text, ordered by row and hash."""
    n = len(off) - 1
    start, end, row = words(data, off)
    count = np.bincount(row, minlength=n)
    word = span_hashes(data, start, end)
    rows, hashes = [], []
    if len(word) >= size:
        whole = np.flatnonzero(row[: len(word) - size + 1] == row[size - 1 :])
        h = np.zeros(len(whole), np.uint64)
        for k in range(size):
            h = mix64(h * MIX + word[whole + k])
        rows.append(row[whole])
        hashes.append(h)
    for i in np.flatnonzero(count < size):  # short texts, one by one
        own = word[np.searchsorted(row, i) : np.searchsorted(row, i, "right")] if count[i] else span_hashes(data, off[i : i + 1], off[i + 1 : i + 2])
        h = np.uint64(count[i] + 1)
        for w in own:
            h = mix64(np.array([(int(h) * int(MIX) + int(w)) & 0xFFFFFFFFFFFFFFFF], np.uint64))[0]
        rows.append(np.array([i]))
        hashes.append(np.array([h], np.uint64))
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    r, h = np.concatenate(rows), np.concatenate(hashes)
    order = np.lexsort((h, r))
    r, h = r[order], h[order]
    keep = np.ones(len(r), bool)
    keep[1:] = (r[1:] != r[:-1]) | (h[1:] != h[:-1])
    return r[keep], h[keep]


def _seeds(n: int) -> tuple[np.ndarray, np.ndarray]:
    draw = mix64(np.arange(1, 2 * n + 1, dtype=np.uint64) * MIX)
    return draw[:n], draw[n:] | np.uint64(1)


def trie_keys(h: np.ndarray, first: np.ndarray, trees: int, least: int, full: int = FULL_DEPTH) -> np.ndarray:
    """(texts, trees) numbers whose order is the order of each tree's trie; h in runs that begin at `first`. The bits
    above 8 * (full - least) name the tree and the prefix of `least` levels, each byte below them one deeper level."""
    add, times = _seeds(trees * full)
    out = np.empty((len(first), trees), np.uint64)
    deeper = full - least
    low = np.uint64((1 << 8 * deeper) - 1)
    for t in range(trees):
        key = np.full(len(first), t + 1, np.uint64)
        for k in range(full):
            value = np.minimum.reduceat((h ^ add[t * full + k]) * times[t * full + k], first)
            if k < least:
                key = mix64(key ^ value)
                if k == least - 1:
                    key &= ~low
            else:
                key |= (mix64(value) & np.uint64(255)) << np.uint64(8 * (full - 1 - k))
        out[:, t] = key
    return out


def signed(docs: DataFrame, trees: int, least: int) -> DataFrame:
    """_doc, a, b (128-bit name of the set), n (its size), keys (trees x 8 bytes)."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for part in pieces(batch, most=1 << 20):
            row, h = shingles(*text_bytes(part.column("text")))
            first = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]]))
            n = np.diff(np.append(first, len(row)))
            a, b = np.add.reduceat(mix64(h), first), np.add.reduceat(mix64(h ^ np.uint64(0x5BD1E995)), first)
            keys = trie_keys(h, first, trees, least)
            yield pa.RecordBatch.from_arrays([part.column("_doc"), pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), pa.array(n.astype(np.int64)), pa.array([k.tobytes() for k in keys], pa.binary())], ["_doc", "a", "b", "n", "keys"])

    return per_batch(docs.select("_doc", "text"), work, "_doc long, a long, b long, n long, keys binary")


def _keyed(reps: DataFrame) -> DataFrame:
    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        keys = np.frombuffer(b"".join(batch.column("keys").to_pylist()), np.int64)
        each = len(keys) // max(1, batch.num_rows)
        return pa.RecordBatch.from_arrays([pa.array(keys), pa.array(np.repeat(np.asarray(batch.column("rep")), each))], ["key", "rep"])

    return per_batch(reps.select("rep", "keys"), work, "key long, rep long")


def prefix(depth: int, full: int = FULL_DEPTH):
    """The node of a key at a depth."""
    return F.shiftrightunsigned("key", 8 * (full - depth))


def forest_nodes(keyed: DataFrame, trees: int, threshold: float, recall: float, full: int = FULL_DEPTH, small: int | None = None) -> tuple[DataFrame, DataFrame]:
    """keyed: key, rep. (narrow nodes as node, rep, with two members or more; wide nodes as node, rep, low, where low is
    the least member)."""
    least, small = least_depth(trees, threshold, recall, full), small or SMALL
    own = keyed.withColumn("node", prefix(least))
    often = own.groupBy("node").agg(F.count("*").alias("members"), F.min("rep").alias("low")).filter("members > 1")
    shared = stage(own.join(often, "node"), "shared")
    crowded = shared.filter(F.col("members") > small)

    # members of the deeper nodes below crowded ones, from counts of whole keys
    counts = stage(crowded.groupBy("key").agg(F.count("*").alias(f"n{full}")), "counts")
    depths, chosen = counts, F.when(F.col(f"n{full}") <= small, full)
    for d in range(full - 1, least, -1):
        at = counts.groupBy(prefix(d).alias(f"p{d}")).agg(F.sum(f"n{full}").alias(f"n{d}"))
        depths = depths.withColumn(f"p{d}", prefix(d)).join(at, f"p{d}")
        chosen = F.when(F.col(f"n{d}") <= small, d).otherwise(chosen)  # the shortest that is narrow
    deep = stage(crowded.join(depths.select("key", chosen.alias("depth")), "key"), "deep")

    # how much of the chance to miss a pair each document has left, and which prefixes it must shorten
    miss = lambda d: math.log(1 - threshold**d)
    looked = F.lit(0.0)
    for d in range(least + 1, full + 1):
        looked = F.when(F.col("depth") == d, miss(d)).otherwise(looked)
    slack = math.log(1 - recall) - trees * miss(least) + 1e-9
    by_rep = Window.partitionBy("rep")
    cost = deep.withColumn("cost", looked - miss(least)).withColumn("left", F.sum("cost").over(by_rep) - F.sum("cost").over(by_rep.orderBy("members", "node").rowsBetween(Window.unboundedPreceding, 0)) + F.col("cost"))
    wide = stage(cost.filter(F.col("left") > slack).select("node").distinct(), "wide")
    below = deep.join(wide, "node", "left_anti").filter("depth is not null")
    at = F.lit(None).cast("long")
    for d in range(least + 1, full + 1):
        at = F.when(F.col("depth") == d, prefix(d)).otherwise(at)
    narrow = shared.filter(F.col("members") <= small).select("node", "rep").unionByName(below.select(F.xxhash64("depth", at).alias("node"), "rep"))
    return narrow, crowded.join(wide, "node").select("node", "rep", "low")


def _stars(edges: DataFrame) -> bool:
    """Whether edges (u, v), distinct and with u > v, are stars around their least nodes: no node has two parents, or a parent
    and a child."""
    side = lambda node, child: edges.select(F.col(node).alias("node"), F.lit(child).alias("child"))
    nodes = side("u", 1).unionByName(side("v", 0)).groupBy("node").agg(F.sum("child").alias("parents"), F.min("child").alias("least"))
    return nodes.filter("parents > 1 or (parents > 0 and least = 0)").agg(F.count("*")).first()[0] == 0


def components(edges: DataFrame, label: str = "component") -> DataFrame:
    """node, root (its component's smallest node) of every node of edges (u, v) that is not itself the root. Stars are
    contracted in rounds until nothing but stars is left; each round is a written table."""
    now = stage(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u <> v").distinct(), label)
    while not _stars(now):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = stage(both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct(), label)
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        now = stage(small, label)
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))


def _sets(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """rep, n, set (sorted 8-byte hashes) of the wanted documents."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for part in pieces(batch, most=1 << 20):
            row, h = shingles(*text_bytes(part.column("text")))
            cuts = np.searchsorted(row, np.arange(part.num_rows + 1))
            yield pa.RecordBatch.from_arrays([part.column("_doc"), pa.array(np.diff(cuts)), pa.array([h[s:e].tobytes() for s, e in zip(cuts[:-1], cuts[1:])], pa.binary())], ["rep", "n", "set"])

    rows = docs.select("_doc", "text").join(wanted.select(F.col("rep").alias("_doc")), "_doc", "left_semi")
    return per_batch(rows, work, "rep long, n long, set binary")


def alike(inter, na, nb, threshold: float = THRESHOLD):
    """Jaccard at or above the threshold, from the sizes."""
    return inter >= threshold * (na + nb - inter) - 1e-9


def _verified(pairs: DataFrame, threshold: float) -> DataFrame:
    """u, v, wu, wv of the pairs (with sets su, sv) at or above the threshold."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        yes = []
        for s in range(0, batch.num_rows, 256):
            part = batch.slice(s, 256)
            x, y = (part.column(c).to_pylist() for c in ("su", "sv"))
            nx, ny = (np.array([len(b) // 8 for b in z], np.int64) for z in (x, y))
            h = np.frombuffer(b"".join(x) + b"".join(y), np.uint64)
            pair = np.concatenate([np.repeat(np.arange(len(x)), nx), np.repeat(np.arange(len(y)), ny)])
            order = np.lexsort((h, pair))
            h, pair = h[order], pair[order]
            inter = np.bincount(pair[1:][(h[1:] == h[:-1]) & (pair[1:] == pair[:-1])], minlength=len(x))
            yes.append(alike(inter, nx, ny, threshold))
        keep = pa.array(np.concatenate(yes)) if yes else pa.array([], pa.bool_())
        yield pa.RecordBatch.from_arrays([batch.column(c).filter(keep) for c in ("u", "v", "wu", "wv")], ["u", "v", "wu", "wv"])

    return per_batch(pairs, work, "u long, v long, wu long, wv long")


def block_links(ids: np.ndarray, weights: np.ndarray, sets: list[np.ndarray], other: int, threshold: float = THRESHOLD) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Links of members of one block (all of them, other = 0) or between the first len - other members and the rest:
    (summed weights of each member's links, edges of a spanning forest)."""
    n = len(ids)
    size = np.array([len(s) for s in sets], np.int64)
    h = np.concatenate(sets)
    member = np.repeat(np.arange(n), size)
    term, column, often = np.unique(h, return_inverse=True, return_counts=True)
    shared = often > 1
    place = np.cumsum(shared) - 1
    keep = shared[column]
    column, member = place[column[keep]], member[keep]
    order = np.argsort(column, kind="stable")
    column, member = column[order], member[order]
    m = n - other if other else n
    inter = np.zeros((m, n - m if other else n), np.float32)
    step = 4096
    for s in range(0, int(shared.sum()), step):
        a, b = np.searchsorted(column, [s, s + step])
        block = np.zeros((n, step), np.float32)
        block[member[a:b], column[a:b] - s] = 1
        inter += block[:m] @ (block[m:] if other else block).T
    linked = alike(inter.astype(np.int64), size[:m, None], (size[m:] if other else size)[None, :], threshold)
    if not other:
        np.fill_diagonal(linked, False)
    total = np.zeros(n, np.int64)
    total[:m] = linked @ (weights[m:] if other else weights)
    if other:
        total[m:] = linked.T @ weights[:m]
    root = np.arange(n)

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    edges = []
    for i, row in enumerate(linked):
        near = np.flatnonzero(row) + (m if other else 0)
        for j in near[root[near] != root[i]] if len(near) else ():
            a, b = find(i), find(int(j))
            if a != b:
                root[max(a, b)] = min(a, b)
                edges.append((int(ids[i]), int(ids[j])))
    return total, edges


def _family_links(members: DataFrame, threshold: float) -> DataFrame:
    """u, v (null or an edge of a spanning forest), links: from members (family, blocks, rep, weight, set)."""
    own = F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")
    placed = members.withColumn("own", own)
    spread = placed.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("to")).select("family", F.least("own", "to").alias("i"), F.greatest("own", "to").alias("j"), (F.col("own") == F.greatest("own", "to")).alias("right"), "rep", "weight", "set")

    def work(table: pa.Table) -> pa.Table:
        right = np.asarray(table.column("right"))
        alone = table.column("i")[0].as_py() == table.column("j")[0].as_py()
        order = np.lexsort((np.asarray(table.column("rep")), right))
        table = table.take(pa.array(order))
        other = 0 if alone else int(right.sum())
        if not alone and (other == 0 or other == table.num_rows):
            return pa.table({"u": pa.array([], pa.int64()), "v": pa.array([], pa.int64()), "links": pa.array([], pa.int64())})
        ids = np.asarray(table.column("rep"))
        total, edges = block_links(ids, np.asarray(table.column("weight")), [np.frombuffer(b, np.uint64) for b in table.column("set").to_pylist()], other, threshold)
        u = np.concatenate([ids, np.array([e[0] for e in edges], np.int64)])
        v = pa.concat_arrays([pa.nulls(len(ids), pa.int64()), pa.array([e[1] for e in edges], pa.int64())])
        return pa.table({"u": pa.array(u), "v": v, "links": pa.array(np.concatenate([total, np.zeros(len(edges), np.int64)]))})

    return spread.groupBy("family", "i", "j").applyInArrow(work, "u long, v long, links long")


def _classes(docs: DataFrame, threshold: float = THRESHOLD, trees: int = TREES, recall: float = RECALL) -> DataFrame:
    """_doc, rep, class_id, n_links; docs has _doc."""
    held = stage(signed(docs, trees, least_depth(trees, threshold, recall)), "signed")
    reps = held.groupBy("a", "b", "n").agg(F.min(F.struct("_doc", "keys")).alias("x"), F.count("*").alias("weight")).select("a", "b", "n", F.col("x._doc").alias("rep"), F.col("x.keys").alias("keys"), "weight")
    reps = stage(reps, "representatives")
    narrow, wide = forest_nodes(_keyed(reps), trees, threshold, recall)
    narrow, wide = stage(narrow, "narrow"), stage(wide, "wide")
    big = components(wide.select(F.col("rep").alias("u"), F.col("low").alias("v")), "family").select("node", "root")
    family = stage(big.unionByName(big.select(F.col("root").alias("node"), "root")).distinct(), "families")
    sets = stage(_sets(docs, narrow.select("rep").unionByName(wide.select("rep")).distinct()), "sets").join(reps.select("rep", "weight"), "rep")

    # pairs in narrow nodes, each once, but for those within a family
    listed = narrow.groupBy("node").agg(F.sort_array(F.collect_list("rep")).alias("m")).filter(F.size("m") > 1)
    pairs = stage(
        listed.select("m", F.posexplode("m").alias("i", "u")).select("u", F.explode(F.expr("slice(m, i + 2, size(m))")).alias("v")).distinct()
        .join(family.select(F.col("node").alias("u"), F.col("root").alias("fu")), "u", "left")
        .join(family.select(F.col("node").alias("v"), F.col("root").alias("fv")), "v", "left")
        .filter("fu is null or fv is null or fu <> fv").select("u", "v"),
        "pairs",
    )
    side = lambda x: sets.select(F.col("rep").alias(x), F.col("n").alias(f"n{x}"), F.col("weight").alias(f"w{x}"), F.col("set").alias(f"s{x}"))
    sizes = sets.select("rep", "n")
    near = (
        pairs.join(sizes.select(F.col("rep").alias("u"), F.col("n").alias("nu")), "u").join(sizes.select(F.col("rep").alias("v"), F.col("n").alias("nv")), "v")
        # a set smaller than the threshold times the other's size cannot be alike
        .filter(F.least("nu", "nv") >= F.greatest("nu", "nv") * threshold - 1e-6).select("u", "v")
    )
    links = stage(_verified(near.join(side("u"), "u").join(side("v"), "v").select("u", "v", "wu", "wv", "su", "sv"), threshold), "links")

    # families, block by block
    counts = family.groupBy("root").agg((F.floor(F.count("*") / BLOCK) + 1).cast("int").alias("blocks"))
    members = family.join(counts, "root").select(F.col("root").alias("family"), "blocks", F.col("node").alias("rep")).join(sets, "rep")
    inside = stage(_family_links(members, threshold), "family-links")

    edges = links.select("u", "v").unionByName(inside.filter("v is not null").select("u", "v"))
    root = components(edges, "class")
    total = (
        links.select(F.col("u").alias("rep"), F.col("wv").alias("k")).unionByName(links.select(F.col("v").alias("rep"), F.col("wu").alias("k")))
        .unionByName(inside.filter("v is null").select(F.col("u").alias("rep"), F.col("links").alias("k"))).groupBy("rep").agg(F.sum("k").alias("k"))
    )
    done = (
        reps.select("a", "b", "n", "rep", "weight").join(total, "rep", "left").join(root.select(F.col("node").alias("rep"), "root"), "rep", "left")
        .select("a", "b", "n", "rep", F.coalesce("root", "rep").alias("class_id"), (F.coalesce("k", F.lit(0)) + F.col("weight") - 1).alias("n_links"))
    )
    return held.select("_doc", "a", "b", "n").join(done, ["a", "b", "n"]).select("_doc", "rep", "class_id", "n_links")


def classes(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, class_id (smallest id of the class), n_links (documents at or above the threshold), copy_of (smallest id
    with the same shingles)."""
    base = numbered(docs)
    found = _classes(base, threshold)
    ids = base.select("_doc", "doc_id")
    out = found.join(ids, "_doc")
    if _is_id(base):
        return out.select("doc_id", "class_id", "n_links", F.col("rep").alias("copy_of"))
    named = lambda c: ids.select(F.col("_doc").alias(c), F.col("doc_id").alias(f"{c}_id"))
    return out.join(named("class_id"), "class_id").join(named("rep"), "rep").select("doc_id", F.col("class_id_id").alias("class_id"), "n_links", F.col("rep_id").alias("copy_of"))


def _is_id(base: DataFrame) -> bool:
    """Whether _doc is the id in every row."""
    return base.filter(~F.col("_doc").eqNullSafe(F.col("doc_id"))).isEmpty()


def keep_one(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """docs without those that are not the first of their class. Rows equal in id and text are one document; of them the
    first by the other columns (as text) stays."""
    base = numbered(docs)
    first = _classes(base, threshold).filter(F.col("_doc") == F.col("class_id")).select("_doc")
    if _is_id(base):
        return docs.join(first.select(F.col("_doc").alias("doc_id")), "doc_id", "left_semi").select(*docs.columns)
    kept = base.join(first, "_doc", "left_semi").select(F.col("doc_id").alias("i"), F.col("text").alias("t")).distinct().alias("k")
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    one = own.groupBy(F.col("row.doc_id").alias("i"), F.col("row.text").alias("t")).agg(F.min_by("row", F.to_json("row")).alias("row")).alias("d")
    return one.join(kept, F.col("d.i").eqNullSafe(F.col("k.i")) & F.col("d.t").eqNullSafe(F.col("k.t"))).select("d.row.*")
