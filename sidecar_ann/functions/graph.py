"""Proximity graphs: robust pruning, beam search, build, insert, delete. Arrays of one shard in one process.

A graph is a table (n, R) of neighbours, -1 where a node has fewer. Searches run for many queries in step: each round
expands the best unvisited node of every query's pool, so the work is array work."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..errors import BadParameter
from .quantize import adc_table


@dataclass
class GraphParams:
    R: int = 16
    L: int = 40
    alpha: float = 1.2
    metric: str = "l2"
    saturate: bool = True
    n_entries: int = 16
    repair: bool = True
    seed: int = 0

    def __post_init__(self) -> None:
        if self.R < 1 or self.L < 1 or self.alpha < 1 or self.n_entries < 1:
            raise BadParameter("R, L and n_entries must be positive, alpha at least 1")


@dataclass
class Search:
    ids: np.ndarray  # (queries, L), -1 for none
    distance: np.ndarray  # squared L2, or minus the product
    visited: np.ndarray  # (queries,) nodes expanded
    distances: np.ndarray  # (queries,) distances computed
    trail: list[np.ndarray] | None = None


def _measure(metric: str):
    """Distances of gathered vectors (q, c, d) to queries (q, d)."""
    if metric in ("ip", "cosine"):
        return lambda v, q: -np.einsum("qcd,qd->qc", v, q)
    return lambda v, q: (np.einsum("qcd,qcd->qc", v, v) - 2 * np.einsum("qcd,qd->qc", v, q)) + (q * q).sum(1)[:, None]


def beam_search(x: np.ndarray | None, table: np.ndarray, entries: np.ndarray, q: np.ndarray, L: int, metric: str = "l2", codes: np.ndarray | None = None, book: np.ndarray | None = None, keep_trail: bool = False) -> Search:
    """L best nodes of each query. With codes and book, distances are read from tables of parts, else from x. A beam as wide
    as the graph drops no node, so it ends with all that the entries reach: these are found once and measured in blocks."""
    n, nq = len(table), len(q)
    q = q.astype(np.float64)
    if n == 0 or nq == 0:
        return Search(np.full((nq, L), -1), np.full((nq, L), np.inf), np.zeros(nq, int), np.zeros(nq, int), [np.zeros(0, np.int64)] * nq)
    if L >= n and not keep_trail:
        return _whole(x, table, entries, q, L, metric, codes, book)
    if codes is not None:
        tables = np.stack([adc_table(v, book, metric) for v in q])
        m = np.arange(book.shape[0])
        measure = lambda r, c: tables[r[:, None], m[None], codes[c]].sum(-1)
    else:
        own, f = x.astype(np.float64), _measure(metric)
        measure = lambda r, c: f(own[c][:, None], q[r])[:, 0]
    width = max(L, 1)
    rows = np.arange(nq)
    seen = np.zeros((nq, n), bool)
    start = np.unique(entries)
    seen[:, start] = True
    counted, visited = np.full(nq, len(start), np.int64), np.zeros(nq, np.int64)
    r = np.repeat(rows, len(start))
    dist = measure(r, np.tile(start, nq)).reshape(nq, -1)
    order = np.lexsort((start[None, :].repeat(nq, 0), dist), axis=1)[:, :width]
    # pools are not in order: a round needs the best open node and the worst one only
    ids = np.full((nq, width), -1)
    far = np.full((nq, width), np.inf)
    k = order.shape[1]
    ids[:, :k], far[:, :k] = start[order], np.take_along_axis(dist, order, 1)
    done = np.zeros((nq, width), bool)
    worst = far.max(1)
    trail: list[np.ndarray] = []
    while True:
        at = np.where(done, np.inf, far).argmin(1)
        live = ~done[rows, at] & (ids[rows, at] >= 0)
        if not live.any():
            break
        node = np.where(live, ids[rows, at], 0)
        done[rows[live], at[live]] = True
        visited += live
        if keep_trail:
            trail.append(np.where(live, node, -1))
        near = np.where(live[:, None], table[node], -1)
        fresh = near >= 0
        safe = np.where(fresh, near, 0)
        fresh &= ~seen[rows[:, None], safe]
        r, c = np.nonzero(fresh)
        if not len(r):
            continue
        seen[r, safe[r, c]] = True
        counted += fresh.sum(1)
        d = np.full(fresh.shape, np.inf)
        d[r, c] = measure(r, safe[r, c])
        hit = np.flatnonzero((d < worst[:, None]).any(1))
        if not len(hit):
            continue
        d = d[hit]
        all_ids = np.concatenate([ids[hit], np.where(np.isfinite(d), safe[hit], -1)], 1)
        all_far = np.concatenate([far[hit], d], 1)
        all_done = np.concatenate([done[hit], np.zeros(d.shape, bool)], 1)
        order = np.argpartition(all_far, width - 1, axis=1)[:, :width]
        ids[hit], far[hit], done[hit] = (np.take_along_axis(v, order, 1) for v in (all_ids, all_far, all_done))
        worst[hit] = far[hit].max(1)
    order = np.lexsort((np.where(ids < 0, n, ids), far), axis=1)
    ids, far = np.take_along_axis(ids, order, 1), np.take_along_axis(far, order, 1)
    found = None
    if keep_trail:
        steps = np.stack(trail, 1) if trail else np.zeros((nq, 0), np.int64)
        found = [t[t >= 0] for t in steps]
    return Search(ids, far, visited, counted, found)


def _whole(x: np.ndarray | None, table: np.ndarray, entries: np.ndarray, q: np.ndarray, L: int, metric: str, codes: np.ndarray | None, book: np.ndarray | None) -> Search:
    """What a search with a beam of all nodes returns."""
    node = np.flatnonzero(reachable(table, entries))
    ids, far = np.full((len(q), L), -1), np.full((len(q), L), np.inf)
    own = None if codes is not None else x[node].astype(np.float64)
    m = None if codes is None else np.arange(book.shape[0])
    for i, v in enumerate(q):
        if codes is not None:
            d = adc_table(v, book, metric)[m, codes[node]].sum(-1)
        elif metric in ("ip", "cosine"):
            d = -(own @ v)
        else:
            d = ((own - v) ** 2).sum(1)
        order = np.lexsort((node, d))
        ids[i, : len(node)], far[i, : len(node)] = node[order], d[order]
    count = np.full(len(q), len(node), np.int64)
    return Search(ids, far, count, count.copy())


def _pairs(x: np.ndarray, metric: str) -> np.ndarray:
    g = x @ x.T
    if metric in ("ip", "cosine"):
        return -g
    s = np.diag(g)
    return np.maximum(s[:, None] + s[None, :] - 2 * g, 0)


def robust_prune(x: np.ndarray, p: int, candidates: np.ndarray, alpha: float, R: int, metric: str = "l2", saturate: bool = False) -> np.ndarray:
    """At most R of the candidates: nearest first; one that is nearer (by alpha) to a kept one than to p is left out.
    saturate: free places go to the nearest of those left out. Squared distances, so alpha enters squared; for products
    unit vectors are assumed and chords compared."""
    cand = np.unique(candidates)
    cand = cand[(cand != p) & (cand >= 0)]
    if not len(cand):
        return cand
    own = x[cand].astype(np.float64)
    to_p = ((own - x[p].astype(np.float64)) ** 2).sum(1)
    order = np.lexsort((cand, to_p))
    cand, own, to_p = cand[order], own[order], to_p[order]
    # of many candidates only the rows of the kept ones, which are R at most, are measured
    between = _pairs(own, "l2") if len(cand) <= 1024 else None
    alive = np.ones(len(cand), bool)
    kept = []
    a = alpha * alpha
    for i in range(len(cand)):
        if not alive[i]:
            continue
        kept.append(i)
        if len(kept) == R:
            break
        alive &= a * (between[i] if between is not None else ((own - own[i]) ** 2).sum(1)) > to_p
    if saturate and len(kept) < R:
        rest = np.setdiff1d(np.arange(len(cand)), kept)
        kept += rest[: R - len(kept)].tolist()
    return cand[kept]


def medoid(x: np.ndarray) -> int:
    """The node closest to the mean; ties to the smaller number."""
    if not len(x):
        return 0
    return int((((x - x.astype(np.float64).mean(0)) ** 2).sum(1)).argmin())


def entry_points(x: np.ndarray, n: int, seed: int = 0) -> np.ndarray:
    """The medoid and the nodes closest to the centres of n - 1 cells."""
    first = medoid(x)
    if n <= 1 or len(x) <= 1:
        return np.array([first])
    from .quantize import kmeans

    centres, _ = kmeans(x, min(n - 1, len(x)), 6, seed)
    near = [int(((x - c) ** 2).sum(1).argmin()) for c in centres]
    return np.array([first, *(i for i in dict.fromkeys(near) if i != first)])


def _as_table(lists: list[np.ndarray], R: int) -> np.ndarray:
    out = np.full((len(lists), R), -1, np.int64)
    for i, v in enumerate(lists):
        out[i, : len(v)] = v
    return out


def as_lists(table: np.ndarray) -> list[np.ndarray]:
    return [np.sort(row[row >= 0]) for row in table]


#: Members of the matrices that one step of `prune_many` holds.
PRUNE_CELLS = 2 << 20


def prune_many(x: np.ndarray, nodes: np.ndarray, candidates: list[np.ndarray], alpha: float, R: int, metric: str = "l2", saturate: bool = False) -> np.ndarray:
    """(nodes, R): what `robust_prune` keeps of each node's candidates, -1 in free places. Nodes with about as many
    candidates go in step; one with more than 1,024 goes alone."""
    out = np.full((len(nodes), R), -1, np.int64)
    width = np.array([len(c) for c in candidates], np.int64)
    order = np.argsort(width, kind="stable")
    s = 0
    while s < len(order) and width[order[s]] <= 1024:
        w = int(width[order[s]])
        e = s + 1
        while e < len(order) and width[order[e]] <= min(1024, 2 * w + 8) and (e - s + 1) * int(width[order[e]]) * max(int(width[order[e]]), x.shape[1]) <= PRUNE_CELLS:
            e += 1
        at = order[s:e]
        own = np.full((len(at), max(1, int(width[at].max()))), -1, np.int64)
        for i, k in enumerate(at):
            own[i, : width[k]] = candidates[k]
        out[at] = _prune_step(x, np.asarray(nodes)[at], own, alpha, R, saturate)
        s = e
    for k in order[s:]:
        kept = robust_prune(x, int(nodes[k]), candidates[k], alpha, R, metric, saturate)
        out[k, : len(kept)] = kept
    return out


def _prune_step(x: np.ndarray, nodes: np.ndarray, cand: np.ndarray, alpha: float, R: int, saturate: bool) -> np.ndarray:
    """`prune_many` of one matrix of candidates, -1 for none."""
    cand = np.sort(np.where(cand == nodes[:, None], -1, cand), axis=1)
    ok = cand >= 0
    ok[:, 1:] &= cand[:, 1:] != cand[:, :-1]
    own = x[np.maximum(cand, 0)].astype(np.float64)
    to_p = np.where(ok, ((own - x[nodes].astype(np.float64)[:, None]) ** 2).sum(2), np.inf)
    order = np.argsort(to_p, axis=1, kind="stable")[:, : max(1, int(ok.sum(1).max()))]
    cand, ok, to_p = (np.take_along_axis(v, order, 1) for v in (cand, ok, to_p))
    own = np.take_along_axis(own, order[:, :, None], 1)
    size = (own * own).sum(2)
    between = np.maximum(size[:, :, None] + size[:, None, :] - 2 * (own @ own.transpose(0, 2, 1)), 0) * (alpha * alpha)
    alive, kept, count = ok.copy(), np.zeros_like(ok), np.zeros(len(nodes), np.int64)
    for i in range(cand.shape[1]):
        take = alive[:, i] & (count < R)
        if take.any():
            kept[:, i] = take
            count += take
            alive &= ~take[:, None] | (between[:, i] > to_p)
    place = np.where(kept, np.arange(cand.shape[1]), 1 << 40)
    if saturate:
        rest = ok & ~kept
        rest &= np.cumsum(rest, 1) <= (R - count)[:, None]
        place = np.where(rest, (1 << 20) + np.arange(cand.shape[1]), place)
    first = np.argsort(place, axis=1, kind="stable")[:, :R]
    out = np.full((len(nodes), R), -1, np.int64)
    out[:, : first.shape[1]] = np.where(np.take_along_axis(place, first, 1) < 1 << 40, np.take_along_axis(cand, first, 1), -1)
    return out


def _link(x: np.ndarray, table: np.ndarray, nodes: np.ndarray, out: np.ndarray, p: GraphParams, alpha: float, saturate: bool) -> None:
    """Sets the out-edges (nodes, R) of nodes and adds the reverse edges; nodes that get too many are pruned again."""
    R = table.shape[1]
    table[nodes] = out
    r, c = np.nonzero(out >= 0)
    order = np.lexsort((nodes[r], out[r, c]))
    to, new = out[r, c][order], nodes[r][order]
    ends, starts, group = np.unique(to, return_index=True, return_inverse=True)
    if not len(ends):
        return
    fresh = ~(table[to] == new[:, None]).any(1)
    total = (table[ends] >= 0).sum(1) + np.bincount(group, fresh, len(ends)).astype(np.int64)
    few = total <= R
    # rows with room: old and new in order
    mine = fresh & few[group]
    rank = np.cumsum(mine) - 1
    rank -= rank[starts][group] - mine[starts][group] + 1
    wide = np.full((len(ends), 2 * R), -1, np.int64)
    wide[:, :R] = table[ends]
    wide[group[mine], R + rank[mine]] = new[mine]
    wide = np.sort(np.where(wide < 0, len(table), wide), axis=1)[:, :R]
    table[ends[few]] = np.where(wide < len(table), wide, -1)[few]
    full = np.flatnonzero(~few)
    if len(full):
        stops = np.append(starts[1:], len(to))
        both = [np.concatenate([table[ends[k]], new[starts[k] : stops[k]]]) for k in full]
        table[ends[full]] = prune_many(x, ends[full], both, alpha, R, p.metric, saturate)


def build_graph(x: np.ndarray, p: GraphParams) -> tuple[np.ndarray, np.ndarray]:
    """((n, R) neighbours, entry nodes): a random start, a pass at alpha 1 and one at alpha, in random order; then free
    places are filled, and nodes that no entry reaches are linked in."""
    n = len(x)
    x = x.astype(np.float64)
    if n == 0:
        return np.zeros((0, p.R), np.int64), np.zeros(0, np.int64)
    rng = np.random.default_rng(p.seed)
    R = min(p.R, max(1, n - 1))
    table = np.full((n, p.R), -1, np.int64)
    if n > 1:
        for i in range(n):
            pick = rng.choice(n - 1, R, replace=False)
            table[i, :R] = pick + (pick >= i)
    entries = entry_points(x, p.n_entries, p.seed)
    batch = max(16, min(256, n // 8))
    for alpha in (1.0, p.alpha) if p.alpha > 1 else (1.0,):
        order = rng.permutation(n)
        for s in range(0, n, batch):
            nodes = order[s : s + batch]
            got = beam_search(x, table, entries, x[nodes], p.L, "l2", keep_trail=True)
            last = p.saturate and alpha == p.alpha
            out = prune_many(x, nodes, [np.concatenate([got.ids[k], got.trail[k], table[i]]) for k, i in enumerate(nodes)], alpha, p.R, p.metric, last)
            _link(x, table, nodes, out, p, alpha, last)
    if p.repair:
        repair(x, table, entries)
    return table, entries


def reachable(table: np.ndarray, entries: np.ndarray) -> np.ndarray:
    seen = np.zeros(len(table), bool)
    front = np.unique(entries)
    while len(front):
        seen[front] = True
        near = np.unique(table[front])
        front = near[(near >= 0) & ~seen[np.maximum(near, 0)]]
    return seen


def repair(x: np.ndarray, table: np.ndarray, entries: np.ndarray) -> int:
    """Links nodes out of reach from their nearest reached node, in place of its farthest neighbour if that stays in
    reach. The number of edges set."""
    made = 0
    tried: set[tuple[int, int]] = set()
    seen, parent = _tree(table, entries)
    size = (x * x).sum(1)
    at_i = 0
    while True:
        while at_i < len(seen) and seen[at_i]:
            at_i += 1
        if at_i == len(seen):
            return made
        i = at_i
        inside = np.flatnonzero(seen)
        for j in inside[np.argsort(size[inside] - 2 * (x[inside] @ x[i]), kind="stable")]:
            own = table[j]
            free = np.flatnonzero(own < 0)
            if len(free):
                table[j, free[0]] = i
                break
            far = own[np.argsort(-((x[own] - x[j]) ** 2).sum(1), kind="stable")]
            placed = False
            for f in far:
                if (int(j), int(f)) in tried:
                    continue
                at = int(np.flatnonzero(own == f)[0])
                table[j, at] = i
                # what another edge was found by stays in reach without this one
                if parent[f] != j:
                    placed = True
                else:
                    again, way = _tree(table, entries)
                    if again[f]:
                        placed, seen, parent = True, again, way
                if placed:
                    tried.add((int(j), i))
                    break
                table[j, at] = f
            if placed:
                break
        else:
            return made
        made += 1
        if not seen[i]:
            parent[i] = j
            _spread(table, np.array([i]), seen, parent)


def _tree(table: np.ndarray, entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes in reach, the node whose edge each was found by; -1 for entries)."""
    seen, parent = np.zeros(len(table), bool), np.full(len(table), -1, np.int64)
    _spread(table, np.unique(entries), seen, parent)
    return seen, parent


def _spread(table: np.ndarray, front: np.ndarray, seen: np.ndarray, parent: np.ndarray) -> None:
    """Adds what front reaches to seen and parent."""
    seen[front] = True
    while len(front):
        to = table[front]
        r, c = np.nonzero((to >= 0) & ~seen[np.maximum(to, 0)])
        near, first = np.unique(to[r, c], return_index=True)
        parent[near] = front[r[first]]
        seen[near] = True
        front = near


def insert(x: np.ndarray, table: np.ndarray, entries: np.ndarray, new: np.ndarray, p: GraphParams) -> tuple[np.ndarray, np.ndarray, dict]:
    """(vectors, table, counters) with new vectors added: search, prune, forward and reverse edges, in small batches."""
    visits = dists = 0
    n0 = len(x)
    if not n0:
        t, e = build_graph(new, p)
        return new, t, {"visits": 0, "distances": 0, "entries": e}
    x = np.concatenate([x, new]).astype(np.float64)
    table = np.concatenate([table, np.full((len(new), table.shape[1]), -1, np.int64)])
    for s in range(n0, len(x), 32):
        nodes = np.arange(s, min(s + 32, len(x)))
        got = beam_search(x, table, entries, x[nodes], p.L, "l2", keep_trail=True)
        visits, dists = visits + int(got.visited.sum()), dists + int(got.distances.sum())
        out = prune_many(x, nodes, [np.concatenate([got.ids[k], got.trail[k], nodes]) for k in range(len(nodes))], p.alpha, table.shape[1], p.metric, p.saturate)
        _link(x, table, nodes, out, p, p.alpha, p.saturate)
    if p.repair:
        repair(x, table, entries)
    return x, table, {"visits": visits, "distances": dists, "entries": entries}


def consolidate(x: np.ndarray, table: np.ndarray, dead: np.ndarray, p: GraphParams) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hard delete: (kept nodes, their table, entries). Neighbours of a deleted node get its live neighbours as
    candidates and are pruned again."""
    keep = np.flatnonzero(~dead)
    out = []
    for i in keep:
        own = table[i][table[i] >= 0]
        gone = own[dead[own]]
        if len(gone):
            more = table[gone].ravel()
            cand = np.concatenate([own[~dead[own]], more[more >= 0]])
            own = robust_prune(x, int(i), cand[~dead[cand]], p.alpha, p.R, p.metric, p.saturate)
        out.append(own)
    number = np.full(len(x), -1, np.int64)
    number[keep] = np.arange(len(keep))
    small = _as_table([number[v] for v in out], table.shape[1])
    entries = entry_points(x[keep], p.n_entries, p.seed) if len(keep) else np.zeros(0, np.int64)
    if p.repair and len(keep):
        repair(x[keep], small, entries)
    return keep, small, entries


# ---------------------------------------------------------------- layered graph (a baseline)
def build_hnsw(x: np.ndarray, M: int = 16, ef: int = 64, seed: int = 0) -> list[tuple[np.ndarray, np.ndarray]]:
    """Layers from the top: (nodes, (nodes, width) neighbours by their place in the layer). Level sizes fall by M; each
    layer links its nodes by pruned searches in itself, 2 M wide at the bottom."""
    n = len(x)
    rng = np.random.default_rng(seed)
    level = np.floor(-np.log(rng.random(n)) / np.log(max(M, 2))).astype(np.int64)
    layers = []
    for lv in range(int(level.max(initial=0)), -1, -1):
        nodes = np.flatnonzero(level >= lv)
        width = 2 * M if lv == 0 else M
        table, _ = build_graph(x[nodes], GraphParams(R=width, L=ef, alpha=1.0, n_entries=1, seed=seed, saturate=True, repair=True))
        layers.append((nodes, table))
    return layers


def search_hnsw(x: np.ndarray, layers: list[tuple[np.ndarray, np.ndarray]], q: np.ndarray, ef: int, metric: str = "l2") -> Search:
    """Greedy through the upper layers, then a beam of ef at the bottom."""
    if not layers:
        return beam_search(x, np.zeros((0, 1), np.int64), np.zeros(0, np.int64), q, ef)
    starts = [np.array([medoid(x[layers[0][0]])])] * len(q)
    got = None
    for depth, (nodes, table) in enumerate(layers):
        last = depth == len(layers) - 1
        entry = np.unique(np.concatenate(starts))
        got = beam_search(x[nodes], table, entry, q, ef if last else 1, metric)
        if not last:
            below = layers[depth + 1][0]
            starts = [np.searchsorted(below, nodes[r[:1]]) for r in got.ids]
    return got


def reachable_hnsw(x: np.ndarray, layers: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Nodes that a search without a bound on its beam finds: what is reached on a layer is where the next one begins."""
    seen = np.zeros(len(x), bool)
    if layers:
        seen[layers[0][0][medoid(x[layers[0][0]])]] = True
    for nodes, table in layers:
        seen[nodes[reachable(table, np.flatnonzero(seen[nodes]))]] = True
    return seen
