"""k-means and product quantization on numpy blocks."""

from __future__ import annotations

import numpy as np

from ..errors import BadParameter


def nearest(x: np.ndarray, centres: np.ndarray, block: int = 8192) -> tuple[np.ndarray, np.ndarray]:
    """(number of the nearest centre, squared distance); ties to the smaller number."""
    who, far = np.empty(len(x), np.int64), np.empty(len(x))
    c = centres.astype(np.float64)
    for s in range(0, len(x), block):
        d = ((x[s : s + block].astype(np.float64)[:, None, :] - c[None]) ** 2).sum(-1) if len(c) * c.shape[1] <= 512 else _by_product(x[s : s + block], c)
        who[s : s + block] = d.argmin(1)
        far[s : s + block] = d[np.arange(len(d)), who[s : s + block]]
    return who, far


def _by_product(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    return np.maximum((x * x).sum(1)[:, None] + (c * c).sum(1)[None] - 2 * x @ c.T, 0)


def kmeans(x: np.ndarray, k: int, iters: int = 10, seed: int = 0, init: str = "plus") -> tuple[np.ndarray, list[float]]:
    """(centres, inertia after each assignment). init: "plus" draws by squared distance, "first" takes the first rows.
    An empty cell keeps its centre."""
    k = min(k, len(x))
    if k < 1:
        raise BadParameter("k-means needs rows and k > 0")
    x = x.astype(np.float64)
    if init == "first":
        centres = x[:k].copy()
    else:
        rng = np.random.default_rng(seed)
        chosen = [int(rng.integers(len(x)))]
        far = ((x - x[chosen[0]]) ** 2).sum(1)
        for _ in range(k - 1):
            total = far.sum()
            chosen.append(int(rng.choice(len(x), p=far / total)) if total > 0 else int(rng.integers(len(x))))
            far = np.minimum(far, ((x - x[chosen[-1]]) ** 2).sum(1))
        centres = x[chosen].copy()
    history = []
    for _ in range(iters):
        who, d = nearest(x, centres)
        history.append(float(d.sum()))
        count = np.bincount(who, minlength=k)
        sums = np.zeros_like(centres)
        np.add.at(sums, who, x)
        centres = np.where(count[:, None] > 0, sums / np.maximum(count, 1)[:, None], centres)
    return centres, history


def train_pq(x: np.ndarray, m: int, nbits: int, iters: int = 8, seed: int = 0, init: str = "plus") -> tuple[np.ndarray, list[float]]:
    """((m, codes, dim / m) codebook, total error after each round)."""
    d = x.shape[1]
    if m < 1 or d % m:
        raise BadParameter(f"{m} subspaces do not divide {d} dimensions")
    if not 1 <= nbits <= 8:
        raise BadParameter("1 to 8 bits a code")
    books, errors = [], np.zeros(iters)
    for s in range(m):
        sub = x[:, s * (d // m) : (s + 1) * (d // m)]
        book, history = kmeans(sub, 1 << nbits, iters, seed + s, init)
        if len(book) < 1 << nbits:
            book = np.concatenate([book, np.repeat(book[-1:], (1 << nbits) - len(book), 0)])
        books.append(book)
        errors += np.array(history)
    return np.stack(books).astype(np.float32), errors.tolist()


def pq_encode(x: np.ndarray, book: np.ndarray) -> np.ndarray:
    m, _, w = book.shape
    return np.stack([nearest(x[:, s * w : (s + 1) * w], book[s])[0] for s in range(m)], 1).astype(np.uint8)


def pq_decode(codes: np.ndarray, book: np.ndarray) -> np.ndarray:
    return np.concatenate([book[s][codes[:, s]] for s in range(book.shape[0])], 1)


def adc_table(q: np.ndarray, book: np.ndarray, metric: str = "l2") -> np.ndarray:
    """(m, codes) parts of the distance: squared differences, or minus products for ip and cosine (of unit vectors)."""
    m, _, w = book.shape
    parts = q.astype(np.float64).reshape(m, 1, w)
    return -(book * parts).sum(-1) if metric in ("ip", "cosine") else ((book - parts) ** 2).sum(-1)


def adc_scores(codes: np.ndarray, table: np.ndarray) -> np.ndarray:
    return table[np.arange(table.shape[0]), codes].sum(-1)


def pq_mse(x: np.ndarray, book: np.ndarray) -> float:
    return float(((x - pq_decode(pq_encode(x, book), book)) ** 2).sum(1).mean())
