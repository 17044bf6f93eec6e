"""Distances as Catalyst expressions (double, summed in order) and as numpy blocks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

METRICS = ("l2", "l2sq", "cosine", "ip")


def _d(x: Column) -> Column:
    return x.cast("double")


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: _d(x) * _d(y)))


def l2sq(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: (_d(x) - _d(y)) * (_d(x) - _d(y))))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def l2_norm(a: Column) -> Column:
    return F.sqrt(_sum(F.transform(a, lambda x: _d(x) * _d(x))))


def cosine(a: Column, b: Column) -> Column:
    """1 - cosine; null for a zero vector."""
    scale = l2_norm(a) * l2_norm(b)
    return F.when(scale > 0, F.lit(1.0) - dot(a, b) / scale)


def neg_ip(a: Column, b: Column) -> Column:
    return -dot(a, b)


def normalize(a: Column) -> Column:
    """The vector over its norm; null for a zero vector."""
    n = l2_norm(a)
    return F.when(n > 0, F.transform(a, lambda x: _d(x) / n))


def is_valid_vector(a: Column, dim: int) -> Column:
    """Of the wanted length, with finite members only."""
    return F.coalesce((F.size(a) == dim) & F.forall(a, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(_d(x)) < float("inf"))), F.lit(False))


def metric(name: str):
    return {"l2": l2, "l2sq": l2sq, "cosine": cosine, "ip": neg_ip}[name]


def literal(vector) -> Column:
    return F.array(*[F.lit(float(x)) for x in vector])


# ---------------------------------------------------------------- blocks
def block_distances(x: np.ndarray, q: np.ndarray, name: str = "l2") -> np.ndarray:
    """(queries, rows): a matrix product, for coarse passes."""
    x, q = x.astype(np.float64), q.astype(np.float64)
    if name == "ip":
        return -(q @ x.T)
    if name == "cosine":
        nx, nq = np.linalg.norm(x, axis=1), np.linalg.norm(q, axis=1)
        scale = nq[:, None] * nx[None, :]
        with np.errstate(invalid="ignore", divide="ignore"):
            return np.where(scale > 0, 1 - q @ x.T / scale, np.nan)
    sq = np.maximum((q * q).sum(1)[:, None] + (x * x).sum(1)[None, :] - 2 * (q @ x.T), 0)
    return np.sqrt(sq) if name == "l2" else sq


def exact_distances(x: np.ndarray, q: np.ndarray, name: str = "l2") -> np.ndarray:
    """Row by row difference form, for the digits that are returned. x and q are broadcast against each other."""
    x, q = x.astype(np.float64), q.astype(np.float64)
    if name in ("l2", "l2sq"):
        sq = ((x - q) ** 2).sum(-1)
        return np.sqrt(sq) if name == "l2" else sq
    ip = (x * q).sum(-1)
    if name == "ip":
        return -ip
    scale = np.linalg.norm(x, axis=-1) * np.linalg.norm(q, axis=-1)
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.where(scale > 0, 1 - ip / scale, np.nan)


def lower_bound(name: str, d: np.ndarray, radius: np.ndarray, q_norm: float = 1.0) -> np.ndarray:
    """Least distance that a member of a ball (centre at distance d, radius in L2) can have from the query. d is the L2
    distance to the centre for l2 and l2sq; for cosine all vectors are of unit length and d is their chord; for ip, d is
    minus the inner product of query and centre."""
    if name == "ip":
        return d - q_norm * radius
    chord = np.maximum(d - radius, 0)
    return {"l2": chord, "l2sq": chord**2, "cosine": chord**2 / 2}[name]


# ---------------------------------------------------------------- SQL functions
def register_functions(spark: SparkSession) -> None:
    """l2_distance, cosine_distance, inner_product, l2_norm, normalize_vector: SQL bodies that the optimizer inlines."""
    both = "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>"
    dot_ = "aggregate(zip_with(a, b, (x, y) -> x * y), 0.0D, (s, x) -> s + x)"
    norm = lambda v: f"sqrt(aggregate(transform({v}, x -> x * x), 0.0D, (s, x) -> s + x))"
    for head, body in (
        (f"l2_distance({both}) RETURNS DOUBLE", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, x) -> s + x))"),
        (f"inner_product({both}) RETURNS DOUBLE", dot_),
        (f"cosine_distance({both}) RETURNS DOUBLE", f"CASE WHEN {norm('a')} * {norm('b')} > 0 THEN 1.0D - {dot_} / ({norm('a')} * {norm('b')}) END"),
        ("l2_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE", norm("a")),
        ("normalize_vector(a ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>", f"CASE WHEN {norm('a')} > 0 THEN transform(a, x -> x / {norm('a')}) END"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
