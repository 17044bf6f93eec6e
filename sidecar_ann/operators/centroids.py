"""File centroids: mean and radius of the vectors of each data file; pruning by them on the driver or as a plan."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import distance as D
from ..sources.catalog import DataFile, Snapshot, Table, file_number

#: Bytes of centroids up to which they are broadcast for the radius pass.
BROADCAST_BYTES = 64 << 20


def file_centroids(rows: DataFrame, dim: int, key: str = "file_no", vector: str = "v") -> DataFrame:
    """key, n, centroid: means by dimension, with map-side sums."""
    return rows.groupBy(key).agg(F.count("*").alias("n"), F.array(*[F.avg(F.col(vector)[i].cast("double")) for i in range(dim)]).alias("centroid"))


def file_radii(rows: DataFrame, centroids: DataFrame, files: int, dim: int, key: str = "file_no", vector: str = "v") -> DataFrame:
    """key, n, centroid, radius: the largest L2 distance of a member."""
    side = centroids.select(key, "n", "centroid")
    side = F.broadcast(side) if files * dim * 8 <= BROADCAST_BYTES else side
    far = rows.join(side.select(key, "centroid"), key).groupBy(key).agg(F.max(D.l2(F.col(vector), F.col("centroid"))).alias("radius"))
    return far.join(side, key).select(key, "n", "centroid", "radius")


def centroids_of(table: Table, snap: Snapshot, column: str, dim: int, files: list[DataFile] | None = None) -> list[dict]:
    """One row a file; only the vector column is read."""
    own = table.log.files(snap) if files is None else files
    if not own:
        return []
    rows = table.read_files(snap, [f.path for f in own]).select(file_number().alias("file_no"), F.col(column).alias("v")).filter(D.is_valid_vector(F.col("v"), dim))
    got = file_radii(rows, file_centroids(rows, dim), len(own), dim).collect()
    return sorted(({"file_no": r["file_no"], "n": r["n"], "centroid": np.array(r["centroid"]), "radius": r["radius"]} for r in got), key=lambda r: r["file_no"])


class CentroidProbe:
    """Decoded centroids on the driver."""

    def __init__(self, file_no: np.ndarray, centroid: np.ndarray, radius: np.ndarray, metric: str = "l2"):
        self.file_no, self.centroid, self.radius, self.metric = np.asarray(file_no), np.asarray(centroid, np.float64), np.asarray(radius, np.float64), metric

    def bounds(self, q: np.ndarray) -> np.ndarray:
        q = np.asarray(q, np.float64)
        if self.metric == "ip":
            return D.lower_bound("ip", -(self.centroid @ q), self.radius, float(np.linalg.norm(q)))
        if self.metric == "cosine":
            q = q / (np.linalg.norm(q) or 1.0)
        return D.lower_bound(self.metric, np.sqrt(((self.centroid - q) ** 2).sum(1)), self.radius)

    def within(self, q: np.ndarray, threshold: float) -> list[int]:
        """Files that may hold a vector at most `threshold` away: none with one is left out."""
        return self.file_no[self.bounds(q) <= threshold].tolist()

    def closest(self, q: np.ndarray, nprobe: int) -> list[int]:
        d = ((self.centroid - np.asarray(q, np.float64)) ** 2).sum(1)
        return self.file_no[np.lexsort((self.file_no, d))[:nprobe]].tolist()

    def by_bound(self, q: np.ndarray) -> list[tuple[float, int]]:
        b = self.bounds(q)
        return [(float(b[i]), int(self.file_no[i])) for i in np.lexsort((self.file_no, b))]
