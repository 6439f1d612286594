"""Clustering of all parts of all subspaces at once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship

Centroids = list[np.ndarray]  # one array (clusters x dims) per part
#: Numbers that a block of rows is compared by at a time.
CELLS = 1 << 21


def matrix(column: pa.Array, d: int) -> np.ndarray:
    """A list column as a dense matrix."""
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, d).astype(np.float64, copy=False)


def assign(x: np.ndarray, centroids: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Number of the closest centroid of each row, the lowest of equals."""
    out = np.empty(len(x), dtype=np.int64)
    step = max(1, CELLS // max(centroids.size, 1)) if metric == "l1" else max(1, CELLS // max(len(centroids), 1))
    square = (centroids * centroids).sum(axis=1)
    for at in range(0, len(x), step):
        y = x[at : at + step]
        if metric == "l1":
            out[at : at + step] = np.argmin(np.abs(y[:, None, :] - centroids[None]).sum(axis=2), axis=1)
            continue
        far = square - 2 * (y @ centroids.T)
        best = far.min(axis=1)
        out[at : at + step] = np.argmin(far, axis=1)
        # products lose digits: where others come this close, plain differences decide
        slack = 1e-9 * ((y * y).sum(axis=1) + square.max(initial=0.0))
        for i in np.flatnonzero((far <= (best + slack)[:, None]).sum(axis=1) > 1).tolist():
            near = np.flatnonzero(far[i] <= best[i] + slack[i])
            out[at + i] = near[np.argmin(((y[i] - centroids[near]) ** 2).sum(axis=1))]
    return out


def seed_centroids(points: DataFrame, parts: list, k: int, seed: int = 0, how: str = "hash") -> Centroids:
    """k start vectors per part: the points of least keyed digest, or (farthest) a spread choice among the first 8 k of them."""
    take = k if how == "hash" else 8 * k
    rows = points.select("id", "vec").orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))), "id").limit(take).collect()  # k vectors
    x = np.array([r["vec"] for r in rows], dtype=np.float64)
    out = []
    for dims in parts:
        y = x[:, list(dims)]
        if how == "farthest":
            chosen = [0]
            far = ((y - y[0]) ** 2).sum(axis=1)
            while len(chosen) < min(k, len(y)):
                chosen.append(int(np.argmax(far)))
                far = np.minimum(far, ((y - y[chosen[-1]]) ** 2).sum(axis=1))
            y = y[chosen]
        out.append(y[:k].copy())
    return out


def lloyd_step(points: DataFrame, parts: list, centroids: Centroids, d: int, grid: bool = False, metric: str = "l2") -> tuple[Centroids, float]:
    """One round for all parts in one scan: tasks send sums per cluster and dimension, d times clusters of them at most.
    Returns the new centroids (an empty cluster keeps its place; on a grid means are rounded half up) and the cost before."""
    shared = points.sparkSession.sparkContext.broadcast(centroids)

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        total = [np.zeros_like(x) for x in c]
        count = [np.zeros(len(x), dtype=np.int64) for x in c]
        cost = 0.0
        for b in batches:
            x = matrix(b.column("vec"), d)
            for h, dims in enumerate(parts):
                y = x[:, list(dims)]
                a = assign(y, c[h], metric)
                np.add.at(total[h], a, y)
                count[h] += np.bincount(a, minlength=len(c[h]))
                diff = y - c[h][a]
                cost += float(np.abs(diff).sum() if metric == "l1" else (diff * diff).sum())
        rows = [(h, i, j, float(total[h][i, j]), int(count[h][i])) for h in range(len(c)) for i in np.flatnonzero(count[h]) for j in range(c[h].shape[1])]
        rows.append((-1, 0, 0, cost, 0))
        yield pa.RecordBatch.from_arrays([pa.array([int(r[i]) for r in rows], pa.int32()) for i in range(3)] + [pa.array([r[3] for r in rows], pa.float64()), pa.array([r[4] for r in rows], pa.int64())], ["half", "cid", "dim", "total", "n"])

    got = points.select("vec").mapInArrow(sums, "half int, cid int, dim int, total double, n long").groupBy("half", "cid", "dim").agg(F.sum("total").alias("total"), F.sum("n").alias("n")).collect()  # clusters x d rows
    new = [c.copy() for c in centroids]
    cost = 0.0
    for r in got:
        if r["half"] < 0:
            cost = r["total"]
        elif r["n"]:
            mean = r["total"] / r["n"]
            new[r["half"]][r["cid"], r["dim"]] = np.floor(mean + 0.5) if grid else mean
    return new, cost


def lloyd(points: DataFrame, parts: list, k: int, d: int, iterations: int = 10, seed: int = 0, grid: bool = False, metric: str = "l2", sample_rows: int | None = None, how: str = "hash") -> tuple[Centroids, list[float]]:
    """Centroids of every part and the cost of each round. `sample_rows` bounds the training rows by keyed digest."""
    ship(points.sparkSession)
    rows = train_sample(points, sample_rows, seed) if sample_rows else points
    centroids = seed_centroids(points, parts, k, seed, how)
    rows = rows.persist()
    costs = []
    try:
        for _ in range(iterations):
            centroids, cost = lloyd_step(rows, parts, centroids, d, grid, metric)
            costs.append(cost)
    finally:
        rows.unpersist()
    return centroids, costs


def train_sample(points: DataFrame, rows: int, seed: int = 0) -> DataFrame:
    """About `rows` rows, chosen by digest of the id: the same on every engine and at every partitioning."""
    n = points.count()
    cut = min(1.0, rows / max(n, 1))
    value = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long")
    return points.where(value < F.lit(int(cut * (1 << 32))))


def mllib_centroids(points: DataFrame, parts: list, k: int, iterations: int = 10, seed: int = 0) -> Centroids:
    """The same by the library's trainer, part by part."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    out = []
    for dims in parts:
        x = points.select(array_to_vector(F.array(*[F.col("vec")[i] for i in dims])).alias("features"))
        out.append(np.array(KMeans(k=k, maxIter=iterations, seed=seed).fit(x).clusterCenters()))
    return out
