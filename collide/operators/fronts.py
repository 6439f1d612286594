"""Front ends: what is done to vectors before they are divided into subspaces."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..functions.vectors import VectorSet
from ..session import ship
from .clustering import matrix


def mapped(df: DataFrame, id_col: str, vec_col: str, weights: np.ndarray, shift: np.ndarray | None = None) -> DataFrame:
    """Each vector (less shift) times a matrix, in Arrow batches; one map, the matrix is broadcast (d x m numbers)."""
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast((weights, shift))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, s = shared.value
        for b in batches:
            x = matrix(b.column(vec_col), len(w))
            y = (x - s if s is not None else x) @ w
            offsets = pa.array(np.arange(0, y.size + 1, y.shape[1], dtype=np.int32))
            yield pa.RecordBatch.from_arrays([b.column(id_col), pa.ListArray.from_arrays(offsets, pa.array(np.ascontiguousarray(y).reshape(-1)))], [id_col, vec_col])

    return df.select(id_col, vec_col).mapInArrow(run, f"{id_col} long, {vec_col} array<double>")


def gaussian(d: int, m: int, seed: int = 0) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((d, m)) / np.sqrt(m)


def with_matrix(data: VectorSet, weights: np.ndarray, shift: np.ndarray | None = None) -> VectorSet:
    return VectorSet(mapped(data.points, "id", "vec", weights, shift), mapped(data.queries, "qid", "qvec", weights, shift), weights.shape[1], 1.0, data.n)


def project_lsh(data: VectorSet, m: int, seed: int = 0) -> VectorSet:
    """Random Gaussian projection to m dimensions."""
    return with_matrix(data, gaussian(data.d, m, seed))


def covariance(points: DataFrame, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Mean and covariance: every task sends d + d * d sums."""
    ship(points.sparkSession)

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, first, second = 0, np.zeros(d), np.zeros((d, d))
        for b in batches:
            x = matrix(b.column("vec"), d)
            n += len(x)
            first += x.sum(axis=0)
            second += x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([first.tolist()], pa.list_(pa.float64())), pa.array([second.reshape(-1).tolist()], pa.list_(pa.float64()))], ["n", "first", "second"])

    n, first, second = 0, np.zeros(d), np.zeros(d * d)
    for r in points.select("vec").mapInArrow(sums, "n long, first array<double>, second array<double>").toLocalIterator():
        n, first, second = n + r["n"], first + np.array(r["first"]), second + np.array(r["second"])
    mean = first / max(n, 1)
    return mean, second.reshape(d, d) / max(n, 1) - np.outer(mean, mean)


def principal(points: DataFrame, d: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Mean and the m leading components (d x m), signs fixed so that the same data give the same components."""
    mean, cov = covariance(points, d)
    _, vectors = np.linalg.eigh(cov)
    top = vectors[:, ::-1][:, :m]
    return mean, top * np.sign(top[np.argmax(np.abs(top), axis=0), np.arange(top.shape[1])])


def project_pca(data: VectorSet, m: int) -> VectorSet:
    mean, w = principal(data.points, data.d, m)
    return with_matrix(data, w, mean)


def front_end(data: VectorSet, front: str, m: int, seed: int = 0) -> VectorSet:
    """divide (nothing is done), lsh or pca."""
    return {"divide": lambda: data, "lsh": lambda: project_lsh(data, m, seed), "pca": lambda: project_pca(data, m)}[front]()
