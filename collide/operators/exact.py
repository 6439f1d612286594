"""Exact nearest neighbours: the truth of all measures."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distances import order_distance, true_distance
from ..functions.vectors import VectorSet
from ..session import BROADCAST_QUERIES
from .blocks import nearest


def blocks_of(queries: DataFrame, key: str = "qid", rows: int = BROADCAST_QUERIES) -> list[DataFrame]:
    """A query set in blocks of about `rows` rows, which may be broadcast."""
    n = -(-queries.count() // rows)
    return [queries.where(F.pmod(F.xxhash64(key), F.lit(n)) == i) for i in range(n)] if n > 1 else [queries]


def in_blocks(data: VectorSet, run: Callable[[VectorSet], DataFrame], rows: int = BROADCAST_QUERIES) -> DataFrame:
    """A search of a query set of any size: block by block."""
    out = None
    for q in blocks_of(data.queries, "qid", rows):
        part = run(replace(data, queries=q))
        out = part if out is None else out.unionByName(part)
    return out


def paired(points: DataFrame, queries: DataFrame) -> DataFrame:
    """Every point with every query of a query set, which is a block of bounded size and so broadcast."""
    return points.crossJoin(F.broadcast(queries))


def first_k(df: DataFrame, k: int, order: Column | str = "dist", tie: str = "id") -> DataFrame:
    """The k least rows of each query with their rank; Spark limits groups before and after the shuffle."""
    w = Window.partitionBy("qid").orderBy(F.col(order) if isinstance(order, str) else order, F.col(tie))
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def exact_knn(points: DataFrame, queries: DataFrame, k: int, d: int, metric: str = "l2", unit: float = 1.0, kernel: str = "auto") -> DataFrame:
    """qid, rank, id, distance. kernel: auto (matrices in Arrow batches), unrolled or hof (a row per pair; the check of the other)."""
    blocks = blocks_of(queries)
    if len(blocks) > 1:
        return in_blocks(VectorSet(points, queries, d, unit), lambda b: exact_knn(b.points, b.queries, k, d, metric, unit, kernel))
    if kernel == "auto":
        near = nearest(points, queries, k, d, metric)
    else:
        near = paired(points, queries).select("qid", "id", order_distance("vec", "qvec", d, metric, kernel).alias("dist"))
    ranked = first_k(near, k)
    return ranked.select("qid", F.col("rank").cast("int").alias("rank"), "id", F.round(true_distance(F.col("dist"), metric, unit), 6).alias("distance"))


def reported(found: DataFrame, metric: str = "l2", unit: float = 1.0) -> DataFrame:
    """qid, rank, id, distance, score of what a search by blocks found."""
    return found.select("qid", "rank", "id", F.round(true_distance(F.col("dist"), metric, unit), 6).alias("distance"), "score")


def radius_search(points: DataFrame, queries: DataFrame, radius: float, d: int, metric: str = "l2", unit: float = 1.0) -> DataFrame:
    """qid, id, distance of all points within a radius. The first coordinate's interval prunes before the distance is formed."""
    r = radius * unit
    near = points.join(F.broadcast(queries), F.abs(F.col("vec")[0] - F.col("qvec")[0]) <= r)
    dist = near.select("qid", "id", order_distance("vec", "qvec", d, metric).alias("dist"))
    return dist.where(F.col("dist") <= (r * r if metric == "l2" else r)).select("qid", "id", F.round(true_distance(F.col("dist"), metric, unit), 6).alias("distance"))
