"""The search from SQL: distance functions, a table function that traces walks, and an ANN table."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from .functions.vectors import VectorSet
from .operators.cellindex import CellIndex
from .operators.scan import SearchParams
from .operators.search import indexed_search
from .operators.walks import activation_walk

_FUNCTIONS = {
    "l2_squared": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, t) -> s + t)",
    "l1_distance": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, t) -> s + t)",
    "subspace_l2": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>, first INT, size INT) RETURNS DOUBLE RETURN aggregate(zip_with(slice(a, first, size), slice(b, first, size), (x, y) -> (x - y) * (x - y)), 0D, (s, t) -> s + t)",
}


@udtf(returnType="round int, pos1 int, pos2 int, total double, active int")
class WalkTrace:
    """walk_trace(d1, d2, sizes (row by row), target): what the activation walk takes, round by round."""

    def eval(self, d1: list, d2: list, sizes: list, target: int) -> Iterator[tuple]:
        trace: list = []
        n = len(d2)
        activation_walk(d1, d2, [sizes[i * n : (i + 1) * n] for i in range(len(d1))], target, trace)
        yield from trace


def register(spark: SparkSession) -> None:
    for name, body in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("walk_trace", WalkTrace)


def ann_table(spark: SparkSession, index: CellIndex, points: DataFrame, queries: DataFrame, params: SearchParams, view: str = "ann_search") -> DataFrame:
    """A view with the neighbours of a block of queries: SELECT * FROM ann_search WHERE qid = ..."""
    out = indexed_search(index, VectorSet(points, queries, index.d, 1.0, index.n), params)
    out.createOrReplaceTempView(view)
    return out
