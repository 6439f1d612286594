"""Retrieval of cells in ascending summed distance until they hold enough points.

A cell is a pair of places in two lists of distances, each sorted by (distance, cluster). All walks give the same cells in
the same order: by (sum, first place, second place). Whole cells are taken, so the last may overshoot the target.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator, Sequence

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

Cell = tuple[int, int]
_NEVER = float("inf")


def activation_walk(d1: Sequence[float], d2: Sequence[float], sizes: Sequence[Sequence[int]], target: int, trace: list | None = None) -> list[Cell]:
    """Walk with one open row per first-half cluster. sizes[i][j]: points of the cell at places (i, j).

    Only the first row is open at the start; taking a row's first cell opens the next row, and a row that is used up is
    closed, so neither unopened nor finished rows can win a tie.
    """
    front = [_NEVER] * len(d1)  # sum of each open row's next cell
    next_in = [0] * len(d1)
    front[0] = d1[0] + d2[0]
    taken: list[Cell] = []
    held = 0
    while held < target:
        i = min(range(len(front)), key=front.__getitem__)
        if front[i] == _NEVER:
            break
        j = next_in[i]
        taken.append((i, j))
        held += sizes[i][j]
        if trace is not None:
            trace.append((len(taken), i, j, front[i], sum(x < _NEVER for x in front)))
        next_in[i] = j + 1
        front[i] = d1[i] + d2[j + 1] if j + 1 < len(d2) else _NEVER
        if j == 0 and i + 1 < len(d1):
            front[i + 1] = d1[i + 1] + d2[0]
    return taken


def heap_walk(d1: Sequence[float], d2: Sequence[float], sizes: Sequence[Sequence[int]], target: int) -> list[Cell]:
    """The same with a priority queue of the frontier."""
    queue = [(d1[0] + d2[0], 0, 0)]
    taken: list[Cell] = []
    held = 0
    while queue and held < target:
        _, i, j = heapq.heappop(queue)
        taken.append((i, j))
        held += sizes[i][j]
        if j + 1 < len(d2):
            heapq.heappush(queue, (d1[i] + d2[j + 1], i, j + 1))
        if j == 0 and i + 1 < len(d1):
            heapq.heappush(queue, (d1[i + 1] + d2[0], i + 1, 0))
    return taken


def sorted_walk(d1: Sequence[float], d2: Sequence[float], sizes: Sequence[Sequence[int]], target: int) -> list[Cell]:
    """All sums, sorted, cut where enough points are held."""
    cells = sorted((a + b, i, j) for i, a in enumerate(d1) for j, b in enumerate(d2))
    taken, held = [], 0
    for _, i, j in cells:
        if held >= target:
            break
        taken.append((i, j))
        held += sizes[i][j]
    return taken


WALKS = {"activation": activation_walk, "heap": heap_walk, "sorted": sorted_walk}


def _both(lists: DataFrame) -> DataFrame:
    """qid, sub, one, two: both halves' lists side by side."""
    return lists.groupBy("qid", "sub").agg(F.max(F.when(F.col("half") == 0, F.col("ranked"))).alias("one"), F.max(F.when(F.col("half") == 1, F.col("ranked"))).alias("two"))


def prefix_walk(lists: DataFrame, sizes: DataFrame, target: int, sqrt_k: int) -> DataFrame:
    """The sorted form in the engine: qid, sub, c1, c2, sum_dist, n_points, pop_order.

    lists: qid, sub, half (0 or 1), ranked array<struct<dist, cid>>. A query and subspace have sqrt_k ** 2 rows here.
    """
    pairs = _both(lists).select("qid", "sub", "two", F.posexplode("one").alias("p1", "r1")).select("qid", "sub", "p1", "r1", F.posexplode("two").alias("p2", "r2"))
    cells = pairs.select("qid", "sub", "p1", "p2", F.col("r1.cid").alias("c1"), F.col("r2.cid").alias("c2"), (F.col("r1.dist") + F.col("r2.dist")).alias("sum_dist"))
    cells = cells.withColumn("cell", F.col("c1") * sqrt_k + F.col("c2")).join(F.broadcast(sizes), ["sub", "cell"], "left").withColumn("n_points", F.coalesce("n_points", F.lit(0)))
    w = Window.partitionBy("qid", "sub").orderBy("sum_dist", "p1", "p2")
    run = cells.withColumn("before", F.coalesce(F.sum("n_points").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("pop_order", F.row_number().over(w))
    return run.where(F.col("before") < target).select("qid", "sub", F.col("c1").cast("int").alias("c1"), F.col("c2").cast("int").alias("c2"), "sum_dist", F.col("n_points").cast("long").alias("n_points"), F.col("pop_order").cast("int").alias("pop_order"))


_CELLS = "qid long, sub int, c1 int, c2 int, sum_dist double, n_points long, pop_order int"


def list_walk(lists: DataFrame, sizes: DataFrame, target: int, sqrt_k: int, walk: str = "activation") -> DataFrame:
    """Walks over the sorted lists in Arrow batches, a row per query and subspace; sizes (cells, at most subspaces x K) are broadcast."""
    spark = lists.sparkSession
    table: dict[tuple[int, int], int] = {(r["sub"], r["cell"]): r["n_points"] for r in sizes.toLocalIterator()}
    shared = spark.sparkContext.broadcast(table)
    step = WALKS[walk]
    both = _both(lists)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = shared.value
        for b in batches:
            rows = []
            for q, s, one, two in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                d1, c1 = [x["dist"] for x in one], [x["cid"] for x in one]
                d2, c2 = [x["dist"] for x in two], [x["cid"] for x in two]
                held = [[t.get((s, i * sqrt_k + j), 0) for j in c2] for i in c1]
                for n, (i, j) in enumerate(step(d1, d2, held, target), 1):
                    rows.append((q, s, c1[i], c2[j], d1[i] + d2[j], held[i][j], n))
            kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.int64(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)], ["qid", "sub", "c1", "c2", "sum_dist", "n_points", "pop_order"])

    return both.select("qid", "sub", "one", "two").mapInArrow(run, _CELLS)


def flat_walk(lists: DataFrame, sizes: DataFrame, target: int) -> DataFrame:
    """Clusters of one list per subspace in ascending distance until enough points are held: qid, sub, cell."""
    c = lists.select("qid", "sub", F.posexplode("ranked").alias("p", "r")).select("qid", "sub", "p", F.col("r.cid").alias("cell"))
    c = c.join(F.broadcast(sizes), ["sub", "cell"], "left").withColumn("n_points", F.coalesce("n_points", F.lit(0)))
    w = Window.partitionBy("qid", "sub").orderBy("p")
    return c.withColumn("before", F.coalesce(F.sum("n_points").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).where(F.col("before") < target).select("qid", "sub", "cell")
