"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from typing import Any

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall_at_k(result: DataFrame, truth: DataFrame, k: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Share of the true neighbours found, over all queries (and per setting, where `by` names columns of result)."""
    settings = result.select(*by).distinct() if by else None
    wanted = truth.select("qid", "id").withColumn("t", F.lit(1))
    found = result.select("qid", "id", *by).join(wanted, ["qid", "id"])
    n = truth.select("qid").distinct().agg(F.count(F.lit(1)).alias("queries"))
    hit = (found.groupBy(*by) if by else found.groupBy()).agg(F.count(F.lit(1)).alias("hits"))
    if settings is not None:
        hit = settings.join(hit, list(by), "left").withColumn("hits", F.coalesce("hits", F.lit(0)))
    return hit.crossJoin(F.broadcast(n)).select(*by, (F.col("hits") / (F.col("queries") * k)).alias("recall"))


def recall_by_distance(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Share of results no farther than the k-th true neighbour: copies of a point count as it does."""
    last = truth.groupBy("qid").agg(F.max("distance").alias("limit"))
    ok = result.join(last, "qid").where(F.col("distance") <= F.col("limit"))
    n = truth.select("qid").distinct().agg(F.count(F.lit(1)).alias("queries"))
    return ok.agg(F.count(F.lit(1)).alias("hits")).crossJoin(F.broadcast(n)).select((F.col("hits") / (F.col("queries") * k)).alias("recall"))


def relative_errors(result: DataFrame, truth: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """qid, rank, error: (found - true) / true; 0/0 is 0, x/0 is null (counted as excluded)."""
    t = truth.select("qid", "rank", F.col("distance").alias("true"))
    j = result.select("qid", "rank", "distance", *by).join(t, ["qid", "rank"])
    return j.select("qid", "rank", *by, F.when(F.col("true") > 0, (F.col("distance") - F.col("true")) / F.col("true")).when(F.col("distance") == 0, F.lit(0.0)).alias("error"))


def mean_relative_error(result: DataFrame, truth: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    e = relative_errors(result, truth, by)
    return (e.groupBy(*by) if by else e.groupBy()).agg(F.round(F.avg("error"), 6).alias("mre"), F.sum(F.col("error").isNull().cast("long")).alias("excluded"))


def lid_mle(knn: DataFrame, k: int) -> DataFrame:
    """Local intrinsic dimensionality: -1 / mean of ln(r_i / r_k) over a query's k neighbours, averaged over queries."""
    w = Window.partitionBy("qid")
    logs = knn.where(F.col("distance") > 0).withColumn("far", F.max("distance").over(w)).where(F.col("distance") < F.col("far"))
    each = logs.groupBy("qid").agg((-1 / F.avg(F.log(F.col("distance") / F.col("far")))).alias("lid"))
    return each.agg(F.round(F.avg("lid"), 4).alias("lid"))


def score_by_rank(scores: DataFrame, distances: DataFrame, buckets: int = 20) -> DataFrame:
    """rank_bucket, avg_score: mean score of points by decile-like bucket of their true rank."""
    w = Window.partitionBy("qid")
    ranked = distances.withColumn("r", F.row_number().over(w.orderBy("dist", "id"))).withColumn("n", F.count(F.lit(1)).over(w))
    b = F.floor((F.col("r") - 1) * buckets / F.col("n")).cast("int")
    j = ranked.select("qid", "id", b.alias("rank_bucket")).join(scores, ["qid", "id"])
    return j.groupBy("rank_bucket").agg(F.round(F.sum("score") / F.count(F.lit(1)), 6).alias("avg_score"))


def turning_point(curve: list[tuple[float, float]]) -> float:
    """Knee of a falling curve: the point farthest from its chord, as a share of the x range."""
    (x0, y0), (x1, y1) = curve[0], curve[-1]

    def apart(p):
        return abs((y1 - y0) * p[0] - (x1 - x0) * p[1] + x1 * y0 - y1 * x0)

    best = max(curve, key=apart)
    return (best[0] - x0) / ((x1 - x0) or 1)


def timed(action: Callable[[], Any]) -> tuple[Any, float]:
    start = time.perf_counter()
    out = action()
    return out, time.perf_counter() - start


def query_time(frame: DataFrame, queries: int) -> float:
    """Seconds per query of a result that is computed whole."""
    _, s = timed(lambda: frame.write.format("noop").mode("overwrite").save())
    return s / max(queries, 1)


def qps(seconds_per_query: float) -> float:
    return 1.0 / seconds_per_query if seconds_per_query else float("inf")


def speedup(base: float, other: float) -> float:
    return base / other


def tradeoff_curve(settings: Iterable, run: Callable[[Any], DataFrame], truth: DataFrame, k: int, queries: int) -> list[tuple[Any, float, float, float]]:
    """(setting, recall, mean relative error, queries per second) for each setting."""
    out = []
    for s in settings:
        result = run(s).persist()
        seconds = query_time(result, queries)
        r = recall_at_k(result, truth, k).first()["recall"]
        e = mean_relative_error(result, truth).first()["mre"]
        out.append((s, r, e, qps(seconds)))
        result.unpersist()
    return out


def min_beta_for_recall(curve: Iterable[tuple[float, float]], target: float) -> float | None:
    """The least candidate share whose recall reaches the target."""
    ok = [beta for beta, recall in curve if recall >= target]
    return min(ok) if ok else None


def walk_stats(cells: DataFrame, target: int) -> DataFrame:
    """qid, sub, pops, points, overshoot of a walk."""
    return cells.groupBy("qid", "sub").agg(F.count(F.lit(1)).alias("pops"), F.sum("n_points").alias("points")).withColumn("overshoot", F.col("points") / F.lit(target))
