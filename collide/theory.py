"""The guarantees' formulas, and what the data say beside them."""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction
from math import e, sqrt
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import session
from .plans.subspaces import SubspacePlan

GAMMA = 0.375  # fixed value: the usual shift of normal order statistics


def subspace_moments(points: DataFrame, queries: DataFrame, plan: SubspacePlan, unit: float = 1.0) -> DataFrame:
    """sub, mean, variance of squared distances in each subspace over all pairs."""
    rows = [(s, m / unit**2, v / unit**4) for s, (m, v) in enumerate(pair_moments(points, queries, [list(x) for x in plan.dims])) if m is not None]
    return points.sparkSession.createDataFrame(rows, "sub int, mean double, variance double")


def _sums(vectors: DataFrame, vec: str, dims: list[list[int]]) -> list[tuple]:
    """Per list of dimensions: number, sums of x, of x x', of |x|**2 x, and of |x|**4, exact for whole numbers; one pass."""
    session.ship(vectors.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            at = b.column("vec").filter(b.column("vec").is_valid())
            x = at.flatten().to_numpy(zero_copy_only=False).reshape(len(at), -1)
            part = []
            for d in dims:
                for lo in range(0, len(x), 4096):  # sums of whole numbers stay exact in a block, and are added up as Python's
                    y = x[lo : lo + 4096, d]
                    square = (y * y).sum(axis=1)
                    sums = np.concatenate([[len(y)], y.sum(axis=0), (y.T @ y).reshape(-1), square @ y, [square @ square]])
                    part.append((tuple(d), [Fraction(v) for v in sums.tolist()]))
            for d, sums in part:
                total = total or {}
                total[d] = [a + b for a, b in zip(total[d], sums, strict=True)] if d in total else sums
        for i, d in enumerate(dims):
            if total and tuple(d) in total:
                yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([[str(v) for v in total[tuple(d)]]], pa.list_(pa.string()))], ["part", "sums"])

    out: list = [None] * len(dims)
    for r in vectors.select(F.col(vec).alias("vec")).mapInArrow(run, "part int, sums array<string>").toLocalIterator():  # a few numbers per task
        sums = [Fraction(v) for v in r["sums"]]
        out[r["part"]] = sums if out[r["part"]] is None else [a + b for a, b in zip(out[r["part"]], sums, strict=True)]
    return out


def pair_moments(points: DataFrame, queries: DataFrame, dims: list[list[int]]) -> list[tuple[float | None, float | None]]:
    """Per list of dimensions: mean and variance of squared distances over all pairs of points and queries. No pair is formed: the
    square of |p|**2 + |q|**2 - 2 p.q is a sum of products of moments of either side. None where a side is empty."""
    out: list[tuple[float | None, float | None]] = []
    for d, p, q in zip(dims, _sums(points, "vec", dims), _sums(queries, "qvec", dims), strict=True):
        if p is None or q is None:
            out.append((None, None))
            continue
        w = len(d)
        (p1, p2, p3, p4), (q1, q2, q3, q4) = (([v / x[0] for v in x[1 : 1 + w]], [v / x[0] for v in x[1 + w : 1 + w + w * w]], [v / x[0] for v in x[1 + w + w * w : -1]], x[-1] / x[0]) for x in (p, q))
        ps, qs = sum(p2[:: w + 1]), sum(q2[:: w + 1])  # mean squares of lengths
        dot = lambda a, b: sum(x * y for x, y in zip(a, b, strict=True))
        mean = ps + qs - 2 * dot(p1, q1)
        square = p4 + q4 + 2 * ps * qs + 4 * dot(p2, q2) - 4 * dot(p3, q1) - 4 * dot(p1, q3)
        out.append((float(mean), float(square - mean * mean)))
    return out


def collision_threshold(m: float, var: float, alpha: float) -> float:
    return sqrt((1 - alpha) * (var + m * m))


def alpha_floor(m: float, var: float) -> float:
    r = 1 + m * m / var
    return max(1 / r, 1 - e * e / r)


def ordering_bound(m: float, var: float, ns: int, alpha: float, c: int | None = None) -> dict[str, float | bool]:
    """Probability that a higher score means a smaller distance, and whether the side condition can hold."""
    c = ns - 1 if c is None else c
    g = sqrt((1 - alpha) * (1 + m * m / var))
    side = e > (c + 1) * g + sqrt(8 * (ns - 1)) * (ns - c - 1)
    return {"probability": 1 - 0.25 - 1 / (e * e), "claimed": 0.5 - 1 / (e * e), "side_condition_ok": side}


def kth_moments(k: int, n: int, ns: int, m: float, var: float) -> tuple[float, float]:
    """Mean and variance of the k-th least of n distances over ns subspaces, taken as normal."""
    p = (k - GAMMA) / (n - 2 * GAMMA + 1)
    normal = NormalDist()
    z = normal.inv_cdf(p)
    q = k / (n + 1)
    variance = ns * var * q * (1 - q) / ((n + 2) * normal.pdf(normal.inv_cdf(q)) ** 2)
    return ns * m + z * sqrt(ns * var), variance


def answer_bound(k: int, n: int) -> float:
    """1 - V / t**2 for full collisions: at least one half."""
    return 1 - n**4 / (2 * (n + 1) ** 2 * (n + 2) * k * (n - k + 1))


def answer_condition(k: int, n: int, ns: int, m: float, var: float, alpha: float) -> tuple[float, float, bool]:
    """The t at which the answer bound is one half, the t that its condition asks for, and whether the first exceeds the second."""
    q = k / (n + 1)
    normal = NormalDist()
    t = sqrt(2 * ns * var) / n * k * (n - k + 1) / n / normal.pdf(normal.inv_cdf(q))
    least = ns * m * sqrt((1 - alpha) * (1 + var / (m * m))) - kth_moments(k, n, ns, m, var)[0]
    return t, least, t > least


def ordering_agreement(scores: DataFrame, distances: DataFrame, n_sub: int) -> DataFrame:
    """high, low, pairs, agreement: of all pairs of points with scores high > low, the share whose distances agree.

    No pair is formed: per query, points of each score that lie farther away are a running count over distances."""
    j = scores.join(distances, ["qid", "id"])
    levels = range(n_sub + 1)
    at = j.groupBy("qid", "dist").agg(*[F.sum((F.col("score") == k).cast("long")).alias(f"c{k}") for k in levels])
    w = Window.partitionBy("qid").orderBy(F.col("dist").desc()).rowsBetween(Window.unboundedPreceding, -1)
    run = at.select("*", *[F.coalesce(F.sum(f"c{k}").over(w), F.lit(0)).alias(f"f{k}") for k in levels])
    both = [(h, lo) for h in levels for lo in range(h)]
    per = run.groupBy("qid").agg(*[F.sum(f"c{k}").alias(f"n{k}") for k in levels], *[F.sum(F.col(f"c{h}") * F.col(f"f{lo}")).alias(f"r{h}_{lo}") for h, lo in both])
    rows = F.array(*[F.struct(F.lit(h).alias("high"), F.lit(lo).alias("low"), (F.col(f"n{h}") * F.col(f"n{lo}")).alias("pairs"), F.col(f"r{h}_{lo}").alias("right")) for h, lo in both])
    g = per.select(F.explode(rows).alias("x")).groupBy("x.high", "x.low").agg(F.sum("x.pairs").alias("pairs"), F.sum("x.right").alias("right"))
    return g.where("pairs > 0").select("high", "low", "pairs", (F.col("right") / F.col("pairs")).alias("agreement"))


def answered_share(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Share of queries whose k neighbours were all found."""
    hits = result.select("qid", "id").join(truth.select("qid", "id"), ["qid", "id"]).groupBy("qid").agg(F.count(F.lit(1)).alias("hits"))
    per = truth.select("qid").distinct().join(hits, "qid", "left")
    return per.agg(F.avg((F.coalesce("hits", F.lit(0)) == k).cast("double")).alias("answered"))
