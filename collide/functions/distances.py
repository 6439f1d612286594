"""Distances between two array columns as Column expressions; they stay inside generated code."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Terms that are written out; longer sums go through higher-order functions.
UNROLLED = 128


def _check(metric: str) -> None:
    if metric not in ("l2", "l1"):
        raise ValueError(f"metric is l2 or l1, not {metric!r}")


def partial(a: str, b: str, dims: Sequence[int], metric: str = "l2", kernel: str = "auto") -> Column:
    """Sum over dims of squared (l2) or absolute (l1) differences of array columns a and b."""
    _check(metric)
    if kernel == "auto":
        kernel = "unrolled" if len(dims) <= UNROLLED else "hof"
    if kernel == "unrolled":
        terms = [f"abs({a}[{i}] - {b}[{i}])" if metric == "l1" else f"(({a}[{i}] - {b}[{i}]) * ({a}[{i}] - {b}[{i}]))" for i in dims]
        return F.expr(" + ".join(terms))
    contiguous = list(dims) == list(range(dims[0], dims[0] + len(dims)))
    x = F.slice(a, dims[0] + 1, len(dims)) if contiguous else F.transform(F.array(*map(F.lit, dims)), lambda i: F.get(a, i))
    y = F.slice(b, dims[0] + 1, len(dims)) if contiguous else F.transform(F.array(*map(F.lit, dims)), lambda i: F.get(b, i))
    each = F.zip_with(x, y, (lambda u, v: F.abs(u - v)) if metric == "l1" else (lambda u, v: (u - v) * (u - v)))
    return F.aggregate(each, F.lit(0.0), lambda s, t: s + t)


def order_distance(a: str, b: str, d: int, metric: str = "l2", kernel: str = "auto") -> Column:
    """What ranks like the distance over all dimensions: its square for l2."""
    return partial(a, b, range(d), metric, kernel)


def true_distance(order: Column, metric: str = "l2", unit: float = 1.0) -> Column:
    """The distance from its order value; `unit` is the length of one step where vectors lie on an integer grid."""
    _check(metric)
    value = F.sqrt(order) if metric == "l2" else order
    return value / F.lit(float(unit)) if unit != 1.0 else value
