"""Searches of the baselines by blocks: queries are dealt out over the broadcast points and over arrays of what a build wrote.

For sets of at most `blocks.NUMBERS` values. A search marks the pool of each query of a small block in a row of booleans, from which
the k nearest are taken; no row is made per query and point. Where pools are a few leaves, only the distances to their points are formed. Pools are those of the table forms in `baselines`, ties by id included.
"""

from __future__ import annotations

import weakref
from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import VectorSet
from ..session import ship
from . import blocks
from .blocks import Points
from .exact import reported

#: (arrays, points, queries, first radii) -> which points are in each query's pool.
Mark = Callable[[Any, Points, np.ndarray, np.ndarray], np.ndarray]
#: (arrays, query, distances to the points at some places) -> places of the query's pool, ascending.
Pick = Callable[[Any, np.ndarray, Callable[[np.ndarray], np.ndarray]], np.ndarray]

_held: weakref.WeakKeyDictionary[DataFrame, Points | None] = weakref.WeakKeyDictionary()


def points_of(data: VectorSet) -> Points | None:
    """The points for a broadcast, collected once for all searches of one set; None where they are too many or ids repeat."""
    if not blocks.fits(data.n, data.d):
        return None
    if data.points not in _held:
        _held[data.points] = blocks.collected(data.points, data.d)
        if (np.diff(_held[data.points].ids) == 0).any():
            _held[data.points] = None
    return _held[data.points]


def lists(table: DataFrame, points: Points, column: str, kind: str = "int") -> np.ndarray | None:
    """A list column, or a number, of a written table by the points' places, a row for each; None where its ids are not the points'."""
    c = F.col(column) if table.schema[column].dataType.typeName() == "array" else F.array(column)
    got = table.select(F.col("id").cast("long").alias("id"), c.cast(f"array<{kind}>").alias("c")).toArrow().combine_chunks()
    ids = got.column("id").to_numpy()
    order = np.argsort(ids, kind="stable")
    if not np.array_equal(ids[order], points.ids):
        return None
    return got.column("c").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order]


def picked(arrays: Any, pick: Pick, p: Points, q: np.ndarray, product: bool, kind: type, k: int) -> tuple[np.ndarray, ...]:
    """(row, rank from 1, place, distance) of the k nearest of each query's few."""
    out = []
    for i in range(len(q)):

        def far(at: np.ndarray, one=q[i : i + 1]) -> np.ndarray:
            return blocks.distances(one, np.ascontiguousarray(p.x[:, at]), "l2", product, kind)[0]

        at = pick(arrays, q[i], far)
        dist = far(at)
        order = np.argsort(dist, kind="stable")[:k]
        out.append((np.full(len(order), i), np.arange(1, len(order) + 1), at[order], dist[order].astype(np.float64)))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def search(data: VectorSet, k: int, points: Points, arrays: Any, mark: Mark | None, radii: DataFrame | None = None, pick: Pick | None = None) -> DataFrame:
    """qid, rank, id, distance, score (0)."""
    spark, d = data.queries.sparkSession, data.d
    ship(spark)
    shared = spark.sparkContext.broadcast((points, arrays))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, a = shared.value
        step = max(1, blocks.WHOLE // (8 * max(len(p.ids), 1)))
        for b in batches:
            b = b.filter(b.column("qvec").is_valid())
            qids, asked = blocks.rows_of(b, "qid", "qvec", d)
            r = b.column("r").to_numpy()
            for i in range(0, len(qids), step):
                q = np.ascontiguousarray(asked[i : i + step])
                product, kind = blocks._exact(max(p.top, blocks._top(q)), d, "l2")
                if pick is not None:
                    at, rank, place, dist = picked(a, pick, p, q, product, kind, k)
                else:
                    pool = mark(a, p, q, r[i : i + step])
                    whole = blocks.distances(q, p.x, "l2", product, kind)
                    at, rank, place = blocks.ranked(whole, pool, k)
                    dist = whole[at, place].astype(np.float64)
                yield pa.RecordBatch.from_arrays([blocks._ids(qids[i + at]), pa.array(rank, pa.int32()), blocks._ids(p.ids[place]), pa.array(dist), pa.array(np.zeros(len(at)), pa.int32())], ["qid", "rank", "id", "dist", "score"])

    asked = data.queries.withColumn("r", F.lit(0.0)) if radii is None else data.queries.join(radii, "qid")
    asked = asked.select(F.col("qid").cast("long").alias("qid"), F.col("qvec").cast("array<double>").alias("qvec"), F.col("r").cast("double").alias("r"))
    rows = asked.repartition(4 * spark.sparkContext.defaultParallelism).mapInArrow(run, blocks.FOUND)
    return reported(rows, "l2", data.unit)


def tiles(p: Points, rows: int = 1 << 14) -> Iterator[tuple[slice, np.ndarray]]:
    """Points a tile at a time, a row each, so that what is derived from them stays small."""
    for lo in range(0, p.x.shape[1], rows):
        at = slice(lo, lo + rows)
        yield at, p.x[:, at].T.astype(np.float64)


# --- marks ------------------------------------------------------------------------------------------------------------


def rings(target: int, c: float) -> Mark:
    """Leaves of each tree in rings around the query until they hold the pool. Arrays: weights, and of each tree the boxes' lows, highs and
    sizes with the box of each point."""

    def mark(a, p, q, r):
        w, trees = a
        x, out = q @ w, np.zeros((len(p.ids), len(q)), dtype=bool)
        for t, (lo, hi, size, at) in enumerate(trees):
            K = lo.shape[1]
            y, gap = x[:, t * K : (t + 1) * K], np.zeros((len(q), len(lo)))
            for j in range(K):
                g = np.maximum(np.maximum(lo[:, j] - y[:, j, None], y[:, j, None] - hi[:, j]), 0.0)
                gap += g * g
            with np.errstate(divide="ignore"):
                reach = np.log(np.sqrt(gap)) / np.log(c)
            ring = np.where(gap <= 0, -(1 << 30), np.ceil(np.where(gap <= 0, 0, reach))).astype(np.int64)
            order = np.argsort(ring, axis=1, kind="stable")
            ring, n = np.take_along_axis(ring, order, 1), size[order]
            new = np.ones(ring.shape, dtype=bool)
            new[:, 1:] = ring[:, 1:] != ring[:, :-1]
            before = np.maximum.accumulate(np.where(new, n.cumsum(axis=1) - n, 0), axis=1)
            taken = np.zeros(ring.shape, dtype=bool)
            np.put_along_axis(taken, order, before < target, 1)
            out |= blocks.spread(taken, at)
        return np.ascontiguousarray(out.T)

    return mark


def _widened(reach: np.ndarray, r: np.ndarray, target: int, c: float) -> np.ndarray:
    """What lies within a radius that grows by c until it holds the pool. The first radius is the distance of a point, which other
    rounding is not to put outside."""
    target, r = min(target, reach.shape[1]), r.copy()
    while True:
        inside = reach <= r[:, None] * (1 + 1e-12)
        short = inside.sum(axis=1) < target
        if not short.any():
            return inside
        r[short] *= c


def windows(target: int, c: float, L: int, K: int) -> Mark:
    """Cubes in any of the projected spaces. Arrays: weights."""

    def mark(w, p, q, r):
        y, reach = q @ w, np.empty((len(q), len(p.ids)))
        for at, x in tiles(p):
            x, best = np.ascontiguousarray((x @ w).T), None
            for t in range(L):
                far = np.abs(x[t * K] - y[:, t * K, None])
                for j in range(t * K + 1, (t + 1) * K):
                    np.maximum(far, np.abs(x[j] - y[:, j, None]), out=far)
                best = far if best is None else np.minimum(best, far, out=best)
            reach[:, at] = best
        return _widened(reach, r, target, c)

    return mark


def ball(target: int, c: float) -> Mark:
    """Balls in the projected space. Arrays: weights."""

    def mark(w, p, q, r):
        y, reach = q @ w, np.empty((len(q), len(p.ids)))
        for at, x in tiles(p):
            reach[:, at] = np.sqrt(blocks.distances(y, np.ascontiguousarray((x @ w).T), "l2", False))
        return _widened(reach, r, target, c)

    return mark


def longest_runs(same: np.ndarray, m: int) -> np.ndarray:
    """The longest run of set bits of each mask on a circle of m places."""
    out, full = np.zeros(same.shape, dtype=np.uint8), np.uint64((1 << m) - 1)
    at = np.flatnonzero(same)
    x = same.reshape(-1)[at]
    flat = out.reshape(-1)
    for length in range(1, m + 1):
        flat[at] = length
        x = x & ((x << np.uint64(1) | x >> np.uint64(m - 1)) & full)
        left = x != 0
        at, x = at[left], x[left]
        if not len(at):
            break
    return out


def circular(check_k: int) -> Mark:
    """The points of the longest circular runs of equal hashes. Arrays: projection, shift, the points' hashes (a row for each hash)."""

    def mark(a, p, q, r):
        w, shift, strings = a
        asked, same = np.floor(q @ w + shift).astype(np.int32), np.zeros((len(q), len(p.ids)), dtype=np.uint64)
        for j in range(len(strings)):
            same |= (strings[j] == asked[:, j, None]).astype(np.uint64) << np.uint64(j)
        return blocks.best_scored(longest_runs(same, len(strings)), check_k)

    return mark


def keys(cell: np.ndarray, codes: np.ndarray, words: list) -> np.ndarray:
    """A row per book: each point's cell and code as one number."""
    return np.stack([cell.astype(np.int32) * len(w) + codes[:, s] for s, w in enumerate(words)])


def quantised(target: int, pool: int) -> Mark:
    """Cells in ascending distance until they hold enough; distances to decoded vectors rank what they hold. Of each book there is a
    table of the distances to what a cell and a code are decoded to, and points look theirs up. Arrays: mean, rotation, coarse centroids, code words, each point's
    cell and keys."""

    def mark(a, p, q, r):
        mean, rotation, c, words, cell, keys = a
        y = (q - mean) @ rotation
        half, wide = c[0].shape[1], len(c[1])
        far = (((y[:, None, :half] - c[0]) ** 2).sum(axis=2)[:, :, None] + ((y[:, None, half:] - c[1]) ** 2).sum(axis=2)[:, None]).reshape(len(q), -1)
        order = np.argsort(far, axis=1, kind="stable")
        n = np.bincount(cell, minlength=far.shape[1])[order]
        cells = np.zeros(far.shape, dtype=bool)
        np.put_along_axis(cells, order, n.cumsum(axis=1) - n < target, 1)
        centre = np.hstack([np.repeat(c[0], wide, axis=0), np.tile(c[1], (len(c[0]), 1))])
        estimate, lo = np.zeros((len(cell), len(q))), 0
        for w, key in zip(words, keys, strict=True):
            decoded = (centre[:, None, lo : lo + w.shape[1]] + w).reshape(-1, w.shape[1])
            estimate += blocks.spread(blocks.distances(y[:, lo : lo + w.shape[1]], np.ascontiguousarray(decoded.T), "l2", False), key)
            lo += w.shape[1]
        out, taken = np.zeros((len(q), len(cell)), dtype=bool), blocks.spread(cells, cell)
        for i in range(len(q)):
            at = np.flatnonzero(taken[:, i])
            out[i, at] = blocks.least(estimate[at, i][None], pool)[0]
        return out

    return mark


def members(leaf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places sorted by leaf, and where each leaf starts."""
    order = np.argsort(leaf, kind="stable").astype(np.int32)
    return order, np.searchsorted(leaf[order], np.arange(int(leaf.max(initial=-1)) + 2))


def _of(m: tuple[np.ndarray, np.ndarray], leaf: int) -> np.ndarray:
    order, start = m
    return order[start[leaf] : start[leaf + 1]] if leaf + 1 < len(start) else order[:0]


def forest(leaves: Callable) -> Pick:
    """Points of the best leaves. Arrays: trees, sizes of their leaves, members of each tree's leaves."""

    def pick(a, q, far):
        trees, sizes, own = a
        at = [_of(own[t], leaf) for t, leaf in leaves(trees, sizes, q)]
        return np.unique(np.concatenate(at)) if at else np.empty(0, dtype=np.int32)

    return pick


def hopped(leaves: Callable, hops: int, beam: int) -> Pick:
    """Points of the best leaves, then along edges. Arrays: trees, sizes of their leaves, members of the leaves, edges by their start."""

    def pick(a, q, far):
        trees, sizes, own, (start, to) = a

        def closest(at: list) -> np.ndarray:
            at = np.unique(np.concatenate(at)) if at else np.empty(0, dtype=np.int32)
            return at[np.argsort(far(at), kind="stable")[:beam]]

        front = closest([_of(own[t], leaf) for t, leaf in leaves(trees, sizes, q)])
        for _ in range(hops):
            front = closest([front, *[to[start[j] : start[j + 1]] for j in front.tolist()]])
        return np.sort(front)

    return pick
