"""Distances by blocks: matrices of queries and points in Arrow batches instead of a row per pair.

Both forms give the rows of the plain ones (`first_k` over `paired`, windows over `part_distances`), ties by id included. Values on
an integer grid are multiplied, which is exact while all sums stay below 2**53; other values, and L1, are summed by plain
differences in the order of the dimensions, as the generated code sums them.

`nearest` streams the points past a broadcast block of queries. `by_query` deals out the queries and broadcasts the points,
sorted by id, because a rank border needs all distances of a query; it is for sets of at most NUMBERS values.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship

#: Values of a point set that is broadcast.
NUMBERS = 40_000_000
#: Bytes of a block of distances.
TILE = 1 << 24
#: Bytes of a block of distances of which only the least are kept, so that it stays in a core's cache.
NEAR = 1 << 21
#: Fetched rows that are put in their places at once.
ROWS = 10_000
#: Bytes of the whole distances of a small block of queries to all points of a set that is broadcast, and points that are multiplied at a time.
WHOLE = 1 << 25
WIDE = 4_096
#: Elements of a block that is summed dimension by dimension, so that it stays in a core's cache.
CACHED = 1 << 16
_NULL = np.iinfo(np.int64).min  # a null id: before all others, as Spark sorts it


def rows_of(b: pa.RecordBatch, key: str, vec: str, d: int) -> tuple[np.ndarray, np.ndarray]:
    """ids and vectors of a batch; rows without a vector are left out."""
    there = b.column(vec).is_valid()
    b = b.filter(there) if b.column(vec).null_count else b
    x = b.column(vec).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
    if len(x) != len(b):
        raise ValueError(f"vectors are to have {d} values")
    return b.column(key).fill_null(int(_NULL)).to_numpy(zero_copy_only=False), x


def _exact(top: float, d: int, metric: str) -> tuple[bool, type]:
    """For whole numbers up to `top`: may distances be formed by products, and the type that sums of differences need."""
    if metric == "l1":
        return False, np.float32 if 2 * top * d < 1 << 24 else np.float64
    return 4 * top * top * d < 1 << 52, np.float64


def _top(x: np.ndarray) -> float:
    """The largest absolute value, infinite where there are values off the integer grid."""
    if not x.size:
        return 0.0
    top = float(np.abs(x).max())
    return top if np.isfinite(top) and np.array_equal(x, np.floor(x)) else float("inf")


def distances(q: np.ndarray, p: np.ndarray, metric: str, product: bool, kind: type = np.float64) -> np.ndarray:
    """(queries x points) from queries (rows) and points (columns): squares for l2."""
    if product:  # the lengths are two more dimensions: one product, and no pass over its result
        wide, tall = np.empty((len(q), q.shape[1] + 2)), np.empty((len(p) + 2, min(p.shape[1], WIDE)))
        np.multiply(q, -2.0, out=wide[:, :-2])
        wide[:, -2] = np.einsum("ij,ij->i", q, q, dtype=np.float64)
        wide[:, -1] = 1
        out = np.empty((len(q), p.shape[1]))
        for j in range(0, p.shape[1], WIDE):  # so that the points' eight-byte copy stays in the cache
            t = tall[:, : min(WIDE, p.shape[1] - j)]
            t[:-2] = p[:, j : j + WIDE]
            t[-2] = 1
            np.einsum("ij,ij->j", t[:-2], t[:-2], out=t[-1])
            np.matmul(wide, t, out=out[:, j : j + WIDE])
        return out
    q, p = q.astype(kind, copy=False), p.astype(kind, copy=False)
    out = np.empty((len(q), p.shape[1]), dtype=kind)
    wide = min(max(p.shape[1], 1), 4096)
    tall = max(1, CACHED // wide)
    for i in range(0, len(q), tall):
        for j in range(0, p.shape[1], wide):
            total = out[i : i + tall, j : j + wide]
            for k in range(q.shape[1]):
                diff = p[k, j : j + wide] - q[i : i + tall, k, None]
                np.abs(diff, out=diff) if metric == "l1" else np.multiply(diff, diff, out=diff)
                if k:
                    total += diff
                else:
                    total[:] = diff
    return out


# --- nearest neighbours -----------------------------------------------------------------------------------------------


class Best:
    """The k least (distance, id) of each of n queries, among what was offered."""

    def __init__(self, n: int, k: int):
        self.k, self.limit = k, np.full(n, np.inf)
        self.q, self.dist, self.id = np.empty(0, dtype=np.int64), np.empty(0), np.empty(0, dtype=np.int64)
        self.waiting: list[tuple] = []
        self.held = 0

    def offer(self, dist: np.ndarray, ids: np.ndarray, first: int = 0) -> None:
        """Distances of queries from number `first` on to the points of these ids."""
        limit = self.limit[first : first + len(dist)]
        if dist.shape[1] > self.k and np.isinf(limit).any():
            limit = np.minimum(limit, np.partition(dist, self.k - 1, axis=1)[:, self.k - 1])
        at = np.flatnonzero(~(dist > limit[:, None]))  # what is no number stays, and is sorted last
        if len(at):
            q, p = np.divmod(at, dist.shape[1])
            self.waiting.append((q + first, dist.ravel()[at].astype(np.float64, copy=False), ids[p]))
            self.held += len(at)
            if self.held > 2 * self.k * len(self.limit):
                self.settle()

    def settle(self) -> None:
        q, dist, id_ = (np.concatenate(x) for x in zip((self.q, self.dist, self.id), *self.waiting, strict=True))
        order = np.lexsort((id_, dist, q))
        q, dist, id_ = q[order], dist[order], id_[order]
        at = np.arange(len(q)) - np.searchsorted(q, q)
        keep = at < self.k
        full = at == self.k - 1
        self.limit[q[full]] = np.where(np.isnan(dist[full]), np.inf, dist[full])
        self.q, self.dist, self.id, self.waiting, self.held = q[keep], dist[keep], id_[keep], [], 0


def _ids(values: np.ndarray) -> pa.Array:
    return pa.array(values, pa.int64(), mask=values == _NULL)


def nearest(points: DataFrame, queries: DataFrame, k: int, d: int, metric: str = "l2") -> DataFrame:
    """qid, id, dist: the k nearest points of each query within each task's points; the nearest of all are among them. `queries` is
    a block that may be broadcast."""
    spark = points.sparkSession
    ship(spark)
    asked = queries.select(F.col("qid").cast("long").alias("qid"), F.col("qvec").cast("array<double>").alias("qvec")).toArrow().combine_chunks()
    batches = asked.to_batches()
    parts = [rows_of(b, "qid", "qvec", d) for b in batches]
    qids = np.concatenate([p[0] for p in parts]) if parts else np.empty(0, dtype=np.int64)
    q = np.concatenate([p[1] for p in parts]) if parts else np.empty((0, d))
    shared = spark.sparkContext.broadcast((qids, q, _top(q)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, q, top = shared.value
        best = Best(len(q), k)
        step = max(256, NEAR // (8 * max(len(q), 1)))
        tall = max(1, NEAR // (8 * step))
        for b in batches if len(q) else ():
            ids, x = rows_of(b, "id", "vec", d)
            product, kind = _exact(max(top, _top(x)), d, metric)
            for j in range(0, len(ids), step):
                p = np.ascontiguousarray(x[j : j + step].T)
                for i in range(0, len(q), tall):
                    best.offer(distances(q[i : i + tall], p, metric, product, kind), ids[j : j + step], i)
        best.settle()
        for lo in range(0, len(best.q), 100_000):
            part = slice(lo, lo + 100_000)
            yield pa.RecordBatch.from_arrays([_ids(qids[best.q[part]]), _ids(best.id[part]), pa.array(best.dist[part])], ["qid", "id", "dist"])

    return points.select(F.col("id").cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "qid long, id long, dist double")


# --- borders without a broadcast of points -----------------------------------------------------------------------------

#: Distance classes an octave: neighbouring classes differ by a third of a percent.
OCTAVE = 256
_CLASS = 1 << 20
#: Class counts that a task hands on together.
HELD = 4_000_000


def distance_classes(dist: np.ndarray) -> np.ndarray:
    """A class from 0 on that grows with the distance and needs no look at the data's extremes."""
    with np.errstate(divide="ignore"):
        c = np.floor(np.log2(np.maximum(dist, 0)) * OCTAVE)
    return np.where(dist > 0, c + _CLASS // 2, 0).astype(np.int64)


class Parts:
    """Distances in each subspace between a block of queries, broadcast, and points that are streamed past it."""

    def __init__(self, points: DataFrame, queries: DataFrame, plan_dims: list, metric: str):
        d = max(i for x in plan_dims for i in x) + 1
        self.points = points.select(F.col("id").cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec"))
        ship(points.sparkSession)
        asked = queries.select(F.col("qid").cast("long").alias("qid"), F.col("qvec").cast("array<double>").alias("qvec")).toArrow()
        got = [rows_of(b, "qid", "qvec", d) for b in asked.to_batches()]
        self.qids = np.concatenate([g[0] for g in got]) if got else np.empty(0, dtype=np.int64)
        q = np.concatenate([g[1] for g in got]) if got else np.empty((0, d))
        self.dims, self.d, self.metric = [list(x) for x in plan_dims], d, metric
        self.spark = points.sparkSession
        self.shared = self.spark.sparkContext.broadcast((self.qids, q, _top(q)))

    def stream(self, body: Callable, schema: str) -> DataFrame:
        """Rows of body(tiles), tiles being (qids, number of the first query, ids, distances of each subspace)."""
        shared, dims, d, metric = self.shared, self.dims, self.d, self.metric

        def tiles(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
            qids, q, top = shared.value
            for b in batches if len(q) else ():
                ids, x = rows_of(b, "id", "vec", d)
                product, kind = _exact(max(top, _top(x)), d, metric)
                p = np.ascontiguousarray(x.T)
                tall = max(1, TILE // (8 * len(dims) * max(len(ids), 1)))
                for i in range(0, len(q), tall):
                    yield qids[i : i + tall], i, ids, [distances(q[i : i + tall][:, at], p[at], metric, product, kind) for at in dims]

        return self.points.mapInArrow(lambda batches: body(tiles(batches)), schema)

    def class_counts(self) -> DataFrame:
        """qid, sub, class, c: points of each distance class, by task."""
        n, shared = len(self.dims), self.shared

        def run(tiles: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
            waiting: list[tuple] = []
            held = 0

            def settled() -> Iterator[pa.RecordBatch]:
                keys, at = np.unique(np.concatenate([w[0] for w in waiting]), return_inverse=True)
                counts = np.bincount(at, weights=np.concatenate([w[1] for w in waiting])).astype(np.int64)
                for lo in range(0, len(keys), 100_000):
                    k = keys[lo : lo + 100_000]
                    yield pa.RecordBatch.from_arrays([_ids(shared.value[0][k // _CLASS // n]), pa.array((k // _CLASS % n).astype(np.int32)), pa.array((k % _CLASS).astype(np.int32)), pa.array(counts[lo : lo + 100_000])], ["qid", "sub", "class", "c"])

            for _, first, _, parts in tiles:
                for s, dist in enumerate(parts):
                    row = ((np.arange(len(dist)) + first) * n + s) * _CLASS
                    waiting.append(np.unique(distance_classes(dist) + row[:, None], return_counts=True))
                    held += len(waiting[-1][0])
                if held > HELD:
                    yield from settled()
                    waiting, held = [], 0
            if waiting:
                yield from settled()

        return self.stream(run, "qid long, sub int, class int, c long")

    def _table(self, rows: pa.Table, column: str, missing: int | float, kind: type) -> np.ndarray:
        """(queries x subspaces) from rows of qid and sub."""
        out = np.full((len(self.qids), len(self.dims)), missing, dtype=kind)
        order = np.argsort(self.qids, kind="stable")
        at = order[np.searchsorted(self.qids[order], rows.column("qid").fill_null(int(_NULL)).to_numpy())] if rows.num_rows else np.empty(0, dtype=np.int64)
        out[at, rows.column("sub").to_numpy()] = rows.column(column).fill_null(int(_NULL)).to_numpy() if kind is np.int64 else rows.column(column).to_numpy()
        return out

    def sure_and_border(self, borders: DataFrame) -> DataFrame:
        """qid, id, sure, border, of a row per query and subspace (qid, sub, class): in how many subspaces a point's class lies before the
        border's, and its distances in those where it is the same; points of neither are left out."""
        got = borders.select("qid", "sub", F.col("class").cast("long").alias("class")).toArrow()
        classes = np.full((len(self.qids), len(self.dims)), -1, dtype=np.int64)
        order = np.argsort(self.qids, kind="stable")
        if got.num_rows:
            classes[order[np.searchsorted(self.qids[order], got.column("qid").fill_null(int(_NULL)).to_numpy())], got.column("sub").to_numpy()] = got.column("class").to_numpy()
        at = self.spark.sparkContext.broadcast(classes)

        def run(tiles: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
            for qids, first, ids, parts in tiles:
                limit = at.value[first : first + len(qids)]
                sure = np.zeros((len(qids), len(ids)), dtype=np.int8)
                same = np.zeros((len(qids), len(ids), len(parts)), dtype=bool)
                for s, dist in enumerate(parts):
                    c = distance_classes(dist)
                    sure += c < limit[:, s, None]
                    same[:, :, s] = c == limit[:, s, None]
                q, p = np.nonzero((sure > 0) | same.any(axis=2))
                pair, s = np.nonzero(same[q, p])
                dist = np.stack(parts)[s, q[pair], p[pair]].astype(np.float64)
                ends = np.append(0, np.cumsum(np.bincount(pair, minlength=len(q)))).astype(np.int32)
                border = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(s.astype(np.int32)), pa.array(dist)], ["sub", "dist"]))
                yield pa.RecordBatch.from_arrays([_ids(qids[q]), _ids(ids[p]), pa.array(sure[q, p]), border], ["qid", "id", "sure", "border"])

        return self.stream(run, "qid long, id long, sure byte, border array<struct<sub:int,dist:double>>")


# --- whole rankings ---------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Points:
    """All points of a set by id: ids, vectors (a column each), the largest absolute value of whole numbers (else infinite), cells."""

    ids: np.ndarray
    x: np.ndarray
    top: float
    codes: np.ndarray | None = None


def fits(n: int, d: int) -> bool:
    return n * d <= NUMBERS


def collected(points: DataFrame, d: int, codes: DataFrame | None = None) -> Points:
    """The points on the driver, for a broadcast: at most NUMBERS values, in four bytes each where these hold them exactly."""
    p = points.select(F.col("id").cast("long").alias("id"), "vec").where("vec IS NOT NULL")
    lost = F.exists("vec", lambda v: v.isNull() | (v != v.cast("float").cast("double")))
    kind = "float" if p.where(lost).isEmpty() else "double"
    p = p.select("id", F.col("vec").cast(f"array<{kind}>").alias("vec"))
    p = p.join(codes.select("id", F.col("cells").cast("array<int>").alias("cells")), "id") if codes is not None else p
    got = p.toArrow().combine_chunks()
    id_ = got.column("id").fill_null(int(_NULL)).to_numpy()
    order = np.argsort(id_, kind="stable")
    place = np.empty_like(order)
    place[order] = np.arange(len(order))
    # each row is put where it belongs: beside what was fetched there is one copy on the driver, which is then sent
    x, top, at = np.empty((d, len(order)), dtype=np.float32 if kind == "float" else np.float64), 0.0, 0
    cells = None
    for b in got.to_batches(max_chunksize=ROWS):
        rows = rows_of(b, "id", "vec", d)[1]
        here = place[at : at + len(b)]
        x[:, here] = rows.T
        if codes is not None:
            c = b.column("cells").flatten().to_numpy(zero_copy_only=False).reshape(len(b), -1)
            cells = np.empty((c.shape[1], len(order)), dtype=c.dtype) if cells is None else cells
            cells[:, here] = c.T
        top, at = max(top, _top(rows)), at + len(b)
    return Points(id_[order], x, top, cells)


def first_true(mask: np.ndarray, need: np.ndarray) -> np.ndarray:
    """Of each row's true places only the first `need`."""
    for i in np.flatnonzero(mask.sum(axis=1) > need).tolist():
        mask[i, np.flatnonzero(mask[i])[max(int(need[i]), 0) :]] = False
    return mask


def least(dist: np.ndarray, m: int) -> np.ndarray:
    """Which are the m least of each row, equal ones by place."""
    if m >= dist.shape[1]:
        return np.ones(dist.shape, dtype=bool)
    limit = np.partition(dist, m - 1, axis=1)[:, m - 1, None]
    inside = dist <= limit
    if np.count_nonzero(inside) == m * len(dist):
        return inside
    below = dist < limit
    return below | first_true(inside & ~below, m - below.sum(axis=1))


def best_scored(score: np.ndarray, pool: int) -> np.ndarray:
    """Which are the `pool` best-scored of each row, equal ones by place: a histogram gives the cut, the class there is divided."""
    if pool >= score.shape[1]:
        return np.ones(score.shape, dtype=bool)
    counts = np.stack([np.bincount(r, minlength=256) for r in score])[:, ::-1].cumsum(axis=1)
    at = (counts < pool).sum(axis=1)
    cut = (255 - at).astype(np.int16)[:, None]
    need = pool - np.where(at > 0, np.take_along_axis(counts, np.maximum(at - 1, 0)[:, None], 1)[:, 0], 0)
    return (score > cut) | first_true(score == cut, need)


def ranked(whole: np.ndarray, among: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, rank from 1, place) of the k nearest of each row among some, equal ones by place."""
    out = []
    for i in range(len(whole)):
        at = np.flatnonzero(among[i])
        dist = whole[i, at]
        if len(at) > k:
            near = ~(dist > np.partition(dist, k - 1)[k - 1])
            at, dist = at[near], dist[near]
        at = at[np.argsort(dist, kind="stable")[:k]]
        out.append((np.full(len(at), i), np.arange(1, len(at) + 1), at))
    return tuple(np.concatenate([o[j] for o in out]) if out else np.empty(0, dtype=np.int64) for j in range(3))


def spread(table: np.ndarray, at: np.ndarray) -> np.ndarray:
    """(points x queries) of a table (queries x cells) at each point's cell: one look-up serves a point for all queries."""
    return np.take(np.ascontiguousarray(table.T), at, axis=0)


Scores = Callable[[Points, np.ndarray], tuple[np.ndarray, np.ndarray]]
Body = Callable[[np.ndarray, np.ndarray, np.ndarray, Points], list]


def collisions(plan_dims: list, m: int, metric: str) -> Scores:
    """Per block of queries: scores of all points, and whole distances."""
    dims = [list(x) for x in plan_dims]

    def run(points: Points, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        top = max(points.top, _top(q))
        product, kind = _exact(top, len(points.x), metric)
        score = np.zeros((len(q), points.x.shape[1]), dtype=np.uint8)
        each = sorted(i for x in dims for i in x) == list(range(len(points.x))) and np.isfinite(top)
        whole = np.zeros(score.shape) if each else None
        for x in dims:
            part = distances(q[:, x], points.x[x], metric, product, kind)
            score += least(part, m)
            if each:
                whole += part  # whole numbers: the order of sums does not matter
        return score, whole if each else distances(q, points.x, metric, product, kind)

    return run


def walked(centroids: list, parts: list, per: int, target: int, metric: str, half_distance: str) -> Scores:
    """Scores by an index's cells, and whole distances: per subspace the cells in ascending order of their centroid distances' sums,
    equal ones by the places in both lists, until they hold `target` points."""

    def run(points: Points, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        score = np.zeros((points.x.shape[1], len(q)), dtype=np.uint8)
        for s in range(len(parts) // per):
            cells = total = None
            for h in range(s * per, (s + 1) * per):
                dist = distances(q[:, list(parts[h])], centroids[h].T, metric, False)
                dist = np.sqrt(dist) if metric == "l2" and half_distance == "plain" else dist
                order = np.argsort(dist, axis=1, kind="stable")
                dist = np.take_along_axis(dist, order, 1)
                if cells is None:
                    cells, total = order, dist
                else:
                    cells = (cells[:, :, None] * dist.shape[1] + order[:, None, :]).reshape(len(q), -1)
                    total = (total[:, :, None] + dist[:, None, :]).reshape(len(q), -1)
            cells = np.take_along_axis(cells, np.argsort(total, axis=1, kind="stable"), 1)
            held = np.bincount(points.codes[s], minlength=cells.shape[1])[cells]
            active = np.zeros(cells.shape, dtype=np.uint8)
            np.put_along_axis(active, cells, held.cumsum(axis=1) - held < target, 1)
            score += spread(active, points.codes[s])
        product, kind = _exact(max(points.top, _top(q)), len(points.x), metric)
        return np.ascontiguousarray(score.T), distances(q, points.x, metric, product, kind)

    return run


def by_query(points: Points, queries: DataFrame, d: int, scores: Scores, body: Body, schema: str) -> DataFrame:
    """Rows that `body` (qids, scores, whole distances, points) makes of each small block of queries."""
    spark = queries.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(points)
    columns = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = shared.value
        step = max(1, WHOLE // (8 * max(len(p.ids), 1)))
        for b in batches:
            qids, q = rows_of(b, "qid", "qvec", d)
            for i in range(0, len(qids), step):
                score, whole = scores(p, np.ascontiguousarray(q[i : i + step]))
                yield pa.RecordBatch.from_arrays(body(qids[i : i + step], score, whole, p), columns)

    asked = queries.select(F.col("qid").cast("long").alias("qid"), F.col("qvec").cast("array<double>").alias("qvec"))
    return asked.repartition(4 * spark.sparkContext.defaultParallelism).mapInArrow(run, schema)


def found(k: int, pool: int) -> Body:
    """qid, rank, id, dist, score: the k nearest of the pool."""

    def run(qids, score, whole, points):
        i, rank, at = ranked(whole, best_scored(score, pool), k)
        return [_ids(qids[i]), pa.array(rank, pa.int32()), _ids(points.ids[at]), pa.array(whole[i, at].astype(np.float64)), pa.array(score[i, at], pa.int32())]

    return run


FOUND = "qid long, rank int, id long, dist double, score int"


def best(k: int) -> Body:
    """qid, rank, id, score: the k first by score, equal ones by place; no distance is looked at."""

    def run(qids, score, whole, points):
        i, rank, at = ranked(-score.astype(np.int16), best_scored(score, k), k)
        return [_ids(qids[i]), pa.array(rank, pa.int32()), _ids(points.ids[at]), pa.array(score[i, at], pa.int32())]

    return run


BEST = "qid long, rank int, id long, score int"


def scored(least_score: int = 0) -> Body:
    """qid, id, score of all points of a score at least."""

    def run(qids, score, whole, points):
        i, at = np.nonzero(score >= least_score)
        return [_ids(qids[i]), _ids(points.ids[at]), pa.array(score[i, at], pa.int32())]

    return run


SCORED = "qid long, id long, score int"


def counted(pool: int = 0) -> Body:
    """qid, points that collide, their collisions, and how many of the `pool` best-scored are among the `pool` nearest."""

    def run(qids, score, whole, points):
        shared = (best_scored(score, pool) & least(whole, pool)).sum(axis=1) if pool else np.zeros(len(qids))
        counts = (np.count_nonzero(score, axis=1), score.sum(axis=1, dtype=np.int64), shared)
        return [_ids(qids), *[pa.array(c, pa.int64()) for c in counts]]

    return run


COUNTED = "qid long, candidates long, collisions long, shared long"


def steps(pool: int) -> Body:
    """qid, and how many points are compared, collide, and are in the pool."""

    def run(qids, score, whole, points):
        counts = (np.full(len(qids), score.shape[1]), np.count_nonzero(score, axis=1), best_scored(score, pool).sum(axis=1))
        return [_ids(qids), *[pa.array(c, pa.int64()) for c in counts]]

    return run


STEPS = "qid long, pairs long, scored long, pool long"


def curve(buckets: int) -> Body:
    """qid, rank_bucket, total, n: scores of the points of each bucket of their true rank."""

    def run(qids, score, whole, points):
        n = score.shape[1]
        bucket = np.arange(n) * buckets // max(n, 1)
        q, b, total, size = [], [], [], []
        for i in range(len(qids)):
            s = score[i, np.argsort(whole[i], kind="stable")]
            at = np.unique(bucket)
            q.append(np.full(len(at), qids[i]))
            b.append(at)
            total.append(np.bincount(bucket, weights=s, minlength=buckets)[at])
            size.append(np.bincount(bucket, minlength=buckets)[at])
        q, b, total, size = (np.concatenate(x) if x else np.empty(0) for x in (q, b, total, size))
        return [_ids(q.astype(np.int64)), pa.array(b.astype(np.int32)), pa.array(total.astype(np.int64)), pa.array(size.astype(np.int64))]

    return run


CURVE = "qid long, rank_bucket int, total long, n long"


def scan(points: DataFrame, queries: DataFrame, plan_dims: list, d: int, m: int, body: Body, schema: str, metric: str = "l2") -> DataFrame:
    """What `body` makes of the scores of all points."""
    return by_query(collected(points, d), queries, d, collisions(plan_dims, m, metric), body, schema)
