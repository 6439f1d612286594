"""Baselines by family, set-wise: each is built once (tables and small arrays) and then searched, and ends in the shared exact
re-rank: qid, rank, id, distance, score.

With full probing (all leaves, beta 1, every cell, beams over whole graphs) each returns the exact neighbours; the two graphs
do so where their graphs are connected. Searches take query sets in blocks, which are broadcast; sets that fit are searched by
`baseline_blocks`, with the same pools, larger ones by the joins here.
"""

from __future__ import annotations

import heapq
import math
import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import VectorSet
from ..plans.subspaces import SubspacePlan, plan_contiguous
from ..session import materialise, share_of, ship, table_bytes
from . import baseline_blocks, blocks
from .candidates import rerank
from .cellindex import IndexParams, assign_codes, build_cell_index
from .clustering import lloyd, matrix, train_sample
from .exact import first_k, in_blocks, paired, reported
from .fronts import gaussian, mapped, principal, with_matrix


@dataclass
class State:
    """What a build leaves: written tables, and small values that a search broadcasts."""

    tables: dict[str, DataFrame]
    small: dict[str, Any] = field(default_factory=dict)

    def __getitem__(self, name: str) -> Any:
        return self.tables[name] if name in self.tables else self.small[name]

    def bytes(self) -> int:
        """Bytes of the files and of the arrays."""
        return sum(map(table_bytes, self.tables.values())) + sum(len(pickle.dumps(x)) for x in self.small.values())


def _pool(data: VectorSet, beta: float, k: int) -> int:
    return min(data.n, max(k, share_of(beta, data.n)) + k)


def _ranked(found: DataFrame, data: VectorSet, k: int) -> DataFrame:
    """found: qid, id (repeats allowed)."""
    return rerank(found.select("qid", "id").distinct().withColumn("score", F.lit(0)), data.points, data.queries, k, data.d, "l2", data.unit)


def _lists(values: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.arange(0, values.size + 1, values.shape[1], dtype=np.int32)), pa.array(np.ascontiguousarray(values).reshape(-1)))


def _grow(near: Callable[[DataFrame], DataFrame], start: DataFrame, target: int, c: float) -> DataFrame:
    """qid, id within a radius of each query that grows by c until `target` points are held. `near` gives the points within the
    radius r of each query (qid, r); only queries that are still short go on."""
    radii, done = start, None
    while True:
        found = materialise(near(radii).select("qid", "id").distinct(), "within")
        held = radii.join(found.groupBy("qid").agg(F.count(F.lit(1)).alias("n")), "qid", "left")
        done = found if done is None else done.unionByName(found)
        radii = materialise(held.where(F.coalesce("n", F.lit(0)) < target).select("qid", (F.col("r") * c).alias("r")), "radii")
        if radii.isEmpty():
            return done


def _first_radius(sample: DataFrame, queries: DataFrame, reach: Column, target: int, n: int) -> DataFrame:
    """qid, r: where a sample says that the pool fills."""
    share = min(1.0, target / max(n, 1))
    return paired(sample, queries).select("qid", reach.alias("reach")).groupBy("qid").agg(F.greatest(F.percentile_approx("reach", share, 1000), F.lit(1e-9)).alias("r"))


#: Points of which first radii are estimated.
RADIUS_SAMPLE = 2_000

# --- 1: trees over quantised projections ------------------------------------------------------------------------------


def build_encoded_trees(data: VectorSet, L: int = 4, K: int = 16, regions: int = 256, leaf_rows: int = 64, seed: int = 0) -> State:
    """L trees of K projections, each quantised into equally filled regions; a point's code is its K region numbers. A leaf is the
    leading bits of the codes, dealt over the coordinates, as many as leave about `leaf_rows` points; its box is the extent of
    its points."""
    spark = data.points.sparkSession
    w = gaussian(data.d, L * K, seed)
    p = materialise(mapped(data.points, "id", "vec", w).withColumnRenamed("vec", "proj"), "projected")
    shares = ", ".join(f"{i / regions!r}D" for i in range(1, regions))  # as text: made one by one for each coordinate, the literals take seconds
    marks = p.select(F.posexplode("proj").alias("j", "x")).groupBy("j").agg(F.expr(f"percentile_approx(x, array({shares}), 10000)").alias("q"))
    edges = np.array([r["q"] for r in sorted(marks.collect())]).reshape(-1, regions - 1)  # a row per coordinate
    bits = max(1, (regions - 1).bit_length())
    depth = max(1, min(62, K * bits, int(np.ceil(np.log2(max(data.n, 1) / leaf_rows))) if data.n > leaf_rows else 1))
    shared = spark.sparkContext.broadcast(edges)

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = shared.value
        for b in batches:
            x = matrix(b.column("proj"), L * K)
            codes = np.stack([np.searchsorted(e[j], x[:, j], side="left") for j in range(L * K)], axis=1).astype(np.int16)
            leaf = np.zeros((len(x), L), dtype=np.int64)
            for t in range(L):
                for at in range(depth):
                    j, bit = at % K, bits - 1 - at // K
                    leaf[:, t] = leaf[:, t] * 2 + (codes[:, t * K + j] >> bit & 1)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("proj"), _lists(codes), _lists(leaf)], ["id", "proj", "codes", "leaf"])

    coded = materialise(p.mapInArrow(code, "id long, proj array<double>, codes array<short>, leaf array<long>"), "coded")
    each = None
    for t in range(L):
        box = coded.groupBy(F.lit(t).alias("tree"), F.col("leaf")[t].alias("leaf")).agg(F.count(F.lit(1)).alias("n"), F.array(*[F.min(F.col("proj")[t * K + j]) for j in range(K)]).alias("lo"), F.array(*[F.max(F.col("proj")[t * K + j]) for j in range(K)]).alias("hi"))
        each = box if each is None else each.unionByName(box)
    return State({"boxes": materialise(each, "boxes"), "codes": materialise(coded.select("id", "codes", "leaf"), "codes")}, {"weights": w, "edges": edges, "K": K})


def search_encoded_trees(state: State, data: VectorSet, k: int, beta: float = 0.1, c: float = 1.5) -> DataFrame:
    """Leaves within a radius around the query, grown by c until the pool is full."""
    K = state["K"]
    points = baseline_blocks.points_of(data)
    leaf = None if points is None else baseline_blocks.lists(state["codes"], points, "leaf", "long")
    if leaf is not None:
        boxes = state["boxes"].toPandas().sort_values(["tree", "leaf"])
        trees = []
        for t, b in boxes.groupby("tree"):
            trees.append((np.stack(b["lo"]), np.stack(b["hi"]), b["n"].to_numpy(), np.searchsorted(b["leaf"].to_numpy(), leaf[:, t]).astype(np.int32)))
        return baseline_blocks.search(data, k, points, (state["weights"], trees), baseline_blocks.rings(_pool(data, beta, k), c))
    q = mapped(data.queries, "qid", "qvec", state["weights"])
    near = state["boxes"].crossJoin(F.broadcast(q))  # a row per leaf, of many points each
    sides = F.zip_with("lo", F.slice("qvec", F.col("tree") * K + 1, F.lit(K)), lambda a, x: F.struct(a.alias("a"), x.alias("x")))
    gap = F.aggregate(F.zip_with(sides, "hi", lambda s, h: F.greatest(s.a - s.x, s.x - h, F.lit(0.0))), F.lit(0.0), lambda s, g: s + g * g)
    bound = near.select("qid", "tree", "leaf", "n", F.sqrt(gap).alias("reach"))
    ring = F.when(F.col("reach") <= 0, F.lit(-(1 << 30))).otherwise(F.ceil(F.log("reach") / F.log(F.lit(c)))).cast("int")
    rings = bound.withColumn("ring", ring)
    held = rings.groupBy("qid", "tree", "ring").agg(F.sum("n").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("qid", "tree").orderBy("ring").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    open_rings = held.withColumn("before", before).where(F.col("before") < _pool(data, beta, k)).select("qid", "tree", "ring")
    taken = rings.join(open_rings, ["qid", "tree", "ring"]).select("qid", "tree", "leaf")
    placed = state["codes"].select("id", F.posexplode("leaf").alias("tree", "leaf"))
    return _ranked(placed.join(taken, ["tree", "leaf"]), data, k)


# --- 2: windows centred at the query ----------------------------------------------------------------------------------


def build_windows(data: VectorSet, L: int = 5, K: int = 12, seed: int = 0) -> State:
    """Each point in L projected spaces, a row per space, in buckets of its first coordinate there."""
    w = gaussian(data.d, L * K, seed)
    p = mapped(data.points, "id", "vec", w)
    spaces = p.select("id", F.posexplode(F.array(*[F.slice("vec", t * K + 1, K) for t in range(L)])).alias("space", "at"))
    spaces = materialise(spaces, "spaces")
    width = spaces.agg((F.stddev_pop(F.col("at")[0]) / 8).alias("s")).first()["s"] or 1.0
    placed = materialise(spaces.withColumn("bucket", F.floor(F.col("at")[0] / width)).repartitionByRange("space", "bucket").sortWithinPartitions("space", "bucket"), "windows")
    span = placed.agg(F.min("bucket").alias("lo"), F.max("bucket").alias("hi")).first()
    return State({"placed": placed}, {"weights": w, "K": K, "L": L, "width": width, "span": (span["lo"], span["hi"])})


def _buckets(middle: Column, radius: Column, width: float, span: tuple[int, int]) -> Column:
    """The buckets that [middle - radius, middle + radius] touches, of those there are."""
    lo, hi = F.greatest(F.floor((middle - radius) / width), F.lit(span[0])), F.least(F.floor((middle + radius) / width), F.lit(span[1]))
    return F.when(lo <= hi, F.sequence(lo, hi)).otherwise(F.expr("cast(array() as array<bigint>)"))


def search_windows(state: State, data: VectorSet, k: int, beta: float = 0.1, c: float = 1.5) -> DataFrame:
    """Cubes around the query in the projected spaces, widened by c until the pool is full: a range join on the first coordinate's
    buckets, then the other coordinates. A point is found when any space's cube holds it."""
    K, L, w = state["K"], state["L"], state["weights"]
    q = mapped(data.queries, "qid", "qvec", w)
    target = _pool(data, beta, k)

    def reach(t: int) -> Column:
        return F.greatest(*[F.abs(F.col("vec")[t * K + j] - F.col("qvec")[t * K + j]) for j in range(K)])

    sample = mapped(train_sample(data.points, RADIUS_SAMPLE), "id", "vec", w)
    start = materialise(_first_radius(sample, q, F.least(*[reach(t) for t in range(L)]), target, data.n), "radii")
    if (points := baseline_blocks.points_of(data)) is not None:
        return baseline_blocks.search(data, k, points, w, baseline_blocks.windows(target, c, L, K), start)

    def near(radii: DataFrame) -> DataFrame:
        asked = q.join(radii, "qid").select("qid", "r", F.posexplode(F.array(*[F.slice("qvec", t * K + 1, K) for t in range(L)])).alias("space", "q_at"))
        asked = asked.withColumn("bucket", F.explode(_buckets(F.col("q_at")[0], F.col("r"), state["width"], state["span"])))
        inside = F.forall(F.zip_with("at", "q_at", lambda a, b: F.abs(a - b)), lambda x: x <= F.col("r"))
        return state["placed"].join(F.broadcast(asked), ["space", "bucket"]).where(inside)

    return _ranked(_grow(near, start, target, c), data, k)


# --- 3: ball in one projected space with pivots -----------------------------------------------------------------------


def _distance(a: str, b: Column | str) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def build_ball(data: VectorSet, m: int = 15, s: int = 5, seed: int = 0) -> State:
    """Points in one projected space with their distances to s pivots, in buckets of the first of these."""
    w = gaussian(data.d, m, seed)
    p = materialise(mapped(data.points, "id", "vec", w), "projected")
    pivots = [list(map(float, r["vec"])) for r in p.orderBy(F.xxhash64("id"), "id").limit(s).collect()]  # s points
    far = materialise(p.withColumn("far", _to_pivots("vec", pivots)), "far")
    width = far.agg((F.stddev_pop(F.col("far")[0]) / 8).alias("s")).first()["s"] or 1.0
    placed = materialise(far.withColumn("bucket", F.floor(F.col("far")[0] / width)).repartitionByRange("bucket").sortWithinPartitions("bucket"), "ball")
    span = placed.agg(F.min("bucket").alias("lo"), F.max("bucket").alias("hi")).first()
    return State({"placed": placed}, {"weights": w, "pivots": pivots, "width": width, "span": (span["lo"], span["hi"])})


def _to_pivots(column: str, pivots: list[list[float]]) -> Column:
    return F.array(*[_distance(column, F.array(*map(F.lit, v))) for v in pivots])


def search_ball(state: State, data: VectorSet, k: int, beta: float = 0.1, c: float = 1.5) -> DataFrame:
    """Balls of growing radius: a range join on the distance to the first pivot, the other pivots rule points out, and only what is
    left has its projected distance computed."""
    w, target = state["weights"], _pool(data, beta, k)
    q = mapped(data.queries, "qid", "qvec", w)
    q = q.withColumn("q_far", _to_pivots("qvec", state["pivots"]))
    sample = mapped(train_sample(data.points, RADIUS_SAMPLE), "id", "vec", w)
    start = materialise(_first_radius(sample, q, _distance("vec", "qvec"), target, data.n), "radii")
    if (points := baseline_blocks.points_of(data)) is not None:
        return baseline_blocks.search(data, k, points, w, baseline_blocks.ball(target, c), start)

    def near(radii: DataFrame) -> DataFrame:
        asked = q.join(radii, "qid").withColumn("bucket", F.explode(_buckets(F.col("q_far")[0], F.col("r"), state["width"], state["span"])))
        some = state["placed"].join(F.broadcast(asked), "bucket")
        allowed = F.forall(F.zip_with("far", "q_far", lambda a, b: F.abs(a - b)), lambda x: x <= F.col("r"))
        return some.where(allowed).where(_distance("vec", "qvec") <= F.col("r"))

    return _ranked(_grow(near, start, target, c), data, k)


# --- 4: longest circular run of equal hashes --------------------------------------------------------------------------


def build_circular(data: VectorSet, m: int = 64, run: int = 3, width: float | None = None, seed: int = 0) -> State:
    """m hashes of each point as a circular string, and the strings' postings: (place, `run` hashes in a row) -> points."""
    if m > 64:
        raise ValueError("at most 64 hashes: places are kept as bits of one number")
    rng = np.random.default_rng(seed)
    a, shift = rng.standard_normal((data.d, m)), rng.random(m)
    if width is None:
        p = mapped(train_sample(data.points, RADIUS_SAMPLE), "id", "vec", a)
        width = float(p.select(F.explode("vec").alias("x")).agg(F.stddev_pop("x").alias("s")).first()["s"] or 1.0)
    strings = materialise(_strings(data.points, "id", "vec", a, shift, width), "strings")
    return State({"strings": strings, "postings": materialise(_posted(strings, "id", m, run).repartitionByRange("place", "name").sortWithinPartitions("place", "name"), "postings")}, {"a": a, "shift": shift, "width": width, "run": run})


def _strings(df: DataFrame, id_col: str, vec_col: str, a: np.ndarray, shift: np.ndarray, width: float) -> DataFrame:
    p = mapped(df, id_col, vec_col, a / width, None)
    return p.select(id_col, F.zip_with(vec_col, F.array(*map(F.lit, shift.tolist())), lambda x, s: F.floor(x + s).cast("int")).alias("string"))


def _posted(strings: DataFrame, id_col: str, m: int, run: int) -> DataFrame:
    """place, name, id: every `run` hashes in a row, around the end."""
    around = F.concat(F.col("string"), F.slice("string", 1, run - 1)) if run > 1 else F.col("string")
    s = strings.select(id_col, around.alias("s"))
    names = F.array(*[F.xxhash64(*[F.col("s")[j + i] for i in range(run)]) for j in range(m)])
    return s.select(id_col, F.posexplode(names).alias("place", "name"))


def _longest(mask: Column, m: int) -> Column:
    """The longest run of set bits on a circle of m places: how often a mask may be met with itself, turned by one, until nothing
    is left."""
    full = -1 if m == 64 else (1 << m) - 1

    def turn(x: Column) -> Column:
        return F.shiftleft(x, 1).bitwiseOR(F.shiftrightunsigned(x, m - 1)).bitwiseAND(F.lit(full).cast("long"))

    start = F.struct(mask.alias("x"), F.lit(0).alias("length"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(m)), start, lambda acc, _: F.when(acc.x == 0, acc).otherwise(F.struct(acc.x.bitwiseAND(turn(acc.x)).alias("x"), (acc["length"] + 1).alias("length"))), lambda acc: acc["length"])


def search_circular(state: State, data: VectorSet, k: int, check_k: int = 256) -> DataFrame:
    """The check_k points with the longest run of places equal to the query's. Points that share a posting come first; queries with
    fewer such points than check_k compare whole strings."""
    run, m = state["run"], state["a"].shape[1]
    points = baseline_blocks.points_of(data)
    strings = None if points is None else baseline_blocks.lists(state["strings"], points, "string")
    if strings is not None:
        arrays = (state["a"] / state["width"], state["shift"], np.ascontiguousarray(strings.T))
        return baseline_blocks.search(data, k, points, arrays, baseline_blocks.circular(check_k))
    q = materialise(_strings(data.queries, "qid", "qvec", state["a"], state["shift"], state["width"]), "strings")
    asked = _posted(q, "qid", m, run)
    bit = F.expr("shiftleft(1L, place)")
    met = state["postings"].join(F.broadcast(asked), ["place", "name"]).groupBy("qid", "id").agg(F.bit_or(bit).alias("mask"))
    met = materialise(met.select("qid", "id", F.least(_longest(F.col("mask"), m) + (run - 1), F.lit(m)).alias("run")), "met")
    few = q.join(met.groupBy("qid").agg(F.count(F.lit(1)).alias("n")), "qid", "left").where(F.coalesce("n", F.lit(0)) < check_k).select("qid", F.col("string").alias("q_string"))
    same = F.zip_with(F.zip_with("string", "q_string", lambda x, y: (x == y).cast("long")), F.sequence(F.lit(0), F.lit(m - 1)), lambda x, j: F.call_function("shiftleft", x, j))
    whole = state["strings"].crossJoin(F.broadcast(few)).select("qid", "id", _longest(F.aggregate(same, F.lit(0).cast("long"), lambda t, x: t.bitwiseOR(x)), m).alias("run"))
    both = met.join(F.broadcast(few.select("qid")), "qid", "left_anti").unionByName(whole)
    w = Window.partitionBy("qid").orderBy(F.col("run").desc(), "id")
    return _ranked(both.withColumn("r", F.row_number().over(w)).where(F.col("r") <= check_k), data, k)


# --- 5: rotated product quantiser -------------------------------------------------------------------------------------


def build_rotated_pq(data: VectorSet, cells: int = 16, codewords: int = 16, books: int = 8, iterations: int = 5, seed: int = 0) -> State:
    """Rotation to principal axes dealt evenly to the halves, coarse cells of two halves' clusters, and codes of what the cells
    leave over; rows sorted by cell."""
    mean, w = principal(data.points, data.d, data.d)
    w = w[:, [j for r in range(2) for j in range(r, data.d, 2)]]  # strong and weak axes in both halves
    turned = with_matrix(data, w, mean)
    whole = SubspacePlan(data.d, (tuple(range(data.d)),))
    index = build_cell_index(turned.points, whole, IndexParams(sqrt_k=cells, iterations=iterations, seed=seed))
    spot = data.points.sparkSession.sparkContext.broadcast(index.centroids)
    d = data.d

    def rest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = spot.value
        for b in batches:
            cell = b.column("cells").flatten().to_numpy()
            x = matrix(b.column("vec"), d) - np.hstack([c[0][cell // len(c[1])], c[1][cell % len(c[1])]])
            yield pa.RecordBatch.from_arrays([b.column("id"), _lists(x)], ["id", "vec"])

    residual = materialise(turned.points.join(index.codes, "id").select("id", "vec", "cells").mapInArrow(rest, "id long, vec array<double>"), "residual")
    parts = list(plan_contiguous(d, books).dims)
    words, _ = lloyd(residual, parts, codewords, d, iterations, seed)
    codes = assign_codes(residual, words, parts, d, per_sub=1).withColumnRenamed("cells", "codes")
    placed = index.codes.select("id", F.col("cells")[0].alias("cell")).join(codes, "id")
    placed = materialise(placed.repartitionByRange("cell").sortWithinPartitions("cell"), "quantised")
    sizes = {r["cell"]: r["n"] for r in placed.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row per cell
    return State({"placed": placed}, {"mean": mean, "rotation": w, "coarse": index.centroids, "words": words, "sizes": sizes})


def search_rotated_pq(state: State, data: VectorSet, k: int, beta: float = 0.1, gamma: float = 0.5) -> DataFrame:
    """Cells in ascending distance until they hold the share gamma (or the pool) of the points; distances to decoded vectors rank
    what they hold, and the best go to the exact re-rank."""
    spark = data.points.sparkSession
    ship(spark)
    c, words, sizes = state["coarse"], state["words"], state["sizes"]
    points = baseline_blocks.points_of(data)
    codes = None if points is None else baseline_blocks.lists(state["placed"], points, "codes")
    if codes is not None:
        cell = baseline_blocks.lists(state["placed"], points, "cell")[:, 0]
        target = max(_pool(data, beta, k), share_of(gamma, data.n))
        return baseline_blocks.search(data, k, points, (state["mean"], state["rotation"], c, words, cell, baseline_blocks.keys(cell, codes, words)), baseline_blocks.quantised(target, _pool(data, beta, k)))
    qs = mapped(data.queries, "qid", "qvec", state["rotation"], state["mean"]).collect()  # a block of queries
    half, target = c[0].shape[1], max(_pool(data, beta, k), share_of(gamma, data.n))
    rows, q_of = [], {}
    for r in qs:
        q = q_of[r["qid"]] = np.array(r["qvec"], dtype=np.float64)
        far = (((q[:half] - c[0]) ** 2).sum(axis=1)[:, None] + ((q[half:] - c[1]) ** 2).sum(axis=1)[None]).reshape(-1)
        held = 0
        for cell in np.argsort(far, kind="stable").tolist():
            if held >= target:
                break
            if cell in sizes:
                rows.append((r["qid"], cell))
                held += sizes[cell]
    taken = spark.createDataFrame(rows, "qid long, cell int")
    shared = spark.sparkContext.broadcast((q_of, c, words))

    def estimate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, c, wd = shared.value
        for b in batches:
            if not b.num_rows:
                continue
            cell = b.column("cell").to_numpy()
            code = b.column("codes").flatten().to_numpy().reshape(-1, len(wd))
            x = np.hstack([c[0][cell // len(c[1])], c[1][cell % len(c[1])]]) + np.hstack([wd[s][code[:, s]] for s in range(len(wd))])
            asked = np.stack([q[i] for i in b.column("qid").to_pylist()])
            yield pa.RecordBatch.from_arrays([b.column("qid"), b.column("id"), pa.array(((x - asked) ** 2).sum(axis=1))], ["qid", "id", "estimate"])

    scored = state["placed"].join(F.broadcast(taken), "cell").select("qid", "id", "cell", "codes").mapInArrow(estimate, "qid long, id long, estimate double")
    w = Window.partitionBy("qid").orderBy("estimate", "id")
    return _ranked(scored.withColumn("r", F.row_number().over(w)).where(F.col("r") <= _pool(data, beta, k)), data, k)


# --- 6: forest of two-point splits ------------------------------------------------------------------------------------


def _split(x: np.ndarray, rows: np.ndarray, rng: np.random.Generator, balanced: bool) -> tuple[np.ndarray, float] | None:
    """A hyperplane between two of the rows; balanced: through the middle row along the line of two cluster centres."""
    a, b = x[rng.choice(rows, 2, replace=False)]
    if balanced:
        for _ in range(4):
            side = ((x[rows] - a) ** 2).sum(axis=1) < ((x[rows] - b) ** 2).sum(axis=1)
            if 0 < side.sum() < len(rows):
                a, b = x[rows[side]].mean(axis=0), x[rows[~side]].mean(axis=0)
        normal = a - b
        return normal, float(np.median(x[rows] @ normal))
    return a - b, float((a - b) @ (a + b) / 2)


def _grown(x: np.ndarray, small: int, rng: np.random.Generator, balanced: bool = False) -> list[tuple]:
    """Nodes of a tree over the rows of x: (normal, offset, left, right), or (None, leaf number, -1, -1)."""
    nodes: list = []

    def grow(rows: np.ndarray) -> int:
        at = len(nodes)
        nodes.append((None, at, -1, -1))
        if len(rows) > small:
            normal, offset = _split(x, rows, rng, balanced)
            side = x[rows] @ normal > offset
            if 0 < side.sum() < len(rows):
                nodes[at] = (normal, offset, grow(rows[~side]), grow(rows[side]))
        return at

    grow(np.arange(len(x)))
    return nodes


def _routed(v: np.ndarray, nodes: list[tuple], both: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """The leaf of each row, and (with `both`) the leaf that it reaches by taking the other side where its margin is least."""
    first, second = np.zeros(len(v), dtype=np.int32), np.zeros(len(v), dtype=np.int32)
    least, turn = np.full(len(v), np.inf), np.full(len(v), -1)
    for out, flip in ((first, None), (second, turn))[: 1 + both]:
        todo = [(0, np.arange(len(v)))]
        while todo:
            at, rows = todo.pop()
            normal, offset, left, right = nodes[at]
            if normal is None:
                out[rows] = at
            elif len(rows):
                margin = (v[rows] @ normal - offset) / (math.sqrt(normal @ normal) or 1.0)
                side = margin > 0
                if not both:
                    pass
                elif flip is None:
                    closer = np.abs(margin) < least[rows]
                    least[rows[closer]], turn[rows[closer]] = np.abs(margin)[closer], at
                else:
                    side = np.where(flip[rows] == at, ~side, side)
                todo += [(left, rows[~side]), (right, rows[side])]
    return first, second


def _placed(data: VectorSet, trees: list[list[tuple]], second: bool) -> DataFrame:
    """id, vec, leaf: the leaf of each tree, or with `second` the two leaves of the one tree. One map."""
    spark = data.points.sparkSession
    ship(spark)
    shared, d = spark.sparkContext.broadcast(trees), data.d

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = matrix(b.column("vec"), d)
            leaves = [_routed(v, nodes, second) for nodes in shared.value]
            out = np.stack(list(leaves[0]) if second else [x[0] for x in leaves], axis=1)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("vec"), _lists(out)], ["id", "vec", "leaf"])

    return data.points.select("id", "vec").mapInArrow(route, "id long, vec array<double>, leaf array<int>")


def _sizes(leaves: DataFrame) -> dict[tuple[int, int], int]:
    got = leaves.select(F.posexplode("leaf").alias("tree", "leaf")).groupBy("tree", "leaf").agg(F.count(F.lit(1)).alias("n")).collect()  # leaves of trees grown on the sample
    return {(r["tree"], r["leaf"]): r["n"] for r in got}


def _best_leaves(trees: list[list[tuple]], sizes: dict, q: np.ndarray, enough: Callable[[int, int], bool]) -> Iterator[tuple[int, int]]:
    """(tree, leaf) by margin across all trees, the most promising first, until `enough` (leaves, points held)."""
    queue = [(-np.inf, t, 0) for t in range(len(trees))]
    heapq.heapify(queue)
    leaves = held = 0
    while queue and not enough(leaves, held):
        margin, t, at = heapq.heappop(queue)
        normal, offset, left, right = trees[t][at]
        if normal is None:
            leaves, held = leaves + 1, held + sizes.get((t, at), 0)
            yield t, at
            continue
        side = float(q @ normal - offset) / (math.sqrt(normal @ normal) or 1.0)
        near, far = (right, left) if side > 0 else (left, right)
        heapq.heappush(queue, (margin, t, near))
        heapq.heappush(queue, (max(margin, abs(side)), t, far))


def _leaves_of_queries(state: State, data: VectorSet, enough: Callable[[int, int], bool]) -> DataFrame:
    rows = [(r["qid"], t, at) for r in data.queries.collect() for t, at in _best_leaves(state["trees"], state["sizes"], np.array(r["qvec"]), enough)]  # a block of queries
    return data.points.sparkSession.createDataFrame(rows, "qid long, tree int, leaf int")


def _sampled(data: VectorSet, sample: int, seed: int) -> np.ndarray:
    return np.array([r["vec"] for r in train_sample(data.points, sample, seed).orderBy("id").collect()], dtype=np.float64).reshape(-1, data.d)  # `sample` rows


def build_forest(data: VectorSet, trees: int = 30, leaf_size: int = 32, sample: int = 10_000, seed: int = 0) -> State:
    """Trees are grown on a bounded sample, split by hyperplanes between two of its points; one map then routes all points."""
    x = _sampled(data, sample, seed)
    small = max(2, int(leaf_size * min(1.0, len(x) / max(data.n, 1))))
    rng = np.random.default_rng(seed)
    grown = [_grown(x, small, rng) for _ in range(trees)]
    leaves = materialise(_placed(data, grown, False).select("id", "leaf"), "forest")
    return State({"leaves": leaves}, {"trees": grown, "sizes": _sizes(leaves)})


def search_forest(state: State, data: VectorSet, k: int, search_k: int = 1000) -> DataFrame:
    """Leaves by margin across all trees, the most promising first, until they hold search_k points."""
    points = baseline_blocks.points_of(data)
    leaf = None if points is None else baseline_blocks.lists(state["leaves"], points, "leaf")
    if leaf is not None:
        own = [baseline_blocks.members(x) for x in leaf.T]
        return baseline_blocks.search(data, k, points, (state["trees"], state["sizes"], own), None, pick=baseline_blocks.forest(lambda trees, sizes, q: _best_leaves(trees, sizes, q, lambda leaves, held: held >= search_k)))
    wanted = _leaves_of_queries(state, data, lambda leaves, held: held >= search_k)
    placed = state["leaves"].select("id", F.posexplode("leaf").alias("tree", "leaf"))
    return _ranked(placed.join(F.broadcast(wanted), ["tree", "leaf"]), data, k)


# --- 7: layered proximity graphs, one per partition -------------------------------------------------------------------


class LayeredGraph:
    """A layered proximity graph over the rows of one partition."""

    def __init__(self, x: np.ndarray, links: int, ef: int, seed: int = 0):
        self.x, self.links, self.ef = x, links, ef
        table = self.table(x)
        rng = np.random.default_rng(seed)
        level = np.minimum((-np.log(rng.random(len(x))) / np.log(max(links, 2))).astype(int), 8)
        self.layers: list[dict[int, list[int]]] = []
        self.entry = -1
        for i in range(len(x)):
            self._insert(i, int(level[i]), table)

    def table(self, q: np.ndarray) -> np.ndarray:
        """Squared distances of some queries (rows) to the partition's few rows, formed together; walks look them up."""
        product, kind = blocks._exact(max(blocks._top(self.x), blocks._top(q)), max(self.x.shape[1], 1), "l2")
        return blocks.distances(q, np.ascontiguousarray(self.x.T), "l2", product, kind)

    def beam(self, far: list[float], starts: list[int], ef: int, layer: int) -> list[tuple[float, int]]:
        """The ef nearest met from `starts` on; far: the query's distances."""
        seen = set(starts)
        front = [(far[i], i) for i in starts]
        heapq.heapify(front)
        best = [(-a, i) for a, i in front]
        heapq.heapify(best)
        while len(best) > ef:
            heapq.heappop(best)
        while front:
            a, i = heapq.heappop(front)
            if a > -best[0][0] and len(best) >= ef:
                break
            for j in self.layers[layer].get(i, ()):
                if j in seen:
                    continue
                seen.add(j)
                b = far[j]
                if len(best) < ef or b < -best[0][0]:
                    heapq.heappush(front, (b, j))
                    heapq.heappush(best, (-b, j))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted((-a, i) for a, i in best)

    def _insert(self, i: int, level: int, table: np.ndarray) -> None:
        top = len(self.layers) - 1
        if self.entry >= 0:
            at, far = [self.entry], table[i].tolist()
            for layer in range(top, level, -1):
                at = [self.beam(far, at, 1, layer)[0][1]]
            for layer in range(min(level, top), -1, -1):
                found = self.beam(far, at, self.ef, layer)
                graph = self.layers[layer]
                graph[i] = [j for _, j in found[: self.links]]
                for j in graph[i]:
                    graph[j].append(i)
                    if len(graph[j]) > 2 * self.links:
                        d = table[j, graph[j]]
                        graph[j] = [graph[j][t] for t in np.argsort(d, kind="stable")[: 2 * self.links]]
                at = [j for _, j in found]
        while len(self.layers) <= level:
            self.layers.append({i: []})
            self.entry = i

    def search(self, far: list[float], k: int, ef: int) -> list[tuple[float, int]]:
        """(distance, row) of the k nearest found; far: the query's row of `table`."""
        at = [self.entry]
        for layer in range(len(self.layers) - 1, 0, -1):
            at = [self.beam(far, at, 1, layer)[0][1]]
        return self.beam(far, at, max(ef, k), 0)[:k]


def build_layered_graph(data: VectorSet, links: int = 25, ef_build: int = 200, rows: int = 1_000, seed: int = 0) -> State:
    """A graph for every `rows` points, written as one value each, so as many graphs as the points need and each bounded."""
    ship(data.points.sparkSession)
    parts = max(1, -(-data.n // rows))

    def build(pdf):
        import pandas as pd

        pdf = pdf.sort_values("id")
        g = LayeredGraph(np.stack(pdf["vec"].to_numpy()).astype(np.float64), links, ef_build, seed)
        return pd.DataFrame({"part": [int(pdf["part"].iloc[0])], "graph": [pickle.dumps((pdf["id"].to_numpy(), g))]})

    dealt = data.points.select("id", "vec", F.pmod(F.xxhash64("id"), F.lit(parts)).alias("part"))
    return State({"graphs": materialise(dealt.groupBy("part").applyInPandas(build, "part long, graph binary"), "graphs")}, {"parts": parts})


def search_layered_graph(state: State, data: VectorSet, k: int, ef: int = 300) -> DataFrame:
    """Every query visits every graph, and the best are merged by the re-rank. This fans out where a single graph would not, which is
    the price of building without a global lock."""
    spark = data.points.sparkSession
    ship(spark)
    qs = data.queries.orderBy("qid").collect()  # a block of queries
    shared = spark.sparkContext.broadcast((np.array([r["qid"] for r in qs]), np.array([r["qvec"] for r in qs], dtype=np.float64)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q = shared.value
        for b in batches:
            for x in b.column("graph"):
                ids, g = pickle.loads(x.as_py())
                for lo in range(0, len(qid), 1024):
                    rows = [(int(qid[lo + i]), int(ids[j]), a) for i, far in enumerate(g.table(q[lo : lo + 1024])) for a, j in g.search(far.tolist(), k, ef)]
                    yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.float64() if i == 2 else pa.int64()) for i in range(3)], ["qid", "id", "dist"])

    found = state["graphs"].select("graph").repartition(min(state["parts"], 10_000)).mapInArrow(run, "qid long, id long, dist double")
    return reported(first_k(found, k).withColumn("rank", F.col("rank").cast("int")).withColumn("score", F.lit(0)), "l2", data.unit)


# --- 8: balanced tree that seeds a neighbourhood graph ----------------------------------------------------------------


def build_tree_graph(data: VectorSet, leaf_rows: int = 128, links: int = 10, sample: int = 10_000, seed: int = 0) -> State:
    """A tree split recursively in halves of equal size (on a bounded sample) down to leaves of about `leaf_rows` points, so leaves
    grow in number, not in size. Each leaf holds an exact neighbour graph; a point is also put in the leaf beyond its nearest
    border, which links neighbouring leaves."""
    x = _sampled(data, sample, seed)
    small = max(2, int(leaf_rows * min(1.0, len(x) / max(data.n, 1))))
    tree = _grown(x, small, np.random.default_rng(seed), balanced=True)
    placed = materialise(_placed(data, [tree], True), "placed")

    def edges(pdf):
        import pandas as pd

        y, ids = np.stack(pdf["vec"].to_numpy()).astype(np.float64), pdf["id"].to_numpy()
        square = (y * y).sum(axis=1)
        rows = []
        for lo in range(0, len(y), 512):
            far = square[lo : lo + 512, None] - 2 * (y[lo : lo + 512] @ y.T) + square[None]
            near = np.argsort(far, axis=1, kind="stable")[:, : links + 1]
            rows += [(int(ids[lo + i]), int(ids[j])) for i in range(len(near)) for j in near[i] if j != lo + i]
        return pd.DataFrame(rows, columns=["src", "dst"])

    dealt = placed.select("id", "vec", F.explode(F.array_distinct("leaf")).alias("leaf"))
    graph = materialise(dealt.groupBy("leaf").applyInPandas(edges, "src long, dst long").distinct(), "edges")
    leaves = materialise(placed.select("id", F.slice("leaf", 1, 1).alias("leaf")), "leaves")
    return State({"leaves": leaves, "edges": graph}, {"trees": [tree], "sizes": _sizes(leaves)})


def search_tree_graph(state: State, data: VectorSet, k: int, probes: int = 2, hops: int = 3, beam: int = 64) -> DataFrame:
    """A query starts in its most promising leaves and follows edges for a bounded number of hops. Each hop is a join on edges, cut by
    a beam per query."""
    points = baseline_blocks.points_of(data)
    leaf = None if points is None else baseline_blocks.lists(state["leaves"], points, "leaf")
    if leaf is not None:
        e = state["edges"].toArrow()
        src, to = (np.searchsorted(points.ids, e.column(x).to_numpy()).astype(np.int32) for x in ("src", "dst"))
        edges = np.searchsorted(np.sort(src), np.arange(len(points.ids) + 1)), to[np.argsort(src, kind="stable")]
        arrays = (state["trees"], state["sizes"], [baseline_blocks.members(leaf[:, 0])], edges)
        return baseline_blocks.search(data, k, points, arrays, None, pick=baseline_blocks.hopped(lambda trees, sizes, q: _best_leaves(trees, sizes, q, lambda leaves, held: leaves >= probes), hops, beam))
    wanted = _leaves_of_queries(state, data, lambda leaves, held: leaves >= probes).select("qid", "leaf")
    first = state["leaves"].select("id", F.col("leaf")[0].alias("leaf")).join(F.broadcast(wanted), "leaf").select("qid", "id")

    def closest(found: DataFrame) -> DataFrame:
        full = found.distinct().join(data.points, "id").join(F.broadcast(data.queries), "qid")
        dist = F.aggregate(F.zip_with("vec", "qvec", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, t: s + t)
        w = Window.partitionBy("qid").orderBy("dist", "id")
        return full.select("qid", "id", dist.alias("dist")).withColumn("r", F.row_number().over(w)).where(F.col("r") <= beam).select("qid", "id")

    front = materialise(closest(first), "front")
    for _ in range(hops):
        step = front.join(state["edges"], F.col("id") == F.col("src")).select("qid", F.col("dst").alias("id"))
        front = materialise(closest(front.unionByName(step)), "front")
    return _ranked(front, data, k)


# --- all by name ------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Method:
    """A baseline: build(data, **parameters), then search(state, data, k, **parameters) for any query set."""

    build: Callable[..., State]
    find: Callable[..., DataFrame]
    guaranteed: bool
    parallel: bool  # whether the published measurements ran it on many threads; here all are

    def search(self, state: State, data: VectorSet, k: int, **probe) -> DataFrame:
        return in_blocks(data, lambda b: self.find(state, b, k, **probe))

    def __call__(self, data: VectorSet, k: int, **parameters) -> DataFrame:
        """Build and search in one go; parameters are sorted out by name."""
        names = self.build.__code__.co_varnames[: self.build.__code__.co_argcount]
        return self.search(self.build(data, **{x: v for x, v in parameters.items() if x in names}), data, k, **{x: v for x, v in parameters.items() if x not in names})


GUARANTEED = {
    "encoded_projection_trees": Method(build_encoded_trees, search_encoded_trees, True, False),
    "query_centred_windows": Method(build_windows, search_windows, True, False),
    "projected_metric_ball": Method(build_ball, search_ball, True, False),
    "circular_match": Method(build_circular, search_circular, True, False),
}
UNGUARANTEED = {
    "rotated_product_quantiser": Method(build_rotated_pq, search_rotated_pq, False, True),
    "projection_forest": Method(build_forest, search_forest, False, True),
    "layered_graph": Method(build_layered_graph, search_layered_graph, False, True),
    "tree_graph_hybrid": Method(build_tree_graph, search_tree_graph, False, True),
}
