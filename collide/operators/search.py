"""Search with the cell index."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..costmodel import choose_layout
from ..functions.vectors import VectorSet
from ..session import ship
from . import blocks
from .candidates import rerank, top_scored
from .cellindex import CellIndex
from .exact import blocks_of, in_blocks, reported
from .scan import SearchParams
from .walks import flat_walk, list_walk, prefix_walk


def centroid_distances(index: CellIndex, queries: DataFrame, half_distance: str = "squared") -> DataFrame:
    """qid, sub, half, ranked: distances of each query's part to the part's centroids, sorted by (distance, cluster)."""
    per, metric = index.params.parts, index.params.metric
    rows = [(h // per, h % per, list(map(int, dims)), [[float(v) for v in c] for c in index.centroids[h]]) for h, dims in enumerate(index.parts())]
    table = queries.sparkSession.createDataFrame(rows, "sub int, half int, dims array<int>, centroids array<array<double>>")
    both = queries.crossJoin(F.broadcast(table))  # a row per part: all centroids once, clusters x dimensions numbers
    both = both.select("qid", "sub", "half", "centroids", F.transform("dims", lambda i: F.get("qvec", i)).alias("part"))
    dist = F.transform("centroids", lambda c, i: F.struct(_half(F.col("part"), c, metric, half_distance).alias("dist"), i.cast("int").alias("cid")))
    return both.select("qid", "sub", "half", F.array_sort(dist).alias("ranked"))


def _half(q, c, metric: str, half_distance: str):
    each = F.zip_with(q, c, (lambda u, v: F.abs(u - v)) if metric == "l1" else (lambda u, v: (u - v) * (u - v)))
    total = F.aggregate(each, F.lit(0.0), lambda s, t: s + t)
    return F.sqrt(total) if metric == "l2" and half_distance == "plain" else total


def activated_cells(index: CellIndex, queries: DataFrame, target: int, walk: str = "prefix", half_distance: str = "squared") -> DataFrame:
    """qid, sub, cell (and c1, c2, pop_order where there are two parts)."""
    lists = centroid_distances(index, queries, half_distance)
    sizes = index.cell_sizes()
    k = len(index.centroids[0])
    if index.params.parts == 1:
        return flat_walk(lists, sizes, target)
    if index.params.parts != 2:
        return _many_parts(index, lists, sizes, target)
    cells = prefix_walk(lists, sizes, target, k) if walk == "prefix" else list_walk(lists, sizes, target, k, walk)
    return cells.withColumn("cell", F.col("c1") * k + F.col("c2"))


def _many_parts(index: CellIndex, lists: DataFrame, sizes: DataFrame, target: int) -> DataFrame:
    """More than two parts: all combinations, which stay few because each part has fewer clusters."""
    from pyspark.sql import Window

    k = len(index.centroids[0])
    cells = None
    for p in range(index.params.parts):
        one = lists.where(F.col("half") == p).select("qid", "sub", F.posexplode("ranked").alias(f"p{p}", "r")).select("qid", "sub", f"p{p}", F.col("r.dist").alias("d"), F.col("r.cid").alias("c"))
        if cells is None:
            cells = one.select("qid", "sub", "p0", F.col("d").alias("total"), F.col("c").alias("cell"))
        else:
            cells = cells.join(one, ["qid", "sub"]).withColumn("total", F.col("total") + F.col("d")).withColumn("cell", F.col("cell") * k + F.col("c")).drop("d", "c")
    w = Window.partitionBy("qid", "sub").orderBy("total", *[f"p{p}" for p in range(index.params.parts)])
    run = cells.join(F.broadcast(sizes), ["sub", "cell"], "left").withColumn("n_points", F.coalesce("n_points", F.lit(0)))
    run = run.withColumn("before", F.coalesce(F.sum("n_points").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return run.where(F.col("before") < target).select("qid", "sub", F.col("cell").cast("int").alias("cell"))


#: Activated cells that are written into the filter of a scan; more are left to the join.
LISTED_CELLS = 2_000


def count_hits_postings(postings: DataFrame, cells: DataFrame) -> DataFrame:
    """qid, id, score >= 1 from the inverted form: of stored postings only row groups with activated cells are read, and their hits
    are shuffled."""
    wanted = cells.groupBy("sub").agg(F.collect_set("cell").alias("cells")).collect()  # subspaces x cells at most
    if sum(len(r["cells"]) for r in wanted) <= LISTED_CELLS:
        some = F.lit(False)
        for r in wanted:
            some = some | ((F.col("sub") == r["sub"]) & F.col("cell").isin(*r["cells"]))
        postings = postings.where(some)
    hits = postings.join(F.broadcast(cells.select("qid", "sub", "cell")), ["sub", "cell"])
    return hits.groupBy("qid", "id").agg(F.count(F.lit(1)).cast("int").alias("score"))


def score_codes(codes: DataFrame, cells: DataFrame, n_sub: int) -> DataFrame:
    """qid, id, score of every point from the forward form: one scan, no hit is shuffled. JVM only."""
    per_sub = cells.groupBy("qid", "sub").agg(F.collect_list("cell").alias("cells"))
    sets = per_sub.groupBy("qid").agg(F.map_from_entries(F.collect_list(F.struct("sub", "cells"))).alias("active"))
    score = F.lit(0)
    for s in range(n_sub):
        score = score + F.coalesce(F.array_contains(F.element_at("active", F.lit(s)), F.col("cells")[s]), F.lit(False)).cast("int")
    return codes.crossJoin(F.broadcast(sets)).select("qid", "id", score.alias("score"))


def score_codes_arrow(codes: DataFrame, cells: DataFrame, n_sub: int, n_cells: int) -> DataFrame:
    """The same for many queries: per subspace a 0/1 table (cells x queries); a point's scores for all queries are n_sub row sums.

    The tables are queries x subspaces x cells bytes; query sets are walked in blocks that keep this bounded."""
    spark = codes.sparkSession
    ship(spark)
    rows = cells.select("qid", "sub", "cell").collect()  # a block of queries; at most queries x subspaces x cells
    qids = sorted({r["qid"] for r in rows})
    at = {q: i for i, q in enumerate(qids)}
    tables = np.zeros((n_sub, n_cells, len(qids)), dtype=np.uint8)
    for r in rows:
        tables[r["sub"], r["cell"], at[r["qid"]]] = 1
    shared = spark.sparkContext.broadcast((np.array(qids, dtype=np.int64), tables))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, t = shared.value
        for b in batches:
            ids = b.column("id").to_numpy()
            c = b.column("cells").flatten().to_numpy(zero_copy_only=False).reshape(-1, n_sub)
            for lo in range(0, len(ids), 4096):
                part = c[lo : lo + 4096]
                score = t[0][part[:, 0]].copy()
                for s in range(1, n_sub):
                    score += t[s][part[:, s]]
                i, j = np.divmod(np.arange(score.size), len(q))
                yield pa.RecordBatch.from_arrays([pa.array(q[j]), pa.array(ids[lo : lo + 4096][i]), pa.array(score.reshape(-1).astype(np.int32))], ["qid", "id", "score"])

    return codes.select("id", "cells").mapInArrow(run, "qid long, id long, score int")


def indexed_search(index: CellIndex, data: VectorSet, params: SearchParams, walk: str = "prefix", layout: str = "auto") -> DataFrame:
    """qid, rank, id, distance, score. layout: blocks (codes and points broadcast, queries dealt out), forward (codes), arrow (codes,
    for many queries), inverted (postings) or auto: blocks where the points fit, else by bytes."""
    if index.d != data.d or index.params.metric != params.metric:
        raise ValueError("index and query differ in dimension or metric")
    if layout == "blocks" or layout == "auto" and blocks.fits(index.n, index.d) and walk == "prefix" and params.tie_policy == "id" and index.params.parts <= 2 and index.plan.n_sub < 256:
        points = blocks.collected(data.points, data.d, index.codes)
        if len(points.ids) == index.n or layout == "blocks":  # else there are other points than the index has
            scores = blocks.walked(index.centroids, index.parts(), index.params.parts, params.collide(index.n), params.metric, params.half_distance)
            return reported(blocks.by_query(points, data.queries, data.d, scores, blocks.found(params.k, params.pool(index.n)), blocks.FOUND), params.metric, data.unit)
    if len(blocks_of(data.queries)) > 1:
        return in_blocks(data, lambda b: indexed_search(index, b, params, walk, layout))
    cells = activated_cells(index, data.queries, params.collide(index.n), walk, params.half_distance)
    if layout == "auto":
        layout = choose_layout(data.queries.count(), params.alpha, index.n, index.plan.n_sub)
    if layout == "inverted":
        hits = count_hits_postings(index.postings(), cells)
        # points without a hit count only where hits do not fill the pool
        every = index.codes.select("id").crossJoin(F.broadcast(data.queries.select("qid")))
        few = data.queries.select("qid").join(hits.groupBy("qid").agg(F.count(F.lit(1)).alias("n")), "qid", "left").where(F.coalesce("n", F.lit(0)) < min(params.pool(index.n), index.n)).select("qid")
        none = every.join(F.broadcast(few), "qid", "left_semi").join(hits.select("qid", "id"), ["qid", "id"], "left_anti").select("qid", "id", F.lit(0).alias("score"))
        scores = hits.unionByName(none)
    elif layout == "arrow":
        scores = score_codes_arrow(index.codes, cells, index.plan.n_sub, len(index.centroids[0]) ** index.params.parts)
    else:
        scores = score_codes(index.codes, cells, index.plan.n_sub)
    pool = top_scored(scores, params.pool(index.n), params.tie_policy, index.n)
    return rerank(pool, data.points, data.queries, params.k, data.d, params.metric, data.unit)


