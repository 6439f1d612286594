"""Collisions and their scores.

A point collides with a query in a subspace when it is among the closest fraction alpha of all points there. The border
is found exactly without ranking all points: counts by distance bucket show the bucket that holds it, and only rows of
that bucket are ranked.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distances import partial
from ..plans.subspaces import SubspacePlan
from ..session import materialise
from . import blocks
from .exact import paired

BUCKETS = 512
#: Up to so many points per query a plain ranking is cheaper than the passes that find borders; both give the same rows.
RANKED_POINTS = 100_000


def part_distances(points: DataFrame, queries: DataFrame, dims: list, metric: str = "l2", kernel: str = "auto") -> DataFrame | blocks.Parts:
    """qid, id, parts: one distance per dimension list, in order. With kernel blocks no row per pair, but blocks to be streamed."""
    if kernel == "blocks":
        return blocks.Parts(points, queries, dims, metric)
    return paired(points, queries).select("qid", "id", F.array(*[partial("vec", "qvec", d, metric, kernel) for d in dims]).alias("parts"))


def borders(df: DataFrame, keys: list[str], value: str, tie: str, m: int | Column) -> DataFrame:
    """keys, limit_value, limit_tie: the m-th least row of each key by (value, tie), exactly; keys of fewer rows get their last.

    Three small shuffles: extremes, counts by bucket, and the rows of one bucket. A bucket that holds more than a few rows of
    equal value is no harm: only its keys are ranked, and Spark's group limit cuts them before the shuffle.
    """
    m = F.lit(m) if isinstance(m, int) else m
    span = df.groupBy(*keys).agg(F.min(value).alias("lo"), F.max(value).alias("hi"))
    wide = F.greatest((F.col("hi") - F.col("lo")) / BUCKETS, F.lit(1e-300))
    bucket = F.least(F.floor((F.col(value) - F.col("lo")) / wide), F.lit(BUCKETS - 1)).cast("int")
    placed = df.join(F.broadcast(span), keys).withColumn("bucket", bucket)
    counts = placed.groupBy(*keys, "bucket").agg(F.count(F.lit(1)).alias("c"))
    w = Window.partitionBy(*keys).orderBy("bucket")
    run = counts.withColumn("upto", F.sum("c").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("total", F.sum("c").over(Window.partitionBy(*keys)))
    goal = F.least(m, F.col("total"))
    at = run.where((F.col("upto") >= goal) & (F.col("upto") - F.col("c") < goal)).select(*keys, "bucket", (goal - (F.col("upto") - F.col("c"))).alias("border_rank"))
    inside = placed.join(F.broadcast(at), [*keys, "bucket"])
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy(value, tie))
    return inside.withColumn("border_r", rank).where(F.col("border_r") == F.col("border_rank")).select(*keys, F.col(value).alias("limit_value"), F.col(tie).alias("limit_tie"))


def hit_scores(points: DataFrame, queries: DataFrame, plan: SubspacePlan, m: int, metric: str = "l2") -> DataFrame:
    """qid, id, score >= 1 as a written table. Each distance is formed twice, by blocks: once to count points by distance class, and once,
    when the class that holds each border is known, to write what is surely inside with the few rows whose class decides. Borders
    among those, and later the cut of the scores, are taken from the table."""
    parts = part_distances(points, queries, list(plan.dims), metric, "blocks")
    counts = parts.class_counts().groupBy("qid", "sub", "class").agg(F.sum("c").alias("c"))
    w = Window.partitionBy("qid", "sub").orderBy("class")  # distance classes of a query, not points
    run = counts.withColumn("upto", F.sum("c").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("total", F.sum("c").over(Window.partitionBy("qid", "sub")))
    goal = F.least(F.lit(m), F.col("total"))
    at = materialise(run.where((F.col("upto") >= goal) & (F.col("upto") - F.col("c") < goal)).select("qid", "sub", "class", (goal - F.col("upto") + F.col("c")).alias("need")), "classes")
    found = materialise(parts.sure_and_border(at), "scores")
    rows = found.where(F.size("border") > 0).select("qid", "id", F.inline("border")).join(F.broadcast(at.select("qid", "sub", "need")), ["qid", "sub"])
    limits = borders(rows, ["qid", "sub", "need"], "dist", "id", F.col("need")).groupBy("qid").agg(F.map_from_entries(F.collect_list(F.struct("sub", F.struct(F.col("limit_value").alias("v"), F.col("limit_tie").alias("t"))))).alias("limits"))
    limit = lambda x: F.element_at("limits", x.sub)
    inside = F.size(F.filter("border", lambda x: (x.dist < limit(x)["v"]) | ((x.dist == limit(x)["v"]) & (F.col("id") <= limit(x)["t"]))))
    score = found.join(F.broadcast(limits), "qid").select("qid", "id", (F.col("sure") + inside).cast("int").alias("score"))
    return materialise(score.where("score > 0"), "scores")


def with_zeros(hits: DataFrame, points: DataFrame, queries: DataFrame, pool: int) -> DataFrame:
    """hits, and for queries whose hits do not fill the pool all other points at score 0."""
    filled = hits.groupBy("qid").agg(F.count(F.lit(1)).alias("hit"))
    few = queries.select("qid").join(filled, "qid", "left").where(F.coalesce("hit", F.lit(0)) < pool).select("qid")
    if few.isEmpty():
        return hits
    none = points.select("id").crossJoin(F.broadcast(few)).join(hits.select("qid", "id"), ["qid", "id"], "left_anti")
    return hits.unionByName(none.select("qid", "id", F.lit(0).alias("score")))


def within(value: str, tie: str) -> Column:
    """Is the row at or before its key's border?"""
    return (F.col(value) < F.col("limit_value")) | ((F.col(value) == F.col("limit_value")) & (F.col(tie) <= F.col("limit_tie")))


def exploded(parts: DataFrame) -> DataFrame:
    return parts.select("qid", "id", F.posexplode("parts").alias("sub", "dist"))


def subspace_collisions(points: DataFrame, queries: DataFrame, plan: SubspacePlan, m: int, metric: str = "l2", select: str = "histogram") -> DataFrame:
    """qid, sub, id of the m closest points of each query in each subspace."""
    rows = exploded(part_distances(points, queries, list(plan.dims), metric))
    if select == "rank":
        w = Window.partitionBy("qid", "sub").orderBy("dist", "id")
        return rows.withColumn("r", F.row_number().over(w)).where(F.col("r") <= m).select("qid", "sub", "id")
    limits = borders(rows, ["qid", "sub"], "dist", "id", m)
    return rows.join(F.broadcast(limits), ["qid", "sub"]).where(within("dist", "id")).select("qid", "sub", "id")


def whole_space_collisions(points: DataFrame, queries: DataFrame, d: int, m: int, metric: str = "l2") -> DataFrame:
    """qid, id of the m closest points over all dimensions."""
    one = SubspacePlan(d, (tuple(range(d)),))
    return subspace_collisions(points, queries, one, m, metric, "rank").select("qid", "id")


def collision_scores(hits: DataFrame) -> DataFrame:
    """qid, id, score from collisions."""
    return hits.groupBy("qid", "id").agg(F.count(F.lit(1)).cast("int").alias("score"))


def scan_scores(points: DataFrame, queries: DataFrame, plan: SubspacePlan, m: int, metric: str = "l2", select: str = "histogram", kernel: str = "auto") -> DataFrame:
    """qid, id, score of every point, score 0 included.

    With `histogram` borders are found by distance classes (`hit_scores`). With `rank` all hits are ranked by windows; it is the
    plain form for small inputs and the check of the other.
    """
    if select == "rank":
        hits = subspace_collisions(points, queries, plan, m, metric, "rank")
        return points.select("id").crossJoin(F.broadcast(queries.select("qid"))).join(collision_scores(hits), ["qid", "id"], "left").select("qid", "id", F.coalesce("score", F.lit(0)).alias("score"))
    hits = hit_scores(points, queries, plan, m, metric)
    return points.select("id").crossJoin(F.broadcast(queries.select("qid"))).join(hits, ["qid", "id"], "left").select("qid", "id", F.coalesce("score", F.lit(0)).alias("score"))
