"""From scores to a pool of candidates, and from the pool to ranked neighbours."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distances import order_distance, true_distance
from .collisions import RANKED_POINTS, borders, within
from .exact import first_k

TIES = ("id", "hash", "all")


def top_scored(scores: DataFrame, pool: int, tie_policy: str = "id", n: int | None = None) -> DataFrame:
    """qid, id, score of the `pool` best-scored points of each query.

    Scores have few values, so a histogram per query gives the cut; only the class at the cut is divided: by id, by a hash
    of the id (unbiased), or not at all ('all' keeps the whole class). With few points (n given) they are ranked plainly.
    """
    if tie_policy not in TIES:
        raise ValueError(f"tie_policy is one of {TIES}")
    tie = F.col("id").cast("double") if tie_policy == "id" else F.pmod(F.xxhash64("id", F.lit("tie")), F.lit(1 << 52)).cast("double")
    if n is not None and n <= RANKED_POINTS and tie_policy != "all":
        w = Window.partitionBy("qid").orderBy(F.col("score").desc(), tie, "id")
        return scores.withColumn("pool_rank", F.row_number().over(w)).where(F.col("pool_rank") <= pool).select("qid", "id", "score")
    counts = scores.groupBy("qid", "score").agg(F.count(F.lit(1)).alias("c"))
    w = Window.partitionBy("qid").orderBy(F.col("score").desc())
    run = counts.withColumn("upto", F.sum("c").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("total", F.sum("c").over(Window.partitionBy("qid")))
    goal = F.least(F.lit(pool), F.col("total"))
    cut = run.where((F.col("upto") >= goal) & (F.col("upto") - F.col("c") < goal)).select("qid", F.col("score").alias("cut"), (goal - F.col("upto") + F.col("c")).alias("need"))
    tagged = scores.join(F.broadcast(cut), "qid")
    if tie_policy == "all":
        return tagged.where(F.col("score") >= F.col("cut")).select("qid", "id", "score")
    above = tagged.where(F.col("score") > F.col("cut")).select("qid", "id", "score")
    level = tagged.where(F.col("score") == F.col("cut")).withColumn("v", tie)
    kept = level.join(F.broadcast(_class_limits(level)), "qid").where(within("v", "id")).select("qid", "id", "score")
    return above.unionByName(kept)


def _class_limits(level: DataFrame) -> DataFrame:
    """The last admitted row of each query's class at the cut; `need` is the same in all rows of a query."""
    return borders(level.select("qid", "need", "v", "id"), ["qid", "need"], "v", "id", F.col("need")).drop("need")


def rerank(pool: DataFrame, points: DataFrame, queries: DataFrame, k: int, d: int, metric: str = "l2", unit: float = 1.0, kernel: str = "auto") -> DataFrame:
    """qid, rank, id, distance, score: exact distances for the pool only. Spark broadcasts the pool where it is small."""
    full = pool.join(points.select("id", "vec"), "id").join(F.broadcast(queries), "qid")
    ranked = first_k(full.select("qid", "id", "score", order_distance("vec", "qvec", d, metric, kernel).alias("dist")), k)
    return ranked.select("qid", F.col("rank").cast("int").alias("rank"), "id", F.round(true_distance(F.col("dist"), metric, unit), 6).alias("distance"), F.col("score").cast("int").alias("score"))


def without_rerank(scores: DataFrame, k: int) -> DataFrame:
    """The first k by score and id: the ablation without exact distances."""
    w = Window.partitionBy("qid").orderBy(F.col("score").desc(), "id")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", F.col("rank").cast("int").alias("rank"), "id", F.col("score").cast("int").alias("score"))
