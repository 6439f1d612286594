"""Connected components by contraction, as joins and aggregates; links never leave the executors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def _jump(names: DataFrame) -> DataFrame:
    """Each node's name replaced by that name's own."""
    on = names.select(F.col("node").alias("via"), F.col("name").alias("further"))
    return names.join(on, F.col("name") == F.col("via"), "left").select("node", F.coalesce("further", "name").alias("name"))


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, component) for every end of links(a, b); the component is one of its nodes.

    Each round every node takes its least neighbour (or itself) as its name, links are renamed and those within a name
    are dropped. Pointers are followed four steps within a round; ids are hashes, so chains of falling ids are short and few
    rounds are needed. Hot nodes are met by partial aggregation.
    """
    edges = common.materialise(links.select("a", "b").where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    nodes = None
    for _ in range(rounds):
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("name"))
        least = common.materialise(_jump(_jump(least)))
        if nodes is None:
            nodes = least.select("node", F.col("name").alias("component"))
        else:
            step = least.select(F.col("node").alias("old"), "name")
            nodes = nodes.join(step, F.col("component") == F.col("old"), "left").select("node", F.coalesce("name", "component").alias("component"))
        nodes = common.materialise(nodes)
        left, right = least.select(F.col("node").alias("a"), F.col("name").alias("na")), least.select(F.col("node").alias("b"), F.col("name").alias("nb"))
        renamed = edges.join(left, "a").join(right, "b").where("na <> nb")
        edges = common.materialise(renamed.select(F.least("na", "nb").alias("a"), F.greatest("na", "nb").alias("b")).distinct())
        if edges.isEmpty():
            return nodes
    raise RuntimeError(f"components did not settle in {rounds} rounds")
