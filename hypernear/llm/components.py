"""Connected components of an edge table, by alternating stars; nothing is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import persisted


def star(edges: DataFrame, large: bool) -> DataFrame:
    """Point each node's neighbours at the least of them: larger neighbours (large) or the smaller and itself."""
    pair = lambda a, b: F.struct(F.col(a).alias("u"), F.col(b).alias("v"))
    if large:
        both = edges.select(F.inline(F.array(pair("u", "v"), pair("v", "u"))))
    else:
        both = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    joined = both.join(least, "u")
    if large:
        return joined.filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return joined.select(F.inline(F.array(pair("v", "m"), pair("u", "m")))).filter("u <> v")


def components(edges: DataFrame, most_rounds: int = 60, few: int = 250_000) -> DataFrame:
    """(node, component) of every node on an edge (u, v); a component is named by its least node.

    A round halves the distances to the least node, so the rounds are about the logarithm of the longest path. It is over once
    every node has one edge, and no edge leads on from its end. Up to ``few`` edges, a few megabytes, need no shuffle at all.
    """
    one = edges.count() <= few
    edges = edges.coalesce(1) if one else edges
    now = edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    for _ in range(most_rounds):
        now = persisted(star(star(now, True), False).distinct(), "components")
        now = now.coalesce(1) if one else now
        ends = now.groupBy("u").agg(F.count("*").alias("n"))
        on = now.select(F.col("v").alias("u")).distinct().join(ends.select("u"), "u", "left_semi")
        if on.isEmpty() and ends.filter("n > 1").isEmpty():
            return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
