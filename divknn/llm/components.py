"""Connected components of an edge table, by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import saved


def connected(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """``(node, comp)`` for every node of ``edges(a, b)``; ``comp`` is the smallest node of its component.

    Every step aggregates to one minimum per node before it joins, so no neighbourhood is gathered in
    one place; hot nodes are left to the skew handling of the join. Rounds needed grow as the logarithm of
    the longest chain; an error is raised where ``rounds`` is not enough.
    """
    now, before = saved(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()), None
    for _ in range(rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        linked = large.join(small, "u").where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = saved(linked.unionByName(small.select("u", F.col("m").alias("v"))).distinct())
        state = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"components did not converge in {rounds} rounds")
    leaves = now.select(F.col("u").alias("node"), F.col("v").alias("comp"))
    return leaves.unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct())
