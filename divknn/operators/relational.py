"""Relational operators around nearest neighbours."""

from __future__ import annotations

from divknn.functions.generators import Generator, divergence
from divknn.operators.baselines import build_whole_tree
from divknn.operators.index import Index
from divknn.operators.search import exact_knn, range_search
from divknn.operators.vectors import broadcast_parts, scan_knn, union_of, width
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def knn_join(left: DataFrame, right: DataFrame | Index, gen: Generator, k: int, exclude_self: bool = False) -> DataFrame:
    """The k nearest rows of ``right`` for every row of ``left`` (both (id, vec)); left goes in blocks of checked size."""
    queries = left.select(F.col("id").alias("qid"), F.col("vec").alias("yvec"))
    return exact_knn(right, queries, k, exclude_self=exclude_self) if isinstance(right, Index) else scan_knn(right, queries, gen, k, exclude_self)


def filtered_knn(points: DataFrame, condition: Column, queries: DataFrame, gen: Generator, k: int) -> DataFrame:
    """Neighbours among the rows that meet the condition: it comes first, as bounds from other rows would be wrong."""
    return scan_knn(points.where(condition), queries, gen, k)


def label_vote(neighbours: DataFrame, labels: DataFrame) -> DataFrame:
    """(qid, label, votes): the most frequent label, ties to the smaller one; labels: (id, label)."""
    votes = neighbours.join(labels, "id").groupBy("qid", "label").agg(F.count("*").alias("votes"))
    w = Window.partitionBy("qid").orderBy(F.desc("votes"), "label")
    return votes.withColumn("r", F.row_number().over(w)).where("r = 1").select("qid", "label", "votes")


def similar_pairs(points: DataFrame, few: DataFrame, gen: Generator, radius: float) -> DataFrame:
    """(qid, id, divergence) within a radius of a few stated points, themselves left out."""
    q = few.select(F.col("id").alias("qid"), F.col("vec").alias("yvec"))
    near = union_of([points.join(part, (F.col("id") != F.col("qid")) & (divergence(gen, "vec", "yvec") <= radius)) for part in broadcast_parts(q, width(points))])
    return near.select("qid", "id", divergence(gen, "vec", "yvec").alias("divergence"))


def all_similar_pairs(points: DataFrame, gen: Generator, radius: float, digits: int | None = None) -> DataFrame:
    """(qid, id, divergence) of all pairs within a radius, in either direction: one row a pair, qid < id, the smaller divergence.

    Every point asks a whole-space tree, in query blocks of checked size; ids are unique. Both directions of a pair are
    measured where it is found, so nothing is shuffled to unite them. ``digits`` rounds in the tasks.
    """
    queries = points.select(F.col("id").alias("qid"), F.col("vec").alias("yvec"), F.lit(float(radius)).alias("radius"))
    return range_search(build_whole_tree(points, gen), queries, once=True, digits=digits)


def report(measures: DataFrame) -> DataFrame:
    """Means of a measure by (view, method), by view, and over all."""
    return measures.rollup("view", "method").agg(F.avg("value").alias("value"), F.count("*").alias("n"))


def versus(measures: DataFrame) -> DataFrame:
    """One column per method: the on/off table of an ablation."""
    return measures.groupBy("view", "k").pivot("method").agg(F.avg("value"))
