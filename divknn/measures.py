"""Cost and accuracy of searches."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from divknn.operators.baselines import CellIndex, Visits, cell_candidates
from divknn.operators.index import Index
from divknn.operators.search import candidate_pages, touched_leaves
from divknn.operators.vectors import matrix_of, sub_batches
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def timed(work: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """(result, seconds) with every row computed and nothing kept."""
    began = time.perf_counter()
    out = work()
    if isinstance(out, DataFrame):
        out.write.format("noop").mode("overwrite").save()
    return out, time.perf_counter() - began


def task_seconds(spark: SparkSession) -> float:
    """Seconds that tasks have run so far on all executors, their Python included: the work of a search, whatever its wall time."""
    jvm, sc = spark.sparkContext._jvm, spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    return sum(stages.apply(i).executorRunTime() for i in range(stages.size())) / 1000


def overall_ratio(result: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, ratio, undefined): mean over ranks of returned over true divergence. 0/0 counts as 1; positive over 0 is left out and counted."""
    both = result.select("qid", "rank", F.col("divergence").alias("got")).join(truth.select("qid", "rank", F.col("divergence").alias("want")), ["qid", "rank"])
    tiny = F.lit(1e-12)
    ratio = F.when((F.col("want") <= tiny) & (F.col("got") <= tiny), 1.0).when(F.col("want") > tiny, F.col("got") / F.col("want"))
    return both.withColumn("ratio", ratio).groupBy("qid").agg(F.avg("ratio").alias("ratio"), F.sum(F.col("ratio").isNull().cast("long")).alias("undefined"))


def recall(result: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, recall): share of the true neighbours that were returned."""
    hit = truth.select("qid", "id").join(result.select("qid", "id").withColumn("hit", F.lit(1)), ["qid", "id"], "left")
    return hit.groupBy("qid").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def success_rate(result: DataFrame, truth: DataFrame) -> float:
    """Share of the queries with all true neighbours."""
    return recall(result, truth).agg(F.avg((F.col("recall") >= 1 - 1e-12).cast("double")).alias("v")).first()["v"]


def candidate_share(index: Index, qids: np.ndarray, y: np.ndarray, r: np.ndarray, granularity: str = "leaf") -> DataFrame:
    """(qid, n_candidates, share, data_pages): pages of the shared layout that hold a candidate."""
    found = candidate_pages(index, qids, y, r, granularity)
    counted = found.groupBy("qid").agg(F.sum("n").alias("n_candidates"), F.count_distinct("page").alias("data_pages"))
    return counted.withColumn("share", F.col("n_candidates") / index.n)


def forest_index_pages(index: Index, y: np.ndarray, r: np.ndarray) -> float:
    """Pages of tree nodes looked at, a query on average; summaries are read whole and come on top."""
    per_page = max(1, index.page_bytes // (8 * max(len(b) for b in index.blocks) + 32))
    return touched_leaves(index, y, r).looked / len(y) / per_page + index.n * index.m * 16 / index.page_bytes


def cell_pages(cells: CellIndex, layout: Index, qids: np.ndarray, y: np.ndarray, k: int) -> DataFrame:
    """(qid, n_candidates, data_pages, index_pages) of the cell scan, its points in the given layout."""
    found = cell_candidates(cells, qids, y, k).join(layout.points.select("id", "page"), "id")
    return found.groupBy("qid").agg(F.count("*").alias("n_candidates"), F.count_distinct("page").alias("data_pages")).withColumn("index_pages", F.lit(cells.index_pages()))


def tree_pages(index: Index, visits: Visits) -> np.ndarray:
    """Data pages of the leaves that a tree search read, per query, from each leaf's place in the layout."""
    per_page = max(1, index.page_bytes // (4 * index.d))
    sizes = index.trees[0].count[index.trees[0].leaf_nodes()]
    ends = np.cumsum(sizes)
    first, last = (ends - sizes) // per_page, np.maximum(ends - 1, 0) // per_page
    out = np.zeros(len(visits.seen), np.int64)
    for q, seen in enumerate(visits.seen):
        before = -1
        for leaf in np.flatnonzero(seen & (sizes > 0)):
            out[q] += last[leaf] - max(first[leaf], before + 1) + 1
            before = last[leaf]
    return out


def block_overlap(index: Index, qids: np.ndarray, y: np.ndarray, r: np.ndarray) -> DataFrame:
    """(qid, overlap): candidates of the blocks added up, over their union; M where all blocks agree."""
    reach = touched_leaves(index, y, r)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits, each, union = reach.masks(), np.zeros(len(qids), np.int64), np.zeros(len(qids), np.int64)
        for b in sub_batches(batches):
            leaves = matrix_of(b.column("leaves"))
            own = [h.T[leaves[:, j]] for j, h in enumerate(hits)]
            each += sum(m.sum(0) for m in own)
            union += np.any(own, axis=0).sum(0)
        yield pa.RecordBatch.from_arrays([pa.array(qids), pa.array(each), pa.array(union)], names=["qid", "each", "both"])

    found = index.points.select("leaves").mapInArrow(count, "qid long, each long, both long").groupBy("qid").agg(F.sum("each").alias("each"), F.sum("both").alias("both"))
    return found.where("both > 0").select("qid", (F.col("each") / F.col("both")).alias("overlap"))


def tightness(psum: DataFrame, qsum: DataFrame, pairs: DataFrame) -> DataFrame:
    """(mean, median) of bound over divergence; pairs: (qid, id, divergence)."""
    from divknn.operators.summaries import ceiling

    both = pairs.where("divergence > 1e-9").join(psum, "id").join(qsum, "qid").select((ceiling() / F.col("divergence")).alias("r"))
    return both.agg(F.avg("r").alias("mean"), F.median("r").alias("median"))


def relative_gain(old: float, new: float) -> float:
    return 1 - new / old if old else 0.0
