"""Streams of queries and of points, and vectors from event streams."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from divknn.functions.generators import Generator, divergence
from divknn.operators.index import Index, load_index, save_index
from divknn.operators.search import exact_knn
from divknn.operators.vectors import QUERY_NUMBERS, best_k, scan_knn, width
from divknn.storage import delete, saved, shared_dir
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def answer_stream(index: Index, queries: DataFrame, k: int, sink: Callable[[DataFrame, int], None], checkpoint: str):
    """Each micro-batch of (qid, yvec) is searched in a static index and handed to ``sink``."""

    def step(batch: DataFrame, number: int) -> None:
        sink(exact_knn(index, batch, k), number)

    return queries.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).start()


def append(index: Index, fresh: DataFrame) -> Index:
    """The index with more points: they go down the trees, radii and counts grow on their paths, summaries follow.

    Bounds stay valid, so searches stay exact. New points fill pages of their own after the old ones, in leaf
    order among themselves. The old index is not changed. A point of known id replaces the old one (see ``remove``).
    """
    import copy

    from divknn.operators.index import _radii, in_leaf_order, paged
    from divknn.operators.summaries import Summaries
    from divknn.operators.vectors import matrix_of, sub_batches

    gen, d, blocks = index.gen, index.d, index.blocks
    trees = copy.deepcopy(index.trees)
    which, index_lead = Summaries(gen, blocks, index.centre), index.lead

    def place(batches):
        import pyarrow as pa

        for b in sub_batches(batches):
            x = matrix_of(b.column("vec"), d)
            leaves = np.stack([t.leaf[t.assign(gen, x[:, t.dims])] for t in trees], axis=1).astype(np.int32)
            edge = pa.array(np.arange(0, leaves.size + 1, leaves.shape[1]), pa.int32())
            sums = [pa.ListArray.from_arrays(edge, pa.array(v.ravel())) for v in which.points(x)]
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("vec"), pa.ListArray.from_arrays(edge, pa.array(leaves.ravel())), pa.array(leaves[:, index_lead]), *sums], names=["id", "vec", "leaves", "leaf_ord", "phi", "sq"])

    placed = saved(gen.prepared(fresh).select("id", "vec").mapInArrow(place, "id long, vec array<double>, leaves array<int>, leaf_ord int, phi array<double>, sq array<double>"))
    new, before = in_leaf_order(placed, shared_dir(fresh.sparkSession))
    old = remove(index, new.select("id"))
    grown = copy.copy(old)
    more = [t for t in trees]
    for t in more:
        t.count = np.zeros_like(t.count)
        t.radius = np.zeros_like(t.radius)
    _radii(new.select("vec", "leaves"), gen, more)
    for t, was in zip(more, index.trees, strict=True):
        t.radius, t.count = np.maximum(t.radius, was.radius), t.count + was.count
    grown.trees = more
    grown.n = old.n + new.count()
    last = index.points.agg(F.max("page").alias("p")).first()["p"]
    tail = paged(new, before, max(1, index.page_bytes // (4 * d))).withColumn("page", F.col("page") + F.lit(-1 if last is None else last) + 1)
    grown.points = old.points.unionByName(tail)
    grown.summaries = old.summaries.unionByName(new.select("id", "leaf_ord", "phi", "sq"))
    return grown


def remove(index: Index, ids: DataFrame) -> Index:
    """The index without some points: an anti join hides them; radii stay, which is safe."""
    import copy

    out = copy.copy(index)
    gone = ids.select("id").distinct()
    out.points, out.summaries = index.points.join(gone, "id", "left_anti"), index.summaries.join(gone, "id", "left_anti")
    out.n = out.points.count()
    return out


def versions(spark: SparkSession, path: str) -> list[int]:
    """Numbers of the whole versions of an index under ``path``: those whose manifest is written."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    files = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not files.exists(where):
        return []
    found = [s.getPath() for s in files.listStatus(where)]
    done = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    return sorted(int(p.getName()[1:]) for p in found if p.getName()[1:].isdigit() and files.exists(done(p, "manifest/_SUCCESS")))


def latest_index(spark: SparkSession, path: str, gen: Generator | None = None) -> Index:
    """The newest whole version that ``append_stream`` has left under ``path``."""
    return load_index(spark, f"{path}/v{versions(spark, path)[-1]}", gen)


def append_stream(index: Index, points: DataFrame, path: str, checkpoint: str, keep: int = 2):
    """Micro-batches of (id, vec) are added to an index kept under ``path``, a version a batch.

    ``index`` is version 0 of an empty folder. A version is whole once its manifest is there, and a batch
    that a restarted stream brings again is not added twice, so nothing is lost or doubled. Versions are
    written whole, without what was replaced; the last ``keep`` stay for searches under way.
    """
    spark, gen = points.sparkSession, index.gen
    if not versions(spark, path):
        save_index(index, f"{path}/v0")

    def step(batch: DataFrame, number: int) -> None:
        done = versions(spark, path)
        if number + 1 <= done[-1]:
            return
        current = load_index(spark, f"{path}/v{done[-1]}", gen)
        delete(spark, f"{path}/v{number + 1}")  # left unfinished by a failure
        save_index(append(current, batch) if batch.limit(1).count() else current, f"{path}/v{number + 1}")
        for old in versions(spark, path)[:-keep]:
            delete(spark, f"{path}/v{old}")

    return points.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).start()


def event_vectors(events: DataFrame, window: str = "1 day", lateness: str = "2 hours") -> DataFrame:
    """(user_id, window, vec): sums of value by event type in tumbling windows; repeats of an event are ignored, and late rows of a stream dropped."""
    kinds = ["click", "view", "purchase", "login", "search"]
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    once = timed.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else timed.dropDuplicates(["event_id"])
    sums = [F.sum(F.when(F.col("event_type") == t, F.col("value")).otherwise(0.0)).alias(t) for t in kinds]
    rest = F.sum(F.when(~F.col("event_type").isin(kinds), F.col("value")).otherwise(0.0)).alias("rest")
    return once.groupBy("user_id", F.window("ts", window)).agg(*sums, rest).select("user_id", "window", F.array(*kinds, "rest").alias("vec"))


def session_counts(events: DataFrame, gap: str = "30 minutes", lateness: str = "2 hours") -> DataFrame:
    """(user_id, session, n): events by session window."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness).groupBy("user_id", F.session_window("ts", gap).alias("session")).agg(F.count("*").alias("n"))


def running_top(points: DataFrame, queries: DataFrame, gen: Generator, k: int) -> DataFrame:
    """(qid, rank, id, divergence), updated as points arrive; the state of a query is its k best so far."""
    schema, state = "qid long, rank int, id long, divergence double", "ids array<long>, divs array<double>"
    if queries.count() * width(queries.withColumnRenamed("yvec", "vec")) > QUERY_NUMBERS:
        raise ValueError("too many queries for one stream: split them over several")
    pairs = points.crossJoin(F.broadcast(queries)).select("qid", "id", divergence(gen, "vec", "yvec").alias("divergence"))

    def update(key: tuple, frames: Iterator[pd.DataFrame], held: GroupState) -> Iterator[pd.DataFrame]:
        ids, divs = (list(map(list, held.get)) if held.exists else [[], []])
        for f in frames:
            both = sorted(zip([*divs, *f["divergence"]], [*ids, *f["id"]], strict=True), key=lambda t: (round(t[0], 9), t[1]))[:k]
            divs, ids = [float(d) for d, _ in both], [int(i) for _, i in both]
        held.update((ids, divs))
        yield pd.DataFrame({"qid": [key[0]] * len(ids), "rank": range(1, len(ids) + 1), "id": ids, "divergence": divs})

    return pairs.groupBy("qid").applyInPandasWithState(update, schema, state, "update", GroupStateTimeout.NoTimeout)


def merge_top(old: DataFrame, fresh: DataFrame, queries: DataFrame, gen: Generator, k: int) -> DataFrame:
    """Top k of old and new points from the old top k and the new points alone."""
    return best_k(old.select("qid", "id", "divergence").unionByName(scan_knn(fresh, queries, gen, k).select("qid", "id", "divergence")), k)
