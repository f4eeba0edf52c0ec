"""Vectors in Arrow batches, query blocks of checked size, and the top-k of many queries."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from divknn.functions.generators import Generator
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Numbers of all query vectors that one pass takes to the executors (128 MB); more queries take more passes.
QUERY_NUMBERS = 1 << 24
ROWS = 2048
PARTIAL = "qid long, id long, divergence double"


def matrix_of(column: pa.ListArray, d: int | None = None) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1 if len(column) else (d or 0))


def block_size(d: int, more: int = 0) -> int:
    """Queries of a block."""
    return max(1, QUERY_NUMBERS // (max(d, 1) + ROWS + more))


def query_blocks(queries: DataFrame, d: int, more: int = 0) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(qids, vectors) in blocks whose size is checked.

    A query costs its own numbers, one for each row of a batch (divergences) and ``more``, what a method
    holds for it besides (leaves of all trees, cells of all dimensions).
    """
    most = block_size(d, more)
    ids, rows = [], []
    for r in queries.select("qid", "yvec").toLocalIterator():
        if r["yvec"] is None or len(r["yvec"]) != d or not np.isfinite(r["yvec"]).all():
            raise ValueError(f"query {r['qid']} is not a vector of {d} finite numbers")
        ids.append(r["qid"])
        rows.append(r["yvec"])
        if len(ids) == most:
            yield np.array(ids, np.int64), np.array(rows, float)
            ids, rows = [], []
    if ids:
        yield np.array(ids, np.int64), np.array(rows, float)


#: Queries that meet a batch of rows at once, so that a task holds few values whatever the number of queries.
TILE = 512


class Smallest:
    """The k smallest values of each query among those offered, ties by the smaller id; what is offered waits unsorted until there is much of it."""

    def __init__(self, n: int, k: int, limit: np.ndarray | None = None):
        self.k, self.limit = k, np.full(n, np.inf) if limit is None else np.array(limit, float)
        self.held = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        self.wait: list[tuple] = []

    def within(self, values: np.ndarray, q: slice, slack: float) -> tuple[np.ndarray, np.ndarray]:
        """(query, row) of the values (queries, rows) that may be among the k smallest; infinite ones are not."""
        own = self.limit[q]
        if values.shape[1] > self.k and np.isinf(own).any():  # k rows of the batch bound what no row bounds yet
            new = np.isinf(own)
            own[new] = np.partition(values[new], self.k - 1, axis=1)[:, self.k - 1]
        i, row = np.nonzero(values <= np.minimum(own + slack * (1 + np.abs(own)), np.finfo(float).max)[:, None])
        return i + q.start, row

    def offer(self, q: np.ndarray, ids: np.ndarray, values: np.ndarray) -> None:
        if len(q):
            self.wait.append((q, ids, values))
        if sum(len(w[0]) for w in self.wait) > max(1 << 18, len(self.held[0])):
            self.settle()

    def settle(self) -> None:
        q, i, v = (np.concatenate(c) for c in zip(self.held, *self.wait, strict=True))
        order = np.lexsort((i, np.round(v, 9), q))
        q, i, v = q[order], i[order], v[order]
        place = np.arange(len(q)) - np.searchsorted(q, q)
        last, keep = place == self.k - 1, place < self.k
        self.limit[q[last]] = np.minimum(self.limit[q[last]], v[last])
        self.held, self.wait = (q[keep], i[keep], v[keep]), []


class LocalTop:
    """The k best points of each query among the rows seen by a task; memory is k for each query.

    ``limit``: upper bounds of the k-th smallest divergence of each query; farther points are not measured.
    """

    def __init__(self, gen: Generator, qids: np.ndarray, y: np.ndarray, k: int, exclude_self: bool, limit: np.ndarray | None = None):
        self.gen, self.qids, self.y, self.k, self.exclude = gen, qids, y, k, exclude_self
        self.best = Smallest(len(qids), k, limit)
        g = gen.grad(y)  # a query's part of the divergence beside its slopes: one product gives all of it
        self.slopes = np.concatenate((-g, np.ones((len(y), 1)), ((g * y).sum(1) - gen.phi(y).sum(1))[:, None]), axis=1)

    def add(self, ids: np.ndarray, x: np.ndarray, allowed: np.ndarray | None = None) -> None:
        """allowed: (rows, queries) mask of the pairs to consider."""
        if not len(ids):
            return
        right = np.concatenate((x, self.gen.phi(x).sum(1)[:, None], np.ones((len(x), 1))), axis=1).T
        for lo in range(0, len(self.qids), TILE):
            tile = slice(lo, min(lo + TILE, len(self.qids)))
            rough = self.slopes[tile] @ right
            if allowed is not None:
                rough[~allowed[:, tile].T] = np.inf
            if self.exclude:
                rough[self.qids[tile][:, None] == ids[None, :]] = np.inf
            q, row = self.best.within(rough, tile, 1e-7)
            for at in range(0, len(q), 1 << 12):
                i, j = q[at : at + (1 << 12)], row[at : at + (1 << 12)]
                self.best.offer(i, ids[j], self.gen.divergence(x[j], self.y[i]))

    def rows(self) -> pa.RecordBatch:
        self.best.settle()
        q, i, d = self.best.held
        return pa.RecordBatch.from_arrays([pa.array(self.qids[q]), pa.array(i), pa.array(d)], names=["qid", "id", "divergence"])


def best_k(partial: DataFrame, k: int) -> DataFrame:
    """(qid, rank, id, divergence): ties by the smaller id."""
    w = Window.partitionBy("qid").orderBy(F.round("divergence", 9), "id")
    return partial.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", F.col("rank").cast("int"), "id", "divergence")


def each_block(queries: DataFrame, d: int, work: Callable[[np.ndarray, np.ndarray], DataFrame], more: int = 0) -> DataFrame | None:
    out = None
    for qids, y in query_blocks(queries, d, more):
        found = work(qids, y)
        out = found if out is None else out.unionByName(found)
    return out


def broadcast_parts(few: DataFrame, numbers: int, key: str = "qid") -> list[DataFrame]:
    """Parts of ``few`` (rows of ``numbers`` numbers each), marked for broadcast, none larger than ``QUERY_NUMBERS``."""
    parts = -(-few.count() * max(1, numbers) // QUERY_NUMBERS)
    if parts <= 1:
        return [F.broadcast(few)]
    return [F.broadcast(few.where(F.pmod(F.xxhash64(key), F.lit(parts)) == i)) for i in range(parts)]


def union_of(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def check_k(k: int) -> None:
    if k < 1:
        raise ValueError("k must be 1 or more")


def sub_batches(batches: Iterator[pa.RecordBatch], rows: int = ROWS) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for lo in range(0, b.num_rows, rows):
            yield b.slice(lo, rows)


def scan_knn(points: DataFrame, queries: DataFrame, gen: Generator, k: int, exclude_self: bool = False) -> DataFrame:
    """Exhaustive search: every point against every query by matrix products, k rows a task and query leave it."""
    check_k(k)
    points, d = gen.prepared(points), width(points)
    queries = gen.prepared(queries, "yvec")

    def work(qids: np.ndarray, y: np.ndarray) -> DataFrame:
        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            top = LocalTop(gen, qids, y, k, exclude_self)
            for b in sub_batches(batches):
                top.add(b.column("id").to_numpy(), matrix_of(b.column("vec")))
            yield top.rows()

        return points.select("id", "vec").mapInArrow(scan, PARTIAL)

    found = each_block(queries, d, work)
    return best_k(found if found is not None else empty(points, PARTIAL), k)


#: Pairs that leave a task in one batch.
PAIRS = 1 << 18


def all_pairs(points: DataFrame, queries: DataFrame, gen: Generator, digits: int | None = None) -> DataFrame:
    """(qid, id, divergence) of every point with every query, by matrix products; ``digits`` rounds in the tasks."""
    points, d = gen.prepared(points), width(points)
    queries = gen.prepared(queries, "yvec")

    def work(qids: np.ndarray, y: np.ndarray) -> DataFrame:
        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in sub_batches(batches, max(1, PAIRS // len(qids))):
                dist = gen.pairs(matrix_of(b.column("vec")), y).ravel()
                dist = dist if digits is None else np.round(dist, digits)
                yield pa.RecordBatch.from_arrays([pa.array(np.tile(qids, b.num_rows)), pa.array(np.repeat(b.column("id").to_numpy(), len(qids))), pa.array(dist + 0.0)], names=["qid", "id", "divergence"])

        return points.select("id", "vec").mapInArrow(scan, PARTIAL)

    found = each_block(queries, d, work)
    return found if found is not None else empty(points, PARTIAL)


def empty(like: DataFrame, schema: str) -> DataFrame:
    return like.sparkSession.createDataFrame([], schema)


def given(spark: SparkSession, **columns: list | pa.Array) -> DataFrame:
    """A table of the driver's columns, sent as Arrow: rows of Python objects pass Python workers on their way."""
    return spark.createDataFrame(pa.table(columns))


def width(points: DataFrame) -> int:
    first = points.select(F.size("vec").alias("d")).first()
    return first["d"] if first else 0


#: One point in so many bounds the k-th distance before all points are looked at.
SHARE = 16


def scan_knn_columns(points: DataFrame, queries: DataFrame, gen: Generator, k: int, exclude_self: bool = False) -> DataFrame:
    """The same in built-in functions alone: broadcast join, divergence as an expression, limited window.

    The divergence is a point's part, a query's part and a product of the two; the k-th smallest among a share of
    the points is an upper bound, so that only pairs within it are measured exactly and sorted.
    """
    from divknn.functions.generators import divergence

    check_k(k)
    d, asked = width(points), gen.prepared(queries, "yvec")
    of = lambda v, e: F.expr(f"coalesce(aggregate({v}, 0D, (s, t) -> s + {e}), double('NaN'))")
    each = lambda v, c: [F.coalesce(F.get(v, F.lit(i)), F.lit(float("nan"))).alias(f"{c}{i}") for i in range(d)]
    phi, grad = gen.phi_sql.format(t="t"), gen.grad_sql.format(t="t")
    x = gen.prepared(points).select("id", "vec", of("vec", phi).alias("phi"), F.sqrt(of("vec", "t * t")).alias("long"), *each("vec", "x"))
    y = asked.select("qid", "yvec", (of("yvec", f"t * ({grad})") - of("yvec", phi)).alias("own"), F.expr(f"transform(yvec, t -> {grad})").alias("g"))
    y = y.select("qid", "yvec", "own", F.sqrt(of("g", "t * t")).alias("steep"), *each("g", "g"))
    dot = [F.col(f"x{i}") * F.col(f"g{i}") for i in range(d)]  # columns and no arrays: functions over arrays are interpreted for each element
    while len(dot) > 1:  # a flat tree of sums
        dot = [a + b for a, b in zip(dot[::2], dot[1::2], strict=False)] + dot[len(dot) - len(dot) % 2 :]
    rough = F.col("phi") + F.col("own") - dot[0] if dot else F.lit(0.0)
    apart = F.col("id") != F.col("qid") if exclude_self else F.lit(True)

    some = union_of([x.where(F.pmod(F.xxhash64("id"), F.lit(SHARE)) == 0).crossJoin(q) for q in broadcast_parts(y, 2 * d)]).where(apart).select("qid", rough.alias("rough"))
    w = Window.partitionBy("qid").orderBy("rough")
    limits = some.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).where(F.col("rank") == k).select("qid", F.col("rough").alias("most"))
    bounded = y.join(limits, "qid", "left").withColumn("most", F.coalesce("most", F.lit(float("inf"))))
    slack = 1e-9 * (1 + F.abs("most") + F.col("long") * F.col("steep"))
    near = union_of([x.crossJoin(q) for q in broadcast_parts(bounded, 2 * d)]).where(apart & (rough <= F.col("most") + slack))
    return best_k(near.select("qid", "id", divergence(gen, "vec", "yvec").alias("divergence")), k)
