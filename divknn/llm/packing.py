"""Best-fit packing of token pieces with a matching of the large ones.

Lengths are whole numbers up to the capacity, so a packing is decided on the histogram of lengths, whose
size does not grow with the data: at most two pieces above a third of the capacity share a sequence, and
each of the longest takes the longest partner that fits; the shorter ones go, longest first, where they
leave the smallest gap. Groups of equal sequences move together, which gives the same packing as placing
pieces one by one. Pieces then find their places by their rank among pieces of equal length.

A null text is one end id. Rows that repeat are packed each. An empty table gives no rows. A document
longer than the capacity is cut, and only then. Other columns are not read.
"""

from __future__ import annotations

import bisect
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import saved, text_slices, table
from .tokens import ChunkEncoder, vocabulary_path

CAPACITY, END = 4096, 1
_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
#: Pieces of one length are ranked in this many parts at least, and in parts of about PART rows.
SALTS, PART = 16, 250_000


def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ChunkEncoder(path)
        for batch in batches:
            keys = batch.column("doc_id")
            for a, b, texts in text_slices(batch):
                ids, offsets = encoder.encode(texts, end)
                sizes = np.diff(offsets)
                count = -(-sizes // capacity)
                owner = np.repeat(np.arange(b - a), count)
                piece = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
                start = piece * capacity
                length = np.minimum(capacity, sizes[owner] - start)
                wide, at = ids.astype("<u4"), offsets[owner] + start
                sums = [zlib.crc32(wide[s : s + n].data) for s, n in zip(at, length, strict=True)]
                yield pa.RecordBatch.from_arrays([keys[a:b].take(pa.array(owner)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), pa.array(sums, pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(cut, _PIECES)


class _Gaps:
    """Groups of equal open sequences by free space."""

    def __init__(self):
        self.by: dict[int, list[list[int]]] = defaultdict(list)  # gap -> [pattern, how many, pieces so far]
        self.sorted: list[int] = []

    def add(self, gap: int, group: list[int]) -> None:
        if gap not in self.by or not self.by[gap]:
            bisect.insort(self.sorted, gap)
        self.by[gap].append(group)

    def take(self, gap: int) -> list[int]:
        group = self.by[gap].pop()
        if not self.by[gap]:
            self.sorted.pop(bisect.bisect_left(self.sorted, gap))
        return group

    def smallest(self, least: int) -> int | None:
        i = bisect.bisect_left(self.sorted, least)
        return self.sorted[i] if i < len(self.sorted) else None


def plan_bins(histogram: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """([(length, rank from, rank to, first sequence, offset)], sequences): pieces of a length by rank."""
    left = dict(histogram)
    runs: list[tuple[int, int, int, int, int]] = []
    ranked = defaultdict(int)
    made = 0
    gaps = _Gaps()

    def place(length: int, n: int, first: int, offset: int) -> None:
        runs.append((length, ranked[length], ranked[length] + n, first, offset))
        ranked[length] += n
        left[length] -= n

    large = sorted(x for x in left if 3 * x > capacity and left[x])
    while large:  # the longest with the longest partner that fits
        top = large[-1]
        i = bisect.bisect_right(large, capacity - top) - 1
        if i < 0:
            n, first = left[top], made
            place(top, n, first, 0)
            gaps.add(capacity - top, [first, n])
        else:
            mate = large[i]
            n = left[top] // 2 if mate == top else min(left[top], left[mate])
            if mate == top and n == 0:  # one is left over: a shorter partner, or none
                shorter = large[i - 1] if i else None
                n, mate = 1, shorter
            first = made
            place(top, n, first, 0)
            if mate is not None:
                place(mate, n, first, top)
            gaps.add(capacity - top - (mate or 0), [first, n])
        made += n
        large = [x for x in large if left[x]]
    for length in sorted((x for x in left if left[x]), reverse=True):
        while left[length]:
            gap = gaps.smallest(length)
            if gap is None:
                fit = capacity // length
                n = max(1, left[length] // fit)
                each = min(fit, left[length])
                for j in range(each):
                    place(length, n, made, j * length)
                gaps.add(capacity - each * length, [made, n])
                made += n
                continue
            first, n = gaps.take(gap)
            fill = min(n, left[length])
            place(length, fill, first, capacity - gap)
            gaps.add(gap - length, [first, fill])
            if fill < n:
                gaps.add(gap, [first + fill, n - fill])
    return runs, made


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """One row per piece with its sequence and place."""
    cut = saved(pieces(docs, path, capacity, end))
    histogram = {r["length"]: r["count"] for r in cut.groupBy("length").count().collect()}  # at most ``capacity`` rows
    runs, _ = plan_bins(histogram, capacity)
    salts = max(SALTS, sum(histogram.values()) // PART)
    salted = cut.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)))
    before = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    before = before.select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt")) - F.col("n")).alias("before"))
    own = F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32"))
    ranked = salted.withColumn("own", own).join(before, ["length", "salt"]).select(*[c.split()[0] for c in _PIECES.split(", ")], (F.col("before") + F.col("own") - 1).alias("rank"))

    listed = np.array(sorted(runs), np.int64).reshape(-1, 5)  # a few for each length: bounded by the capacity
    width = int(listed[:, 2].max() + 1) if len(listed) else 1
    keys = listed[:, 0] * width + listed[:, 1]

    def assign(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            run = listed[np.searchsorted(keys, f["length"].to_numpy() * width + f["rank"].to_numpy(), "right") - 1]
            f["sequence_id"], f["offset"] = run[:, 3] + f.pop("rank") - run[:, 1], run[:, 4]
            yield f

    return ranked.mapInPandas(assign, f"{_PIECES}, sequence_id long, offset long")


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), vocabulary_path())
