"""The index: blocks, summaries and a forest of ball trees over one shared layout, as tables and a manifest."""

from __future__ import annotations

import json
import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from divknn.functions import generators
from divknn.functions.generators import Generator
from divknn.operators.balltree import BallTree, build_tree
from divknn.operators.summaries import Summaries
from divknn.operators.vectors import ROWS, given, matrix_of, sub_batches, width
from divknn.plans import costmodel
from divknn.plans.partition import make_blocks, survey
from divknn.storage import delete, shared_dir
from divknn.storage import saved_vectors as saved
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows a tree's splits are trained on, at most.
SAMPLE = 20_000


@dataclass
class Index:
    gen: Generator
    blocks: list[list[int]]
    d: int
    n: int
    trees: list[BallTree]
    points: DataFrame  # id, vec, leaves, leaf_ord, page, slot
    summaries: DataFrame  # id, leaf_ord, phi, sq
    page_bytes: int
    path: str
    centre: np.ndarray | None = None
    model: costmodel.CostModel | None = None
    lead: int = 0

    @property
    def m(self) -> int:
        return len(self.blocks)

    def which(self) -> Summaries:
        return Summaries(self.gen, self.blocks, self.centre)

    def node_pages(self) -> int:
        """Pages of all node tables: a centre, a radius and three numbers each."""
        return sum(-(-len(t.leaf) * (8 * len(t.dims) + 32) // self.page_bytes) for t in self.trees)


def _sampled(points: DataFrame, n: int, most: int) -> DataFrame:
    """Rows picked by a hash of their id, ``most`` at most, in one part in the order of their ids: the same whatever the partitioning. Vectors come as bytes."""
    picked = points if n <= most else points.where(F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < int(1_000_000 * most / n * 0.95))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([v.tobytes() for v in matrix_of(b.column("vec"))], pa.binary())], names=["id", "vec"])

    return picked.select("id", "vec").mapInArrow(pack, "id long, vec binary").orderBy("id", "vec").limit(most).select("vec")


def bounded_sample(points: DataFrame, n: int, most: int = SAMPLE) -> np.ndarray:
    """The sample on the driver."""
    rows = _sampled(points, n, most).toArrow()  # bytes in one piece: rows of them would take several times the room
    return np.frombuffer(b"".join(v.as_buffer() for v in rows["vec"])).reshape(rows.num_rows, -1) if rows.num_rows else np.zeros(0)


def on_sample(points: DataFrame, n: int, blocks: list[list[int]], work: Callable[[int, np.ndarray], bytes], most: int = SAMPLE) -> list[bytes]:
    """``work(number, rows)`` for each block of coordinates of the sample, in a task each: the sample never meets on the driver."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = 0
        for b in sub_batches(batches):
            x = np.frombuffer(b"".join(b.column("vec").to_pylist())).reshape(b.num_rows, -1)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(blocks))), pa.array(np.full(len(blocks), place)), pa.array([np.ascontiguousarray(x[:, own]).tobytes() for own in blocks], pa.binary())], names=["block", "place", "held"])
            place += b.num_rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for b in batches:
            for j, place, own in zip(*(b.column(c).to_pylist() for c in ("block", "place", "held")), strict=True):
                held.setdefault(j, []).append((place, own))
        for j, own in held.items():
            rows = np.frombuffer(b"".join(v for _, v in sorted(own))).reshape(-1, len(blocks[j]))
            yield pa.RecordBatch.from_arrays([pa.array([j]), pa.array([work(j, rows)], pa.binary())], names=["block", "out"])

    pieces = _sampled(points, n, most).mapInArrow(cut, "block long, place long, held binary").repartition(len(blocks), "block")
    return [r["out"] for r in sorted(pieces.mapInArrow(run, "block long, out binary").collect(), key=lambda r: r["block"])]


def _grow(points: DataFrame, n: int, gen: Generator, blocks: list[list[int]], leaf_size: int, max_depth: int, seed: int) -> tuple[list[BallTree], np.ndarray]:
    """A tree for each block, each grown in a task of its own from its coordinates of the sample; and the sample's mean."""

    def grow(j: int, own: np.ndarray) -> bytes:
        scaled = max(min(leaf_size, 8), round(leaf_size * len(own) / n))  # fewer rows of a sample make poor splits
        tree = build_tree(own, gen, list(range(len(blocks[j]))), scaled, max_depth, seed + j)
        tree.dims = list(blocks[j])
        return pickle.dumps((tree, own.mean(0)))

    found, mean = [pickle.loads(v) for v in on_sample(points, n, blocks, grow)], np.zeros(sum(map(len, blocks)))
    for tree, own in found:
        mean[tree.dims] = own
    return [tree for tree, _ in found], mean


def paged(rows: DataFrame, before: list[int], per_page: int) -> DataFrame:
    """The layout's points with their page and slot: a row's place is its place in its part and what the parts before hold."""
    ordinal = F.array(*map(F.lit, before))[F.col("part")].cast("long") + F.col("place")
    return rows.select("id", "vec", "leaves", "leaf_ord", F.floor(ordinal / per_page).alias("page"), F.pmod(ordinal, F.lit(per_page)).cast("int").alias("slot"))


def _write_layout(points: DataFrame, gen: Generator, trees: list[BallTree], lead: int, page_bytes: int, d: int, path: str) -> tuple[DataFrame, list[int]]:
    """Points in the leaf order of the lead block, with their leaves in all trees and their page: a range sort, no group of a leaf meets in one task."""
    schema = "id long, vec array<double>, leaves array<int>, leaf_ord int"

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sub_batches(batches):
            x = matrix_of(b.column("vec"), d)
            leaves = np.stack([t.leaf[t.assign(gen, x[:, t.dims])] for t in trees], axis=1).astype(np.int32)
            edge = pa.array(np.arange(0, leaves.size + 1, leaves.shape[1]), pa.int32())
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("vec"), pa.ListArray.from_arrays(edge, pa.array(leaves.ravel())), pa.array(leaves[:, lead])], names=["id", "vec", "leaves", "leaf_ord"])

    placed = saved(points.select("id", "vec").mapInArrow(place, schema), f"{path}/assigned")
    laid, before = in_leaf_order(placed, f"{path}/points")
    delete(points.sparkSession, f"{path}/assigned")
    return paged(laid, before, max(1, page_bytes // (4 * d))), before


def in_leaf_order(placed: DataFrame, path: str) -> tuple[DataFrame, list[int]]:
    """Rows by (leaf_ord, id) with their part and place in it, written; and the rows before each part."""
    ordered = placed.repartitionByRange("leaf_ord", "id").sortWithinPartitions("leaf_ord", "id")
    at = F.monotonically_increasing_id()  # the part in the upper bits, the place in it in the lower 33
    laid = saved(ordered.withColumn("part", F.shiftright(at, 33).cast("int")).withColumn("place", at.bitwiseAND((1 << 33) - 1)), path)
    sizes = {r["part"]: r["count"] for r in laid.groupBy("part").count().collect()}  # one number a part
    return laid, np.concatenate(([0], np.cumsum([sizes.get(j, 0) for j in range(max(sizes, default=0) + 1)]))).tolist()


def _radii(points: DataFrame, gen: Generator, trees: list[BallTree]) -> None:
    """Radii and sizes of all nodes of all trees in one pass over all points."""
    paths = [t.paths() for t in trees]
    leaf_nodes = [t.leaf_nodes() for t in trees]

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        radius, count = [np.zeros(len(t.leaf)) for t in trees], [np.zeros(len(t.leaf), np.int64) for t in trees]
        for b in sub_batches(batches, 8 * ROWS):
            x, leaves = matrix_of(b.column("vec")), matrix_of(b.column("leaves"))
            for j, t in enumerate(trees):
                order = np.argsort(leaves[:, j], kind="stable")  # leaves are numbered left to right, so rows of a node are neighbours
                own, up = x[order][:, t.dims], paths[j][leaf_nodes[j][leaves[order, j]]]
                count[j] += np.bincount(up[:, 0], minlength=len(t.leaf))
                for level in range(up.shape[1]):
                    rows = np.flatnonzero(up[:, level] >= 0)
                    if not len(rows):  # no row of the batch lies so deep
                        break
                    nodes = up[rows, level]
                    far = gen.divergence(own[rows] if len(rows) < len(own) else own, t.centre[nodes])
                    by = np.argsort(nodes, kind="stable")
                    first = np.flatnonzero(np.concatenate(([True], nodes[by][1:] != nodes[by][:-1])))
                    np.maximum.at(radius[j], nodes[by][first], np.maximum.reduceat(far[by], first))
        for j, t in enumerate(trees):  # counted at the leaves, summed up the tree: children have larger numbers
            parent = t.parents()
            for node in range(len(parent) - 1, 0, -1):
                count[j][parent[node]] += count[j][node]
        which = np.concatenate([np.full(len(r), j) for j, r in enumerate(radius)])
        node = np.concatenate([np.arange(len(r)) for r in radius])
        yield pa.RecordBatch.from_arrays([pa.array(which), pa.array(node), pa.array(np.concatenate(radius)), pa.array(np.concatenate(count))], names=["block", "node", "radius", "count"])

    found = points.select("vec", "leaves").mapInArrow(scan, "block long, node long, radius double, count long").groupBy("block", "node").agg(F.max("radius").alias("radius"), F.sum("count").alias("count"))
    rows = found.toArrow()  # one row a node
    block, node, radius, count = (rows[c].to_numpy() for c in ("block", "node", "radius", "count"))
    for j, t in enumerate(trees):
        own = block == j
        t.radius[node[own]], t.count[node[own]] = radius[own] * (1 + 1e-12), count[own]


def nodes_table(spark: SparkSession, trees: list[BallTree]) -> DataFrame:
    """A row a node; columns of numbers go to the engine, as rows of Python objects took a large part of the driver's memory."""
    sizes = [len(t.leaf) for t in trees]
    wide = np.concatenate(([0], np.cumsum(np.repeat([t.centre.shape[1] for t in trees], sizes))))
    of = lambda each, kind: pa.array(np.concatenate([each(t) for t in trees]), kind)
    columns = {
        "block": pa.array(np.repeat(np.arange(len(trees)), sizes), pa.int32()), "node": of(lambda t: np.arange(len(t.leaf)), pa.int64()), "parent": of(BallTree.parents, pa.int64()),
        "depth": of(lambda t: t.depth, pa.int32()), "is_leaf": of(lambda t: t.leaf >= 0, pa.bool_()), "left": of(lambda t: t.left, pa.int64()), "right": of(lambda t: t.right, pa.int64()), "leaf": of(lambda t: t.leaf, pa.int32()),
        "centre": pa.ListArray.from_arrays(pa.array(wide, pa.int32()), of(lambda t: t.centre.ravel(), pa.float64())), "radius": of(lambda t: t.radius, pa.float64()), "n_points": of(lambda t: t.count, pa.int64()),
    }
    return given(spark, **columns)


def build_index(
    points: DataFrame, gen: Generator, m: int | str = "auto", strategy: str = "decorrelated", seed: int = 42, leaf_size: int = 64, max_depth: int = 12,
    page_bytes: int = 32 << 10, centre: bool = False, path: str | None = None, first: int | None = None, k: int = 1, stored: bool = False,
) -> Index:
    """Choose the blocks, summarise every point, grow a tree per block, lay the points out and write it all.

    ``stored``: the points are read from files as they are, so that a copy of them would spare no work.
    """
    spark, path = points.sparkSession, path or shared_dir(points.sparkSession)
    points = gen.prepared(points).select("id", "vec")
    if not stored or gen.weights:
        points = saved(points, f"{path}/input")  # several passes follow
    found = survey(points, strategy == "decorrelated")
    n, d = found.n, found.d
    if found.bad or d != found.most:
        raise ValueError("vectors must not be null, hold no null or NaN, and be of one length")
    if gen.domain == "positive" and n and found.low <= 0:
        raise ValueError(f"{gen.name} needs positive coordinates; see shift_positive")
    if not n:
        raise ValueError("an index needs points")
    model = None
    if m == "auto":
        model = costmodel.fit(points, gen, n, d, seed=seed)
        m = model.optimal_blocks(k)
    blocks = make_blocks(points, int(m), strategy, seed, first, found)
    trees, mean = _grow(points, n, gen, blocks, leaf_size, max_depth, seed)
    lead = int(np.random.default_rng(seed).integers(len(blocks)))
    laid, before = _write_layout(points, gen, trees, lead, page_bytes, d, path)
    _radii(laid, gen, trees)
    mean = mean if centre else None
    which = Summaries(gen, blocks, mean)

    def summarise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sub_batches(batches, 4096):
            pair = which.points(matrix_of(b.column("vec")))
            edge = pa.array(np.arange(0, pair[0].size + 1, len(blocks)), pa.int32())
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("leaf_ord"), *[pa.ListArray.from_arrays(edge, pa.array(v.ravel())) for v in pair]], names=["id", "leaf_ord", "phi", "sq"])

    sums = saved(laid.select("id", "leaf_ord", "vec").mapInArrow(summarise, "id long, leaf_ord int, phi array<double>, sq array<double>"), f"{path}/summaries")
    delete(spark, f"{path}/input")
    nodes_table(spark, trees).repartition("block").write.partitionBy("block").parquet(f"{path}/nodes")
    index = Index(gen, blocks, d, n, trees, laid, sums, page_bytes, path, mean, model, lead)
    _write_manifest(spark, index, path, before)
    return index


def _write_manifest(spark: SparkSession, index: Index, path: str, before: list[int] | None) -> None:
    """Last of all: where it is, the index is whole."""
    facts = {"generator": index.gen.name, "weights": index.gen.weights, "d": index.d, "n": index.n, "blocks": index.blocks, "lead": index.lead, "page_bytes": index.page_bytes, "before": before}
    facts |= {"centre": None if index.centre is None else index.centre.tolist(), "model": index.model and index.model.as_dict()}
    given(spark, value=[json.dumps(facts)]).coalesce(1).write.text(f"{path}/manifest")


def save_index(index: Index, path: str) -> None:
    """Write all of an index, also one that appends and removals have changed."""
    spark = index.points.sparkSession
    index.points.select("id", "vec", "leaves", "leaf_ord", "page", "slot").write.mode("overwrite").parquet(f"{path}/points")
    index.summaries.write.mode("overwrite").parquet(f"{path}/summaries")
    nodes_table(spark, index.trees).repartition("block").write.mode("overwrite").partitionBy("block").parquet(f"{path}/nodes")
    _write_manifest(spark, index, path, None)


def load_index(spark: SparkSession, path: str, gen: Generator | None = None) -> Index:
    """Read an index back. Generators with parameters are given again."""
    m = json.loads(spark.read.text(f"{path}/manifest").first()["value"])
    if gen is None:
        gen = generators.mahalanobis(m["weights"]) if m["weights"] else generators.get(m["generator"])
    rows: dict[int, list] = {}
    for r in spark.read.parquet(f"{path}/nodes").orderBy("block", "node").collect():
        rows.setdefault(r["block"], []).append(r)
    col = lambda j, c: np.array([r[c] for r in rows[j]])
    trees = [BallTree(b, col(j, "centre"), col(j, "left"), col(j, "right"), col(j, "depth"), col(j, "leaf"), col(j, "radius"), col(j, "n_points")) for j, b in enumerate(m["blocks"])]
    points = spark.read.parquet(f"{path}/points")
    points = points if m["before"] is None else paged(points, m["before"], max(1, m["page_bytes"] // (4 * m["d"])))
    return Index(gen, m["blocks"], m["d"], m["n"], trees, points, spark.read.parquet(f"{path}/summaries"), m["page_bytes"], path, None if m["centre"] is None else np.array(m["centre"]), m["model"] and costmodel.CostModel(**m["model"]), m["lead"])


__all__ = ["Index", "bounded_sample", "build_index", "in_leaf_order", "load_index", "nodes_table", "paged", "save_index", "width"]
