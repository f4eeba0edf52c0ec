"""Methods to compare with: a scan of quantised cells, a whole-space ball tree, and a distribution-guided tree."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from divknn.functions.generators import Generator
from divknn.operators.approx import dimension_stats
from divknn.operators.balltree import nearest_in_ball
from divknn.operators.index import Index, build_index, on_sample
from divknn.operators.vectors import PARTIAL, LocalTop, best_k, check_k, each_block, empty, given, matrix_of, sub_batches, width
from divknn.plans.partition import contiguous_blocks
from divknn.storage import delete, shared_dir
from divknn.storage import saved_vectors as saved
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

# Cell scan.


@dataclass
class CellIndex:
    gen: Generator
    d: int
    n: int
    edges: np.ndarray  # (d, cells + 1); outer edges hold all points
    codes: DataFrame  # id, code
    points: DataFrame  # id, code, vec
    page_bytes: int
    path: str

    @property
    def bits(self) -> int:
        return int(np.ceil(np.log2(self.edges.shape[1] - 1)))

    def index_pages(self) -> int:
        """Every search reads all codes."""
        return -(-self.n * self.d * self.bits // 8 // self.page_bytes)


def build_cells(points: DataFrame, gen: Generator, bits: int = 6, edges: str = "quantile", page_bytes: int = 32 << 10, stored: bool = False) -> CellIndex:
    """Codes of ``bits`` bits a dimension; inner edges from a bounded sample, outer ones from all points. ``stored``: as for an index."""
    spark, path = points.sparkSession, shared_dir(points.sparkSession)
    points = gen.prepared(points).select("id", "vec")
    if not stored or gen.weights:
        points = saved(points, f"{path}/input")  # several passes follow
    d = width(points)
    ends = dimension_stats(points)
    n, cells = (ends[0]["n"] if ends else 0), 1 << bits
    if not n:
        raise ValueError("cells need points")
    lo, hi = np.array([r["lo"] for r in ends]), np.array([r["hi"] for r in ends])
    if edges == "quantile":
        runs = contiguous_blocks(d, -(-d // 16))
        inner = np.concatenate([np.frombuffer(v).reshape(-1, cells - 1) for v in on_sample(points, n, runs, lambda _, x: np.ascontiguousarray(np.quantile(x, np.arange(1, cells) / cells, axis=0).T).tobytes())])
    else:
        inner = lo[:, None] + (hi - lo)[:, None] * np.arange(1, cells) / cells
    grid = np.concatenate((lo[:, None], np.clip(inner, lo[:, None], hi[:, None]), hi[:, None]), axis=1)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sub_batches(batches):
            x = matrix_of(b.column("vec"))
            code = np.stack([np.searchsorted(grid[i, 1:-1], x[:, i], "right") for i in range(d)], axis=1).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([r.tobytes() for r in code], pa.binary()), b.column("vec")], names=["id", "code", "vec"])

    laid = saved(points.mapInArrow(encode, "id long, code binary, vec array<double>"), f"{path}/cells")  # a scan of codes reads their column only
    delete(spark, f"{path}/input")
    return CellIndex(gen, d, n, grid, laid.select("id", "code"), laid, page_bytes, path)


def _cell_tables(gen: Generator, grid: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(d, cells, q) least and most of a coordinate's divergence in a cell: convex in x with its least at y."""
    one = lambda x, v: np.maximum(gen.phi(x) - gen.phi(v) - gen.grad(v) * (x - v), 0)
    left, right = grid[:, :-1, None], grid[:, 1:, None]
    v = y.T[:, None, :]
    a, b = one(left, v), one(right, v)
    inside = (left <= v) & (v <= right)
    slack = 1e-12 * (1 + np.abs(gen.phi(v)))
    return np.where(inside, 0, np.maximum(np.minimum(a, b) - slack, 0)), np.maximum(a, b) + slack


#: Bounds added up at once: what a core's cache holds.
CHUNK = 1 << 17


def cell_bound(codes: np.ndarray, table: np.ndarray) -> np.ndarray:
    """(rows, queries) of one of the tables: every dimension's value of the row's cell, added up."""
    out = np.zeros((len(codes), table.shape[2]))
    step = max(1, CHUNK // max(1, table.shape[2]))
    own = np.empty((step, table.shape[2]))
    for lo in range(0, len(codes), step):
        part, some = out[lo : lo + step], codes[lo : lo + step]
        for i in range(codes.shape[1]):
            part += np.take(table[i], some[:, i], axis=0, out=own[: len(some)], mode="clip")
    return out


def _decode(b: pa.RecordBatch, d: int) -> np.ndarray:
    return np.frombuffer(b"".join(b.column("code").to_pylist()), np.uint8).reshape(-1, d)


def _cell_limits(cells: CellIndex, qids: np.ndarray, y: np.ndarray, k: int, exclude_self: bool) -> np.ndarray:
    """The k-th smallest most bound of each query."""
    gen, grid, d = cells.gen, cells.edges, cells.d

    def tops(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        most, best = _cell_tables(gen, grid, y)[1], np.full((k, len(qids)), np.inf)
        for b in sub_batches(batches):
            high = cell_bound(_decode(b, d), most)
            if exclude_self:
                high[b.column("id").to_numpy()[:, None] == qids[None, :]] = np.inf
            better = np.flatnonzero((high < best.max(0)).any(0))
            if len(better):
                best[:, better] = np.partition(np.concatenate((best[:, better], high[:, better])), k - 1, axis=0)[:k]
        yield pa.RecordBatch.from_arrays([pa.array(np.tile(qids, k)), pa.array(best.ravel())], names=["qid", "high"])

    w = Window.partitionBy("qid").orderBy("high")
    kth = cells.codes.mapInArrow(tops, "qid long, high double").withColumn("rank", F.row_number().over(w)).where(F.col("rank") == k)
    limits = {r["qid"]: r["high"] for r in kth.collect()}  # one row a query
    return np.array([limits.get(int(q), np.inf) for q in qids])


def cell_candidates(cells: CellIndex, qids: np.ndarray, y: np.ndarray, k: int, exclude_self: bool = False) -> DataFrame:
    """(qid, id) that the bounds cannot rule out: least bound within the k-th smallest most bound."""
    gen, grid, d, limit = cells.gen, cells.edges, cells.d, _cell_limits(cells, qids, y, k, exclude_self)

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        least = _cell_tables(gen, grid, y)[0]
        for b in sub_batches(batches):
            row, q = np.nonzero(cell_bound(_decode(b, d), least) <= limit)
            yield pa.RecordBatch.from_arrays([pa.array(qids[q]), b.column("id").take(pa.array(row))], names=["qid", "id"])

    return cells.codes.mapInArrow(pick, "qid long, id long")


def cell_knn(cells: CellIndex, queries: DataFrame, k: int, exclude_self: bool = False) -> DataFrame:
    """Exact: scan all codes for the limits, then measure what the bounds allow where it lies: k rows a task and query leave the second scan."""
    check_k(k)
    gen, grid, d = cells.gen, cells.edges, cells.d

    def work(qids: np.ndarray, y: np.ndarray) -> DataFrame:
        limit = _cell_limits(cells, qids, y, k, exclude_self)

        def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            least, top = _cell_tables(gen, grid, y)[0], LocalTop(gen, qids, y, k, exclude_self)
            for b in sub_batches(batches):
                keep = cell_bound(_decode(b, d), least) <= limit
                rows = np.flatnonzero(keep.any(1))
                if len(rows):
                    top.add(b.column("id").to_numpy()[rows], matrix_of(b.column("vec"))[rows], keep[rows])
            yield top.rows()

        return cells.points.select("id", "code", "vec").mapInArrow(measure, PARTIAL)

    queries = gen.prepared(queries, "yvec")
    found = each_block(queries, d, work, 2 * d << cells.bits)
    return best_k(found if found is not None else empty(queries, PARTIAL), k)


# Whole-space trees.


def build_whole_tree(points: DataFrame, gen: Generator, leaf_size: int = 64, seed: int = 42, page_bytes: int = 32 << 10, stored: bool = False) -> Index:
    """One ball tree over all dimensions, stored as the forest is."""
    return build_index(points, gen, 1, "contiguous", seed, leaf_size, page_bytes=page_bytes, path=shared_dir(points.sparkSession), stored=stored)


@dataclass
class Visits:
    """What a tree search looked at: leaves of each query, and rounds."""

    seen: np.ndarray  # (queries, leaves)
    rounds: int

    @property
    def leaves(self) -> np.ndarray:
        return self.seen.sum(1)


def _leaf_bounds(index: Index, y: np.ndarray) -> np.ndarray:
    """(queries, leaves) lower bounds of the divergence of a leaf's points, in tasks; empty leaves are out of reach."""
    spark, tree, gen = index.points.sparkSession, index.trees[0], index.gen
    nodes = tree.leaf_nodes()
    own = tree.count[nodes] > 0
    centre, radius = tree.centre[nodes[own]][:, np.argsort(tree.dims)], tree.radius[nodes[own]]
    cuts = np.array_split(np.arange(len(y)), min(len(y), 2 * spark.sparkContext.defaultParallelism))

    def bound(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, held in zip(batch.column("part").to_pylist(), batch.column("held").to_pylist(), strict=True):
                for row, one in enumerate(np.frombuffer(held).reshape(-1, y_width)):
                    low = nearest_in_ball(gen, centre, radius, np.repeat(one[None, :], len(centre), axis=0))[0]
                    yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([row]), pa.array([low.tobytes()])], names=["part", "row", "low"])

    y_width = y.shape[1]
    asked = given(spark, part=list(range(len(cuts))), held=[np.ascontiguousarray(y[rows], dtype=float).tobytes() for rows in cuts]).repartition(len(cuts), "part")
    out = np.full((len(y), len(nodes)), np.inf)
    for r in asked.mapInArrow(bound, "part long, row long, low binary").collect():  # a number for each query of the block and leaf
        out[cuts[r["part"]][r["row"]], own] = np.frombuffer(r["low"])
    return out


def _read_leaves(index: Index, qids: np.ndarray, y: np.ndarray, wanted: np.ndarray, k: int, exclude_self: bool) -> DataFrame:
    """k best of the wanted (query, leaf) pairs; the leaf column prunes the scan."""
    gen, some = index.gen, np.flatnonzero(wanted.any(0))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = LocalTop(gen, qids, y, k, exclude_self)
        for b in sub_batches(batches):
            top.add(b.column("id").to_numpy(), matrix_of(b.column("vec")), wanted.T[b.column("leaf_ord").to_numpy()])
        yield top.rows()

    lead = index.points.where(F.col("leaf_ord").isin([int(v) for v in some])) if len(some) <= 2_000 else index.points
    return best_k(lead.select("id", "vec", "leaf_ord").mapInArrow(scan, PARTIAL), k)


def tree_search(index: Index, qids: np.ndarray, y: np.ndarray, k: int, exclude_self: bool = False, first: int = 4, keep=None) -> tuple[DataFrame, Visits]:
    """Leaves in order of their lower bounds, in rounds of doubling size, until no bound is under the k-th distance.

    ``keep(query, leaves, kth)`` may rule out leaves on other grounds (then the search is approximate).
    """
    bounds = _leaf_bounds(index, y)
    order = np.argsort(bounds, axis=1, kind="stable")
    done = np.zeros(len(qids), np.int64)
    seen = np.zeros(bounds.shape, bool)
    kth = np.full(len(qids), np.inf)
    spark, rounds, step, best = index.points.sparkSession, 0, first, {int(q): [] for q in qids}
    while True:
        wanted = np.zeros(bounds.shape, bool)
        for q in range(len(qids)):
            nxt = order[q, done[q] : done[q] + step]
            nxt = nxt[bounds[q, nxt] <= kth[q] + 1e-9 * (1 + min(kth[q], 1e300))] if len(nxt) else nxt
            nxt = nxt[np.isfinite(bounds[q, nxt])]
            if keep is not None and len(nxt) and np.isfinite(kth[q]):
                nxt = nxt[keep(q, nxt, kth[q])]
            wanted[q, nxt] = True
            done[q] += step
        open_ = np.array([done[q] < bounds.shape[1] and bounds[q, order[q, done[q]]] <= kth[q] for q in range(len(qids))])
        if wanted.any():
            rounds += 1
            for r in _read_leaves(index, qids, y, wanted, k, exclude_self).collect():  # k rows a query
                best[r["qid"]].append((round(r["divergence"], 9), r["id"], r["divergence"]))
            for q, qid in enumerate(qids):
                best[int(qid)] = sorted(best[int(qid)])[:k]
                if len(best[int(qid)]) == k:
                    kth[q] = best[int(qid)][-1][2]
            seen |= wanted
        if not open_.any():
            break
        step *= 2
    rows = [(q, i + 1, b[1], b[2]) for q, own in best.items() for i, b in enumerate(own)]
    return spark.createDataFrame(rows, "qid long, rank int, id long, divergence double"), Visits(seen, rounds)


def tree_knn(index: Index, queries: DataFrame, k: int, exclude_self: bool = False) -> DataFrame:
    """Exact search by a whole-space tree (an index of one block)."""
    check_k(k)
    if index.m != 1:
        raise ValueError("tree_knn needs an index of one block")
    found = each_block(index.gen.prepared(queries, "yvec"), index.d, lambda q, y: tree_search(index, q, y, k, exclude_self)[0], 3 * index.trees[0].leaves)
    return found if found is not None else best_k(empty(queries, PARTIAL), k)


def leaf_moments(index: Index) -> tuple[np.ndarray, np.ndarray]:
    """Mean and variance of the divergence of a leaf's points to its centre."""
    tree, gen = index.trees[0], index.gen
    centre = tree.centre[tree.leaf_nodes()][:, np.argsort(tree.dims)]

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sub_batches(batches):
            leaf = b.column("leaf_ord").to_numpy()
            own = gen.divergence(matrix_of(b.column("vec")), centre[leaf])
            yield pa.RecordBatch.from_arrays([pa.array(leaf), pa.array(own)], names=["leaf", "v"])

    rows = index.points.select("vec", "leaf_ord").mapInArrow(scan, "leaf int, v double").groupBy("leaf").agg(F.avg("v").alias("m"), F.var_pop("v").alias("s")).collect()
    mean, var = np.zeros(len(centre)), np.zeros(len(centre))
    for r in rows:
        mean[r["leaf"]], var[r["leaf"]] = r["m"], r["s"] or 0.0
    return mean, var


def guided_search(index: Index, qids: np.ndarray, y: np.ndarray, k: int, p: float, exclude_self: bool = False) -> tuple[DataFrame, Visits]:
    """Skips leaves that hold a better point with a probability under 1 - p.

    The mean divergence of a leaf's points to y is that of its centre plus their mean divergence to the centre.
    """
    tree, gen = index.trees[0], index.gen
    nodes = tree.leaf_nodes()
    centre, count = tree.centre[nodes][:, np.argsort(tree.dims)], tree.count[nodes]
    mean, var = leaf_moments(index)

    def keep(q: int, leaves: np.ndarray, kth: float) -> np.ndarray:
        to_y = gen.divergence(centre[leaves], y[q])
        sd = np.sqrt(np.maximum(var[leaves] + 2 * mean[leaves] * to_y / max(1, y.shape[1]) * 2, 1e-18))
        share = np.array([NormalDist(m, s).cdf(kth) for m, s in zip(to_y + mean[leaves], sd, strict=True)])
        return 1 - (1 - np.minimum(share, 1)) ** count[leaves] >= 1 - p

    return tree_search(index, qids, y, k, exclude_self, keep=keep if p < 1 else None)


def guided_tree_knn(index: Index, queries: DataFrame, k: int, p: float, exclude_self: bool = False) -> DataFrame:
    check_k(k)
    if not 0 < p <= 1:
        raise ValueError("p must be in (0, 1]")
    found = each_block(index.gen.prepared(queries, "yvec"), index.d, lambda q, y: guided_search(index, q, y, k, p, exclude_self)[0], 3 * index.trees[0].leaves)
    return found if found is not None else best_k(empty(queries, PARTIAL), k)
