"""Exact search: bounds for all points, range searches per block, and a refinement fused with the filter."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from divknn.functions.generators import Generator, divergence
from divknn.operators.balltree import tree_range
from divknn.operators.index import Index
from divknn.operators.summaries import lowest_totals
from divknn.operators.vectors import PAIRS, PARTIAL, QUERY_NUMBERS, ROWS, SHARE, TILE, LocalTop, best_k, block_size, broadcast_parts, check_k, each_block, empty, given, matrix_of, sub_batches, union_of
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def block_range(points: DataFrame, queries: DataFrame, gen: Generator, dims: list[int]) -> DataFrame:
    """(qid, id, divergence) within ``radius`` of each query in one block; queries: (qid, yvec, radius)."""
    cut = "transform(array(" + ",".join(map(str, dims)) + "), i -> {v}[i])"
    x = points.select("id", F.expr(cut.format(v="vec")).alias("x"))
    y = queries.select("qid", "radius", F.expr(cut.format(v="yvec")).alias("y"))
    pairs = union_of([x.join(q, divergence(gen, "x", "y") <= F.col("radius") + 1e-9 * (1 + F.abs("radius"))) for q in broadcast_parts(y, len(dims))])
    return pairs.select("qid", "id", divergence(gen, "x", "y").alias("divergence"))


def query_budgets(index: Index, qids: np.ndarray, y: np.ndarray, k: int, tighten: bool = False, exclude_self: bool = False, sample: float | None = None) -> dict:
    """Block budgets of each query, from the point of k-th smallest whole bound; one row a query reaches the driver.

    ``tighten``: the k points of smallest bounds are measured exactly; budgets shrink so that they add up to the largest.
    """
    which, sums = index.which(), index.summaries
    if sample is not None:
        part = sums.where(F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < int(sample * 1_000_000))
        sums = part if part.limit(k + exclude_self).count() > k else sums
    top = lowest_totals(sums, which, qids, y, k, exclude_self)
    q = which.queries(y)
    place = {int(v): i for i, v in enumerate(qids)}
    out = {"r": np.full((len(qids), index.m), np.inf), "pivot": np.full(len(qids), -1), "total": np.full(len(qids), np.inf), "kappa": np.zeros(len(qids)), "sq": np.zeros(len(qids)), "roots": np.zeros((len(qids), index.m))}
    # The last of the k rows meets its summary again; a query with fewer points than k keeps everything.
    last = top.where(F.col("rank") == k)
    if tighten:
        top = top.cache()
    for r in sums.join(F.broadcast(last.select("qid", "id", "total")), "id").select("qid", "id", "total", "phi", "sq").collect():  # one row a query
        i = place[r["qid"]]
        phi, sq = np.array(r["phi"])[None, :], np.array(r["sq"])[None, :]
        own = which.bounds(phi, sq, tuple(v[i : i + 1] for v in q))[0, 0]
        if out["pivot"][i] >= 0 and own.sum() <= out["r"][i].sum():
            continue  # of points that share an id the farthest bounds all
        out["r"][i] = own
        out["pivot"][i], out["total"][i], out["sq"][i] = r["id"], r["total"], sq.sum()
        out["roots"][i] = np.sqrt(sq[0] * q[2][i])
        out["kappa"][i] = phi.sum() + (q[0][i] + q[1][i]).sum()
    if tighten:
        seeds = top.select("qid", "id").join(index.points.select("id", "vec"), "id")
        worst: dict[int, float] = {}
        gen = index.gen
        for r in seeds.select("qid", "vec").toLocalIterator():  # k rows a query
            i = place[r["qid"]]
            worst[i] = max(worst.get(i, 0.0), float(gen.divergence(np.array(r["vec"]), y[i])))
        for i, w in worst.items():
            if np.isfinite(out["total"][i]) and w < out["total"][i]:
                out["r"][i] *= w / out["total"][i]  # any budgets with this sum keep every neighbour
        top.unpersist()
    return out


class Reach:
    """Leaves that the budgets of a block of queries reach, as bits; ``every`` marks queries that some block lets reach all."""

    def __init__(self, bits: list[np.ndarray], leaves: list[int], looked: int, every: np.ndarray):
        self.bits, self.leaves, self.looked, self.every = bits, leaves, looked, every

    def masks(self) -> list[np.ndarray]:
        """Per block a (queries, leaves) mask."""
        return [np.unpackbits(b, axis=1, count=n).view(bool) for b, n in zip(self.bits, self.leaves, strict=True)]

    def touched(self) -> np.ndarray:
        return sum(m.sum(1) for m in self.masks())


def touched_leaves(index: Index, y: np.ndarray, r: np.ndarray) -> Reach:
    """The ball tests of a block of queries against all trees, a task for each tree and part of the queries."""
    spark, gen = index.points.sparkSession, index.gen
    cuts = np.array_split(np.arange(len(y)), max(1, min(len(y), -(-2 * spark.sparkContext.defaultParallelism // max(1, index.m)))))
    rows = [(j, i, pickle.dumps((t, y[rows][:, t.dims], np.minimum(r[rows, j], 1e300)))) for j, t in enumerate(index.trees) for i, rows in enumerate(cuts)]

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for j, i, held in zip(*(batch.column(c).to_pylist() for c in ("block", "part", "held")), strict=True):
                tree, own, radius = pickle.loads(held)
                hit, looked = tree_range(tree, gen, own, radius)
                full = tree.count[tree.leaf_nodes()] > 0
                yield pa.RecordBatch.from_arrays([pa.array([j]), pa.array([i]), pa.array([looked]), pa.array([np.packbits(hit, axis=1).tobytes()]), pa.array([np.packbits(hit[:, full].all(1)).tobytes()])], names=["block", "part", "looked", "bits", "every"])

    asked = given(spark, block=[r[0] for r in rows], part=[r[1] for r in rows], held=[r[2] for r in rows]).repartition(len(rows), "block", "part")
    found = {(f["block"], f["part"]): f for f in asked.mapInArrow(test, "block long, part long, looked long, bits binary, every binary").collect()}  # bits of a checked number
    bits = [np.concatenate([np.frombuffer(found[j, i]["bits"], np.uint8).reshape(len(rows), -(-t.leaves // 8)) for i, rows in enumerate(cuts)]) for j, t in enumerate(index.trees)]
    every = np.concatenate([np.any([np.unpackbits(np.frombuffer(found[j, i]["every"], np.uint8), count=len(rows)).view(bool) for j in range(index.m)], axis=0) for i, rows in enumerate(cuts)])
    return Reach(bits, [t.leaves for t in index.trees], sum(f["looked"] for f in found.values()), every)


#: From this share of the points on that a budget surely reaches, looking for the rest costs more than measuring it.
MOST = 0.5


def reach_most(index: Index, y: np.ndarray, r: np.ndarray) -> np.ndarray:
    """Queries whose budget in some block reaches ``MOST`` of the points, told by the leaves' centres alone: a centre lies in its ball.

    One matrix product a block in place of a ball test a leaf. False says nothing: ball tests then decide.
    """
    gen, blocks, held, sizes = index.gen, index.blocks, [], []
    for t in index.trees:
        nodes = t.leaf_nodes()
        nodes = nodes[t.count[nodes] > 0]
        held.append(t.centre[nodes])
        sizes.append(t.count[nodes].astype(float))
    most = MOST * index.n
    cuts = np.array_split(np.arange(len(y)), max(1, min(len(y), 2 * index.points.sparkSession.sparkContext.defaultParallelism)))

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, own in zip(batch.column("part").to_pylist(), batch.column("held").to_pylist(), strict=True):
                yy, rr = pickle.loads(own)
                found = np.zeros(len(yy), bool)
                for j, b in enumerate(blocks):
                    for lo in range(0, len(yy), TILE):
                        rest = lo + np.flatnonzero(~found[lo : lo + TILE])
                        if len(rest):
                            found[rest] = sizes[j] @ (gen.matrix(held[j], yy[rest][:, b]) <= rr[rest, j]) >= most
                yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([np.packbits(found).tobytes()])], names=["part", "found"])

    rows = [(i, pickle.dumps((y[own], r[own]))) for i, own in enumerate(cuts)]
    asked = given(index.points.sparkSession, part=[r[0] for r in rows], held=[r[1] for r in rows]).repartition(len(rows), "part")
    out = np.zeros(len(y), bool)
    for f in asked.mapInArrow(test, "part long, found binary").collect():  # a bit a query
        out[cuts[f["part"]]] = np.unpackbits(np.frombuffer(f["found"], np.uint8), count=len(cuts[f["part"]])).view(bool)
    return out


def held_by(index: Index) -> int:
    """Numbers that a search holds for a query besides its vector."""
    return sum(t.leaves for t in index.trees) // 8 + 4 * index.m


def _mask(blocks: list[list[int]], gen: Generator, x: np.ndarray, leaves: np.ndarray, y: np.ndarray, hits: list[np.ndarray], every: np.ndarray, r: np.ndarray, granularity: str) -> np.ndarray:
    """(rows, queries): whether some block keeps the pair."""
    keep = np.zeros((len(x), len(y)), bool)
    if granularity == "leaf":
        keep[:, every] = True
    rest = np.arange(len(y)) if granularity == "point" else np.flatnonzero(~every)
    if not len(rest):
        return keep
    some = np.zeros((len(x), len(rest)), bool)
    for j, b in enumerate(blocks):
        near = hits[j].T[leaves[:, j]][:, rest]
        if granularity == "point":
            near &= gen.matrix(x[:, b], y[:, b]) <= r[:, j] + 1e-9 * (1 + np.abs(r[:, j]))
        some |= near
    keep[:, rest] = some
    return keep


def candidates(index: Index, qids: np.ndarray, y: np.ndarray, r: np.ndarray, granularity: str = "leaf") -> DataFrame:
    """(qid, id, page) of every candidate: each point decides by its own leaves, so nothing is shuffled to unite the blocks."""
    reach = touched_leaves(index, y, r)
    gen, blocks = index.gen, index.blocks

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = reach.masks()
        for b in sub_batches(batches):
            row, q = np.nonzero(_mask(blocks, gen, matrix_of(b.column("vec")), matrix_of(b.column("leaves")), y, hits, reach.every, r, granularity))
            yield pa.RecordBatch.from_arrays([pa.array(qids[q]), b.column("id").take(pa.array(row)), b.column("page").take(pa.array(row))], names=["qid", "id", "page"])

    return index.points.select("id", "vec", "leaves", "page").mapInArrow(pick, "qid long, id long, page long")


def candidate_pages(index: Index, qids: np.ndarray, y: np.ndarray, r: np.ndarray, granularity: str = "leaf") -> DataFrame:
    """(qid, page, n): the candidates on a page, counted where they lie; a page that two batches share comes twice."""
    reach = touched_leaves(index, y, r)
    gen, blocks = index.gen, index.blocks

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = reach.masks()
        for b in sub_batches(batches):
            keep = _mask(blocks, gen, matrix_of(b.column("vec")), matrix_of(b.column("leaves")), y, hits, reach.every, r, granularity)
            page = b.column("page").to_numpy()
            order = np.argsort(page, kind="stable")
            first = np.flatnonzero(np.concatenate(([True], page[order][1:] != page[order][:-1])))
            n = np.add.reduceat(keep[order], first, axis=0, dtype=np.int64)
            at, q = np.nonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(qids[q]), pa.array(page[order][first][at]), pa.array(n[at, q])], names=["qid", "page", "n"])

    return index.points.select("vec", "leaves", "page").mapInArrow(tally, "qid long, page long, n long")


#: Points from which on a share of them bounds the k-th divergences before all are looked at.
MANY = 1 << 15


def first_limits(index: Index, qids: np.ndarray, y: np.ndarray, k: int, exclude_self: bool) -> np.ndarray:
    """Upper bounds of the k-th smallest divergences: those among one point in ``SHARE``."""
    gen = index.gen

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = LocalTop(gen, qids, y, k, exclude_self)
        for b in sub_batches(batches):
            top.add(b.column("id").to_numpy(), matrix_of(b.column("vec")))
        yield top.rows()

    some = index.points.where(F.pmod(F.xxhash64("id"), F.lit(SHARE)) == 0).select("id", "vec").mapInArrow(scan, PARTIAL)
    out, place = np.full(len(qids), np.inf), {int(v): i for i, v in enumerate(qids)}
    for r in best_k(some, k).where(F.col("rank") == k).select("qid", "divergence").collect():  # one row a query
        out[place[r["qid"]]] = r["divergence"]
    return out


def refine_within(index: Index, qids: np.ndarray, y: np.ndarray, r: np.ndarray, k: int, granularity: str, exclude_self: bool, exact: bool = False) -> DataFrame:
    """Filter and exact distances in one pass over the points: k rows a task and query leave it.

    ``exact``: the budgets keep all k neighbours, so that points farther than the k-th of any part need not be measured.
    """
    limit = first_limits(index, qids, y, k, exclude_self) if exact and index.n >= MANY else np.full(len(qids), np.inf)
    if granularity == "point":
        return _refine(index, qids, y, r, k, granularity, exclude_self, limit)
    whole = reach_most(index, y, r)
    parts = [_scan_all(index, qids[whole], y[whole], k, exclude_self, limit[whole])] if whole.any() else []
    rest, step = np.flatnonzero(~whole), max(1, QUERY_NUMBERS // (index.d + ROWS + held_by(index)))
    for lo in range(0, len(rest), step):
        own = rest[lo : lo + step]
        parts.append(_refine(index, qids[own], y[own], r[own], k, granularity, exclude_self, limit[own]))
    return union_of(parts)


def _scan_all(index: Index, qids: np.ndarray, y: np.ndarray, k: int, exclude_self: bool, limit: np.ndarray) -> DataFrame:
    """Queries to which all or most points are candidates: all are measured."""
    gen = index.gen

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = LocalTop(gen, qids, y, k, exclude_self, limit)
        for b in sub_batches(batches):
            top.add(b.column("id").to_numpy(), matrix_of(b.column("vec")))
        yield top.rows()

    return index.points.select("id", "vec").mapInArrow(scan, PARTIAL)


def _refine(index: Index, qids: np.ndarray, y: np.ndarray, r: np.ndarray, k: int, granularity: str, exclude_self: bool, limit: np.ndarray) -> DataFrame:
    reach = touched_leaves(index, y, r)
    gen, blocks = index.gen, index.blocks

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top, hits = LocalTop(gen, qids, y, k, exclude_self, limit), reach.masks()
        for b in sub_batches(batches):
            x = matrix_of(b.column("vec"))
            keep = _mask(blocks, gen, x, matrix_of(b.column("leaves")), y, hits, reach.every, r, granularity)
            rows = np.flatnonzero(keep.any(1))
            if len(rows):
                top.add(b.column("id").to_numpy()[rows], x[rows], keep[rows])
        yield top.rows()

    return index.points.select("id", "vec", "leaves").mapInArrow(scan, PARTIAL)


def exact_knn(index: Index, queries: DataFrame, k: int, granularity: str = "leaf", tighten: bool = False, exclude_self: bool = False, sample: float | None = None) -> DataFrame:
    """(qid, rank, id, divergence) of the k nearest points; ties by the smaller id."""
    check_k(k)

    def work(qids: np.ndarray, y: np.ndarray) -> DataFrame:
        r = query_budgets(index, qids, y, k, tighten, exclude_self, sample)["r"]
        return refine_within(index, qids, y, r, k, granularity, exclude_self, True)

    # Bits of leaves are held for those queries alone that some leaf is out of reach of, in blocks of their own.
    found = each_block(index.gen.prepared(queries, "yvec"), index.d, work, held_by(index) if granularity == "point" else 4 * index.m)
    return best_k(found if found is not None else empty(queries, PARTIAL), k)


def _within(gen: Generator, x: np.ndarray, y: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows, queries): divergences of x from y, and whether they are within r; close calls are measured in difference form."""
    dist = gen.pairs(x, y)
    row, q = np.nonzero(np.abs(dist - r) <= 1e-9 * (1 + np.abs(r)))
    for lo in range(0, len(row), 1 << 14):
        i, j = row[lo : lo + (1 << 14)], q[lo : lo + (1 << 14)]
        dist[i, j] = gen.divergence(x[i], y[j])
    return dist, dist <= r


class Sides:
    """Points that are measured both ways: ``a.asking @ b.asked.T`` are the divergences of b's points from a's."""

    def __init__(self, gen: Generator, ids: np.ndarray, leaf: np.ndarray, x: np.ndarray):
        g, phi, one = gen.grad(x), gen.phi(x), np.ones((len(x), 1))
        self.ids, self.leaf, self.x = ids, leaf, x
        self.asked = np.concatenate((x, phi.sum(1)[:, None], one), axis=1)
        self.asking = np.concatenate((-g, one, ((g * x).sum(1) - phi.sum(1))[:, None]), axis=1)
        self.size = np.abs(phi).sum(1) + np.abs(g * x).sum(1)  # what the products cancel to small divergences

    def some(self, rows: np.ndarray) -> Sides:
        out = object.__new__(Sides)
        for name, v in vars(self).items():
            setattr(out, name, v[rows])
        return out


def _within_either(gen: Generator, a: Sides, b: Sides, r: float, allowed: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of a, row of b, the smaller divergence) of the pairs within r in either direction; ``allowed``: (a, b) mask of the pairs to consider.

    As in ``pairs``, small divergences and close calls are measured in difference form.
    """
    most = a.size.max() + b.size.max()
    slack = 1e-9 * (1 + abs(r)) + 1e-13 * most
    low = a.asking @ b.asked.T
    np.fmin(low, a.asked @ b.asking.T, out=low)
    near = low <= r + slack
    if allowed is not None:
        near &= allowed
    at, each = np.flatnonzero(near), np.count_nonzero(near, axis=1)
    value, i = low.ravel()[at], np.repeat(np.arange(len(each)), each)
    j = at - i * near.shape[1]
    rough = np.flatnonzero((value <= 1e-6 * most) | (value >= r - slack))
    if len(rough):
        rough = rough[(value[rough] <= 1e-6 * (a.size[i[rough]] + b.size[j[rough]])) | (value[rough] >= r - slack)]
        for lo in range(0, len(rough), 1 << 14):
            own = rough[lo : lo + (1 << 14)]
            x, y = a.x[i[own]], b.x[j[own]]
            value[own] = np.fmin(gen.divergence(x, y), gen.divergence(y, x))
        keep = value <= r
        if not keep.all():
            i, j, value = i[keep], j[keep], value[keep]
    return i, j, value


def leaf_pairs(index: Index, r: float) -> np.ndarray:
    """(leaves, leaves) of the lead block's tree: whether a point of the one leaf reaches the other's ball, in either direction.

    The points ask where they lie. Matrix products tell what is surely reached, by its centre or as the point lies in the
    ball; ball tests decide the leaves that no point of a leaf is told to reach.
    """
    tree, gen, r = index.trees[index.lead], index.gen, min(r, 1e300)
    nodes = tree.leaf_nodes()
    full = tree.count[nodes] > 0
    centre, radius = tree.centre[nodes[full]], tree.radius[nodes[full]]
    step = max(1, PAIRS // tree.leaves)  # a bounded number of ball tests at once

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, seen = np.zeros((tree.leaves, tree.leaves), bool), np.zeros(tree.leaves, bool)
        found[:, ~full] = True  # nothing to look for
        for b in sub_batches(batches):
            leaf, x = b.column("leaf_ord").to_numpy(), matrix_of(b.column("vec"))
            order = np.argsort(leaf, kind="stable")
            leaf, x = leaf[order], x[order][:, tree.dims]
            sure = (gen.matrix(x, centre) <= radius) | (gen.matrix(centre, x).T <= r)
            first = np.flatnonzero(np.concatenate(([True], leaf[1:] != leaf[:-1])))
            own = leaf[first]
            seen[own] = True
            found[np.ix_(own, full)] |= np.logical_or.reduceat(sure, first, axis=0)
            rest = np.flatnonzero(~found[leaf].all(1))
            rest = rest[np.argsort((np.arange(len(leaf)) - np.repeat(first, np.diff([*first, len(leaf)])))[rest], kind="stable")]  # what a leaf's first points find the others need not
            for lo in range(0, len(rest), step):
                wanted = ~found[leaf[rest[lo : lo + step]]]
                some = wanted.any(1)
                rows = rest[lo : lo + step][some]
                if len(rows):
                    hit, _ = tree_range(tree, gen, x[rows], np.full(len(rows), r), wanted[some])
                    np.logical_or.at(found, leaf[rows], hit)
        found[:, ~full] = False
        own = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(own), pa.array([v.tobytes() for v in np.packbits(found[own], axis=1)], pa.binary())], names=["leaf", "bits"])

    out = np.zeros((tree.leaves, -(-tree.leaves // 8)), np.uint8)
    for f in index.points.select("vec", "leaf_ord").mapInArrow(ask, "leaf long, bits binary").collect():  # bits of a leaf, twice where two tasks share it
        out[f["leaf"]] |= np.frombuffer(f["bits"], np.uint8)
    out = np.unpackbits(out, axis=1, count=tree.leaves).view(bool)
    return out | out.T


def _leaf_order(index: Index, most: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(ids, leaves, vectors) of all points by (leaf, id), so many at once; they come to the driver as bytes."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sub_batches(batches):
            held = [b.column("id").to_numpy(), b.column("leaf_ord").to_numpy(), matrix_of(b.column("vec"))]
            yield pa.RecordBatch.from_arrays([pa.array([v.tobytes()], pa.binary()) for v in held], names=["id", "leaf", "vec"])

    ordered = index.points.select("id", "leaf_ord", "vec").orderBy("leaf_ord", "id")
    held: list[tuple] = []
    for p in ordered.mapInArrow(pack, "id binary, leaf binary, vec binary").toLocalIterator():
        held.append((np.frombuffer(p["id"], np.int64), np.frombuffer(p["leaf"], np.int32), np.frombuffer(p["vec"]).reshape(-1, index.d)))
        if sum(len(h[0]) for h in held) >= most:
            whole = [np.concatenate(c) for c in zip(*held, strict=True)]
            ends = range(most, len(whole[0]) + 1, most)
            for end in ends:
                yield tuple(v[end - most : end] for v in whole)
            held = [tuple(v[ends[-1] :] for v in whole)]
    if sum(len(h[0]) for h in held):
        yield tuple(np.concatenate(c) for c in zip(*held, strict=True))


def _pairs_once(index: Index, r: float, digits: int | None) -> DataFrame:
    """A block of points in leaf order meets the points after it: a pair is looked at once, both ways, if its leaves reach each other."""
    gen, reach, parts = index.gen, leaf_pairs(index, r), []
    for ids, leaf, x in _leaf_order(index, block_size(index.d, index.trees[index.lead].leaves // 8)):
        cuts = [slice(lo, lo + TILE) for lo in range(0, len(ids), TILE)]
        bits = np.stack([np.packbits(reach[np.unique(leaf[c])].any(0)) for c in cuts])

        def scan(batches: Iterator[pa.RecordBatch], ids=ids, leaf=leaf, x=x, cuts=cuts, bits=bits) -> Iterator[pa.RecordBatch]:
            tiles = [(Sides(gen, ids[c], leaf[c], x[c]), np.unpackbits(v).view(bool)) for c, v in zip(cuts, bits, strict=True)]
            wait: list[tuple] = []

            def told() -> pa.RecordBatch:
                one, two, value = (np.concatenate(c) for c in zip(*wait, strict=True))
                wait.clear()
                value = value if digits is None else np.round(value, digits)
                return pa.RecordBatch.from_arrays([pa.array(np.minimum(one, two)), pa.array(np.maximum(one, two)), pa.array(value + 0.0)], names=["qid", "id", "divergence"])

            for b in sub_batches(batches, TILE):
                all_rows = Sides(gen, b.column("id").to_numpy(), b.column("leaf_ord").to_numpy(), matrix_of(b.column("vec")))
                for tile, open_ in tiles:
                    rows = open_[all_rows.leaf] & (all_rows.leaf >= tile.leaf[0])
                    if not rows.any():
                        continue
                    own, after = all_rows if rows.all() else all_rows.some(rows), None
                    if own.leaf.min() <= tile.leaf[-1]:
                        after = (own.leaf > tile.leaf[:, None]) | (own.leaf == tile.leaf[:, None]) & (own.ids > tile.ids[:, None])
                    i, j, value = _within_either(gen, tile, own, r, after)
                    if len(i):
                        wait.append((tile.ids[i], own.ids[j], value))
                    if sum(len(w[0]) for w in wait) >= PAIRS // 4:
                        yield told()
            if wait:
                yield told()

        later = index.points.where(F.col("leaf_ord") >= int(leaf[0]))  # the files are in the order of the leaves
        parts.append(later.select("id", "vec", "leaf_ord").mapInArrow(scan, PARTIAL))
    return union_of(parts)


def range_search(index: Index, queries: DataFrame, granularity: str = "leaf", once: bool = False, digits: int | None = None) -> DataFrame:
    """(qid, id, divergence) of all points within each query's radius; queries: (qid, yvec, radius). One whole-space tree serves best.

    ``once``, where all points of the index ask with one radius: a pair is given once, qid < id, with the smaller
    divergence; ``digits`` rounds it in the tasks.
    """
    if once:
        asked = queries.agg(F.count("*").alias("n"), F.min("radius").alias("least"), F.max("radius").alias("most")).first()
        if asked["n"] != index.n or asked["least"] != asked["most"]:
            raise ValueError("all points of the index must ask, with one radius")
        return _pairs_once(index, float(asked["most"]), digits)

    def work(qids: np.ndarray, y: np.ndarray) -> DataFrame:
        r, y = y[:, -1], y[:, :-1]  # the radius travels as a last coordinate
        budget = np.repeat(r[:, None], index.m, axis=1)  # a point within r is within r in every block
        reach = touched_leaves(index, y, budget)
        gen = index.gen

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            hits = reach.masks()
            for b in sub_batches(batches, max(1, 4 * PAIRS // len(y))):  # a bounded number of pairs at once
                ids, x, leaves = b.column("id").to_numpy(), matrix_of(b.column("vec")), matrix_of(b.column("leaves"))
                dist, near = _within(gen, x, y, r)
                for j in range(len(hits)):
                    near &= hits[j].T[leaves[:, j]]
                row, q = np.nonzero(near)
                yield pa.RecordBatch.from_arrays([pa.array(qids[q]), pa.array(ids[row]), pa.array(dist[row, q])], names=["qid", "id", "divergence"])

        return index.points.select("id", "vec", "leaves").mapInArrow(scan, PARTIAL)

    asked = queries.select("qid", F.concat("yvec", F.array(F.col("radius").cast("double"))).alias("yvec"))
    found = each_block(asked, index.d + 1, work, held_by(index))
    return found if found is not None else empty(queries, PARTIAL)


def blockwise_knn_union(points: DataFrame, queries: DataFrame, gen: Generator, blocks: list[list[int]], k: int) -> DataFrame:
    """Union of the k nearest of each block, refined: NOT exact, kept to show why range searches are needed."""
    from divknn.operators.vectors import scan_knn

    out = None
    for b in blocks:
        cut = lambda c, b=b: F.array(*[F.col(c)[i] for i in b])
        own = scan_knn(points.select("id", cut("vec").alias("vec")), queries.select("qid", cut("yvec").alias("yvec")), gen, k).select("qid", "id")
        out = own if out is None else out.unionByName(own)
    near = out.distinct().join(points, "id").join(queries, "qid")
    return best_k(near.select("qid", "id", divergence(gen, "vec", "yvec").alias("divergence")), k)
