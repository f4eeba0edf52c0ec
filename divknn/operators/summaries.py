"""Two numbers a block for points, three for queries, and the bounds they give."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from divknn.functions.generators import Generator
from divknn.operators.vectors import TILE, Smallest, each_block, empty, matrix_of, sub_batches
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

Blocks = list[list[int]]


def _literal(blocks: Blocks) -> str:
    return "array(" + ",".join("array(" + ",".join(map(str, b)) + ")" for b in blocks) + ")"


def data_summary(points: DataFrame, gen: Generator, blocks: Blocks) -> DataFrame:
    """(id, psum): per block the sum of phi and the squared norm."""
    phi = gen.phi_sql.format(t="vec[i]")
    psum = f"transform({_literal(blocks)}, b -> struct(aggregate(b, 0D, (s, i) -> s + {phi}) as phi_sum, aggregate(b, 0D, (s, i) -> s + vec[i] * vec[i]) as sq_norm))"
    return points.select("id", F.expr(psum).alias("psum"))


def query_summary(queries: DataFrame, gen: Generator, blocks: Blocks) -> DataFrame:
    """(qid, qsum): per block minus the sum of phi, the product with the gradient, the gradient's squared norm."""
    phi, grad = gen.phi_sql.format(t="yvec[i]"), gen.grad_sql.format(t="yvec[i]")
    qsum = (
        f"transform({_literal(blocks)}, b -> struct(-aggregate(b, 0D, (s, i) -> s + {phi}) as neg_phi,"
        f" aggregate(b, 0D, (s, i) -> s + yvec[i] * ({grad})) as self_dot, aggregate(b, 0D, (s, i) -> s + ({grad}) * ({grad})) as grad_sq))"
    )
    return queries.select("qid", F.expr(qsum).alias("qsum"))


def block_ceiling(p: Column, s: Column) -> Column:
    return p["phi_sum"] + s["neg_phi"] + s["self_dot"] + F.sqrt(p["sq_norm"] * s["grad_sq"])


def ceilings(psum: str = "psum", qsum: str = "qsum") -> Column:
    """The bound of each block."""
    return F.zip_with(psum, qsum, block_ceiling)


def ceiling(psum: str = "psum", qsum: str = "qsum") -> Column:
    """Upper bound of the whole divergence: the blocks' bounds added."""
    return F.aggregate(ceilings(psum, qsum), F.lit(0.0), lambda a, v: a + v)


def floor_bound(psum: str = "psum", qsum: str = "qsum") -> Column:
    """Lower bound: the same inequality with the other sign, at least 0 in each block."""
    low = lambda p, s: F.greatest(p["phi_sum"] + s["neg_phi"] + s["self_dot"] - F.sqrt(p["sq_norm"] * s["grad_sq"]), F.lit(0.0))
    return F.aggregate(F.zip_with(psum, qsum, low), F.lit(0.0), lambda a, v: a + v)


def budgets(psum: DataFrame, qsum: DataFrame, k: int, sample: float | None = None) -> DataFrame:
    """(qid, pivot_id, total, budgets): the block bounds of the point with the k-th smallest whole bound.

    With ``sample`` only that share of the points (by a hash of their id, at least k) is asked: still valid.
    """
    if sample is not None:
        part = psum.where(F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < int(sample * 1_000_000))
        psum = part if part.limit(k).count() >= k else psum
    first = qsum.select(F.size("qsum").alias("m")).first()
    m = first["m"] if first else 1
    sums = psum.select("id", F.col("psum.phi_sum").alias("phi"), F.col("psum.sq_norm").alias("sq"))
    asked = qsum.select("qid", F.concat("qsum.neg_phi", "qsum.self_dot", "qsum.grad_sq").alias("yvec"))
    given = _Given(gen=None, blocks=[[j] for j in range(m)])

    def work(qids: np.ndarray, y: np.ndarray) -> DataFrame:
        return lowest_totals(sums, given, qids, y, k).select("qid", "id", "rank")

    found = each_block(asked, 3 * m, work, 3 * 4096)
    if found is None:
        found = empty(psum, "qid long, id long, rank int")
    # The last of a query's k rows alone meets the points again: no pair carries its blocks through a sort.
    pivots = found.groupBy("qid").agg(F.max_by("id", "rank").alias("id"))
    return pivots.join(psum, "id").join(qsum, "qid").select("qid", F.col("id").alias("pivot_id"), ceiling().alias("total"), ceilings().alias("budgets"))


class Summaries:
    """The same numbers as matrices; ``centre`` subtracts the tangent of phi at that point (a tighter, still valid bound)."""

    def __init__(self, gen: Generator, blocks: Blocks, centre: np.ndarray | None = None):
        self.gen, self.blocks, self.centre = gen, blocks, centre
        d = sum(map(len, blocks))
        self.member = np.zeros((d, len(blocks)))
        for j, b in enumerate(blocks):
            self.member[b, j] = 1

    def _phi(self, x: np.ndarray) -> np.ndarray:
        if self.centre is None:
            return self.gen.phi(x)
        c = self.centre
        return self.gen.phi(x) - self.gen.phi(c) - self.gen.grad(c) * (x - c)

    def points(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        moved = x if self.centre is None else x - self.centre
        return self._phi(x) @ self.member, (moved * moved) @ self.member

    def queries(self, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        g = self.gen.grad(y) if self.centre is None else self.gen.grad(y) - self.gen.grad(self.centre)
        moved = y if self.centre is None else y - self.centre
        return -(self._phi(y) @ self.member), (moved * g) @ self.member, (g * g) @ self.member

    def bounds(self, phi: np.ndarray, sq: np.ndarray, q: tuple[np.ndarray, np.ndarray, np.ndarray]) -> np.ndarray:
        """(n, q, M) block bounds of few points."""
        return phi[:, None, :] + (q[0] + q[1])[None, :, :] + np.sqrt(sq[:, None, :] * q[2][None, :, :])

    def totals(self, phi: np.ndarray, sq: np.ndarray, q: tuple[np.ndarray, np.ndarray, np.ndarray]) -> np.ndarray:
        """(n, q) whole bounds by one matrix product."""
        return phi.sum(1)[:, None] + (q[0] + q[1]).sum(1)[None, :] + np.sqrt(sq) @ np.sqrt(q[2]).T


class _Given(Summaries):
    """Queries that come as their three numbers a block."""

    def queries(self, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return tuple(np.split(y, 3, axis=1))


def lowest_totals(summaries: DataFrame, which: Summaries, qids: np.ndarray, y: np.ndarray, k: int, exclude_self: bool = False) -> DataFrame:
    """(qid, id, total, rank) of the k smallest whole bounds of each query; k rows a task and query are shuffled, without their blocks."""
    schema = "qid long, id long, total double"

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b, steep = which.queries(y)
        left = np.concatenate((np.sqrt(steep), np.ones((len(y), 1)), (a + b).sum(1)[:, None]), axis=1)
        best = Smallest(len(qids), k)
        for batch in sub_batches(batches):
            ids, phi, sq = batch.column("id").to_numpy(), matrix_of(batch.column("phi")), matrix_of(batch.column("sq"))
            right = np.concatenate((np.sqrt(sq), phi.sum(1)[:, None], np.ones((len(sq), 1))), axis=1).T
            for lo in range(0, len(qids), TILE):
                tile = slice(lo, min(lo + TILE, len(qids)))
                totals = left[tile] @ right
                if exclude_self:
                    totals[qids[tile][:, None] == ids[None, :]] = np.inf
                q, row = best.within(totals, tile, 1e-9)
                best.offer(q, ids[row], totals[q - lo, row])
        best.settle()
        q, i, v = best.held
        yield pa.RecordBatch.from_arrays([pa.array(qids[q]), pa.array(i), pa.array(v)], names=["qid", "id", "total"])

    w = Window.partitionBy("qid").orderBy(F.round("total", 9), "id")
    found = summaries.select("id", "phi", "sq").mapInArrow(scan, schema)
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


__all__ = ["Summaries", "block_ceiling", "budgets", "ceiling", "ceilings", "data_summary", "each_block", "empty", "floor_bound", "lowest_totals", "query_summary"]
