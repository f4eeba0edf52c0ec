"""How many blocks: a decaying bound, its candidates, and the cost of a search."""

from __future__ import annotations

import math
import warnings
from dataclasses import asdict, dataclass

import numpy as np
from divknn.functions.generators import Generator
from divknn.operators.summaries import Summaries
from divknn.plans.partition import contiguous_blocks
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CostModel:
    """The bound at M blocks is ``a * alpha**M``; a share ``beta`` times the bound of the n points are candidates."""

    a: float
    alpha: float
    beta: float
    n: int
    d: int

    def as_dict(self) -> dict:
        return asdict(self)

    def cost(self, m: float, k: int = 1, page_bytes: int | None = None, iops: float | None = None, passes: int = 1) -> float:
        """Operations of a search; with a page size and a rate, seconds of reading candidates are added."""
        logk = math.log2(k) if k > 1 else 0.0
        share = min(1.0, self.beta * self.a * self.alpha**m)
        total = self.d + passes * m * self.n + self.n * logk + self.beta * self.a * self.alpha**m * self.n * (self.d + logk)
        if page_bytes and iops:
            total += share * self.n * self.d * 4 / page_bytes / iops
        return total

    def tree_cost(self, m: int, leaf_size: int) -> float:
        """Nodes looked at by the range searches: small beside the rest."""
        share = min(1.0, self.beta * self.a * self.alpha**m)
        return m * max(share * self.n / leaf_size, 1) * math.log2(max(2.0, self.n / leaf_size))

    def root(self, k: int = 1) -> float:
        """Where the derivative is zero; n cancels. The linear term counts twice: bounds are evaluated and added."""
        if not 0 < self.alpha < 1:
            return -math.inf
        logk = math.log2(k) if k > 1 else 0.0
        right = 2.0 / (-self.beta * self.a * math.log(self.alpha) * (self.d + logk))
        return math.log(right) / math.log(self.alpha)

    def optimal_blocks(self, k: int = 1) -> int:
        """The better whole neighbour of the root, within 1..d."""
        x = self.root(k)
        if not math.isfinite(x) or x < 1:
            warnings.warn(f"the bound hardly falls with the number of blocks (alpha {self.alpha:.4f}, root {x:.1f}): one block", stacklevel=2)
            return 1
        lo = min(max(1, math.floor(x)), self.d)
        return min((lo, min(lo + 1, self.d)), key=lambda m: self.cost(m, k, passes=2))

    def scan_optimum(self, k: int = 1, **io) -> int:
        """The same by trying every number of blocks; needed with the reading term."""
        return min(range(1, self.d + 1), key=lambda m: self.cost(m, k, passes=2, **io))


def sample_pairs(points: DataFrame, n: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """``n`` pairs of points by hash order: collected, as many rows as asked for."""
    rows = points.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(2 * n).select("vec").collect()
    x = np.array([r["vec"] for r in rows], float)
    half = max(1, len(x) // 2)
    return x[:half], x[half : 2 * half] if len(x) > 1 else x[:1]


def pair_bounds(gen: Generator, x: np.ndarray, y: np.ndarray, m: int) -> np.ndarray:
    s = Summaries(gen, contiguous_blocks(x.shape[1], m))
    phi, sq = s.points(x)
    a, b, c = s.queries(y)
    return (phi + a + b + np.sqrt(sq * c)).sum(1)


def fit_decay(gen: Generator, x: np.ndarray, y: np.ndarray, m_lo: int, m_hi: int) -> tuple[float, float]:
    """(a, alpha) from the bounds of sampled pairs at two numbers of blocks, averaged as logarithms."""
    lo, hi = (np.log(np.maximum(pair_bounds(gen, x, y, m), 1e-12)) for m in (m_lo, m_hi))
    slope = float((hi - lo).mean()) / max(1, m_hi - m_lo)
    return float(np.exp(lo.mean() - slope * m_lo)), float(np.exp(slope))


def fit_beta(points: DataFrame, gen: Generator, y: np.ndarray, bounds: np.ndarray, mode: str = "ratio") -> tuple[float, float]:
    """(beta, mean share): the share of points within each sample's bound, over the bound (``ratio``) or as it is (``share``)."""
    from divknn.operators.vectors import matrix_of, sub_batches

    def count(batches):
        import pyarrow as pa

        n, inside = 0, np.zeros(len(y))
        for b in sub_batches(batches):
            own = gen.matrix(matrix_of(b.column("vec")), y)
            n, inside = n + len(own), inside + (own <= bounds).sum(0)
        yield pa.RecordBatch.from_arrays([pa.array([float(n)]), pa.array([inside.tolist()], pa.list_(pa.float64()))], names=["n", "inside"])

    rows = points.select("vec").mapInArrow(count, "n double, inside array<double>").select("n", F.posexplode("inside").alias("i", "v")).groupBy("i").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).orderBy("i").collect()
    share = np.array([r["v"] / max(r["n"], 1) for r in rows])
    return float((share / bounds).mean() if mode == "ratio" else share.mean()), float(share.mean())


def fit(points: DataFrame, gen: Generator, n: int, d: int, m_lo: int = 2, m_hi: int = 16, n_samples: int = 50, seed: int = 42, mode: str = "ratio") -> CostModel:
    x, y = sample_pairs(points, n_samples, seed)
    m_hi = min(m_hi, d)
    a, alpha = fit_decay(gen, x, y, min(m_lo, m_hi), m_hi)
    beta, _ = fit_beta(points, gen, y, np.maximum(pair_bounds(gen, x, y, max(1, m_hi // 2)), 1e-12), mode)
    return CostModel(a, alpha, beta, n, d)
