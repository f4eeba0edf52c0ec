"""Probabilistic search: budgets shrunk for a wished probability.

The whole bound of a pivot is kappa + m, where m bounds the mixed term -sum x_i g(y_i) by its norms. If that
term is distributed as Psi, the coefficient c with Psi(c m) = p Psi(m) + (1 - p) Psi(-kappa) cuts the part of
m that matters with probability 1 - p only.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from divknn.functions.generators import Generator
from divknn.operators.index import Index
from divknn.operators.search import held_by, query_budgets, refine_within
from divknn.operators.vectors import PARTIAL, best_k, check_k, each_block, empty, matrix_of, sub_batches
from divknn.storage import saved
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

EDGE = 1e-12


@dataclass
class Dimensions:
    """Per dimension: the fitted family and its two numbers (mean and sd, or ends), and the histogram behind it."""

    family: list[str]
    p1: np.ndarray
    p2: np.ndarray
    edges: np.ndarray
    shares: np.ndarray

    def moments(self) -> tuple[np.ndarray, np.ndarray]:
        flat = np.array([f == "uniform" for f in self.family])
        return np.where(flat, (self.p1 + self.p2) / 2, self.p1), np.where(flat, (self.p2 - self.p1) ** 2 / 12, self.p2**2)


def dimension_stats(points: DataFrame) -> list[dict]:
    """Count, mean, deviation, least and most of every dimension: one row a task and dimension, merged without cancellation."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, mean, sq, lo, hi = 0, 0.0, 0.0, np.inf, -np.inf
        for b in sub_batches(batches, 1 << 15):
            x = matrix_of(b.column("vec"))
            if len(x):
                own, more = x.mean(0), len(x)
                sq = sq + ((x - own) ** 2).sum(0) + (own - mean) ** 2 * (n * more / (n + more))
                mean, n = mean + (own - mean) * (more / (n + more)), n + more
                lo, hi = np.minimum(lo, x.min(0)), np.maximum(hi, x.max(0))
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(mean))), pa.array(np.full(len(mean), n)), pa.array(mean), pa.array(sq), pa.array(lo), pa.array(hi)], names=["dim", "n", "mean", "sq", "lo", "hi"])

    parts = points.select("vec").mapInArrow(sums, "dim long, n long, mean double, sq double, lo double, hi double")
    n, total = F.sum("n"), F.sum(F.col("mean") * F.col("n"))
    out = parts.groupBy("dim").agg(n.alias("n"), (total / n).alias("mean"), F.sum("sq").alias("within"), F.collect_list(F.struct("n", "mean")).alias("parts"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    between = F.aggregate("parts", F.lit(0.0), lambda a, p: a + p["n"] * (p["mean"] - F.col("mean")) * (p["mean"] - F.col("mean")))
    rows = out.select("dim", "n", "mean", F.sqrt((F.col("within") + between) / F.col("n")).alias("sd"), "lo", "hi").collect()  # one row a dimension
    return sorted((r.asDict() for r in rows), key=lambda r: r["dim"])


def fit_dimensions(points: DataFrame, bins: int = 32, family: str = "auto") -> Dimensions:
    """Histogram of every dimension, then the family - normal or uniform - of least squared error against it."""
    stats = dimension_stats(points)
    d, lo = len(stats), np.array([r["lo"] for r in stats])
    span = np.maximum(np.array([r["hi"] for r in stats]) - lo, 1e-300)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(d * bins, np.int64)
        for b in sub_batches(batches):
            cell = np.minimum(np.floor((matrix_of(b.column("vec")) - lo) / span * bins), bins - 1).astype(np.int64)
            total += np.bincount((cell + np.arange(d) * bins).ravel(), minlength=d * bins)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(d * bins)), pa.array(total)], names=["at", "n"])

    counts = points.select("vec").mapInArrow(count, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).collect()  # d x bins numbers
    shares, edges = np.zeros((d, bins)), np.zeros((d, bins + 1))
    for r in counts:
        shares[r["at"] // bins, r["at"] % bins] = r["n"] / stats[r["at"] // bins]["n"]
    names, p1, p2 = [], np.zeros(d), np.zeros(d)
    for i, r in enumerate(stats):
        edges[i] = np.linspace(r["lo"], r["hi"], bins + 1)
        sd = max(r["sd"] or 0.0, 1e-12)
        normal = NormalDist(r["mean"], sd)
        as_normal = np.diff([normal.cdf(e) for e in edges[i]])
        error = ((shares[i] - as_normal) ** 2).sum(), ((shares[i] - 1 / bins) ** 2).sum()
        pick = family if family in ("normal", "uniform") else "normal" if error[0] <= error[1] else "uniform"
        names.append(pick)
        p1[i], p2[i] = (r["mean"], sd) if pick == "normal" else (r["lo"], r["hi"])
    return Dimensions(names, p1, p2, edges, shares)


class Mixed:
    """Distribution of the mixed term of one query."""

    def __init__(self, mean: float, sd: float, values: np.ndarray | None = None):
        self.normal, self.values = NormalDist(mean, max(sd, 1e-12)), values

    def cdf(self, t: float) -> float:
        raw = self.normal.cdf(t) if self.values is None else np.searchsorted(self.values, t, "right") / len(self.values)
        return min(max(float(raw), EDGE), 1 - EDGE)

    def inverse(self, p: float) -> float:
        p = min(max(p, EDGE), 1 - EDGE)
        return self.normal.inv_cdf(p) if self.values is None else float(np.quantile(self.values, p))


def mixed_distribution(gen: Generator, y: np.ndarray, dims: Dimensions, sample: np.ndarray | None = None) -> Mixed:
    """Dimensions taken as independent; with a sample, the sample's own values of the term."""
    g = gen.grad(y)
    mean, var = dims.moments()
    values = None if sample is None else np.sort(-(sample @ g))
    return Mixed(float(-(mean * g).sum()), float(np.sqrt((var * g * g).sum())), values)


def shrink_coefficient(dist: Mixed, kappa: float, m: float, p: float) -> float:
    """c in (0, 1]; 1 at p = 1."""
    if not 0 < p <= 1:
        raise ValueError("p must be in (0, 1]")
    if p == 1 or m <= 0:
        return 1.0
    return min(1.0, dist.inverse(p * dist.cdf(m) + (1 - p) * dist.cdf(-kappa)) / m)


def shrunk_budgets(index: Index, y: np.ndarray, found: dict, p: float, dims: Dimensions, family: str, apply: str, sample: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """(budgets, c of each query): ``whole`` scales every budget, ``root`` its root term alone."""
    q = index.which().queries(y)
    r, c = found["r"].copy(), np.ones(len(y))
    for i in range(len(y)):
        if not np.isfinite(found["total"][i]):
            continue
        kappa = found["kappa"][i]
        m = float(np.sqrt(found["sq"][i] * q[2][i].sum()))  # norms of the whole space
        c[i] = shrink_coefficient(mixed_distribution(index.gen, y[i], dims, sample if family == "empirical" else None), kappa, m, p)
        if apply == "whole" and 0 < c[i] <= 1:
            r[i] *= c[i]
        else:  # the root terms of the blocks are the budgets without their exact parts, which stay whatever c is
            r[i] -= (1 - max(c[i], 0.0)) * found["roots"][i]
    return r, c


def approx_knn(
    index: Index, queries: DataFrame, k: int, p: float, family: str = "auto", apply: str = "whole", granularity: str = "point",
    dims: Dimensions | None = None, exclude_self: bool = False, seed_sample: int = 5_000,
) -> DataFrame:
    """(qid, rank, id, divergence, coefficient, widened): neighbours with about the wished probability.

    Queries left with fewer than k points are answered again with the exact budgets and marked.
    """
    check_k(k)
    if not 0 < p <= 1:
        raise ValueError("p must be in (0, 1]")
    from divknn.operators.index import bounded_sample

    dims = dims or fit_dimensions(index.points, family=family if family in ("normal", "uniform") else "auto")
    sample = bounded_sample(index.points, index.n, seed_sample) if family == "empirical" else None

    def work(qids: np.ndarray, y: np.ndarray) -> DataFrame:
        found = query_budgets(index, qids, y, k, exclude_self=exclude_self)
        r, c = shrunk_budgets(index, y, found, p, dims, family, apply, sample)
        spark = index.points.sparkSession
        first = saved(best_k(refine_within(index, qids, y, r, k, granularity, exclude_self), k))  # counted, then returned
        full = min(k, index.n - int(exclude_self))
        have = {row["qid"]: row["count"] for row in first.groupBy("qid").count().collect()}  # one row a query
        few = np.array([have.get(int(q), 0) < full for q in qids])
        marks = spark.createDataFrame([(int(q), float(v), bool(f)) for q, v, f in zip(qids, c, few, strict=True)], "qid long, coefficient double, widened boolean")
        out = first.join(F.broadcast(marks.where("not widened")), "qid")
        if few.any():
            again = best_k(refine_within(index, qids[few], y[few], found["r"][few], k, granularity, exclude_self), k)
            out = out.unionByName(again.join(F.broadcast(marks), "qid"))
        return out

    found = each_block(index.gen.prepared(queries, "yvec"), index.d, work, held_by(index))
    return found if found is not None else best_k(empty(queries, PARTIAL), k).withColumns({"coefficient": F.lit(1.0), "widened": F.lit(False)})
