"""Dividing dimensions into blocks."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from divknn.operators.vectors import width
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Blocks = list[list[int]]


def contiguous_blocks(d: int, m: int, mode: str = "balanced") -> Blocks:
    """Equal runs of dimensions. ``ceil``: all of width ceil(d/m), empty ones dropped; ``balanced``: widths differ by one at most."""
    m = min(max(1, m), d)
    if mode == "ceil":
        step = -(-d // m)
        return [list(range(i, min(i + step, d))) for i in range(0, d, step)]
    return [b.tolist() for b in np.array_split(np.arange(d), m)]


def random_blocks(d: int, m: int, seed: int = 42) -> Blocks:
    order = np.random.default_rng(seed).permutation(d)
    return [sorted(order[b].tolist()) for b in contiguous_blocks(d, m)]


#: Numbers of a task's sums that travel in one row.
PIECE = 1 << 13


@dataclass
class Survey:
    """What one pass tells of a table of vectors. ``cross`` is None where it was not asked for, a vector is bad or widths differ."""

    n: int
    d: int  # the least width; ``most`` is the largest
    most: int
    bad: int  # vectors that are null, or hold a null or NaN
    low: float  # the least coordinate
    sums: np.ndarray | None
    cross: np.ndarray | None


def survey(points: DataFrame, products: bool = True) -> Survey:
    """One pass: rows, widths, bad vectors, least coordinate, and sums and cross products; partial sums of d**2 numbers a task, added by Spark."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, least, most, bad, low, total = 0, np.inf, -1, 0, np.inf, None
        for b in batches:
            vec = b.column("vec")
            n += len(vec)
            long, flat = pc.list_value_length(vec).drop_null().to_numpy(zero_copy_only=False), vec.flatten()
            if not len(long):
                bad += len(vec)
                continue
            least, most, clean = min(least, long.min()), max(most, long.max()), False
            x = flat.to_numpy(zero_copy_only=False)  # nulls come as NaN
            if len(x):
                low = np.fmin(low, np.fmin.reduce(x))
                odd = np.isnan(x)
                clean = not odd.any()
                if not clean:
                    bad += len(np.unique(np.repeat(np.arange(len(long)), long)[odd]))
            bad += vec.null_count
            if products and clean and least == most and not vec.null_count:
                x = x.reshape(len(vec), -1)
                own = np.concatenate((x.sum(0), (x.T @ x).ravel()))
                total = own if total is None else total + own if len(total) == len(own) else None
        pieces = [] if total is None else [total[i : i + PIECE].tobytes() for i in range(0, len(total), PIECE)]
        head = np.array([n, least, most, bad, low], float).tobytes()
        yield pa.RecordBatch.from_arrays([pa.array(range(-1, len(pieces)), pa.int64()), pa.array([head, *pieces], pa.binary())], names=["at", "v"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[int, np.ndarray] = {}
        for b in batches:
            for at, v in zip(b.column("at").to_pylist(), b.column("v").to_pylist(), strict=True):
                own = np.frombuffer(v)
                if at in found and at >= 0 and len(own) != len(found[at]):
                    continue  # of tables of two widths no products are told
                found[at] = own if at not in found else joined(found[at], own) if at < 0 else found[at] + own
        yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), pa.array([v.tobytes() for v in found.values()], pa.binary())], names=["at", "v"])

    def joined(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.array([a[0] + b[0], min(a[1], b[1]), max(a[2], b[2]), a[3] + b[3], min(a[4], b[4])])

    parts = points.select("vec").mapInArrow(look, "at long, v binary").repartition("at").mapInArrow(add, "at long, v binary")
    found = {r["at"]: np.frombuffer(r["v"]) for r in parts.collect()}  # d**2 numbers
    n, least, most, bad, low = found.pop(-1, [0, np.inf, -1, 0, np.inf])
    d = int(least) if np.isfinite(least) else 0
    flat = np.concatenate([found[i] for i in sorted(found)]) if found else np.zeros(0)
    whole = len(flat) == d + d * d and d == most and not bad
    return Survey(int(n), d, max(int(most), 0), int(bad), float(low), flat[:d] if whole else None, flat[d:].reshape(d, d) if whole else None)


def moments(points: DataFrame) -> tuple[int, np.ndarray, np.ndarray]:
    """(rows, sums, cross products) in one pass."""
    found = survey(points)
    if found.bad or found.d != found.most:
        raise ValueError("vectors must not be null, hold no null or NaN, and be of one length")
    if found.cross is None:
        found.sums, found.cross = np.zeros(found.d), np.zeros((found.d, found.d))
    return found.n, found.sums, found.cross


def abs_correlation(points: DataFrame, found: Survey | None = None) -> np.ndarray:
    """Absolute Pearson correlations; a constant dimension correlates with none."""
    n, s, g = (found.n, found.sums, found.cross) if found and found.cross is not None else moments(points)
    cov = g / max(n, 1) - np.outer(s, s) / max(n, 1) ** 2
    sd = np.sqrt(np.maximum(np.diag(cov), 0))
    scale = np.outer(sd, sd)
    r = np.abs(np.divide(cov, scale, out=np.zeros_like(cov), where=scale > 1e-12 * np.abs(g).max(initial=1) / max(n, 1)))
    np.fill_diagonal(r, 1)
    return r


def group_similar(r: np.ndarray, m: int, seed: int = 42, first: int | None = None) -> list[list[int]]:
    """Groups of ``m`` dimensions: each grows by the free one most correlated with any of its members."""
    d, rng = len(r), np.random.default_rng(seed)
    free = np.ones(d, bool)
    groups: list[list[int]] = []
    while free.any():
        start = first if first is not None and not groups else int(rng.choice(np.flatnonzero(free)))
        group, nearest = [], np.zeros(d)
        while len(group) < m and free.any():
            pick = start if not group else int(np.argmax(np.where(free, nearest, -1)))
            group.append(pick)
            free[pick] = False
            nearest = np.maximum(nearest, r[pick])
        groups.append(group)
    return groups


def deal_groups(groups: list[list[int]], m: int, seed: int = 42) -> Blocks:
    """Every block draws at most one dimension of each group; a short group goes to the smallest blocks."""
    rng = np.random.default_rng(seed + 1)
    blocks: Blocks = [[] for _ in range(m)]
    for g in groups:
        places = sorted(rng.permutation(m).tolist(), key=lambda j: len(blocks[j]))
        for j, dim in zip(places, rng.permutation(g).tolist(), strict=False):
            blocks[j].append(dim)
    return [sorted(b) for b in blocks if b]


def decorrelated_blocks(points: DataFrame, m: int, seed: int = 42, first: int | None = None, found: Survey | None = None) -> Blocks:
    """Dimensions that correlate strongly land in different blocks, so that the blocks resemble each other."""
    r = abs_correlation(points, found)
    m = min(max(1, m), len(r))
    return deal_groups(group_similar(r, m, seed, first), m, seed)


def make_blocks(points: DataFrame, m: int, strategy: str = "decorrelated", seed: int = 42, first: int | None = None, found: Survey | None = None) -> Blocks:
    """``found``: what a pass over the points has told already."""
    if strategy == "decorrelated":
        return decorrelated_blocks(points, m, seed, first, found)
    d = found.d if found else width(points)
    return contiguous_blocks(d, m) if strategy == "contiguous" else random_blocks(d, m, seed)


def split_blocks(vec: str, blocks: Blocks) -> Column:
    """array<array<double>>: the coordinates of each block."""
    return F.array(*[F.array(*[F.col(vec)[i] for i in b]) for b in blocks])
