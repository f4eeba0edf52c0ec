"""Ball trees: recursive two-means under a divergence, and range search with only centres and radii.

The splitting centres are found on a bounded sample; all points are then sent down the tree, and radii are
maxima over all points, so that pruning is exact whatever the sample.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass

import numpy as np
from divknn.functions.generators import Generator


@dataclass
class BallTree:
    """Nodes of one block in arrays; node 0 is the root, children have larger numbers. Leaves are numbered left to right."""

    dims: list[int]
    centre: np.ndarray
    left: np.ndarray
    right: np.ndarray
    depth: np.ndarray
    leaf: np.ndarray  # number of the leaf, -1 inside
    radius: np.ndarray
    count: np.ndarray

    @property
    def leaves(self) -> int:
        return int(self.leaf.max()) + 1

    def parents(self) -> np.ndarray:
        out = np.full(len(self.leaf), -1)
        inner = np.flatnonzero(self.left >= 0)
        out[self.left[inner]] = inner
        out[self.right[inner]] = inner
        return out

    def leaf_nodes(self) -> np.ndarray:
        nodes = np.flatnonzero(self.leaf >= 0)
        return nodes[np.argsort(self.leaf[nodes])]

    def assign(self, gen: Generator, x: np.ndarray) -> np.ndarray:
        """Leaf node of each row: the nearer of two children at each step, told by a hyperplane."""
        inner = self.left >= 0
        slope, level = np.zeros_like(self.centre), np.zeros(len(self.centre))
        slope[inner], level[inner] = bisector(gen, self.centre[self.left[inner]], self.centre[self.right[inner]])
        at = np.zeros(len(x), np.int64)
        open_ = np.arange(len(x)) if inner[0] else np.zeros(0, np.int64)
        while len(open_):
            here = at[open_]
            near = (x[open_] * slope[here]).sum(1) <= level[here]
            at[open_] = np.where(near, self.left[here], self.right[here])
            open_ = open_[inner[at[open_]]]
        return at

    def spans(self) -> np.ndarray:
        """(nodes, 2): the first leaf below each node, and the one after the last."""
        out = np.stack((self.leaf, self.leaf + 1), axis=1)
        for node in np.flatnonzero(self.left >= 0)[::-1]:
            out[node] = out[self.left[node], 0], out[self.right[node], 1]
        return out

    def paths(self) -> np.ndarray:
        """(nodes, depth) ancestors of each node, itself included, -1 where there is none."""
        parent, out = self.parents(), []
        at = np.arange(len(parent))
        while (at >= 0).any():
            out.append(at)
            at = np.where(at >= 0, parent[np.maximum(at, 0)], -1)
        return np.stack(out, axis=1)


def bisector(gen: Generator, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(slope, level): a point x is no farther from a than from b where slope . x <= level, as the convex parts of x cancel."""
    ga, gb = gen.grad(a), gen.grad(b)
    return gb - ga, (gen.phi(a) - ga * a - gen.phi(b) + gb * b).sum(-1)


def _split(gen: Generator, x: np.ndarray, rng: np.random.Generator, rounds: int = 8) -> np.ndarray | None:
    """Mask of the first of two clusters; None if the points cannot be told apart."""
    a = x[rng.integers(len(x))]
    b = x[np.argmax(gen.divergence(x, a))]
    before = None
    for _ in range(rounds + 1):
        slope, level = bisector(gen, a, b)
        near = x @ slope <= level
        if near.all() or not near.any():
            return None
        if before is not None and np.array_equal(near, before):
            break
        before = near
        a, b = x[near].mean(0), x[~near].mean(0)  # the mean is the best centre for every divergence
    return near


def build_tree(sample: np.ndarray, gen: Generator, dims: list[int], leaf_size: int, max_depth: int = 12, seed: int = 42) -> BallTree:
    """Tree over the block's coordinates of a sample; leaves hold ``leaf_size`` sample rows at most, unless at ``max_depth``."""
    x, rng = sample[:, dims], np.random.default_rng(seed)
    centre, left, right, depth, leaf = [], [], [], [], []
    leaves = itertools.count()

    def grow(rows: np.ndarray, level: int) -> int:
        own = len(centre)
        centre.append(x[rows].mean(0))
        for a, v in ((left, -1), (right, -1), (depth, level), (leaf, -1)):
            a.append(v)
        near = _split(gen, x[rows], rng) if len(rows) > leaf_size and level < max_depth else None
        if near is None:
            leaf[own] = next(leaves)
        else:
            left[own] = grow(rows[near], level + 1)
            right[own] = grow(rows[~near], level + 1)
        return own

    grow(np.arange(len(x)), 0)
    n = len(centre)
    return BallTree(list(dims), np.array(centre), np.array(left), np.array(right), np.array(depth), np.array(leaf), np.zeros(n), np.zeros(n, np.int64))


def nearest_in_ball(gen: Generator, c: np.ndarray, radius: np.ndarray, y: np.ndarray, rounds: int = 24) -> tuple[np.ndarray, np.ndarray]:
    """(lower, upper) bounds of the least divergence to ``y`` of a point in each ball {x : D(x, c) <= radius}.

    On the curve whose gradients mix those of y and c, every mixing share gives a lower bound by duality,
    and every point inside the ball an upper bound; bisection brings them together.
    """
    zero = gen.divergence(y, c) <= radius
    gy, gc = gen.grad(y), gen.grad(c)
    lo, hi = np.zeros(len(c)), np.ones(len(c))
    lower, upper = np.zeros(len(c)), gen.divergence(c, y)
    for _ in range(rounds):
        share = (lo + hi) / 2
        x = gen.grad_inv((1 - share)[:, None] * gy + share[:, None] * gc)
        to_c, to_y = gen.divergence(x, c), gen.divergence(x, y)
        lower = np.maximum(lower, to_y + share / np.maximum(1 - share, 1e-12) * (to_c - radius))
        inside = to_c <= radius
        upper = np.where(inside, np.minimum(upper, to_y), upper)
        lo, hi = np.where(inside, lo, share), np.where(inside, share, hi)
    return np.where(zero, 0, lower), np.where(zero, 0, upper)


def ball_vs_range(gen: Generator, c: np.ndarray, radius: np.ndarray, y: np.ndarray, r: np.ndarray) -> np.ndarray:
    """For each pair of a ball and a range {x : D(x, y) <= r}: -1 apart, 1 ball inside range (told for G1 only), 0 visit."""
    out, limit = np.zeros(len(c), np.int64), r + 1e-9 * (1 + np.abs(r))
    # The same bisection as in nearest_in_ball, but a pair leaves it as soon as either bound has decided.
    open_ = np.flatnonzero((gen.divergence(y, c) > radius) & (gen.divergence(c, y) > r))
    lo, hi = np.zeros(len(open_)), np.ones(len(open_))
    for _ in range(24):
        if not len(open_):
            break
        cc, yy, most = c[open_], y[open_], radius[open_]
        share = (lo + hi) / 2
        x = gen.grad_inv((1 - share)[:, None] * gen.grad(yy) + share[:, None] * gen.grad(cc))
        to_c, to_y = gen.divergence(x, cc), gen.divergence(x, yy)
        lower = to_y + share / np.maximum(1 - share, 1e-12) * (to_c - most)
        inside = to_c <= most
        apart = lower > limit[open_]
        out[open_[apart]] = -1
        go = ~apart & ~(inside & (to_y <= r[open_]))
        lo, hi, open_ = np.where(inside, lo, share)[go], np.where(inside, share, hi)[go], open_[go]
    if gen.name == "squared_euclidean":
        inside = (np.sqrt(2 * radius) + np.sqrt(2 * gen.divergence(c, y))) ** 2 / 2 <= r
        out = np.where(inside & (out == 0), 1, out)
    return out


def tree_range(tree: BallTree, gen: Generator, y: np.ndarray, r: np.ndarray, wanted: np.ndarray | None = None) -> tuple[np.ndarray, int]:
    """((queries, leaves) mask of the leaves a range may reach; nodes looked at). y: block coordinates of each query.

    ``wanted``: (queries, leaves) mask of the leaves asked about; nodes above none of them are not looked at.
    """
    hit = np.zeros((len(y), tree.leaves), bool)
    if wanted is not None:
        before, span = np.zeros((len(y), tree.leaves + 1), np.int32), tree.spans()
        np.cumsum(wanted, axis=1, out=before[:, 1:])
    q, node, looked = np.arange(len(y)), np.zeros(len(y), np.int64), 0
    while len(q):
        if wanted is not None:
            some = before[q, span[node, 1]] > before[q, span[node, 0]]
            q, node = q[some], node[some]
        looked += len(q)
        alive = tree.count[node] > 0
        q, node = q[alive], node[alive]
        reach = ball_vs_range(gen, tree.centre[node], tree.radius[node], y[q], r[q]) >= 0
        q, node = q[reach], node[reach]
        end = tree.leaf[node] >= 0
        hit[q[end], tree.leaf[node[end]]] = True
        q, node = q[~end], node[~end]
        q, node = np.concatenate((q, q)), np.concatenate((tree.left[node], tree.right[node]))
    return hit, looked
