"""All pairs within a radius: what is looked at, and how often."""

import numpy as np
import pytest
from divknn import workloads
from divknn.functions import generators as G
from divknn.operators import baselines, search, vectors
from divknn.operators.balltree import tree_range
from divknn.operators.relational import all_similar_pairs
from divknn.operators.search import Sides, _within_either, leaf_pairs, range_search


def points_of(spark, x):
    return spark.createDataFrame([(i, list(map(float, r))) for i, r in enumerate(x)], "id long, vec array<double>")


def smaller(g, x):
    """The smaller divergence of each pair, in difference form."""
    d = np.array([g.divergence(x, y) for y in x])
    return np.fmin(d, d.T)


def lumps():
    rng = np.random.default_rng(7)
    return np.concatenate([rng.random((n, 10)) * s + c for n, s, c in ((160, 0.4, 0.1), (60, 0.1, 1.5), (40, 0.05, 4.0))])


def check(spark, x, g, r, both):
    rows = all_similar_pairs(points_of(spark, x).repartition(3), g, r).collect()
    got = {(p["qid"], p["id"]): p["divergence"] for p in rows}
    assert len(rows) == len(got) and got.keys() == set(zip(*map(np.ndarray.tolist, np.nonzero(np.triu(both <= r, 1))), strict=True))
    assert all(abs(v - both[k]) < 1e-9 for k, v in got.items())


def test_blocks_meet_what_comes_after_them(spark, sf, monkeypatch):
    """A pair is in the work of one block alone, and its divergence leaves the task rounded."""
    monkeypatch.setattr(vectors, "QUERY_NUMBERS", 400_000)
    plan = workloads.QUERIES["similar_pairs_all"](spark, sf)._jdf.queryExecution()
    own = plan.executedPlan().toString()
    assert own.count("GreaterThanOrEqual(leaf_ord,") == own.count("MapInArrow") > 2
    assert "round(" not in plan.optimizedPlan().toString()


def test_weighted_pairs(spark):
    """The points that ask are scaled as those that are asked."""
    x, weights = lumps()[::3], [1 + i / 3 for i in range(10)]
    check(spark, x, G.mahalanobis(weights), 0.5, smaller(G.squared_euclidean(), x * np.sqrt(weights)))


@pytest.mark.parametrize("g", [G.exponential(), G.itakura_saito(), G.lp_norm(3.0)], ids=lambda g: g.name)
def test_pairs_of_leaves(spark, monkeypatch, g):
    """No pair within the radius is lost, and leaves far from each other do not meet; also if ball tests alone tell."""
    x = lumps()
    both, r = smaller(g, x), 0.05
    check(spark, x, g, r, both)
    index = baselines.build_whole_tree(points_of(spark, x), g, leaf_size=16)
    leaf = {p["id"]: p["leaf_ord"] for p in index.points.select("id", "leaf_ord").collect()}
    near = [(leaf[i], leaf[j]) for i, j in np.argwhere(both <= r).tolist()]
    found = leaf_pairs(index, r)
    assert (found == found.T).all() and all(found[p] for p in near) and 0 < found.mean() < 0.9
    tree = index.trees[0]
    hit, looked = tree_range(tree, g, x, np.full(len(x), r))
    wanted = np.random.default_rng(1).random(hit.shape) < 0.2
    some, fewer = tree_range(tree, g, x, np.full(len(x), r), wanted)
    assert (some == hit & wanted).all() and fewer < looked
    monkeypatch.setattr(search, "PAIRS", 1)  # a point at once
    assert (leaf_pairs(index, r) == found).all()


def test_a_leaf_larger_than_a_block(spark, monkeypatch):
    x = lumps()
    x[20:120] = x[20]
    monkeypatch.setattr(vectors, "QUERY_NUMBERS", 30_000)
    check(spark, x, G.exponential(), 0.05, smaller(G.exponential(), x))


def test_large_numbers_and_close_calls():
    """Products that cancel decide nothing: neither of large coordinates nor at the radius; what overflows one way is measured the other."""
    g, rng = G.exponential(), np.random.default_rng(3)
    x = np.concatenate([rng.random((40, 6)), 20 + rng.random((40, 6)) * 5e-5, [[800.0] + [0.0] * 5]])
    with np.errstate(all="ignore"):
        both = smaller(g, x)
        r = float(both[3, 17])
        a = Sides(g, np.arange(len(x)), np.zeros(len(x), np.int32), x)
        i, j, value = _within_either(g, a, a, r)
        assert set(zip(i.tolist(), j.tolist(), strict=True)) == set(map(tuple, np.argwhere(both <= r).tolist())) > {(3, 17), (17, 3)}
        assert (both[40:80, 40:80] <= r).any() and (both[40:80, 40:80] > r).any() and np.allclose(value, both[i, j], rtol=1e-6, atol=1e-12)


def test_all_must_ask_alike(spark):
    index = baselines.build_whole_tree(df := points_of(spark, lumps()), G.exponential())
    for asked in ("id qid", "vec yvec", "double(id) radius"), ("id + 1 qid", "vec yvec", "0.5D radius"):
        with pytest.raises(ValueError):
            range_search(index, df.where("id > 0" if "0.5" in asked[2] else "true").selectExpr(*asked), once=True)
