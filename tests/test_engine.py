"""Exactness, bounds, trees, partitioning and probabilities."""

import itertools

import numpy as np
import pytest
from divknn import measures, workloads
from divknn.functions import generators as G
from divknn.operators import approx, baselines, balltree
from divknn.operators.index import build_index, load_index
from divknn.operators.search import blockwise_knn_union, exact_knn, query_budgets, touched_leaves
from divknn.operators.summaries import Summaries
from divknn.operators.vectors import query_blocks, scan_knn, scan_knn_columns
from divknn.plans import costmodel, partition
from divknn.sources import views
from pyspark.errors import PySparkException

ALL = [G.squared_euclidean(), G.itakura_saito(), G.exponential(), G.shannon(), G.lp_norm(3), G.lp_quasi(0.5)]


def rows(df):
    return [(r["qid"], r["rank"], r["id"], round(r["divergence"], 6)) for r in df.orderBy("qid", "rank").collect()]


def points_of(spark, x):
    return spark.createDataFrame([(i, list(map(float, r))) for i, r in enumerate(x)], "id long, vec array<double>")


@pytest.fixture(scope="module")
def mixed(spark):
    rng = np.random.default_rng(1)
    x = rng.gamma(2.0, 0.5, (400, 4)) @ rng.random((4, 24)) + 0.1
    x[7] = x[3]  # a tie
    return points_of(spark, x).cache(), x


def test_divergences():
    rng = np.random.default_rng(0)
    x, y = rng.random((50, 9)) + 0.2, rng.random((50, 9)) + 0.2
    for g in ALL:
        d = g.divergence(x, y)
        assert (d >= 0).all() and np.allclose(g.divergence(x, x), 0) and np.allclose(np.diag(g.matrix(x, y)), d, atol=1e-9)
        assert np.allclose(g.grad_inv(g.grad(x)), x)
        assert np.allclose(g.divergence(x[:, :4], y[:, :4]) + g.divergence(x[:, 4:], y[:, 4:]), d)
    assert not np.allclose(G.exponential().divergence(x, y), G.exponential().divergence(y, x))
    with pytest.raises(ValueError, match="sum over blocks"):
        G.get("kl")


def test_bounds_hold_plain_and_centred():
    rng = np.random.default_rng(2)
    x, y = rng.random((80, 12)) + 0.1, rng.random((30, 12)) + 0.1
    for g, m, centre in itertools.product(ALL, (1, 3, 12), (None, x.mean(0))):
        s = Summaries(g, partition.contiguous_blocks(12, m), centre)
        bounds = s.bounds(*s.points(x), s.queries(y))
        assert np.allclose(bounds.sum(2), s.totals(*s.points(x), s.queries(y)))
        for j, b in enumerate(s.blocks):
            assert (bounds[:, :, j] >= g.matrix(x[:, b], y[:, b]) - 1e-9).all()
    totals = [Summaries(G.exponential(), partition.contiguous_blocks(12, m)) for m in (1, 2, 4, 12)]
    totals = [s.totals(*s.points(x), s.queries(y)) for s in totals]
    assert all((b <= a + 1e-9).all() for a, b in itertools.pairwise(totals))  # nested partitions


@pytest.mark.parametrize("name", ["exponential", "itakura_saito", "lp_quasi"])
def test_all_methods_agree(spark, mixed, name):
    df, x = mixed
    g, q = G.get(name), views.sample_queries(df, 8)
    for k in (5, 401):
        want = rows(scan_knn(df, q, g, k))
        assert rows(scan_knn_columns(df, q, g, k)) == want and len(want) == 8 * min(k, 400)
    want = rows(scan_knn(df, q, g, 5))
    for strategy, granularity, tighten, centre in (("decorrelated", "leaf", False, False), ("contiguous", "point", True, False), ("random", "point", False, True)):
        index = build_index(df, g, 4, strategy, leaf_size=20, centre=centre)
        assert rows(exact_knn(index, q, 5, granularity, tighten)) == want
    assert rows(exact_knn(load_index(spark, index.path, g), q, 5)) == want
    assert rows(baselines.cell_knn(baselines.build_cells(df, g, 4), q, 5)) == want
    assert rows(baselines.tree_knn(baselines.build_whole_tree(df, g, 20), q, 5)) == want
    assert rows(approx.approx_knn(index, q, 5, 1.0).drop("coefficient", "widened")) == want
    assert rows(exact_knn(index, q, 5, exclude_self=True)) == rows(scan_knn(df, q, g, 5, exclude_self=True))


def test_blockwise_neighbours_miss(spark):
    x = np.array([[0, 0], [0, 9], [9, 0], [2, 2]], float)
    df, g = points_of(spark, x), G.squared_euclidean()
    q = df.where("id = 0").selectExpr("100 as qid", "vec as yvec")
    blockwise = {r[2] for r in rows(blockwise_knn_union(df.where("id > 0"), q, g, [[0], [1]], 1))}
    assert blockwise != {r[2] for r in rows(scan_knn(df.where("id > 0"), q, g, 1))} == {3}


def test_trees(mixed):
    _, x = mixed
    for g in ALL:
        tree = balltree.build_tree(x, g, list(range(6)), 15, seed=3)
        own, leaf = x[:, :6], tree.assign(g, x[:, :6])
        paths = tree.paths()
        for i, node in enumerate(leaf):
            for a in paths[node][paths[node] >= 0]:
                tree.radius[a] = max(tree.radius[a], g.divergence(own[i], tree.centre[a]))
                tree.count[a] += 1
        assert tree.count[0] == len(x) and (tree.leaf[leaf] >= 0).all()
        y = own[:10]
        full = g.matrix(own, y)
        lower, upper = balltree.nearest_in_ball(g, np.repeat(tree.centre[1:2], 10, 0), np.repeat(tree.radius[1], 10), y)
        inside = paths[leaf][:, ::-1]
        member = (inside == 1).any(1)
        if member.any():
            assert (lower <= full[member].min(0) + 1e-9).all() and (lower <= upper + 1e-9).all()
        for r in (0.0, np.quantile(full, 0.1), np.inf):
            hit, _ = balltree.tree_range(tree, g, y, np.full(10, min(r, 1e300)))
            assert all(hit[q, tree.leaf[leaf[i]]] for i, q in np.argwhere(full <= r))


def test_partitioners(mixed):
    df, x = mixed
    r = partition.abs_correlation(df)
    assert np.allclose(r, np.abs(np.corrcoef(x.T)))
    assert partition.group_similar(np.array(workloads.SIX), 3, first=0) == [[0, 4, 5], [3, 1, 2]] or sorted(partition.group_similar(np.array(workloads.SIX), 3, first=0)[0]) == [0, 4, 5]
    for m in (1, 5, 7, 24, 30):
        for blocks in (partition.contiguous_blocks(24, m), partition.random_blocks(24, m), partition.decorrelated_blocks(df, m)):
            assert sorted(i for b in blocks for i in b) == list(range(24))
            assert max(map(len, blocks)) - min(map(len, blocks)) <= 1
    groups = partition.group_similar(r, 6)
    for b in partition.deal_groups(groups, 6):
        assert all(len(set(b) & set(g)) <= 1 for g in groups)
    assert [len(b) for b in partition.contiguous_blocks(200, 21, "ceil")] == [10] * 20


def test_cost_model():
    for a, alpha, beta, d, k in ((500, 0.9, 0.01, 128, 1), (50, 0.97, 0.01, 200, 20), (2000, 0.8, 0.001, 64, 5)):
        small, large = (costmodel.CostModel(a, alpha, beta, n, d) for n in (1000, 10**7))
        assert small.optimal_blocks(k) == large.optimal_blocks(k)
        if 1 < small.root(k) < d:
            assert abs(small.optimal_blocks(k) - small.scan_optimum(k)) <= 1
    with pytest.warns(UserWarning):
        assert costmodel.CostModel(10, 1.01, 0.1, 100, 8).optimal_blocks() == 1


def test_probability(spark):
    df = views.gauss(spark, 1500, 40, 0.3).cache()
    g, q = G.exponential(), views.sample_queries(df, 10)
    index, dims = build_index(df, g, 5), approx.fit_dimensions(df)
    assert dims.family.count("normal") >= 38
    assert approx.fit_dimensions(views.uniform(spark, 1500, 10)).family.count("uniform") >= 9
    truth = scan_knn(df, q, g, 10).cache()
    last = 0.0
    for p in (0.5, 0.8, 0.95, 1.0):
        out = approx.approx_knn(index, q, 10, p, dims=dims)
        c = out.selectExpr("avg(coefficient)").first()[0]
        ratio = measures.overall_ratio(out, truth).selectExpr("min(ratio)").first()[0]
        assert c >= last - 1e-9 and ratio >= 1 - 1e-9 and out.count() == 100
        last = c
    assert last == 1.0
    sample = np.array([r["vec"] for r in df.collect()])
    y = sample[0]
    mixed = approx.mixed_distribution(g, y, dims)
    values = -(sample @ g.grad(y))
    assert abs(mixed.normal.mean - values.mean()) < 0.05 * abs(values.mean()) and abs(mixed.normal.stdev - values.std()) < 0.1 * values.std()


def test_overall_ratio_rules(spark):
    mk = lambda v: spark.createDataFrame([(1, i + 1, i, float(d)) for i, d in enumerate(v)], "qid long, rank int, id long, divergence double")
    r = measures.overall_ratio(mk([0, 2, 3, 4]), mk([0, 1, 3, 0])).first()
    assert r["ratio"] == pytest.approx((1 + 2 + 1) / 3) and r["undefined"] == 1


def test_pages_and_determinism(spark, mixed):
    df, x = mixed
    g, q = G.exponential(), views.sample_queries(df, 6)
    index = build_index(df, g, 3, page_bytes=4 * 24 * 3)  # three points a page
    pages = index.points.groupBy("page").count().collect()
    assert len(pages) == 134 and max(r["count"] for r in pages) == 3
    qids, y = next(query_blocks(q, 24))
    r = query_budgets(index, qids, y, 5)["r"]
    share = measures.candidate_share(index, qids, y, r)
    assert all(r_["n_candidates"] <= 3 * r_["data_pages"] and r_["data_pages"] <= 134 for r_ in share.collect())
    reach = touched_leaves(index, y, r)
    assert reach.looked > 0 and (reach.touched() > 0).all()
    again = build_index(df.repartition(7), g, 3, page_bytes=4 * 24 * 3)
    assert again.blocks == index.blocks and rows(exact_knn(again, q, 5)) == rows(exact_knn(index, q, 5))


def test_errors(spark, mixed):
    df, _ = mixed
    g, q = G.exponential(), views.sample_queries(df, 2)
    with pytest.raises(ValueError):
        scan_knn(df, q, g, 0)
    index = build_index(df, g, 2)
    for p in (0, 1.1):
        with pytest.raises(ValueError):
            approx.approx_knn(index, q, 3, p)
    bad = lambda v: spark.createDataFrame([(1, [1.0, 2.0]), (2, v)], "id long, vec array<double>")
    for v in (None, [1.0], [1.0, float("nan")], [1.0, None]):
        with pytest.raises(ValueError):
            build_index(bad(v), g, 1)
        with pytest.raises(PySparkException):
            G.check_domain(bad(v), g, 2).collect()
    with pytest.raises(ValueError, match="positive"):
        build_index(bad([0.0, 1.0]), G.itakura_saito(), 1)
    assert build_index(G.shift_positive(bad([-3.0, 1.0]), 0.5), G.itakura_saito(), 1).n == 2
