"""What an index costs before it answers: passes over the points, and what meets on the driver."""

import hashlib

import numpy as np
import pyarrow as pa
import pytest
from divknn import measures
from divknn.functions import generators as G
from divknn.operators import baselines, index as indexes
from divknn.operators.balltree import build_tree
from divknn.operators.search import candidates, query_budgets
from divknn.plans import partition
from divknn.sources import views


def points_of(spark, x):
    return spark.createDataFrame([(i, None if r is None else list(r)) for i, r in enumerate(x)], "id long, vec array<double>")


def test_words_are_hashed_many_at_once(monkeypatch):
    """As hashlib does it, around the edges of a block of MD5 and of a slice."""
    monkeypatch.setattr(views, "HASHED", 7)
    words = [b"w" * k for k in (0, 1, 3, 54, 55, 56, 57, 63, 64, 65, 119, 500)] + [str(i).encode() for i in range(50)]
    for lo in (0, 5):
        got = views._word_hashes(pa.array(words, pa.binary()).slice(lo))
        assert got.tolist() == [int(hashlib.md5(w).hexdigest()[:8], 16) for w in words[lo:]]
    assert not len(views._word_hashes(pa.array([], pa.binary())))


def test_one_pass_tells_all(spark):
    x = np.random.default_rng(3).random((500, 120)) + 0.5
    found = partition.survey(points_of(spark, x.tolist()).repartition(5))
    assert (found.n, found.d, found.most, found.bad, found.low) == (500, 120, 120, 0, x.min())
    assert np.allclose(found.sums, x.sum(0)) and np.allclose(found.cross, x.T @ x)
    assert partition.survey(points_of(spark, x.tolist()), False).cross is None
    odd = partition.survey(points_of(spark, [[1.0, 2.0], None, [float("nan"), float("nan")], [1.0, None], [-3.0], []]).coalesce(1))
    assert (odd.n, odd.d, odd.most, odd.bad, odd.low, odd.cross) == (6, 0, 2, 3, -3.0, None)
    assert partition.survey(points_of(spark, [])).n == 0
    for last in ([1.0], [1.0, float("nan")], None):
        bad = points_of(spark, [[1.0, 2.0], last]).repartition(2)
        assert partition.survey(bad).cross is None
        with pytest.raises(ValueError):
            partition.moments(bad)


def test_the_sample_stays_off_the_driver(spark, monkeypatch):
    """Trees and cells are those of the whole sample, which no one collects; a stored table is not copied."""
    x = np.random.default_rng(4).random((700, 40)) + 0.1
    df, g = points_of(spark, x.tolist()).repartition(3).cache(), G.itakura_saito()
    sample = indexes.bounded_sample(df, 700, 300)
    for module in (indexes, baselines):
        monkeypatch.setattr(module, "bounded_sample", None, raising=False)
    monkeypatch.setattr(indexes.on_sample, "__defaults__", (300,))
    monkeypatch.setattr(indexes, "saved", lambda frame, path, real=indexes.saved: pytest.fail("copied") if path.endswith("/input") else real(frame, path))
    monkeypatch.setattr(baselines, "saved", indexes.saved)
    index = indexes.build_index(df, g, 3, centre=True, stored=True)
    assert np.array_equal(index.centre, sample.mean(0))
    for j, t in enumerate(index.trees):
        want = build_tree(sample, g, index.blocks[j], max(8, round(64 * len(sample) / 700)), 12, 42 + j)
        assert np.array_equal(t.centre, want.centre) and t.dims == want.dims and t.count[0] == 700
    cells = baselines.build_cells(df, g, stored=True)
    assert np.array_equal(cells.edges[:, 1:-1], np.quantile(sample, np.arange(1, 64) / 64, axis=0).T)
    again = indexes.load_index(spark, index.path)
    assert all(np.array_equal(getattr(a, c), getattr(b, c)) for a, b in zip(index.trees, again.trees, strict=True) for c in ("centre", "radius", "count", "leaf", "left", "depth"))


@pytest.mark.parametrize("granularity", ["leaf", "point"])
def test_candidates_are_counted_where_they_lie(spark, granularity):
    x = np.random.default_rng(6).random((600, 12)) + 0.1
    index = indexes.build_index(points_of(spark, x.tolist()), G.itakura_saito(), 3, page_bytes=400, leaf_size=8)
    qids, y = np.arange(4), x[:4]
    r = query_budgets(index, qids, y, 5)["r"] / 6
    want = {}
    for c in candidates(index, qids, y, r, granularity).collect():
        want.setdefault(c["qid"], []).append(c["page"])
    got = {c["qid"]: (c["n_candidates"], c["data_pages"]) for c in measures.candidate_share(index, qids, y, r, granularity).collect()}
    assert got == {q: (len(p), len(set(p))) for q, p in want.items()} and want
