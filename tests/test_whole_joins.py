"""Joins in which all rows take part, against brute force."""

import numpy as np
import pytest
from divknn import workloads
from divknn.functions import generators as G
from divknn.operators import vectors
from divknn.sources import views


@pytest.fixture(autouse=True)
def several_blocks(monkeypatch):
    monkeypatch.setattr(vectors, "QUERY_NUMBERS", 400_000)


def arrays(spark, sf, view):
    rows = sorted((r["id"], r["vec"]) for r in views.catalogue()[view].load(spark, sf).collect())
    return np.array([k for k, _ in rows]), np.array([v for _, v in rows])


def test_all_similar_pairs(spark, sf):
    ids, x = arrays(spark, sf, "emb64")
    g = G.exponential()
    d = np.array([g.divergence(x, y) for y in x]).T  # of each point from each query
    d = np.minimum(d, d.T)
    a, b = np.nonzero(np.triu(d <= 0.9, 1))
    got = {(r["qid"], r["id"]): r["divergence"] for r in workloads.QUERIES["similar_pairs_all"](spark, sf).collect()}
    want = {(int(ids[i]), int(ids[j])): d[i, j] for i, j in zip(a, b, strict=True)}
    assert got.keys() == want.keys() and len({q for q, _ in got}) > 20
    assert all(abs(v - want[k]) < 1e-5 for k, v in got.items())
    assert workloads.QUERIES["similar_pairs_all"](spark, sf).count() == len(want)


def test_knn_join_of_all_parts(spark, sf):
    ids, x = arrays(spark, sf, "part_month")
    g = G.itakura_saito()
    got = {(r["qid"], r["rank"]): r["id"] for r in workloads.QUERIES["knn_join_parts"](spark, sf).collect()}
    want = {}
    for q, y in zip(ids, x, strict=True):
        for rank, i in enumerate(np.lexsort((ids, np.round(g.divergence(x, y), 9)))[:5], 1):
            want[int(q), rank] = int(ids[i])
    assert got == want and len(got) == 5 * len(ids)
