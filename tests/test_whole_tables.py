"""Searches in which every id divisible by 20 asks, in several query blocks, and those whose SQL suits small tables only."""

import pytest
from divknn import part_queries, workloads  # noqa: F401
from divknn.operators import vectors

from .compare import same


@pytest.mark.parametrize("name", sorted(workloads.SMALL_ORACLES))
def test_all_order_lines(spark, sf, name):
    same(workloads.QUERIES[name](spark, sf), workloads.SMALL_ORACLES[name], sf)


@pytest.mark.parametrize("name", ["candidate_share", "exact_knn_emb_exp", "scan_knn_columns_exp", "tree_range_emb_exp", "cell_knn_emb_exp", "tree_knn_emb_exp", "approx_knn_p100", "similar_pairs_all"])
def test_more_queries_than_a_block(spark, sf, name, monkeypatch):
    monkeypatch.setattr(vectors, "QUERY_NUMBERS", 20_000)
    same(workloads.QUERIES[name](spark, sf), workloads.ORACLES[name], sf)


def test_measures_cover_all_queries(spark, sf, monkeypatch):
    monkeypatch.setattr(vectors, "QUERY_NUMBERS", 20_000)
    for name in ("page_reads", "block_overlap"):
        assert sorted(r["qid"] for r in workloads.QUERIES[name](spark, sf).collect()) == list(range(0, 500, 20))
