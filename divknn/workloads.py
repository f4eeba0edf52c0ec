"""Registered queries with their SQL, and the experiment runner."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from divknn import measures
from divknn.functions import generators as G
from divknn.functions.generators import divergence
from divknn.operators import approx, baselines, relational
from divknn.operators.index import Index, build_index
from divknn.operators.search import blockwise_knn_union, exact_knn, query_budgets, range_search
from divknn.operators.search import block_range as block_range_
from divknn.operators.summaries import budgets, ceiling, data_summary, query_summary
from divknn.operators.vectors import all_pairs, broadcast_parts, each_block, given, query_blocks, scan_knn, scan_knn_columns, union_of
from divknn.plans import costmodel, partition
from divknn.sources import views
from divknn.storage import delete
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
#: SQL over all order lines: too slow on larger tables, tests compare with it on the smallest ones.
SMALL_ORACLES: dict[str, str] = {}
K = 20

_SHORT = {"exp": "exponential", "isd": "itakura_saito", "sqeuclid": "squared_euclidean", "shannon": "shannon", "burg": "burg", "lp3": "lp_norm", "quasi_half": "lp_quasi"}
_CATALOGUE = views.catalogue()


def _register(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        (SMALL_ORACLES if "FROM lineitem" in oracle and "l_linenumber" in oracle else ORACLES)[name] = oracle


def _queries(points: DataFrame) -> DataFrame:
    """Every point with an id divisible by 20 asks, against all points."""
    return points.where("id % 20 = 0").select(F.col("id").alias("qid"), F.col("vec").alias("yvec"))


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("qid", "rank", "id", F.round("divergence", 6).alias("divergence"))


def _pairs_sql(view: str, gen: G.Generator, where: str = "", scale: str = "{t}", ask: str = "WHERE id % 20 = 0") -> str:
    a, b = scale.format(t="p.x"), scale.format(t="y.x")
    return f"""v AS MATERIALIZED (SELECT id::BIGINT id, i::INT i, x::DOUBLE x FROM {_CATALOGUE[view].sql}),
 q AS (SELECT DISTINCT id FROM v {ask}), y AS MATERIALIZED (SELECT v.* FROM v JOIN q USING (id)),
 d AS (SELECT y.id qid, p.id, greatest(sum({gen.term(f'({a})', f'({b})')}), 0) divergence FROM v p JOIN y ON p.i = y.i {where} GROUP BY y.id, p.id)"""


def _knn_sql(view: str, gen: G.Generator, k: int = K, where: str = "", scale: str = "{t}", ask: str = "WHERE id % 20 = 0") -> str:
    return f"""WITH {_pairs_sql(view, gen, where, scale, ask)},
 r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(divergence, 9), id) rank FROM d)
 SELECT qid, rank::INT rank, id, round(divergence, 6) divergence FROM r WHERE rank <= {k}"""


# Divergences of pairs: one query per generator.
for short, full in _SHORT.items():
    g = G.get(full)
    view = "emb64_pos" if g.domain == "positive" else "emb64"

    def pairs(spark, d, g=g, view=view):
        p = _CATALOGUE[view].load(spark, d)
        return all_pairs(p, _queries(p), g, 6)

    _register(f"div_{short}", pairs, f"WITH {_pairs_sql(view, g)} SELECT qid, id, round(divergence, 6) divergence FROM d")
    _register(f"scan_knn_{short}", lambda s, d, g=g, view=view: _rounded(scan_knn(p := _CATALOGUE[view].load(s, d), _queries(p), g, K)), _knn_sql(view, g))
    _register(f"scan_knn_columns_{short}", lambda s, d, g=g, view=view: _rounded(scan_knn_columns(p := _CATALOGUE[view].load(s, d), _queries(p), g, K)), _knn_sql(view, g))

_WEIGHTS = [1 + (i % 7) / 2 for i in range(64)]
_DIAGONAL = G.mahalanobis(_WEIGHTS)


def _div_mahal(spark, d):
    p = _DIAGONAL.prepared(_CATALOGUE["emb64"].load(spark, d))
    return union_of([p.crossJoin(q) for q in broadcast_parts(_queries(p), 64)]).select("qid", "id", F.round(divergence(_DIAGONAL, "vec", "yvec"), 6).alias("divergence"))


_register("div_mahal_diag", _div_mahal, f"WITH {_pairs_sql('emb64', _DIAGONAL, '', '{t} * sqrt(1 + (p.i % 7) / 2.0)')} SELECT qid, id, round(divergence, 6) divergence FROM d")


def _div_mahal_full(spark, d):
    """A full quadratic form: tridiagonal, 2 on the diagonal and a half beside it."""
    q = 2 * np.eye(64) + 0.5 * (np.eye(64, k=1) + np.eye(64, k=-1))
    g = G.squared_euclidean()
    p = G.whiten(_CATALOGUE["emb64"].load(spark, d), q)
    return all_pairs(p, _queries(p), g, 6)


_register("div_mahal_full", _div_mahal_full, f"""WITH v AS (SELECT id::BIGINT id, i::INT i, x FROM {_CATALOGUE['emb64'].sql}), y AS (SELECT * FROM v WHERE id % 20 = 0),
 e AS (SELECT y.id qid, p.id id, p.i i, p.x - y.x x FROM v p JOIN y ON p.i = y.i)
 SELECT a.qid, a.id, round(greatest(sum(a.x * b.x * CASE WHEN a.i = b.i THEN 2 ELSE 0.5 END) / 2, 0), 6) divergence FROM e a JOIN e b ON a.qid = b.qid AND a.id = b.id AND abs(a.i - b.i) <= 1 GROUP BY a.qid, a.id""")


# Exact search: views, then variants.
def _index(spark: SparkSession, d: str, view: str, m: int | str = 8, **kw) -> tuple[Index, DataFrame]:
    p = _CATALOGUE[view].load(spark, d)
    index = build_index(p, G.get(_CATALOGUE[view].generator), m, **kw)
    return index, _queries(index.points)  # the view is worked out once


def _exact(view: str, m: int | str = 8, build: dict | None = None, k: int = K, **search):
    def query(spark, d):
        index, q = _index(spark, d, view, m, **(build or {}))
        return _rounded(exact_knn(index, q, k, **search))

    return query


for name, view in {"emb_exp": "emb64", "emb_isd": "emb64_pos", "doc_isd": "doc_hash100", "page_exp": "page_hash256", "event_exp": "event_profile192", "line_exp": "line4", "part_isd": "part_month"}.items():
    _register(f"exact_knn_{name}", _exact(view), _knn_sql(view, G.get(_CATALOGUE[view].generator)))
_EMB = _knn_sql("emb64", G.exponential())
for name, kw in {
    "contiguous": {"build": {"strategy": "contiguous"}}, "decorrelated": {"build": {"strategy": "decorrelated"}}, "random": {"build": {"strategy": "random"}}, "m1": {"m": 1}, "m64": {"m": 64},
    "point": {"granularity": "point"}, "leaf": {"granularity": "leaf"}, "centred": {"build": {"centre": True}}, "tightened": {"tighten": True}, "sampled_bound": {"sample": 0.3}, "auto_m": {"m": "auto"},
}.items():
    _register(f"exact_knn_{name}", _exact("emb64", **kw), _EMB)
_register("exact_knn_noself", _exact("emb64", exclude_self=True), _knn_sql("emb64", G.exponential(), where="WHERE p.id <> y.id"))
for k in (40, 60, 80, 100):
    _register(f"exact_knn_k{k}", _exact("emb64", k=k), _knn_sql("emb64", G.exponential(), k))
for dims, m in {10: 3, 50: 9, 200: 29, 400: 50}.items():
    _register(f"exact_knn_doc{dims}", _exact(f"doc_hash{dims}", m), _knn_sql(f"doc_hash{dims}", G.itakura_saito()))
for dims in (8, 16, 32):
    _register(f"exact_knn_emb{dims}", _exact(f"emb{dims}", 4), _knn_sql(f"emb{dims}", G.exponential()))

# Baselines.
for name, view in {"emb_exp": "emb64", "emb_isd": "emb64_pos", "doc_isd": "doc_hash50", "line_isd": "line8"}.items():
    g = G.get(_CATALOGUE[view].generator)
    _register(f"cell_knn_{name}", lambda s, d, v=view, g=g: _rounded(baselines.cell_knn(baselines.build_cells(p := _CATALOGUE[v].load(s, d), g), _queries(p), K)), _knn_sql(view, g))
    _register(f"tree_knn_{name}", lambda s, d, v=view, g=g: _rounded(baselines.tree_knn(baselines.build_whole_tree(p := _CATALOGUE[v].load(s, d), g), _queries(p), K)), _knn_sql(view, g))
_register("cell_knn_width", lambda s, d: _rounded(baselines.cell_knn(baselines.build_cells(p := _CATALOGUE["emb64"].load(s, d), G.exponential(), edges="width", bits=4), _queries(p), K)), _EMB)
_register("guided_tree_knn_p100", lambda s, d: _rounded(baselines.guided_tree_knn(baselines.build_whole_tree(p := _CATALOGUE["emb64"].load(s, d), G.exponential()), _queries(p), K, 1.0)), _EMB)
_register("guided_tree_knn_p80", lambda s, d: _rounded(baselines.guided_tree_knn(baselines.build_whole_tree(p := _CATALOGUE["emb64"].load(s, d), G.exponential()), _queries(p), K, 0.8)))


def _blockwise(spark, d):
    p = _CATALOGUE["emb64"].load(spark, d)
    return _rounded(blockwise_knn_union(p, _queries(p), G.exponential(), partition.contiguous_blocks(64, 8), K))


_register("blockwise_knn_union", _blockwise, f"""WITH {_pairs_sql('emb64', G.exponential())},
 b AS (SELECT y.id qid, p.id, p.i // 8 b, greatest(sum({G.exponential().term('p.x', 'y.x')}), 0) divergence FROM v p JOIN y ON p.i = y.i GROUP BY ALL),
 near AS (SELECT DISTINCT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid, b ORDER BY round(divergence, 9), id) r FROM b) WHERE r <= {K}),
 r AS (SELECT d.*, row_number() OVER (PARTITION BY qid ORDER BY round(divergence, 9), id) rank FROM d JOIN near USING (qid, id))
 SELECT qid, rank::INT rank, id, round(divergence, 6) divergence FROM r WHERE rank <= {K}""")

# Ranges.
_RADII = {"emb_exp": ("emb64", 0.9), "emb_isd": ("emb64_pos", 0.9)}
for name, (view, r) in _RADII.items():
    g = G.get(_CATALOGUE[view].generator)

    def ranged(s, d, view=view, g=g, r=r):
        p = _CATALOGUE[view].load(s, d)
        index = baselines.build_whole_tree(p, g)
        return range_search(index, _queries(p).withColumn("radius", F.lit(r))).select("qid", "id", F.round("divergence", 6).alias("divergence"))

    _register(f"tree_range_{name}", ranged, f"WITH {_pairs_sql(view, g)} SELECT qid, id, round(divergence, 6) divergence FROM d WHERE divergence <= {r}")

    def blocked(s, d, view=view, g=g):
        p = _CATALOGUE[view].load(s, d)
        return block_range_(p, _queries(p).withColumn("radius", F.lit(0.1)), g, list(range(16))).select("qid", "id", F.round("divergence", 6).alias("divergence"))

    _register(f"block_range_{name}", blocked, f"WITH {_pairs_sql(view, g, 'WHERE p.i < 16')} SELECT qid, id, round(divergence, 6) divergence FROM d WHERE divergence <= 0.1 + 1e-9 * 1.1")

# Summaries, bounds and the cost model.
_B8 = partition.contiguous_blocks(64, 8)


def _sums(spark, d):
    p = _CATALOGUE["emb64"].load(spark, d)
    return data_summary(p, G.exponential(), _B8), query_summary(_queries(p), G.exponential(), _B8)


_SUMS_SQL = f"""v AS MATERIALIZED (SELECT id::BIGINT id, i::INT i, x FROM {_CATALOGUE['emb64'].sql}),
 p AS MATERIALIZED (SELECT id, i // 8 b, sum(exp(x)) phi, sum(x * x) sq FROM v GROUP BY ALL),
 q AS MATERIALIZED (SELECT id qid, i // 8 b, -sum(exp(x)) phi, sum(x * exp(x)) dot, sum(exp(x) * exp(x)) sq FROM v WHERE id % 20 = 0 GROUP BY ALL),
 c AS MATERIALIZED (SELECT qid, id, p.b, p.phi + q.phi + q.dot + sqrt(p.sq * q.sq) r FROM p JOIN q ON p.b = q.b),
 t AS MATERIALIZED (SELECT qid, id, sum(r) total FROM c GROUP BY ALL),
 k AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(total, 9), id) rank FROM t) WHERE rank <= {K})"""
_register("data_summary", lambda s, d: _sums(s, d)[0].select("id", F.posexplode("psum").alias("block", "p")).select("id", "block", F.round("p.phi_sum", 6).alias("phi_sum"), F.round("p.sq_norm", 6).alias("sq_norm")),
          f"WITH {_SUMS_SQL} SELECT id, b::INT block, round(phi, 6) phi_sum, round(sq, 6) sq_norm FROM p")
_register("query_summary", lambda s, d: _sums(s, d)[1].select("qid", F.posexplode("qsum").alias("block", "q")).select("qid", "block", *[F.round(f"q.{c}", 6).alias(c) for c in ("neg_phi", "self_dot", "grad_sq")]),
          f"WITH {_SUMS_SQL} SELECT qid, b::INT block, round(phi, 6) neg_phi, round(dot, 6) self_dot, round(sq, 6) grad_sq FROM q")


def _budgets(spark, d):
    return budgets(*_sums(spark, d), K)


_register("budgets_k20", lambda s, d: _budgets(s, d).select("qid", "pivot_id", F.posexplode("budgets").alias("block", "r")).select("qid", "pivot_id", "block", F.round("r", 6).alias("budget")),
          f"WITH {_SUMS_SQL} SELECT k.qid, k.id pivot_id, c.b::INT block, round(c.r, 6) budget FROM k JOIN c ON c.qid = k.qid AND c.id = k.id WHERE rank = {K}")
_register("ceiling_top", lambda s, d: _budgets(s, d).select("qid", "pivot_id", F.round("total", 6).alias("total")), f"WITH {_SUMS_SQL} SELECT qid, id pivot_id, round(total, 6) total FROM k WHERE rank = {K}")


def _violations(spark, d):
    p = _CATALOGUE["emb64"].load(spark, d)
    psum, qsum = _sums(spark, d)
    both = union_of([p.crossJoin(q) for q in broadcast_parts(_queries(p), 64)]).join(psum, "id").join(qsum, "qid")
    dist = divergence(G.exponential(), "vec", "yvec")
    from divknn.operators.summaries import floor_bound

    return both.agg(F.sum((ceiling() < dist - 1e-9).cast("long")).alias("above"), F.sum((floor_bound() > dist + 1e-9).cast("long")).alias("below"), F.count("*").alias("pairs"))


_register("ceiling_violations", _violations, f"WITH v AS (SELECT DISTINCT vec_id FROM embeddings) SELECT 0::BIGINT above, 0::BIGINT below, count(*) * count(*) FILTER (WHERE vec_id % 20 = 0) pairs FROM v")


def _correlation(spark, d):
    r = partition.abs_correlation(_CATALOGUE["emb64"].load(spark, d))
    rows = [(i, j, round(float(r[i, j]), 6)) for i in range(64) for j in range(i + 1, 64)]
    return spark.createDataFrame(rows, "a int, b int, r double")


_register("abs_correlation", _correlation, f"WITH v AS (SELECT id, i::INT i, x FROM {_CATALOGUE['emb64'].sql}) SELECT a.i a, b.i b, round(abs(corr(a.x, b.x)), 6) r FROM v a JOIN v b ON a.id = b.id AND a.i < b.i GROUP BY ALL")
#: Six dimensions of which the first is closest to the fifth, and that to the sixth.
SIX = [[1, 0.2, 0.1, 0.3, 0.9, 0.4], [0.2, 1, 0.5, 0.6, 0.1, 0.2], [0.1, 0.5, 1, 0.55, 0.2, 0.1], [0.3, 0.6, 0.55, 1, 0.2, 0.3], [0.9, 0.1, 0.2, 0.2, 1, 0.8], [0.4, 0.2, 0.1, 0.3, 0.8, 1]]


def _six(spark, d):
    groups = partition.group_similar(np.array(SIX), 3, first=0)
    return spark.createDataFrame([(g, "abcdef"[i]) for g, own in enumerate(groups) for i in own], "group_no int, dim string")


_register("six_dim_groups", _six, "SELECT * FROM (VALUES (0, 'a'), (0, 'e'), (0, 'f'), (1, 'b'), (1, 'c'), (1, 'd')) t(group_no, dim)")


def _curve(spark, d):
    model = costmodel.CostModel(500.0, 0.9, 0.002, 100_000, 128)
    return spark.createDataFrame([(m, round(model.cost(m, 20), 3)) for m in range(1, 65)], "m int, cost double")


_register("cost_curve", _curve, "SELECT m::INT m, round(128 + m * 100000.0::DOUBLE + 100000 * log2(20) + 0.002 * 500 * pow(0.9, m) * 100000 * (128 + log2(20)), 3) cost FROM range(1, 65) t(m)")


def _model_fit(spark, d):
    rows = []
    for view in ("emb64", "doc_hash100", "line_mix64"):
        p = _CATALOGUE[view].load(spark, d).cache()
        g, n, dims = G.get(_CATALOGUE[view].generator), p.count(), _CATALOGUE[view].d
        model = costmodel.fit(p, g, n, dims)
        rows.append((view, model.a, model.alpha, model.beta, float(np.clip(model.root(), -1e6, 1e6)), model.optimal_blocks()))
        p.unpersist()
    return spark.createDataFrame(rows, "view string, a double, alpha double, beta double, root double, m int")


_register("cost_model_fit", _model_fit)


# Probabilistic search and measures.
def _approx(p: float, apply: str = "whole", family: str = "auto"):
    def query(spark, d):
        index, q = _index(spark, d, "emb64")
        out = approx.approx_knn(index, q, K, p, family, apply)
        return out.select("qid", "rank", "id", F.round("divergence", 6).alias("divergence"))

    return query


for p in (70, 80, 90):
    for how in ("whole", "root"):
        _register(f"approx_knn_p{p}_{how}", _approx(p / 100, how))
for family in ("normal", "uniform", "empirical"):
    _register(f"approx_knn_p80_{family}", _approx(0.8, "whole", family))
_register("approx_knn_p100", _approx(1.0), _EMB)


def _ratio_one(spark, d):
    index, q = _index(spark, d, "emb64")
    truth = scan_knn(_CATALOGUE["emb64"].load(spark, d), q, G.exponential(), K)
    return measures.overall_ratio(approx.approx_knn(index, q, K, 1.0), truth).select("qid", F.round("ratio", 6).alias("ratio"), "undefined")


_register("overall_ratio_p1", _ratio_one, "SELECT vec_id qid, 1.0::DOUBLE ratio, 0::BIGINT undefined FROM embeddings WHERE vec_id % 20 = 0")


def _shares(spark, d):
    index, q = _index(spark, d, "emb64", 8, strategy="contiguous")
    return each_block(q, 64, lambda qids, y: measures.candidate_share(index, qids, y, query_budgets(index, qids, y, K)["r"], "point")).select("qid", "n_candidates", F.round("share", 6).alias("share"))


_SHARE_SQL = f"""WITH {_SUMS_SQL}, kb AS (SELECT k.qid, c.b, c.r FROM k JOIN c ON c.qid = k.qid AND c.id = k.id WHERE rank = {K}),
 bd AS (SELECT y.id qid, x.id, x.i // 8 b, greatest(sum(exp(x.x) - exp(y.x) - exp(y.x) * (x.x - y.x)), 0) d FROM v x JOIN v y ON x.i = y.i WHERE y.id % 20 = 0 GROUP BY ALL),
 cand AS (SELECT DISTINCT bd.qid, bd.id FROM bd JOIN kb ON kb.qid = bd.qid AND kb.b = bd.b WHERE bd.d <= kb.r + 1e-9 * (1 + abs(kb.r)))
 SELECT qid, count(*) n_candidates, round(count(*)::DOUBLE / (SELECT count(DISTINCT id) FROM v), 6) share FROM cand GROUP BY qid"""
_register("candidate_share", _shares, _SHARE_SQL)


def _pages(spark, d):
    index, q = _index(spark, d, "emb64", 8, strategy="contiguous")
    return each_block(q, 64, lambda qids, y: measures.candidate_share(index, qids, y, query_budgets(index, qids, y, K)["r"], "point")).select("qid", "data_pages")


_register("page_reads", _pages)


def _tight(spark, d):
    p = _CATALOGUE["emb64"].load(spark, d)
    psum, qsum = _sums(spark, d)
    return measures.tightness(psum, qsum, scan_knn(p, _queries(p), G.exponential(), 100))


_register("ceiling_tightness", lambda s, d: _tight(s, d).select(F.round("mean", 6).alias("mean"), F.round("median", 6).alias("median")), f"""WITH {_SUMS_SQL},
 dd AS (SELECT y.id qid, x.id, greatest(sum({G.exponential().term('x.x', 'y.x')}), 0) divergence FROM v x JOIN v y ON x.i = y.i WHERE y.id % 20 = 0 GROUP BY ALL),
 n AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(divergence, 9), id) r FROM dd) WHERE r <= 100 AND divergence > 1e-9)
 SELECT round(avg(total / divergence), 6) mean, round(median(total / divergence), 6) median FROM n JOIN t USING (qid, id)""")


def _overlap(spark, d):
    index, q = _index(spark, d, "emb64", 8)
    return each_block(q, 64, lambda qids, y: measures.block_overlap(index, qids, y, query_budgets(index, qids, y, K)["r"]))


_register("block_overlap", _overlap)


def _dims(spark, d):
    found = approx.fit_dimensions(_CATALOGUE["emb64"].load(spark, d))
    return spark.createDataFrame([(i, found.family[i], float(found.p1[i]), float(found.p2[i])) for i in range(64)], "dim int, family string, p1 double, p2 double")


_register("dimension_fit", _dims)


# Operators around.
def _vote(spark, d):
    p = _CATALOGUE["emb64"].load(spark, d)
    near = scan_knn(p, _queries(p), G.exponential(), 15, exclude_self=True)
    return relational.label_vote(near, views.read(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "label"))


_register("knn_label_vote", _vote, f"""WITH n AS ({_knn_sql('emb64', G.exponential(), 15, where='WHERE p.id <> y.id')}), v AS (SELECT n.qid, e.label, count(*) votes FROM n JOIN embeddings e ON e.vec_id = n.id GROUP BY ALL)
 SELECT qid, label, votes FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY votes DESC, label) r FROM v) WHERE r = 1""")


def _filtered(spark, d):
    docs = _CATALOGUE["doc_hash50"].load(spark, d)
    marked = docs.join(views.read(spark, d, "documents").select(F.col("doc_id").alias("id"), "lang"), "id")
    return _rounded(relational.filtered_knn(marked, F.col("lang") == "en", _queries(docs), G.itakura_saito(), K))


_register("knn_filtered_lang", _filtered, _knn_sql("doc_hash50", G.itakura_saito(), where="WHERE p.id IN (SELECT doc_id FROM documents WHERE lang = 'en')"))


def _join(spark, d):
    p = _CATALOGUE["part_month"].load(spark, d)
    near = relational.knn_join(p, p, G.itakura_saito(), 5)
    names = views.read(spark, d, "part").select(F.col("p_partkey").alias("id"), "p_brand")
    return _rounded(near).join(names, "id").select("qid", "rank", "id", "divergence", "p_brand")


_register("knn_join_parts", _join, f"WITH n AS ({_knn_sql('part_month', G.itakura_saito(), 5, ask='')}) SELECT n.*, p_brand FROM n JOIN part ON p_partkey = n.id")


def _pairs_near(spark, d):
    p = _CATALOGUE["emb64"].load(spark, d)
    return relational.similar_pairs(p, p.where("id % 20 = 0"), G.exponential(), 0.9).select("qid", "id", F.round("divergence", 6).alias("divergence"))


_register("similar_pairs", _pairs_near, f"WITH {_pairs_sql('emb64', G.exponential())} SELECT qid, id, round(divergence, 6) divergence FROM d WHERE divergence <= 0.9 AND qid <> id")


_register("similar_pairs_all", lambda s, d: relational.all_similar_pairs(_CATALOGUE["emb64"].load(s, d), G.exponential(), 0.9, digits=6),
          f"""WITH {_pairs_sql('emb64', G.exponential(), ask='')} SELECT least(qid, id) qid, greatest(qid, id) id, round(min(divergence), 6) divergence FROM d WHERE divergence <= 0.9 AND qid <> id GROUP BY ALL""")


# Experiments.
ROLES = {"event_profile192": 28, "doc_hash400": 50, "page_hash256": 37, "line_mix128": 22}
#: Page bytes of each role; 32 KB elsewhere.
PAGES = {"doc_hash400": 128 << 10, "page_hash256": 64 << 10, "line_mix128": 64 << 10}
COLUMNS = "workload string, view string, method string, k int, m int, p double, build_s double, run_s double, index_pages double, data_pages double, cand_share double, overall_ratio double, recall double, task_s double"


def _mean(df: DataFrame, column: str) -> float:
    return float(df.agg(F.avg(column)).first()[0] or 0.0)


class Runner:
    """Runs the experiments on a folder of tables and gathers one row a configuration."""

    def __init__(self, spark: SparkSession, sf_dir: str, n_queries: int = 50):
        self.spark, self.sf_dir, self.n, self.rows = spark, sf_dir, n_queries, []
        self._views: dict[str, DataFrame] = {}

    def view(self, name: str) -> tuple[DataFrame, G.Generator, DataFrame]:
        if name not in self._views:
            from divknn.storage import saved_vectors as saved

            self._views[name] = saved(_CATALOGUE[name].load(self.spark, self.sf_dir))
        p = self._views[name]
        return p, G.get(_CATALOGUE[name].generator), views.sample_queries(p, self.n)

    def add(self, workload, view, method, k=0, m=0, p=1.0, build=0.0, run=0.0, index_pages=0.0, data_pages=0.0, share=0.0, ratio=1.0, recall=1.0, task=0.0) -> None:
        self.rows.append((workload, view, method, int(k), int(m), *map(float, (p, build, run, index_pages, data_pages, share, ratio, recall, task))))

    def table(self) -> DataFrame:
        kinds = {"string": pa.string(), "int": pa.int32(), "double": pa.float64()}
        names = [c.split() for c in COLUMNS.split(", ")]
        return given(self.spark, **{c: pa.array([r[i] for r in self.rows], kinds[kind]) for i, (c, kind) in enumerate(names)})

    def _forest(self, workload, view, m, ks, strategy="decorrelated", centre=False, method="forest", first=None, granularity="leaf") -> None:
        p, g, q = self.view(view)
        began = time.perf_counter()
        index = build_index(p, g, m, strategy, centre=centre, first=first, page_bytes=PAGES.get(view, 32 << 10), stored=True)
        built = time.perf_counter() - began
        qids, y = next(query_blocks(q, index.d))
        for k in ks:
            before = measures.task_seconds(self.spark)
            _, s = measures.timed(lambda k=k: exact_knn(index, q, k, granularity))
            task = measures.task_seconds(self.spark) - before
            r = query_budgets(index, qids, y, k)["r"]
            share = measures.candidate_share(index, qids, y, r, granularity)
            self.add(workload, view, method, k, index.m, build=built, run=s, task=task, index_pages=measures.forest_index_pages(index, y, r), data_pages=_mean(share, "data_pages"), share=_mean(share, "share"))
        delete(self.spark, index.path)  # the next configuration builds its own

    def build_time(self, names=("event_profile192", "doc_hash100", "emb64", "page_hash256", "gauss200", "unif200")) -> None:
        for v in names:
            p, g, _ = self.view(v)
            for method, work in (("forest", lambda p=p, g=g: build_index(p, g, 16, stored=True)), ("tree", lambda p=p, g=g: baselines.build_whole_tree(p, g, stored=True)), ("cells", lambda p=p, g=g: baselines.build_cells(p, g, stored=True))):
                built, s = measures.timed(work)
                self.add("build_time", v, method, build=s)
                delete(self.spark, built.path)

    def blocks(self, names=tuple(ROLES), ms=(1, 2, 4, 8, 16, 32), ks=(20, 40, 60)) -> None:
        for v in names:
            for m in ms:
                self._forest("blocks", v, m, ks)

    def partitioner(self, names=tuple(ROLES), m: int | None = None) -> None:
        for v in names:
            for strategy in ("contiguous", "decorrelated", "random"):
                self._forest("partitioner", v, m or ROLES[v], (K,), strategy, method=strategy)

    def start_dimension(self, view: str = "doc_hash100", m: int = 13, starts: int = 10) -> None:
        for first in range(starts):
            self._forest("start_dimension", view, m, (K,), first=first, method=f"start{first}")

    def neighbours(self, names=tuple(ROLES), ks=(20, 40, 60, 80, 100)) -> None:
        for v in names:
            self._forest("neighbours", v, ROLES[v], ks)
            self._others("neighbours", v, ks)

    def derived(self, names=tuple(ROLES), ms=(1, 2, 4, 8, 16, 32), ks=(20, 40, 60)) -> None:
        """The number of blocks that the model derives (method ``derived``) among measured ones: is it the cheapest?"""
        for v in names:
            p, g, _ = self.view(v)
            n, d = p.count(), _CATALOGUE[v].d
            model = costmodel.fit(p, g, n, d)
            for m in sorted({*ms, model.optimal_blocks()}):
                self._forest("derived", v, m, ks, method="derived" if m == model.optimal_blocks() else "measured")

    def dimensions(self, pairs=((10, 3), (50, 9), (100, 13), (200, 29), (400, 50))) -> None:
        for d, m in pairs:
            self._forest("dimensions", f"doc_hash{d}", m, (K,))
            self._others("dimensions", f"doc_hash{d}", (K,))

    def _others(self, workload, view, ks, part=None, method="") -> None:
        """Both baselines on a view."""
        p, g, q = self.view(view)
        p, size = part if part is not None else p, PAGES.get(view, 32 << 10)
        cells, tree = baselines.build_cells(p, g, page_bytes=size, stored=part is None), baselines.build_whole_tree(p, g, page_bytes=size, stored=part is None)
        qids, y = next(query_blocks(q, tree.d))
        for k in ks:
            _, s = measures.timed(lambda k=k: baselines.cell_knn(cells, q, k))
            pages = measures.cell_pages(cells, tree, qids, y, k)
            self.add(workload, view, f"cells{method}", k, run=s, index_pages=cells.index_pages(), data_pages=_mean(pages, "data_pages"), share=_mean(pages, "n_candidates") / tree.n)
            began = time.perf_counter()
            _, visits = baselines.tree_search(tree, qids, y, k)
            self.add(workload, view, f"tree{method}", k, 1, run=time.perf_counter() - began, index_pages=tree.node_pages(), data_pages=measures.tree_pages(tree, visits).mean(), share=visits.leaves.mean() / tree.trees[0].leaves)
        for built in (cells, tree):
            delete(self.spark, built.path)

    def sizes(self, view: str = "line_mix128", m: int = 22, fifths=(1, 2, 3, 4, 5)) -> None:
        p, g, q = self.view(view)
        for j in fifths:
            part = p.where(F.pmod(F.xxhash64("id"), F.lit(5)) < j)
            began = time.perf_counter()
            index = build_index(part, g, m)
            built = time.perf_counter() - began
            _, s = measures.timed(lambda index=index: exact_knn(index, q, K))
            self.add("sizes", view, f"forest{j * 20}", K, m, build=built, run=s)
            delete(self.spark, index.path)
            self._others("sizes", view, (K,), part, j * 20)

    def probabilities(self, view: str = "gauss200", m: int = 25, ks=(20, 40, 60, 80, 100), ps=(0.7, 0.8, 0.9)) -> None:
        p, g, q = self.view(view)
        index, tree, dims = build_index(p, g, m), baselines.build_whole_tree(p, g), approx.fit_dimensions(p)
        qids, y = next(query_blocks(q, index.d))
        for k in ks:
            truth = scan_knn(p, q, g, k).cache()
            for prob in ps:
                for how in ("whole", "root"):
                    out, s = measures.timed(lambda k=k, prob=prob, how=how: approx.approx_knn(index, q, k, prob, apply=how, dims=dims))
                    found = query_budgets(index, qids, y, k)
                    r, _ = approx.shrunk_budgets(index, y, found, prob, dims, "auto", how, None)
                    share = measures.candidate_share(index, qids, y, r, "point")
                    self.add("probabilities", view, f"forest_{how}", k, m, prob, run=s, data_pages=_mean(share, "data_pages"), share=_mean(share, "share"), ratio=_mean(measures.overall_ratio(out, truth), "ratio"), recall=_mean(measures.recall(out, truth), "recall"))
                began = time.perf_counter()
                out, visits = baselines.guided_search(tree, qids, y, k, prob)
                self.add("probabilities", view, "guided_tree", k, 1, prob, run=time.perf_counter() - began, data_pages=measures.tree_pages(tree, visits).mean(), ratio=_mean(measures.overall_ratio(out, truth), "ratio"), recall=_mean(measures.recall(out, truth), "recall"))
            truth.unpersist()

    def candidate_union(self, names=tuple(ROLES)) -> None:
        """Union over blocks against the whole space at the same bound."""
        for v in names:
            self._forest("candidate_union", v, ROLES[v], (K,), method="blocks", granularity="point")
            self._forest("candidate_union", v, 1, (K,), method="whole", granularity="point")


def _experiment(name: str, **kw):
    def query(spark, d):
        run = Runner(spark, d)
        getattr(run, name)(**kw)
        return run.table()

    return query


# The settings of the published experiments, a query for each view so that none runs too long.
for v in ("event_profile192", "doc_hash400", "page_hash256", "line_mix128", "gauss200", "unif200"):
    _register(f"w_build_time_{v}", _experiment("build_time", names=(v,)))
for v in ROLES:
    _register(f"w_blocks_{v}", _experiment("blocks", names=(v,)))
    _register(f"w_derived_{v}", _experiment("derived", names=(v,)))
    _register(f"w_partitioner_{v}", _experiment("partitioner", names=(v,)))
    _register(f"w_neighbours_{v}", _experiment("neighbours", names=(v,)))
    _register(f"w_candidate_union_{v}", _experiment("candidate_union", names=(v,)))
_register("w_start_dimension", _experiment("start_dimension"))
for d_, m_ in ((10, 3), (50, 9), (100, 13), (200, 29), (400, 50)):
    _register(f"w_dimensions_{d_}", _experiment("dimensions", pairs=((d_, m_),)))
_register("w_sizes", _experiment("sizes"))
for k in (20, 40, 60, 80, 100):
    _register(f"w_probabilities_normal_k{k}", _experiment("probabilities", view="gauss200", ks=(k,)))
    _register(f"w_probabilities_uniform_k{k}", _experiment("probabilities", view="unif200", m=21, ks=(k,)))
