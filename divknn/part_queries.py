"""Registered queries of single parts, each with its SQL: blocks, cost model, layout, fits, reports, SQL functions, windows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from divknn import measures
from divknn.functions import generators as G
from divknn.functions import sql as sql_functions
from divknn.operators import approx, relational
from divknn.operators.index import build_index, load_index
from divknn.operators.search import exact_knn
from divknn.operators.vectors import broadcast_parts, matrix_of, scan_knn, union_of
from divknn.plans import costmodel, partition
from divknn.sources import views
from divknn.streaming import streams
from divknn.workloads import _CATALOGUE, _EMB, K, _knn_sql, _pairs_sql, _queries, _register, _rounded
from pyspark.sql import functions as F

_EMB_SQL = _CATALOGUE["emb64"].sql


def _emb(spark, d):
    return _CATALOGUE["emb64"].load(spark, d)


# Generators: one of the user's own, and a positive one shifted into its domain.
_QUARTIC = G.custom("quartic", "pow({t},4)", "(4*pow({t},3))", lambda t: t**4, lambda t: 4 * t**3, lambda s: np.cbrt(s / 4))
_register("scan_knn_custom", lambda s, d: _rounded(scan_knn(p := _emb(s, d), _queries(p), _QUARTIC, K)), _knn_sql("emb64", _QUARTIC))
_register("scan_knn_lp4", lambda s, d: _rounded(scan_knn(p := _emb(s, d), _queries(p), G.lp_norm(4.0), K)), _knn_sql("emb64", G.lp_norm(4.0)))


def _shifted(spark, d):
    p = G.shift_positive(_emb(spark, d), 0.25)
    return _rounded(scan_knn(p, _queries(p), G.itakura_saito(), K))


_register("scan_knn_shifted", _shifted, _knn_sql("emb64", G.itakura_saito(), scale="({t} - (SELECT min(x) FROM v) + 0.25)"))

# Indexed search under every other generator, appended to, reduced and read back.
for _name, _gen, _view in (("sqeuclid", G.squared_euclidean(), "emb64"), ("shannon", G.shannon(), "emb64_pos"), ("burg", G.burg(), "emb64_pos"), ("lp3", G.lp_norm(3.0), "emb64"), ("quasi_half", G.lp_quasi(0.5), "emb64_pos")):
    _register(f"exact_knn_gen_{_name}", lambda s, d, g=_gen, v=_view: _rounded(exact_knn(build_index(p := _CATALOGUE[v].load(s, d), g, 8), _queries(p), K)), _knn_sql(_view, _gen))
_MAHAL = G.mahalanobis([1 + (i % 7) / 2 for i in range(64)])
_register("exact_knn_gen_mahal", lambda s, d: _rounded(exact_knn(build_index(p := _emb(s, d), _MAHAL, 8), _queries(p), K)), _knn_sql("emb64", _MAHAL, scale="{t} * sqrt(1 + (p.i % 7) / 2.0)"))


def _appended(spark, d):
    p, g = _emb(spark, d), G.exponential()
    return _rounded(exact_knn(streams.append(build_index(p.where("id % 2 = 0"), g, 4), p.where("id % 2 = 1")), _queries(p), K))


def _removed(spark, d):
    p, g = _emb(spark, d), G.exponential()
    return _rounded(exact_knn(streams.remove(build_index(p, g, 4), p.where("id % 3 = 0")), _queries(p), K))


_register("append_knn", _appended, _EMB)
_register("remove_knn", _removed, _knn_sql("emb64", G.exponential(), where="WHERE p.id % 3 <> 0"))
_register("reloaded_knn", lambda s, d: _rounded(exact_knn(load_index(s, build_index(p := _emb(s, d), G.exponential(), 4).path), _queries(p), K)), _EMB)
_register("merge_top_knn", lambda s, d: _rounded(streams.merge_top(scan_knn((p := _emb(s, d)).where("id % 2 = 0"), _queries(p), G.exponential(), K), p.where("id % 2 = 1"), _queries(p), G.exponential(), K)), _EMB)


def _pages(spark, d):
    """Points on each page of the shared layout, and whether leaves keep together along it."""
    index = build_index(_emb(spark, d), G.exponential(), 4, page_bytes=4 * 64 * 10)
    laid = index.points.groupBy("page").agg(F.count("*").alias("points"), F.count_distinct("slot").alias("slots"), F.min("leaf_ord").alias("lo"), F.max("leaf_ord").alias("hi"))
    after = laid.select((F.col("page") - 1).alias("page"), F.col("lo").alias("next"))
    return laid.join(after, "page", "left").select("page", "points", "slots", (F.coalesce("next", "hi") >= F.col("hi")).alias("in_order"))


_register("layout_pages", _pages, "SELECT (r // 10)::BIGINT page, count(*) points, count(*) slots, true in_order FROM (SELECT row_number() OVER (ORDER BY vec_id) - 1 r FROM embeddings) GROUP BY ALL")

# Blocks.
_MS = (1, 5, 21, 50)


def _blocks_of(mode):
    def query(spark, d):
        rows = [(m, j, i) for m in _MS for j, b in enumerate(partition.contiguous_blocks(64, m, mode)) for i in b]
        return spark.createDataFrame(rows, "m int, block int, dim int")

    return query


_register("blocks_ceil", _blocks_of("ceil"), f"SELECT m::INT m, (i // ceil(64.0 / m)::INT)::INT block, i::INT dim FROM (SELECT unnest({list(_MS)}) m) CROSS JOIN (SELECT unnest(range(64)) i)")
_register("blocks_balanced", _blocks_of("balanced"), f"""SELECT m::INT m, (CASE WHEN i < (64 % m) * (64 // m + 1) THEN i // (64 // m + 1) ELSE 64 % m + (i - (64 % m) * (64 // m + 1)) // (64 // m) END)::INT block, i::INT dim
 FROM (SELECT unnest({list(_MS)}) m) CROSS JOIN (SELECT unnest(range(64)) i)""")


def _dealt(spark, d):
    """Blocks dealt from groups of similar dimensions: their sizes, and how many groups each draws from."""
    r = partition.abs_correlation(_emb(spark, d))
    groups = partition.group_similar(r, 8)
    of = {i: g for g, own in enumerate(groups) for i in own}
    return spark.createDataFrame([(j, len(b), len({of[i] for i in b})) for j, b in enumerate(partition.deal_groups(groups, 8))], "block int, dims int, groups int")


_register("blocks_dealt", _dealt, "SELECT i::INT block, 8::INT dims, 8::INT groups FROM range(8) t(i)")
_register("blocks_random", lambda s, d: s.createDataFrame([(j, len(b)) for j, b in enumerate(partition.random_blocks(64, 8))] + [(-1, len({i for b in partition.random_blocks(64, 8) for i in b}))], "block int, dims int"),
          "SELECT (i - 1)::INT block, (CASE WHEN i = 0 THEN 64 ELSE 8 END)::INT dims FROM range(9) t(i)")
_register("block_split", lambda s, d: _emb(s, d).select("id", F.posexplode(partition.split_blocks("vec", partition.contiguous_blocks(64, 5))).alias("block", "x")).select("id", "block", F.size("x").alias("dims"), F.round(F.aggregate("x", F.lit(0.0), lambda a, b: a + b), 6).alias("total")),
          f"SELECT id::BIGINT id, (CASE WHEN i < 52 THEN i // 13 ELSE 4 END)::INT block, count(*)::INT dims, round(sum(x), 6) total FROM {_EMB_SQL} GROUP BY ALL")

# Cost model.
_GRID = [(a, alpha, beta) for a in (500.0, 5000.0) for alpha in (0.8, 0.9, 0.95) for beta in (0.01, 0.05)]
_GRID_SQL = "(VALUES " + ", ".join(f"({a}::DOUBLE, {al}::DOUBLE, {b}::DOUBLE)" for a, al, b in _GRID) + ") g(a, alpha, beta)"
_COST_SQL = f"""c AS (SELECT a, alpha, beta, k, m, 128 + {{passes}} * m * 100000.0::DOUBLE + 100000 * log2(k) + beta * a * pow(alpha, m) * 100000 * (128 + log2(k)) cost
 FROM {_GRID_SQL} CROSS JOIN (SELECT unnest([1, 20, 100]) k) CROSS JOIN range(1, 129) t(m))"""


def _models():
    return [(p, costmodel.CostModel(*p, 100_000, 128)) for p in _GRID]


_register("cost_optimum", lambda s, d: s.createDataFrame([(*p, k, m.optimal_blocks(k), m.scan_optimum(k)) for p, m in _models() for k in (1, 20, 100)], "a double, alpha double, beta double, k int, derived int, tried int"),
          f"WITH {_COST_SQL.format(passes=2)} SELECT a, alpha, beta, k::INT k, arg_min(m, cost)::INT derived, arg_min(m, cost)::INT tried FROM c GROUP BY ALL")
_register("cost_with_reads", lambda s, d: s.createDataFrame([(*p, m, round(c.cost(m, 20, 32 << 10, 5_000.0), 4)) for p, c in _models() for m in range(1, 65)], "a double, alpha double, beta double, m int, cost double"),
          f"""WITH {_COST_SQL.format(passes=1)} SELECT a, alpha, beta, m::INT m, round(cost + least(1, beta * a * pow(alpha, m)) * 100000 * 128 * 4 / 32768 / 5000, 4) cost FROM c WHERE k = 20 AND m <= 64""")
_register("tree_cost_curve", lambda s, d: s.createDataFrame([(*p, m, round(c.tree_cost(m, 64), 4)) for p, c in _models() for m in range(1, 65)], "a double, alpha double, beta double, m int, cost double"),
          f"SELECT a, alpha, beta, m::INT m, round(m * greatest(least(1, beta * a * pow(alpha, m)) * 100000 / 64, 1) * log2(100000.0 / 64), 4) cost FROM {_GRID_SQL} CROSS JOIN range(1, 65) t(m)")
_register("cost_trend", lambda s, d: s.createDataFrame([(*p, m, bool(c.cost(m + 1, 20, passes=2) < c.cost(m, 20, passes=2))) for p, c in _models() for m in range(1, 64)], "a double, alpha double, beta double, m int, falls boolean"),
          f"WITH {_COST_SQL.format(passes=2)} SELECT a, alpha, beta, m::INT m, n < cost falls FROM (SELECT *, lead(cost) OVER (PARTITION BY a, alpha, beta, k ORDER BY m) n FROM c WHERE k = 20) WHERE m < 64")


def _pairs(spark, d):
    """Fifty pairs: points 0-49 with points 50-99."""
    rows = _emb(spark, d).where("id < 100").orderBy("id").collect()
    x = np.array([r["vec"] for r in rows])
    return x[:50], x[50:]


_PAIR_BOUNDS = f"""v AS MATERIALIZED (SELECT id::BIGINT id, i::INT i, x FROM {_EMB_SQL}),
 e AS (SELECT m, p.id, (p.i // (64 // m)) b, sum(exp(p.x)) + sum(y.x * exp(y.x)) - sum(exp(y.x)) + sqrt(sum(p.x * p.x) * sum(exp(y.x) * exp(y.x))) r FROM v p JOIN v y ON y.id = p.id + 50 AND y.i = p.i CROSS JOIN (SELECT unnest([2, 8, 16]) m) WHERE p.id < 50 GROUP BY ALL),
 t AS MATERIALIZED (SELECT m, id, greatest(sum(r), 1e-12) r FROM e GROUP BY ALL)"""


def _decay(spark, d):
    a, alpha = costmodel.fit_decay(G.exponential(), *_pairs(spark, d), 2, 16)
    return spark.createDataFrame([(round(a, 6), round(alpha, 8))], "a double, alpha double")


_register("cost_decay_fit", _decay, f"WITH {_PAIR_BOUNDS}, l AS (SELECT m, avg(ln(r)) l FROM t GROUP BY m), s AS (SELECT (max(l) FILTER (WHERE m = 16) - max(l) FILTER (WHERE m = 2)) / 14 s, max(l) FILTER (WHERE m = 2) l FROM l) SELECT round(exp(l - 2 * s), 6) a, round(exp(s), 8) alpha FROM s")


def _beta(spark, d):
    x, y = _pairs(spark, d)
    bounds = costmodel.pair_bounds(G.exponential(), x, y, 8)
    ratio, share = costmodel.fit_beta(_emb(spark, d), G.exponential(), y, bounds)
    return spark.createDataFrame([(round(ratio, 8), round(share, 8))], "beta double, share double")


_register("cost_beta_fit", _beta, f"""WITH {_PAIR_BOUNDS}, d AS (SELECT y.id - 50 id, p.id pid, greatest(sum({G.exponential().term('p.x', 'y.x')}), 0) d FROM v p JOIN v y ON y.i = p.i WHERE y.id BETWEEN 50 AND 99 GROUP BY ALL),
 s AS (SELECT t.id, any_value(t.r) r, avg((d.d <= t.r)::INT) share FROM d JOIN t ON t.id = d.id AND m = 8 GROUP BY t.id) SELECT round(avg(share / r), 8) beta, round(avg(share), 8) share FROM s""")

# Fits of dimensions and of the mixed term.
_register("dimension_moments", lambda s, d: s.createDataFrame([(int(r["dim"]), int(r["n"]), *(round(float(r[c]), 6) for c in ("mean", "sd", "lo", "hi"))) for r in approx.dimension_stats(_emb(s, d))], "dim int, n long, mean double, sd double, lo double, hi double"),
          f"SELECT i::INT dim, count(*) n, round(avg(x), 6) mean, round(stddev_pop(x), 6) sd, round(min(x), 6) lo, round(max(x), 6) hi FROM {_EMB_SQL} GROUP BY i")


def _histogram(spark, d):
    fit = approx.fit_dimensions(_emb(spark, d))
    return spark.createDataFrame([(i, b, round(float(v), 8)) for i, own in enumerate(fit.shares) for b, v in enumerate(own) if v], "dim int, bin int, share double")


_register("dimension_histogram", _histogram, f"""WITH v AS (SELECT * FROM {_EMB_SQL}), e AS (SELECT i, min(x) lo, max(x) - min(x) span, count(*) n FROM v GROUP BY i)
 SELECT v.i::INT dim, least(floor((x - lo) / span * 32), 31)::INT bin, round(count(*)::DOUBLE / any_value(n), 8) share FROM v JOIN e USING (i) GROUP BY ALL""")


def _mixed(family):
    def query(spark, d):
        p = _emb(spark, d)
        dims = approx.fit_dimensions(p, family="normal" if family == "empirical" else family)
        sample = np.array([r["vec"] for r in p.orderBy("id").collect()]) if family == "empirical" else None
        rows = []
        for r in _queries(p).collect():
            dist = approx.mixed_distribution(G.exponential(), np.array(r["yvec"]), dims, sample)
            rows.append((r["qid"], round(dist.normal.mean, 6), round(dist.normal.stdev, 6), round(dist.inverse(0.5), 6)))
        return spark.createDataFrame(rows, "qid long, mean double, sd double, middle double")

    return query


_MOMENTS_SQL = {"normal": ("avg(x)", "var_pop(x)"), "uniform": ("(min(x) + max(x)) / 2", "pow(max(x) - min(x), 2) / 12")}
for _family, (_m, _v) in _MOMENTS_SQL.items():
    _register(f"mixed_term_{_family}", _mixed(_family), f"""WITH v AS MATERIALIZED (SELECT id::BIGINT id, i, x FROM {_EMB_SQL}), m AS (SELECT i, {_m} m, {_v} s FROM v GROUP BY i)
 SELECT id qid, round(-sum(m * exp(x)), 6) mean, round(sqrt(sum(s * exp(x) * exp(x))), 6) sd, round(-sum(m * exp(x)), 6) middle FROM v JOIN m USING (i) WHERE id % 20 = 0 GROUP BY id""")
_register("mixed_term_empirical", lambda s, d: _mixed("empirical")(s, d).select("qid", "middle"), f"""WITH v AS MATERIALIZED (SELECT id::BIGINT id, i, x FROM {_EMB_SQL}),
 t AS (SELECT y.id qid, p.id, -sum(p.x * exp(y.x)) t FROM v p JOIN v y USING (i) WHERE y.id % 20 = 0 GROUP BY ALL) SELECT qid, round(quantile_cont(t, 0.5), 6) middle FROM t GROUP BY qid""")


def _coefficients(spark, d):
    """Shrinking coefficients of the bound of each query with itself: at most 1, one at p = 1, and growing with p."""
    p, g = _emb(spark, d), G.exponential()
    dims = approx.fit_dimensions(p, family="normal")

    def shrink(batches):
        for b in batches:
            rows = []
            for qid, y in zip(b.column("qid").to_pylist(), matrix_of(b.column("yvec")), strict=True):
                dist, kappa, m = approx.mixed_distribution(g, y, dims), float((y * g.grad(y)).sum()), float(np.sqrt((y * y).sum() * (g.grad(y) ** 2).sum()))
                c = [approx.shrink_coefficient(dist, kappa, m, v) for v in (0.5, 0.7, 0.8, 0.9, 1.0)]
                rows.append((qid, round(kappa, 6), round(m, 6), c[-1], all(a <= b for a, b in zip(c, c[1:], strict=False)), all(v <= 1 for v in c)))
            names = ("qid", "kappa", "m", "whole", "grows", "bounded")
            types = (pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.bool_(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names=list(names))

    return _queries(p).mapInArrow(shrink, "qid long, kappa double, m double, whole double, grows boolean, bounded boolean")


_register("shrink_coefficients", _coefficients, f"SELECT id::BIGINT qid, round(sum(x * exp(x)), 6) kappa, round(sqrt(sum(x * x) * sum(exp(x) * exp(x))), 6) m, 1.0::DOUBLE whole, true grows, true bounded FROM {_EMB_SQL} WHERE id % 20 = 0 GROUP BY id")

# Measures at p = 1, and the gain.


def _recall(spark, d):
    p = _emb(spark, d)
    index, q = build_index(p, G.exponential(), 8), _queries(p)
    out, truth = approx.approx_knn(index, q, K, 1.0), scan_knn(p, q, G.exponential(), K)
    return measures.recall(out, truth).select("qid", F.round("recall", 6).alias("recall"), F.lit(measures.success_rate(out, truth)).alias("success"))


_register("recall_p1", _recall, "SELECT vec_id qid, 1.0::DOUBLE recall, 1.0::DOUBLE success FROM embeddings WHERE vec_id % 20 = 0")


def _blockwise_recall(spark, d):
    from divknn.operators.search import blockwise_knn_union

    p = _emb(spark, d)
    q = _queries(p)
    near = blockwise_knn_union(p, q, G.exponential(), partition.contiguous_blocks(64, 8), K)
    truth = scan_knn(p, q, G.exponential(), K)
    return measures.recall(near, truth).join(measures.overall_ratio(near, truth), "qid").select("qid", F.round("recall", 6).alias("recall"), F.round("ratio", 6).alias("ratio"))


_register("blockwise_recall", _blockwise_recall, f"""WITH {_pairs_sql('emb64', G.exponential())},
 b AS (SELECT y.id qid, p.id, p.i // 8 b, greatest(sum({G.exponential().term('p.x', 'y.x')}), 0) divergence FROM v p JOIN y ON p.i = y.i GROUP BY ALL),
 near AS (SELECT DISTINCT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid, b ORDER BY round(divergence, 9), id) r FROM b) WHERE r <= {K}),
 got AS (SELECT * FROM (SELECT d.*, row_number() OVER (PARTITION BY qid ORDER BY round(divergence, 9), id) rank FROM d JOIN near USING (qid, id)) WHERE rank <= {K}),
 truth AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(divergence, 9), id) rank FROM d) WHERE rank <= {K}),
 h AS (SELECT t.qid, avg((g.id IS NOT NULL)::INT) recall FROM truth t LEFT JOIN got g USING (qid, id) GROUP BY t.qid),
 r AS (SELECT t.qid, avg(CASE WHEN t.divergence <= 1e-12 AND g.divergence <= 1e-12 THEN 1 WHEN t.divergence > 1e-12 THEN g.divergence / t.divergence END) ratio FROM truth t JOIN got g ON g.qid = t.qid AND g.rank = t.rank GROUP BY t.qid)
 SELECT qid, round(recall, 6) recall, round(ratio, 6) ratio FROM h JOIN r USING (qid)""")
_GAINS = [(10.0, 7.0), (4.0, 4.0), (2.0, 3.0), (0.0, 1.0)]
_register("relative_gains", lambda s, d: s.createDataFrame([(a, b, round(measures.relative_gain(a, b), 6)) for a, b in _GAINS], "old double, new double, gain double"),
          f"SELECT o::DOUBLE old, n::DOUBLE new, CASE WHEN o = 0 THEN 0 ELSE round(1 - n / o, 6) END::DOUBLE gain FROM (VALUES {', '.join(f'({a}, {b})' for a, b in _GAINS)}) t(o, n)")

# Reports.


def _long(spark, d):
    return views.read(spark, d, "lineitem").select(F.col("l_returnflag").alias("view"), F.col("l_linestatus").alias("method"), F.col("l_linenumber").alias("k"), F.col("l_quantity").cast("double").alias("value"))


_register("report_rollup", lambda s, d: relational.report(_long(s, d)).select("view", "method", F.round("value", 6).alias("value"), "n"),
          "SELECT l_returnflag AS view, l_linestatus AS method, round(avg(l_quantity), 6) AS value, count(*) n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
_register("report_pivot", lambda s, d: relational.versus(_long(s, d)).select("view", "k", F.round("F", 6).alias("F"), F.round("O", 6).alias("O")),
          "SELECT l_returnflag AS view, l_linenumber k, round(avg(l_quantity) FILTER (WHERE l_linestatus = 'F'), 6) AS \"F\", round(avg(l_quantity) FILTER (WHERE l_linestatus = 'O'), 6) AS \"O\" FROM lineitem GROUP BY ALL")

# SQL functions and the table function.


def _sql_pairs(spark, d):
    sql_functions.register(spark)
    p = _emb(spark, d)
    pairs = union_of([p.crossJoin(q) for q in broadcast_parts(_queries(p), 64)])
    return pairs.select("qid", "id", F.expr("round(bregman_exponential(vec, yvec), 6)").alias("divergence"))


_register("sql_function", _sql_pairs, f"WITH {_pairs_sql('emb64', G.exponential())} SELECT qid, id, round(divergence, 6) divergence FROM d")


def _sql_table(spark, d):
    sql_functions.register(spark)
    p = _emb(spark, d)
    p.createOrReplaceTempView("divknn_points")
    y = sql_functions.literal(p.where("id = 0").first()["vec"])
    return spark.sql(f"SELECT id, round(divergence, 6) divergence FROM bregman_knn(TABLE(divknn_points), {y}, {K}, 'exponential') ORDER BY divergence, id LIMIT {K}")


_register("sql_table_function", _sql_table, _knn_sql("emb64", G.exponential(), ask="WHERE id = 0").replace("SELECT qid, rank::INT rank, id,", "SELECT id,"))

# Windows of events; the same functions serve streams.
_register("event_windows", lambda s, d: streams.event_vectors(views.read(s, d, "events")).select("user_id", F.col("window.start").cast("date").alias("day"), *[F.round(F.col("vec")[i], 4).alias(f"v{i}") for i in range(6)]),
          "WITH e AS (SELECT DISTINCT ON (event_id) * FROM events) SELECT user_id, ts::DATE AS day, " + ", ".join(f"round(sum(CASE WHEN event_type = '{t}' THEN value ELSE 0 END), 4) v{i}" for i, t in enumerate(("click", "view", "purchase", "login", "search"))) + ", round(sum(CASE WHEN event_type NOT IN ('click', 'view', 'purchase', 'login', 'search') THEN value ELSE 0 END), 4) v5 FROM e GROUP BY ALL")
_register("event_sessions", lambda s, d: streams.session_counts(views.read(s, d, "events"), "6 hours").select("user_id", F.unix_timestamp(F.col("session.start")).alias("began"), "n"),
          """WITH o AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END fresh FROM events WHERE ts IS NOT NULL WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
 g AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) s FROM o) SELECT user_id, floor(epoch(min(ts)))::BIGINT began, count(*) n FROM g GROUP BY user_id, s""")  # fmt: skip

