"""Queries of the training-data operators, and SQL for those it can express."""

from __future__ import annotations

from . import binary_output, decontaminate, fm_index, html_pages, jaccard_join, licenses, packing, quality, secrets, suffix_array

QUERIES = {
    "op1_fm_index_dedup": fm_index.op1_fm_index_dedup,
    "op2_secret_scan": secrets.op2_secret_scan,
    "op3_jaccard_join": jaccard_join.op3_jaccard_join,
    "op4_suffix_array_dedup": suffix_array.op4_suffix_array_dedup,
    "op5_license_scan": licenses.op5_license_scan,
    "op6_html_extraction": html_pages.op6_html_extraction,
    "op7_arrow_tokens": binary_output.op7_arrow_tokens,
    "op8_quality_rules": quality.op8_quality_rules,
    "op9_benchmark_decontamination": decontaminate.op9_benchmark_decontamination,
    "op10_best_fit_packing": packing.op10_best_fit_packing,
}
_WORDS = r"list_filter(string_split_regex({t}, '[\x20\x09-\x0D]+'), lambda v: v <> '')"
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"

ORACLES: dict[str, str] = {
    "op1_fm_index_dedup": f"""WITH d AS MATERIALIZED (SELECT doc_id, coalesce({_WORDS.format(t="text")}, []) w FROM documents),
 x AS MATERIALIZED (SELECT doc_id, i, md5(array_to_string(w[i:i + 49], ' ')) k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) i FROM d)),
 f AS (SELECT k, min(doc_id) first FROM x GROUP BY k),
 r AS (SELECT DISTINCT doc_id, unnest(range(i, i + 50)) j FROM x JOIN f USING (k) WHERE first < doc_id),
 g AS (SELECT doc_id, list(j) gone FROM r GROUP BY doc_id),
 p AS (SELECT d.doc_id, w, unnest(range(1, len(w) + 1)) j FROM d JOIN g USING (doc_id)),
 kept AS (SELECT p.doc_id, string_agg(w[p.j], ' ' ORDER BY p.j) t FROM p LEFT JOIN r ON r.doc_id = p.doc_id AND r.j = p.j WHERE r.j IS NULL GROUP BY p.doc_id)
 SELECT d.doc_id, len(w)::BIGINT n_words, coalesce(len(gone), 0)::BIGINT n_removed, sha256(CASE WHEN gone IS NULL THEN array_to_string(w, ' ') ELSE coalesce(t, '') END) kept_sha256
 FROM d LEFT JOIN g USING (doc_id) LEFT JOIN kept USING (doc_id)""",
    "op3_jaccard_join": f"""WITH RECURSIVE w AS (SELECT doc_id, coalesce({_WORDS.format(t=f"translate(text, '{_UPPER}', '{_UPPER.lower()}')")}, []) w FROM documents),
 s AS MATERIALIZED (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' '))) END s FROM w),
 u AS MATERIALIZED (SELECT doc_id, unnest(s) g FROM s),
 c AS (SELECT a.doc_id a, b.doc_id b, count(*) n FROM u a JOIN u b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
 l AS MATERIALIZED (SELECT a, b FROM c JOIN s x ON x.doc_id = a JOIN s y ON y.doc_id = b WHERE 100 * n >= 90 * (len(x.s) + len(y.s) - n)),
 e AS MATERIALIZED (SELECT a, b FROM l UNION SELECT b, a FROM l),
 reach AS (SELECT doc_id id, doc_id other FROM s UNION SELECT reach.id, e.b FROM reach JOIN e ON e.a = reach.other)
 SELECT s.doc_id, len(s.s)::BIGINT n_shingles, min(other) component_id FROM s JOIN reach ON reach.id = s.doc_id GROUP BY s.doc_id, len(s.s)""",
}
