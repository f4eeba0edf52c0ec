"""Small strata and rows without a language are judged, as far as their labels go."""

import math
from fractions import Fraction

import corpus_pipeline
from divknn.llm import quality
from divknn.llm.common import table
from pyspark.sql import functions as F

from .helpers import SCHEMA
from .test_quality import brute as brute_stats


def corpus(spark, sizes):
    """(docs, labels): per language ``sizes`` good texts and a tenth as many of symbol junk; labels for all but one in eleven."""
    rows, marks = [], []
    for lang, n in sizes.items():
        for j in range(n + n // 10):
            k, junk = len(rows), j >= n
            text = " ".join(f"w{k}x{i}" for i in range(30 + j % 20)) + ("".join(f" #{i}$%<|>***" for i in range(8)) if junk else "")
            rows.append((k, text, lang, "s", len(text)))
            if j % 11:
                marks.append((k, 0 if junk else 1, 0))
    return spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(marks, "doc_id long, quality int, toxic int")


def test_rules_that_labels_can_certify():
    for n, strata in ((100, 1), (219, 4), (300, 4), (600, 4), (5000, 5)):
        j = quality.testable(n, strata, 0.02, 0.05)
        sure = lambda j: quality.binomial_cdf(0, n, 0.02 / j) <= 0.05 / (strata * j)
        assert (j == 0 or sure(j)) and (j == len(quality.RULES) or not sure(j + 1))
    assert quality.testable(0, 1, 0.02, 0.05) == 0 and quality.testable(10**6, 4, 0.02, 0.05) == len(quality.RULES)


def test_small_and_nameless_strata(spark, tmp_path):
    docs, labels = corpus(spark, {"en": 500, None: 450, "": 60})
    cutoffs = quality.certified_cutoffs(quality.scored(docs), labels)
    assert set(cutoffs) == {"en", None} and all("symbols" in c for c in cutoffs.values())
    report = quality.quality_report(docs, labels)
    kept = {r[0] for r in report.where("kept").select("doc_id").collect()}
    junk = docs.where("contains(text, '$')")
    assert {r[0] for r in docs.select("doc_id").collect()} - kept == {r[0] for r in junk.where("lang = 'en' or lang is null").select("doc_id").collect()}
    labels.write.parquet(f"{tmp_path}/labels.parquet")  # the stage of the pipeline, where cutoffs exist
    assert {r[0] for r in corpus_pipeline.reject_bad(spark, docs, str(tmp_path)).select("doc_id").collect()} == kept


def brute_kept(rows, marks, alpha=0.02, delta=0.05):
    """{doc_id: kept} from plain counting; rows: (doc_id, text, lang)."""
    def score(text):
        text = text or ""
        n, chars, symbols, dup, repeats, failed = brute_stats(text)
        lines = sum(bool(x.strip(" \t\n\r\x0b\x0c")) for x in text.split("\n"))
        share = lambda a, b: min(400, 400 * a // max(1, b))
        upper = sum("A" <= c <= "Z" for c in text)
        return failed, [share(symbols, chars), share(repeats, n), share(dup, lines), share(upper, chars), max(0, 400 - n)]

    scored = [(k, lang, *score(t)) for k, t, lang in rows]
    held = {}
    for k, lang, failed, s in scored:
        if not failed and k in marks:
            held.setdefault(lang, []).append((marks[k], s))
    tail = lambda k, n, p: sum(math.comb(n, i) * Fraction(p) ** i * (1 - Fraction(p)) ** (n - i) for i in range(k + 1))
    cut = {}
    for lang, own in held.items():
        n = sum(m for m, _ in own)
        j = max((j for j in range(1, 6) if (1 - alpha / j) ** n <= delta / (len(held) * j)), default=0)
        for r in range(j):
            best = (0, None)
            for t in range(400, 0, -1):
                false, caught = (sum(m == q and s[r] >= t for m, s in own) for q in (1, 0))
                if tail(false, n, alpha / j) > delta / (len(held) * j):
                    break
                best = (caught, t) if caught > best[0] else best
            if best[1]:
                cut[lang, r] = best[1]
    return sorted((str(k), not failed and all(s[r] < cut.get((lang, r), 401) for r in range(5))) for k, lang, failed, s in scored), cut


def test_verdicts_match_brute_force(spark):
    docs, labels = corpus(spark, {"en": 500, "de": 240, None: 60})
    d = "/root/testdata/sf0.01"
    for docs, labels in ((docs, labels), (table(spark, d, "documents"), table(spark, d, "labels"))):
        rows = [(r[0], r[1], r[2]) for r in docs.select("doc_id", "text", "lang").collect()]
        want, cut = brute_kept(rows, {r[0]: r[1] for r in labels.collect()})
        assert cut  # something is certified on either table
        assert sorted((str(r[0]), r[1]) for r in quality.quality_report(docs, labels).select("doc_id", "kept").collect()) == want


def test_clashing_columns(spark):
    docs, labels = corpus(spark, {"en": 300})
    wide = docs.withColumn("scores", F.lit("x")).withColumn("n_words", F.lit("y")).withColumn("base_failed", F.lit("z"))
    out = quality.keep_good(wide, labels)
    assert out.columns == wide.columns
    assert {r[0] for r in out.collect()} == {r[0] for r in quality.keep_good(docs, labels).collect()}
    assert {(r["lang"], r["rule"]) for r in quality.strata_report(docs, labels).collect()} == {("en", "symbols")}


def test_every_language_of_the_given_table(spark):
    d = "/root/testdata/sf0.1"
    cutoffs = quality.certified_cutoffs(quality.scored(table(spark, d, "documents")), table(spark, d, "labels"))
    assert set(cutoffs) == {"en", "de", "fr", "es"}
