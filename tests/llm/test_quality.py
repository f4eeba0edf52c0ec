import math
from collections import Counter

import numpy as np
from divknn.llm import quality
from divknn.llm.common import table

from .helpers import AWKWARD, WORDS, docs


def brute(text):
    text = text or ""
    words = WORDS.findall(text)
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    often, hit, seen, dup = Counter(windows), set(), set(), 0
    for i, w in enumerate(windows):
        if often[w] > 1:
            hit |= set(range(i, i + 8))
    for line in text.split("\n"):
        if WORDS.search(line):
            dup += line in seen
            seen.add(line)
    n = len(words)
    return n, sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), dup, len(hit), n < 20 or 100 * len(hit) > 30 * n


def test_statistics(spark, sf):
    for df in (table(spark, sf, "documents"), docs(spark, AWKWARD + [(30, "a b c d e f g h " * 3 + "\nline\n\nline\n#$ x")])):
        want = sorted((str(r[0]), *brute(r[1])) for r in df.select("doc_id", "text").collect())
        got = quality.quality_report(df, table(spark, sf, "labels")).collect()
        assert sorted((str(r[0]), *r[1:7]) for r in got) == want
        assert all(not r["kept"] for r in got if r["base_failed"])


def test_empty_tables(spark, sf):
    labels = table(spark, sf, "labels")
    assert quality.quality_report(docs(spark, []), labels).count() == 0
    assert quality.quality_report(table(spark, sf, "documents"), labels.limit(0)).where("kept = base_failed").count() == 0


def test_exact_bound():
    for n, p in ((10, 0.3), (400, 0.01)):
        pmf = [math.comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(n + 1)]
        for k in (0, 1, 5):
            assert abs(quality.binomial_cdf(k, n, p) - sum(pmf[: k + 1])) < 1e-9


def test_walk_limits_false_rejections():
    rng = np.random.default_rng(3)
    good, bad = np.zeros(401, int), np.zeros(401, int)
    np.add.at(good, rng.integers(0, 100, 5000), 1)
    np.add.at(bad, rng.integers(80, 300, 500), 1)
    t = quality.walk(good, bad, 0.004, 0.01)
    assert 90 <= t <= 101 and good[t:].sum() / good.sum() < 0.004
    assert quality.walk(good // 100, bad, 0.004, 0.01) is None  # too few labels certify nothing


def test_filter_agrees_with_report(spark):
    d = "/root/testdata/sf0.1"
    documents, labels = table(spark, d, "documents"), table(spark, d, "labels")
    kept = quality.quality_report(documents, labels).where("kept")
    out = quality.keep_good(documents, labels)
    assert out.columns == documents.columns
    assert sorted(r[0] for r in out.select("doc_id").collect()) == sorted(r[0] for r in kept.select("doc_id").collect())
    marked = quality.quality_report(documents, labels).where("not base_failed").join(labels, "doc_id")
    n = {(r[0], r[1]): r[2] for r in marked.groupBy("quality", "kept").count().collect()}
    assert n.get((1, False), 0) <= 0.01 * n[1, True]
    assert n.get((0, False), 0) >= 0.5 * n.get((0, True), 0), n
