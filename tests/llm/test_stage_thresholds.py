"""The pipeline's stage links by five words and 0.8; op3_jaccard_join by its own contract."""

import corpus_pipeline
import numpy as np
from divknn.llm import jaccard_join
from divknn.llm.common import table

from .helpers import AWKWARD, WORDS, docs
from .test_jaccard_join import brute as brute_op3
from .test_jaccard_join import lower


def brute(rows, percent=80, k=5):
    """Ids that stay: the smallest of each group, every pair compared."""
    sets = []
    for _, t in rows:
        w = WORDS.findall(lower(t or ""))
        sets.append(frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else []))
    group = list(range(len(rows)))
    for i, s in enumerate(sets):
        for j in range(i):
            if s and 100 * len(s & sets[j]) >= percent * len(s | sets[j]) and group[i] != group[j]:
                group = [group[j] if g == group[i] else g for g in group]
    return sorted({min(rows[j][0] for j in range(len(rows)) if group[j] == g) for g in set(group)})


def ids(df):
    return sorted(r[0] for r in df.select("doc_id").collect())


def test_stage_on_given_documents(spark):
    df = table(spark, "/root/testdata/sf0.01", "documents")
    rows = [(r[0], r[1]) for r in df.select("doc_id", "text").collect()]
    want = brute(rows)
    assert ids(corpus_pipeline.one_of_similar(spark, df, "")) == want
    assert len(want) < sum(k == c for k, _, c in brute_op3(rows))  # 0.9 on three words leaves more


def test_stage_on_large_groups(spark):
    rng = np.random.default_rng(4)
    rows = [r for r in AWKWARD if r[0] is not None and r[0] != 7]
    for base in range(3):
        words = [f"w{x}" for x in rng.integers(0, 3000, 150)]
        for j in range(100):
            own = list(words)
            for _ in range(int(rng.integers(0, 8))):
                own[int(rng.integers(len(own)))] = f"z{rng.integers(40)}" if rng.random() < 0.5 else f"y{rng.integers(10**9)}"
            rows.append((100 + base * 1000 + j, " ".join(own)))
    assert ids(jaccard_join.one_per_group(docs(spark, rows))) == brute(rows)


def test_stage_on_small_sets(spark):
    rng = np.random.default_rng(6)
    rows = []
    for base in range(30):
        words = [f"w{x}" for x in rng.integers(0, 3000, int(rng.integers(3, 60)))]
        for j in range(8):
            words = list(words)
            for _ in range(int(rng.integers(0, 2))):
                words[int(rng.integers(len(words)))] = f"z{rng.integers(10**9)}"
            rows.append((1000 + base * 10 + j, " ".join(words + ["end"] * int(rng.random() < 0.3))))
    assert ids(jaccard_join.one_per_group(docs(spark, rows))) == brute(rows)
