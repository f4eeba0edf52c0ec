"""The hashed word counts of texts, cut many at once."""

import hashlib
import re

import pytest
from divknn.sources import views
from pyspark.sql import functions as F

ROWS = [(1, None), (2, ""), (3, "one two One é two\x00three"), (3, "again two"), (4, "K KÉLVIN ﬁ İstanbul a1b2"), (5, "x" * 5000 + " " + "y z " * 3000), (6, "12 34"), (7, "\u212aELVIN \u0130STANBUL \u212b \u03a3\u03a3 \u1e9e QI\u0130\u0307"), (None, "no id"), *[(100 + i, f"word{chr(97 + i % 26)} w{i}") for i in range(40)]]


@pytest.mark.parametrize(("letters", "pattern"), [("abcdefghijklmnopqrstuvwxyz", "[a-z]+"), ("abcdefghijklmnopqrstuvwxyz0123456789", "[a-z0-9]+")])
def test_counts_word_by_word(spark, monkeypatch, letters, pattern):
    monkeypatch.setattr(views, "TEXT_ROWS", 7)
    df, d = spark.createDataFrame(ROWS, "id long, text string"), 13
    want = {}
    for k, t in df.select("id", F.lower("text").alias("t")).collect():
        own = want.setdefault(k, [0.0] * d)
        for w in re.findall(pattern, t or ""):
            own[int(hashlib.md5(w.encode()).hexdigest()[:8], 16) % d] += 1
    for empty in (True, False):
        got = {r["id"]: (list(r["c"]), r["total"]) for r in views._word_counts(df, letters, d, empty).collect()}
        assert got == {k: (c, sum(c)) for k, c in want.items() if empty or any(c)}


def test_texts_are_cut_many_at_once(monkeypatch):
    """About TEXT_BYTES together, a long one stays whole, and every row comes once."""
    import numpy as np

    monkeypatch.setattr(views, "TEXT_BYTES", 10)
    monkeypatch.setattr(views, "TEXT_ROWS", 3)
    assert list(views._some_rows(np.array([4, 4, 4, 50, 0, 0, 0, 0, 1]))) == [(0, 2), (2, 3), (3, 4), (4, 7), (7, 9)]
    assert list(views._some_rows(np.array([], int))) == []


def test_lower_case_of_all_letters(spark):
    """Every code point as the engine's own lower case shows it, as far as ASCII letters go."""
    points = [c for c in range(1, 0x110000) if not 0xD800 <= c < 0xE000]
    df = spark.createDataFrame([(i, "".join(map(chr, points[i : i + 5000]))) for i in range(0, len(points), 5000)], "id long, text string")
    for text, low in df.select("text", F.lower("text")).collect():
        assert re.findall("[a-z0-9]+", low) == re.findall("[a-z0-9]+", views._lower(text.encode()).decode())
