import hashlib

import numpy as np
import pytest
from divknn.llm import fm_index, suffix_array
from divknn.llm.common import runs_of, table

from .helpers import AWKWARD, docs


def brute_words(rows):
    first = {}
    split = [(k, (t or "").encode().split()) for k, t in rows]
    rank = lambda k: (1 << 62) if k is None else k
    for k, w in split:
        for i in range(len(w) - 49):
            key = tuple(w[i : i + 50])
            first[key] = min(rank(k), first.get(key, rank(k)))
    out = []
    for k, w in split:
        gone = np.zeros(len(w), bool)
        for i in range(len(w) - 49):
            if first[tuple(w[i : i + 50])] < rank(k):
                gone[i : i + 50] = True
        out.append((str(k), len(w), int(gone.sum()), hashlib.sha256(b" ".join(x for x, g in zip(w, gone, strict=True) if not g)).hexdigest()))
    return sorted(out)


def brute_bytes(rows):
    first, rank = {}, lambda k: (1 << 62) if k is None else k
    texts = [(k, (t or "").encode()) for k, t in rows]
    for k, b in texts:
        for i in range(len(b) - 99):
            key = b[i : i + 100]
            first[key] = min((rank(k), i), first.get(key, (rank(k), i)))
    out = []
    for k, b in texts:
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - 99):
            if first[b[i : i + 100]] < (rank(k), i):
                gone[i : i + 100] = True
        out.append((str(k), len(b), int(gone.sum()), len(runs_of(gone)[0]), hashlib.sha256(np.frombuffer(b, np.uint8)[~gone].tobytes()).hexdigest()))
    return sorted(out)


def passages():
    rng = np.random.default_rng(2)
    shared = [" ".join(f"s{x}" for x in rng.integers(0, 500, 70)) for _ in range(3)]
    rows = list(AWKWARD)
    for i in range(60):
        own = [f"o{x}" for x in rng.integers(0, 40, int(rng.integers(5, 200)))]
        at = int(rng.integers(len(own)))
        rows.append((100 + i, " ".join([*own[:at], shared[i % 3], *own[at:]])))
    return rows + [(500 + i, rows[-1 - i][1]) for i in range(5)] + [(600, "\x00 a" * 300)]


@pytest.mark.parametrize("most", [None, 150])
def test_words(spark, most):
    for rows in (passages(), [], [(1, "x")]):
        got = fm_index.remove_repeated_passages(docs(spark, rows), most).collect()
        assert sorted((str(r[0]), *r[1:]) for r in got) == brute_words(rows)


@pytest.mark.parametrize("most", [None, 400])
def test_bytes(spark, most):
    for rows in (passages(), [], [(1, "x")]):
        got = suffix_array.remove_repeated_strings(docs(spark, rows), most).collect()
        assert sorted((str(r[0]), *r[1:]) for r in got) == brute_bytes(rows)


def surrounded(n, inner, outer, few):
    """One passage in ``n`` surroundings, of which some share the words next to it."""
    rng = np.random.default_rng(9)
    passage = " ".join(f"p{x}" for x in range(inner))
    some = lambda: " ".join(f"q{x}" if rng.random() < 0.2 else f"r{rng.integers(10**9)}" for x in rng.integers(0, few, int(rng.integers(1, outer))))
    return [(i, f"{some()} {passage} {some()}") for i in range(n)]


def test_a_passage_in_ever_new_surroundings(spark):
    rows = surrounded(10_000, 60, 12, 5)
    got = fm_index.remove_repeated_passages(docs(spark, rows)).collect()
    assert sorted((str(r[0]), *r[1:]) for r in got) == brute_words(rows)
    rows = surrounded(1_500, 40, 8, 5)
    got = suffix_array.remove_repeated_strings(docs(spark, rows), 50_000).collect()
    assert sorted((str(r[0]), *r[1:]) for r in got) == brute_bytes(rows)


def test_given_documents(spark, sf):
    df = table(spark, sf, "documents")
    rows = [(r[0], r[1]) for r in df.select("doc_id", "text").collect()]
    assert sorted((str(r[0]), *r[1:]) for r in fm_index.remove_repeated_passages(df).collect()) == brute_words(rows)
    assert sorted((str(r[0]), *r[1:]) for r in suffix_array.remove_repeated_strings(df).collect()) == brute_bytes(rows)


def test_matching_statistics():
    rng = np.random.default_rng(7)
    for sigma, cap in ((2, 6), (4, 10), (30, 5)):
        text = rng.integers(0, sigma + 1, 400)
        index = fm_index.FMIndex(text, sigma + 1, cap)
        queries = [rng.integers(1, sigma + 1, int(rng.integers(1, 60))) for _ in range(20)]
        got = {}
        sizes = np.array([len(q) for q in queries])
        for who, at, depth, row in index.stream(np.concatenate(queries), np.cumsum(sizes), sizes):
            for w, a, d, r in zip(who, at, depth, row, strict=True):
                got[w, a] = d
                if d == cap:  # the first place of a full match
                    s = int(index.first(np.array([r]))[0])
                    assert np.array_equal(text[s : s + d], queries[w][a : a + d]) and not any(np.array_equal(text[i : i + d], queries[w][a : a + d]) for i in range(s))
        held = text.tobytes()
        for w, q in enumerate(queries):
            for a in range(len(q)):
                want = 0
                while want < cap and a + want < len(q):
                    part = q[a : a + want + 1].tobytes()
                    p = held.find(part)
                    while p >= 0 and p % 8:
                        p = held.find(part, p + 1)
                    if p < 0:
                        break
                    want += 1
                assert got[w, a] == want


def test_two_stage_order():
    rng = np.random.default_rng(9)
    for top in (2, 5, 256):
        text = rng.integers(0, top, 3000).astype(np.uint8)
        text[500:900], text[1000:1300] = 1, text[0:300]
        order = suffix_array.suffix_order(text, 40)
        assert sorted(order) == list(range(len(text)))
        raw = text.tobytes() + b"\0" * 40
        keys = [raw[i : i + 40] for i in order]
        assert keys == sorted(keys)
