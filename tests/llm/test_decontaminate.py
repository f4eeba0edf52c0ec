import numpy as np
from divknn.llm import decontaminate
from divknn.llm.common import FOLD, table, word_hashes

from .helpers import AWKWARD, docs


def plain_distance(item, text):
    row = [0] * (len(text) + 1)
    for i, a in enumerate(item, 1):
        new = [i]
        for j, b in enumerate(text, 1):
            new.append(min(row[j - 1] + (a != b), row[j] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_alignment():
    rng = np.random.default_rng(4)
    for _ in range(200):
        item, text = rng.integers(0, 4, int(rng.integers(1, 12))), rng.integers(0, 4, int(rng.integers(0, 30)))
        edits, a, b = decontaminate.edit_place(item, text)
        assert edits == plain_distance(item, text)
        if b > a:
            assert edits == plain_distance(item, text[a:b])


def edited(words, edits, rng):
    words = list(words)
    for _ in range(edits):
        at = int(rng.integers(len(words)))
        kind = rng.integers(3)
        if kind == 0:
            words[at] = f"q{rng.integers(10**6)}"
        elif kind == 1:
            words.insert(at, f"q{rng.integers(10**6)}")
        elif len(words) > 1:
            del words[at]
    return words


def test_recall_against_all_edits(spark, sf):
    rng = np.random.default_rng(6)
    bench = table(spark, sf, "benchmark")
    items = [(r["item_id"], r["text"].encode().translate(FOLD).decode().split()) for r in bench.collect()]
    rows, want = [], []
    for i in range(600):
        k, words = items[i % len(items)]
        noise = [f"n{x}" for x in rng.integers(0, 500, 60)]
        rows.append((i, " ".join([*noise[:30], *edited(words, int(rng.integers(0, len(words) // 5 + 1)), rng), *noise[30:]])))
        want.append((i, k))
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.benchmark_matches(docs(spark, rows), bench).collect()}
    recall = len(got & set(want)) / len(want)
    assert recall >= 0.95, recall


def test_given_documents_against_brute_force(spark):
    d = "/root/testdata/sf0.001"
    df, bench = table(spark, d, "documents"), table(spark, d, "benchmark")
    texts = [(r[0], r[1]) for r in df.select("doc_id", "text").collect()]
    got = decontaminate.benchmark_matches(df, bench).collect()
    want = set()
    items = [(r["item_id"], word_hashes([r["text"].encode().translate(FOLD)])[0]) for r in bench.collect()]
    for k, t in texts:
        h = word_hashes([t.encode().translate(FOLD)])[0]
        for i, item in items:
            if len(np.intersect1d(item, h)) >= len(np.unique(item)) - len(item) // 5 and decontaminate.edit_place(item, h)[0] <= len(item) // 5:
                want.add((k, i))
    assert want and {(r["doc_id"], r["item_id"]) for r in got} == want
    kept = decontaminate.drop_contaminated(df, bench)
    assert kept.columns == df.columns and {r[0] for r in kept.select("doc_id").collect()} == {k for k, _ in texts} - {k for k, _ in want}


def test_awkward(spark, sf):
    bench = table(spark, sf, "benchmark")
    item = bench.first()["text"]
    rows = [*AWKWARD, (70, item), (71, item.upper()), (None, item)]
    got = decontaminate.benchmark_matches(docs(spark, rows), bench).collect()
    assert sorted(str(r["doc_id"]) for r in got) == ["70", "71", "None"]
    assert decontaminate.benchmark_matches(docs(spark, rows), bench.limit(0)).count() == 0
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "one")], "item_id long, text string")
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.benchmark_matches(docs(spark, rows), odd).collect()} == {(4, 3)}
    assert decontaminate.drop_contaminated(docs(spark, []), bench).count() == 0
