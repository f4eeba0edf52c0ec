import numpy as np
from divknn.llm import jaccard_join
from divknn.llm.common import table

from .helpers import AWKWARD, WORDS, docs


def lower(t):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in t)


def brute(rows):
    sets = []
    for _, t in rows:
        w = WORDS.findall(lower(t or ""))
        sets.append(frozenset(tuple(w[i : i + 3]) for i in range(len(w) - 2)) if len(w) > 2 else frozenset([tuple(w)] if w else []))
    parent = list(range(len(rows)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    index = {}
    for i, s in enumerate(sets):
        near = {}
        for g in s:
            for j in index.get(g, ()):
                near[j] = near.get(j, 0) + 1
            index.setdefault(g, []).append(i)
        for j, n in near.items():
            if 100 * n >= 90 * (len(s) + len(sets[j]) - n):
                parent[root(i)] = root(j)
    least = {}
    for i, (k, _) in enumerate(rows):
        if k is not None:
            least[root(i)] = min(k, least.get(root(i), k))
    return sorted((str(k), len(s), str(least.get(root(i)))) for i, ((k, _), s) in enumerate(zip(rows, sets, strict=True)))


def check(df):
    rows = [(r[0], r[1]) for r in df.select("doc_id", "text").collect()]
    got = jaccard_join.similar_components(df).collect()
    assert sorted((str(r[0]), r[1], str(r[2])) for r in got) == brute(rows)


def test_given_documents(spark):
    check(table(spark, "/root/testdata/sf0.01", "documents"))


def test_chains_small_sets_and_awkward(spark):
    rng = np.random.default_rng(5)
    rows = list(AWKWARD)
    for base in range(30):
        words = [f"w{x}" for x in rng.integers(0, 3000, int(rng.integers(3, 120)))]
        for j in range(8):
            words = list(words)
            for _ in range(int(rng.integers(0, 3))):
                words[int(rng.integers(len(words)))] = f"z{rng.integers(10**9)}"
            if rng.random() < 0.3:
                words = words + ["end"]
            rows.append((1000 + base * 10 + j, " ".join(words)))
    check(docs(spark, rows))
    check(docs(spark, []))


def test_one_of_each_group_stays(spark):
    out = jaccard_join.one_per_group(docs(spark, [(3, "a b c d"), (1, "A b  c d"), (2, "x y z"), (2, "x y z"), (9, None)]))
    assert sorted(r[0] for r in out.collect()) == [1, 2, 9]


def test_large_groups_of_near_copies(spark):
    rng = np.random.default_rng(8)
    rows = []
    for base in range(3):
        words = [f"w{x}" for x in rng.integers(0, 3000, 150)]
        family = [words]
        for j in range(150):
            own = list(family[int(rng.integers(len(family)))] if rng.random() < 0.3 else words)
            for _ in range(int(rng.integers(0, 9))):
                own[int(rng.integers(len(own)))] = f"z{rng.integers(40)}" if rng.random() < 0.5 else f"y{rng.integers(10**9)}"
            if rng.random() < 0.2:
                own = own + [f"t{x}" for x in range(int(rng.integers(20)))]
            family.append(own)
        rows += [(base * 1000 + j, " ".join(w)) for j, w in enumerate(family)]
    rng.shuffle(rows)
    check(docs(spark, [(int(k), t) for k, t in rows]))
