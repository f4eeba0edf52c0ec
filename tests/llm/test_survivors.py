"""Rows without an id, and ids with several texts, in the stage that keeps one of each group."""

import numpy as np
from divknn.llm import jaccard_join

from .helpers import docs
from .test_jaccard_join import brute as brute_op3


def kept(spark, rows):
    out = jaccard_join.one_per_group(docs(spark, rows))
    assert out.columns == docs(spark, []).columns
    return sorted(((r["doc_id"], r["text"]) for r in out.collect()), key=str)


def text(seed, swap=None):
    words = [f"w{x}" for x in np.random.default_rng(seed).integers(0, 5000, 60)]
    return " ".join(words if swap is None else words[:-1] + [swap])


def test_rows_without_id(spark):
    alone = [(None, text(i)) for i in range(6)]
    linked = [(None, text(20)), (7, text(20, "end")), (9, text(20, "stop")), (None, text(20))]
    nameless = [(None, text(30)), (None, text(30, "end")), (None, text(30))]
    bare = [(None, None), (None, ""), (None, " \t"), (None, None)]
    got = kept(spark, alone + linked + nameless + bare)
    left = [r for r in got if r in nameless]
    assert len(left) == 1 and sorted([*alone, linked[1], left[0], *bare], key=str) == got


def test_one_id_with_two_texts(spark):
    rows = [(5, text(1)), (5, text(2)), (3, text(2, "end")), (5, text(1)), (6, None), (6, None), (6, " "), (8, text(4)), (8, text(4, "end"))]
    got = kept(spark, rows)
    left = [r for r in got if r[0] == 8]
    assert len(left) == 1 and sorted([(5, text(1)), (3, text(2, "end")), (6, None), (6, " "), *left], key=str) == got


def test_every_group_keeps_one_row(spark):
    rng = np.random.default_rng(11)
    rows = [(None if rng.random() < 0.4 else int(rng.integers(0, 20)), text(int(rng.integers(0, 30)))) for _ in range(150)]
    got = kept(spark, rows)
    assert len({t for _, t in rows}) == len(got) == len({t for _, t in got})
    for k, t in got:
        assert k == min((i for i, u in rows if u == t and i is not None), default=None)


def test_groups_are_as_before(spark):
    rows = [(None, text(1)), (4, text(1, "end")), (None, text(2)), (4, text(3)), (2, None)]
    out = jaccard_join.similar_components(docs(spark, rows))
    assert sorted((str(r[0]), r[1], str(r[2])) for r in out.collect()) == brute_op3(rows)
