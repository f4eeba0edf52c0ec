"""Keys of all sets are shuffled once, and copies in one task post none."""

from divknn.llm import jaccard_join

from .helpers import AWKWARD, docs


def test_keys_meet_by_one_shuffle(spark, monkeypatch):
    plans = []
    saved = jaccard_join.saved
    monkeypatch.setattr(jaccard_join, "saved", lambda df: (plans.append(df._jdf.queryExecution().executedPlan().toString()), saved(df))[1])
    rows = [(1, 10, 0, 1), (2, 10, 0, 1), (2, 10, 0, 1), (3, 11, 0, 1), (3, 11, 0, 1), (4, 12, 1, 2), (5, 12, 1, 2), (6, 12, 2, 1)]
    posted = spark.createDataFrame(rows, "node long, key long, c int, need int")
    got = sorted(map(tuple, jaccard_join._met(posted).collect()))
    assert got == sorted({r for r in rows if r[1] != 11})
    assert len(plans) == 1 and plans[0].count("Exchange hashpartitioning") == 1


def test_copies_in_a_task_post_once(spark):
    rows = [(100 + i, "one text of a few words that is copied " * 3) for i in range(50)] + AWKWARD
    signed = jaccard_join.signed(docs(spark, rows).coalesce(1)).collect()
    named = [r for r in signed if r["node"] is not None]
    assert sum(r["fresh"] for r in named) == len({r["node"] for r in named}) < len(named)
