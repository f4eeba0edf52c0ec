"""Spark query against its SQL in DuckDB."""

import math

import duckdb


def run_oracle(sql, sf_dir):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    rel = con.sql(sql)
    return rel.columns, rel.fetchall()


def same(spark_df, sql, sf_dir):
    cols, want = run_oracle(sql, sf_dir)
    names = sorted(cols)
    assert sorted(spark_df.columns) == names, (spark_df.columns, cols)
    got = sorted((tuple(r[c] for c in names) for r in spark_df.collect()), key=str)
    place = [cols.index(c) for c in names]
    want = sorted((tuple(r[i] for i in place) for r in want), key=str)
    assert len(got) == len(want), (len(got), len(want))
    key = lambda r: tuple(x if not isinstance(x, float) else round(x, 4) for x in r)
    got, want = sorted(got, key=lambda r: str(key(r))), sorted(want, key=lambda r: str(key(r)))
    for g, w in zip(got, want, strict=True):
        for a, b in zip(g, w, strict=True):
            assert a == b or (isinstance(a, float) and math.isclose(a, b, rel_tol=1e-6, abs_tol=2e-6)), (g, w)
    return sum(g != w for g, w in zip(got, want, strict=True))
