"""SQL access: divergences as functions and searches as table functions."""

from __future__ import annotations

import re

from divknn.functions import generators
from divknn.operators.vectors import LocalTop
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

NAMES = ("squared_euclidean", "itakura_saito", "exponential", "shannon", "lp_norm", "lp_quasi")


def register(spark: SparkSession) -> list[str]:
    """``bregman_<generator>(x, y)`` for arrays of doubles, inlined when a query is analysed; the names made."""
    made = []
    for name in NAMES:
        body = f"greatest(aggregate(zip_with(x, y, (a, b) -> {generators.get(name).term('a', 'b')}), 0D, (s, v) -> s + v), 0D)"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION bregman_{name}(x ARRAY<DOUBLE>, y ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
        made.append(f"bregman_{name}")
    spark.udtf.register("bregman_knn", BregmanKnn)
    return made


@udtf(returnType="id: bigint, divergence: double")
class BregmanKnn:
    """``SELECT * FROM bregman_knn(TABLE(points) [PARTITION BY ..], ARRAY(..), k, 'exponential')``: the best k of each partition.

    Over a partitioned table every partition gives its k best; ``ORDER BY divergence, id LIMIT k`` makes them one.
    """

    def __init__(self):
        self.top = None
        self.ids: list[int] = []
        self.rows: list[list[float]] = []

    def eval(self, row, query, k, generator):
        import numpy as np

        if self.top is None:
            self.top = LocalTop(generators.get(generator), np.array([0]), np.array([query], float), k, False)
        self.ids.append(row["id"])
        self.rows.append(row["vec"])
        if len(self.ids) == 1024:
            self._flush()

    def _flush(self):
        import numpy as np

        if self.ids:
            self.top.add(np.array(self.ids), np.array(self.rows, float))
            self.ids, self.rows = [], []

    def terminate(self):
        if self.top is not None:
            self._flush()
            found = self.top.rows()
            yield from zip(found.column("id").to_pylist(), found.column("divergence").to_pylist(), strict=True)


def literal(vector) -> str:
    """SQL text of a vector."""
    out = "array(" + ",".join(f"{float(v)!r}D" for v in vector) + ")"
    return re.sub(r"(inf|nan)D", r"double('\1')", out)
