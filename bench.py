"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = HERE + os.pathsep + os.environ.get("PYTHONPATH", "")

from divknn.functions import generators as G  # noqa: E402
from divknn.operators import approx, baselines  # noqa: E402
from divknn.operators.index import build_index  # noqa: E402
from divknn.operators.search import exact_knn  # noqa: E402
from divknn.operators.vectors import scan_knn  # noqa: E402
from divknn.sources import views  # noqa: E402
from divknn.storage import saved  # noqa: E402


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name, work):
        began = time.perf_counter()
        out = work()
        if hasattr(out, "write"):
            out.write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)
        return out

    for view, m in (("emb64", 8), ("doc_hash100", 13), ("event_profile192", 28), ("line_mix64", 22)):
        v = views.catalogue()[view]
        gen = G.get(v.generator)
        points = timed(f"{view}_load", lambda v=v: saved(v.load(spark, sf_dir)))
        queries = views.sample_queries(points, 50).cache()
        queries.count()
        timed(f"{view}_scan_k20", lambda points=points, queries=queries, gen=gen: scan_knn(points, queries, gen, 20))
        index = timed(f"{view}_build_forest", lambda points=points, gen=gen, m=m: build_index(points, gen, m))
        timed(f"{view}_exact_k20", lambda index=index, queries=queries: exact_knn(index, queries, 20))
        cells = timed(f"{view}_build_cells", lambda points=points, gen=gen: baselines.build_cells(points, gen))
        if view != "line_mix64":  # its candidates are most of 600,000 points for every query
            timed(f"{view}_cells_k20", lambda cells=cells, queries=queries: baselines.cell_knn(cells, queries, 20))
            tree = timed(f"{view}_build_tree", lambda points=points, gen=gen: baselines.build_whole_tree(points, gen))
            timed(f"{view}_tree_k20", lambda tree=tree, queries=queries: baselines.tree_knn(tree, queries, 20))
            timed(f"{view}_approx_p80_k20", lambda index=index, queries=queries: approx.approx_knn(index, queries, 20, 0.8))
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
