"""SQL, streams, plans and the registry."""

import pytest
from divknn import workloads
from divknn.functions import generators as G
from divknn.functions import sql
from divknn.operators.index import build_index
from divknn.operators.search import exact_knn
from divknn.operators.vectors import best_k, scan_knn, scan_knn_columns
from divknn.sources import views
from divknn.streaming import streams
from pyspark.sql import functions as F

from .compare import same
from .test_engine import rows


@pytest.mark.parametrize("name", ["div_exp", "scan_knn_isd", "exact_knn_emb_exp", "exact_knn_part_isd", "cell_knn_emb_isd", "tree_range_emb_exp", "budgets_k20", "candidate_share", "six_dim_groups", "cost_curve", "abs_correlation", "knn_label_vote"])
def test_oracles(spark, sf, name):
    same(workloads.QUERIES[name](spark, sf), workloads.ORACLES[name], sf)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 25 * 20
    assert set(e.oracle_sql()) <= set(e.queries())


def test_sql(spark, sf):
    p = views.emb(spark, sf)
    p.createOrReplaceTempView("points")
    sql.register(spark)
    y = p.where("id = 3").first()["vec"]
    want = [r["id"] for r in scan_knn(p, p.where("id = 3").selectExpr("id qid", "vec yvec"), G.exponential(), 5).orderBy("rank").collect()]
    got = spark.sql(f"SELECT id, bregman_exponential(vec, {sql.literal(y)}) d FROM points ORDER BY d, id LIMIT 5").collect()
    assert [r["id"] for r in got] == want
    got = spark.sql(f"SELECT * FROM bregman_knn(TABLE(points), {sql.literal(y)}, 5, 'exponential') ORDER BY divergence, id LIMIT 5").collect()
    assert [r["id"] for r in got] == want


def test_plans(spark, sf, capsys):
    p = views.emb(spark, sf)
    q = views.sample_queries(p, 4)
    scan_knn_columns(p, q, G.exponential(), 5).explain()
    text = capsys.readouterr().out
    assert "WindowGroupLimit" in text and "BroadcastNestedLoopJoin" in text and "CartesianProduct" not in text


def test_append_equals_rebuild(spark, sf):
    p, g = views.emb(spark, sf), G.exponential()
    q = views.sample_queries(p, 5)
    grown = streams.append(build_index(p.where("id < 300"), g, 4), p.where("id >= 300"))
    assert rows(exact_knn(grown, q, 10)) == rows(scan_knn(p, q, g, 10))
    less = streams.remove(grown, p.where("id % 3 = 0"))
    assert rows(exact_knn(less, q, 10)) == rows(scan_knn(p.where("id % 3 <> 0"), q, g, 10))
    old = scan_knn(p.where("id < 300"), q, g, 10)
    assert rows(streams.merge_top(old, p.where("id >= 300"), q, g, 10)) == rows(scan_knn(p, q, g, 10))


def test_streams(spark, sf, tmp_path):
    p, g = views.emb(spark, sf), G.exponential()
    q = views.sample_queries(p, 3)
    p.repartition(2).write.parquet(f"{tmp_path}/p")
    q.write.parquet(f"{tmp_path}/q")
    stream = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/p")
    run = streams.running_top(stream, q, g, 5).writeStream.outputMode("update").format("memory").queryName("top").option("checkpointLocation", f"{tmp_path}/c").start()
    run.processAllAvailable()
    run.stop()
    final = best_k(spark.table("top").select("qid", "id", "divergence").distinct(), 5)
    assert rows(final) == rows(scan_knn(p, q, g, 5))
    index, seen = build_index(p, g, 4), []
    ask = spark.readStream.schema(q.schema).parquet(f"{tmp_path}/q")
    run = streams.answer_stream(index, ask, 5, lambda df, _: seen.extend(rows(df)), f"{tmp_path}/c2")
    run.processAllAvailable()
    run.stop()
    assert sorted(seen) == sorted(rows(scan_knn(p, q, g, 5)))


def test_event_windows(spark, sf, tmp_path):
    """A stream gives the windows of the whole table that the watermark has closed, each once, repeats ignored."""
    events = views.read(spark, sf, "events")
    first = events.orderBy("ts").limit(1).withColumn("ts", F.expr("ts + interval 60 days")).withColumn("event_id", F.lit(-1).cast("long"))  # closes the windows before
    events.unionByName(events.limit(50)).coalesce(1).write.parquet(f"{tmp_path}/e/1")
    first.write.parquet(f"{tmp_path}/e/2")
    stream = spark.readStream.schema(events.schema).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/e")
    run = streams.event_vectors(stream).writeStream.outputMode("append").format("memory").queryName("ev").option("checkpointLocation", f"{tmp_path}/c").start()
    run.processAllAvailable()
    run.stop()
    key = lambda df: sorted((r["user_id"], str(r["window"]["start"]), tuple(round(v, 4) for v in r["vec"])) for r in df.collect())
    got, want = key(spark.table("ev")), key(streams.event_vectors(events))
    assert len(got) > 100 and len(set(got)) == len(got) and set(got) <= set(want) and len(got) > 0.5 * len(want)


def test_sessions(spark, sf, tmp_path):
    events = views.read(spark, sf, "events")
    events.coalesce(1).write.parquet(f"{tmp_path}/e")
    stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/e")
    run = streams.session_counts(stream, "6 hours").writeStream.outputMode("complete").format("memory").queryName("se").option("checkpointLocation", f"{tmp_path}/c").start()
    run.processAllAvailable()
    run.stop()
    key = lambda df: sorted((r["user_id"], str(r["session"]["start"]), r["n"]) for r in df.collect())
    got = key(spark.table("se"))
    assert got == key(streams.session_counts(events, "6 hours")) and sum(n for _, _, n in got) == events.count()


def test_append_stream_survives_a_restart(spark, sf, tmp_path):
    p, g = views.emb(spark, sf), G.exponential()
    q, folder = views.sample_queries(p, 5), f"{tmp_path}/index"
    for i in (1, 2):
        p.where(f"id >= 300 and id % 2 = {i - 1}").coalesce(1).write.parquet(f"{tmp_path}/p{i}")

    def run(paths):
        stream = spark.readStream.schema(p.schema).parquet(f"{tmp_path}/in")
        import os
        import shutil

        for path in paths:
            for f in os.listdir(path):
                if f.endswith(".parquet"):
                    shutil.copy(f"{path}/{f}", f"{tmp_path}/in/{f}")
        go = streams.append_stream(build_index(p.where("id < 300"), g, 4), stream, folder, f"{tmp_path}/c")
        go.processAllAvailable()
        go.stop()

    (tmp_path / "in").mkdir()
    run([f"{tmp_path}/p1"])
    assert streams.latest_index(spark, folder).n == p.where("id < 300 or id % 2 = 0").count()
    run([f"{tmp_path}/p2"])  # a new driver knows nothing but the folder and the checkpoint
    grown = streams.latest_index(spark, folder)
    assert grown.n == p.count() and len(streams.versions(spark, folder)) == 2
    assert rows(exact_knn(grown, q, 10)) == rows(scan_knn(p, q, g, 10))
    pages = grown.points.groupBy("page").count().collect()
    assert min(r["page"] for r in pages) == 0 and max(r["count"] for r in pages) <= grown.page_bytes // (4 * 64)


def test_query_readers(spark, tmp_path):
    (tmp_path / "q.json").write_text('{"qid": 1, "yvec": [0.5, 2]}\n')
    (tmp_path / "q.csv").write_text("1,0.5;2\n")
    want = [(1, [0.5, 2.0])]
    assert [(r[0], r[1]) for r in views.queries_from_json(spark, f"{tmp_path}/q.json").collect()] == want
    assert [(r[0], r[1]) for r in views.queries_from_csv(spark, f"{tmp_path}/q.csv").collect()] == want


def test_shared_folder_is_needed_on_a_cluster(spark, monkeypatch):
    from divknn import storage

    class Other:
        master, conf = "spark://host:7077", {}

        @property
        def sparkContext(self):  # noqa: N802
            return self

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        storage.shared_dir(Other())
