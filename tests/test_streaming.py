"""Streams give what the batch gives; sources and table functions read back."""

from pyspark.sql import functions as F

from ngramlake.functions.text import SEP
from ngramlake.operators import index as idx
from ngramlake.operators import udtf
from ngramlake.sources import tables
from ngramlake.sources.window_index import WindowIndexSource
from ngramlake.streaming import events as ev


def folder(spark, df, path, parts=3):
    df.repartition(parts).write.mode("overwrite").parquet(str(path))
    return str(path)


def test_tumbling_equals_batch(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet")
    stream = ev.read_stream(spark, folder(spark, e, tmp_path / "e"), e.schema, files=9)
    got = ev.run_now(ev.tumbling_counts(stream), "tumbling", "complete")
    want = e.groupBy(F.date_trunc("hour", "ts").alias("start"), "event_type").count()
    assert {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}
    twice = ev.read_stream(spark, folder(spark, e.unionByName(e), tmp_path / "d"), e.schema, files=9)
    assert ev.run_now(ev.distinct_events(twice), "distinct_events").count() == e.count()
    assert ev.run_now(ev.session_counts(stream), "sessions", "append").count() >= 0
    assert ev.run_now(ev.latency_monitor(stream), "latency", "complete").agg(F.sum("n")).first()[0] == 2 * e.count()
    assert ev.run_now(ev.error_followups(stream), "followups").count() >= 0


def test_watch_and_delta(spark, tmp_path):
    docs = spark.createDataFrame([(1, "a b c d e"), (2, "x y z"), (3, "c d e f")], "doc_id long, text string")
    stream = ev.read_stream(spark, folder(spark, docs, tmp_path / "docs"), docs.schema)
    watched = ev.run_now(ev.contamination_watch(stream, spark.createDataFrame([(SEP.join("cde"),)], "key string"), 3), "watched")
    assert {r.doc_id for r in watched.collect()} == {1, 3}
    start = idx.build_index(tables.corpus(spark.createDataFrame([(0, "a b")], "doc_id long, text string")), 3, 4)
    kept = []
    ev.delta_index(stream, start, lambda i, n: kept.append(i)).option("checkpointLocation", str(tmp_path / "c")).start().awaitTermination()
    whole = idx.build_index(tables.corpus(docs.unionByName(spark.createDataFrame([(0, "a b")], "doc_id long, text string"))), 3, 4)
    rows = lambda i: {tuple(r) for r in i.runs.select("key", "run").collect()}
    assert len(kept[-1].deltas) == 3 and rows(idx.compact_index(kept[-1])) == rows(whole)


def test_sources(spark, tmp_path):
    docs = tables.corpus(spark.createDataFrame([(0, "b a c"), (1, "b a d")], "doc_id long, text string"))
    index = idx.build_index(docs, 2, 2, with_postings=False)
    index.runs.write.parquet(str(tmp_path / "runs"))
    spark.dataSource.register(WindowIndexSource)
    got = spark.read.format("window_index").option("runs", str(tmp_path / "runs")).option("prefix", "b").load()
    assert [(r.key, r.run) for r in got.collect()] == [(f"b{SEP}a", 2)]
    assert idx.index_report(index)["runs_rows"] == index.runs.count()
    udtf.register(spark)
    assert spark.sql("select gram from text_windows('A b, c', 2)").count() == 3
    docs.select("doc_id").write.json(str(tmp_path / "j"))
    assert tables.read_any(spark, str(tmp_path / "j"), "json", "doc_id long").count() == 2
    assert tables.hash_sample(docs, "doc_id", 1).count() == 1
