"""Streams: contamination watch, delta indexing, latency monitor, sessions, dedup, joins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ngramlake.functions.text import key_of, tokens
from ngramlake.operators import index as idx

LATE = "10 minutes"


def read_stream(spark: SparkSession, folder: str, schema, name: str | None = None, files: int = 1) -> DataFrame:
    """New Parquet files of a folder; ``name`` picks one table of a folder of tables.  Times
    without a zone are read in the session's, for watermarks need a zone."""
    r = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    df = (r.option("pathGlobFilter", name) if name else r).parquet(folder)
    local = [f.name for f in df.schema.fields if f.dataType.typeName() == "timestamp_ntz"]
    return df.withColumns({c: F.col(c).cast("timestamp") for c in local})


def run_now(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run over what there is, into a table in memory of that name."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def tumbling_counts(events: DataFrame, length: str = "1 hour", late: str = LATE) -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", length), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def latency_monitor(events: DataFrame, length: str = "1 hour", slide: str = "30 minutes", late: str = LATE) -> DataFrame:
    """Count, failures and p95 of each sliding window (sketch-based percentile)."""
    g = events.withWatermark("ts", late).groupBy(F.window("ts", length, slide))
    return g.agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("failed"), F.percentile_approx("value", 0.95).alias("p95")).select(F.col("window.start").alias("start"), "n", "failed", "p95")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = LATE) -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def distinct_events(events: DataFrame, late: str = LATE) -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def error_followups(events: DataFrame, within: str = "30 minutes", late: str = LATE) -> DataFrame:
    """Events of a user within a span after an error: a stream-stream interval join."""
    errors = events.where("event_type = 'error'").select(F.col("user_id").alias("u"), F.col("ts").alias("at"), F.col("event_id").alias("error_id")).withWatermark("at", late)
    rest = events.where("event_type <> 'error'").withWatermark("ts", late)
    return rest.join(errors, (F.col("user_id") == F.col("u")) & (F.col("ts") > F.col("at")) & (F.col("ts") <= F.col("at") + F.expr(f"interval {within}"))).select("error_id", "event_id", "user_id", "ts")


def contamination_watch(docs: DataFrame, patterns: DataFrame, length: int, text: str = "text") -> DataFrame:
    """``doc_id, key`` of arriving documents that hold one of the test windows (a fixed,
    broadcast set, expanded by soft search beforehand)."""
    t = tokens(F.col(text))
    own = F.transform(F.sequence(F.lit(0), F.size("t") - length), lambda i: key_of(F.slice("t", i + 1, length)))
    rows = docs.select("doc_id", t.alias("t")).where(F.size("t") >= length).select("doc_id", F.explode(own).alias("key"))
    return rows.join(F.broadcast(patterns.select("key").distinct()), "key", "left_semi")


def delta_index(docs: DataFrame, index: idx.WindowIndex, commit: Callable[[idx.WindowIndex, int], None], text: str = "text"):
    """Appends each micro-batch to the index; ``commit`` stores it by batch id, so a batch
    that runs again replaces its own result."""
    held = {"index": index, "batch": -1}

    def each(batch: DataFrame, number: int) -> None:
        if number <= held["batch"]:
            return
        grown = idx.append_index(held["index"], batch.select("doc_id", tokens(F.col(text)).alias("tokens")))
        commit(grown, number)
        held.update(index=grown, batch=number)

    return docs.writeStream.foreachBatch(each).trigger(availableNow=True)
