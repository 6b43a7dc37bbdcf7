"""Structured Streaming forms: windows and raw scores on arrival, running moments, provisional choices, event time.

Scoring a window needs no other window, so it is a stateless map; standardising needs corpus moments, which are
kept as mergeable sums per category and read as the latest snapshot.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farspan.operators import score, windows

DOCUMENTS = "doc_id bigint, text string, lang string, source string, n_chars bigint"
EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_documents(spark: SparkSession, path: str, files_per_trigger: int = 100) -> DataFrame:
    return spark.readStream.schema(DOCUMENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 100) -> DataFrame:
    """Events with ts as an instant: a time without zone can't carry a watermark."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def score_stream(documents: DataFrame, profile, L: int, k: int) -> DataFrame:
    """Document stream to raw scores, append mode, no state."""
    named = documents.select("doc_id", F.col("lang").alias("category"), "text")
    return score.score_windows(windows.cut(windows.tokenize(named), L), profile, k)


def running_sums(raw: DataFrame) -> DataFrame:
    """Mergeable sums per category, for update or complete mode."""
    return raw.groupBy("category").agg(F.count("*").alias("n"), F.sum("ds").alias("ds_1"), F.sum(F.col("ds") ** 2).alias("ds_2"), F.sum("du").alias("du_1"), F.sum(F.col("du") ** 2).alias("du_2"))


def moments_of_sums(sums: DataFrame) -> DataFrame:
    n = F.col("n")
    sd = lambda x: F.sqrt(F.greatest(F.lit(0.0), F.col(f"{x}_2") / n - (F.col(f"{x}_1") / n) ** 2))
    return sums.select(F.col("category").alias("scope"), "n", (F.col("ds_1") / n).alias("ds_mean"), sd("ds").alias("ds_sd"), (F.col("du_1") / n).alias("du_mean"), sd("du").alias("du_sd"))


def provisional_picks(raw: DataFrame, moments_path: str, out_path: str, alpha: float, cut: float):
    """A foreachBatch writer: standardise with the latest snapshot of moments and keep scores above the cut.

    A batch is written under its number, so that a replayed batch replaces itself.
    """

    def write(batch: DataFrame, number: int) -> None:
        known = batch.sparkSession.read.parquet(moments_path)
        scored = score.combine(score.standardize(batch, "category", known=known), alpha)
        scored.where(F.col("lds") >= cut).write.mode("overwrite").parquet(f"{out_path}/batch={number}")

    return raw.writeStream.foreachBatch(write)


def tumbling(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts and sums by event type in event-time windows; rows later than the watermark are dropped."""
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(span.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("value")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "value")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Event types of each user session in order."""
    held = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("e"))
    return held.select("user_id", F.col("w.start").alias("start"), F.transform("e", lambda x: x["event_type"]).alias("toks"))


def first_copies(documents: DataFrame) -> DataFrame:
    """Exact copies dropped on arrival, by text hash (state grows with distinct texts; bound it by a watermark if there is one)."""
    return documents.withColumn("h", F.sha2(F.coalesce("text", F.lit("")), 256)).dropDuplicates(["h"]).drop("h")


def first_copies_within(documents: DataFrame, time_col: str, late: str) -> DataFrame:
    return documents.withWatermark(time_col, late).withColumn("h", F.sha2(F.coalesce("text", F.lit("")), 256)).dropDuplicatesWithinWatermark(["h"]).drop("h")


def interval_join(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream: events of two kinds by the same user within a span."""
    a = left.withWatermark("ts", late).select(F.col("user_id").alias("u"), F.col("ts").alias("ts_a"), F.col("event_id").alias("id_a"))
    b = right.withWatermark("ts", late).select("user_id", F.col("ts").alias("ts_b"), F.col("event_id").alias("id_b"))
    return a.join(b, (F.col("u") == F.col("user_id")) & (F.col("ts_b") >= F.col("ts_a")) & (F.col("ts_b") <= F.col("ts_a") + F.expr(f"INTERVAL {within}"))).select("user_id", "id_a", "id_b", "ts_a", "ts_b")


def with_labels(raw: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream-static join."""
    return raw.join(labels.select("doc_id", "quality", "toxic"), "doc_id", "left")


def top_m(raw: DataFrame, m: int):
    """The m strongest windows of each category, kept in state: a row goes out whenever it enters the list."""
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Top(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.kept = handle.getValueState("kept", "rows array<struct<ds: double, doc_id: bigint, start: bigint>>")

        def handleInputRows(self, key, rows, timers):
            have = [(r[0], r[1], r[2]) for r in self.kept.get()[0]] if self.kept.exists() else []
            before = set(have)
            for pdf in rows:
                have += list(zip(pdf["ds"], pdf["doc_id"], pdf["start"], strict=True))
                have = sorted(set(have), key=lambda r: (-r[0], r[1], r[2]))[:m]
            self.kept.update((have,))
            new = [r for r in have if r not in before]
            if new:
                yield pd.DataFrame({"category": [key[0]] * len(new), "ds": [r[0] for r in new], "doc_id": [r[1] for r in new], "start": [r[2] for r in new]})

        def close(self) -> None:
            pass

    return raw.groupBy("category").transformWithStateInPandas(Top(), "category string, ds double, doc_id bigint, start bigint", "update", "none")


def drain(df: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Run a stream over what is there now, into Parquet; a second run with the same checkpoint adds only what is new."""
    df.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path).awaitTermination()


def drain_to_memory(df: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.table(name)
