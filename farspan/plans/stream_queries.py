"""Streams drained once over the given tables, for comparison with batch answers."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farspan.functions.columns import scaled
from farspan.operators import profiles
from farspan.plans.oracles import SCORED, with_
from farspan.sources.intermediate import shared_dir
from farspan.streaming import streams

L, K = 128, 32


def _folder(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/farspan-stream-{uuid.uuid4().hex}"


def _documents(s: SparkSession, d: str) -> DataFrame:
    # a stream reads folders; the glob matches the one table
    return streams.read_documents(s, f"{d}/documents.parque[t]")


def _events(s: SparkSession, d: str) -> DataFrame:
    return streams.read_events(s, f"{d}/events.parque[t]")


def stream_scores(s: SparkSession, d: str) -> DataFrame:
    root = _folder(s)
    streams.drain(streams.score_stream(_documents(s, d), profiles.HexDot(), L, K).drop("cpu_ms"), f"{root}/out", f"{root}/checkpoint")
    return s.read.parquet(f"{root}/out").select("doc_id", "category", "start", scaled(F.col("ds"), 6).alias("ds_e6"), scaled(F.col("du"), 9).alias("du_e9"))


def stream_moments(s: SparkSession, d: str) -> DataFrame:
    raw = streams.score_stream(_documents(s, d), profiles.HexDot(), L, K)
    held = streams.drain_to_memory(streams.running_sums(raw), "sums_" + uuid.uuid4().hex)
    m = streams.moments_of_sums(held)
    return m.select("scope", "n", F.round("ds_mean", 6).alias("ds_mean"), F.round("ds_sd", 6).alias("ds_sd"), F.round("du_mean", 9).alias("du_mean"))


def stream_daily_events(s: SparkSession, d: str) -> DataFrame:
    held = streams.drain_to_memory(streams.tumbling(_events(s, d)), "daily_" + uuid.uuid4().hex)
    return held.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n", F.round("value", 4).alias("value"))


def stream_first_copies(s: SparkSession, d: str) -> DataFrame:
    root = _folder(s)
    streams.drain(streams.first_copies(_documents(s, d)).select(F.md5("text").alias("h")), f"{root}/out", f"{root}/checkpoint")
    return s.read.parquet(f"{root}/out")


STREAMS = {f.__name__: f for f in (stream_scores, stream_moments, stream_daily_events, stream_first_copies)}

STREAM_ORACLES = {
    "stream_scores": with_(*SCORED) + "select doc_id, category, start, round(ds * 1e6)::bigint as ds_e6, round(du * 1e9)::bigint as du_e9 from raw",
    "stream_moments": with_(*SCORED) + "select category as scope, count(*) as n, round(avg(ds), 6) as ds_mean, round(stddev_pop(ds), 6) as ds_sd, round(avg(du), 9) as du_mean from raw group by category",
    "stream_daily_events": "select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n, round(sum(value), 4) as value from events group by all",
    "stream_first_copies": "select distinct md5(text) as h from documents",
}
