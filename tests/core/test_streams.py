import datetime as dt

from pyspark.sql import functions as F

from farspan.operators import profiles
from farspan.streaming import streams

T0 = dt.datetime(2024, 1, 1)


def events(spark, path):
    rows = [(i, T0 + dt.timedelta(minutes=m), u, kind, 1.0, "{}") for i, (m, u, kind) in enumerate([(0, 1, "view"), (10, 1, "purchase"), (100, 1, "view"), (5, 2, "view"), (300, 2, "purchase"), (3000, 3, "view")])]
    spark.createDataFrame(rows, "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string").write.parquet(path)
    return streams.read_events(spark, path)


def test_sessions_and_interval_join(spark, tmp_path):
    e = events(spark, f"{tmp_path}/e")
    streams.drain(streams.sessions(e), f"{tmp_path}/s", f"{tmp_path}/c1")
    got = sorted((r.user_id, r.toks) for r in spark.read.parquet(f"{tmp_path}/s").collect())
    assert got == [(1, ["view"]), (1, ["view", "purchase"]), (2, ["purchase"]), (2, ["view"])]  # the last session stays open
    joined = streams.interval_join(e.where("event_type = 'view'"), e.where("event_type = 'purchase'"))
    streams.drain(joined, f"{tmp_path}/j", f"{tmp_path}/c2")
    assert [(r.id_a, r.id_b) for r in spark.read.parquet(f"{tmp_path}/j").collect()] == [(0, 1)]


def documents(spark, path):
    rows = [(i, " ".join(f"w{(i * j) % 5}" for j in range(16)), "en" if i % 2 else "de", "s", 10) for i in range(10)]
    spark.createDataFrame(rows, streams.DOCUMENTS).write.parquet(path)
    return streams.score_stream(streams.read_documents(spark, path), profiles.HexDot(), 8, 2)


def test_picks_labels_and_state(spark, tmp_path):
    raw = documents(spark, f"{tmp_path}/d")
    held = spark.read.parquet(f"{tmp_path}/d")
    sums = streams.moments_of_sums(streams.drain_to_memory(streams.running_sums(raw), "running"))
    sums.write.parquet(f"{tmp_path}/m")
    streams.provisional_picks(raw, f"{tmp_path}/m", f"{tmp_path}/p", 0.5, 0.0).option("checkpointLocation", f"{tmp_path}/c1").trigger(availableNow=True).start().awaitTermination()
    picks = spark.read.parquet(f"{tmp_path}/p")
    assert 0 < picks.count() < 20 and picks.agg(F.min("lds")).first()[0] >= 0
    labels = spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int")
    streams.drain(streams.with_labels(raw, labels), f"{tmp_path}/l", f"{tmp_path}/c2")
    assert spark.read.parquet(f"{tmp_path}/l").where("quality = 1").select("doc_id").distinct().count() == 1
    assert held.count() == 10
    provider = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(provider)
    spark.conf.set(provider, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        seen = []
        query = streams.top_m(raw, 2).writeStream.outputMode("update").foreachBatch(lambda b, _: seen.extend(b.collect())).option("checkpointLocation", f"{tmp_path}/c3").trigger(availableNow=True).start()
        query.awaitTermination()
    finally:
        spark.conf.set(provider, before)
    best = {}
    for r in spark.read.parquet(f"{tmp_path}/l").collect():
        best.setdefault(r.category, []).append((-r.ds, r.doc_id, r.start))
    for c, rows in best.items():
        top = {(d, s) for _, d, s in sorted(rows)[:2]}
        assert top <= {(r.doc_id, r.start) for r in seen if r.category == c}


def test_late_rows_are_dropped(spark, tmp_path):
    e = events(spark, f"{tmp_path}/e")
    streams.drain(streams.tumbling(e), f"{tmp_path}/t", f"{tmp_path}/c")
    late = [(99, T0, 9, "view", 1.0, "{}")]
    spark.createDataFrame(late, "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string").write.mode("append").parquet(f"{tmp_path}/e")
    streams.drain(streams.tumbling(streams.read_events(spark, f"{tmp_path}/e")), f"{tmp_path}/t", f"{tmp_path}/c")
    assert spark.read.parquet(f"{tmp_path}/t").agg(F.sum("n")).first()[0] == 5
