"""Readers, writers, intermediate tables, SQL functions, and measures that no registered query compares."""

import hashlib
import os

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from farspan.functions import udfs
from farspan.operators import evaluate, probe_batch, profiles, score
from farspan.plans import queries
from farspan.sources import intermediate, sinks, tables
from farspan.streaming import streams

DOCS = "doc_id long, category string, text string, n_chars long"


def test_corpora_put_together(spark):
    a = spark.createDataFrame([(1, "en", "x", 1)], DOCS)
    b = spark.createDataFrame([(2, "fr", "y")], "doc_id long, category string, text string")
    assert sorted(tuple(r) for r in tables.gather(a, b).collect()) == [(1, "en", "x", 1), (2, "fr", "y", None)]


def test_whole_files_and_formats(spark, tmp_path):
    (tmp_path / "books").mkdir()
    for name, text in (("a.txt", "one\ntwo"), ("b.txt", "three")):
        (tmp_path / "books" / name).write_text(text)
    got = {os.path.basename(r.path): r.text for r in tables.whole_text(spark, str(tmp_path / "books")).collect()}
    assert got == {"a.txt": "one\ntwo", "b.txt": "three"}
    df = spark.createDataFrame([(1, "en", "x", 1), (2, "fr", "y", 2)], DOCS)
    for fmt in ("json", "orc", "csv"):
        sinks.write(df, f"{tmp_path}/{fmt}", fmt)
        assert sorted(tuple(r) for r in tables.read(spark, fmt, f"{tmp_path}/{fmt}", DOCS).collect()) == [(1, "en", "x", 1), (2, "fr", "y", 2)]


def test_views(spark, tmp_path):
    for name in tables.NAMES:
        spark.createDataFrame([(len(name),)], "n int").write.parquet(f"{tmp_path}/{name}.parquet")
    tables.register_views(spark, str(tmp_path))
    assert spark.sql("select d.n + l.n as n from documents d, lineitem l").first().n == 17


def test_selection_and_slices(spark, tmp_path):
    df = spark.createDataFrame([(i, "en" if i % 2 else "de", ["a", str(i)]) for i in range(10)], "doc_id long, category string, toks array<string>")
    sinks.write_selection(df, f"{tmp_path}/p", rows_per_file=2)
    assert spark.read.parquet(f"{tmp_path}/p").where("category = 'de'").count() == 5
    assert sum(f.endswith(".parquet") for _, _, files in os.walk(f"{tmp_path}/p") for f in files) >= 5
    sinks.write_selection(df, f"{tmp_path}/c", "csv")
    assert {r[0] for r in spark.read.csv(f"{tmp_path}/c/category=en").select("_c1").collect()} == {f"a {i}" for i in range(1, 10, 2)}
    runs = []

    def one(name):
        runs.append(name)
        if name == "bad":
            raise ValueError(name)
        return df.limit(1)

    assert sinks.write_slices(one, ["x", "y"], f"{tmp_path}/s", os.path.exists) == ["x", "y"]
    with pytest.raises(ValueError):
        sinks.write_slices(one, ["x", "z", "bad"], f"{tmp_path}/s", os.path.exists)
    assert sinks.write_slices(one, ["x", "y", "z"], f"{tmp_path}/s", os.path.exists) == [] and runs == ["x", "y", "z", "bad"]


def test_bucketed_tables_join_without_a_shuffle(spark):
    df = spark.range(100).select("id", (F.col("id") % 7).alias("v"))
    for name in ("farspan_left", "farspan_right"):
        sinks.save_bucketed(df, name, "id", 4)
    try:
        joined = spark.table("farspan_left").hint("merge").join(spark.table("farspan_right"), "id")
        assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString() and joined.count() == 100
    finally:
        for name in ("farspan_left", "farspan_right"):
            spark.sql(f"drop table {name}")


def test_intermediate_tables(spark):
    """Only what is made inside a scratch goes at its end; settings are as before; no shuffle file is left."""
    key = intermediate._CLEANUP
    before = spark.conf.get(key, None)
    df = spark.range(1000).select((F.col("id") % 10).alias("k")).groupBy("k").count()
    kept = intermediate.written(df, "kept")
    with intermediate.scratch(spark) as made:
        assert intermediate.written(df, "inner").count() == 10 and len(made) == 1 and os.path.isdir(made[0])
        with intermediate.scratch(spark) as deeper:
            intermediate.written(df, "deeper")
        assert len(made) == 1 and not os.path.exists(deeper[0])
    assert not os.path.exists(made[0]) and kept.count() == 10 and spark.conf.get(key, None) == before


def test_no_local_folder_on_a_cluster():
    class Conf:
        def get(self, *_):
            return None

    class Context:
        master = "spark://host:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    with pytest.raises(RuntimeError):
        intermediate.shared_dir(Session())
    Context.master = "local[4]"
    assert intermediate.shared_dir(Session()) == intermediate.LOCAL_DIR


def test_smaller_batches_are_kept(spark):
    key = intermediate._ARROW_BYTES
    before = spark.conf.get(key)
    try:
        for held, want in (("64m", str(4 << 20)), ("1m", "1m"), (str(1 << 20), str(1 << 20))):
            spark.conf.set(key, held)
            intermediate.lean_batches(spark.range(1))
            assert spark.conf.get(key) == want
    finally:
        spark.conf.set(key, before)


def test_vector_functions(spark):
    assert udfs.cosine(pd.Series([[1, 0], [1, 1], [0, 0], None]), pd.Series([[1, 0], [1, 0], [1, 0], [1]])).tolist()[:3] == pytest.approx([1.0, 0.5**0.5, 0.0])
    one = pd.Series([[1.0, 0.0], [0.0, 2.0]])
    assert np.allclose(np.array(udfs.rotary(one, pd.Series([0, 3])).tolist()), [[1, 0], [-2 * np.sin(3), 2 * np.cos(3)]])
    assert udfs.far_share(pd.Series([0.5, 0.3, 0.2]), pd.Series([5, 5, 5]), pd.Series([1, 3, 5]), pd.Series([2, 2, 2])) == pytest.approx(0.8)
    assert udfs.far_share(pd.Series([0.0]), pd.Series([1]), pd.Series([1]), pd.Series([0])) == 0.0


def test_smoothing_and_explaining(spark):
    w = spark.createDataFrame([(1, "en", 0, list("abcabc")), (2, "en", 0, list("xyzxyz"))], "doc_id long, category string, start long, toks array<string>").withColumn("len", F.size("toks"))
    plain = {(r.doc_id, r.q): r.ds_q for r in score.token_strength(w, profiles.HexDot(), 2).collect()}
    smooth = {(r.doc_id, r.q): r.smooth for r in score.smoothed(score.token_strength(w, profiles.HexDot(), 2), 1).collect()}
    for (d, q), x in smooth.items():
        assert x == pytest.approx(np.mean([plain[d, j] for j in (q - 1, q, q + 1) if (d, j) in plain]))
    told = sorted((r.q, r.tok, r.ds_q) for r in score.explain_window(w, profiles.HexDot(), 2, 1, 0).collect())
    assert [(q, t) for q, t, _ in told] == list(enumerate("abcabc", 1)) and [x for _, _, x in told] == pytest.approx([plain[1, q] for q in range(1, 7)])


def test_cost_ratios(spark):
    w = spark.createDataFrame([(i,) for i in range(5)], "doc_id long")
    got = {(r.method, r.model): r.ratio for r in evaluate.ratios(evaluate.cost_rows(w, 128, 32), "token_evaluations").collect()}
    assert got == {("attention", "small"): 1.0, ("attention", "large"): 1.0, ("segments", "small"): 4.0, ("segments", "large"): 4.0}


def test_first_copies_within_a_watermark(spark, tmp_path):
    import datetime as dt

    t0 = dt.datetime(2024, 1, 1)
    spark.createDataFrame([(1, "a", t0), (2, "a", t0 + dt.timedelta(minutes=5)), (3, "b", t0)], "doc_id long, text string, at timestamp").coalesce(1).write.parquet(f"{tmp_path}/d")
    stream = spark.readStream.schema("doc_id long, text string, at timestamp").parquet(f"{tmp_path}/d")
    streams.drain(streams.first_copies_within(stream, "at", "1 hour"), f"{tmp_path}/o", f"{tmp_path}/c")
    got = sorted(r.doc_id for r in spark.read.parquet(f"{tmp_path}/o").collect())
    assert len(got) == 2 and 3 in got


def test_long_text_probes(spark):
    hay = [f"w{i}" for i in range(300)]
    for task, size in (("lead", 16), ("lines", 8), ("turns", 16)):
        for depth in (0.0, 0.5, 1.0):
            p = evaluate.probe(task, 3, depth, hay, 128)
            (a, b), part = p["spans"][0], hay[-8:] if task == "lines" else hay[:16]
            assert p["toks"][a : b + 1] == part and b - a + 1 == size and len(p["toks"]) == 128
            assert [p["toks"][q] for q in p["query_pos"]] == part[: len(p["query_pos"])]
            assert evaluate.hit_share(profiles.HexDot(), 16, p["toks"], p["query_pos"], p["spans"], p["answers"]) in (0.0, 1.0)
    rows = spark.createDataFrame([(i, hay[i:]) for i in range(4)], "doc_id long, toks array<string>")
    one = {r.probe_id: r.hit for r in evaluate.probed(rows, [profiles.HexDot()], 16, ("single_2", "lead")).collect()}
    two = {r.probe_id: r.hit for r in evaluate.probe_hits(evaluate.probes(rows, ("single_2", "lead")), profiles.HexDot(), 16).collect()}
    assert one == two and len(one) == 4 * 2 * 11


def test_probes_in_batches(spark, monkeypatch):
    """Words of probes made in arrays are those of ``probe``; hits are those of single probes, whatever the haystack's size;
    no probe is built or answered on its own."""
    rng = np.random.default_rng(3)
    words = lambda n: [f"w{i}" for i in rng.integers(0, 90, n)]
    held = [(7, words(128), words(40)), (123_456, words(300), words(61)), (9, [], words(5)), (10, words(20), words(245)), (11, words(40), [])]
    rows = spark.createDataFrame(held, "doc_id long, toks array<string>, passage array<string>")
    tasks, hexdot = (*evaluate.NIAH, *evaluate.RULER_MORE, *evaluate.LONG_TEXT), profiles.HexDot()
    whole = evaluate.probes(rows, tasks)
    want = {r.probe_id: (len(r.toks), len(r.answer_pos), hashlib.md5(" ".join(r.toks).encode()).hexdigest()) for r in whole.collect()}
    hits = {r.probe_id: r.hit for r in evaluate.probe_hits(whole, hexdot, 16).collect()}
    assert {r.probe_id: (r.len, r.answers, r.h) for r in evaluate.probe_digests(rows, tasks).collect()} == want and len(want) == 5 * 16 * 11
    assert {r.probe_id: r.hit for r in evaluate.probed(rows, [hexdot], 16, tasks).collect()} == hits
    texts = [("x" * i + str(i)).encode()[:55] for i in range(60)]
    assert [bytes(r).hex() for r in probe_batch.md5(probe_batch._padded(texts))] == [hashlib.md5(x).hexdigest() for x in texts]
    monkeypatch.setattr(evaluate, "hit_share", None)
    _, b, c = zip(*held, strict=True)
    probe_batch.layout(evaluate.NIAH, (0.5,), 256, 128, 40)
    monkeypatch.setattr(evaluate, "probe", None)
    assert len(list(probe_batch.hits([1, 2], [b[0]] * 2, [c[0]] * 2, evaluate.NIAH, (0.5,), 256, 16, 4.6, 16))) == 2


def test_probes_tallied(spark):
    """Sums of hits by task are those of single probes, in as many rows as tasks and partitions, not probes."""
    rng, tasks = np.random.default_rng(5), ("single_3", "multikey_3", "multivalue", "lines")
    words = lambda n: [f"w{i}" for i in rng.integers(0, 90, n)]
    held = [(n, words(128), words(30 + n % 2)) for n in (5, 99, 100, 12_345, 4, 1_000_000_007)]
    rows = spark.createDataFrame(held, "doc_id long, toks array<string>, passage array<string>").coalesce(1)
    single = evaluate.probe_hits(evaluate.probes(rows, tasks), profiles.HexDot(), 16)
    sums = evaluate.tallied(rows, profiles.HexDot(), 16, tasks)
    assert sums.count() == len(tasks)
    assert sorted(evaluate.accuracy(sums).collect()) == sorted(evaluate.accuracy(single).collect())
    assert evaluate.tallied(rows.limit(0), profiles.HexDot(), 16, tasks).count() == 0
    assert evaluate.accuracy(evaluate.tallied(rows, profiles.HexDot(), 16, ("turns",))).first() == evaluate.accuracy(evaluate.probe_hits(evaluate.probes(rows, ("turns",)), profiles.HexDot(), 16)).first()
    # made-up words of one answer are hashed only if a probe holds them
    plan = probe_batch.layout(("single_2",), (0.5,), 256, 128, 40)
    assert probe_batch._seeds(plan.names, plan.pairs, plan.used, 3).rows == 2


LONG = [(1, 128, 200), (2, 128, 400), (3, 300, 59), (4, 128, 40)]


def _long_haystacks(spark):
    """(doc_id, toks, passage) with more words than the 256 tokens of a probe hold, but for the last."""
    held = [(n, [f"w{n}_{i}" for i in range(size)], [f"p{i}" for i in range(passage)]) for n, size, passage in LONG]
    return spark.createDataFrame(held, "doc_id long, toks array<string>, passage array<string>")


def test_accuracy_is_of_whole_haystacks(spark, monkeypatch):
    """niah_accuracy: a long passage or window shortens no haystack, and every word of it competes with the needle."""
    prose = [t for t in evaluate.NIAH if t not in ("single_1", "multikey_2", "multikey_3")]
    for r in evaluate.probes(_long_haystacks(spark)).collect():
        n, size, passage = LONG[int(r.probe_id.split(":")[1]) - 1]
        held = {w for w in r.toks if w.startswith(f"w{n}_")}
        assert len(held) == (size if r.task in prose else 0) and {f"p{i}" for i in range(passage)} <= set(r.toks)
        assert len(r.toks) >= size + passage and (n != 4 or len(r.toks) == 256)
    monkeypatch.setattr(queries, "_haystacks", lambda s, d: _long_haystacks(s))
    want = evaluate.accuracy(evaluate.probe_hits(evaluate.probes(_long_haystacks(spark)), profiles.HexDot(), 16))
    assert sorted(queries.niah_accuracy(spark, "").collect()) == sorted(want.collect())


def test_digests_are_of_whole_haystacks(spark, monkeypatch):
    """niah_probes: a long passage or window shortens no haystack; sizes and texts are those of single probes."""
    monkeypatch.setattr(queries, "_haystacks", lambda s, d: _long_haystacks(s))
    want = {r.probe_id: (len(r.toks), hashlib.md5(" ".join(r.toks).encode()).hexdigest()) for r in evaluate.probes(_long_haystacks(spark)).collect()}
    got = {r.probe_id: (r.len, r.h) for r in queries.niah_probes(spark, "").collect()}
    assert got == want and len(got) == len(LONG) * 8 * 11
    # needle of three words and question of three besides the haystack and its passage
    assert [got[f"single_2:{n}:0.5:0"][0] for n, *_ in LONG] == [max(256, size + passage + 6) for _, size, passage in LONG]


def test_ruler_probes_are_of_whole_haystacks(spark, monkeypatch):
    """ruler_probes: the five tasks beside the needles keep their haystack as well, and all 13 are answered in it."""
    monkeypatch.setattr(queries, "_haystacks", lambda s, d: _long_haystacks(s))
    tasks = (*evaluate.NIAH, *evaluate.RULER_MORE)
    asked = evaluate.probes(_long_haystacks(spark), tasks)
    for r in asked.where(F.col("task").isin(*evaluate.RULER_MORE)).collect():
        n, size, _ = LONG[int(r.probe_id.split(":")[1]) - 1]
        assert len({w for w in r.toks if w.startswith(f"w{n}_")}) == size
    assert sorted(queries.ruler_probes(spark, "").collect()) == sorted(evaluate.accuracy(evaluate.probe_hits(asked, profiles.HexDot(), 16)).collect())


def test_proxy_model_by_hand(spark):
    """Vocabulary of two words, one window to learn from, one to judge."""
    schema = "doc_id long, start long, toks array<string>"
    picked, held = spark.createDataFrame([(1, 0, list("abaab"))], schema), spark.createDataFrame([(2, 0, list("abz"))], schema)
    got = evaluate.proxy_lm(picked, held, 2).first()
    # unigram a 3/6, b 2/6, rest 1/6; pairs a>b 2 of 3, a>a 1 of 3, b>a 1 of 1; cache weight: a third and fourth a, second b
    lam = min(0.5, 3 / 5)
    first, second, third = 3 / 6, 0.5 * 2 / 6 + 0.5 * 2 / 3, (1 - lam) * (0.5 * 1 / 6 + 0)
    assert got.far_rate == pytest.approx(lam) and got.tokens == 3
    assert got.nats == pytest.approx(-(np.log(first) + np.log(second) + np.log(third)) / 3)
