import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from farspan.functions.columns import starts, tokens
from farspan.functions.udfs import WindowSpans
from farspan.operators import windows


def step_by_step(n, L):
    """Front and back windows are taken off until at most three windows are left."""
    if n < L:
        return []
    front, back, low, high = [], [], 0, n
    while high - low > 3 * L:
        front.append(low)
        back.append(high - L)
        low, high = low + L, high - L
    rest = high - low
    if rest == L:
        middle = [low]
    elif rest <= 2 * L:
        middle = [low, high - L]
    else:
        middle = [low, low + (rest - L) // 2, high - L]
    return sorted(front + middle + back)


FIXED = {3: [], 4: [0], 5: [0, 1], 8: [0, 4], 9: [0, 2, 5], 12: [0, 4, 8], 13: [0, 4, 5, 9], 17: [0, 4, 6, 9, 13]}


def test_worked_values(spark):
    got = {r.n: r.s for r in spark.createDataFrame([(n,) for n in FIXED], "n long").select("n", starts(F.col("n"), 4).alias("s")).collect()}
    assert got == FIXED
    big = [32768, 32769, 65536, 65537, 98304, 98305, 200000]
    at = {r.n: r.s for r in spark.createDataFrame([(n,) for n in big], "n long").select("n", starts(F.col("n"), 32768).alias("s")).collect()}
    assert [len(at[n]) for n in big] == [1, 2, 2, 3, 3, 4, 7]
    assert at[200000] == [0, 32768, 65536, 83616, 101696, 134464, 167232]


@pytest.mark.parametrize("L", [1, 2, 5, 16])
def test_closed_form_is_the_stepwise_rule(spark, L):
    got = {r.n: r.s for r in spark.range(0, 40 * L + 3).select(F.col("id").alias("n"), starts(F.col("id"), L).alias("s")).collect()}
    assert all(got[n] == step_by_step(n, L) for n in got)


@settings(max_examples=100, deadline=None)
@given(st.integers(0, 5000), st.integers(1, 300))
def test_table_function(n, L):
    assert [s for _, s in WindowSpans().eval(n, L)] == step_by_step(n, L)


def docs(spark):
    rows = [(1, "en", "a b c d e f g h i", 17), (2, "en", "a b", 3), (3, "de", None, None), (4, "de", " \n ", 3), (5, "de", "x y z w", 7), (6, "en", "", 0)]
    return spark.createDataFrame(rows, "doc_id long, category string, text string, n_chars long")


def test_tokens(spark):
    one = spark.createDataFrame([("Aé b\u000b c.d",)], "t string")
    get = lambda mode: one.select(tokens(F.col("t"), mode).alias("x")).first().x
    assert get("word") == ["Aé", "b", "c.d"]
    assert get("wordpunct") == ["Aé", "b", "c", ".", "d"]
    assert get("char") == list("Aé b\u000b c.d") and get("utf8")[1:3] == ["C3", "A9"]
    assert all(0 <= int(x) < 50 for x in get("hash(50)"))


def test_cut_and_baselines(spark):
    t = windows.tokenize(docs(spark))
    got = {(r.doc_id, r.start): (r.part, r.toks) for r in windows.cut(t, 4).collect()}
    assert got == {(1, 0): ("front", list("abcd")), (1, 2): ("middle", list("cdef")), (1, 5): ("back", list("fghi")), (5, 0): ("middle", ["x", "y", "z", "w"])}
    assert {r.doc_id: r.toks for r in windows.truncate(t, 4).collect()} == {1: list("abcd"), 5: ["x", "y", "z", "w"]}
    assert sorted((r.doc_id, r.start) for r in windows.stride(t, 4, 3).collect()) == [(1, 0), (1, 3), (5, 0)]
    padded = {r.doc_id: r.toks for r in windows.cut(t, 4, short="pad").where("doc_id = 2").collect()}
    assert padded == {2: ["a", "b", "<pad>", "<pad>"]}
    assert {r.doc_id for r in windows.long_only(docs(spark), 4).collect()} == {1, 5}


def test_packing_keeps_tokens_in_order(spark):
    rows = [(i, "en", " ".join(f"d{i}t{j}" for j in range(3))) for i in range(50)]
    t = windows.tokenize(spark.createDataFrame(rows, "doc_id long, category string, text string"))
    packed = windows.concat_pack(t, 8, buckets=2).collect()
    seen = [x for r in packed for x in r.toks]
    assert all(len(r.toks) == 8 for r in packed) and len(seen) == len(set(seen)) and len(seen) > 130


def test_coverage_and_clean(spark):
    c = windows.coverage(windows.tokenize(docs(spark)), 4).collect()
    assert all(r.covered and r.distinct_starts and 0 <= r.overlap < 4 for r in c) and len(c) == 2
    more = docs(spark).union(spark.createDataFrame([(9, "en", "a b", 3), (10, "en", "*** ### a", 9)], "doc_id long, category string, text string, n_chars long"))
    assert {r.doc_id for r in windows.clean(more).collect()} == {1, 2, 5}


def test_scan_is_pruned_and_filtered(spark, tmp_path):
    docs(spark).withColumn("lang", F.lit("en")).write.parquet(f"{tmp_path}/documents.parquet")
    from farspan.sources import tables

    plan = windows.spans(windows.tokenize(windows.long_only(tables.read_corpus(spark, str(tmp_path)), 4)), 4)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThanOrEqual(n_chars,7)]" in plan and "Exchange" not in plan


def test_few_tasks_a_core_are_dealt_anew(spark):
    """More tasks than cores, but not many more, leave cores idle in the last round."""
    cores = spark.sparkContext.defaultParallelism
    for tasks, dealt in ((cores + 1, 4 * cores), (5 * cores, 5 * cores)):
        df = windows.spread(spark.range(0, 200, 1, tasks).withColumnRenamed("id", "doc_id"))
        assert df.rdd.getNumPartitions() == dealt and df.distinct().count() == 200
