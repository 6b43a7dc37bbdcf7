import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from farspan.llm import substring_dedup
from farspan.llm.suffix_array import COVER, MODULUS, equal_classes, suffix_order


def brute(rows, length=100):
    first = {}
    texts = sorted({(d if d is not None else -(2**63), (t or "").encode()) for d, t in rows})
    for d, raw in texts:
        for p in range(len(raw) - length + 1):
            s = raw[p : p + length]
            first[s] = min(first.get(s, (d, p)), (d, p))
    out = []
    for d, t in rows:
        raw, key = (t or "").encode(), d if d is not None else -(2**63)
        cut = bytearray(len(raw))
        for p in range(len(raw) - length + 1):
            if first[raw[p : p + length]] < (key, p):
                cut[p : p + length] = b"\1" * length
        spans = sum(1 for i, c in enumerate(cut) if c and (i == 0 or not cut[i - 1]))
        out.append((d if d is not None else -1, len(raw), sum(cut), spans, bytes(b for b, c in zip(raw, cut) if not c)))
    return sorted(out)


def corpus(seed, n=60):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdéñ") for _ in range(r.randint(1, 9)))
    passage = " ".join(word() for _ in range(40))
    base = [" ".join(word() for _ in range(r.choice([0, 5, 30, 150]))) for _ in range(10)]
    rows = []
    for i in range(n):
        t = r.choice(base)
        if r.random() < 0.5:
            at = r.randrange(len(t) + 1)
            t = t[:at] + passage[r.randrange(20) :] + t[at:]
        if r.random() < 0.3:
            t = t + t
        rows.append((r.choice([i, i * 7]), t))
    return rows + [(500, "a" * 400), (501, "ab" * 150), (502, "x" + "a" * 130), (None, passage), (None, None), (3, None), (9, ""), (600, passage), (600, passage), (600, passage + "!"), (601, "é" * 99)]


def run(spark, rows, **more):
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as id", "2 as th", "'z' as starts").repartition(4)
    got = substring_dedup.remove_repeats(df, **more).withColumn("n", F.expr("aggregate(spans, 0L, (s, x) -> s + x.end - x.start)"))
    return sorted((x.doc_id if x.doc_id is not None else -1, x.n_bytes, x.n, len(x.spans), bytes(x.kept)) for x in got.collect())


def test_equals_brute_force(spark):
    for seed in (1, 2):
        rows = corpus(seed)
        assert run(spark, rows) == brute(rows)


def test_frequent_anchors_by_context(spark, monkeypatch):
    monkeypatch.setattr(substring_dedup, "HOT_CLASS", 0)
    monkeypatch.setattr(substring_dedup, "HELD", 7)
    rows = corpus(3)
    assert run(spark, rows) == brute(rows)


def test_small_blocks(spark, monkeypatch):
    monkeypatch.setattr(substring_dedup, "BLOCK_BYTES", 500)
    rows = corpus(4)
    assert run(spark, rows) == brute(rows)


def test_empty_table(spark):
    assert run(spark, []) == []


def test_cover_meets_every_difference():
    assert {(a - b) % MODULUS for a in COVER for b in COVER} == set(range(MODULUS))


@settings(max_examples=60, deadline=None)
@given(st.binary(min_size=1, max_size=12), st.integers(1, 60), st.integers(0, 2**32))
def test_suffix_order(piece, times, seed):
    block = np.frombuffer(piece * times + piece[::-1] * 3, np.uint8)
    r = np.random.default_rng(seed)
    at = np.sort(r.choice(len(block), r.integers(1, len(block) + 1), replace=False))
    order = suffix_order(block, at, 100)
    cut = [block.tobytes()[i : i + 100].ljust(100, b"\0") for i in order]
    assert cut == sorted(cut)
    classes = equal_classes(block, order, 100)
    assert all((classes[i] == classes[i + 1]) == (cut[i] == cut[i + 1]) for i in range(len(cut) - 1))


@pytest.mark.parametrize("length", [33, 64, 300, 1000])
def test_other_lengths(spark, length):
    r = random.Random(length)
    word = lambda: "".join(r.choice("abcdé") for _ in range(r.randint(1, 9)))
    base = [" ".join(word() for _ in range(r.choice([5, 60, 400]))) for _ in range(5)]
    rows = [(i, (base[i % 5] + base[(i * 3) % 5])[r.randrange(80) :]) for i in range(16)] + [(99, "a" * 2100), (98, None)]
    assert run(spark, rows, length=length) == brute(rows, length)


def test_lengths_out_of_range(spark):
    df = spark.createDataFrame([(1, "a")], "doc_id long, text string")
    for length in (32, 16_416):
        with pytest.raises(ValueError):
            substring_dedup.remove_repeats(df, length=length)


def test_entries_keep_their_fields():
    one = substring_dedup.packed([5], [6], [2**32 - 1], [7], [-8], [2**31 - 1], [16_383], [16_000], [2])
    assert [x.tolist() for x in substring_dedup.unpacked([c.to_numpy() for c in one.columns])] == [[5], [6], [7], [-8], [2**31 - 1], [16_383], [16_000], [2], [2**32 - 1]]


def test_texts_without_id(spark):
    passage = "".join(random.Random(3).choice("abcdefgh ") for _ in range(150))
    rows = [(None, f"{passage}{i}") for i in range(40)] + [(0, passage)]
    assert run(spark, rows) == brute(rows)
