"""The pipeline's stages against plain Python on a small table."""

import random
from collections import Counter

import pytest

import corpus_pipeline
from tests.llm.test_ngram_join import brute as components
from tests.llm.test_substring_dedup import brute as repeats


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    root = tmp_path_factory.mktemp("sf")
    r = random.Random(11)
    syllables = {"en": ["the", "ing", "tion", "sh"], "fr": ["le", "eau", "qu", "ment"]}
    word = lambda lang: "".join(r.choice(syllables[lang]) for _ in range(r.randint(1, 4)))
    text = lambda lang, n: " ".join(word(lang) for _ in range(n))
    passage = text("en", 40)
    rows, labels = [], []
    for i in range(160):
        lang = "en" if i % 2 else "fr"
        t = text(lang, r.choice([20, 80, 150]))
        if i % 9 == 0:
            t = t + " " + passage
        if i % 8 == 3:
            t += " blorkish stuff"
        labels.append((i, 1, int(i % 8 == 3)))
        rows.append((i, t, lang, "s", len(t)))
    rows += [(200, rows[5][1], "en", "s", 1), (201, rows[7][1] + " more", "en", "s", 1), (202, "123 456", "en", "s", 7), (203, None, None, None, None), (5, rows[5][1], "en", "s", 1), (None, text("en", 30), "en", "s", 1)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{root}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{root}/labels.parquet")
    return str(root)


def test_stages(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    names = docs.columns
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = [(r.doc_id, r.text) for r in docs.collect()]
        docs = stage(spark, docs, folder)
        assert docs.columns == names
        docs = spark.createDataFrame(docs.collect(), docs.schema)
        kept[name] = (before, [(r.doc_id, r.text) for r in docs.collect()])
    before, after = kept["toxicity"]
    assert {d for d, _ in before} - {d for d, _ in after} == {i for i in range(160) if i % 8 == 3}
    before, after = kept["language_id"]
    assert {d for d, _ in before} - {d for d, _ in after} == {202, 203}
    before, after = kept["ngram_jaccard"]
    same = {(d, c) for d, _, c in components(before)}
    assert sorted(d for d, _ in after if d is not None) == sorted({c for d, c in same if d != -1}) and len([1 for d, _ in after if d is None]) == 1
    before, after = kept["substring_dedup"]
    want = {(d if d != -1 else None): k.decode(errors="ignore") for d, n, cut, _, k in repeats(before) if k or not cut}
    assert dict(after) == want
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, folder).collect()
    assert sum(x.n_tokens for x in packed) == sum(len(t.split()) for _, t in after)


def test_run(spark, folder):
    """The run is its stages one after another, on all rows, and every word that is left is packed once."""
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, folder)
    want = Counter()
    for r in docs.select("doc_id", "text").collect():
        want[r.doc_id] += len((r.text or "").encode().split())
    got = Counter()
    bins = {}
    for r in corpus_pipeline.run(spark, folder).collect():
        got[r.doc_id] += r.n_tokens
        if r.sequence_id is not None:
            bins.setdefault((r.sequence_id, r.capacity), []).append((r.position, r.n_tokens))
    assert got == want and len(want) > 100
    for (_, capacity), own in bins.items():
        own.sort()
        assert all(p == sum(n for _, n in own[:i]) for i, (p, _) in enumerate(own)) and sum(n for _, n in own) <= capacity


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stages_take_odd_tables(spark, folder, name):
    """Empty tables, nulls in every column, repeated rows and further columns with names that clash."""
    stage, schema = dict(corpus_pipeline.STAGES)[name], "doc_id long, text string, lang string, source string, n_chars long, score double, node long, id long, starts string"
    odd = [(None,) * 9, (None,) * 9, (1, "the cat sat", None, None, None, 0.5, 1, 2, "z"), (1, "the cat sat", None, None, None, 0.5, 1, 2, "z"), (2, "", "en", "s", 0, None, None, None, None), (3, "x" * 5000, "en", "s", 5000, 1.0, 3, 4, "y")]
    nothing = stage(spark, spark.createDataFrame([], schema), folder)
    assert nothing.collect() == []
    out = stage(spark, spark.createDataFrame(odd, schema), folder)
    if name != "best_fit_packing":
        assert out.columns == [x.split()[0] for x in schema.split(", ")]
    out.collect()
