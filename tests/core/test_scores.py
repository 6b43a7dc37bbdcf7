import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from farspan.config import Config
from farspan.operators import cells, kernel, profiles, score
from farspan.sources import intermediate
from farspan.selector import LongDependencySelector

FIXED = [  # tokens, k, strength, uniformity over the triangle
    ("a b a c a b", 2, 0.284913106, -0.042138745),
    ("a b c d e f", 2, 0.045258267, -0.001372569),
    ("the cat sat on the mat", 2, 0.112319055, -0.019535546),
]


def full(profile, toks):
    state, L = profile.state(toks), len(toks)
    p = np.zeros((profile.heads, L, L))
    p[:] = profile.rows(state, 0, L)
    return p


def direct(p, k, over="triangle", ddof=0):
    L = p.shape[0]
    far = np.array([[p[q, i] if i <= q - k else 0.0 for i in range(L)] for q in range(L)])
    if over == "token":
        values = far.sum(axis=1)
    elif over == "square":
        values = far[k:, : max(0, L - k)].ravel()
    else:
        values = np.array([p[q, i] for q in range(L) for i in range(L) if i <= q - k])
    du = -values.var(ddof=ddof) if len(values) - ddof > 0 else 0.0
    return far.sum() / L, du


@pytest.mark.parametrize(("text", "k", "ds", "du"), FIXED)
def test_worked_values(text, k, ds, du):
    r = kernel.score(profiles.HexDot(), text.split(), [k])[0]
    assert r["ds"] == pytest.approx(ds, abs=1e-9) and r["du"] == pytest.approx(du, abs=1e-9)


def test_variants_of_the_worked_value():
    toks = FIXED[0][0].split()
    get = lambda **m: kernel.score(profiles.HexDot(), toks, [2], **m)[0]["du"]
    assert get(over="square") == pytest.approx(-0.033185897, abs=1e-9) and get(over="token") == pytest.approx(-0.075987381, abs=1e-9)


@pytest.mark.parametrize("L", [1, 2, 7, 64, 129])
@pytest.mark.parametrize("name", ["hexdot", "small", "uniform", "copy"])
def test_blocks_equal_the_full_matrix(L, name):
    r = np.random.default_rng(L)
    toks = [f"t{x}" for x in r.integers(0, 20, L)]
    p = profiles.named(name)
    near = 1e-6 if name == "small" else 1e-10  # single-precision products depend on the block
    whole = full(p, toks)
    assert np.allclose(whole.sum(axis=2), 1)
    for k in (0, 1, L // 4, L, L + 3):
        for over in ("triangle", "square", "token"):
            for block in (1, 5, 64):
                got = kernel.score(p, toks, [k], block, over)[0]
                want = direct(whole.mean(axis=0), k, over)
                assert got["ds"] == pytest.approx(want[0], abs=near) and got["du"] == pytest.approx(want[1], abs=near)
        heads = [direct(h, k) for h in whole]
        got = kernel.score(p, toks, [k], head_agg="per_head")[0]
        assert (got["ds"], got["du"]) == (pytest.approx(np.mean([h[0] for h in heads]), abs=near), pytest.approx(np.mean([h[1] for h in heads]), abs=near))


def test_windows_together_score_as_alone(spark, monkeypatch):
    """Windows of several lengths in one pass; each is never scored on its own, unless it is empty or too long."""
    r = np.random.default_rng(2)
    rows = [(i, "en", 0, [f"t{x}" for x in r.integers(0, 30, n)]) for i, n in enumerate([0, 1, 40, 130, 40, 130, 7])]
    w = spark.createDataFrame(rows, "doc_id long, category string, start long, toks array<string>")
    for p, near in ((profiles.HexDot(), 1e-12), (profiles.named("small"), 1e-6), (profiles.named("large"), 1e-6), (profiles.Decoder(layer=2), 1e-5)):
        for more in ({}, {"front": "<s>"}, {"var_over": "token"}, {"ddof": 1}):
            got = {(x.doc_id, x.k): x for x in score.score_windows(w, p, [3, 50], **more).collect()}
            assert len(got) == 14
            for d, _, _, toks in rows:
                toks = ["<s>"] * ("front" in more) + toks
                for x in kernel.score(p, toks, [3, 50], over=more.get("var_over", "triangle"), ddof=more.get("ddof", 0)):
                    for c in ("len", "ds", "du", "far_mean", "far_cells", "sink_share", "pair_ops"):
                        assert got[d, x["k"]][c] == pytest.approx(x[c], abs=near), (p.name, c)
    small = profiles.named("small")
    monkeypatch.setattr(profiles, "TABLE", 0)
    profiles._first_layer.cache_clear()
    words, codes = [f"t{i}" for i in range(30)], r.integers(0, 30, (5, 40))
    monkeypatch.setattr(kernel, "token_strengths", None)
    one = kernel.score_many(small, words, codes, [3])
    monkeypatch.setattr(profiles, "TABLE", 1 << 22)
    profiles._first_layer.cache_clear()
    assert [x[0]["ds"] for x in one] == pytest.approx([x[0]["ds"] for x in kernel.score_many(small, words, codes, [3])], abs=1e-6)


def test_profiles_in_one_pass(spark):
    """A list of profiles gives each one's rows, from one reading of the windows."""
    r = np.random.default_rng(6)
    rows = [(i, "en", 0, [f"t{x}" for x in r.integers(0, 30, n)]) for i, n in enumerate([1, 40, 1_100, 40])]
    w = spark.createDataFrame(rows, "doc_id long, category string, start long, toks array<string>")
    listed = [profiles.named("small"), profiles.named("large")]
    both = score.score_windows(w, listed, [3, 50])
    assert str(both._jdf.queryExecution().executedPlan().toString()).count("MapInArrow") == 1
    key = lambda x: (x.doc_id, x.k, x.profile)
    got = {key(x): x for x in both.drop("cpu_ms").collect()}
    alone = {key(x): x for p in listed for x in score.score_windows(w, p, [3, 50]).drop("cpu_ms").collect()}
    assert got == alone and len(got) == 16


def test_heads_share_their_keys():
    """Keys that several heads share are held once; positions turn them as one by one."""
    codes, words = np.arange(12).reshape(2, 6), [f"t{i}" for i in range(12)]
    for p in (profiles.named("small"), profiles.named("large")):
        q, k, _ = p.states(words, codes)
        assert q.shape == (2, p.heads, 6, p.width) and k.shape == (2, p.kv_heads, 6, p.width)
        one, two = p.state(words[6:])
        logits = q[1] @ np.repeat(k[1], p.heads // p.kv_heads, axis=0).transpose(0, 2, 1)
        assert logits == pytest.approx((one / np.sqrt(p.width)) @ two.transpose(0, 2, 1), abs=1e-4)


def test_sinks_of_all_layers_in_one_pass(spark, monkeypatch):
    from farspan.operators import evaluate

    r = np.random.default_rng(4)
    rows = [(i, "en", 0, [f"t{x}" for x in r.integers(0, 30, n)]) for i, n in enumerate([1, 40, 130, 40])]
    w = spark.createDataFrame(rows, "doc_id long, category string, start long, toks array<string>")
    want = {j: np.mean([kernel.token_strengths(profiles.Decoder(layer=j), t, [0])[2] for *_, t in rows]) for j in range(1, 5)}
    got = {x.layer: x for x in evaluate.sink_by_layer(w, lambda j: profiles.Decoder(layer=j), 4).collect()}
    assert got.keys() == want.keys() and all(got[j].sink_share == pytest.approx(want[j], abs=1e-5) and got[j].windows == 4 for j in want)
    monkeypatch.setattr(profiles.Decoder, "state", None)
    assert profiles.Decoder(layer=3).sinks(["a", "b"], np.array([[0, 1, 1]])).shape == (1, 3)
    mixed = evaluate.sink_by_layer(w, lambda j: profiles.Analytic("sink" if j == 1 else "self"), 2).collect()
    assert {x.layer: x.windows for x in mixed} == {1: 4, 2: 4}


def test_known_attention():
    toks, L = list("abcdefgh"), 8
    get = lambda kind, k: kernel.score(profiles.Analytic(kind), toks, [k])[0]
    assert get("uniform", 1)["ds"] == pytest.approx(sum((q - 1) / q for q in range(1, 9)) / 8)
    assert (get("self", 2)["ds"], get("self", 2)["du"]) == (0, 0)
    p = 2 / (L - 2 + 1)
    assert get("sink", 2)["ds"] == (L - 2) / L and get("sink", 2)["du"] == pytest.approx(-p * (1 - p)) and get("sink", 2)["sink_share"] == 1
    assert get("previous", 0)["ds"] == 1 and get("uniform", 9)["ds"] == 0
    four = kernel.score(profiles.Analytic("uniform"), list("abcd"), [1])[0]
    assert four["ds"] == pytest.approx(23 / 48) and four["du"] == pytest.approx(-41 / 5184)


def test_several_k_in_one_pass():
    toks = [hashlib.md5(str(i).encode()).hexdigest()[:2] for i in range(90)]
    many = kernel.score(profiles.HexDot(), toks, [5, 20, 45])
    assert [r["ds"] for r in many] == [kernel.score(profiles.HexDot(), toks, [k])[0]["ds"] for k in (5, 20, 45)]


def test_rotary_attention_depends_on_distance_only():
    p = profiles.Decoder()
    a, b = p.state(["x"] * 12)
    rows = p.rows((a, b), 0, 12)
    logits = (a @ b.transpose(0, 2, 1))[0]
    assert np.allclose(logits[5, 3], logits[9, 7], atol=1e-3) and rows.shape == (4, 12, 12)


def test_deeper_layer_and_saved_weights(tmp_path):
    toks = [f"w{i % 7}" for i in range(20)]
    deep = profiles.Decoder(layer=2)
    assert np.allclose(full(deep, toks).sum(axis=2), 1)
    np.savez(tmp_path / "w.npz", **profiles.Decoder().weights())
    held = profiles.Decoder(name="weights", path=str(tmp_path / "w.npz"))
    assert np.allclose(full(held, toks), full(profiles.Decoder(), toks))


def test_sampled_rows_are_near_the_exact_strength():
    toks = [f"w{(i * 7) % 40}" for i in range(256)]
    exact = kernel.score(profiles.HexDot(), toks, [64])[0]["ds"]
    near = kernel.score_sampled(profiles.HexDot(), toks, 64, 64)
    assert abs(near["ds_hat"] - exact) < 4 * near["se"] + 1e-3
    every = kernel.score_sampled(profiles.HexDot(), toks, 64, 10_000)
    assert every["ds_hat"] == pytest.approx(exact)


def windows(spark):
    rows = [(i, "en" if i % 2 else "de", 0, f"a b a c a{i} b d e".split()) for i in range(12)]
    return spark.createDataFrame(rows, "doc_id long, category string, start long, toks array<string>").withColumn("len", F.size("toks"))


def test_cells_agree_with_the_kernel(spark):
    w = windows(spark)
    one = {r.doc_id: r for r in cells.scores(cells.cells(w), 2).collect()}
    two = {r.doc_id: r for r in score.score_windows(w, profiles.HexDot(), 2).collect()}
    for d, r in one.items():
        assert r.ds == pytest.approx(two[d].ds) and r.ds_block == pytest.approx(r.ds) and r.du == pytest.approx(two[d].du) and r.off < 1e-12
    last = cells.cumulative(cells.cells(w)).where("q = m").agg(F.min("a"), F.max("a")).first()
    assert last[0] == pytest.approx(1) and last[1] == pytest.approx(1)
    with pytest.raises(ValueError, match="too many"):
        cells.cells(w.withColumn("len", F.lit(2_000_000)))


def test_cells_in_arrays_have_no_limit(spark, monkeypatch):
    """The registered queries' form of the cells: as the relation, and not refused where the relation is."""
    w = windows(spark).unionByName(spark.createDataFrame([(50, "en", 0, ["a"], 1), (51, "de", 3, ["b", "a"], 2)], "doc_id long, category string, start long, toks array<string>, len int"))
    want = {r.doc_id: r for r in cells.scores(cells.cells(w), 2).collect()}
    upto = {(r.doc_id, r.m): r.a for r in cells.cumulative(cells.cells(w)).where("q = 4").collect()}
    monkeypatch.setattr(cells, "MOST_CELLS", 10)
    monkeypatch.setattr(cells, "HELD_CELLS", 40)
    with pytest.raises(ValueError, match="too many"):
        cells.cells(w)
    got = {r.doc_id: r for r in cells.window_scores(w, 2).collect()}
    assert got.keys() == want.keys()
    for d, r in got.items():
        assert (r.ds, r.ds_block, r.du, r.off) == pytest.approx(tuple(want[d][c] for c in ("ds", "ds_block", "du", "off")), abs=1e-12)
    rows = {(r.doc_id, r.m): r.a for r in cells.cumulative_row(w, 4).collect()}
    assert rows.keys() == upto.keys() and len(rows) == 48 and all(rows[x] == pytest.approx(upto[x]) for x in upto)


def test_learned_vectors_are_kept_for_all_words(spark):
    """More words than the 50,000 that once kept their vectors, in several blocks; unknown words are zero."""
    rng = np.random.default_rng(5)
    table = {f"w{i}": x for i, x in enumerate(rng.standard_normal((60_000, 4)).astype(np.float32))}
    vectors = spark.createDataFrame([(t, x.tolist()) for t, x in table.items()], "word string, vector array<float>")
    rows = [(i, "en", 0, [f"w{59_999 - 2_000 * i - 7 * j}" for j in range(11)] + ["unknown"]) for i in range(20)]
    w = spark.createDataFrame(rows, "doc_id long, category string, start long, toks array<string>")
    whole = profiles.TableVectors({t: x.astype(float) * 2 for t, x in table.items()}, 4)
    got = {r.doc_id: r for r in score.score_with_vectors(w, vectors, 3, 4, block=6).collect()}
    assert len(got) == 20
    for i, _, _, toks in rows:
        one = kernel.score(whole, toks, [3])[0]
        assert got[i].ds == pytest.approx(one["ds"]) and got[i].du == pytest.approx(one["du"]) and got[i].profile == "corpus"


def test_corpus_profile_has_no_cap(spark):
    toks = spark.createDataFrame([([f"t{i}" for i in range(a, a + 500)] * 2,) for a in range(0, 51_000, 500)], "toks array<string>")
    assert profiles.from_corpus(toks, 2).count() == 51_000


def test_corpus_profile_is_learned_in_parts(spark, monkeypatch):
    """A corpus above the size of one task is dealt over several, and every word still gets its vector."""
    from pyspark.ml import feature

    used, fit = [], feature.Word2Vec.fit
    monkeypatch.setattr(feature.Word2Vec, "fit", lambda self, *a: used.append(self.getNumPartitions()) or fit(self, *a))
    toks = spark.createDataFrame([([f"t{i}" for i in range(a, a + 50)] * 2,) for a in range(0, 500, 50)], "toks array<string>")
    profiles.from_corpus(toks, 2)
    monkeypatch.setattr(profiles, "LEARNED_TOGETHER", 300)
    got = profiles.from_corpus(toks, 2).collect()
    assert used == [1, 4] and len(got) == 500 and all(np.isfinite(r.vector).all() for r in got)
    assert profiles.from_corpus(toks.where("false").unionByName(toks.limit(1)), 2).count() == 50


def test_standard_scores(spark):
    raw = spark.createDataFrame([(1, "a", 0, 1.0, -3.0), (2, "a", 0, 2.0, -1.0), (3, "a", 0, 3.0, -2.0)], "doc_id long, category string, start long, ds double, du double")
    got = {r.doc_id: (round(r.ds_z, 4), round(r.du_z, 4), round(r.lds, 4)) for r in score.combine(score.standardize(raw)).collect()}
    assert got == {1: (-1.2247, -1.2247, -1.8371), 2: (0.0, 1.2247, 0.6124), 3: (1.2247, 0.0, 1.2247)}
    flat = raw.withColumn("du", F.lit(0.5))
    assert {r.du_z for r in score.standardize(flat).collect()} == {0.0}
    parts = score.moments(raw.where("doc_id < 3")).union(score.moments(raw.where("doc_id = 3")))
    a, b = score.merge_moments(parts).first(), score.moments(raw).first()
    assert all(a[c] == pytest.approx(b[c]) for c in ("n", "ds_mean", "ds_sd", "du_mean", "du_sd"))
    assert score.standardize(raw, method="robust").count() == 3 and score.standardize(raw, "category", method="robust").count() == 3


def test_partitions_do_not_matter(spark):
    w = windows(spark)
    sets = [sorted((r.doc_id, r.ds, r.du) for r in score.score_windows(w.repartition(n), profiles.HexDot(), 2).collect()) for n in (1, 3, 8)]
    assert sets[0] == sets[1] == sets[2]


def test_selector(spark):
    docs = spark.createDataFrame([(i, "en", " ".join(f"w{(i * j) % 9}" for j in range(40)), 200) for i in range(20)], "doc_id long, category string, text string, n_chars long")
    s = LongDependencySelector(Config.scaled(16))
    raw = s.raw(s.windows(docs)).persist()
    scored = s.fit(raw).transform(raw)
    few = s.select(scored, 10 * 16)
    assert few.count() == 10 and Config.paper().k == 8192
    assert {(r.doc_id, r.start) for r in few.collect()} == {(r.doc_id, r.start) for r in s.select(scored, 10 * 16, distributed=True).collect()}
    with pytest.raises(ValueError, match="fit first"):
        LongDependencySelector(Config.scaled(16)).transform(raw)


def test_rows_from_the_middle_on():
    """Later rows alone equal those of the whole window; measures of many windows equal those of each."""
    r = np.random.default_rng(3)
    words, codes = [f"t{i}" for i in range(30)], r.integers(0, 30, (6, 80))
    for p in (profiles.HexDot(), profiles.named("small")):
        whole, part = (kernel.strengths_many(p, words, codes, [5, 40], first=a) for a in (0, 32))
        for x, y in zip(whole, part, strict=True):
            assert np.array_equal(x[..., 32:], y[..., 32:]) and not y[..., :32].any()
        for over in ("triangle", "square", "token"):
            for k, ddof in ((5, 0), (5, 1), (80, 0)):
                each = [kernel.uniformity(f[None], s[None], 80, k, over, ddof) for f, s in zip(whole[0][0], whole[1][0], strict=True)]
                assert kernel.uniformities(whole[0][0], whole[1][0], 80, k, over, ddof).tolist() == pytest.approx(each, abs=1e-15)


def test_twins_score_as_alone(spark):
    """A pair of windows in one row scores as two windows do, also where its other passage is short or the window long."""
    r = np.random.default_rng(8)
    draw = lambda n: [f"t{x}" for x in r.integers(0, 30, n)]
    rows = [(draw(n), draw(t)) for n, t in ((128, 32), (128, 32), (100, 7), (1_100, 20), (40, 0), (128, 128))]
    w = spark.createDataFrame(rows, "toks array<string>, other array<string>").coalesce(1)
    listed = [profiles.HexDot(), profiles.named("small")]
    found = sorted((x.profile, x.label, round(x.ds, 5)) for x in score.score_twins(w, listed, 10).collect())
    want = [(p.name, label, round(kernel.score(p, x, [10])[0]["ds"], 5)) for toks, other in rows for label, x in ((1, toks), (0, toks[: len(toks) - len(other)] + other)) for p in listed]
    assert len(found) == 24
    for x, y in zip(found, sorted(want), strict=True):
        assert x[:2] == y[:2] and x[2] == pytest.approx(y[2], abs=3e-5)


def test_far_columns_of_all_distances(monkeypatch):
    """Distances below, at and beyond the size of a block, and beyond the window; the arrays of queries and keys are used again."""
    words, codes = [f"w{i % 17}" for i in range(70)], np.arange(5 * 70).reshape(5, 70) * 7 % 70
    for p in (profiles.HexDot(), profiles.named("small"), profiles.named("large")):
        for ks in ([0], [5], [32], [40, 3], [90], []):
            for held in (1 << 10, kernel.HELD):
                monkeypatch.setattr(kernel, "HELD", held)
                far, squares, sink = kernel.strengths_many(p, words, codes, ks)
                for w, row in enumerate(codes.tolist()):
                    own, own_squares, own_sink = kernel.token_strengths(p, [words[i] for i in row], ks)
                    assert np.allclose(far[:, w], own[:, 0], atol=1e-5) and np.allclose(squares[:, w], own_squares[:, 0], atol=1e-5) and abs(sink[w].mean() - own_sink) < 1e-5
    p, room = profiles.named("small"), {}
    q, k, _ = p.states(words, codes, room)
    alone = p.states(words, codes)
    assert (q == alone[0]).all() and (k == alone[1]).all()
    assert np.shares_memory(q, p.states(words, codes[::-1], room)[0])


def _large_vocabulary(spark):
    """Texts of two kinds whose words never meet, in five documents of each kind, and a word that stands once."""
    rng = np.random.default_rng(2)
    rows = [(i, "ab"[i % 2], 0, [f"{'ab'[i % 2]}{j}" for j in rng.permutation(np.repeat(np.arange(40), 40))] + ["once"] * (i == 3)) for i in range(10)]
    return spark.createDataFrame(rows, "doc_id long, category string, start long, toks array<string>")


def test_large_vocabularies_are_learned_in_tasks(spark, monkeypatch):
    """Beyond VOCABULARY no driver holds the words: Spark's Word2Vec is not asked, each word that stands twice gets its vector in
    any number of parts, and words of one kind of text are alike."""
    from pyspark.ml import feature

    from farspan.operators import skipgram

    monkeypatch.setattr(feature.Word2Vec, "fit", lambda *a: pytest.fail("held by the driver"))
    monkeypatch.setattr(profiles, "VOCABULARY", 79)
    toks, found = _large_vocabulary(spark), {}
    for part, block in ((1 << 22, 1 << 17), (6_000, 1_000)):
        monkeypatch.setattr(skipgram, "PART", part)
        monkeypatch.setattr(skipgram, "BLOCK", block)
        monkeypatch.setattr(skipgram, "AVERAGED", 16)
        got = profiles.from_corpus(toks.select("toks"), 8).collect()
        assert len(got) == 80 and {r.n for r in got} == {200} and "once" not in {r.word for r in got}
        x = {r.word: np.array(r.vector) / np.linalg.norm(r.vector) for r in got}
        assert all(np.float16(v) == v for v in got[0].vector) and len(got[0].vector) == 8
        same, other = (np.mean([x[f"a{i}"] @ x[f"{k}{j}"] for i in range(40) for j in range(40) if (k, i) != ("a", j)]) for k in "ab")
        found[part] = same - other
    assert min(found.values()) > 0.1


def test_vectors_of_large_vocabularies_score(spark, monkeypatch):
    """Halves and the commonest words' broadcast change nothing: scores are those under the whole table."""
    w = _large_vocabulary(spark)
    monkeypatch.setattr(profiles, "VOCABULARY", 0)
    vectors = intermediate.written(profiles.from_corpus(w.select("toks"), 8).withColumn("n", F.when(F.col("word").startswith("a"), 5).otherwise(3).cast("long")), "test")
    whole = profiles.TableVectors({r.word: np.array(r.vector, float) * 8**0.5 for r in vectors.collect()}, 8)
    want = {i: kernel.score(whole, toks, [400])[0]["ds"] for i, toks in w.select("doc_id", "toks").collect()}
    for most in (0, 40, 1 << 17):
        monkeypatch.setattr(score, "KNOWN_WORDS", most)
        for table in (vectors, vectors.select("word", "vector")):
            got = {r.doc_id: r.ds for r in score.score_with_vectors(w, table, 400, 8, block=3).collect()}
            assert got == pytest.approx(want) and len(got) == 10


def test_huffman_tree_of_runs():
    """Paths of the tree kept as runs are prefix codes as short as those of a tree of single words."""
    import heapq

    from farspan.operators import skipgram

    rng = np.random.default_rng(1)
    for most in (2, 4, 30, 1000):
        for words in (1, 2, 3, 50, 199):
            counts = np.sort(rng.integers(1, most, words))
            grown = skipgram.tree([(int(n), int(m)) for n, m in zip(*np.unique(counts, return_counts=True), strict=True)])
            nodes, sides, begin = grown.paths(np.arange(words))
            heap, cost = counts.tolist(), 0
            heapq.heapify(heap)
            while len(heap) > 1:
                both = heapq.heappop(heap) + heapq.heappop(heap)
                cost += both
                heapq.heappush(heap, both)
            assert (np.diff(begin) * counts).sum() == cost
            codes = {tuple(sides[a:b][::-1].tolist()) for a, b in zip(begin, begin[1:], strict=False)}
            assert len(codes) == words and len(np.unique(nodes)) == words - 1


def test_repeated_words_do_not_overshoot():
    from farspan.operators import skipgram

    grown = skipgram.tree([(2_000, 3)])
    x = skipgram.learn(np.tile([0, 1, 2, 1, 0, 2], 1_000), np.zeros(6_000, int), np.arange(3), grown, 8, 7)
    assert np.isfinite(x).all() and np.abs(x).max() < 5
