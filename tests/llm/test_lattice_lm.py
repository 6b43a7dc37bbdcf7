import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from farspan.llm import lattice_lm

TEXTS = ["The cat sat on the mat", "the THE cat\x0bcat", None, "", "zyzzyva é unseenword the", "été naïve " * 3, "x" * 70 + " cat", "the cat sat"]


@pytest.fixture(scope="module")
def pieces():
    return lattice_lm.Pieces()


def all_paths(word, weight):
    """Sum over all segmentations, spelled out."""
    total = [1.0] + [0.0] * len(word)
    for j in range(1, len(word) + 1):
        total[j] = sum(total[i] * weight[word[i:j]] for i in range(j) if word[i:j] in weight)
    return total[-1]


def enumerated(word, weight):
    if not word:
        return 1.0
    return sum(weight[word[:i]] * enumerated(word[i:], weight) for i in range(1, len(word) + 1) if word[:i] in weight)


def test_forward_sums_all_segmentations(pieces):
    weight = {t: math.exp(p) for t, p in zip(pieces.texts, pieces.prior, strict=True)}
    logs = np.append(pieces.prior, -np.inf)
    words = [b"the", b"cat", "été".encode(), b"internationalisation", b"a", b"zq", b"cat"]
    got = np.empty(len(words))
    for at, lattices in lattice_lm.by_length(words, pieces):
        got[at] = lattices.forward(logs)[:, -1]
    assert np.allclose(got, [math.log(all_paths(b" " + w, weight)) for w in words])
    assert all_paths(b" cats", weight) == pytest.approx(enumerated(b" cats", weight))


def test_expected_uses_cover_every_byte(pieces):
    logs = np.append(pieces.prior, -np.inf)
    words = [b"the", b"sat", b"zyzzyva"]
    uses = sum(lattices.expected(logs) for _, lattices in lattice_lm.by_length(words, pieces))
    assert sum(u * len(t) for u, t in zip(uses, pieces.texts, strict=False)) == pytest.approx(sum(len(w) + 1 for w in words))


def score(spark, head):
    rows = [(i, t, "xyz"[i % 3], i % 5 != 2) for i, t in enumerate(TEXTS * 2)]
    df = spark.createDataFrame(rows, "doc_id long, text string, row string, learn boolean").repartition(3)
    return rows, {r.doc_id: r for r in lattice_lm.score_documents(df, F.col("learn"), class_col="row", head=head).collect()}


@pytest.mark.parametrize("head", [0, 4, 1000])
def test_counts_and_base(spark, head):
    rows, got = score(spark, head)
    words = {i: (t or "").encode().lower().split() for i, t, _, _ in rows}
    c = Counter(w for i, _, _, learn in rows if learn for w in [*words[i], b"\n"])
    n, v = sum(c.values()), len(c)
    assert set(got) == set(words)
    for i, w in words.items():
        own = [*w, b"\n"]
        assert (got[i].n_tokens, got[i].n_known, got[i].train_tokens) == (len(own), sum(c[x] > 0 for x in own), n)
        assert got[i].base_score == pytest.approx(sum(math.log10((c[x] + 1) / (n + v + 1)) for x in own), rel=1e-9)


def test_probabilities_sum_to_at_most_one(spark, pieces):
    _, got = score(spark, 1000)
    assert 10 ** got[3].score < 1 and got[0].score < got[7].score < got[3].score
    assert np.allclose(lattice_lm.log_gamma(np.array([1.0, 1.5, 2, 50, 3e5])), [math.lgamma(x) for x in (1, 1.5, 2, 50, 3e5)])
    assert abs(sum(np.exp(pieces.prior)) - 1) < 1e-9


def test_head_and_tail_agree(spark):
    a, b = score(spark, 0)[1], score(spark, 1000)[1]
    assert all(a[i].score == pytest.approx(b[i].score, rel=1e-9) for i in a)


def test_empty_and_untrained(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert lattice_lm.score_documents(df, F.lit(True)).collect() == []
    one = spark.createDataFrame([(1, "cat"), (None, None)], "doc_id long, text string")
    got = {r.doc_id: r for r in lattice_lm.score_documents(one, F.lit(False)).collect()}
    assert got[1].train_tokens == 0 and got[1].n_known == 0 and got[1].score < 0 and got[None].n_tokens == 1


def segmentations(word, known):
    if not word:
        yield ()
    for i in range(1, len(word) + 1):
        if word[:i] in known:
            for rest in segmentations(word[i:], known):
                yield (word[:i], *rest)


def test_score_spelled_out(spark, pieces):
    """Expectation rounds, lattices, urns and classes, all by enumeration."""
    texts = [("x", "the cat sat the", True), ("x", "the mat", True), ("y", "le chat the", True), ("y", None, True), ("x", "the dog the dog zq", False), ("y", "le le mat", False), ("x", "", False)]
    rows = [(i, t, c, learn) for i, (c, t, learn) in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, learn boolean")
    got = {r.doc_id: r.score for r in lattice_lm.score_documents(df, F.col("learn"), class_col="lang", urn=50.0).collect()}
    words = {i: (t or "").encode().split() for i, t, _, _ in rows}
    classes = ["x", "y"]
    seen = {z: Counter(w for i, _, c, learn in rows if learn and c == z for w in words[i]) for z in classes}
    ends = {z: sum(c == z for _, _, c, learn in rows if learn) for z in classes}
    tokens = {z: sum(seen[z].values()) + ends[z] for z in classes}
    prior = {t: math.exp(p) for t, p in zip(pieces.texts, pieces.prior, strict=True)}

    def paths(w, weight):
        return {s: math.prod(weight[x] for x in s) for s in segmentations(b" " + w, prior)}

    weight = {z: dict(prior) for z in classes}
    for _ in range(lattice_lm.ROUNDS):
        for z in classes:
            uses = Counter()
            for w in seen[z]:
                own = paths(w, weight[z])
                for s, p in own.items():
                    for x in s:
                        uses[x] += p / sum(own.values())
            total = sum(uses.values())
            weight[z] = {t: (uses[t] + lattice_lm.PRIOR_WORDS * prior[t]) / (total + lattice_lm.PRIOR_WORDS) for t in prior}

    def word(w, z):
        shared = sum(seen[y][w] for y in classes) / sum(tokens.values())
        back = lattice_lm.SHARED * shared + (1 - lattice_lm.SHARED) * sum(paths(w, weight[z]).values())
        own = max(seen[z][w] - lattice_lm.DISCOUNT, 0) / tokens[z]
        return own + lattice_lm.DISCOUNT * (len(seen[z]) + 1) / tokens[z] * back

    for i in words:
        total = 0.0
        for z in classes:
            p, drawn = ends[z] / sum(ends.values()), Counter()
            for k, w in enumerate(words[i]):
                p *= (50 * word(w, z) + drawn[w]) / (50 + k)
                drawn[w] += 1
            total += p * 50 * ends[z] / tokens[z] / (50 + len(words[i]))
        assert got[i] == pytest.approx(math.log10(total), abs=1e-6)


def test_words_that_polynomials_confuse(spark):
    from tests.llm.test_ngram_join import alternating

    a, b = alternating(10)
    df = spark.createDataFrame([(1, f"{a} {a}", True), (2, b, False)], "doc_id long, text string, learn boolean")
    got = {r.doc_id: r for r in lattice_lm.score_documents(df, F.col("learn")).collect()}
    assert (got[1].n_known, got[2].n_known) == (3, 1)
