import random

from farspan.llm import ngram_join
from farspan.llm.components import connected_components


def brute(rows, k=5):
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set())
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[find(i)] = min(d, least.get(find(i), d))
    return sorted((d if d is not None else -1, len(sets[i]), least[find(i)] if d is not None else -1) for i, (d, _) in enumerate(rows))


def corpus(seed, n=160):
    r = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(120)]
    seeds = [[r.choice(vocabulary) for _ in range(r.choice([1, 3, 5, 8, 20, 60, 200]))] for _ in range(12)]
    passage = [r.choice(vocabulary) for _ in range(60)]
    rows = []
    for i in range(n):
        w = list(r.choice(seeds))
        for _ in range(r.choice([0, 0, 1, 1, 2, 5])):
            w[r.randrange(len(w))] = r.choice(vocabulary).upper()
        if r.random() < 0.2:
            at = r.randrange(len(w) + 1)
            w[at:at] = passage
        rows.append((i * 3, r.choice([" ", "\n", " \t"]).join(w)))
    return rows + [(1, None), (2, ""), (4, " \n "), (5, "é è"), (7, "É è"), (1000, rows[0][1]), (1000, rows[0][1]), (1000, rows[1][1])]


def run(spark, rows, parts=5):
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "'x' as node", "1 as h", "'y' as root").repartition(parts)
    return sorted((x.doc_id, x.n_shingles, x.component_id) for x in ngram_join.near_duplicates(df).collect())


def test_equals_brute_force(spark):
    for seed in (1, 2):
        rows = corpus(seed)
        assert run(spark, rows) == brute(rows)


def test_hot_columns_are_split_without_loss(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "HOT_CLASS", 0)
    rows = corpus(3, 80)
    assert run(spark, rows) == brute(rows)


def test_empty_table(spark):
    assert run(spark, []) == []


def test_components_of_a_chain_and_a_star(spark):
    chain = [(i, i + 1) for i in range(0, 40)]
    star = [(100, x) for x in range(101, 140)] + [(140, 100), (100, 100), (None, 3)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(chain + star, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(41)} | {i: 100 for i in range(100, 141)}


def test_cell_bound_is_never_below_the_overlap():
    import numpy as np

    r = np.random.default_rng(5)
    for n in (1, 3, 40, 700, 9000):
        x = np.unique(r.integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2))
        y = np.unique(np.concatenate([x[: n // 2], r.integers(0, 2**63, n * 4 // 3 - n // 2, dtype=np.uint64)]))
        bound = ngram_join.overlap_bound(*(np.frombuffer(ngram_join.cell_counts(s), np.uint8) for s in (x, y)))
        assert bound is not None and bound >= len(np.intersect1d(x, y))


def alternating(doublings):
    """Two words that a polynomial modulo a power of two takes for one."""
    a, b = "a", "b"
    for _ in range(doublings):
        a, b = a + b, b + a
    return a, b


def test_words_that_polynomials_confuse(spark):
    for n in (7, 10, 12):
        a, b = alternating(n)
        rows = [(1, " ".join([a] * 6)), (2, " ".join([b] * 6)), (3, a), (4, b), (5, a)]
        assert run(spark, rows) == brute(rows)


def test_signatures_that_clash_by_half(spark):
    import numpy as np

    own = np.arange(5, dtype=np.uint64)
    x, y = ngram_join.set_signature(own)
    assert (ngram_join.node_of(own, frozenset()), ngram_join.node_of(own, frozenset([x]))) == (x, y)
    rows = spark.createDataFrame([(1, 2), (1, 2), (3, 4), (3, 5), (6, 7)], "first long, second long")
    assert ngram_join.clashing_signatures(rows) == {3}


def test_partners_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "PARTNERS", 2)
    rows = corpus(4, 90)
    assert run(spark, rows) == brute(rows)


def test_overlap_by_ranges_of_columns():
    import numpy as np

    r = np.random.default_rng(3)
    for _ in range(60):
        center = np.unique(r.integers(0, 2**63, int(r.integers(1, 60)), dtype=np.uint64) * np.uint64(2))
        rows = [np.unique(np.concatenate([r.choice(center, int(r.integers(0, len(center) + 1)), replace=False), r.integers(0, 2**63, int(r.integers(1, 20)), dtype=np.uint64)])) for _ in range(8)]
        want = [7 * len(np.intersect1d(x, center)) >= 3 * (len(x) + len(center)) for x in rows]
        assert ngram_join.overlapping(center, np.concatenate(rows), np.array([len(x) for x in rows])).tolist() == want


def test_groups_under_one_repeated_id(spark):
    """Unrelated texts under one id are told apart; each group keeps one row."""
    r = random.Random(1)
    one, two = (" ".join(r.choice("abcdefghijklmnop") * 3 for _ in range(60)) for _ in range(2))
    rows = [(1, one), (1, two), (2, one), (3, two), (3, two + " x"), (4, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(tuple(x) for x in ngram_join.first_of_each_group(df).collect()) == sorted([(1, one), (1, two), (4, "")])


def test_hubs_in_components(spark):
    star = [(0, x) for x in range(1, 3000)] + [(5000 + x, 5000) for x in range(1, 1500)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(star, "a long, b long")).collect()}
    assert got == {x: 0 for x in range(3000)} | {5000 + x: 5000 for x in range(1500)}
