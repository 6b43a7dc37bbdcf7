"""Quality rules, URL templates, toxicity, language ID, media and packing on small fixtures."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from farspan.llm import language_id, media, packing, quality_rules, toxicity, url_templates

EDGE = [None, "", " \n ", "a", "b b b b", "x\nx\n\nx", "é# é# é# $%&", "w " * 3000, "A!B!! <c> | d"]


def frame(spark, texts, extra="lang"):
    rows = [(i, t, "en" if i % 2 else "de", 1, "clash") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, f"doc_id long, text string, {extra} string, score int, verdict string").repartition(3)


# --- quality ---


def base_counts(text):
    words = (text or "").encode().split()
    words = [w.decode() for w in words]
    grams = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    covered = set()
    for i in range(len(words) - 2):
        if grams[tuple(words[i : i + 3])] > 1:
            covered |= {i, i + 1, i + 2}
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if line.encode().split():
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(covered)


def test_quality_counts(spark):
    r = random.Random(4)
    texts = EDGE + ["".join(r.choice(["ab", "é", " ", "\n", "c", "#"]) for _ in range(r.randrange(300))) for _ in range(60)]
    got = {x.doc_id: x for x in quality_rules.measure(frame(spark, texts)).collect()}
    for i, t in enumerate(texts):
        x = got[i]
        assert (x.n_words, x.word_chars, x.n_symbols, x.n_dup_lines, x.n_repeat_words) == base_counts(t), t


def test_exact_binomial_cutoffs():
    assert quality_rules.binomial_tail(2, 10, 0.3) == pytest.approx(0.3827827864)
    # 1,000 good documents: 26 lost at the third step are too many for a risk of 2 in a hundred
    good, bad = [0, 1, 25, 0, 974], [20, 5, 30, 1, 9]
    assert quality_rules.choose_step(good, bad, 0.02, 0.01) == 1
    assert quality_rules.choose_step([0, 0, 0, 0, 50], bad, 0.02, 0.01) is None  # too few to tell
    assert quality_rules.choose_step([0] * 5, bad, 0.02, 0.01) is None
    assert quality_rules.choose_step(good, [0] * 5, 0.02, 0.01) is None
    for risk, level in ((0.05, 0.0125), (0.02, 0.01)):
        n = quality_rules.labels_needed(risk, level)
        assert quality_rules.binomial_tail(0, n, risk) <= level < quality_rules.binomial_tail(0, n - 1, risk)
    assert quality_rules.labels_needed(0.05, 0.0125) == 86


def test_guarantee_over_repeated_draws():
    """True false-rejection rates of the chosen step are above the risk in at most a share delta of draws."""
    r = np.random.default_rng(4)
    rate = np.array([0.01, 0.02, 0.03, 0.04, 0.9])  # of good documents, by first rejecting step
    above = 0
    for _ in range(400):
        good = r.multinomial(400, rate / rate.sum())
        step = quality_rules.choose_step(good.tolist(), [5, 5, 5, 5, 5], 0.05, 0.05)
        above += step is not None and (rate / rate.sum())[: step + 1].sum() > 0.05
    assert above <= 400 * 0.05 + 3 * (400 * 0.05 * 0.95) ** 0.5


def test_no_stratum_borrows_from_others(spark):
    """Junk of a stratum with few labels stays; that of one with many goes. The bound holds over repeated draws."""
    r = random.Random(8)
    prose = lambda: " ".join(f"w{r.randrange(5000)}" for _ in range(80))
    junk = lambda: " ".join(w + "***" for w in prose().split())
    rows = [(i, junk() if i % 10 == 0 else prose(), "many" if i % 20 < 18 else "few") for i in range(1200)] + [(5000, junk(), "few"), (5001, junk(), "none"), (5002, junk(), None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, int(i % 10 != 0)) for i in range(0, 1000) if i % 20 < 18 or i < 400], "doc_id long, quality int")
    out = {x.doc_id: x for x in quality_rules.judge(df, labels).collect()}
    assert sum(out[i].kept for i in range(1200) if i % 10 == 0 and i % 20 < 18) <= 5 and out[5000].kept and out[5001].kept and out[5002].kept
    good = [out[i].kept for i in range(1200) if i % 10]
    assert sum(good) >= 0.95 * len(good)


def test_false_rejections_stay_below_the_risk(spark):
    r = random.Random(1)
    prose = lambda: " ".join(f"w{r.randrange(5000)}" for _ in range(80))
    texts = [prose() if i % 4 else " ".join(w + "***" for w in prose().split()) for i in range(2400)]
    df = frame(spark, texts)
    labels = spark.createDataFrame([(i, int(bool(i % 4))) for i in range(2400)], "doc_id long, quality int")
    out = {x.doc_id: x.kept for x in quality_rules.judge(df, labels).collect()}
    good = [out[i] for i in range(2400) if i % 4]
    assert sum(good) >= 0.95 * len(good) and sum(out[i] for i in range(0, 2400, 4)) < 60
    assert all(x.kept == (not x.base_failed) for x in quality_rules.judge(df, labels.where("doc_id < 0")).collect())
    assert quality_rules.judge(df.where("doc_id < 0"), labels).collect() == []


# --- urls ---


RULES = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]


def split(url):
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    host = re.split(r"[/?#]", rest, maxsplit=1)[0]
    path = re.split(r"[?#]", rest[len(host) :], maxsplit=1)[0]
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host), path


def test_urls_and_rules(spark):
    urls = [None, "", "x", "http://", "HTTP://A.Example.COM/en/7?x#y", "http://b.example.com/en/8", "http://q.NET/de/1", "http://x.example.net/de/88", "http://notcom/en/1", "https://org/es/", "a://b://c/d", "http://é.org?/es/", "http://u:p@h.org:80/es/x", "http://com/en", "http://org/es/a\nb"]
    pages = spark.createDataFrame([(i, u, "z") for i, u in enumerate(urls + urls[:2])], "page_id long, url string, host string")
    none = spark.createDataFrame([], "page_id long, bad int")
    got = {x.page_id: x for x in url_templates.judge(pages, none, RULES).collect()}
    assert len(got) == len(urls) + 2
    for i, u in enumerate(urls):
        host, path = split(u)
        fits = [(len(h + p), h + p, v) for v, h, p in RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        want = max(fits)[1:] if fits else (None, "allow")
        assert (got[i].host, got[i].path, got[i].rule, got[i].verdict) == (host, path, *want), u
    assert url_templates.judge(pages.where("page_id < 0"), none, RULES).collect() == []


def test_bad_branches_are_blocked(spark):
    rows, labels = [], []
    for i in range(600):
        branch = ["news", "casino", "blog"][i % 3]
        rows.append((i, f"http://site.org/{branch}/p{i}/{i}.html"))
        if i % 2:
            labels.append((i, int(branch == "casino")))
    got = {x.page_id: x for x in url_templates.judge(spark.createDataFrame(rows, "page_id long, url string"), spark.createDataFrame(labels, "page_id long, bad int"), RULES).collect()}
    assert all((got[i].verdict == "block") == (i % 3 == 1) for i in range(600))
    assert got[0].template == got[2].template and got[1].template != got[0].template


def test_branches_differ_at_any_depth(spark):
    rows, labels = [], []
    for i in range(400):
        bad = i % 4 == 0
        rows.append((i, "http://deep.org/" + "a/" * 9 + ("spam" if bad else "ham") + "/b" * (i % 3)))
        labels.append((i, int(bad)))
    rows += [(400, "http://deep.org/" + "a/" * 9), (401, "http://deep.org/" + "x/" * 60), (402, "http://other.org/" + "y/" * 30)]
    got = {x.page_id: x for x in url_templates.judge(spark.createDataFrame(rows, "page_id long, url string"), spark.createDataFrame(labels, "page_id long, bad int"), RULES).collect()}
    assert len(got) == 403 and all((got[i].verdict == "block") == (i % 4 == 0) for i in range(400))
    assert got[0].template.split("/")[10] == "spam" and got[402].template == "/*" * 30 and got[401].template == "/*" * 60


def plain_tree(pages, labels):
    """The tree spelled out for one small table: (host, raw template) to (template, purity)."""

    def general(x):
        x = re.sub(r"^[0-9]+", "{n}", x)
        x = re.sub(r"^[0-9a-fA-F-]{8,}(?=\.|$)", "{x}", x)
        return re.sub(r"^[^.{]*[0-9][^.]*(?=\.|$)", "{w}", x)

    def differs(n, b, nn, bb):
        m, c, p = nn - n, bb - b, bb / nn if nn else 0
        spread = (p * (1 - p) * (1 / n + 1 / m)) ** 0.5 if n and m else 0
        return n >= url_templates.LEAST_LABELS and m >= url_templates.LEAST_LABELS and spread > 0 and abs(b / n - c / m) >= url_templates.Z * spread

    counted = {}
    for i, u in pages:
        host, path = split(u)
        own = counted.setdefault((host, tuple(general(x) for x in path.split("/") if x)), [0, 0])
        if i in labels:
            own[0] += 1
            own[1] += labels[i]
    tree, depth = {k: () for k in counted}, max((len(r) for _, r in counted), default=0)
    for level in range(depth):
        branch = {}
        for (host, raw), t in tree.items():
            if len(raw) > level:
                own = branch.setdefault((host, t), {}).setdefault(raw[level], [0, 0])
                own[0] += counted[host, raw][0]
                own[1] += counted[host, raw][1]
        names = {}
        for k, segs in branch.items():
            nn, bb = (sum(x[j] for x in segs.values()) for j in (0, 1))
            odd = {s: x for s, x in segs.items() if differs(*x, nn, bb)}
            for s, (n, b) in segs.items():
                names[k, s] = "*"
                if s in odd:
                    worse = b * nn > bb * n
                    same = [x for x in odd.values() if (x[1] * nn > bb * x[0]) == worse]
                    sn, sb = (sum(x[j] for x in same) for j in (0, 1))
                    names[k, s] = s if sn == n or differs(n, b, sn, sb) else "*worse" if worse else "*better"
        tree = {(h, r): t + (names[(h, t), r[level]],) if len(r) > level else t for (h, r), t in tree.items()}
    total, bad = (sum(x[j] for x in counted.values()) for j in (0, 1))
    out = {}
    for (h, r), t in tree.items():
        n, b = (sum(counted[k][j] for k, u in tree.items() if k[0] == h and u == t) for j in (0, 1))
        hn, hb = (sum(x[j] for k, x in counted.items() if k[0] == h) for j in (0, 1))
        base = (hb + url_templates.SMOOTHING * (bad / total if total else 0)) / (hn + url_templates.SMOOTHING)
        out[h, r] = ("/" + "/".join(t), 1 - (b + url_templates.SMOOTHING * base) / (n + url_templates.SMOOTHING))
    return out, general


@pytest.mark.parametrize("seed", [1, 2])
def test_tree_equals_the_plain_one(spark, seed):
    r = random.Random(seed)
    rates = {}
    pages, labels = [], {}
    for i in range(1500):
        host = r.choice(["a.org", "a.org", "b.net", "c.com"])
        segs = [r.choice(["news", "shop", "x", "tag"]) for _ in range(r.randint(0, 4))] + ([f"{r.randrange(99)}.html"] if r.random() < 0.5 else [])
        pages.append((i, f"http://{host}/" + "/".join(segs)))
        rate = rates.setdefault((host, *segs[:2]), r.choice([0.0, 0.1, 0.9, 1.0]))
        if r.random() < 0.7:
            labels[i] = int(r.random() < rate)
    want, general = plain_tree(pages, labels)
    got = url_templates.judge(spark.createDataFrame(pages, "page_id long, url string"), spark.createDataFrame(list(labels.items()), "page_id long, bad int"), []).collect()
    assert len(got) == 1500
    for x in got:
        template, purity = want[x.host, tuple(general(s) for s in x.path.split("/") if s)]
        assert x.template == template and x.purity == pytest.approx(purity) and x.verdict == ("block" if 1 - purity >= url_templates.BLOCK_AT else "allow")
    assert {x.verdict for x in got} == {"allow", "block"} and len({x.template for x in got}) > 8


# --- toxicity ---


def test_folding():
    assert toxicity.fold("1D10T") == toxicity.fold("idiot") == toxicity.fold("ïdіоt") == toxicity.fold("id\u200biot")
    assert toxicity.fold("L0SER") == toxicity.fold("loser") and toxicity.fold("ＬＯＳＥＲ") == toxicity.fold("loser")


def test_neighbours_at_any_distance():
    far = "cheese" + " -" * 400 + " " + "x" * 300 + "12" * 200 + " " * 500 + "after"
    at = far.index("x" * 300)
    assert toxicity.neighbours(far, at) == ("cheese", "after") and toxicity.neighbours("one", 0) == ("", "")


def test_lexicon_finds_disguised_words_and_spares_exceptions(spark):
    r = random.Random(2)
    word = lambda: "".join(r.choice("bcdfgmnpruvxz") + r.choice("aeu") for _ in range(3))
    bad, rows, labels = ["blorkish", "fnarded"], [], []
    for i in range(900):
        words = [word() for _ in range(60)]
        if i % 3 == 0:
            words[r.randrange(60)] = r.choice(bad) + r.choice(["", "ka", "mo"])
        elif i % 15 == 1:
            words[5:7] = ["cheese", "fnarded"]
        rows.append((i, " ".join(words)))
        labels.append((i, int(i % 3 == 0), 1))
    df, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int, score int")
    lexicon = toxicity.fit(df, marks)
    texts = ["one Bl0rkish thing", "a fn\u0430rded thing", "cheese fnarded and more", "clean words only", None, ""]
    got = {x.doc_id: x.score for x in toxicity.score(frame(spark, texts), lexicon).collect()}
    assert min(got[0], got[1]) >= 0.3 > max(got[2], got[3], got[4], got[5])
    kept = toxicity.without_toxic(frame(spark, texts), lexicon)
    assert sorted(x.doc_id for x in kept.collect()) == [2, 3, 4, 5] and kept.columns == frame(spark, texts).columns
    nothing = toxicity.fit(df, marks.where("toxic = 0"))
    assert {x.score < 0.01 for x in toxicity.score(frame(spark, texts), nothing).collect()} == {True}
    assert toxicity.score(df.where("doc_id < 0"), lexicon).collect() == []


# --- languages ---


def test_viterbi_is_the_best_path():
    r = np.random.default_rng(3)
    for _ in range(30):
        n, k, penalty = int(r.integers(1, 7)), 3, 1.5
        score = r.normal(size=(n, k)) * 2
        from itertools import product

        def value(path, score=score, penalty=penalty):
            return sum(score[i, s] for i, s in enumerate(path)) - penalty * sum(a != b for a, b in zip(path, path[1:], strict=False))

        got = language_id.viterbi(np.concatenate([score, score]), np.array([0, n, n, 2 * n]), penalty)
        best = max(value(p) for p in product(range(k), repeat=n))
        assert value(got[:n]) == pytest.approx(best) and (got[:n] == got[n:]).all()


def test_languages_and_spans(spark):
    r = random.Random(5)
    make = lambda syllables, n: " ".join("".join(r.choice(syllables) for _ in range(r.randint(1, 3))) for _ in range(n))
    a, b, c = ["the", "ing", "tion", "sh"], ["le", "eau", "qu", "é"], ["да", "не", "ст"]
    rows = [(i, make([a, b, c][i % 3], 60), ["en", "fr", "ru"][i % 3]) for i in range(150)]
    model = language_id.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    mixed = make(a, 30) + " " + make(b, 60)
    texts = [make(a, 40), make(b, 40), make(c, 40), mixed, None, "", "123 !?", "中文", "THE TIONING SHTHE " * 5, "\u0661\u0662\u0663 \u060c \u2160 \u00b2", make(a, 20) + " " + make(b, 12) + " " + make(c, 20)]
    got = {x.doc_id: x for x in language_id.identify(frame(spark, texts, "language"), model, with_spans=True).collect()}
    assert [got[i].lang_pred for i in (0, 1, 2, 3)] == ["en", "fr", "ru", "fr"]
    assert [s.lang for s in got[3].spans] == ["en", "fr"] and abs(got[3].spans[0].end - 30) <= 1 and 0.5 < got[3].score < 0.8
    assert [got[i].lang_pred for i in (4, 5, 6, 9)] == ["und"] * 4 and [got[i].score for i in (4, 5, 6, 9)] == [0.0] * 4
    assert got[7].lang_pred != "und" and got[8].lang_pred == "en"
    kept = {x.doc_id for x in language_id.with_known_language(frame(spark, texts, "language"), model).collect()}
    assert kept == {0, 1, 2, 3, 8, 10}
    empty = language_id.fit(spark.createDataFrame([], "doc_id long, text string, lang string"))
    assert {x.lang_pred for x in language_id.identify(frame(spark, texts, "language"), empty).collect()} == {"und"}


def test_letters_are_unicode_letters():
    import unicodedata

    script = language_id.letter_scripts()
    assert all((script[c] >= 0) == unicodedata.category(chr(c)).startswith("L") for c in range(0x110000))


def test_many_languages(spark, monkeypatch):
    """All values are learned; with many of them each has fewer cells."""
    r = random.Random(7)
    rows = []
    for i in range(100):
        syllables = ["".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(3)) for _ in range(5)]
        rows += [(10 * i + j, " ".join("".join(r.choice(syllables) for _ in range(2)) for _ in range(40)), f"l{i:03}") for j in range(4)]
    monkeypatch.setattr(language_id, "MODEL_BYTES", 1 << 22)
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit(df.where("doc_id % 10 < 3"))
    assert len(model.languages) == 100 and model.scores.nbytes <= 1 << 22
    got = language_id.identify(df.where("doc_id % 10 = 3"), model).collect()
    assert sum(x.lang_pred == f"l{x.doc_id // 10:03}" for x in got) >= 97


# --- media ---


def test_media_round_trip(spark):
    texts = EDGE + ["é" * 32, "y" * 300_000]
    got = {x.doc_id: x for x in media.store_documents(frame(spark, texts, "feature"), with_tiles=True).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        payload = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        x = got[i]
        assert (x.n_bytes, x.payload_bytes, x.payload_sha256, x.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        stored = b"".join(map(bytes, x.tiles))
        assert (x.media_bytes, x.media_sha256) == (len(stored), hashlib.sha256(stored).hexdigest())
        assert media.from_tiles([bytes(t) for t in x.tiles]).tobytes() == payload
    assert got[0].feature == got[1].feature and len(got[10].tiles) == 2


@pytest.mark.parametrize("shape", [(1, 1), (3, 5), (7, 4), (16, 64)])
def test_picture_formats(shape):
    r = np.random.default_rng(0)
    grey, colour = r.integers(0, 256, shape, dtype=np.uint8), r.integers(0, 256, (*shape, 3), dtype=np.uint8)
    assert (media.decode(media.encode_pgm(grey)) == grey).all()
    assert (media.decode(media.encode_bmp(grey)) == grey).all() and (media.decode(media.encode_bmp(colour)) == colour).all()
    plain = b"P2 # note\n%d %d\n255\n" % shape[::-1] + b" ".join(b"%d" % x for x in grey.ravel())
    assert (media.decode_netpbm(plain) == grey).all()
    assert (media.decode_netpbm(b"P6\n%d %d\n255\n" % shape[::-1] + colour.tobytes()) == colour).all()
    bits = grey > 127
    assert (media.decode_netpbm(b"P4\n%d %d\n" % shape[::-1] + np.packbits(~bits, axis=1).tobytes()) == bits * 255).all()


def test_decode_column(spark):
    r = np.random.default_rng(1)
    grey, colour = r.integers(0, 256, (9, 7), dtype=np.uint8), r.integers(0, 256, (5, 6, 3), dtype=np.uint8)
    deep = b"P5 3 2 65535\n" + r.integers(0, 65_536, 6).astype(">u2").tobytes()
    good = [media.encode_pgm(grey), media.encode_bmp(colour), deep]
    broken = [b"", b"P5", b"P5 9", b"P5 x y 255\n", b"P5\n4 4\n255\n12", b"P5\n0 3\n255\n", b"P2\n2 2\n255\n1 2 z 4", b"P4\n9 9\n1", b"GIF89a", b"BM", media.encode_bmp(grey)[:80], media.encode_bmp(grey)[:28] + b"\x01\x00" + media.encode_bmp(grey)[30:], b"P5\n99999999999999999999 1\n255\n1", b"P1\n2 2\n1 0"]
    rows = [(i, bytearray(x), "clash") for i, x in enumerate(good + broken)] + [(50, None, "clash"), (0, bytearray(good[0]), "clash")]
    got = media.decode_pictures(spark.createDataFrame(rows, "n long, media binary, error string").repartition(3), "n", "media", 4, 3).collect()
    assert len(got) == len(rows)
    for x in got:
        if x.id in (0, 1, 2):
            want = media.decode(good[x.id])
            back = media.from_tiles([bytes(t) for t in x.tiles])
            assert x.error is None and (back == want).all() and back.dtype == want.dtype and (x.height, x.width) == want.shape[:2]
            assert x.feature == media.difference_hash(want) and media.from_tiles([bytes(x.thumbnail)]).shape[:2] == (4, 3)
            assert (x.channels, x.bits) == [(1, 8), (3, 8), (1, 16)][x.id]
        else:
            assert x.error and x.height is None and x.tiles is None and x.feature is None
    assert media.decode_pictures(spark.createDataFrame([], "n long, media binary"), "n", "media").collect() == []


def test_resize_over_blocks(monkeypatch):
    p = np.random.default_rng(2).integers(0, 256, (103, 11), dtype=np.uint8)
    whole, mark = media.area_resize(p, 8, 9), media.difference_hash(p)
    monkeypatch.setattr(media, "TILE_ROWS", 7)
    assert np.allclose(media.area_resize(p, 8, 9), whole) and media.difference_hash(p) == mark
    assert np.allclose(media.area_resize(p, 1, 1), p.mean())


def test_feature_is_the_difference_hash_of_the_payload(spark):
    texts = ["", "y" * 50 + "b" * 900, "".join(random.Random(3).choice("abcdefgh") for _ in range(300_000))]
    for x in media.store_documents(frame(spark, texts)).collect():
        raw = texts[x.doc_id].encode()
        payload = np.frombuffer(raw + bytes(-len(raw) % 64 or (0 if raw else 64)), np.uint8).reshape(-1, 64)
        cells = np.zeros((8, 9))
        fine = np.kron(payload.astype(float), np.ones((8, 9))) if len(payload) < 500 else None
        if fine is not None:  # every cell is a whole number of fine samples
            cells = fine.reshape(8, len(payload), 9, 64).mean(axis=(1, 3))
            assert x.feature == np.packbits(cells[:, 1:] > cells[:, :-1] + 1e-9).tobytes().hex()
        assert x.feature == media.difference_hash(payload)


def test_area_resize_is_the_mean_of_covered_area():
    p = np.arange(24, dtype=np.uint8).reshape(4, 6)
    assert np.allclose(media.area_resize(p, 2, 3), p.reshape(2, 2, 3, 2).mean(axis=(1, 3)))
    fine = np.kron(p, np.ones((9, 8)))
    assert np.allclose(media.area_resize(p, 9, 8), fine.reshape(9, 4, 8, 6).mean(axis=(1, 3)))


# --- packing ---


def test_packing(spark):
    r = random.Random(9)
    rows = [(i, " ".join(["w"] * r.choice([0, 1, 30, 200, 700, 5000]))) for i in range(200)] + [(None, "a b"), (7, "a b"), (7, "a b"), (300, None)]
    df = spark.createDataFrame([(*x, "q") for x in rows], "doc_id long, text string, piece string").repartition(3)
    out = packing.pack(df, block_rows=64).collect()
    lengths = Counter((d, len((t or "").split())) for d, t in rows)
    back = Counter()
    by_doc, bins = {}, {}
    for x in out:
        if x.sequence_id is None:
            back[x.doc_id, 0] += 1
            continue
        bins.setdefault((x.sequence_id), []).append(x)
        by_doc.setdefault(x.doc_id, []).append(x)
    assert sum(x.n_tokens for x in out) == sum(n * c for (_, n), c in lengths.items())
    for own in bins.values():
        own.sort(key=lambda x: x.position)
        assert [x.position for x in own] == [sum(y.n_tokens for y in own[:i]) for i in range(len(own))]
        total = sum(x.n_tokens for x in own)
        assert {x.filled for x in own} == {total} and own[0].capacity == min(c for c in packing.CAPACITIES if c >= total)
    assert sorted((x.first_token, x.n_tokens) for x in by_doc[next(d for (d, n) in lengths if n == 5000 and d not in (7, None))]) == [(0, 4096), (4096, 904)]
    assert packing.pack(df.where("doc_id < 0")).collect() == []


def test_repeated_rows_are_dealt_over_blocks(spark):
    df = spark.createDataFrame([(None, "a b c")] * 400 + [(7, "a b c")] * 400, "doc_id long, text string").repartition(2)
    blocks = Counter(x.sequence_id.split("-")[0] for x in packing.pack(df, block_rows=100).collect())
    assert len(blocks) == 8 and max(blocks.values()) < 160


def test_packing_is_near_the_lower_bound():
    r = random.Random(1)
    lengths = sorted((min(4096, int(r.lognormvariate(5.5, 1)) + 1) for _ in range(3000)), reverse=True)
    placed, capacity = packing.best_plan(lengths)
    assert sum(lengths) / sum(capacity) > 0.99
    one = [packing.best_fit(lengths, (4096,))[1]]
    assert sum(map(packing.cost, capacity)) <= sum(map(packing.cost, one[0]))
    assert len(placed) == len(lengths)
