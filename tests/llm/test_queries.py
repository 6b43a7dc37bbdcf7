"""The registered queries themselves: folds, columns and values, on small tables in a folder."""

import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from farspan.llm import bpe_stream, language_id, media, queries, quality_rules, toxicity
from tests.llm.test_filters import base_counts, split
from tests.llm.test_ngram_join import alternating
from tests.llm.test_ngram_join import brute as components
from tests.llm.test_substring_dedup import brute as repeats

COLUMNS = {
    "op1_lattice_lm": {"doc_id": "bigint", "held_out": "boolean", "n_tokens": "bigint", "n_known": "bigint", "train_tokens": "bigint", "base_score": "double", "score": "double"},
    "op2_substring_dedup": {"doc_id": "bigint", "n_bytes": "bigint", "n_removed": "bigint", "n_spans": "bigint", "kept_sha256": "string"},
    "op3_quality_rules": {"doc_id": "bigint", "n_words": "bigint", "word_chars": "bigint", "n_symbols": "bigint", "n_dup_lines": "bigint", "n_repeat_words": "bigint", "base_failed": "boolean", "kept": "boolean"},
    "op4_best_fit_packing": {"doc_id": "bigint", "sequence_id": "string", "capacity": "int"},
    "op5_bpe_stream": {"doc_id": "bigint", "n_tokens": "bigint", "ids_sha256": "string", "decoded_sha256": "string"},
    "op6_url_templates": {"page_id": "bigint", "host": "string", "path": "string", "rule": "string", "verdict": "string"},
    "op7_media_columns": {"doc_id": "bigint", "n_bytes": "bigint", "payload_bytes": "bigint", "payload_sha256": "string", "tail_crc32": "bigint", "media_bytes": "bigint", "media_sha256": "string", "feature": "string"},
    "op8_toxicity": {"doc_id": "bigint", "held_out": "boolean", "score": "double", "predicted": "int"},
    "op9_ngram_jaccard": {"doc_id": "bigint", "n_shingles": "bigint", "component_id": "bigint"},
    "op10_language_id": {"doc_id": "bigint", "held_out": "boolean", "lang_pred": "string", "score": "double"},
}


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    root = tmp_path_factory.mktemp("tables")
    r = random.Random(12)
    syllables = {"en": ["the", "ing", "tion", "sh"], "fr": ["le", "eau", "qu", "ment"]}
    text = lambda lang, n: " ".join("".join(r.choice(syllables[lang]) for _ in range(r.randint(1, 4))) for _ in range(n))
    passage, rows, labels = text("en", 30), [], []
    for i in range(240):
        lang, bad = ("fr" if i % 3 else "en"), i % 5 == 0
        t = text(lang, r.choice([30, 70, 120])) + (" " + passage if i % 7 == 0 else "") + (" blorkish" if i % 8 == 3 else "")
        rows.append((i, " ".join(w + "***" for w in t.split()) if bad else t, lang, "s", len(t)))
        labels.append((i, int(not bad), int(i % 8 == 3)))
    a, b = alternating(10)
    rows += [(300, rows[1][1], "en", "s", 1), (301, rows[2][1] + " more", "fr", "s", 1), (302, "\u0661\u0662 12", None, "s", 1), (303, None, None, None, None), (304, "", "en", "s", 0), (305, f"{a}\n{b}", "en", "s", 1), (306, b, "en", "s", 1)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{root}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{root}/labels.parquet")
    pages = [(i, f"http://h{i % 3}.example.{'com' if i % 2 else 'net'}/{'en' if i % 4 else 'de'}/{i}", "<p>") for i in range(240)] + [(500, None, ""), (501, "no url", "")]
    spark.createDataFrame(pages, "page_id long, url string, html string").write.parquet(f"{root}/pages.parquet")
    return str(root), rows, labels, pages


@pytest.fixture(scope="module")
def results(spark, tables):
    return {name: queries.QUERIES[name](spark, tables[0]) for name in COLUMNS}


@pytest.fixture(scope="module")
def found(results):
    return {name: df.collect() for name, df in results.items()}


@pytest.mark.parametrize("name", COLUMNS)
def test_columns(results, name):
    have = dict(results[name].dtypes)
    assert {c: have.get(c) for c in COLUMNS[name]} == COLUMNS[name]


@pytest.mark.parametrize("name, modulus, rest", [("op1_lattice_lm", 7, 2), ("op8_toxicity", 4, 2), ("op10_language_id", 3, 1)])
def test_folds(found, tables, name, modulus, rest):
    assert {x.doc_id: x.held_out for x in found[name]} == {d: zlib.crc32(str(d).encode()) % modulus == rest for d, *_ in tables[1]}


def test_op1_base(found, tables):
    words = {d: (t or "").encode().lower().split() for d, t, *_ in tables[1]}
    c = Counter(w for d in words if zlib.crc32(str(d).encode()) % 7 != 2 for w in [*words[d], b"\n"])
    n, v = sum(c.values()), len(c)
    for x in found["op1_lattice_lm"]:
        own = [*words[x.doc_id], b"\n"]
        assert (x.n_tokens, x.n_known, x.train_tokens) == (len(own), sum(c[w] > 0 for w in own), n)
        assert x.base_score == pytest.approx(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in own)) and x.score < 0


def test_op2(found, tables):
    want = [(d, n, cut, spans, hashlib.sha256(kept).hexdigest()) for d, n, cut, spans, kept in repeats([(d, t) for d, t, *_ in tables[1]])]
    assert sorted((x.doc_id, x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in found["op2_substring_dedup"]) == want


def test_op3(spark, found, tables):
    """Counts and verdicts in plain Python; only which label is in which part comes from Spark."""
    from pyspark.sql import functions as F

    got, text = {x.doc_id: x for x in found["op3_quality_rules"]}, {d: t for d, t, *_ in tables[1]}
    for d, t in text.items():
        x = got[d]
        assert (x.n_words, x.word_chars, x.n_symbols, x.n_dup_lines, x.n_repeat_words) == base_counts(t)
        assert x.base_failed == (x.n_words < 50 or 100 * x.n_repeat_words > 50 * x.n_words)
    marks = spark.createDataFrame([(d, q) for d, q, _ in tables[2]], "doc_id long, good int")
    path = {x.doc_id for x in marks.where(quality_rules.for_path()).collect()}
    docs = spark.read.parquet(f"{tables[0]}/documents.parquet")
    bins = {x.doc_id: x.asDict() for x in quality_rules.measure(docs).select("doc_id", *[v.alias(r) for r, v in quality_rules.bins().items()]).collect()}
    label = {d: q for d, q, _ in tables[2]}

    def score(rule, b):
        best = 0.0
        for low in range(1, b + 1):
            tail = [label[d] for d in path if bins[d][rule] >= low]
            best = max(best, tail.count(0) / (len(tail) + 1))
        return best

    known = {(r, b): score(r, b) for r in quality_rules.RULES for b in {x[r] for x in bins.values()}}
    worst = {d: max(known[r, x[r]] for r in quality_rules.RULES) for d, x in bins.items()}
    step = {d: sum(level > s for level in quality_rules.LEVELS) for d, s in worst.items()}
    strata = {d: lang for d, _, lang, *_ in tables[1]}
    names = {strata[d] for d in label if d not in path}
    allowed = {}
    for z in names:
        hold = [d for d in label if d not in path and strata[d] == z]
        good, bad = ([sum(step[d] == i and label[d] == q for d in hold) for i in range(len(quality_rules.LEVELS) + 1)] for q in (1, 0))
        allowed[z] = quality_rules.choose_step(good, bad, 0.05, 0.05 / len(names))
    for d, x in got.items():
        cut = allowed.get(strata[d])
        assert x.kept == (not x.base_failed and (cut is None or step[d] > cut)), d
    lost = [d for d in label if strata[d] == "fr" and not got[d].kept and not got[d].base_failed]
    assert allowed["fr"] is not None and lost and all(label[d] == 0 for d in lost)


def test_op4(found, tables):
    placed = Counter()
    for x in found["op4_best_fit_packing"]:
        placed[x.doc_id] += x.n_tokens
    assert placed == {d: len((t or "").encode().split()) for d, t, *_ in tables[1]}


def test_op5(found, tables):
    tokenizers = pytest.importorskip("tokenizers")
    peer = tokenizers.Tokenizer.from_file(bpe_stream.default_vocabulary())
    got = {x.doc_id: x for x in found["op5_bpe_stream"]}
    for d, t, *_ in tables[1]:
        ids = peer.encode(t or "", add_special_tokens=False).ids
        back = peer.decode(ids, skip_special_tokens=False)
        assert (got[d].n_tokens, got[d].ids_sha256, got[d].decoded_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(back.encode()).hexdigest())


def test_op6(found, tables):
    got = {x.page_id: x for x in found["op6_url_templates"]}
    for i, url, _ in tables[3]:
        host, path = split(url)
        fits = [(len(h + p), h + p, v) for v, h, p in queries.URL_RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        assert (got[i].host, got[i].path, got[i].rule) == (host, path, max(fits)[1] if fits else None)
        assert got[i].verdict == max(fits)[2] if fits else got[i].verdict in ("allow", "block")


def test_op7(found, tables):
    got = {x.doc_id: x for x in found["op7_media_columns"]}
    for d, t, *_ in tables[1]:
        raw = (t or "").encode()
        payload = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        x, tile = got[d], media.to_tiles(np.frombuffer(payload, np.uint8).reshape(-1, 64))[0]
        assert (x.n_bytes, x.payload_bytes, x.payload_sha256, x.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        assert (x.media_bytes, x.media_sha256) == (len(tile), hashlib.sha256(tile).hexdigest())


def test_op8(spark, found, tables):
    """Scores follow from the lexicon by a plain search; learned without the held-out fold."""
    labels = spark.read.parquet(f"{tables[0]}/labels.parquet").where(queries.fold(4) != 2)
    lexicon = toxicity.fit(spark.read.parquet(f"{tables[0]}/documents.parquet"), labels)
    assert lexicon.weights
    text = {d: t for d, t, *_ in tables[1]}
    for x in found["op8_toxicity"]:
        folded, total = toxicity.fold(text[x.doc_id] or ""), 0.0
        for i in range(len(folded)):
            if i and folded[i - 1].isalpha():
                continue
            stems = [s for s in lexicon.weights if folded.startswith(s, i)]
            if not stems:
                continue
            stem = max(stems, key=len)
            before, after = toxicity.neighbours(folded, i)
            if (stem, before, True) not in lexicon.exceptions and (stem, after, False) not in lexicon.exceptions:
                total += lexicon.weights[stem]
        assert x.score == pytest.approx(lexicon.probability(total, len(folded.split()))) and x.predicted == (x.score >= 0.3)
    toxic = {d for d, _, t in tables[2] if t}
    assert {x.doc_id for x in found["op8_toxicity"] if x.held_out and x.predicted} == {d for d in toxic if zlib.crc32(str(d).encode()) % 4 == 2}


def test_op9(found, tables):
    assert sorted((x.doc_id, x.n_shingles, x.component_id) for x in found["op9_ngram_jaccard"]) == components([(d, t) for d, t, *_ in tables[1]])


def test_op10(spark, found, tables):
    """Word scores, the best path of labels and the share of letters, in plain Python."""
    model = language_id.fit(spark.read.parquet(f"{tables[0]}/documents.parquet").where(queries.fold(3) != 1))
    mask = 0xFFFFFFFF

    def word_score(w, z):
        raw = b" " + w.lower().encode() + b" "
        total = 0.0
        for a, b, c in zip(raw, raw[1:], raw[2:], strict=False):
            x = (a * 0x9E3779B1 & mask) ^ (b * 0x85EBCA6B & mask) ^ (c * 0xC2B2AE35 & mask)
            x ^= x >> 15
            total += model.scores[z][(x * 0x2C1B3C6D & mask) >> 16]
        return total

    k = len(model.languages)
    got = {x.doc_id: x for x in found["op10_language_id"]}
    for d, t, *_ in tables[1]:
        words = (t or "").split()
        letters = [sum(c.isalpha() for c in w) for w in words]
        if not sum(letters):
            assert (got[d].lang_pred, got[d].score) == ("und", 0.0)
            continue
        best, back = np.zeros(k), []
        for i, w in enumerate(words):
            own = np.array([word_score(w, z) for z in range(k)])
            own = np.maximum(own - own.max(), -language_id.WORD_FLOOR) if letters[i] else np.zeros(k)
            top = int(best.argmax())
            jump = best[top] - language_id.SWITCH_PENALTY
            back.append([z if not i or best[z] >= jump else top for z in range(k)])
            best = (np.maximum(best, jump) if i else best) + own
        z, share = int(best.argmax()), [0] * k
        for i in range(len(words) - 1, -1, -1):
            share[z] += letters[i]
            z = back[i][z]
        assert got[d].lang_pred == model.languages[int(np.argmax(share))] and got[d].score == pytest.approx(max(share) / sum(share), abs=1e-6)
    named = {d: lang for d, _, lang, *_ in tables[1] if lang}
    held = [x for x in found["op10_language_id"] if x.held_out and x.doc_id in named and x.doc_id < 300 and x.doc_id % 7]
    assert sum(x.lang_pred == named[x.doc_id] for x in held) >= 0.97 * len(held)
