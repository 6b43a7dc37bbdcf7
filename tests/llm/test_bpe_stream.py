import hashlib
import json
import tracemalloc

import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from farspan.llm import bpe_stream

tokenizers = pytest.importorskip("tokenizers")


@pytest.fixture(scope="module")
def encoder():
    return bpe_stream.Encoder()


@pytest.fixture(scope="module")
def peer():
    return tokenizers.Tokenizer.from_file(bpe_stream.default_vocabulary())


ODD = ["", " ", "  a", "a  b ", "\n\n x\t\ty", "it's we'll I'd'x", "12 345 ½ ²", "é ñ ß Ünï", "日本語 text", "a\x85b\xa0c d", "\x1c\x1d x\x1f", "x<|endoftext|>y <|endoftext|>", "<|endoftext|><|endoftext|>", "👍🏽 ok", "a" * 1000, "ab" * 400, "!" * 700, " " * 500, "=-" * 300, "​‍", "aA" * 200 + "\xe9" * 300, "़ۖ combining", "a  b  　c \n"]


def same(encoder, peer, text):
    want = peer.encode(text, add_special_tokens=False).ids
    got = np.frombuffer(encoder.encode(text), "<u4")
    assert got.tolist() == want, text[:80]
    d = bpe_stream.Decoder(encoder.merges)
    assert d.feed(got) + d.finish() == peer.decode(want, skip_special_tokens=False)


def test_odd_texts(encoder, peer):
    for text in ODD:
        same(encoder, peer, text)


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=120))
def test_any_text(encoder, peer, text):
    same(encoder, peer, text)


@settings(max_examples=60, deadline=None)
@given(st.one_of(st.text(alphabet="aeinort", min_size=1, max_size=500), st.binary(min_size=1, max_size=300)), st.integers(1, 40))
def test_transducer_in_parts(encoder, text, step):
    """Tokens come out as soon as they are stable, and nothing but the lookahead is held."""
    t = encoder.transducer
    raw, out, held = (text.encode() if isinstance(text, str) else text) * 3, [], 0
    for a in range(0, len(raw), step):
        out += t.feed(raw[a : a + step])
        held = max(held, len(t.tail))
    assert out + t.finish() == encoder.merges.encode_whole(raw)
    assert held <= encoder.merges.lookahead + encoder.transducer.longest


def tiny(tmp_path, pairs):
    """A vocabulary of bytes and the given merges of letters."""
    vocab = {c: i for i, c in enumerate(bpe_stream.byte_letters())}
    for x, y in pairs:
        vocab.setdefault(x + y, len(vocab))
    path = tmp_path / "tiny.json"
    path.write_text(json.dumps({"added_tokens": [], "model": {"vocab": vocab, "merges": [[x, y] for x, y in pairs]}}))
    return bpe_stream.Merges(str(path))


def test_lookahead_of_chains(tmp_path):
    """a stays or goes by what stands up to four letters behind it: (b,c) takes b unless (c,d) takes c first, and so on."""
    m = tiny(tmp_path, [("d", "e"), ("c", "d"), ("b", "c"), ("a", "b")])
    assert m.lookahead == 4
    encode = lambda s: [m.pieces[i].decode() for i in m.encode_whole(s.encode())]
    assert encode("abcde") == ["a", "bc", "de"] and encode("abcdx") == ["ab", "cd", "x"]
    assert tiny(tmp_path, [("a", "b"), ("b", "c")]).lookahead == 1 and tiny(tmp_path, []).lookahead == 0


@settings(max_examples=150, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.randoms(use_true_random=False))
def test_lookahead_suffices_for_any_merge_list(tmp_path, r):
    """Whatever follows, tokens that end the lookahead before the end stay."""
    tokens, pairs = list("abc"), []
    for _ in range(r.randint(1, 14)):
        x, y = r.choice(tokens), r.choice(tokens)
        if (x, y) not in pairs and len(x + y) < 9:
            pairs.append((x, y))
            tokens.append(x + y)
    m = tiny(tmp_path, pairs)
    text = "".join(r.choice("abc") for _ in range(40)).encode()
    for cut in range(1, 30):
        part, whole = m.encode_whole(text[:cut]), m.encode_whole(text)
        end = 0
        for i, token in enumerate(part):
            end += len(m.pieces[token])
            if end > cut - m.lookahead:
                break
            assert whole[i] == token
    t = bpe_stream.Transducer(m)
    assert [x for a in range(0, 40, 3) for x in t.feed(text[a : a + 3])] + t.finish() == m.encode_whole(text)


def test_every_pretoken_goes_through_the_transducer(encoder, monkeypatch):
    monkeypatch.setattr(bpe_stream, "PART", 50)
    monkeypatch.setattr(encoder, "known", {})
    before = encoder.transducer.fed
    text = "some words, some more words " + "x" * 300 + " " * 120 + "end"
    encoder.encode(text)
    pieces = encoder.pattern.findall(text)
    short = {p for p in pieces if len(p) <= bpe_stream.KEPT_LENGTH}
    assert encoder.transducer.fed - before == len(short) + sum(len(p) > bpe_stream.KEPT_LENGTH for p in pieces)
    assert set(encoder.known) == short


def test_parts_of_a_text(encoder, peer, monkeypatch):
    monkeypatch.setattr(bpe_stream, "PART", 7)
    for text in ODD:
        same(encoder, peer, text[:400])


def test_memory_of_a_long_text(encoder):
    """One pre-token of a million bytes, and a text of many: what is held beside the text stays small."""
    for text in ("ab" * 500_000, "some words and 12 more, " * 50_000):
        tracemalloc.start()
        n = sum(len(x) for x in encoder.stream(text))
        _, most = tracemalloc.get_traced_memory()
        tracemalloc.stop()
        assert n > 400_000 and most < 24 << 20


def test_decoder_in_parts(encoder):
    text = "日本語 👍🏽 é " * 20
    ids = np.frombuffer(encoder.encode(text), "<u4")
    d = bpe_stream.Decoder(encoder.merges)
    assert "".join(d.feed(ids[i : i + 1]) for i in range(len(ids))) + d.finish() == text
    assert d.feed(np.array(encoder.merges.of_byte)[[0xE6, 0x97]]) + d.finish() == "�"


def test_documents(spark, peer):
    rows = [(i, t, "x") for i, t in enumerate(ODD)] + [(99, None, "x"), (1, ODD[2], "y"), (None, "null id", "z")]
    df = spark.createDataFrame(rows, "doc_id long, text string, ids string").repartition(3)
    got = sorted((-1 if r.doc_id is None else r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe_stream.round_trip(df).collect())
    want = []
    for d, t, _ in rows:
        ids = peer.encode(t or "", add_special_tokens=False).ids
        want.append((-1 if d is None else d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(peer.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert got == sorted(want)
    back = {r.doc_id: r.text for r in bpe_stream.decode_documents(bpe_stream.encode_documents(df.where("doc_id < 99"))).collect()}
    assert back[3] == ODD[3] and back[0] == ""
    assert bpe_stream.round_trip(df.where("doc_id = 12345")).collect() == []
