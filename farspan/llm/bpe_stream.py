"""Byte-level BPE as a streaming transducer, and back.

A text is a stream of pre-tokens, and no merge crosses their boundaries.  Every pre-token is fed, in parts if it is
long, to a transducer that keeps for each prefix of the undecided bytes the last token of that prefix's encoding:
the tokens that end there are found by an automaton over the vocabulary, and the one stands that is left unmerged
behind the last token of the prefix before it.

How far ahead a decision can depend on what follows is computed from the merge list (``sufficient_lookahead``): whether
rule r = (u, v) may merge at a place depends on bytes behind v only if a rule of lower rank takes v, or the last part v
is made of, away to the right, which in turn may be prevented by a rule of still lower rank, and so on.  Ranks fall along
such a chain, so its longest reach follows from one pass over the list.  A token that ends at least the lookahead
before the last byte read is stable: it is emitted and its bytes are forgotten.  Memory is the lookahead and one
part, however long the pre-token.

Encodings of short pre-tokens that went through the transducer are kept in a table of bounded size for their next
occurrence.  Decoding turns token bytes into text with an incremental UTF-8 state machine.

A null text is an empty one and has no token; ids beyond the vocabulary raise; repeated rows give repeated rows;
an empty table gives an empty result; columns other than id and text are not read.
"""

from __future__ import annotations

import codecs
import hashlib
import json
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from farspan.llm.storage import texts
from farspan.llm.textbatch import all_chunks

#: Fixed value: the pre-token pattern of byte-level BPE, with white space spelled out.
_S = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
PATTERN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_S}\p{{L}}\p{{N}}]+|[{_S}]+(?![^{_S}])|[{_S}]+"
#: Encodings of pre-tokens that a worker keeps; the table starts afresh when it is full.
KEPT = 400_000
#: Characters of a pre-token whose encoding is kept, at most.
KEPT_LENGTH = 64
#: Characters that are split into pre-tokens, and bytes that are fed to the transducer, at once.
PART = 1 << 16
NEVER = 1 << 40


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def byte_letters() -> dict[str, int]:
    """The printable stand-in of each byte in vocabulary files: itself if printable, else the next free one from U+0100."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Merges:
    """Vocabulary and merge list of a byte-level BPE file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            held = json.load(f)
        letters = byte_letters()
        vocabulary = held["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in held["added_tokens"]}
        raw = {i: bytes(letters[c] for c in s) for s, i in vocabulary.items()}
        self.pieces = [b""] * (max([*raw, *self.special.values()]) + 1)
        for i, b in raw.items():
            self.pieces[i] = b
        for s, i in self.special.items():
            self.pieces[i] = s.encode()
        self.of_bytes = {b: i for i, b in raw.items()}
        self.of_byte = [self.of_bytes[bytes([b])] for b in range(256)]
        self.rank: dict[int, int] = {}
        self.made: list[int] = []
        for r, pair in enumerate(held["model"]["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.rank.setdefault(vocabulary[a] << 20 | vocabulary[b], r)
            self.made.append(vocabulary[a + b])
        self.lookahead = self.sufficient_lookahead()
        # the rule that makes each token of its own bytes: its rank (-1 for a byte) and its two parts
        self.rank_of: dict[int, int] = dict.fromkeys(self.of_byte, -1)
        self.left: dict[int, int] = {}
        self.right: dict[int, int] = {}
        for pair, r in self.rank.items():
            u, v, token = pair >> 20, pair & 0xFFFFF, self.made[r]
            if token not in self.rank_of and u in self.rank_of and v in self.rank_of and self._apart(u, v, r):
                self.rank_of[token], self.left[token], self.right[token] = r, u, v
        self._follows: dict[int, bool] = {}

    def sufficient_lookahead(self) -> int:
        """Bytes behind a token's end that decide whether it stands.

        reach[r], for a rule r = (u, v): how far behind v the bytes may lie that keep r from merging.  Either a rule
        q = (v, w) of lower rank takes v, which needs len(w) bytes and reach[q] more; or, while v is being made by its
        own rule, something does that to v's last part, as counted in that rule's reach.  With both terms known
        for all lower ranks, one pass in order of rank fills the table.  A token stands if no rule (token, v) merges
        it, and that shows within len(v) + reach bytes behind it.
        """
        taken: dict[int, int] = {}  # by left part: farthest len(w) + reach[q] among the rules so far
        made_by: dict[int, int] = {}  # by token: reach of the rules that make it
        most = 0
        for pair, r in self.rank.items():  # in order of rank
            u, v = pair >> 20, pair & 0xFFFFF
            reach = max(taken.get(v, 0), made_by.get(v, 0))
            token, span = self.made[r], len(self.pieces[v]) + reach
            taken[u] = max(taken.get(u, 0), span)
            made_by[token] = max(made_by.get(token, 0), reach)
            most = max(most, span)
        return most

    def encode_whole(self, raw: bytes) -> list[int]:
        """Merges in order of rank, leftmost first."""
        ids = [self.of_byte[b] for b in raw]
        rank, made = self.rank.get, self.made
        open_ranks = [rank(a << 20 | b, NEVER) for a, b in zip(ids, ids[1:], strict=False)]
        while open_ranks and (r := min(open_ranks)) != NEVER:
            i = open_ranks.index(r)
            ids[i : i + 2] = [made[r]]
            del open_ranks[i]
            if i:
                open_ranks[i - 1] = rank(ids[i - 1] << 20 | ids[i], NEVER)
            if i < len(open_ranks):
                open_ranks[i] = rank(ids[i] << 20 | ids[i + 1], NEVER)
        return ids

    def _apart(self, x: int, y: int, limit: int) -> bool:
        """Do rules below rank ``limit`` leave these two tokens side by side?

        The merges that made the two are undone in reverse order; at each step the parts that touch must not have had
        a rule that came first.  Of equal ranks the left place comes first.
        """
        rank, rank_of = self.rank.get, self.rank_of
        while True:
            if rank(x << 20 | y, NEVER) < limit:
                return False
            a, b = rank_of[x], rank_of[y]
            if a > b:
                limit, x = a, self.right[x]
            elif b >= 0:
                limit, y = b + 1, self.left[y]
            else:
                return True

    def follows(self, before: int, token: int) -> bool:
        """Do the merges leave these two tokens side by side for good?"""
        key = before << 20 | token
        if key not in self._follows:
            if len(self._follows) > 1_000_000:
                self._follows.clear()
            self._follows[key] = self._apart(before, token, NEVER)
        return self._follows[key]


class Transducer:
    """Encodes one pre-token fed in parts; memory stays within the lookahead and one part."""

    def __init__(self, merges: Merges):
        import ahocorasick

        self.merges = merges
        reached = [(merges.pieces[token], token) for token in merges.rank_of]
        self.longest = max(len(raw) for raw, _ in reached)
        self.automaton = ahocorasick.Automaton()
        for raw, token in reached:
            self.automaton.add_word(raw.decode("latin-1"), (len(raw), token))
        self.automaton.make_automaton()
        self.fed = 0  # pre-tokens that went through
        self.start()

    def start(self) -> None:
        self.tail = b""  # bytes behind the last stable place
        self.last: list[int] = [-1]  # last token of the encoding of each prefix of the tail; first the last stable token

    def feed(self, raw: bytes) -> list[int]:
        """Tokens that have become stable."""
        out: list[int] = []
        for at in range(0, len(raw), PART):
            begin = len(self.tail)
            self.tail += raw[at : at + PART]
            self._advance(begin)
            if len(self.tail) > self.merges.lookahead:
                out += self._stable(len(self.tail) - self.merges.lookahead)
        return out

    def finish(self) -> list[int]:
        out = self._path(len(self.tail))
        self.fed += 1
        self.start()
        return out

    def _advance(self, begin: int) -> None:
        """The last token for every prefix that ends behind ``begin``."""
        last, merges = self.last, self.merges
        known, follows = merges._follows, merges.follows
        back = max(0, begin - self.longest + 1)
        for end, (size, token) in self.automaton.iter(self.tail[back:].decode("latin-1")):
            # tokens that end at one place come longest first
            end += back + 1
            if end < len(last) or end < size:
                continue
            before = last[end - size]
            if before < 0 or (known.get(before << 20 | token) or follows(before, token)):
                last.append(token)
        assert len(last) == len(self.tail) + 1

    def _path(self, end: int) -> list[int]:
        out, pieces = [], self.merges.pieces
        while end:
            out.append(self.last[end])
            end -= len(pieces[out[-1]])
        return out[::-1]

    def _stable(self, upto: int) -> list[int]:
        """Tokens that end at ``upto`` bytes or before; their bytes are forgotten."""
        end, pieces = len(self.tail), self.merges.pieces
        while end > upto:
            end -= len(pieces[self.last[end]])
        out = self._path(end)
        if out:
            self.tail, self.last = self.tail[end:], [out[-1], *self.last[end + 1 :]]
        return out


class Encoder:
    def __init__(self, path: str | None = None):
        import regex

        self.merges = Merges(path or default_vocabulary())
        self.transducer = Transducer(self.merges)
        self.pattern = regex.compile(PATTERN)
        self.blank = regex.compile(rf"[^{_S}] ", regex.REVERSE)
        self.known: dict[str, bytes] = {}
        self.special = regex.compile("|".join(map(regex.escape, sorted(self.merges.special, key=len, reverse=True)))) if self.merges.special else None

    def _word(self, word: str) -> bytes:
        """Ids of a pre-token up to KEPT_LENGTH characters, from the table or through the transducer."""
        found = self.known.get(word)
        if found is None:
            if len(self.known) >= KEPT:
                self.known.clear()
            ids = self.transducer.feed(word.encode()) + self.transducer.finish()
            self.known[word] = found = b"".join([i.to_bytes(4, "little") for i in ids])
        return found

    def _piece(self, text: str, begin: int, end: int) -> Iterator[bytes]:
        if end - begin <= KEPT_LENGTH:
            yield self._word(text[begin:end])
            return
        for at in range(begin, end, PART):
            yield np.array(self.transducer.feed(text[at : min(end, at + PART)].encode()), "<u4").tobytes()
        yield np.array(self.transducer.finish(), "<u4").tobytes()

    def _plain(self, text: str, begin: int, end: int) -> Iterator[bytes]:
        """Text without special tokens.  A part ends before a blank behind something else, where a pre-token always ends."""
        word, short = self._word, KEPT_LENGTH
        while begin < end:
            if (stop := begin + PART) >= end:
                stop = end
            else:
                m = self.blank.search(text, begin, stop)
                stop = m.start() + 1 if m else begin
            if stop > begin:
                pieces = self.pattern.findall(text, begin, stop)
                if max(map(len, pieces)) <= short:
                    yield b"".join(map(word, pieces))
                else:
                    for piece in pieces:
                        yield from self._piece(piece, 0, len(piece))
                begin = stop
            else:  # no such place: one pre-token, however long
                m = self.pattern.match(text, begin, end)
                yield from self._piece(text, begin, m.end())
                begin = m.end()

    def stream(self, text: str) -> Iterator[bytes]:
        """Ids as little-endian unsigned 32-bit integers, as they become stable."""
        at = 0
        if self.special:
            for m in self.special.finditer(text):
                yield from self._plain(text, at, m.start())
                yield self.merges.special[m[0]].to_bytes(4, "little")
                at = m.end()
        yield from self._plain(text, at, len(text))

    def encode(self, text: str) -> bytes:
        return b"".join(self.stream(text))


@lru_cache(maxsize=2)
def encoder(path: str | None = None) -> Encoder:
    """One encoder a worker process and vocabulary: its tables outlive a task."""
    return Encoder(path)


class Decoder:
    """Token ids to text, fed in parts; bytes that are no UTF-8 become U+FFFD."""

    def __init__(self, merges: Merges):
        size = np.array([len(p) for p in merges.pieces])
        self.begin, self.size = np.cumsum(size) - size, size
        self.flat = np.frombuffer(b"".join(merges.pieces), np.uint8)
        self.state = codecs.getincrementaldecoder("utf-8")("replace")

    def bytes_of(self, ids: np.ndarray) -> bytes:
        size = self.size[ids]
        ends = np.cumsum(size)
        at = np.arange(ends[-1] if len(ends) else 0) + np.repeat(self.begin[ids] - (ends - size), size)
        return self.flat[at].tobytes()

    def feed(self, ids: np.ndarray) -> str:
        return self.state.decode(self.bytes_of(ids))

    def finish(self) -> str:
        out = self.state.decode(b"", final=True)
        self.state.reset()
        return out


def encode_documents(df: DataFrame, vocabulary: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids): the token ids of every row as array<int>."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(vocabulary)
        for part, _ in all_chunks(batches):
            ids = [np.frombuffer(own.encode(t or ""), np.int32) for t in part.column(1).to_pylist()]
            offsets = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
            flat = np.concatenate(ids) if ids else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], names=["doc_id", "ids"])

    return texts(df, id_col, text_col).mapInArrow(run, "doc_id long, ids array<int>")


def decode_documents(df: DataFrame, vocabulary: str | None = None, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, text) of rows of ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decoder = Decoder(encoder(vocabulary).merges)
        for batch in batches:
            out = []
            for ids in batch.column(1):
                own = np.asarray(ids.values.fill_null(0), np.int64) if ids.is_valid else np.zeros(0, np.int64)
                out.append("".join([*(decoder.feed(own[a : a + 4096]) for a in range(0, len(own), 4096)), decoder.finish()]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], names=["doc_id", "text"])

    return df.selectExpr(f"cast(`{id_col}` as long) as doc_id", f"cast(`{ids_col}` as array<int>) as ids").mapInArrow(run, "doc_id long, text string")


def round_trip(df: DataFrame, vocabulary: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): both ways in one pass, so that no ids are kept or moved."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(vocabulary)
        decoder = Decoder(own.merges)
        for part, _ in all_chunks(batches):
            n, ids_out, text_out = [], [], []
            for text in part.column(1).to_pylist():
                ids_digest, text_digest, size = hashlib.sha256(), hashlib.sha256(), 0
                for raw in own.stream(text or ""):
                    ids_digest.update(raw)
                    text_digest.update(decoder.feed(np.frombuffer(raw, "<u4")).encode())
                    size += len(raw) // 4
                text_digest.update(decoder.finish().encode())
                n.append(size)
                ids_out.append(ids_digest.hexdigest())
                text_out.append(text_digest.hexdigest())
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(ids_out, pa.string()), pa.array(text_out, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return texts(df, id_col, text_col).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def token_counts(texts_in: Iterable[str | None], encoder: Encoder) -> list[int]:
    return [len(encoder.encode(t or "")) // 4 for t in texts_in]
