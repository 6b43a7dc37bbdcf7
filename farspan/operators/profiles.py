"""What supplies the causal attention of a window.

A profile turns a token list into a state once, and then gives rows of probabilities: ``rows(state, a, b)`` is an
array (heads, b - a, b) whose row q holds the attention of token q on tokens 0..q (0 behind it).
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np


def _digest(token: str) -> str:
    return hashlib.md5(token.encode()).hexdigest()


def causal_weights(logits: np.ndarray, a: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows a.. of a causal attention before division, and what to divide each by; logits (heads, rows, columns) are overwritten."""
    rows = logits.shape[1]
    logits[:, :, a:][:, np.triu(np.ones((rows, logits.shape[2] - a), bool), 1)] = -np.inf
    logits -= logits.max(axis=2, keepdims=True)
    np.exp(logits, out=logits)
    return logits, logits.sum(axis=2, dtype=np.float64)


class DotProfile:
    """Attention from query and key vectors: subclasses give ``state(tokens) -> (Q, K)``, each (heads, L, width)."""

    layers = 1

    def row_weights(self, state: tuple[np.ndarray, np.ndarray], a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        """Rows a to b before division, in the precision of the vectors, and their sums."""
        q, k = state
        return causal_weights((q[:, a:b] / q.dtype.type(np.sqrt(q.shape[2]))) @ k[:, :b].transpose(0, 2, 1), a)

    def rows(self, state: tuple[np.ndarray, np.ndarray], a: int, b: int) -> np.ndarray:
        held, total = self.row_weights(state, a, b)
        return held / total[:, :, None]

    def some_rows(self, state: tuple[np.ndarray, np.ndarray], rows: np.ndarray) -> np.ndarray:
        """(heads, len(rows), last row + 1): these rows only."""
        q, k = state
        logits = (q[:, rows] @ k[:, : rows[-1] + 1].transpose(0, 2, 1)).astype(np.float64) / np.sqrt(q.shape[2])
        logits[:, np.arange(logits.shape[2])[None, :] > rows[:, None]] = -np.inf
        logits -= logits.max(axis=2, keepdims=True)
        np.exp(logits, out=logits)
        return logits / logits.sum(axis=2, keepdims=True)

    def pair_ops(self, L: int, heads: int = 1, width: int = 16) -> int:
        return heads * width * L * (L + 1) // 2

    def states(self, words: list[str], codes: np.ndarray, room: dict | None = None) -> tuple[np.ndarray, np.ndarray, bool]:
        """(Q, K, small) of many windows of one length, whose tokens are the numbers of words: (windows, heads, L, width),
        Q already divided by the root of the width; heads that share their keys may have them once; small: no logit is so
        large that its exponential overflows.  ``room``: arrays of the last call with it, which may be written over."""
        held = [self.state([words[i] for i in row]) for row in codes.tolist()]
        return np.stack([q for q, _ in held]) / held[0][0].dtype.type(np.sqrt(held[0][0].shape[2])), np.stack([k for _, k in held]), False


@dataclass(frozen=True)
class HexDot(DotProfile):
    """Token vector: the first D hexadecimal digits of its md5, centred and scaled; one head, no positions."""

    D: int = 16
    spread: float = 4.6
    name: str = "hexdot"
    heads: int = 1

    @property
    def width(self) -> int:
        return self.D

    def state(self, tokens: list[str]) -> tuple[np.ndarray, np.ndarray]:
        known = {t: i for i, t in enumerate(dict.fromkeys(tokens))}
        raw = np.frombuffer(b"".join([hashlib.md5(t.encode()).digest() for t in known]), np.uint8).reshape(-1, 16)
        digits = np.stack([raw >> 4, raw & 15], axis=2).reshape(-1, 32)[:, : self.D]
        x = ((digits - 7.5) / self.spread)[[known[t] for t in tokens]][None]
        return x, x

    def states(self, words: list[str], codes: np.ndarray, room: dict | None = None) -> tuple[np.ndarray, np.ndarray, bool]:
        x = self.state(words)[0][0][codes][:, None]
        return x / np.sqrt(self.D), x, (7.5 / self.spread) ** 2 * np.sqrt(self.D) < 80


@lru_cache(maxsize=4)
def _weights(seed: int, vocabulary: int, d: int, heads: int, kv_heads: int, width: int, layers: int) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    draw = lambda *shape: (r.standard_normal(shape) / np.sqrt(shape[-2] if len(shape) > 1 else 1)).astype(np.float32)
    w = {"embedding": r.standard_normal((vocabulary, d)).astype(np.float32)}
    for j in range(layers):
        w |= {f"norm{j}": np.ones(d, np.float32), f"q{j}": draw(d, heads * width), f"k{j}": draw(d, kv_heads * width)}
        if j + 1 < layers:
            w |= {f"v{j}": draw(d, kv_heads * width), f"o{j}": draw(heads * width, d), f"norm_mlp{j}": np.ones(d, np.float32), f"gate{j}": draw(d, 2 * d), f"up{j}": draw(d, 2 * d), f"down{j}": draw(2 * d, d)}
    return w


@dataclass(frozen=True)
class Decoder(DotProfile):
    """A decoder layer's attention: embedding, root-mean-square norm, grouped query/key projections, rotary positions.

    ``layer`` is the one whose attention is read; the layers below it run in full.  Weights are seeded, or read
    from an npz file (embedding, norm0, q0, k0, ... as in ``_weights``).
    """

    name: str = "small"
    d: int = 128
    heads: int = 4
    kv_heads: int = 2
    width: int = 32
    rope_base: float = 5e5
    seed: int = 7
    vocabulary: int = 4096
    layer: int = 1
    path: str | None = None

    def weights(self) -> dict[str, np.ndarray]:
        if self.path:
            return _read(self.path)
        return _weights(self.seed, self.vocabulary, self.d, self.heads, self.kv_heads, self.width, self.layer)

    def ids(self, tokens: list[str], size: int) -> list[int]:
        return [int(_digest(t)[:8], 16) % size for t in tokens]

    def states(self, words: list[str], codes: np.ndarray, room: dict | None = None) -> tuple[np.ndarray, np.ndarray, bool]:
        """Projections of the first layer depend on the token alone: they are looked up, and only turned by position."""
        if self.layer > 1:
            return super().states(words, codes, room)
        ids = _known_ids(words, len(self.weights()["embedding"]))
        if (table := _first_layer(self)) is None:
            q, k = self.projected(np.unique(ids))
            ids = np.searchsorted(np.unique(ids), ids)
            q, k, most = _as_pairs(q, self.width), _as_pairs(k, self.width), self.most(q, k)
        else:
            q, k, most = table
        at, turn = ids[codes], _turns(codes.shape[1], self.width, self.rope_base)

        def turned(x: np.ndarray, name: str) -> np.ndarray:
            shape = (*at.shape, *x.shape[1:])
            held = None if room is None else room.get(name)
            if held is None or held.shape != shape:
                held = np.empty(shape, x.dtype)
            if room is not None:
                room[name] = held
            np.take(x, at, axis=0, out=held, mode="clip")  # numbers are within the table; other modes copy once more
            held *= turn[:, None]
            return held.view(np.float32).transpose(0, 2, 1, 3)

        return turned(q, "q"), turned(k, "k"), most < 80

    def projected(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Queries (divided by the root of the width) and keys of the first layer, before positions turn them."""
        w = self.weights()
        x = w["embedding"][ids]
        u = x / np.sqrt((x * x).mean(axis=1, keepdims=True) + 1e-5) * w["norm0"]
        return u @ w["q0"] / np.float32(np.sqrt(self.width)), u @ w["k0"]

    def most(self, q: np.ndarray, k: np.ndarray) -> float:
        """No logit is larger: turning keeps lengths."""
        long = lambda x: float(np.sqrt((x.reshape(len(x), -1, self.width).astype(np.float64) ** 2).sum(axis=2)).max(initial=0))
        return long(q) * long(k)

    def sinks(self, words: list[str], codes: np.ndarray, block: int = 64, held: int = 1 << 17) -> np.ndarray:
        """Share of attention on the first token in each layer up to this one (windows, layers), of windows of one length whose
        tokens are numbers of words: the stack runs once, and a layer's weights are read where they lead on."""
        w, (n, L) = self.weights(), codes.shape
        x = w["embedding"][_known_ids(words, len(w["embedding"]))[codes]].reshape(n * L, -1)
        norm = lambda x, g: x / np.sqrt((x * x).mean(axis=1, keepdims=True) + 1e-5) * g
        split = lambda x, m: x.reshape(n, L, m, -1).transpose(0, 2, 1, 3)
        (cos, sin), root = _angles(L, self.width, self.rope_base), np.float32(np.sqrt(self.width))
        out, each = np.zeros((n, self.layer)), self.heads // self.kv_heads
        for j in range(self.layer):
            last, u = j + 1 == self.layer, norm(x, w[f"norm{j}"])
            q = _turn(split(u @ w[f"q{j}"], self.heads), cos, sin) / root
            k = np.repeat(_turn(split(u @ w[f"k{j}"], self.kv_heads), cos, sin), each, axis=1)
            v = None if last else np.repeat(split(u @ w[f"v{j}"], self.kv_heads), each, axis=1)
            met = None if last else np.empty((n, L, self.heads, v.shape[3]), np.float32)
            for a in range(0, L, block):
                b = min(L, a + block)
                step = max(1, held // (self.heads * (b - a) * b))
                behind = np.triu(np.ones((b - a, b - a), bool), 1)
                for i in range(0, n, step):
                    p = q[i : i + step, :, a:b] @ k[i : i + step, :, :b].transpose(0, 1, 3, 2)
                    np.copyto(p[..., a:], -np.inf, where=behind)
                    p -= p.max(axis=3, keepdims=True)
                    np.exp(p, out=p)
                    total = p.sum(axis=3)
                    out[i : i + step, j] += (p[..., 0] / total).mean(axis=1).sum(axis=1)
                    if not last:
                        met[i : i + step, a:b] = ((p @ v[i : i + step, :, :b]) / total[..., None]).transpose(0, 2, 1, 3)
            if not last:
                x = x + met.reshape(n * L, -1) @ w[f"o{j}"]
                u = norm(x, w[f"norm_mlp{j}"])
                gate = u @ w[f"gate{j}"]
                x = x + (gate / (1 + np.exp(-gate)) * (u @ w[f"up{j}"])) @ w[f"down{j}"]
        return out / L

    def _turned(self, x: np.ndarray) -> np.ndarray:
        """Rotary rotation of component pairs (j, j + width / 2) by position."""
        half = x.shape[2] // 2
        angle = np.arange(x.shape[1])[:, None] * self.rope_base ** (-np.arange(half) / half)
        cos, sin = np.cos(angle).astype(np.float32), np.sin(angle).astype(np.float32)
        a, b = x[:, :, :half], x[:, :, half:]
        return np.concatenate([a * cos - b * sin, a * sin + b * cos], axis=2)

    def state(self, tokens: list[str]) -> tuple[np.ndarray, np.ndarray]:
        w = self.weights()
        x = w["embedding"][self.ids(tokens, len(w["embedding"]))]
        norm = lambda x, g: x / np.sqrt((x * x).mean(axis=1, keepdims=True) + 1e-5) * g
        split = lambda x, n: x.reshape(len(x), n, -1).transpose(1, 0, 2)
        for j in range(self.layer):
            u = norm(x, w[f"norm{j}"])
            q = self._turned(split(u @ w[f"q{j}"], self.heads))
            k = np.repeat(self._turned(split(u @ w[f"k{j}"], self.kv_heads)), self.heads // self.kv_heads, axis=0)
            if j + 1 == self.layer:
                return q, k
            v = np.repeat(split(u @ w[f"v{j}"], self.kv_heads), self.heads // self.kv_heads, axis=0)
            p = self.rows((q, k), 0, len(x)).astype(np.float32)
            x = x + (p @ v).transpose(1, 0, 2).reshape(len(x), -1) @ w[f"o{j}"]
            u = norm(x, w[f"norm_mlp{j}"])
            gate = u @ w[f"gate{j}"]
            x = x + (gate / (1 + np.exp(-gate)) * (u @ w[f"up{j}"])) @ w[f"down{j}"]
        raise AssertionError


def _turn(x: np.ndarray, cos: np.ndarray, sin: np.ndarray) -> np.ndarray:
    half = x.shape[-1] // 2
    a, b = x[..., :half], x[..., half:]
    out = np.empty(x.shape, x.dtype)
    np.subtract(a * cos, b * sin, out=out[..., :half])
    np.add(a * sin, b * cos, out=out[..., half:])
    return out


@lru_cache(maxsize=8)
def _angles(L: int, width: int, base: float) -> tuple[np.ndarray, np.ndarray]:
    half = width // 2
    angle = np.arange(L)[:, None] * base ** (-np.arange(half) / half)
    return np.cos(angle).astype(np.float32), np.sin(angle).astype(np.float32)


def _as_pairs(x: np.ndarray, width: int) -> np.ndarray:
    """(tokens, heads, width / 2): components j and j + width / 2, which turn together, as one complex number."""
    a, b = np.split(x.reshape(len(x), -1, width), 2, axis=2)
    return (a + 1j * b).astype(np.complex64)


@lru_cache(maxsize=8)
def _turns(L: int, width: int, base: float) -> np.ndarray:
    cos, sin = _angles(L, width, base)
    return (cos + 1j * sin).astype(np.complex64)


#: Floats of a table of first-layer projections, at most; beyond, those of a batch's tokens are computed.
TABLE = 1 << 22


@lru_cache(maxsize=4)
def _first_layer(profile: Decoder) -> tuple[np.ndarray, np.ndarray, float] | None:
    size = len(profile.weights()["embedding"])
    if size * (profile.heads + profile.kv_heads) * profile.width > TABLE:
        return None
    q, k = profile.projected(np.arange(size))
    return _as_pairs(q, profile.width), _as_pairs(k, profile.width), profile.most(q, k)


#: Words whose numbers a process keeps, at most.
KNOWN = 1 << 17
_numbers: dict[str, int] = {}
#: The last words that were looked up, their numbers, and those modulo a size: a batch asks for the same ones many times.
_last: list = [None, None, {}]


def _known_ids(words: list[str], size: int) -> np.ndarray:
    """``Decoder.ids`` of a batch's words, most of which were met before."""
    if _last[0] is not words:
        if len(_numbers) > KNOWN:
            _numbers.clear()
        for w in words:
            if w not in _numbers:
                _numbers[w] = int.from_bytes(hashlib.md5(w.encode()).digest()[:4], "big")
        _last[:] = words, np.fromiter(map(_numbers.__getitem__, words), np.int64, len(words)), {}
    if size not in _last[2]:
        _last[2][size] = _last[1] % size
    return _last[2][size]


@lru_cache(maxsize=2)
def _read(path: str) -> dict[str, np.ndarray]:
    with np.load(path) as f:
        return {k: f[k] for k in f.files}


@dataclass(frozen=True)
class Vectors(DotProfile):
    """Q = K = the given vectors (tokens are rows of floats)."""

    name: str = "vectors"
    heads: int = 1
    width: int = 64

    def state(self, tokens) -> tuple[np.ndarray, np.ndarray]:
        x = np.array([np.asarray(t, np.float64) for t in tokens])[None]
        return x, x


@dataclass(frozen=True)
class TableVectors(DotProfile):
    """Token vectors learned elsewhere (for instance Word2Vec); unknown tokens are the zero vector."""

    table: dict = field(hash=False, compare=False)
    width: int = 32
    name: str = "corpus"
    heads: int = 1

    def state(self, tokens: list[str]) -> tuple[np.ndarray, np.ndarray]:
        zero = np.zeros(self.width)
        x = np.array([self.table.get(t, zero) for t in tokens], np.float64)[None]
        return x, x

    def states(self, words: list[str], codes: np.ndarray, room: dict | None = None) -> tuple[np.ndarray, np.ndarray, bool]:
        x = self.state(words)[0][0][codes][:, None]
        return x / np.sqrt(x.shape[3]), x, False


@dataclass(frozen=True)
class RowVectors(TableVectors):
    """The same for words that are numbers of rows of the table, an array."""

    def state(self, tokens) -> tuple[np.ndarray, np.ndarray]:
        x = self.table[np.asarray(tokens)].astype(np.float64)[None]
        return x, x


@dataclass(frozen=True)
class Analytic:
    """Known attention: uniform, self, sink (all on the first token), previous, copy (all on the last equal token)."""

    kind: str = "uniform"
    heads: int = 1
    width: int = 0

    @property
    def name(self) -> str:
        return self.kind

    def state(self, tokens: list[str]) -> list[str]:
        return tokens

    def rows(self, state: list[str], a: int, b: int) -> np.ndarray:
        p = np.zeros((1, b - a, b))
        for q in range(a, b):
            if self.kind == "uniform":
                p[0, q - a, : q + 1] = 1 / (q + 1)
            elif self.kind == "copy":
                p[0, q - a, next((i for i in range(q - 1, -1, -1) if state[i] == state[q]), q)] = 1
            else:
                p[0, q - a, {"self": q, "sink": 0, "previous": max(0, q - 1)}[self.kind]] = 1
        return p

    def pair_ops(self, L: int, heads: int = 1, width: int = 0) -> int:
        return 0


def named(name: str, **more):
    """hexdot, small, large, an analytic kind, or a path to weights (npz:...)."""
    if name == "hexdot":
        return HexDot(**more)
    if name == "small":
        return Decoder(**more)
    if name == "large":
        return Decoder(**({"name": "large", "d": 512, "heads": 8, "kv_heads": 2, "width": 64} | more))
    if name.startswith("npz:"):
        return Decoder(**({"name": "weights", "path": name[4:]} | more))
    return Analytic(name)


#: Tokens that one task learns from, about; vectors of several tasks are averaged.
LEARNED_TOGETHER = 1 << 20
#: Words that Spark's Word2Vec learns, whose driver holds them several times over; larger vocabularies are learned in tasks.
VOCABULARY = 1 << 17


def from_corpus(tokens_df, dim: int = 32, seed: int = 7):
    """(word, vector): a vector for every word that stands twice or more in the corpus.  A table, as the vocabulary grows
    with the corpus; ``score.score_with_vectors`` reads it.

    A corpus of more than LEARNED_TOGETHER tokens is dealt over several tasks; all of it is learned from.  A vocabulary of
    more than VOCABULARY words is learned by ``skipgram``, which no process holds whole; its columns are n (occurrences) and
    half (the vector in half precision) as well."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array
    from pyspark.sql import functions as F

    from farspan.operators import skipgram

    held = skipgram.vectors(tokens_df, VOCABULARY, dim, seed)
    if held is not None:
        return held.select("word", skipgram.as_floats(dim)("half").alias("vector"), "n", "half")
    size = tokens_df.agg(F.sum(F.size("toks").cast("long"))).first()[0] or 0
    parts = max(1, -(-size // LEARNED_TOGETHER))
    model = Word2Vec(vectorSize=dim, seed=seed, minCount=2, inputCol="toks", outputCol="v", maxIter=1, numPartitions=parts).fit(tokens_df.select("toks"))
    return model.getVectors().select("word", vector_to_array(F.col("vector"), "float32").alias("vector"))
