"""All probes of a haystack at once: where words stand is worked out once for haystacks of one size, made-up words are hashed
in arrays, and under the hexdot profile a question meets every word of a haystack in one product.

``evaluate.probe`` says what a probe is, and ``evaluate.hit_share`` what a hit is; here both are done for many.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass
from functools import lru_cache
from operator import itemgetter

import numpy as np

from farspan.operators import evaluate

#: Words of every probe that are neither found nor made up.
FIXED = ("what", "is", *dict.fromkeys(w for w in evaluate.FILLER if w != "is"))
_SHIFTS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(np.sin(i + 1.0)) * 2**32) for i in range(64)]
_TURNS = [[(np.uint32(s), np.uint32(32 - s)) for s in some] for some in _SHIFTS]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
_ROWS = 16384
_HEX = np.array([list(f"{i:02x}".encode()) for i in range(256)], np.uint8)
#: Haystacks whose words are hashed together, at most, and layouts that a worker keeps.
TOGETHER, LAYOUTS = 16, 64


def md5(held: np.ndarray) -> np.ndarray:
    """MD5 (rows x 16 bytes) of short messages: rows of 64 bytes, each a message of up to 55 bytes with its padding."""
    words = np.ascontiguousarray(held.view("<u4").T)
    out = np.stack(md5_columns([int(w[0]) if len(w) and (w == w[0]).all() else w for w in words], len(held)), axis=1)
    return out.astype("<u4", copy=False).view(np.uint8)


def md5_columns(messages: list, n: int) -> list[np.ndarray]:
    """The four 32-bit words of the MD5 of n messages, from the 16 words of each: arrays, or a number that all have."""
    out = [np.empty(n, np.uint32) for _ in _START]
    for at in range(0, n, _ROWS):
        words = [x if isinstance(x, int) else x[at : at + _ROWS] for x in messages]
        state = [np.full(min(_ROWS, n - at), x, np.uint32) for x in _START]
        t, u = np.empty_like(state[0]), np.empty_like(state[0])
        a, b, c, d = state
        for i in range(64):
            turn = i >> 4
            if turn == 0:
                np.bitwise_xor(c, d, out=t)
                t &= b
                t ^= d
                g = i
            elif turn == 1:
                np.bitwise_xor(b, c, out=t)
                t &= d
                t ^= c
                g = (5 * i + 1) & 15
            elif turn == 2:
                np.bitwise_xor(b, c, out=t)
                t ^= d
                g = (3 * i + 5) & 15
            else:
                np.invert(d, out=t)
                t |= b
                t ^= c
                g = (7 * i) & 15
            t += a
            if isinstance(words[g], int):
                t += np.uint32((_SINES[i] + words[g]) & 0xFFFFFFFF)
            else:
                t += words[g]
                t += np.uint32(_SINES[i])
            left, right = _TURNS[turn][i & 3]
            np.left_shift(t, left, out=u)
            t >>= right
            t |= u
            t += b
            a, b, c, d, t = d, t, b, c, a
        for x, own, first in zip(out, (a, b, c, d), _START, strict=True):
            np.add(own, np.uint32(first), out=x[at : at + _ROWS])
    return out


def _padded(messages: list[bytes]) -> np.ndarray:
    """Messages of up to 55 bytes as rows for ``md5``."""
    rows = b"".join((m + b"\x80").ljust(56, b"\0") + (8 * len(m)).to_bytes(8, "little") for m in messages)
    return np.frombuffer(rows, np.uint8).reshape(-1, 64).copy()


def hexdot_digits(digests: np.ndarray, D: int) -> np.ndarray:
    """Twice the centred digits of the hexdot profile, whole numbers: their products are exact and tie where they are equal."""
    return (np.stack([digests >> 4, digests & 15], axis=2).reshape(len(digests), -1)[:, :D].astype(np.float32) * 2) - 15


@dataclass(frozen=True)
class Alike:
    """Probes with as many questions, answers and made-up words: arrays (probes x ...); ``ids`` past a probe's end is -1, and
    ``span`` is the answer span at a position (from 0, or -1)."""

    probes: np.ndarray
    ids: np.ndarray
    asked: np.ndarray
    query: np.ndarray
    span: np.ndarray
    answers: int


@dataclass(frozen=True)
class Layout:
    """Where the words of all probes of a haystack of one size stand, as numbers: words of the haystack, of the passage,
    FIXED ones, and from ``made`` on the probe's made-up ones (keys 0 to 3, values 0 to 3, then a key and a value each)."""

    names: tuple[tuple[str, float], ...]
    words: list
    size: list[int]
    held: list[int]
    made: int
    pairs: tuple[int, ...]
    used: tuple[tuple[int, ...], ...]
    alike: list[Alike]


@lru_cache(maxsize=LAYOUTS)
def layout(tasks: tuple[str, ...], depths: tuple[float, ...], length: int, haystack: int, passage: int) -> Layout:
    first = haystack + passage
    made, fixed = first + len(FIXED), {w: first + i for i, w in enumerate(FIXED)}
    at = {"k": 0, "v": 4}
    name = lambda role, i: made + (at[role] + i if role in at else 8 + 2 * i + (role == "e"))
    names, toks, pairs, found = [], [], [], []
    for task in tasks:
        for depth in depths:
            p = evaluate.probe(task, 0, depth, list(range(haystack)), length, list(range(haystack, first)), name)
            ids = np.array([fixed.get(t, t) if isinstance(t, str) else t for t in p["toks"]], np.int64)
            names.append((task, depth))
            toks.append(ids)
            pairs.append(max(0, -(-(int(ids.max(initial=0)) - made - 7) // 2)))
            found.append(p)
    groups: dict[tuple, list[int]] = {}
    for j, p in enumerate(found):
        groups.setdefault((len(p["query_pos"]), p["answers"], pairs[j]), []).append(j)
    alike = []
    for (_, answers, _), js in groups.items():
        ids = np.full((len(js), max(len(toks[j]) for j in js)), -1)
        span = np.full(ids.shape, -1)
        for row, j in enumerate(js):
            ids[row, : len(toks[j])] = toks[j]
            for s, (x, y) in enumerate(found[j]["spans"]):
                span[row, x : y + 1] = s
        query = np.array([found[j]["query_pos"] for j in js], np.int64)
        alike.append(Alike(np.array(js), ids, np.take_along_axis(ids, query, 1), query, span, answers))
    held = [len(p["answer_pos"]) for p in found]
    used = tuple(tuple(np.unique(x[x >= made] - made).tolist()) for x in toks)
    return Layout(tuple(names), [itemgetter(*x.tolist()) for x in toks], [len(x) for x in toks], held, made, tuple(pairs), used, alike)


@dataclass(frozen=True)
class Names:
    """Messages whose hashes are the made-up words, for numbers of ``digits`` digits, by the form of the word."""

    rows: np.ndarray
    digits_at: list[tuple[int, int, int]]
    forms: list[tuple[str, int, int]]
    of: list[np.ndarray]
    pick: list


@lru_cache(maxsize=48)
def _names(names: tuple[tuple[str, float], ...], pairs: tuple[int, ...], digits: int) -> Names:
    found = []
    for p, ((task, depth), n) in enumerate(zip(names, pairs, strict=True)):
        kind = evaluate.kind_of(task)
        for role, i in [(r, i) for r in "kv" for i in range(4)] + [(r, i) for i in range(n) for r in "de"]:
            slot = {"k": 0, "v": 4}[role] + i if role in "kv" else 8 + 2 * i + (role == "e")
            head, tail = evaluate.seed_parts(task, depth, role, i)
            form = ("value-hex" if kind == "hex" else "value-number") if role in "ve" else "key-12" if role == "k" and kind == "hex" else "key-6"
            found.append((form, len(head), p, slot, head.encode() + b"0" * digits + tail.encode()))
    order = sorted(range(len(found)), key=lambda x: found[x][:2])
    of = [np.zeros(8 + 2 * n, np.int64) for n in pairs]
    digits_at, forms = [], []
    for row, x in enumerate(order):
        form, at, p, slot, _ = found[x]
        of[p][slot] = row
        if not digits_at or digits_at[-1][2] != at or forms[-1][0] != form:
            digits_at.append((row, row, at))
        digits_at[-1] = (digits_at[-1][0], row + 1, at)
        if not forms or forms[-1][0] != form:
            forms.append((form, row, row))
        forms[-1] = (form, forms[-1][1], row + 1)
    return Names(_padded([found[x][4] for x in order]), digits_at, forms, of, [itemgetter(*x.tolist()) for x in of])


_WIDTH = {"key-6": (b"key-", 6), "key-12": (b"key-", 12), "value-number": (b"value-", 7), "value-hex": (b"value-", 32)}


def _words(names: Names, digests: np.ndarray) -> np.ndarray:
    """The made-up words of one haystack as rows for ``md5``."""
    out = np.zeros((len(digests), 64), np.uint8)
    for form, a, b in names.forms:
        head, n = _WIDTH[form]
        if form == "value-number":
            x = digests[a:b, :6].astype(np.int64) @ (256 ** np.arange(5, -1, -1, dtype=np.int64)) % 10**7
            shown = (x[:, None] // 10 ** np.arange(6, -1, -1) % 10 + 48).astype(np.uint8)
        else:
            shown = _HEX[digests[a:b, : -(-n // 2)]].reshape(b - a, -1)[:, :n]
        m = len(head) + n
        out[a:b, : len(head)], out[a:b, len(head) : m], out[a:b, m] = np.frombuffer(head, np.uint8), shown, 0x80
        out[a:b, 56:58] = (8 * m & 255, 8 * m >> 8)
    return out


def made_words(plans: list[Layout], numbers: list[int]) -> list[tuple[Names, np.ndarray]]:
    """For each haystack (its layout and number) the messages of its made-up words and the words, as rows for ``md5``."""
    names = [_names(p.names, p.pairs, len(str(n))) for p, n in zip(plans, numbers, strict=True)]
    held = []
    for x, number in zip(names, numbers, strict=True):
        rows, shown = x.rows.copy(), np.frombuffer(str(number).encode(), np.uint8)
        for a, b, at in x.digits_at:
            rows[a:b, at : at + len(shown)] = shown
        held.append(rows)
    ends = np.cumsum([0, *map(len, held)])
    digests = md5(np.concatenate(held))
    return [(x, _words(x, digests[a:b])) for x, a, b in zip(names, ends, ends[1:], strict=False)]


def _text(names: Names, rows: np.ndarray) -> list[str]:
    out = []
    for form, a, b in names.forms:
        head, n = _WIDTH[form]
        m = len(head) + n
        s = rows[a:b, :m].tobytes().decode()
        out += [s[i : i + m] for i in range(0, len(s), m)]
    return out


@lru_cache(maxsize=1 << 16)
def _digest(word: str) -> bytes:
    return hashlib.md5(word.encode()).digest()


def _few(numbers: list[int], hays: list[list[str]], passages: list[list[str]], tasks, depths, length):
    """(number, words, layout, names, made-up words as rows), haystack after haystack."""
    for a in range(0, len(numbers), TOGETHER):
        plans = [layout(tasks, depths, length, len(h), len(p)) for h, p in zip(hays[a : a + TOGETHER], passages[a : a + TOGETHER], strict=True)]
        made = made_words(plans, numbers[a : a + TOGETHER])
        ends = np.cumsum([0, *(len(rows) for _, rows in made)])
        yield [(numbers[a + j], [*hays[a + j], *passages[a + j], *FIXED], plan, *made[j]) for j, plan in enumerate(plans)], ends


def texts(numbers: list[int], hays: list[list[str]], passages: list[list[str]], tasks: tuple[str, ...], depths: tuple[float, ...], length: int):
    """(task, depth, number, words, answer words, MD5 of the words with blanks between) of every probe."""
    for few, _ in _few(numbers, hays, passages, tasks, depths, length):
        for number, words, plan, names, rows in few:
            made = _text(names, rows)
            for j, (task, depth) in enumerate(plan.names):
                text = " ".join(plan.words[j]([*words, *names.pick[j](made)]))
                yield task, depth, number, plan.size[j], plan.held[j], hashlib.md5(text.encode()).hexdigest()


@lru_cache(maxsize=LAYOUTS)
def _far(tasks: tuple[str, ...], depths: tuple[float, ...], length: int, haystack: int, passage: int, k: int) -> tuple[Layout, list[tuple[np.ndarray, np.ndarray] | None]]:
    """The layout, and for its probes of one question and one answer the far words in the order of their first places (a
    probe with fewer repeats its first), and whether the answer stands there."""
    plan, out = layout(tasks, depths, length, haystack, passage), []
    for x in plan.alike:
        if x.asked.shape[1] > 1 or x.answers > 1 or int(x.query.min()) - k + 1 < 1:
            out.append(None)
            continue
        found = []
        for ids, span, query in zip(x.ids, x.span, x.query[:, 0], strict=True):
            words, places = np.unique(ids[: query - k + 1], return_index=True)
            order = np.argsort(places)
            found.append((words[order], span[places[order]] >= 0))
        most = max(len(words) for words, _ in found)
        fill = lambda v: np.concatenate([v, np.repeat(v[:1], most - len(v))])
        out.append((np.stack([fill(words) for words, _ in found]), np.stack([fill(good) for _, good in found])))
    return plan, out


@dataclass(frozen=True)
class Seeds:
    """Messages whose hashes are the made-up words that the probes use, as ``md5_columns`` takes them, with zeros for the
    digits of a number: where these stand, rows by the form of their word, and the row of each word of each probe."""

    columns: list
    rows: int
    digits_at: list[tuple[int, int, int]]
    forms: list[tuple[str, int, int]]
    of: list[np.ndarray]


@lru_cache(maxsize=4 * LAYOUTS)
def _seeds(names: tuple[tuple[str, float], ...], pairs: tuple[int, ...], used: tuple[tuple[int, ...], ...], digits: int) -> Seeds:
    whole = _names(names, pairs, digits)
    kept = np.unique(np.concatenate([of[list(slots)] for of, slots in zip(whole.of, used, strict=True)]))
    kept = kept if len(kept) else np.zeros(1, np.int64)
    row = np.zeros(len(whole.rows), np.int64)
    row[kept] = np.arange(len(kept))
    cut = lambda marks: [(m, int(x), int(y)) for m, a, b in marks if (y := np.searchsorted(kept, b)) > (x := np.searchsorted(kept, a))]
    digits_at = [(a, b, at) for at, a, b in cut([(at, a, b) for a, b, at in whole.digits_at])]
    held = whole.rows[kept]
    for a, b, at in digits_at:
        held[a:b, at : at + digits] = 0
    touched = {(at + i) // 4 for *_, at in digits_at for i in range(digits)}
    words = np.ascontiguousarray(held.view("<u4").T)
    columns = [w if j in touched or (w != w[0]).any() else int(w[0]) for j, w in enumerate(words)]
    return Seeds(columns, len(kept), digits_at, cut(whole.forms), [row[of] for of in whole.of])


_HEX4 = np.ascontiguousarray(np.concatenate([np.tile(_HEX, (256, 1)), np.repeat(_HEX, 256, axis=0)], axis=1)).view("<u4").ravel()
_HEX2 = np.ascontiguousarray(_HEX).view("<u2").ravel().astype(np.uint32)
_DEC4 = np.frombuffer(b"".join(b"%04d" % i for i in range(10_000)), "<u4")
_DEC2 = np.frombuffer(b"".join(b"%02d" % i for i in range(100)), "<u2").astype(np.uint32)
_KEY, _VALU, _E = (int.from_bytes(x, "little") for x in (b"key-", b"valu", b"e-"))
#: The two digits of each byte, see ``hexdot_digits``.
_DIGITS = np.array([[2 * (i >> 4) - 15, 2 * (i & 15) - 15] for i in range(256)], np.float32).view(np.uint64).ravel()


def _vectors(hashes: list[np.ndarray], D: int) -> np.ndarray:
    """``hexdot_digits`` of hashes in columns."""
    held = np.stack(hashes, axis=1).astype("<u4", copy=False).view(np.uint8)[:, : -(-D // 2)]
    return _DIGITS[held].view(np.float32)[:, :D]


def _made_vectors(seeds: Seeds, numbers: list[int], D: int) -> np.ndarray:
    """Vectors (numbers x rows x D) of the made-up words for numbers of as many digits."""
    shape = (len(numbers), seeds.rows)
    columns = [x if isinstance(x, int) else np.tile(x, (len(numbers), 1)) for x in seeds.columns]
    shown = np.array([list(str(n).encode()) for n in numbers], np.uint32)
    for a, b, at in seeds.digits_at:
        for i in range(shown.shape[1]):
            columns[(at + i) // 4][:, a:b] += (shown[:, i] << np.uint32(8 * ((at + i) % 4)))[:, None]
    flat = lambda columns: [x if isinstance(x, int) else x.reshape(-1) for x in columns]
    hashed = [x.reshape(shape) for x in md5_columns(flat(columns), shape[0] * shape[1])]
    words: list = [np.zeros(shape, np.uint32) for _ in range(10)] + [0] * 4 + [np.zeros(shape, np.uint32), 0]
    for form, x, y in seeds.forms:
        a, b, c, d = (h[:, x:y] for h in hashed)
        low, pair = np.uint32(0xFFFF), lambda p, q: _HEX4[(p >> np.uint32(24)) | ((q & np.uint32(255)) << np.uint32(8))]
        inner = lambda p: _HEX4[(p >> np.uint32(8)) & np.uint32(0xFFFF)]
        if form == "key-6":
            made = [_KEY, _HEX4[a & low], _HEX2[(a >> np.uint32(16)) & np.uint32(255)] | np.uint32(0x800000)]
        elif form == "key-12":
            made = [_KEY, _HEX4[a & low], _HEX4[a >> np.uint32(16)], _HEX4[b & low], 0x80]
        elif form == "value-hex":
            made = [_VALU, (_HEX2[a & np.uint32(255)] << np.uint32(16)) | np.uint32(_E), inner(a), pair(a, b), inner(b), pair(b, c), inner(c), pair(c, d), inner(d), _HEX2[d >> np.uint32(24)] | np.uint32(0x800000)]
        else:
            n = (a.byteswap().astype(np.uint64) << np.uint64(16)) | (b.byteswap() >> np.uint32(16))
            n = (n - n // np.uint64(10**7) * np.uint64(10**7)).astype(np.uint32)
            high = n // np.uint32(10**5)
            n -= high * np.uint32(10**5)
            middle = n // np.uint32(10)
            n -= middle * np.uint32(10)
            made = [_VALU, (_DEC2[high] << np.uint32(16)) | np.uint32(_E), _DEC4[middle], n | np.uint32(0x8030)]
        for j, w in enumerate(made):
            words[j][:, x:y] = w
        words[14][:, x:y] = 8 * sum(_WIDTH[form][1:], len(_WIDTH[form][0]))
    return _vectors(md5_columns(flat(words), shape[0] * shape[1]), D).reshape(*shape, D)


def hits(numbers: list[int], hays: list[list[str]], passages: list[list[str]], tasks: tuple[str, ...], depths: tuple[float, ...], length: int, D: int, spread: float, k: int):
    """(number, names of the probes, hits) of every haystack under the hexdot profile; haystacks of one size come together."""
    scale, alike = 4 * spread * spread * D**0.5, {}
    for i, (n, h, p) in enumerate(zip(numbers, hays, passages, strict=True)):
        alike.setdefault((len(h), len(p), len(str(n))), []).append(i)
    for (hay, passage, digits), rows in alike.items():
        plan, far = _far(tasks, depths, length, hay, passage, k)
        seeds = _seeds(plan.names, plan.pairs, plan.used, digits)
        for a in range(0, len(rows), TOGETHER):
            some = rows[a : a + TOGETHER]
            made = _made_vectors(seeds, [numbers[i] for i in some], D)
            digests = b"".join([_digest(w) for i in some for w in (*hays[i], *passages[i], *FIXED)])
            known = hexdot_digits(np.frombuffer(digests, np.uint8).reshape(-1, 16), D).reshape(len(some), -1, D)
            out = np.empty((len(some), len(plan.names)))
            for x, short in zip(plan.alike, far, strict=True):
                out[:, x.probes] = _hits(x, short, plan.made, known, made[:, np.stack([seeds.of[j] for j in x.probes])], scale, k)
            for i, found in zip(some, out, strict=True):
                yield numbers[i], plan.names, found


def _hits(x: Alike, short: tuple[np.ndarray, np.ndarray] | None, first: int, known: np.ndarray, made: np.ndarray, scale: float, k: int) -> np.ndarray:
    """Hits (haystacks x probes) of probes that are alike; known (haystacks, words, D), made (haystacks, probes, words, D)."""
    n, h, asked = np.arange(len(x.ids)), np.arange(len(known))[:, None], x.asked
    own = made[:, n[:, None], np.maximum(0, asked - first)]
    if (asked < first).any():
        own = np.where((asked < first)[:, :, None], known[:, np.minimum(asked, known.shape[1] - 1)], own)
    questions = asked.shape[1]
    met = (own.reshape(len(known), -1, own.shape[3]) @ known.transpose(0, 2, 1)).reshape(len(known), len(n), questions, -1)
    dots = np.concatenate([met, own @ made.transpose(0, 1, 3, 2)], axis=3)
    if short is not None:
        # one question, one answer: its softmax has the order of the products, which are whole numbers, and a word's first place counts
        far_words, good = short
        best = dots[:, n[:, None], 0, far_words].argmax(axis=2)
        return good[n, best].astype(np.float64)
    at = np.arange(x.ids.shape[1])
    dots = dots[:, n[:, None, None], np.arange(questions)[:, None], np.maximum(0, x.ids)[:, None, :]]
    far = at[None, None, :] <= x.query[:, :, None] - k
    if questions == 1 and int(x.query.min()) - k + 1 >= x.answers:
        total = np.where(far, dots, -np.inf)[:, :, 0]
    else:
        seen = at[None, None, :] <= x.query[:, :, None]
        dots = np.where(seen, dots.astype(np.float64) / scale, -np.inf)
        w = np.exp(dots - dots.max(axis=3, keepdims=True))
        # equal words have equal shares to the last bit; places that only a shorter probe lacks come last
        total = np.where(at[None, :] <= x.query.max(axis=1)[:, None], (np.where(far, w, 0.0) / w.sum(axis=3, keepdims=True)).sum(axis=2), -1.0)
    met = np.zeros((len(known), len(n)), np.int64)
    for _ in range(x.answers):
        best = total.argmax(axis=2)
        span = x.span[n, best]
        met |= np.where(span >= 0, 1 << np.maximum(0, span), 0)
        total[h, n, best] = -np.inf
    return np.bitwise_count(met) / x.answers
