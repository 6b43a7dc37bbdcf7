"""The selectors that attention is compared with: segment perplexity and linguistic measures.

The segment scorer is a reconstruction from its two named ingredients, relative perplexity and distance.
"""

from __future__ import annotations

import math
import re
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farspan.sources.intermediate import written
from farspan.operators import kernel
from farspan.operators.batches import of_one_length
from farspan.operators.score import per_window


def background(windows: DataFrame, order: int = 1) -> DataFrame:
    """Counts of tokens (order 1) or of neighbouring pairs (order 2) over all windows: tok, c."""
    if order == 1:
        return windows.select(F.explode("toks").alias("tok")).groupBy("tok").agg(F.count("*").alias("c"))
    pairs = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("toks") - 1)), lambda i: F.concat_ws("\u0001", F.try_element_at("toks", i), F.try_element_at("toks", i + 1)))
    return windows.where(F.size("toks") > 1).select(F.explode(pairs).alias("tok")).groupBy("tok").agg(F.count("*").alias("c"))


def segments(windows: DataFrame, length: int) -> DataFrame:
    """(doc_id, category, start, s, tok, c): token counts of the full segments of each window."""
    at = windows.select("doc_id", "category", "start", F.floor(F.size("toks") / length).alias("m"), F.posexplode("toks").alias("i", "tok"))
    held = at.withColumn("s", F.floor(F.col("i") / length)).where("s < m")
    return held.groupBy("doc_id", "category", "start", "s", "tok").agg(F.count("*").alias("c"))


def segment_pairs(windows: DataFrame, length: int = 32, beta: float = 0.3) -> DataFrame:
    """seg_pairs: for each later segment si and earlier sj, perplexity of si without and with sj as context.

    P(w | sj) mixes the corpus's add-one unigrams with sj's own counts, so only shared words need a join.
    """
    counts = background(windows)
    size = counts.agg(F.sum("c").alias("n"), F.count("*").alias("v"))
    seg = segments(windows, length).join(counts.withColumnRenamed("c", "corpus"), "tok").join(F.broadcast(size), F.lit(True))
    seg = seg.withColumn("p0", (F.col("corpus") + 1) / (F.col("n") + F.col("v")))
    alone = seg.groupBy("doc_id", "category", "start", "s").agg(F.sum(F.col("c") * F.log("p0")).alias("l0"))
    left = alone.select("doc_id", "category", "start", F.col("s").alias("si"), "l0")
    right = alone.select("doc_id", "start", F.col("s").alias("sj"))
    pairs = left.join(right, ["doc_id", "start"]).where("sj < si")
    a = seg.select("doc_id", "start", F.col("s").alias("si"), "tok", F.col("c").alias("ci"), "p0")
    b = seg.select("doc_id", "start", F.col("s").alias("sj"), "tok", F.col("c").alias("cj"))
    lift = F.log1p(F.col("cj") * beta / (F.col("p0") * (length * (1 - beta))))
    shared = a.join(b, ["doc_id", "start", "tok"]).where("sj < si").groupBy("doc_id", "start", "si", "sj").agg(F.sum(F.col("ci") * lift).alias("gain_sum"))
    out = pairs.join(shared, ["doc_id", "start", "si", "sj"], "left").fillna(0.0, ["gain_sum"])
    given = F.col("l0") + length * math.log(1 - beta) + F.col("gain_sum")
    ppl, cond = F.exp(-F.col("l0") / length), F.exp(-given / length)
    return out.select("doc_id", "category", "start", "si", "sj", ppl.alias("ppl"), cond.alias("ppl_given"), ((ppl - cond) / ppl).alias("gain"), (F.col("si") - F.col("sj")).alias("hops"))


COMBINED = {"product": lambda gain, dist: gain * dist, "gain": lambda gain, dist: gain, "dist": lambda gain, dist: dist, "sum": lambda gain, dist: gain + dist}
#: Repeated units whose counts are broadcast (12 bytes each), at most; beyond, the counts meet the windows in a shuffle.
HEAD = 1 << 22
#: Windows whose units are looked up together, and pairs of their tokens in memory at a time.
ROWS, CELLS = 256, 1 << 20
_LOCAL = "len int, spb double, model_calls long, cpu_ms double"


def _bags(toks: list[str], length: int, order: int) -> tuple[list[str], np.ndarray]:
    """Distinct units of the full segments, and how often each segment holds them (segments x units)."""
    m = len(toks) // length
    held = toks[: m * length]
    units = held if order == 1 else [f"{'' if i % length == 0 else held[i - 1]}\u0001{t}" for i, t in enumerate(held)]
    names = {u: i for i, u in enumerate(dict.fromkeys(units))}
    at = np.fromiter((names[u] for u in units), np.int64, len(units))
    cells = np.repeat(np.arange(m), length) * len(names) + at
    return list(names), np.bincount(cells, minlength=m * len(names)).reshape(m, len(names)).astype(np.float64)


def _scored_locally(toks: list[str], counts, total: int, types: int, length: int, beta: float, order: int, hows: tuple[str, ...] = ("product",)) -> list[dict]:
    """Mean over the segment pairs of positive relative perplexity gain and relative distance, combined.

    All pairs at once: what segment i gains from segment j is a product of two segment x unit matrices.
    """
    began = time.process_time()
    names, bag = _bags(toks, length, order)
    m = len(bag)
    if m < 2:
        return []
    p0 = (np.array([counts.get(u, 0) for u in names], np.float64) + 1) / (total + types)
    alone = bag @ np.log(p0)
    more = bag @ np.log1p(bag * (beta / (p0 * (length * (1 - beta))))).T
    i, j = np.tril_indices(m, -1)
    # (perplexity alone - perplexity given j) / perplexity alone
    gain = np.maximum(0.0, 1 - np.exp(-(length * math.log(1 - beta) + more[i, j]) / length))
    dist = (i - j) / m
    row = {"len": len(toks), "model_calls": len(gain)} | {f"spb_{h}" if len(hows) > 1 else "spb": float(COMBINED[h](gain, dist).mean()) for h in hows}
    return [row | {"cpu_ms": (time.process_time() - began) * 1e3}]


def segment_scores_local(windows: DataFrame, counts: dict[str, int], length: int = 32, beta: float = 0.3, order: int = 1) -> DataFrame:
    """The score window by window, pairs never leaving the task; ``counts``: a whole background that is small.

    order 2 conditions each token on its left neighbour as well (the larger stand-in model).
    """
    total, types = sum(counts.values()), len(counts)
    return per_window(windows, lambda toks: _scored_locally(toks, counts, total, types, length, beta, order), _LOCAL)


def _scored_together(codes: np.ndarray, counts: np.ndarray, total: int, types: int, length: int, beta: float, hows: tuple[str, ...]) -> list[np.ndarray]:
    """``_scored_locally`` of windows of one size (windows x units, numbers of units and their counts): what segment i gains
    from segment j is summed over i's tokens, by how often each stands in j."""
    n, m = len(codes), codes.shape[1] // length
    factor = beta / ((counts + 1.0) / (total + types) * (length * (1 - beta)))
    more = np.zeros((n, m, m))
    for i in range(1, m):
        own = slice(i * length, (i + 1) * length)
        step = max(1, CELLS // (length * i * length))
        for a in range(0, n, step):
            same = codes[a : a + step, own, None] == codes[a : a + step, None, : i * length]
            times = same.view(np.uint8).reshape(len(same), length, i, length).sum(axis=3, dtype=np.uint8 if length < 256 else np.int64)
            more[a : a + step, i, :i] = np.log1p(times * factor[a : a + step, own, None]).sum(axis=1)
    i, j = np.tril_indices(m, -1)
    gain = np.maximum(0.0, 1 - np.exp(-(length * math.log(1 - beta) + more[:, i, j]) / length))
    dist = np.broadcast_to((i - j) / m, gain.shape)
    return [COMBINED[h](gain, dist).mean(axis=1) for h in hows]


def _segment_scores_by_code(windows: DataFrame, units: Column, repeated: DataFrame, total: int, types: int, length: int, beta: float, order: int, hows: tuple[str, ...], schema: str) -> DataFrame:
    """Units as 64-bit hashes that no two of them share, with the counts of repeated ones broadcast: a unit that isn't there
    was seen once, and the first one of a segment at order 2 never."""
    rows = repeated.select(F.xxhash64("tok").alias("code"), F.col("c").cast("int").alias("c")).toArrow()
    code, c = (rows[x].to_numpy() for x in ("code", "c"))
    by_code = np.argsort(code)
    table = windows.sparkSession.sparkContext.broadcast((code[by_code], c[by_code]))
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, held = table.value
        for big in batches:
            for at in range(0, big.num_rows, ROWS):
                batch, began = big.slice(at, ROWS), time.process_time()
                flat = batch.column(3).flatten().to_numpy(zero_copy_only=False)
                ends = np.cumsum(pc.fill_null(pc.list_value_length(batch.column(3)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
                met, place = np.unique(flat, return_inverse=True)
                found = np.minimum(np.searchsorted(keys, met), max(0, len(keys) - 1))
                counts = (np.where(keys[found] == met, held[found], 1) if len(keys) else np.ones(len(met), np.int32))[place]
                taken, scored = [], []
                for (some, codes), (_, known) in zip(of_one_length(flat, ends, len(flat) + 1), of_one_length(counts, ends, len(flat) + 1), strict=True):
                    if codes.shape[1] < 2 * length:
                        continue
                    if order == 2:
                        known[:, ::length] = 0
                    taken.append(some)
                    if codes.shape[1] <= kernel.TOGETHER:
                        scored.append(np.stack(_scored_together(codes, known, total, types, length, beta, hows)))
                    else:
                        alone = [_scored_locally(x.tolist(), dict(zip(x.tolist(), y.tolist(), strict=True)), total, types, length, beta, 1, hows)[0] for x, y in zip(codes, known, strict=True)]
                        scored.append(np.array([[r[h] for r in alone] for h in names[1:-2]]))
                if taken:
                    some = np.concatenate(taken)
                    segments = np.diff(ends, prepend=0)[some] // length
                    spent = (time.process_time() - began) * 1e3 / len(some)
                    columns = [batch.column(i).take(pa.array(some)) for i in (0, 1, 2, 4)]
                    columns += [*map(pa.array, np.concatenate(scored, axis=1)), pa.array(segments * (segments - 1) // 2), pa.array(np.full(len(some), spent))]
                    yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "category", "start", *names])

    codes = F.transform(units, lambda u: F.xxhash64(u)).alias("codes")
    return windows.select(F.col("doc_id").cast("long"), "category", F.col("start").cast("long"), codes, F.size("toks").alias("len")).mapInArrow(run, "doc_id long, category string, start long, " + schema)


def segment_scores(windows: DataFrame, length: int = 32, beta: float = 0.3, how: str | tuple[str, ...] = "product", order: int = 1) -> DataFrame:
    """spb of every window (one column spb_<how> each, if ``how`` names several), against the whole background.

    Scoring is a map over the windows.  Units become 64-bit hashes, and the counts of up to HEAD repeated ones are broadcast; all
    others were seen once.  Beyond that, or if two units share a hash, the units of the windows
    meet their counts in a shuffle and each window gets its own; the background is written first, as its sums and the
    join read it, so both sides of the join are shuffled and a common unit can be split.
    """
    hows = (how,) if isinstance(how, str) else tuple(how)
    schema = _LOCAL if len(hows) == 1 else _LOCAL.replace("spb double", ", ".join(f"spb_{h} double" for h in hows))
    counts = written(background(windows, order), f"background{order}")
    total, types, repeated, most = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*"), F.count_if(F.col("c") > 1), F.coalesce(F.max("c"), F.lit(0))).first()
    held = F.slice("toks", F.lit(1), (F.floor(F.size("toks") / length) * length).cast("int"))
    before = lambda i: F.when(i % length == 0, F.lit("")).otherwise(F.try_element_at("toks", i.cast("int")))
    units = held if order == 1 else F.transform(held, lambda t, i: F.concat(before(i), F.lit("\u0001"), t))
    if repeated <= HEAD and most < 1 << 31 and counts.select(F.count_distinct(F.xxhash64("tok"))).first()[0] == types:
        return _segment_scores_by_code(windows, units, counts.where("c > 1"), total, types, length, beta, order, hows, schema)
    own = windows.select(F.col("doc_id").alias("d"), F.col("start").alias("s"), F.explode(F.array_distinct(units)).alias("tok"))
    met = own.join(counts, "tok").groupBy("d", "s").agg(F.collect_list(F.struct("tok", "c")).alias("known"))
    both = windows.join(met, F.col("doc_id").eqNullSafe(F.col("d")) & F.col("start").eqNullSafe(F.col("s")), "left")

    def compute(row: dict) -> list[dict]:
        known = {x["tok"]: x["c"] for x in row["known"] or []}
        return _scored_locally(row["toks"] or [], known, total, types, length, beta, order, hows)

    return per_window(both.withColumn("both", F.struct("toks", "known")), compute, schema, "both")


#: What ends a unit: so many tokens; a token that ends like a sentence; a token before a line break (mode "lines").
UNITS = ("tokens", "sentences", "paragraphs")
LINE_MARK = "\u2029"
_SENTENCE_END = re.compile(r"[.!?\u2026][\"')\]\u00bb\u201d\u2019]*$")


def _unit_numbers(toks: list[str], units: str, length: int) -> np.ndarray:
    if units == "tokens":
        return np.arange(len(toks)) // length
    ends = (t.endswith(LINE_MARK) if units == "paragraphs" else bool(_SENTENCE_END.search(t.rstrip(LINE_MARK))) for t in toks)
    last = np.fromiter(ends, bool, len(toks))
    return np.concatenate([[0], np.cumsum(last)[:-1]])


def linguistic(windows: DataFrame, unit: int = 32, units: str = "tokens") -> DataFrame:
    """complexity (share of distinct words, entropy of words), coherence (mean cosine of neighbouring units' counts) and
    cohesion (mean share of a unit's distinct words found in the unit before); a map over the windows.

    units: pieces of ``unit`` tokens, sentences, or paragraphs (for windows tokenised in mode "lines").
    """
    if units not in UNITS:
        raise ValueError(f"units must be one of {UNITS}")

    def compute(toks: list[str]) -> list[dict]:
        if not toks:
            return []
        words = [t.rstrip(LINE_MARK) for t in toks]
        names = {w: i for i, w in enumerate(dict.fromkeys(words))}
        at = np.fromiter((names[w] for w in words), np.int64, len(words))
        share = np.bincount(at) / len(at)
        cells, count = np.unique(_unit_numbers(toks, units, unit) * len(names) + at, return_counts=True)
        u, w = cells // len(names), cells % len(names)
        m = int(u[-1]) + 1
        norm, types = np.sqrt(np.bincount(u, count * count, m)), np.bincount(u, minlength=m)
        # a cell meets that of the same word in the unit before
        place = np.searchsorted(cells, cells - len(names))
        met = (u > 0) & (cells[np.minimum(place, len(cells) - 1)] == cells - len(names))
        dot = np.bincount(u[met], count[met] * count[place[met]], m)[1:]
        common = np.bincount(u[met], minlength=m)[1:]
        near = {"coherence": float((dot / (norm[1:] * norm[:-1])).mean()), "cohesion": float((common / types[1:]).mean())} if m > 1 else {"coherence": 0.0, "cohesion": 0.0}
        return [{"type_token": len(names) / len(at), "entropy": float(-(share * np.log(share)).sum()), "units": m} | near]

    return per_window(windows, compute, "type_token double, entropy double, units int, coherence double, cohesion double")
