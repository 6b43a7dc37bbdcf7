"""Raw scores of windows, their standardisation, and the combined score."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from farspan.operators import kernel, skipgram
from farspan.operators.batches import coded, of_one_length
from farspan.operators.profiles import DotProfile, RowVectors, Vectors
from farspan.operators.ranks import ranked
from farspan.sources.intermediate import written

RAW = "doc_id long, category string, start long, len int, k int, profile string, ds double, du double, far_mean double, far_cells long, sink_share double, pair_ops long, cpu_ms double"
_FIELDS = ("len", "k", "ds", "du", "far_mean", "far_cells", "sink_share", "pair_ops", "cpu_ms")
#: Windows handled at once between JVM and Python; long windows are wide rows.
ROWS_AT_ONCE = 64
#: Windows whose words are looked at together, at most, if they have TOKENS_AT_ONCE tokens or fewer.
ROWS_TOGETHER, TOKENS_AT_ONCE = 1024, 1 << 17


def _arrow(columns: dict[str, list], schema: str) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "boolean": pa.bool_()}
    fields = [x.split() for x in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(columns[n], kinds[t]) for n, t in fields], names=[n for n, _ in fields])


def per_window(windows: DataFrame, compute, schema: str, tokens: str = "toks") -> DataFrame:
    """compute(token list) -> list of dicts, for every window; doc_id, category and start are put in front.

    schema names the computed columns only.
    """
    whole = "doc_id long, category string, start long, " + schema
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for a in range(0, big.num_rows, ROWS_AT_ONCE):
                batch = big.slice(a, ROWS_AT_ONCE)
                out: dict[str, list] = {n: [] for n in ("doc_id", "category", "start", *names)}
                keys = zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True)
                for key, toks in zip(keys, batch.column(3).to_pylist(), strict=True):
                    for row in compute(toks or []):
                        for n, v in zip(("doc_id", "category", "start"), key, strict=True):
                            out[n].append(v)
                        for n in names:
                            out[n].append(row[n])
                if out["doc_id"]:
                    yield _arrow(out, whole)

    return windows.select(F.col("doc_id").cast("long"), "category", F.col("start").cast("long"), tokens).mapInArrow(run, whole)


def _parts(batch: pa.RecordBatch, column: int) -> Iterator[pa.RecordBatch]:
    """Pieces of a batch with at most ROWS_TOGETHER rows and about TOKENS_AT_ONCE tokens in their lists; ROWS_AT_ONCE rows in any case."""
    a, sizes = 0, pc.fill_null(pc.list_value_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    upto = np.cumsum(sizes, dtype=np.int64)
    while a < batch.num_rows:
        fits = int(np.searchsorted(upto, TOKENS_AT_ONCE + upto[a] - sizes[a], side="right"))
        b = min(a + ROWS_TOGETHER, max(fits, a + ROWS_AT_ONCE))
        yield batch.slice(a, b - a)
        a = b


def per_batch(windows: DataFrame, compute, alone, schema: str, front: str | None = None) -> DataFrame:
    """``per_window`` for what is faster for many windows: compute(words, codes) -> a list of dicts for each of some windows of
    one length, from their tokens as numbers of words; alone(token list) for windows that are empty or too long for that."""
    whole = "doc_id long, category string, start long, " + schema
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for batch in _parts(big, 3):
                words, codes, ends = coded(batch.column(3))
                rows, found = [], []
                for some, at in of_one_length(codes, ends, ROWS_AT_ONCE * kernel.TOGETHER):
                    if front:
                        at = np.concatenate([np.full((len(at), 1), len(words)), at], axis=1)
                    some_words = [*words, front] if front else words
                    if 0 < at.shape[1] <= kernel.TOGETHER:
                        got = compute(some_words, at)
                    else:
                        got = [alone([some_words[i] for i in row]) for row in at.tolist()]
                    for row, each in zip(some.tolist(), got, strict=True):
                        rows += [row] * len(each)
                        found += each
                if rows:
                    taken = [batch.column(i).take(pa.array(rows)) for i in range(3)]
                    made = _arrow({n: [x[n] for x in found] for n in names}, schema)
                    yield pa.RecordBatch.from_arrays(taken + made.columns, names=["doc_id", "category", "start", *names])

    return windows.select(F.col("doc_id").cast("long"), "category", F.col("start").cast("long"), "toks").mapInArrow(run, whole)


def score_windows(windows: DataFrame, profile, ks: int | list[int], block: int = 128, var_over: str = "triangle", ddof: int = 0, head_agg: str = "mean", front: str | None = None) -> DataFrame:
    """raw_scores: one row per window, k and profile (one, or a list scored in one pass).  Map only; nothing of size L x L is held.

    ``front``: a special token put before every window, as language models do; it takes part like any other token.
    """
    ks = [ks] if isinstance(ks, int) else list(ks)
    listed = list(profile) if isinstance(profile, (list, tuple)) else [profile]
    schema = ", ".join(RAW.split(", ")[3:])
    named = lambda p, rows: [r | {"profile": p.name} for r in rows]
    if all(isinstance(p, DotProfile) and not isinstance(p, Vectors) for p in listed) and head_agg == "mean":

        def many(words: list[str], codes: np.ndarray) -> list[list[dict]]:
            found = [[named(p, r) for r in kernel.score_many(p, words, codes, ks, var_over, ddof)] for p in listed]
            return [sum(rows, []) for rows in zip(*found, strict=True)]

        return per_batch(windows, many, lambda t: [r for p in listed for r in named(p, kernel.score(p, t, ks, block, var_over, ddof))], schema, front)
    lead = [front] if front else []
    return per_window(windows, lambda t: [r for p in listed for r in named(p, kernel.score(p, lead + t, ks, block, var_over, ddof, head_agg))], schema)


def score_twins(windows: DataFrame, profiles: list[DotProfile], k: int) -> DataFrame:
    """profile, label and ds of windows (toks, label 1) and of their twins (label 0), whose last tokens are those of ``other``
    instead.  Twins are scored together: what comes before is the same."""
    schema = "profile string, label int, ds double"

    def alone(p: DotProfile, toks: list[str]) -> float:
        return kernel.score(p, toks, [k])[0]["ds"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for batch in _parts(big, 0):
                words, codes, ends = coded(pa.concat_arrays([batch.column(0), batch.column(1).cast(batch.column(0).type)]))
                lengths = np.diff(ends, prepend=0).reshape(2, -1)
                out: dict[str, list] = {"profile": [], "label": [], "ds": []}
                for L, t in np.unique(lengths, axis=1).T.tolist():
                    rows = np.flatnonzero((lengths[0] == L) & (lengths[1] == t))
                    own, tails = ((codes[(ends[at] - n)[:, None] + np.arange(n)]) for at, n in ((rows, L), (rows + batch.num_rows, t)))
                    for p in profiles:
                        if 0 < L <= kernel.TOGETHER:
                            found = [[r[0]["ds"] for r in one] for one in kernel.score_twins(p, words, own, tails, [k])]
                        else:
                            both = own.tolist(), np.concatenate([own[:, : L - t], tails], axis=1).tolist()
                            found = [[alone(p, [words[i] for i in row]) for row in one] for one in both]
                        for label, ds in zip((1, 0), found, strict=True):
                            out["profile"] += [p.name] * len(ds)
                            out["label"] += [label] * len(ds)
                            out["ds"] += ds
                yield _arrow(out, schema)

    return windows.select("toks", "other").mapInArrow(run, schema)


#: Words whose vectors every task holds, at most, if their occurrences are known.
KNOWN_WORDS = 1 << 18


def _known(vectors: DataFrame, values):
    """(least occurrences, broadcast): the commonest words' numbers and vectors, for every task."""
    at, many = None, 0
    for n, words in sorted(((r.n, r["count"]) for r in vectors.groupBy("n").count().collect()), reverse=True):
        if (many := many + words) > KNOWN_WORDS:
            break
        at = n
    common = vectors.where(F.col("n") >= at).select("word", "half").toArrow() if at is not None else None
    held = ({}, None) if common is None else ({w: i for i, w in enumerate(common.column("word").to_pylist())}, values(common.column("half")).astype(np.float16))
    return at, vectors.sparkSession.sparkContext.broadcast(held)


def score_with_vectors(windows: DataFrame, vectors: DataFrame, k: int, dim: int = 32, name: str = "corpus", block: int = 1024) -> DataFrame:
    """raw_scores under a table of token vectors (word, vector) of any size; unknown tokens are the zero vector.

    Windows are packed into blocks of about ``block`` where they are cut; each block meets the vectors of its own words, so a task
    holds no more than those.  If the table holds occurrences and halves (n, half: see ``skipgram``), the commonest words'
    vectors go to every task, and the others move as halves.
    """
    halves = {"n", "half"} <= set(vectors.columns)
    values = (lambda x: skipgram.from_halves(x.to_pylist(), dim)) if halves else (lambda x: x.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, dim))
    least, known = _known(vectors, values) if halves else (None, None)
    held = written(skipgram.blocks(windows, {"doc_id": "long", "category": "string", "start": "long"}, block, known=known), "window-blocks")
    rare = F.coalesce("rare", F.transform("words", lambda _, i: i))
    asked = held.select("block", F.explode(F.transform(rare, lambda i: F.struct(i.alias("at"), F.get("words", i).alias("word")))).alias("x")).select(F.col("block").alias("of"), "x.*")
    own = vectors.select("word", F.col("half" if halves else "vector").alias("vector"), *(["n"] if halves else []))
    own = own.where(F.col("n") < least) if least is not None else own
    met = asked.join(own.select("word", "vector"), "word").select("of", "at", "vector")
    scale = dim**0.5

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out: dict[str, list] = {x.split()[0]: [] for x in RAW.split(", ")}
        for one in left.to_pylist():
            words, codes, ends = skipgram.unpacked(one["packed"])
            table = np.zeros((len(words), dim))
            if right.num_rows:
                table[right.column("at").to_numpy()] = values(right.column("vector"))
            number, common = known.value if known is not None else ({}, None)
            if number:
                at = np.array([number.get(w, -1) for w in words], np.int64)
                table[at >= 0] = common[at[at >= 0]]
            profile = RowVectors(table * scale, dim, name)
            keys = [{"doc_id": d, "category": c, "start": s} for d, c, s in zip(one["doc_id"], one["category"], one["start"], strict=True)]
            for rows, at in of_one_length(codes, ends, ROWS_AT_ONCE * kernel.TOGETHER):
                for a in range(0, len(rows), ROWS_AT_ONCE):
                    some = at[a : a + ROWS_AT_ONCE]
                    if 0 < some.shape[1] <= kernel.TOGETHER:
                        rows_of, own = np.unique(some, return_inverse=True)
                        found = kernel.score_many(profile, rows_of, own.reshape(some.shape), [k])
                    else:
                        found = [kernel.score(profile, row, [k]) for row in some.tolist()]
                    for w, each in zip(rows[a : a + ROWS_AT_ONCE].tolist(), found, strict=True):
                        for row in each:
                            for c in out:
                                out[c].append(name if c == "profile" else keys[w][c] if c in keys[w] else row[c])
        return pa.Table.from_batches([_arrow(out, RAW)])

    return held.drop("words", "rare").groupBy("block").cogroup(met.groupBy("of")).applyInArrow(run, RAW)


def token_strength(windows: DataFrame, profile, k: int) -> DataFrame:
    """row_stats: one row per token; for inspection and tests."""

    def compute(toks: list) -> list[dict]:
        far, squares, _ = kernel.token_strengths(profile, toks, [k])
        return [{"q": i + 1, "ds_q": float(f), "s2_q": float(s)} for i, (f, s) in enumerate(zip(far[0, 0], squares[0, 0], strict=True))]

    return per_window(windows, compute, "q int, ds_q double, s2_q double")


def explain_window(windows: DataFrame, profile, k: int, doc_id: int, start: int) -> DataFrame:
    """Which tokens of one window look far."""
    one = windows.where((F.col("doc_id") == doc_id) & (F.col("start") == start))
    return token_strength(one, profile, k).join(one.select("doc_id", "start", F.posexplode("toks").alias("i", "tok")).withColumn("q", F.col("i") + 1).drop("i"), ["doc_id", "start", "q"])


def score_sampled(windows: DataFrame, profile, k: int, rows: int = 256) -> DataFrame:
    return per_window(windows, lambda t: [kernel.score_sampled(profile, t, k, rows)], "ds_hat double, du_hat double, se double, rows int")


def _spread(x: Column, ddof: int) -> Column:
    return F.stddev_samp(x) if ddof else F.stddev_pop(x)


def moments(raw: DataFrame, scope: str = "global", ddof: int = 0) -> DataFrame:
    """n, means and deviations of both scores: one row, or one a category."""
    ds, du = F.col("ds"), F.col("du")
    sums = [F.count("*").alias("n"), F.avg(ds).alias("ds_mean"), _spread(ds, ddof).alias("ds_sd"), F.avg(du).alias("du_mean"), _spread(du, ddof).alias("du_sd")]
    if scope == "category":
        return raw.groupBy(F.col("category").alias("scope")).agg(*sums)
    return raw.agg(*sums).select(F.lit("global").alias("scope"), "*")


def merge_moments(parts: DataFrame) -> DataFrame:
    """Moments of a union from the moments of its parts (population deviations)."""
    n = F.sum("n")

    def mean(x: str) -> Column:
        return F.sum(F.col("n") * F.col(f"{x}_mean")) / n

    def sd(x: str) -> Column:
        second = F.sum(F.col("n") * (F.col(f"{x}_sd") ** 2 + F.col(f"{x}_mean") ** 2)) / n
        return F.sqrt(F.greatest(F.lit(0.0), second - mean(x) ** 2))

    return parts.groupBy("scope").agg(n.alias("n"), mean("ds").alias("ds_mean"), sd("ds").alias("ds_sd"), mean("du").alias("du_mean"), sd("du").alias("du_sd"))


def z(x: Column, mean: Column, sd: Column) -> Column:
    """Standard score; 0 where the spread is 0."""
    return F.when(sd > 0, (x - mean) / sd).otherwise(0.0)


def standardize(raw: DataFrame, scope: str = "global", ddof: int = 0, method: str = "moments", known: DataFrame | None = None) -> DataFrame:
    """raw with ds_z and du_z.  The moments are one row, or one a category, and are broadcast.

    method 'robust' uses median and 1.4826 times the median absolute deviation (by sketch).
    """
    if method == "robust":
        keys = [F.col("category").alias("scope")] if scope == "category" else [F.lit("global").alias("scope")]
        mid = raw.groupBy(*keys).agg(*[F.percentile_approx(x, 0.5, 10_000).alias(f"{x}_mean") for x in ("ds", "du")])
        near = raw.join(F.broadcast(mid), raw["category"] == mid["scope"]) if scope == "category" else raw.join(F.broadcast(mid), F.lit(True))
        away = near.groupBy("scope").agg(*[(1.4826 * F.percentile_approx(F.abs(F.col(x) - F.col(f"{x}_mean")), 0.5, 10_000)).alias(f"{x}_sd") for x in ("ds", "du")])
        stats = mid.join(away, "scope")
    else:
        stats = known if known is not None else moments(raw, scope, ddof)
    stats = stats.select(F.col("scope").alias("of"), "ds_mean", "ds_sd", "du_mean", "du_sd")
    joined = raw.join(F.broadcast(stats), raw["category"] == stats["of"]) if scope == "category" else raw.join(F.broadcast(stats), F.lit(True))
    c = F.col
    out = joined.withColumns({"ds_z": z(c("ds"), c("ds_mean"), c("ds_sd")), "du_z": z(c("du"), c("du_mean"), c("du_sd"))})
    return out.drop("of", "ds_mean", "ds_sd", "du_mean", "du_sd")


def combine(scored: DataFrame, alpha: float = 0.5) -> DataFrame:
    """lds = strength + alpha x uniformity, both standardised."""
    return scored.withColumn("lds", F.col("ds_z") + F.lit(alpha) * F.col("du_z"))


def alpha_sweep(scored: DataFrame, alphas: list[float]) -> DataFrame:
    """One row per window and alpha, from one pass over the scores."""
    return scored.withColumn("alpha", F.explode(F.array(*[F.lit(a) for a in alphas]))).withColumn("lds", F.col("ds_z") + F.col("alpha") * F.col("du_z"))


def magnitudes(scored: DataFrame) -> DataFrame:
    """Distribution of both scores before and after standardising; quartiles are exact, interpolated between ranks."""
    long = scored.select(F.expr("stack(4, 'ds', ds, 'du', du, 'ds_z', ds_z, 'du_z', du_z) as (score, x)"))
    whole = long.groupBy("score").agg(F.count("*").alias("n"), F.min("x").alias("low"), F.max("x").alias("high"), F.stddev_pop("x").alias("sd"))
    names, c = {"q1": 0.25, "mid": 0.5, "q3": 0.75}, F.col
    found = ranked(long, "score", c("x"), [c("x")]).join(F.broadcast(whole.select("score", "n")), "score")
    # a row counts for a quartile by how near its rank is to the wanted one
    share = lambda p: F.greatest(F.lit(0.0), 1 - F.abs((c("n") - 1) * p + 1 - c("rnk")))
    near = found.groupBy("score").agg(*[F.sum(c("x") * share(p)).alias(q) for q, p in names.items()])
    return whole.join(near, "score").select("score", "n", "low", "q1", "mid", "q3", "high", "sd")


def by_document(lds: DataFrame) -> DataFrame:
    return lds.groupBy("doc_id", "category").agg(F.count("*").alias("windows"), F.avg("lds").alias("mean_lds"), F.max("lds").alias("best_lds"), F.max_by("start", F.struct("lds", -F.col("start"))).alias("best_start"))


def smoothed(strengths: DataFrame, width: int) -> DataFrame:
    """Token strengths averaged over their neighbours."""
    near = Window.partitionBy("doc_id", "start").orderBy("q").rowsBetween(-width, width)
    return strengths.withColumn("smooth", F.avg("ds_q").over(near))
