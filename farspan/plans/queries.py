"""Registered queries: methods, variants, baselines and workloads over the given tables; README lists what is missing.

Window length 128 and far distance 32 (a quarter) stand for the published 32,768 and 8,192, as no document of the
given tables is that long in words.
"""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from farspan.functions.columns import scaled
from farspan.operators import baselines, cells, evaluate, profiles, score, select, windows
from farspan.sources import tables
from farspan.sources.intermediate import written

L, K = 128, 32
Query = Callable[[SparkSession, str], DataFrame]


def tok(spark: SparkSession, d: str, mode: str = "word") -> DataFrame:
    return windows.tokenize(tables.read_corpus(spark, d), mode)


def win(spark: SparkSession, d: str, L: int = L) -> DataFrame:
    """Windows of all documents; the text rows of a small table, whose scan is one task, are dealt over the cores."""
    long = windows.spread(windows.long_only(tables.read_corpus(spark, d), L))
    return windows.cut(windows.tokenize(long), L)


def raw(spark: SparkSession, d: str, profile=None, k: int | list[int] = K, **more) -> DataFrame:
    return score.score_windows(win(spark, d), profile or profiles.HexDot(), k, **more)


def standard(spark: SparkSession, d: str) -> DataFrame:
    """Raw scores with z-scores.  Scores are written: ranking, counting and joining read them more than once."""
    return score.standardize(written(raw(spark, d).drop("cpu_ms"), "raw"))


def combined(spark: SparkSession, d: str, alpha: float = 0.5) -> DataFrame:
    return score.combine(standard(spark, d), alpha)


def budget(counts: dict[str, int], step: int) -> int:
    return step * select.unit_tokens(sum(counts.values()), L)


def best(scored: DataFrame, step: int, column: str = "lds", method: str = "attention") -> DataFrame:
    return select.top_by_budget(scored, budget(select.category_counts(scored), step), L, column, method)


# --- preprocessing ------------------------------------------------------------------------------------------


def doc_tokens(s: SparkSession, d: str) -> DataFrame:
    return tok(s, d).select("doc_id", "category", "n")


def window_spans(s: SparkSession, d: str) -> DataFrame:
    return windows.spans(tok(s, d), L)


def window_spans_char32k(s: SparkSession, d: str) -> DataFrame:
    """The published constants, with code points as tokens."""
    docs = windows.long_only(tables.read_corpus(s, d), 32_768, "char").select("doc_id", "category", F.col("n_chars").cast("long").alias("n"))
    return windows.spans(docs, 32_768)


def window_branch_counts(s: SparkSession, d: str) -> DataFrame:
    n = F.col("n")
    count = F.when(n >= L, F.ceil(n / L)).otherwise(0)
    return tok(s, d).groupBy("category", windows.branch(n, L).alias("branch")).agg(F.count("*").alias("documents"), F.sum(count).cast("long").alias("windows"))


def window_coverage(s: SparkSession, d: str) -> DataFrame:
    return windows.coverage(tok(s, d), L)


def naive_truncate(s: SparkSession, d: str) -> DataFrame:
    return windows.truncate(tok(s, d), L).select("doc_id", "category", F.md5(F.concat_ws(" ", "toks")).alias("h"))


def stride_windows(s: SparkSession, d: str) -> DataFrame:
    return windows.stride(tok(s, d), L, 64).select("doc_id", "start")


def concat_pack(s: SparkSession, d: str) -> DataFrame:
    """Short documents packed end to end: the text of every full window."""
    packed = windows.concat_pack(tok(s, d), L, 7)
    return packed.select("category", "bucket", F.col("bin").cast("long").alias("bin"), F.md5(F.concat_ws(" ", "toks")).alias("h"))


def clean_documents(s: SparkSession, d: str) -> DataFrame:
    """Documents that are neither blank nor mostly marks nor copies of one with a smaller id."""
    return windows.clean(tables.read_corpus(s, d)).select("doc_id")


# --- scores -------------------------------------------------------------------------------------------------


def attention_scores(s: SparkSession, d: str) -> DataFrame:
    return raw(s, d).select("doc_id", "category", "start", scaled(F.col("ds"), 6).alias("ds_e6"), scaled(F.col("du"), 9).alias("du_e9"), scaled(F.col("sink_share"), 6).alias("sink_e6"))


def attention_multi_k(s: SparkSession, d: str) -> DataFrame:
    return raw(s, d, k=[L // 8, L // 4, L // 2]).groupBy("k").agg(F.count("*").alias("windows"), F.round(F.avg("ds"), 6).alias("ds"), F.round(F.avg("du"), 9).alias("du"))


def token_strength(s: SparkSession, d: str) -> DataFrame:
    return score.token_strength(win(s, d), profiles.HexDot(), K).select("doc_id", "start", "q", scaled(F.col("ds_q"), 6).alias("ds_e6"))


def attention_variants(s: SparkSession, d: str) -> DataFrame:
    w, p, keys = win(s, d), profiles.HexDot(), ["doc_id", "start"]
    one = lambda name, **more: score.score_windows(w, p, K, **more).select(*keys, scaled(F.col("du"), 9).alias(name))
    return one("square_e9", var_over="square").join(one("token_e9", var_over="token"), keys).join(one("sample_e9", ddof=1), keys)


def cells_reference(s: SparkSession, d: str) -> DataFrame:
    found = cells.window_scores(win(s, d, 32), 8)
    return found.select("doc_id", "start", scaled(F.col("ds"), 6).alias("ds_e6"), scaled(F.col("ds_block"), 6).alias("ds_block_e6"), scaled(F.col("du"), 9).alias("du_e9"), scaled(F.col("off"), 9).alias("off_e9"))


def cumulative_attention(s: SparkSession, d: str) -> DataFrame:
    """Mean attention of the last token on the first m tokens."""
    upto = cells.cumulative_row(win(s, d, 32), 32)
    return upto.groupBy("m").agg(scaled(F.avg("a"), 6).alias("mean_e6"), F.count("*").alias("rows"))


def score_moments(s: SparkSession, d: str) -> DataFrame:
    r = written(raw(s, d).drop("cpu_ms"), "raw")
    both = score.moments(r).union(score.moments(r, "category"))
    return both.select("scope", "n", F.round("ds_mean", 6).alias("ds_mean"), F.round("ds_sd", 6).alias("ds_sd"), F.round("du_mean", 9).alias("du_mean"), F.round("du_sd", 9).alias("du_sd"))


def lds_scores(s: SparkSession, d: str) -> DataFrame:
    return combined(s, d).select("doc_id", "category", "start", *[F.round(c, 5).alias(c) for c in ("ds_z", "du_z", "lds")])


def lds_scores_by_category(s: SparkSession, d: str) -> DataFrame:
    z = score.combine(score.standardize(written(raw(s, d).drop("cpu_ms"), "raw"), "category"))
    return z.select("doc_id", "category", "start", F.round("lds", 5).alias("lds"))


def lds_scores_robust(s: SparkSession, d: str) -> DataFrame:
    z = score.combine(score.standardize(written(raw(s, d).drop("cpu_ms"), "raw"), method="robust"))
    return z.select("doc_id", "category", "start", F.round("lds", 5).alias("lds"))


def score_magnitudes(s: SparkSession, d: str) -> DataFrame:
    m = score.magnitudes(standard(s, d))
    return m.select("score", "n", *[F.round(c, 8).alias(c) for c in ("low", "q1", "mid", "q3", "high", "sd")])


def _unsigned_zero(x):
    """A mean that rounds to nothing is 0, whatever side it came from."""
    return F.when(x == 0, 0.0).otherwise(x)


def alpha_sweep(s: SparkSession, d: str) -> DataFrame:
    swept = score.alpha_sweep(standard(s, d), [0.0, 0.25, 0.5, 1.0, 2.0])
    return swept.groupBy("alpha").agg(F.count("*").alias("windows"), _unsigned_zero(F.round(F.avg("lds"), 6)).alias("mean_lds"), F.round(F.stddev_pop("lds"), 6).alias("sd_lds"), F.round(F.max("lds"), 5).alias("best_lds"))


def document_rollup(s: SparkSession, d: str) -> DataFrame:
    return score.by_document(combined(s, d)).select("doc_id", "category", "windows", F.round("mean_lds", 5).alias("mean_lds"), F.round("best_lds", 5).alias("best_lds"))


def score_sampled(s: SparkSession, d: str) -> DataFrame:
    """Error of the sampled-row estimator against the exact strength."""
    w, p = win(s, d), profiles.HexDot()
    exact = score.score_windows(w, p, K).select("doc_id", "start", "ds")
    met = score.score_sampled(w, p, K, 24).join(exact, ["doc_id", "start"])
    off = F.col("ds_hat") - F.col("ds")
    return met.agg(F.count("*").alias("windows"), F.round(F.sqrt(F.avg(off * off)), 6).alias("rmse"), F.round(F.avg(off), 6).alias("bias"), F.round(F.avg((F.abs(off) <= 2 * F.col("se")).cast("int")), 6).alias("within_2se"))


# --- selection ----------------------------------------------------------------------------------------------


def select_top_budget(s: SparkSession, d: str) -> DataFrame:
    return best(combined(s, d), 5).select("method", "budget_tokens", "category", "doc_id", "start", "rnk", "cum_tokens")


def select_by_threshold(s: SparkSession, d: str) -> DataFrame:
    z = combined(s, d)
    return select.top_by_threshold(z, budget(select.category_counts(z), 5), L).select("category", "doc_id", "start")


def select_no_category(s: SparkSession, d: str) -> DataFrame:
    z = combined(s, d)
    return select.top_by_budget(z, budget(select.category_counts(z), 5), L, quota="none").select("doc_id", "start", "rnk")


def select_random(s: SparkSession, d: str) -> DataFrame:
    w = win(s, d).drop("toks")
    return select.random_by_budget(w, budget(select.category_counts(w), 5), L).select("category", "doc_id", "start", "rnk")


def select_ladder(s: SparkSession, d: str) -> DataFrame:
    return select.ladder(combined(s, d), L)


def random_ladder(s: SparkSession, d: str) -> DataFrame:
    return select.ladder(win(s, d).drop("toks"), L, score=None, method="random")


def mix_short(s: SparkSession, d: str) -> DataFrame:
    w, t = win(s, d).drop("toks"), tok(s, d).drop("toks")
    picked = select.random_by_budget(w, budget(select.category_counts(w), 5), L)
    return select.mix_short(picked, t.where(F.col("n") < L), 0.1)


def spb_scores(s: SparkSession, d: str) -> DataFrame:
    return baselines.segment_scores(win(s, d)).select("doc_id", "category", "start", F.round("spb", 6).alias("spb"))


def spb_parts(s: SparkSession, d: str) -> DataFrame:
    """The segment scorer's ingredients alone, and their sum instead of their product."""
    parts = baselines.segment_scores(win(s, d), how=("gain", "dist", "sum"))
    return parts.select("doc_id", "start", *[F.round(f"spb_{h}", 6).alias(n) for h, n in (("gain", "gain"), ("dist", "dist"), ("sum", "both"))])


def spb_scores_pairs_order2(s: SparkSession, d: str) -> DataFrame:
    """The larger stand-in model, window by window, against the counts of all neighbouring pairs."""
    return baselines.segment_scores(win(s, d), order=2).select("doc_id", "category", "start", "len", F.round("spb", 6).alias("spb"), "model_calls")


def select_spb(s: SparkSession, d: str) -> DataFrame:
    return best(written(baselines.segment_scores(win(s, d)), "spb"), 5, "spb", "segments").select("category", "doc_id", "start", "rnk")


def linguistic_metrics(s: SparkSession, d: str) -> DataFrame:
    m = baselines.linguistic(win(s, d))
    return m.select("doc_id", "category", "start", *[F.round(c, 6).alias(c) for c in ("type_token", "entropy", "coherence", "cohesion")])


def linguistic_units(s: SparkSession, d: str) -> DataFrame:
    """The same over sentences and over paragraphs."""
    cut = windows.cut(windows.tokenize(windows.spread(windows.long_only(tables.read_corpus(s, d), L, "lines")), "lines"), L)
    one = lambda units: baselines.linguistic(cut, units=units).select(F.lit(units).alias("units"), "doc_id", "start", F.col("units").cast("long").alias("n_units"), *[F.round(c, 6).alias(c) for c in ("coherence", "cohesion")])
    return one("sentences").unionByName(one("paragraphs"))


# --- measures and experiments -------------------------------------------------------------------------------


def _steps(ladders: DataFrame) -> DataFrame:
    """A rung holds all windows of the rungs below it."""
    wanted = F.array(*[F.lit(x) for x in select.LADDER])
    return ladders.withColumn("step", F.explode(F.filter(wanted, lambda x: x >= F.col("step"))))


def label_rates(s: SparkSession, d: str) -> DataFrame:
    both = select_ladder(s, d).unionByName(random_ladder(s, d))
    rates = evaluate.label_rates(_steps(both), tables.table(s, d, "labels"), ["method", "step"])
    return rates.select("method", "step", "windows", "labelled", F.round("good", 6).alias("good"), F.round("toxic", 6).alias("toxic"))


def selection_agreement(s: SparkSession, d: str) -> DataFrame:
    a = evaluate.agreement(select_top_budget(s, d), select_random(s, d))
    return a.select("common", "either", F.round("jaccard", 9).alias("jaccard"))


def alpha_ablation(s: SparkSession, d: str) -> DataFrame:
    """Choices at alpha 1 and without the uniformity term against the default, at 3 and 5 units."""
    z, labels = standard(s, d), tables.table(s, d, "labels", "doc_id", "quality")
    counts, out = select.category_counts(z), None
    for step in (3, 5):
        pick = lambda a: select.top_by_budget(score.combine(z, a), budget(counts, step), L).select("doc_id", "start").join(z.select("doc_id", "start", "ds_z", "du_z"), ["doc_id", "start"])  # noqa: E731, B023
        base = pick(0.5)
        good = F.avg("quality")
        base_good = base.join(labels, "doc_id").agg(good.alias("g0"))
        for name, alpha in (("alpha_0.5", 0.5), ("alpha_1", 1.0), ("no_uniformity", 0.0)):
            own = pick(alpha)
            kept = own.join(base.select("doc_id", "start", F.lit(1).alias("k")), ["doc_id", "start"], "left")
            row = kept.agg(F.count("*").alias("windows"), F.count("k").alias("kept"), F.round(F.avg("ds_z"), 5).alias("mean_ds_z"), F.round(F.avg("du_z"), 5).alias("mean_du_z"))
            delta = own.join(labels, "doc_id").agg(good.alias("g")).join(F.broadcast(base_good), F.lit(True)).select(F.round(F.col("g") - F.col("g0"), 6).alias("good_delta"))
            row = row.join(F.broadcast(delta), F.lit(True)).select(F.lit(step).alias("step"), F.lit(name).alias("variant"), "windows", "kept", "mean_ds_z", "mean_du_z", "good_delta")
            out = row if out is None else out.unionByName(row)
    return out


def diversity(s: SparkSession, d: str) -> DataFrame:
    picks = select_top_budget(s, d).select("method", "doc_id", "start").unionByName(select_random(s, d).select(F.lit("random").alias("method"), "doc_id", "start"))
    found = evaluate.diversity(picks.join(win(s, d).select("doc_id", "category", "start", "toks"), ["doc_id", "start"]), "method")
    return found.select("method", "windows", "documents", "distinct_windows", "types", "tokens", F.round("largest_category", 6).alias("largest_category"), F.round("near_copies", 6).alias("near_copies"))


def select_random_threshold(s: SparkSession, d: str) -> DataFrame:
    w = win(s, d).drop("toks")
    return select.random_by_threshold(w, budget(select.category_counts(w), 5), L).select("category", "doc_id", "start")


def distinct_token_counts(s: SparkSession, d: str) -> DataFrame:
    """Tokens of all windows, and those counted once where windows overlap."""
    return select.distinct_tokens(win(s, d).drop("toks"))


def front_token_scores(s: SparkSession, d: str) -> DataFrame:
    """Scores with a special token before every window."""
    r = raw(s, d, front="<s>")
    return r.select("doc_id", "category", "start", "len", scaled(F.col("ds"), 6).alias("ds_e6"), scaled(F.col("du"), 9).alias("du_e9"), scaled(F.col("sink_share"), 6).alias("sink_e6"))


def piece_tokens(s: SparkSession, d: str) -> DataFrame:
    """Documents in pieces of a public subword model, and their windows of 512."""
    t = tok(s, d, "piece")
    return t.select("doc_id", "category", "n", F.md5(F.concat_ws(" ", "toks")).alias("h"), F.when(F.col("n") >= 512, F.ceil(F.col("n") / 512)).otherwise(0).cast("long").alias("windows"))


def profile_scores(s: SparkSession, d: str, name: str) -> DataFrame:
    """Combined scores under one of the named profiles, kept, as ranking reads them more than once."""
    return score.combine(score.standardize(written(raw(s, d, profiles.named(name)).drop("cpu_ms"), f"raw-{name}")))


def both_profiles(s: SparkSession, d: str) -> dict[str, DataFrame]:
    """``profile_scores`` of the small and the large profile, from one pass over the windows."""
    r = written(raw(s, d, [profiles.named(n) for n in ("small", "large")]).drop("cpu_ms"), "raw-both")
    return {n: score.combine(score.standardize(r.where(F.col("profile") == n))) for n in ("small", "large")}


def select_small(s: SparkSession, d: str) -> DataFrame:
    """The choices at 1, 3, 5, 10 (and 20) units by the small profile."""
    return select.ladder(profile_scores(s, d, "small"), L, method="attention_small")


def select_large(s: SparkSession, d: str) -> DataFrame:
    return select.ladder(profile_scores(s, d, "large"), L, method="attention_large")


#: Published sets, in units: random to 20, the scorers to 10; and those of the comparison at one scale.
SETS = {"random": select.LADDER} | dict.fromkeys(("segments", "attention_small", "attention_large"), (1, 3, 5, 10))
ONE_SCALE = {"random": (5, 10, 20)} | dict.fromkeys(("segments", "attention_small", "attention_large"), (5,))


def _all_rungs(s: SparkSession, d: str, sets: dict[str, tuple[int, ...]] = SETS) -> tuple[DataFrame, dict[str, DataFrame]]:
    """The choices of the data-scale comparison, each window with the least of its method's sets that takes it, and the
    scores behind them.  Only what the largest set of a method reaches is ranked."""
    spb = written(baselines.segment_scores(win(s, d)), "spb")
    scored = {f"attention_{name}": z for name, z in both_profiles(s, d).items()}
    rung = lambda df, score, method: select.ladder(df, L, sets[method], score, method)
    # the random choice is one of the same windows, whose keys are written with their scores
    rungs = rung(spb, "spb", "segments").unionByName(rung(scored["attention_small"], None, "random"))
    for name, z in scored.items():
        rungs = rungs.unionByName(rung(z, "lds", name))
    return rungs, scored


def _in_sets(rungs: DataFrame, sets: dict[str, tuple[int, ...]]) -> DataFrame:
    """Every (method, step, doc_id, start) of the sets."""
    return _steps(rungs).where(functools.reduce(Column.__or__, [(F.col("method") == m) & F.col("step").isin(*steps) for m, steps in sets.items()]))


def _sizes(s: SparkSession, d: str, sets: dict[str, tuple[int, ...]]) -> DataFrame:
    steps = _in_sets(_all_rungs(s, d, sets)[0], sets)
    return steps.groupBy("method", "step").agg(F.count("*").alias("windows"), (F.count("*") * L).alias("tokens"), F.count_distinct("category").alias("categories"), F.max("rnk").alias("deepest_rank"))


def scale_grid(s: SparkSession, d: str) -> DataFrame:
    """All 17 sets of the data-scale comparison: method x budget, with their sizes."""
    return _sizes(s, d, SETS)


def fixed_scale(s: SparkSession, d: str) -> DataFrame:
    """The six sets of the comparison at one scale."""
    return _sizes(s, d, ONE_SCALE)


def scale_measures(s: SparkSession, d: str) -> DataFrame:
    """The 17 sets with the stand-in measures: strength under both profiles, label rates, documents, and the retrieval
    accuracy of the profile that chose (null for methods without one)."""
    rungs, scored = _all_rungs(s, d)
    z = {n: x.select("doc_id", "start", F.col("ds_z").alias(f"z_{n}")) for n, x in scored.items()}
    # a window is looked up once for each method, however many of its sets hold it
    met = rungs.join(z["attention_small"], ["doc_id", "start"]).join(z["attention_large"], ["doc_id", "start"]).join(tables.table(s, d, "labels", "doc_id", "quality", "toxic"), "doc_id", "left")
    found = _in_sets(met, SETS).groupBy("method", "step").agg(F.count("*").alias("windows"), F.avg("z_attention_small").alias("ds_z_small"), F.avg("z_attention_large").alias("ds_z_large"), F.avg("quality").alias("good"), F.avg("toxic").alias("toxic"), F.count_distinct("doc_id").alias("documents"))
    accuracy = niah_by_profile(s, d).where("task = 'mean'").select(F.concat(F.lit("attention_"), "profile").alias("method"), F.col("accuracy").alias("retrieval"))
    return found.join(F.broadcast(accuracy), "method", "left")


def _grid(s: SparkSession, d: str) -> DataFrame:
    z = combined(s, d)
    spb = written(baselines.segment_scores(win(s, d)), "spb")
    rungs = select.ladder(z, L).unionByName(random_ladder(s, d)).unionByName(select.ladder(spb, L, score="spb", method="segments"))
    steps = _steps(rungs).where("step <= 10 or method = 'random'")
    met = steps.join(z.select("doc_id", "start", "ds_z"), ["doc_id", "start"]).join(tables.table(s, d, "labels", "doc_id", "quality", "toxic"), "doc_id", "left")
    return met.groupBy("method", "step").agg(F.count("*").alias("windows"), F.round(F.avg("ds_z"), 5).alias("mean_ds_z"), F.round(F.avg("quality"), 6).alias("good"), F.round(F.avg("toxic"), 6).alias("toxic"), F.count_distinct("doc_id").alias("documents"))


def scale_grid_hexdot(s: SparkSession, d: str) -> DataFrame:
    """Method x budget under the profile that SQL can follow, each with the stand-in measures."""
    return _grid(s, d)


def cost_ratios(s: SparkSession, d: str) -> DataFrame:
    """Token evaluations of each method and model against the attention scorer with the small model."""
    return evaluate.ratios(evaluate.cost_rows(win(s, d).drop("toks"), L, 32), "token_evaluations").select("method", "model", "token_evaluations", F.round("ratio", 6).alias("ratio"))


def cost_model(s: SparkSession, d: str) -> DataFrame:
    c = evaluate.cost_rows(win(s, d).drop("toks"), L, 32)
    return c.select("method", "model", "windows", "model_calls", "token_evaluations", F.round("multiplications").cast("long").alias("multiplications"), "share_of_pass")


def cost_grid(s: SparkSession, d: str) -> DataFrame:
    """CPU time of both methods and both model sizes over the same windows."""
    w = written(win(s, d), "windows")
    rows = None
    for name in ("small", "large"):
        own = score.score_windows(w, profiles.named(name), K).agg(F.lit("attention").alias("method"), F.lit(name).alias("model"), F.count("*").alias("windows"), F.sum("pair_ops").alias("pair_ops"), F.sum("cpu_ms").alias("cpu_ms"))
        rows = own if rows is None else rows.unionByName(own)
    for name, order in (("small", 1), ("large", 2)):
        own = baselines.segment_scores(w, order=order).agg(F.lit("segments").alias("method"), F.lit(name).alias("model"), F.count("*").alias("windows"), F.sum("model_calls").alias("pair_ops"), F.sum("cpu_ms").alias("cpu_ms"))
        rows = rows.unionByName(own)
    return rows


def attention_scores_small(s: SparkSession, d: str) -> DataFrame:
    return raw(s, d, profiles.named("small")).drop("cpu_ms")


def attention_scores_large(s: SparkSession, d: str) -> DataFrame:
    return raw(s, d, profiles.named("large")).drop("cpu_ms")


def profile_agreement(s: SparkSession, d: str) -> DataFrame:
    """How alike the small and the large scorer rank and choose."""
    out = both_profiles(s, d)
    same = evaluate.agreement(best(out["small"], 5), best(out["large"], 5))
    ranks = evaluate.rank_correlation(out["small"].select("doc_id", "start", F.col("lds").alias("x")).join(out["large"].select("doc_id", "start", F.col("lds").alias("y")), ["doc_id", "start"]), "x", "y")
    return same.join(F.broadcast(ranks), F.lit(True))


def corpus_profile_scores(s: SparkSession, d: str) -> DataFrame:
    """Scores with token vectors learned from the corpus."""
    learned = profiles.from_corpus(tok(s, d))
    return score.score_with_vectors(win(s, d), learned, K).drop("cpu_ms")


def planted_auc(s: SparkSession, d: str) -> DataFrame:
    """Does strength tell a window with a planted far link from its twin without one?"""
    return _planted_auc(s, d, profiles.HexDot()).select("positives", "negatives", F.round("auc", 6).alias("auc"))


def _planted_auc(s: SparkSession, d: str, *listed) -> DataFrame:
    """One row a profile, all scored in one pass over the pairs, twins together."""
    scored = written(score.score_twins(evaluate.planted_pairs(win(s, d)), list(listed), K), "planted")
    one = lambda p: evaluate.auc(scored.where(F.col("profile") == p.name), "ds", "label").select(F.lit(p.name).alias("profile"), "positives", "negatives", "auc")
    return functools.reduce(DataFrame.unionByName, map(one, listed))


def planted_auc_profiles(s: SparkSession, d: str) -> DataFrame:
    """The same for the small and the large profile."""
    return _planted_auc(s, d, profiles.named("small"), profiles.named("large"))


def sink_by_layer(s: SparkSession, d: str) -> DataFrame:
    return evaluate.sink_by_layer(win(s, d), lambda j: profiles.Decoder(layer=j), 4)


def _key(*columns: str):
    return F.md5(F.concat_ws(":", *columns)).alias("key")


def _prose(s: SparkSession, d: str) -> DataFrame:
    return windows.cut(tok(s, d), L).select(_key("doc_id", "start"), "toks")


def _items(s: SparkSession, d: str) -> DataFrame:
    return tables.table(s, d, "benchmark", "item_id", "text").select(_key("item_id"), windows.tokens(F.col("text")).alias("passage"))


def _cores(s: SparkSession) -> int:
    return max(8, int(s.conf.get("spark.sql.shuffle.partitions")))


def _haystacks(s: SparkSession, d: str) -> DataFrame:
    """Every window of every category with the text of a test item to hide in it; see ``evaluate.haystacks``."""
    return evaluate.haystacks(_prose(s, d), _items(s, d)).repartition(_cores(s))


def niah_probes(s: SparkSession, d: str) -> DataFrame:
    return evaluate.probe_digests(_haystacks(s, d))


def niah_accuracy(s: SparkSession, d: str) -> DataFrame:
    return evaluate.accuracy(evaluate.probed(_haystacks(s, d), [profiles.HexDot()], 16))


def _ranked_haystacks(s: SparkSession, d: str) -> DataFrame:
    """Every test item once (doc_id: its rank, passage) in the window of its rank (toks), which begin anew if they are fewer.

    Windows are ranked by their keys; the words of those that are asked for are read again."""
    docs, items = tables.read_corpus(s, d), _items(s, d)
    one = lambda df: windows.cut(windows.tokenize(df), L).select("doc_id", _key("doc_id", "start"), F.md5(F.concat_ws(" ", "toks")).alias("h"), "toks")
    keys = written(one(windows.spread(docs)).select("key", "h", "doc_id"), "keys")
    ranked = evaluate.numbered(keys, "key", "w").select("w", "key", "h", F.col("doc_id").alias("of"))
    hay = evaluate.numbered(items, "key", "i").drop("key").withColumn("w", F.col("i") % max(1, keys.count())).join(ranked, "w", "left")
    hay = written(hay.select(F.col("i").alias("doc_id"), "passage", "of", "key", "h"), "haystacks")
    few = F.broadcast if hay.count() <= 1 << 18 else lambda df: df
    held = one(docs.join(few(hay.select("of").distinct()), F.col("doc_id").eqNullSafe(F.col("of")), "left_semi"))
    held = held.select("key", "h", "toks").join(few(hay.select("key", "h").distinct()), ["key", "h"], "left_semi").dropDuplicates(["key", "h"])
    return hay.join(held, ["key", "h"], "left").select("doc_id", F.coalesce("toks", F.array().cast("array<string>")).alias("toks"), "passage")


def niah_by_profile(s: SparkSession, d: str) -> DataFrame:
    """Retrieval of each profile: every test item once, in a window of its rank, at every task and depth."""
    hay = _ranked_haystacks(s, d).repartition(_cores(s))
    names = ("hexdot", "small", "large")
    hits = written(evaluate.probed(hay, [profiles.named(n) for n in names], 16), "probes")
    out = None
    for name in names:
        row = evaluate.accuracy(hits.where(F.col("profile") == name)).select(F.lit(name).alias("profile"), "task", "accuracy", "probes")
        out = row if out is None else out.unionByName(row)
    return out


def ruler_probes(s: SparkSession, d: str) -> DataFrame:
    """All 13 tasks at all depths."""
    tasks = (*evaluate.NIAH, *evaluate.RULER_MORE)
    return evaluate.accuracy(evaluate.tallied(_haystacks(s, d), profiles.HexDot(), 16, tasks))


LONGBENCH = {"single_doc": 4, "multi_doc": 4, "summarising": 4, "few_shot": 4, "synthetic": 3, "code": 2}


def longbench_groups(s: SparkSession, d: str) -> DataFrame:
    """Six stand-in groups scored 0 to 100 by far attention, with the plain and the task-weighted mean."""
    p = profiles.HexDot()
    tasks = {"single_1": "single_doc", "single_2": "single_doc", "multikey_1": "multi_doc", "qa_1": "multi_doc", "lead": "summarising", "turns": "few_shot", "variable_tracking": "synthetic", "multivalue": "synthetic", "lines": "code", "multikey_2": "code"}
    hits = evaluate.tallied(_haystacks(s, d), p, 16, tuple(t for t in tasks if t != "turns"))
    talk = tables.dialogues(tables.table(s, d, "conversations", "conv_id", "turn", "role", "text"))
    turns = windows.tokenize(talk).where("n > 0").select("doc_id", "toks").repartition(_cores(s), "doc_id")
    hits = hits.unionByName(evaluate.tallied(turns, p, 16, ("turns",)))
    name = F.create_map(*[x for t, g in tasks.items() for x in (F.lit(t), F.lit(g))])
    groups = hits.groupBy(F.try_element_at(name, F.col("task")).alias("group")).agg((100 * (F.sum("hits") / F.sum("probes"))).alias("score")).withColumn("method", F.lit(p.name))
    means = evaluate.grouped_mean(groups, LONGBENCH)
    return groups.join(F.broadcast(means), "method").select("method", "group", "score", "macro_mean", "task_mean")


def _choices(s: SparkSession, d: str) -> dict[str, DataFrame]:
    z = combined(s, d)
    return {"attention": best(z, 5), "random": select.random_by_budget(z, budget(select.category_counts(z), 5), L)}


def _proxy(s: SparkSession, w: DataFrame, choices: dict[str, DataFrame], held: DataFrame) -> DataFrame:
    out = None
    for name, picked in choices.items():
        row = evaluate.proxy_lm(picked.select("doc_id", "start").join(w, ["doc_id", "start"]), held, K)
        row = row.select(F.lit(name).alias("method"), F.round("nats", 6).alias("nats"), "tokens", F.round("far_rate", 6).alias("far_rate"))
        out = row if out is None else out.unionByName(row)
    return out


def proxy_lm(s: SparkSession, d: str) -> DataFrame:
    """Held-out nats per token of the proxy model fitted on each choice; held out are windows of other documents
    whose text no choice holds."""
    w, choices = win(s, d), _choices(s, d)
    used = choices["attention"].select("doc_id").union(choices["random"].select("doc_id")).distinct()
    hashed = w.withColumn("h", F.md5(F.concat_ws(" ", "toks")))
    held = hashed.join(used, "doc_id", "left_anti").join(hashed.join(used, "doc_id", "left_semi").select("h").distinct(), "h", "left_anti").drop("h")
    return _proxy(s, w, choices, written(held, "held-out"))


def short_guard(s: SparkSession, d: str) -> DataFrame:
    """The same proxy on short documents: does the choice hurt them?"""
    short = tok(s, d).where((F.col("n") < L) & (F.col("n") >= 8)).select("doc_id", "category", F.lit(0).cast("long").alias("start"), F.col("n").cast("int").alias("len"), "toks")
    return _proxy(s, win(s, d), _choices(s, d), short)


# --- other tables -------------------------------------------------------------------------------------------


def _digest(r: DataFrame) -> DataFrame:
    return r.select("doc_id", "start", scaled(F.col("ds"), 6).alias("ds_e6"), scaled(F.col("du"), 9).alias("du_e9"))


def conversation_scores(s: SparkSession, d: str) -> DataFrame:
    talk = tables.dialogues(tables.table(s, d, "conversations", "conv_id", "turn", "role", "text"))
    return _digest(score.score_windows(windows.cut(windows.tokenize(talk), L), profiles.HexDot(), K))


def event_sequence_scores(s: SparkSession, d: str) -> DataFrame:
    """Event types of a user in order, as tokens."""
    events = tables.table(s, d, "events", "event_id", "ts", "user_id", "event_type").where("user_id is not null")
    seq = events.groupBy(F.col("user_id").alias("doc_id")).agg(F.transform(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda e: e["event_type"]).alias("toks"))
    toks = seq.select("doc_id", F.lit("events").alias("category"), "toks", F.size("toks").cast("long").alias("n"))
    return _digest(score.score_windows(windows.cut(toks, 8), profiles.HexDot(), 2))


def vector_attention(s: SparkSession, d: str) -> DataFrame:
    """Vectors of a label in order, as queries and keys; k is a quarter of the sequence."""
    from farspan.operators import kernel

    vectors = tables.table(s, d, "embeddings", "vec_id", "embedding", "label")
    seq = vectors.groupBy(F.col("label").cast("long").alias("doc_id")).agg(F.transform(F.sort_array(F.collect_list(F.struct("vec_id", "embedding"))), lambda e: e["embedding"]).alias("toks"))
    p = profiles.Vectors()
    rows = score.per_window(seq.select("doc_id", F.lit("vectors").alias("category"), F.lit(0).cast("long").alias("start"), "toks"), lambda t: [kernel.score(p, t, [len(t) // 4])[0]], "len int, ds double")
    return rows.select("doc_id", "len", scaled(F.col("ds"), 6).alias("ds_e6"))


def page_windows(s: SparkSession, d: str) -> DataFrame:
    pages = tables.table(s, d, "pages", "page_id", "html").select(F.col("page_id").alias("doc_id"), F.lit("page").alias("category"), tables.page_text(F.col("html")).alias("text"))
    return windows.spans(windows.tokenize(pages), L).groupBy("doc_id", "n").agg(F.count("*").alias("windows"), F.sum("start").alias("start_sum"))


def benchmark_overlap(s: SparkSession, d: str) -> DataFrame:
    """Documents that hold eight words in a row of a test item.  Up to 2**18 strings of items are broadcast, so that a
    document's strings meet them where they are read; beyond, both sides are shuffled."""

    def grams(df: DataFrame, key: str) -> DataFrame:
        words = df.select(key, windows.tokens(F.col("text")).alias("w")).where(F.size("w") >= 8)
        return words.select(key, F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - 7), lambda i: F.concat_ws(" ", F.slice("w", i, 8)))).alias("g"))

    docs, items = grams(tables.table(s, d, "documents", "doc_id", "text"), "doc_id"), grams(tables.table(s, d, "benchmark", "item_id", "text"), "item_id")
    held = items.distinct()
    held = F.broadcast(held) if held.count() <= 1 << 18 else held
    return docs.join(held, "g").distinct().groupBy("item_id", "doc_id").agg(F.count("*").alias("shared"))


QUERIES: dict[str, Query] = {
    f.__name__: f
    for f in (
        doc_tokens, window_spans, window_spans_char32k, window_branch_counts, window_coverage, naive_truncate, stride_windows, concat_pack, clean_documents,
        attention_scores, attention_multi_k, token_strength, attention_variants, cells_reference, cumulative_attention, score_moments, lds_scores, lds_scores_by_category, lds_scores_robust, score_magnitudes, alpha_sweep, document_rollup, score_sampled,
        select_top_budget, select_by_threshold, select_no_category, select_random, select_ladder, random_ladder, mix_short, spb_scores, spb_parts, spb_scores_pairs_order2, select_spb, linguistic_metrics, linguistic_units, select_random_threshold, distinct_token_counts, front_token_scores, piece_tokens, select_small, select_large,
        label_rates, selection_agreement, alpha_ablation, diversity, scale_grid, scale_grid_hexdot, fixed_scale, scale_measures, cost_model, cost_ratios, cost_grid, attention_scores_small, attention_scores_large, corpus_profile_scores, profile_agreement, planted_auc, planted_auc_profiles, sink_by_layer, niah_probes, niah_accuracy, niah_by_profile, ruler_probes, longbench_groups, proxy_lm, short_guard,
        conversation_scores, event_sequence_scores, vector_attention, page_windows, benchmark_overlap,
    )
}
