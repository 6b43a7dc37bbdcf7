"""Documents to windows: tokenise, gate, cut, and the naive constructions beside them.

A document stays one row until its windows are cut; nothing here shuffles except packing, and a scan of too few tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from farspan.functions.columns import shuffle_key, starts, tokens

#: Short documents of one chain, about.
BUCKET_ROWS = 100_000


def tokenize(df: DataFrame, mode: str = "word") -> DataFrame:
    """doc_id, category, toks, n.

    Mode ``piece`` or ``piece:<path>`` cuts into pieces of a sentencepiece model, in vectorised batches; all others are
    column expressions.
    """
    if mode.startswith("piece"):
        from farspan.functions.udfs import pieces

        cut = df.select("doc_id", "category", pieces(mode[6:])(F.coalesce("text", F.lit(""))).alias("toks"))
    else:
        cut = df.select("doc_id", "category", tokens(F.col("text"), mode).alias("toks"))
    return cut.withColumn("n", F.size("toks").cast("long"))


def long_only(df: DataFrame, L: int, mode: str = "word") -> DataFrame:
    """Documents that can hold L tokens, judged by n_chars before the text is read: n words need 2n - 1 characters."""
    least = 2 * L - 1 if mode in ("word", "lines") else L if mode == "char" else 0
    return df.where(F.col("n_chars") >= least) if "n_chars" in df.columns and least else df


def spans(df: DataFrame, L: int, middle: str = "centre") -> DataFrame:
    """doc_id, category, n, ord, start of every window; needs n only."""
    return df.select("doc_id", "category", "n", F.posexplode(starts(F.col("n"), L, middle)).alias("ord", "start"))


def branch(n: Column, L: int) -> Column:
    return F.when(n < L, "short").when(n == L, "one").when(n <= 2 * L, "two").when(n <= 3 * L, "three").otherwise("peeled")


def cut(df: DataFrame, L: int, middle: str = "centre", short: str = "drop") -> DataFrame:
    """windows: doc_id, category, start, ord, part, n, len, toks.

    short: what becomes of documents below L tokens - 'drop', 'keep' (one shorter window) or 'pad' (with <pad>).
    """
    at = starts(F.col("n"), L, middle)
    if short != "drop":
        at = F.when((F.col("n") < L) & (F.col("n") > 0), F.array(F.lit(0).cast("long"))).otherwise(at)
    out = df.select("doc_id", "category", "n", "toks", F.size(at).alias("c"), F.posexplode(at).alias("ord", "start"))
    half = F.floor(F.col("c") / 2)
    part = F.when(F.col("ord") < half, "front").when((F.col("c") % 2 == 1) & (F.col("ord") == half), "middle").otherwise("back")
    piece = F.slice("toks", (F.col("start") + 1).cast("int"), L)
    if short == "pad":
        piece = F.concat(piece, F.array_repeat(F.lit("<pad>"), F.greatest(F.lit(0), F.lit(L) - F.size(piece))))
    return out.select("doc_id", "category", "start", "ord", part.alias("part"), "n", piece.alias("toks")).withColumn("len", F.size("toks"))


def truncate(df: DataFrame, L: int) -> DataFrame:
    """The first L tokens only."""
    return df.where(F.col("n") >= L).select("doc_id", "category", F.lit(0).cast("long").alias("start"), F.lit(0).alias("ord"), F.lit("front").alias("part"), "n", F.slice("toks", 1, L).alias("toks"), F.lit(L).alias("len"))


def stride(df: DataFrame, L: int, step: int) -> DataFrame:
    """Windows at a fixed stride; the rest behind the last full one is left out."""
    held = df.where(F.col("n") >= L)
    out = held.select("doc_id", "category", "n", "toks", F.posexplode(F.sequence(F.lit(0).cast("long"), F.col("n") - L, F.lit(step).cast("long"))).alias("ord", "start"))
    return out.select("doc_id", "category", "start", "ord", F.lit("stride").alias("part"), "n", F.slice("toks", (F.col("start") + 1).cast("int"), L).alias("toks"), F.lit(L).alias("len"))


#: Tasks for each core from which on a scan stays as it is.
TASKS_A_CORE = 4


def spread(documents: DataFrame) -> DataFrame:
    """Documents over all cores: a scan with fewer than TASKS_A_CORE tasks for each core of the cluster (a small table, large
    files that can't be split, a last round of tasks for a few cores) is dealt anew, as text and before any tokens exist.
    Any larger scan stays as it is."""
    tasks = TASKS_A_CORE * documents.sparkSession.sparkContext.defaultParallelism
    return documents.repartition(tasks, "doc_id") if documents.rdd.getNumPartitions() < tasks else documents


def concat_order(df: DataFrame, L: int, seed: int, buckets: int | None = None) -> DataFrame:
    """Short documents laid end to end in random order, by category and bucket: where each begins in its chain.

    There is a bucket for about BUCKET_ROWS short documents, 16 at least.
    """
    shorts = df.where((F.col("n") < L) & (F.col("n") > 0))
    buckets = buckets or max(16, -(-shorts.count() // BUCKET_ROWS))
    key = shuffle_key(seed, F.col("doc_id"))
    dealt = shorts.withColumn("key", key).withColumn("bucket", F.pmod(F.conv(F.substring("key", 1, 8), 16, 10).cast("bigint"), F.lit(buckets)).cast("int"))
    chain = Window.partitionBy("category", "bucket").orderBy("key", "doc_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return dealt.withColumn("begin", F.sum("n").over(chain) - F.col("n"))


def concat_pack(df: DataFrame, L: int, seed: int = 7, buckets: int | None = None) -> DataFrame:
    """Windows of L tokens made of short documents end to end; an incomplete last window is left out."""
    placed = concat_order(df, L, seed, buckets)
    flat = placed.select("category", "bucket", "begin", F.posexplode("toks").alias("i", "tok"))
    at = flat.select("category", "bucket", F.floor((F.col("begin") + F.col("i")) / L).alias("bin"), ((F.col("begin") + F.col("i")) % L).alias("q"), "tok")
    packed = at.groupBy("category", "bucket", "bin").agg(F.transform(F.sort_array(F.collect_list(F.struct("q", "tok"))), lambda x: x["tok"]).alias("toks")).where(F.size("toks") == L)
    return packed.select(F.xxhash64("category", "bucket", "bin").alias("doc_id"), "category", "bucket", "bin", F.lit(0).cast("long").alias("start"), F.lit(0).alias("ord"), F.lit("packed").alias("part"), F.lit(L).cast("long").alias("n"), "toks", F.lit(L).alias("len"))


def coverage(df: DataFrame, L: int) -> DataFrame:
    """Per document: windows, whether every token is covered, overlap of windows, whether starts are distinct."""
    one = df.where(F.col("n") >= L).withColumn("s", starts(F.col("n"), L))
    gap = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("s") - 1)), lambda i: F.coalesce(F.try_element_at("s", i + 1) - F.try_element_at("s", i), F.lit(L).cast("long")))
    covered = F.forall(gap, lambda g: g <= L) & (F.element_at("s", 1) == 0) & (F.element_at("s", -1) + L == F.col("n"))
    return one.select("doc_id", "n", F.size("s").cast("long").alias("windows"), covered.alias("covered"), (F.size("s") * F.lit(L).cast("long") - F.col("n")).alias("overlap"), (F.size(F.array_distinct("s")) == F.size("s")).alias("distinct_starts"))


def clean(df: DataFrame, most_marks: float = 0.3) -> DataFrame:
    """Before selection: blank texts, texts full of marks, and exact copies (the least id stays) go."""
    text = F.coalesce(F.col("text"), F.lit(""))
    marks = F.length(F.regexp_replace(text, r"[\p{L}\p{N}\s]", ""))
    kept = df.where(text.rlike(r"[^\x20\x09-\x0D]") & (marks <= most_marks * F.length(text)))
    first = kept.groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    return kept.join(first, "doc_id", "left_semi")
