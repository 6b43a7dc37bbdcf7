"""The registered queries of this subpackage, each over its whole table, and their SQL where SQL can say them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farspan.llm import bpe_stream, language_id, lattice_lm, media, ngram_join, packing, quality_rules, substring_dedup, toxicity, url_templates
from farspan.llm.storage import documents

URL_RULES = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]


def fold(modulus: int) -> F.Column:
    """Which fold a document is in: crc32 of its id as text, modulo."""
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % modulus


def op1_lattice_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = lattice_lm.score_documents(documents(spark, sf_dir), train=fold(7) != 2, class_col="lang")
    return scored.select("doc_id", (~F.col("train")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substring_dedup.remove_repeats(documents(spark, sf_dir), length=100)
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda total, x: total + x["end"] - x["start"])
    return found.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules.judge(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rejected_by")


def op7_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.store_documents(documents(spark, sf_dir))


def op9_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.near_duplicates(documents(spark, sf_dir), k=5).select("doc_id", "n_shingles", "component_id")


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir))


def op5_bpe_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_stream.round_trip(documents(spark, sf_dir))


def op6_url_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    # a page shows the document whose number ends its path, and has that document's quality label
    _, path = url_templates.split_url(F.col("url"))
    shown = pages.select("page_id", F.regexp_extract(path, r"([0-9]{1,18})[^0-9/]*/?$", 1).try_cast("bigint").alias("doc_id"))
    labels = shown.join(spark.read.parquet(f"{sf_dir}/labels.parquet"), "doc_id").select("page_id", (1 - F.col("quality")).alias("bad"))
    return url_templates.judge(pages, labels, URL_RULES).select("page_id", "host", "path", "rule", "verdict", "template", F.round("purity", 9).alias("purity"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    lexicon = toxicity.fit(docs, labels.where(fold(4) != 2))
    scored = toxicity.score(docs, lexicon)
    return scored.select("doc_id", (fold(4) == 2).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = language_id.fit(docs.where(fold(3) != 1))
    return language_id.identify(docs, model).select("doc_id", (fold(3) == 1).alias("held_out"), "lang_pred", "score")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_lattice_lm": op1_lattice_lm,
    "op2_substring_dedup": op2_substring_dedup,
    "op3_quality_rules": op3_quality_rules,
    "op4_best_fit_packing": op4_best_fit_packing,
    "op5_bpe_stream": op5_bpe_stream,
    "op6_url_templates": op6_url_templates,
    "op7_media_columns": op7_media_columns,
    "op8_toxicity": op8_toxicity,
    "op9_ngram_jaccard": op9_ngram_jaccard,
    "op10_language_id": op10_language_id,
}

_WORDS = r"[^\x20\x09-\x0D]+"
_LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

#: The others learn weights, hash with Python's formats or pack greedily: tests hold them against brute force.
ORACLES: dict[str, str] = {
    "op2_substring_dedup": """with d as (select doc_id, hex(encode(coalesce(text, ''))) as h, (length(hex(encode(coalesce(text, '')))) // 2)::bigint as n from documents),
 w as (select doc_id, unnest(range(0, n - 99)) as p, h from d where n >= 100),
 s as (select doc_id, p, md5(substr(h, (2 * p + 1)::bigint, 200)) as s from w),
 later as (select doc_id, p from (select doc_id, p, row_number() over (partition by s order by doc_id, p) as k from s) where k > 1),
 flag as (select doc_id, p, case when p > lag(p) over (partition by doc_id order by p) + 100 then 1 else 0 end as f from later),
 isle as (select doc_id, p, sum(f) over (partition by doc_id order by p) as g from flag),
 runs as (select doc_id, g, min(p) as a, max(p) + 100 as b from isle group by doc_id, g),
 cut as (select r.doc_id, a, b, substr(h, (2 * coalesce(lag(b) over (partition by r.doc_id order by a), 0) + 1)::bigint, (2 * (a - coalesce(lag(b) over (partition by r.doc_id order by a), 0)))::bigint) as piece from runs r join d using (doc_id)),
 summed as (select doc_id, sum(b - a)::bigint as n_removed, count(*)::bigint as n_spans, max(b) as last, string_agg(piece, '' order by a) as before from cut group by doc_id)
 select d.doc_id, d.n as n_bytes, coalesce(n_removed, 0)::bigint as n_removed, coalesce(n_spans, 0)::bigint as n_spans, sha256(unhex(coalesce(before, '') || substr(h, (2 * coalesce(last, 0) + 1)::bigint))) as kept_sha256
 from d left join summed using (doc_id)""",
    "op9_ngram_jaccard": f"""with recursive w as (select doc_id, regexp_extract_all({_LOWERED}, '{_WORDS}') as w from documents),
 sets as (select doc_id, case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')] else list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(list_slice(w, i, i + 4), ' '))) end as s from w),
 sh as (select doc_id, unnest(s) as g, len(s) as n from sets),
 met as (select a.doc_id as x, b.doc_id as y, any_value(a.n) as m, any_value(b.n) as n, count(*) as o from sh a join sh b on a.g = b.g and a.doc_id < b.doc_id group by a.doc_id, b.doc_id),
 link as (select x, y from met where 100 * o >= 75 * (m + n - o)),
 both_ways as (select x, y from link union select y, x from link),
 reach as (select x, y from both_ways union select r.x, b.y from reach r join both_ways b on r.y = b.x)
 select s.doc_id, len(s.s)::bigint as n_shingles, least(s.doc_id, coalesce(min(r.y), s.doc_id)) as component_id from sets s left join reach r on r.x = s.doc_id group by s.doc_id, s.s""",
}
