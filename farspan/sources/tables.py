"""Reading corpora and the given tables; column pruning and length filters reach the scan."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """parquet, orc, json (lines), csv or text; a schema spares the inference pass."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def whole_text(spark: SparkSession, path: str) -> DataFrame:
    """One row per file: books, code."""
    return spark.read.text(path, wholetext=True).select(F.input_file_name().alias("path"), F.col("value").alias("text"))


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in NAMES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read_corpus(spark: SparkSession, sf_dir: str, category: str = "lang", least_chars: int = 0) -> DataFrame:
    """doc_id, category, text, n_chars of documents with at least ``least_chars`` characters (a pushed filter)."""
    df = table(spark, sf_dir, "documents", "doc_id", category, "text", "n_chars").withColumnRenamed(category, "category")
    return df.where(F.col("n_chars") >= least_chars) if least_chars else df


def gather(*corpora: DataFrame) -> DataFrame:
    """Several corpora as one."""
    out = corpora[0]
    for other in corpora[1:]:
        out = out.unionByName(other, allowMissingColumns=True)
    return out


def page_text(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags go, five entities are spelled out."""
    out = F.regexp_replace(html, r"(?s)<!--.*?-->|<(script|style)[^>]*>.*?</(script|style)>", " ")
    out = F.regexp_replace(out, r"<[^>]*>", " ")
    for entity, mark in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        out = F.replace(out, F.lit(entity), F.lit(mark))
    return out


def dialogues(conversations: DataFrame) -> DataFrame:
    """Turns joined in order: one text per conversation."""
    turns = conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("t"))
    return turns.select(F.col("conv_id").alias("doc_id"), F.lit("dialogue").alias("category"), F.concat_ws(" ", F.transform("t", lambda x: F.coalesce(x["text"], F.lit("")))).alias("text"))
