"""Reading the given tables, cutting lineage, and joins that hold under frequent keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farspan.sources.intermediate import lean_batches, written

__all__ = ["documents", "lean_batches", "partitions_for", "spread_join", "texts", "written"]
#: Frequent keys whose one row is broadcast in spread_join, at most.
BROADCAST_ROWS = 1 << 18


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def texts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the identifier and the text, under fixed names, so that other columns can't clash."""
    return lean_batches(df).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def partitions_for(spark: SparkSession, least: int = 8) -> int:
    return max(least, int(spark.conf.get("spark.sql.shuffle.partitions")))


def spread_join(rows: DataFrame, values: DataFrame, key: str | list[str], count: str, total: int) -> DataFrame:
    """rows with the row of ``values`` for their key (one a key at most; rows without one are left out).

    ``count`` is a column of values: how many rows have the key, ``total`` their sum or more.  Keys of
    max(1024, total / BROADCAST_ROWS) rows or more are BROADCAST_ROWS at most, so they are broadcast; only the rows of
    other keys are shuffled, and no task gets a frequent key.  The column ``count`` isn't in the result.
    """
    least = max(1024, -(-total // BROADCAST_ROWS))
    frequent = values.where(F.col(count) >= least).drop(count)
    rare = values.where(F.col(count) < least).drop(count)
    by_broadcast = rows.join(F.broadcast(frequent), key)
    rest = rows.join(F.broadcast(frequent.select(*([key] if isinstance(key, str) else key))), key, "left_anti")
    return by_broadcast.unionByName(rest.join(rare, key))
