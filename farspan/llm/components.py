"""Connected components of an edge table by alternating star contractions; no edge leaves the executors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farspan.llm.storage import spread_join, written


def _star(edges: DataFrame, both_ways: bool, total: int) -> DataFrame:
    """Hang the neighbours of every node on the least of them: all larger ones, or all smaller ones."""
    if both_ways:
        seen = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        seen = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = seen.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("c")).select("a", F.least("a", "m").alias("m"), "c")
    hung = spread_join(seen, least, "a", "c", 2 * total)
    if both_ways:
        out = hung.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        out = hung.select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b")))
    return out.where("a <> b").distinct()


def connected_components(edges: DataFrame, max_rounds: int = 40) -> DataFrame:
    """(node, root) for every node with an edge; root is the least node of the component.

    edges has two long columns a and b; loops, repeated and reversed edges are allowed, nulls are ignored,
    and an empty table gives an empty one.  A node with many neighbours is reduced by partial aggregation, and joined
    back by broadcast.
    """
    mark = lambda df: df.agg(F.count("*"), F.sum(F.xxhash64("a", "b") % 2**31)).first()
    now = written(edges.select("a", "b").where("a <> b").distinct(), "edges")
    last = mark(now)
    for _ in range(max_rounds):
        if last[0] == 0:
            break
        half = written(_star(now, True, last[0]), "edges")
        now = written(_star(half, False, half.count()), "edges")
        before, last = last, mark(now)
        if before == last:
            break
    else:
        raise RuntimeError(f"components didn't settle in {max_rounds} rounds")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select(F.col("b").alias("node"), F.col("b").alias("root"))).distinct()
