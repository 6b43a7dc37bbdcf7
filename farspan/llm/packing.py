"""Best-fit packing into sequences of several permitted lengths.

Documents are dealt into blocks of bounded size by a hash of their row's place; each block is packed on its own: pieces in
decreasing length go where they leave the least room, a new sequence is opened with the capacity that costs least
per token it can be expected to hold, and at the end every sequence is cut down to the least permitted length that
holds its contents.  The plans of several opening policies (all lengths jointly, and each single length) are made
and the cheapest is kept.  A document longer than the largest capacity is cut into full pieces and a rest, and a
sequence never holds more than its capacity.

cost(capacity) = capacity ** COST_POWER + OVERHEAD: longer sequences cost more a token, each sequence something.

Documents of no token are placed nowhere (one row with a null sequence); null ids and repeated rows are packed
like any other row; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from bisect import bisect_left, insort

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farspan.llm.storage import written

CAPACITIES = (256, 512, 1024, 2048, 4096)
COST_POWER = 1.05
OVERHEAD = 16.0
BLOCK_ROWS = 8_192

SCHEMA = "doc_id long, piece int, first_token long, n_tokens int, sequence_id string, position int, capacity int, filled int"


def cost(capacity: int) -> float:
    return capacity**COST_POWER + OVERHEAD


def count_words(text: Column) -> Column:
    """Words ``[^\\x20\\x09-\\x0D]+``: the tokens that are counted unless a length column is given."""
    return F.when(text.isNull(), 0).otherwise(F.size(F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != ""))).cast("long")


class _Open:
    """Open sequences by the room they have left."""

    def __init__(self):
        self.room: list[tuple[int, int]] = []

    def take(self, need: int) -> tuple[int, int] | None:
        i = bisect_left(self.room, (need, -1))
        return self.room.pop(i) if i < len(self.room) else None

    def put(self, room: int, number: int) -> None:
        if room > 0:
            insort(self.room, (room, number))


def _opened(need: int, left: list[int], at: int, capacities: tuple[int, ...]) -> int:
    """The capacity whose cost per token it can hold is least, given the pieces still to come (in decreasing order)."""
    best, least = None, float("inf")
    for c in capacities:
        if c < need:
            continue
        held, i = need, at + 1
        # what would best fill this sequence from the pieces that follow
        while held < c and i < len(left):
            i = bisect_left(left, -(c - held), i, key=lambda x: -x)
            if i < len(left):
                held += left[i]
                i += 1
        rate = cost(c) / held
        if rate < least:
            best, least = c, rate
    return best if best is not None else capacities[-1]


def best_fit(lengths: list[int], capacities: tuple[int, ...]) -> tuple[list[int], list[int]]:
    """lengths in decreasing order -> (sequence of each piece, capacity of each sequence after cutting down)."""
    held, placed, used = _Open(), [], []
    for at, need in enumerate(lengths):
        found = held.take(need)
        if found is None:
            capacity = _opened(need, lengths, at, capacities)
            found = (capacity, len(used))
            used.append(0)
        room, number = found
        placed.append(number)
        used[number] += need
        held.put(room - need, number)
    return placed, [next(c for c in capacities if c >= u) for u in used]


def best_plan(lengths: list[int], capacities: tuple[int, ...] = CAPACITIES) -> tuple[list[int], list[int]]:
    """The cheapest of the joint plan and the plans that open one length only (each cut down at the end)."""
    plans = [best_fit(lengths, capacities)]
    for c in capacities:
        if not lengths or c >= lengths[0]:
            placed, _ = best_fit(lengths, (c,))
            used = [0] * (max(placed, default=-1) + 1)
            for n, s in zip(lengths, placed, strict=True):
                used[s] += n
            plans.append((placed, [next(x for x in capacities if x >= u) for u in used]))
    return min(plans, key=lambda p: sum(map(cost, p[1])))


def pack(df: DataFrame, capacities: tuple[int, ...] = CAPACITIES, id_col: str = "doc_id", length: Column | None = None, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Pieces of all rows with the sequence, position and final capacity of each; only ids and lengths are moved."""
    capacities = tuple(sorted(capacities))
    count = count_words(F.col("text").cast("string")) if length is None else length
    sized = written(df.select(F.col(id_col).cast("long").alias("doc_id"), count.cast("long").alias("n")), "lengths")
    most = capacities[-1]
    total = sized.agg(F.sum(F.ceil(F.col("n") / most)).alias("p")).first().p or 0
    blocks = max(1, -(-total // block_rows))
    # a row's place in the written table: repeated rows and rows without an id spread as well
    placed = sized.withColumn("place", F.monotonically_increasing_id())
    pieces = placed.where("n > 0").select("doc_id", "n", "place", F.posexplode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / most))).alias("piece", "k"))
    pieces = pieces.select("doc_id", "place", "piece", (F.col("k") * most).alias("first_token"), F.least(F.lit(most).cast("long"), F.col("n") - F.col("k") * most).cast("int").alias("n_tokens"))
    dealt = pieces.withColumn("block", F.pmod(F.xxhash64("place", "piece"), F.lit(blocks)).cast("long")).drop("place")

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["n_tokens", "doc_id", "piece"], ascending=[False, True, True], kind="stable", na_position="first").reset_index(drop=True)
        placed, capacity = best_plan(rows["n_tokens"].tolist(), capacities)
        rows["sequence_id"] = [f"{key[0]}-{s}" for s in placed]
        rows["capacity"] = pd.array([capacity[s] for s in placed], "int32")
        rows["position"] = (rows.groupby("sequence_id")["n_tokens"].cumsum() - rows["n_tokens"]).astype("int32")
        rows["filled"] = rows.groupby("sequence_id")["n_tokens"].transform("sum").astype("int32")
        return rows[["doc_id", "piece", "first_token", "n_tokens", "sequence_id", "position", "capacity", "filled"]]

    packed = dealt.groupBy("block").applyInPandas(run, SCHEMA)
    nothing = sized.where("n <= 0 or n is null").selectExpr("doc_id", "0 as piece", "0L as first_token", "0 as n_tokens", "cast(null as string) as sequence_id", "cast(null as int) as position", "cast(null as int) as capacity", "cast(null as int) as filled")
    return packed.union(nothing)
