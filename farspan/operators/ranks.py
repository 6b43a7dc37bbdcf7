"""Ranks and running sums over large groups, without sorting a group in one task.

A quantile sketch gives cut points per group; each value falls between two of them, or on one.  Rows of one such range
are sorted together, and what comes before a range is known from the ranges' sums, a small table.  A value that many
rows share (a cut point) is a range of its own and is split further by the first tie-breaker.  Results are exact: the
sketch only places the cut points.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

RANGES = 128
ACCURACY = 2_000


def in_ranges(df: DataFrame, by: str, key: Column, tie: Column | None = None, ranges: int = RANGES) -> DataFrame:
    """df with ``range`` and ``part``, in the order of key (ascending, nulls last) and, where the key is constant, of tie.

    The cut points, one row for each value of ``by``, are broadcast.
    """
    shares = [i / ranges for i in range(ranges + 1)]
    cut = lambda x: F.array_distinct(F.percentile_approx(x.cast("double"), shares, ACCURACY))
    cuts = [cut(key).alias("cuts")] + ([cut(tie).alias("ties")] if tie is not None else [])
    points = df.groupBy(F.col(by).alias("cut_by")).agg(*cuts)
    met = df.join(F.broadcast(points), F.col(by).eqNullSafe(F.col("cut_by"))).withColumn("cut_x", key.cast("double"))
    x = F.col("cut_x")
    met = met.withColumn("below", _below("cuts", x, ranges + 1))
    on = F.coalesce(F.get("cuts", F.col("below")) == x, F.lit(False))
    last = 2 * F.size("cuts") + 2
    met = met.withColumn("range", F.when(x.isNull(), last).otherwise(2 * F.col("below") + on.cast("int")))
    # only a range of one value may be split by the tie-breaker
    part = F.when(on & (F.col("range") < last), _below("ties", tie.cast("double"), ranges + 1)).otherwise(0) if tie is not None else F.lit(0)
    return met.withColumn("part", part).drop("cuts", "ties", "cut_by", "cut_x", "below")


def _below(cuts: str, x: Column, most: int) -> Column:
    """How many of an ascending array's values (``most`` or fewer) lie below x, by halving; 0 for a null.  x is read at each
    step, so it should be a column that is made already."""
    steps = F.array(*[F.lit(1 << i) for i in reversed(range(most.bit_length()))])
    return F.aggregate(steps, F.lit(0), lambda at, step: at + F.when(F.get(F.col(cuts), at + step - 1) < x, step).otherwise(0))


def running(ranged: DataFrame, by: str, order: list[Column], sums: dict[str, Column], inclusive: bool = True, most: Column | None = None) -> DataFrame:
    """ranged with running sums in the order of range, part and ``order``; ranges' totals are broadcast.

    most: rows of ranges before which the first sum has come to that already go, and are neither shuffled nor sorted.
    """
    keys = [by, "range", "part"]
    totals = ranged.groupBy(*keys).agg(*[F.sum(x).alias(f"all_{n}") for n, x in sums.items()])
    ahead = Window.partitionBy(by).orderBy("range", "part").rowsBetween(Window.unboundedPreceding, -1)
    before = totals.select(*[F.col(k).alias(f"at_{k}") for k in keys], *[F.coalesce(F.sum(f"all_{n}").over(ahead), F.lit(0)).alias(f"before_{n}") for n in sums])
    same = [F.col(k).eqNullSafe(F.col(f"at_{k}")) for k in keys]
    within = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow if inclusive else -1)
    met = ranged.join(F.broadcast(before), same[0] & same[1] & same[2])
    met = met if most is None else met.where(F.col(f"before_{next(iter(sums))}") < most)
    out = met.withColumns({f"own_{n}": F.coalesce(F.sum(x).over(within), F.lit(0)) for n, x in sums.items()})
    return out.withColumns({n: F.col(f"own_{n}") + F.col(f"before_{n}") for n in sums}).drop(*[f"{p}_{n}" for n in sums for p in ("own", "before")], *[f"at_{k}" for k in keys])


def ranked(df: DataFrame, by: str, key: Column, order: list[Column], tie: Column | None = None, most: Column | None = None) -> DataFrame:
    """df with ``rnk``, its rank from 1 within ``by`` in the given order, of which ``key`` is the leading part, ascending.

    most: only the rows up to that rank (a number, or a column that is constant within ``by``)."""
    found = running(in_ranges(df, by, key, tie), by, order, {"rnk": F.lit(1).cast("long")}, most=most).drop("range", "part")
    return found if most is None else found.where(F.col("rnk") <= most)
