"""Choosing windows up to token budgets, category by category."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from farspan.functions.columns import shuffle_key
from farspan.operators.ranks import in_ranges, ranked

LADDER = (1, 3, 5, 10, 20)
#: Decimals of a score that count in a ranking, so that equal windows tie whatever the order of summation.
DIGITS = 6


def unit_tokens(windows: int, L: int, share: int = 40) -> int:
    """One budget unit: a fortieth of the raw window tokens."""
    return windows * L // share


def distinct_tokens(picked: DataFrame) -> DataFrame:
    """category, windows, tokens, distinct: tokens of a choice, and those counted once where windows of a document overlap."""
    after = F.lead("start").over(Window.partitionBy("category", "doc_id").orderBy("start"))
    own = picked.select("category", "len", F.least(F.col("len").cast("long"), F.coalesce(after - F.col("start"), F.col("len").cast("long"))).alias("fresh"))
    return own.groupBy("category").agg(F.count("*").alias("windows"), F.sum("len").alias("tokens"), F.sum("fresh").alias("distinct"))


def wanted_windows(budget: int, L: int) -> int:
    return budget // L


def quotas(counts: dict[str, int], wanted: int, rule: str | dict[str, float] = "proportional") -> dict[str, int]:
    """Windows per category: largest remainders on the shares, ties by name; never more than a category has."""
    names = sorted(counts)
    total = sum(counts.values())
    if rule == "equal":
        share = {c: 1 / len(names) for c in names} if names else {}
    elif isinstance(rule, dict):
        share = rule
    else:
        share = {c: counts[c] / total for c in names} if total else {}
    from fractions import Fraction

    exact = {c: Fraction(wanted * counts[c], total) if rule == "proportional" and total else Fraction(share.get(c, 0)).limit_denominator(10**9) * wanted for c in names}
    floor = {c: int(exact[c]) for c in names}
    left = wanted - sum(floor.values())
    for c in sorted(names, key=lambda c: (floor[c] - exact[c], c))[: max(0, left)]:
        floor[c] += 1
    return {c: min(floor[c], counts[c]) for c in names}


def category_counts(windows: DataFrame) -> dict[str, int]:
    """One number per category on the driver."""
    return {r.category: r["count"] for r in windows.groupBy("category").count().collect()}


def _order(score: str, descending: bool = True) -> list[Column]:
    x = F.round(F.col(score), DIGITS) if descending else F.col(score)
    return [x.desc() if descending else x.asc(), F.col("doc_id"), F.col("start")]


def _quota_column(quota: dict[str, int]) -> Column:
    out = F.lit(0)
    for c, n in sorted(quota.items()):
        out = F.when(F.col("category") == c, n).otherwise(out)
    return out


def _ranked(df: DataFrame, quota: dict[str, int], order: list[Column], key: Column) -> DataFrame:
    """Rank within the category and cut; ``key`` is the leading part of the order, ascending. No task sorts a category, and
    only rows of ranges that the quota reaches are sorted."""
    return ranked(df, "category", key, order, F.col("doc_id"), _quota_column(quota))


def _falling(score: str) -> Column:
    return -F.round(F.col(score), DIGITS)


def _hashed(key: str = "key") -> Column:
    """The head of a hexadecimal key as a number."""
    return F.conv(F.substring(key, 1, 8), 16, 10).cast("double")


def _picked(df: DataFrame, method: str, budget: int, score: str | None, L: int) -> DataFrame:
    return df.select(F.lit(method).alias("method"), F.lit(budget).cast("long").alias("budget_tokens"), "category", "doc_id", "start", "len", (F.round(F.col(score), DIGITS) if score else F.lit(None).cast("double")).alias("score"), F.col("rnk").cast("long").alias("rnk"), (F.col("rnk") * L).cast("long").alias("cum_tokens"))


def top_by_budget(scored: DataFrame, budget: int, L: int, score: str = "lds", method: str = "attention", quota: str | dict = "proportional") -> DataFrame:
    """The best windows of each category, whole windows only, never above the budget."""
    if quota == "none":
        first = ranked(scored.withColumn("all", F.lit(0)), "all", _falling(score), _order(score), F.col("doc_id"), F.lit(wanted_windows(budget, L)))
        return _picked(first.drop("all"), method, budget, score, L)
    q = quotas(category_counts(scored), wanted_windows(budget, L), quota)
    return _picked(_ranked(scored, q, _order(score), _falling(score)), method, budget, score, L)


def top_by_threshold(scored: DataFrame, budget: int, L: int, score: str = "lds", method: str = "attention", quota: str | dict = "proportional") -> DataFrame:
    """The same choice by thresholds: ranges of scores that lie within the quota whole are taken unsorted, only the one
    range of each category that the quota cuts is ranked."""
    return _by_threshold(scored, quotas(category_counts(scored), wanted_windows(budget, L), quota), _falling(score), _order(score)).select(
        F.lit(method).alias("method"), F.lit(budget).cast("long").alias("budget_tokens"), "category", "doc_id", "start", "len", F.round(F.col(score), DIGITS).alias("score")
    )


def _by_threshold(df: DataFrame, quota: dict[str, int], key: Column, order: list[Column]) -> DataFrame:
    """The first rows of each category, as many as its quota, and no rank."""
    names = ["category", "range", "part"]
    ranged = in_ranges(df, "category", key, F.col("doc_id"))
    sizes = ranged.groupBy(*names).agg(F.count("*").alias("range_rows"))
    upto = F.sum("range_rows").over(Window.partitionBy("category").orderBy("range", "part").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    room = sizes.withColumn("room", _quota_column(quota) - upto + F.col("range_rows")).where("room > 0").select(*names, "range_rows", "room")
    met = ranged.join(F.broadcast(room), names)
    band = met.where("range_rows > room").withColumn("rnk", F.row_number().over(Window.partitionBy(*names).orderBy(*order))).where(F.col("rnk") <= F.col("room"))
    return met.where("range_rows <= room").unionByName(band.drop("rnk")).drop("range", "part", "range_rows", "room")


def random_by_threshold(windows: DataFrame, budget: int, L: int, seed: int = 7) -> DataFrame:
    """random_by_budget without ranks: (category, doc_id, start, len) below a threshold of the seeded hash."""
    q = quotas(category_counts(windows), wanted_windows(budget, L))
    keyed = windows.withColumn("key", shuffle_key(seed, F.col("doc_id"), F.col("start")))
    return _by_threshold(keyed, q, _hashed(), _order("key", descending=False)).select("category", "doc_id", "start", "len")


def random_by_budget(windows: DataFrame, budget: int, L: int, seed: int = 7) -> DataFrame:
    """A choice that ignores content: the least keys of a seeded hash order, with the same quotas."""
    q = quotas(category_counts(windows), wanted_windows(budget, L))
    keyed = windows.withColumn("key", shuffle_key(seed, F.col("doc_id"), F.col("start")))
    return _picked(_ranked(keyed, q, _order("key", descending=False), _hashed()), "random", budget, None, L)


def ladder(scored: DataFrame, L: int, steps: tuple[int, ...] = LADDER, score: str | None = "lds", method: str = "attention", seed: int = 7, share: int = 40) -> DataFrame:
    """Nested choices at several budgets from one ranking: a window carries the least step that takes it."""
    counts = category_counts(scored)
    unit = unit_tokens(sum(counts.values()), L, share)
    df = scored if score else scored.withColumn("key", shuffle_key(seed, F.col("doc_id"), F.col("start")))
    order, key = (_order(score), _falling(score)) if score else (_order("key", descending=False), _hashed())
    most = quotas(counts, wanted_windows(max(steps) * unit, L))
    found = _ranked(df, most, order, key)
    step = F.lit(None).cast("int")
    for s in sorted(steps, reverse=True):
        step = F.when(F.col("rnk") <= _quota_column(quotas(counts, wanted_windows(s * unit, L))), s).otherwise(step)
    out = found.withColumn("step", step).where(F.col("step").isNotNull())
    return out.select(F.lit(method).alias("method"), "step", "category", "doc_id", "start", "len", F.col("rnk").cast("long").alias("rnk"))


def mix_short(picked: DataFrame, shorts: DataFrame, ratio: float, seed: int = 7) -> DataFrame:
    """The choice with short documents beside it, about ``ratio`` of its tokens, in seeded order."""
    tokens = picked.agg(F.sum("len")).first()[0] or 0
    keyed = shorts.where("n > 0").select("category", "doc_id", F.lit(0).cast("long").alias("start"), F.col("n").cast("int").alias("len"), F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string"))).alias("key"))
    # running sums over 256 ranges of the key, so that no sort is global
    bucket = keyed.withColumn("b", F.substring("key", 1, 2))
    per = bucket.groupBy("b").agg(F.sum("len").alias("t")).collect()
    before, total = {}, 0
    for r in sorted(per, key=lambda r: r.b):
        before[r.b] = total
        total += r.t
    base = F.create_map(*[x for b, t in before.items() for x in (F.lit(b), F.lit(t))]) if before else F.create_map().cast("map<string,int>")
    upto = F.sum("len").over(Window.partitionBy("b").orderBy("key", "doc_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)) + F.try_element_at(base, F.col("b"))
    chosen = bucket.withColumn("upto", upto).where(F.col("upto") <= int(ratio * tokens))
    long = picked.select("category", "doc_id", "start", "len", F.lit("long").alias("kind"))
    return long.unionByName(chosen.select("category", "doc_id", "start", "len", F.lit("short").alias("kind")))
