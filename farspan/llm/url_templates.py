"""URL filter by path templates, in DataFrame functions only.

A url gets the verdict of the longest explicit rule that fits; any other gets the verdict of its template.
Templates form a tree per host: variable segments (numbers, hexadecimal runs, dates, words that hold digits) are
wildcards from the start; then, level by level from the host down, branches whose labelled rate of bad pages
doesn't differ significantly from that of their siblings together, or that have too few labels to tell, become
one wildcard branch; of the others, those that are alike on the worse or the better side become one branch each.
The tree is as deep as the paths are: only where no branch has labels enough to be split any further is the rest
filled up with the wildcards that it would get anyway.  A final template is blocked if its smoothed share of bad
labelled pages reaches a threshold: the share is drawn towards the host's, and the host's towards that of all pages.

Urls are counted per host and raw template before anything is compared, so the tree is built from one row per
raw template, however many pages share it.  What belongs to a frequent host, branch or template is broadcast (a
bounded number of rows), so no task gets all of its rows.

A null url, or one without ``://``, has an empty host and path.  Labels are (page_id, bad) with bad 0 or 1; null or
unknown labels count as none, of several the largest counts.  Without labels nothing is blocked but by rules.
Repeated rows are judged alike, an empty table gives an empty result, and other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farspan.llm.storage import spread_join, written

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Labelled pages a branch needs before it can differ from its siblings.
LEAST_LABELS = 8
Z = 2.58
SMOOTHING = 10.0
BLOCK_AT = 0.5

Rule = tuple[str, str, str]  # verdict, host, path


def split_url(url: Column) -> tuple[Column, Column]:
    """(host, path): host with A-Z lower-cased."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise("")
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, LOWER)
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def matching_rule(host: Column, path: Column, rules: list[Rule]) -> tuple[Column, Column]:
    """(rule, verdict) of the longest fitting rule, null where none fits."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for v, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        name, verdict = F.when(fits, F.lit(h + p)).otherwise(name), F.when(fits, F.lit(v)).otherwise(verdict)
    return name, verdict


def raw_template(path: Column) -> Column:
    """Segments with the variable ones as wildcards; the extension of a file stays."""
    parts = F.filter(F.split(path, "/"), lambda s: s != "")

    def general(s: Column) -> Column:
        s = F.regexp_replace(s, r"^[0-9]+", "{n}")
        s = F.regexp_replace(s, r"^[0-9a-fA-F-]{8,}(?=\.|$)", "{x}")
        return F.regexp_replace(s, r"^[^.{]*[0-9][^.]*(?=\.|$)", "{w}")

    return F.transform(parts, general)


def _differs(n: str, b: str, nn: str, bb: str) -> Column:
    """Does the bad rate b of n differ from that of the rest of bb of nn, both large enough to tell?"""
    n, b, m, c, p = F.col(n), F.col(b), F.col(nn) - F.col(n), F.col(bb) - F.col(b), F.col(bb) / F.col(nn)
    spread = F.sqrt(p * (1 - p) * (1 / n + 1 / m))
    return F.when((n >= LEAST_LABELS) & (m >= LEAST_LABELS), F.when(spread > 0, F.abs(b / n - c / m) >= Z * spread).otherwise(False)).otherwise(False)


def template_tree(counted: DataFrame, total: int) -> DataFrame:
    """counted (host, raw, labelled, bad, pages; ``total`` rows) with the final template of each raw one."""
    tree, level, node = counted.withColumn("template", F.array().cast("array<string>")), 0, ["host", "template"]
    while True:
        deeper = tree.where(F.size("raw") > level)
        # a branch can differ only if it and its siblings have labels enough
        if not deeper.groupBy(*node).agg(F.sum("labelled").alias("n")).where(F.col("n") >= 2 * LEAST_LABELS).take(1):
            break
        level += 1
        now = deeper.withColumn("seg", F.element_at("raw", F.lit(level)))
        branch = written(now.groupBy(*node, "seg").agg(F.sum("labelled").alias("n"), F.sum("bad").alias("b"), F.count("*").alias("rows")), "url-branches")
        above = branch.groupBy(*node).agg(F.sum("n").alias("nn"), F.sum("b").alias("bb"), F.count("*").alias("branches"))
        beside = spread_join(branch, above, node, "branches", total).withColumn("differs", _differs("n", "b", "nn", "bb"))
        beside = beside.withColumn("side", F.col("differs") & (F.col("b") * F.col("nn") > F.col("bb") * F.col("n")))
        differing = beside.where("differs")
        sides = differing.groupBy(*node, "side").agg(F.sum("n").alias("sn"), F.sum("b").alias("sb"), F.count("*").alias("branches"))
        alone = (F.col("sn") == F.col("n")) | _differs("n", "b", "sn", "sb")
        own = spread_join(differing, sides, [*node, "side"], "branches", total)
        own = own.select(*node, "seg", "rows", F.when(alone, F.col("seg")).when(F.col("side"), "*worse").otherwise("*better").alias("name"))
        named = own.unionByName(beside.where(~F.col("differs")).select(*node, "seg", "rows", F.lit("*").alias("name")))
        merged = spread_join(now, named, [*node, "seg"], "rows", total)
        columns = ["host", "raw", "labelled", "bad", "pages"]
        # written, as the next level reads it several times
        tree = written(merged.select(*columns, F.concat("template", F.array("name")).alias("template")).unionByName(tree.where(F.size("raw") < level).select(*columns, "template")), "url-tree")
    rest = F.array_repeat(F.lit("*"), F.greatest(F.lit(0), F.size("raw") - F.size("template")))
    return tree.withColumn("template", F.concat("template", rest))


def judge(pages: DataFrame, labels: DataFrame, rules: list[Rule], id_col: str = "page_id", url_col: str = "url", block_at: float = BLOCK_AT) -> DataFrame:
    """(page_id, host, path, rule, verdict, template, purity) for every row of pages."""
    host, path = split_url(F.col(url_col).cast("string"))
    seen = pages.select(F.col(id_col).cast("long").alias("page_id"), host.alias("host"), path.alias("path"))
    seen = seen.withColumn("raw", raw_template(F.col("path")))
    marks = labels.select(F.col("page_id").cast("long").alias("page_id"), F.col("bad").cast("int").alias("bad")).where("page_id is not null and bad in (0, 1)").groupBy("page_id").agg(F.max("bad").alias("bad"))
    counted = seen.join(marks, "page_id", "left").groupBy("host", "raw").agg(F.count("bad").alias("labelled"), F.coalesce(F.sum("bad"), F.lit(0)).alias("bad"), F.count("*").alias("pages"))
    counted = written(counted, "url-templates")
    whole = counted.agg(F.sum("labelled").alias("n"), F.sum("bad").alias("b"), F.coalesce(F.sum("pages"), F.lit(0)).alias("pages"), F.count("*").alias("rows")).first()
    overall = whole.b / whole.n if whole.n else 0.0
    tree = template_tree(counted, whole.rows)
    final = tree.groupBy("host", "template").agg(F.sum("labelled").alias("n"), F.sum("bad").alias("b"), F.count("*").alias("rows"))
    hosts = counted.groupBy("host").agg(F.sum("labelled").alias("hn"), F.sum("bad").alias("hb"), F.count("*").alias("branches"))
    base = (F.col("hb") + SMOOTHING * overall) / (F.col("hn") + SMOOTHING)
    purity = 1 - (F.col("b") + SMOOTHING * base) / (F.col("n") + SMOOTHING)
    judged = spread_join(final, hosts, "host", "branches", whole.rows).select("host", "template", "rows", purity.alias("purity"))
    verdicts = spread_join(tree.select("host", "raw", "template", "pages"), judged, ["host", "template"], "rows", whole.rows)
    rule, ruled = matching_rule(F.col("host"), F.col("path"), rules)
    own = F.when(1 - F.col("purity") >= block_at, "block").otherwise("allow")
    shown = F.concat(F.lit("/"), F.concat_ws("/", "template"))
    return spread_join(seen, verdicts, ["host", "raw"], "pages", whole.pages).select("page_id", "host", "path", rule.alias("rule"), F.coalesce(ruled, own).alias("verdict"), shown.alias("template"), "purity")
