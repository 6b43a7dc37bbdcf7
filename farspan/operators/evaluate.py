"""Measures: agreement, label rates, diversity, rank statistics, costs, probes, and a count-based proxy model."""

from __future__ import annotations

import hashlib
from dataclasses import replace

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from farspan.sources.intermediate import lean_batches
from farspan.operators import kernel
from farspan.operators.ranks import in_ranges, running
from farspan.operators.profiles import Decoder, HexDot
from farspan.operators.score import per_batch, per_window

NIAH = ("single_1", "single_2", "single_3", "multikey_1", "multikey_2", "multikey_3", "multivalue", "multiquery")
RULER_MORE = ("variable_tracking", "common_words", "frequent_words", "qa_1", "qa_2")
#: Stand-ins of long-text tasks that are no needles of made-up words: a lead, a repeated line, a pair of turns.
LONG_TEXT = ("lead", "lines", "turns")
DEPTHS = tuple(d / 10 for d in range(11))
FILLER = ("grass", "is", "green", "sky", "is", "blue", "sun", "is", "yellow")


def label_rates(picked: DataFrame, labels: DataFrame, by: list[str]) -> DataFrame:
    """Share of good and toxic documents among the labelled choices, and how many choices carry a label."""
    joined = picked.join(labels.select("doc_id", "quality", "toxic"), "doc_id", "left")
    return joined.groupBy(*by).agg(F.count("*").alias("windows"), F.count("quality").alias("labelled"), F.avg("quality").alias("good"), F.avg("toxic").alias("toxic"))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Common windows and Jaccard similarity of two choices."""
    x = a.select("doc_id", "start", F.lit(1).alias("in_a"))
    y = b.select("doc_id", "start", F.lit(1).alias("in_b"))
    both = x.join(y, ["doc_id", "start"], "full_outer")
    common, size = F.count_if(F.col("in_a").isNotNull() & F.col("in_b").isNotNull()), F.count("*")
    return both.agg(common.alias("common"), size.alias("either"), F.when(size > 0, common / size).otherwise(1.0).alias("jaccard"))


def rank_correlation(scored: DataFrame, x: str, y: str) -> DataFrame:
    """Spearman correlation of two scores; ranks with ties averaged, counted per distinct value."""

    def mean_ranks(df: DataFrame, c: str) -> DataFrame:
        per = df.groupBy(c).agg(F.count("*").alias("m")).withColumn("all", F.lit(0))
        upto = running(in_ranges(per, "all", F.col(c)), "all", [F.col(c)], {"upto": F.col("m")})
        return upto.select(c, (F.col("upto") - (F.col("m") - 1) / 2).alias(f"r_{c}"))

    both = scored.select(F.round(x, 6).alias("x"), F.round(y, 6).alias("y"))
    return both.join(mean_ranks(both, "x"), "x").join(mean_ranks(both, "y"), "y").agg(F.corr("r_x", "r_y").alias("spearman"))


def diversity(picked_windows: DataFrame, by: str) -> DataFrame:
    """Distinct tokens, distinct windows and documents of each choice, the largest category's share of its windows, and
    the share of windows that nearly repeat another one: eight words in a row that start at a hash divisible by 16 are
    compared, and half of a window's being found in windows before it (by doc_id and start) counts."""
    words = picked_windows.select(by, F.explode("toks").alias("tok")).groupBy(by).agg(F.count_distinct("tok").alias("types"), F.count("*").alias("tokens"))
    texts = picked_windows.groupBy(by).agg(F.count("*").alias("windows"), F.count_distinct("doc_id").alias("documents"), F.count_distinct(F.md5(F.concat_ws(" ", "toks"))).alias("distinct_windows"))
    share = picked_windows.groupBy(by, "category").agg(F.count("*").alias("n")).groupBy(by).agg((F.max("n") / F.sum("n")).alias("largest_category"))
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("toks") - 7)), lambda i: F.md5(F.concat_ws(" ", F.slice("toks", i, 8))))
    marks = picked_windows.select(by, "doc_id", "start", F.explode(F.array_distinct(F.filter(grams, lambda g: F.endswith(g, F.lit("0"))))).alias("g"))
    first = marks.groupBy(by, "g").agg(F.min(F.struct("doc_id", "start")).alias("first"))
    again = marks.join(first, [by, "g"]).groupBy(by, "doc_id", "start").agg(F.avg((F.struct("doc_id", "start") != F.col("first")).cast("int")).alias("again"))
    near = again.groupBy(by).agg(F.count_if(F.col("again") >= 0.5).alias("near"))
    return texts.join(words, by).join(share, by).join(near, by, "left").withColumn("near_copies", F.coalesce(F.col("near"), F.lit(0)) / F.col("windows")).drop("near")


def auc(scored: DataFrame, score: str, label: str, digits: int = 9) -> DataFrame:
    """Probability that a positive scores above a negative (ties half), from running counts over distinct scores."""
    x = scored.select(F.round(score, digits).alias("x"), F.col(label).cast("long").alias("y"))
    per = x.groupBy("x").agg(F.sum("y").alias("p"), F.sum(1 - F.col("y")).alias("n")).withColumn("all", F.lit(0))
    upto = running(in_ranges(per, "all", F.col("x")), "all", [F.col("x")], {"upto": F.col("n")})
    won = upto.select("p", "n", (F.col("p") * (F.col("upto") - F.col("n") / 2)).alias("w"))
    return won.agg(F.sum("p").alias("positives"), F.sum("n").alias("negatives"), (F.sum("w") / (F.sum("p") * F.sum("n"))).alias("auc"))


def planted_pairs(windows: DataFrame, length: int = 32, seed: int = 7) -> DataFrame:
    """Pairs of windows that differ only in a far link, one row each: in the last quarter of a window (of L tokens, L >= 4 x
    length) stands a passage of its own first quarter (toks), or of another window's instead (other).  Every window is used;
    the only window of a category is its own other one."""
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string"), F.col("start").cast("string")))
    keyed = windows.withColumn("key", key).withColumn("slot", F.conv(F.substring("key", 1, 2), 16, 10).cast("int"))
    # the other window is the next one of the category in key order, the first one after the last: looked for in 256 ranges
    # of the key, whose first windows form a small ring of their own
    ring, names = Window.partitionBy("category", "slot").orderBy("key", "doc_id", "start"), ["category", "slot"]
    nearby = keyed.withColumn("next", F.lead(F.slice("toks", 1, length)).over(ring))
    firsts = keyed.withColumn("k", F.row_number().over(ring)).where("k = 1").select(*names, F.slice("toks", 1, length).alias("first"))
    round_ = Window.partitionBy("category").orderBy("slot")
    begins = Window.partitionBy("category").orderBy("slot").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    after = firsts.select(*names, F.coalesce(F.lead("first").over(round_), F.first("first").over(begins)).alias("after"))
    other = nearby.join(F.broadcast(after), names).withColumn("other", F.coalesce("next", "after"))
    toks = F.concat(F.slice("toks", 1, F.col("len") - length), F.slice("toks", 1, length))
    return other.select("doc_id", "category", "start", "len", toks.alias("toks"), "other")


def planted(windows: DataFrame, length: int = 32, seed: int = 7) -> DataFrame:
    """``planted_pairs`` with a row for each window: with its own passage (label 1), and with the other one's (label 0)."""
    both = planted_pairs(windows, length, seed).withColumn("label", F.explode(F.array(F.lit(1), F.lit(0))))
    toks = F.when(F.col("label") == 1, F.col("toks")).otherwise(F.concat(F.slice("toks", 1, F.col("len") - length), F.col("other")))
    return both.select("doc_id", "category", (F.col("start") * 2 + F.col("label")).alias("start"), "len", "label", toks.alias("toks"))


# --- probes -------------------------------------------------------------------------------------------------


def _word(kind: str, seed: str) -> str:
    h = hashlib.md5(seed.encode()).hexdigest()
    return str(int(h[:12], 16) % 10**7).zfill(7) if kind == "number" else h


def kind_of(task: str) -> str:
    return "hex" if task in ("single_3", "multikey_3") else "number"


def seed_parts(task: str, depth: float, role: str, i: int) -> tuple[str, str]:
    """What stands before and behind a probe's number in the seed of a made-up word."""
    return (f"{role}{task}:", f":{depth}:{i}") if role in "kv" else (f"{task}:", f":{depth}:0{role}{i}")


def made_up(task: str, number: int, depth: float):
    """The made-up words of a probe: keys (k) and values (v) of its needles, keys (d) and values (e) of what it is hidden in."""
    kind = kind_of(task)

    def name(role: str, i: int) -> str:
        seed = str(number).join(seed_parts(task, depth, role, i))
        if role in "ve":
            return "value-" + _word(kind, seed)
        return "key-" + _word("hex", seed)[: 12 if role == "k" and kind == "hex" else 6]

    return name


def numbered(df: DataFrame, key: str, name: str) -> DataFrame:
    """df with its rank from 0 in the order of a hexadecimal key, counted in 4,096 ranges of the key and added up."""
    at = df.withColumn("range", F.substring(key, 1, 3))
    before = F.coalesce(F.sum("count").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sizes = at.groupBy("range").count().select("range", before.alias("before"))
    within = F.row_number().over(Window.partitionBy("range").orderBy(*dict.fromkeys([key, *df.columns])))
    return at.withColumn("within", within).join(F.broadcast(sizes), "range").withColumn(name, F.col("before") + F.col("within") - 1).drop("range", "within", "before")


def haystacks(windows: DataFrame, items: DataFrame) -> DataFrame:
    """doc_id (a running number), toks, passage: every window (key, toks) with a test item (key, passage), and every item
    with a window.

    Both are ranked by key and paired by rank; the fewer ones begin anew.  Without windows the prose is empty, without
    items the passage.
    """
    n, m = windows.count(), items.count()
    if n >= m > 0:  # the rank of a window is its number already, and its words are moved once
        ranked = numbered(windows, "key", "doc_id").withColumn("i", F.col("doc_id") % m)
        return ranked.join(numbered(items, "key", "i").select("i", "passage"), "i", "left").select("doc_id", "toks", "passage")
    pairs = windows.sparkSession.range(max(n, m)).select(F.col("id").alias("doc_id"), (F.col("id") % max(1, n)).alias("w"), (F.col("id") % max(1, m)).alias("i"))
    none = F.array().cast("array<string>")
    both = pairs.join(numbered(windows, "key", "w").select("w", "toks"), "w", "left").join(numbered(items, "key", "i").select("i", "passage"), "i", "left")
    return both.select("doc_id", F.coalesce("toks", none).alias("toks"), F.coalesce("passage", none).alias("passage"))


def probe(task: str, number: int, depth: float, haystack: list[str], length: int, passage: list[str] | tuple = (), name=None) -> dict:
    """One probe of ``length`` tokens: needles in a haystack, a question at the end, and where the answers stand.

    The passage follows the first needle whole, and needles hide in the whole haystack, or in as many words made up for it; if that
    takes more than ``length`` tokens, the probe is longer (LONG_TEXT: the haystack is shorter).  A needle is ``key is value``; the question repeats the key.  Positions count from 0.
    ``name``: other made-up words, see ``made_up``.
    """
    filler, many = list(FILLER), task in ("multikey_2", "multikey_3")
    name = name or made_up(task, number, depth)
    key = lambda i: name("k", i)
    value = lambda i: name("v", i)
    asked, answers = [key(0)], 1
    needles = [[key(0), "is", value(0)]]
    if task.startswith("multikey") or task in ("qa_1", "qa_2"):
        needles += [[key(i), "is", value(i)] for i in range(1, 4)]
    elif task == "multivalue":
        needles += [[key(0), "is", value(i)] for i in range(1, 4)]
        answers = 4
    elif task == "multiquery":
        needles += [[key(i), "is", value(i)] for i in range(1, 4)]
        asked, answers = [key(i) for i in range(4)], 4
    elif task == "variable_tracking":
        needles = [[key(0), "is", value(0)], [key(1), "is", key(0)], [key(2), "is", key(1)]]
    elif task in ("common_words", "frequent_words"):
        needles = [[key(0), "is", value(0)]] * (3 if task == "common_words" else 5)
    elif task in LONG_TEXT and haystack:
        # the lead asked for by its first words, a line by its first three, a pair of turns by the first of the two
        size, first = {"lead": (16, 4), "lines": (8, 3), "turns": (16, 8)}[task]
        part = haystack[-size:] if task == "lines" else haystack[:size]
        haystack = haystack[: -len(part)] if task == "lines" else haystack[len(part) :]
        needles, asked = [part], part[:first]
    question = ["what", "is", *asked]
    room = max(0 if task in LONG_TEXT else len(haystack), length - len(question) - sum(map(len, needles)) - len(passage))
    if many:
        hay = [w for i in range(room // 3 + 1) for w in (name("d", i), "is", name("e", i))][:room]
    else:
        source = filler if task == "single_1" or not haystack else haystack
        hay = (source * (room // len(source) + 1))[:room]
    places = sorted({min(room, int(room * ((depth + i / len(needles)) % 1.0001))) for i in range(len(needles))})
    while len(places) < len(needles):
        places.append(places[-1])
    toks, spots, last = [], [], 0
    for p, needle in zip(places, needles, strict=True):
        toks += hay[last:p]
        spots.append(range(len(toks), len(toks) + len(needle)))
        toks += needle
        if len(spots) == 1:
            toks += passage
        last = p
    toks += hay[last:]
    at = len(toks) + 2
    toks += question
    wanted = spots if answers > 1 or task in ("common_words", "frequent_words", "variable_tracking") else spots[:1]
    return {"task": task, "depth": depth, "toks": toks, "query_pos": list(range(at, at + len(asked))), "answer_pos": [i for s in wanted for i in s], "spans": [[s[0], s[-1]] for s in wanted], "answers": answers}


def probes(haystacks: DataFrame, tasks: tuple[str, ...] = NIAH, depths: tuple[float, ...] = DEPTHS, length: int = 256, each: int = 1) -> DataFrame:
    """probes: for every haystack (doc_id, toks, and a passage if there is one) one probe per task and depth."""
    schema = "task string, depth double, probe_id string, toks array<string>, query_pos array<int>, answer_pos array<int>, spans array<array<int>>, answers int"

    def run(batches):
        import pandas as pd

        columns = ["task", "depth", "probe_id", "toks", "query_pos", "answer_pos", "spans", "answers"]
        for pdf in batches:
            for doc, toks, passage in zip(pdf["doc_id"], pdf["toks"], pdf["passage"], strict=True):
                rows = []
                for task in tasks:
                    for depth in depths:
                        for i in range(each):
                            p = probe(task, int(doc) * each + i, depth, list(toks), length, list(passage))
                            rows.append(p | {"probe_id": f"{task}:{doc}:{depth}:{i}"})
                yield pd.DataFrame(rows, columns=columns)

    passage = F.col("passage") if "passage" in haystacks.columns else F.array().cast("array<string>")
    return lean_batches(haystacks).select("doc_id", "toks", passage.alias("passage")).mapInPandas(run, schema)


def hit_share(profile, k: int, toks: list[str], query: list[int], spans: list, answers: int) -> float:
    """Share of the answer spans that hold one of the most attended far tokens of the question, as many as there are
    answers (the lowest position wins ties)."""
    total, state = None, profile.state(toks)
    for q in query:
        p = profile.some_rows(state, np.array([q])).mean(axis=0)[0]
        p[max(0, q - k + 1) :] = 0
        total = p if total is None else p + _padded(total, len(p))
    best = (-total).argsort(kind="stable")[:answers]
    return len({s for b in best for s, (x, y) in enumerate(spans) if x <= b <= y}) / answers


#: Probes that are looked at together.
PROBES = 8


def hit_shares(profile: Decoder, k: int, asked: list[dict]) -> list[float]:
    """``hit_share`` of many probes under a decoder's first layer, whose projections depend on the token alone: probes of one
    length and number of questions are looked at together, and only the rows of the questions are made."""
    out, alike = [0.0] * len(asked), {}
    for i, p in enumerate(asked):
        alike.setdefault((len(p["toks"]), len(p["query_pos"])), []).append(i)
    for (L, questions), rows in alike.items():
        for at in range(0, len(rows), PROBES):
            some = [asked[i] for i in rows[at : at + PROBES]]
            n, number = len(some), {}
            codes = np.array([[number.setdefault(t, len(number)) for t in p["toks"]] for p in some])
            q, keys, _ = profile.states(list(number), codes)
            heads, groups, width = q.shape[1], keys.shape[1], q.shape[3]
            places, columns, total = np.array([p["query_pos"] for p in some]), np.arange(L)[None], np.zeros((n, L))
            for j in range(questions):
                own = places[:, j, None]
                p = np.matmul(q[np.arange(n), :, places[:, j]].reshape(n, groups, heads // groups, width), keys.transpose(0, 1, 3, 2)).reshape(n, heads, L).astype(np.float64)
                np.copyto(p, -np.inf, where=(columns > own)[:, None])
                p -= p.max(axis=2, keepdims=True)
                np.exp(p, out=p)
                mean = (p / p.sum(axis=2, keepdims=True)).mean(axis=1)
                total += np.where(columns <= own - k, mean, 0.0)
            best = (-total).argsort(axis=1, kind="stable")
            for i, p, row in zip(rows[at : at + PROBES], some, best, strict=True):
                out[i] = len({s for b in row[: p["answers"]] for s, (x, y) in enumerate(p["spans"]) if x <= b <= y}) / p["answers"]
    return out


def _in_batches(haystacks: DataFrame, answer, schema: str) -> DataFrame:
    """answer(numbers, haystacks, passages) -> columns, for a few haystacks at a time."""
    from farspan.operators.probe_batch import TOGETHER

    def run(batches):
        import pyarrow as pa

        kinds = {"string": pa.string(), "double": pa.float64(), "int": pa.int32()}
        fields = [(n, kinds[t]) for n, t in (x.split() for x in schema.split(", "))]
        for big in batches:
            for a in range(0, big.num_rows, TOGETHER):
                numbers, hays, passages = (c.to_pylist() for c in big.slice(a, TOGETHER).columns)
                columns = answer([int(n) for n in numbers], [list(h) for h in hays], [list(p) for p in passages])
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, (_, t) in zip(columns, fields, strict=True)], names=[n for n, _ in fields])

    passage = F.col("passage") if "passage" in haystacks.columns else F.array().cast("array<string>")
    return lean_batches(haystacks).select("doc_id", "toks", passage.alias("passage")).mapInArrow(run, schema)


def probe_digests(haystacks: DataFrame, tasks: tuple[str, ...] = NIAH, depths: tuple[float, ...] = DEPTHS, length: int = 256) -> DataFrame:
    """(task, depth, probe_id, len, answers, h): size, answer words and MD5 of the text of each of ``probes``, whose words are
    never moved."""

    def answer(numbers, hays, passages):
        from farspan.operators.probe_batch import texts

        task, depth, number, size, held, h = zip(*texts(numbers, hays, passages, tasks, depths, length), strict=True)
        return task, depth, [f"{t}:{n}:{d}:0" for t, d, n in zip(task, depth, number, strict=True)], size, held, h

    return _in_batches(haystacks, answer, "task string, depth double, probe_id string, len int, answers int, h string")


def probed(haystacks: DataFrame, profiles: list, k: int, tasks: tuple[str, ...] = NIAH, depths: tuple[float, ...] = DEPTHS, length: int = 256) -> DataFrame:
    """(profile, task, depth, probe_id, hit): probes made and answered in one pass, so that no probe is ever moved."""

    def answer(numbers, hays, passages):
        from farspan.operators.probe_batch import hits

        slow, rows = [x for x in profiles if not isinstance(x, HexDot)], []
        for x in profiles:
            if x not in slow:
                for n, names, found in hits(numbers, hays, passages, tasks, depths, length, x.D, x.spread, k):
                    rows += [(x.name, task, depth, f"{task}:{n}:{depth}:0", hit) for (task, depth), hit in zip(names, found.tolist(), strict=True)]
        for n, hay, passage in zip(numbers, hays, passages, strict=True) if slow else ():
            asked = [probe(task, n, depth, hay, length, passage) for task in tasks for depth in depths]
            for x in slow:
                together = isinstance(x, Decoder) and x.layer == 1
                found = hit_shares(x, k, asked) if together else [hit_share(x, k, p["toks"], p["query_pos"], p["spans"], p["answers"]) for p in asked]
                rows += [(x.name, p["task"], p["depth"], f"{p['task']}:{n}:{p['depth']}:0", hit) for p, hit in zip(asked, found, strict=True)]
        return zip(*rows, strict=True) if rows else [[]] * 5

    return _in_batches(haystacks, answer, "profile string, task string, depth double, probe_id string, hit double")


def tallied(haystacks: DataFrame, profile: HexDot, k: int, tasks: tuple[str, ...] = NIAH, depths: tuple[float, ...] = DEPTHS, length: int = 256) -> DataFrame:
    """(task, hits, probes): ``probed`` summed up where the probes are answered, a row for each task and partition."""

    def run(batches):
        import pyarrow as pa

        from farspan.operators.probe_batch import hits

        total, seen, names = 0.0, 0, ()
        for batch in batches:
            numbers, hays, passages = (c.to_pylist() for c in batch.columns)
            for _, names, found in hits([int(n) for n in numbers], hays, passages, tasks, depths, length, profile.D, profile.spread, k):
                total, seen = total + found, seen + 1
        if seen:
            held: dict[str, list[float]] = {}
            for (task, _), x in zip(names, total.tolist(), strict=True):
                held.setdefault(task, []).append(x)
            yield pa.RecordBatch.from_pydict({"task": list(held), "hits": [sum(x) for x in held.values()], "probes": [seen * len(x) for x in held.values()]})

    passage = F.col("passage") if "passage" in haystacks.columns else F.array().cast("array<string>")
    return lean_batches(haystacks).select("doc_id", "toks", passage.alias("passage")).mapInArrow(run, "task string, hits double, probes long")


def probe_hits(asked: DataFrame, profile, k: int) -> DataFrame:
    """Does far attention of the question fall on the answers of these probes?  See ``hit_share``."""
    import pandas as pd

    def run(batches):
        for pdf in batches:
            rows = zip(pdf["task"], pdf["depth"], pdf["probe_id"], pdf["toks"], pdf["query_pos"], pdf["spans"], pdf["answers"], strict=True)
            out = [(task, depth, name, hit_share(profile, k, list(toks), [int(q) for q in query], spans, int(answers))) for task, depth, name, toks, query, spans, answers in rows]
            yield pd.DataFrame(out, columns=["task", "depth", "probe_id", "hit"])

    return asked.mapInPandas(run, "task string, depth double, probe_id string, hit double")


def _padded(x, n: int):
    return np.concatenate([x, np.zeros(n - len(x))])


def accuracy(hits: DataFrame) -> DataFrame:
    """Per task in percent, and their mean in a row of its own; of single hits or of sums (``tallied``)."""
    if "hits" in hits.columns:
        per = hits.groupBy("task").agg((100 * (F.sum("hits") / F.sum("probes"))).alias("accuracy"), F.sum("probes").alias("probes"))
    else:
        per = hits.groupBy("task").agg((100 * F.avg("hit")).alias("accuracy"), F.count("*").alias("probes"))
    return per.unionByName(per.agg(F.lit("mean").alias("task"), F.avg("accuracy").alias("accuracy"), F.sum("probes").alias("probes")))


def grouped_mean(scores: DataFrame, weights: dict[str, int]) -> DataFrame:
    """Mean of group means, and mean weighted by the number of tasks of each group."""
    w = F.lit(None).cast("int")
    for g, n in weights.items():
        w = F.when(F.col("group") == g, n).otherwise(w)
    held = scores.withColumn("w", w)
    return held.groupBy("method").agg(F.avg("score").alias("macro_mean"), (F.sum(F.col("score") * F.col("w")) / F.sum("w")).alias("task_mean"))


# --- costs --------------------------------------------------------------------------------------------------


def cost_rows(windows: DataFrame, L: int, segment: int, layers: int = 32) -> DataFrame:
    """Analytic cost of both methods and both model sizes on a window set: passes, token evaluations, multiplications."""
    n = windows.agg(F.count("*").alias("windows"))
    S = L // segment
    small, large = (128, 4, 2, 32), (512, 8, 2, 64)
    rows = []
    for name, (d, heads, kv, width) in (("small", small), ("large", large)):
        pair, projection = heads * width * L * (L + 1) // 2, L * d * width * (heads + kv)
        rows.append(("attention", name, 1, L, pair + projection, 1, layers))
        rows.append(("segments", name, S * (S - 1) // 2, S * (S - 1) // 2 * 2 * segment + S * segment, (pair + projection) * layers * (S * (S - 1) // 2 * 2 * segment + S * segment) // L, layers, layers))
    spark = windows.sparkSession
    plan = spark.createDataFrame(rows, "method string, model string, calls long, tokens long, ops long, layers int, of_layers int")
    per = plan.join(F.broadcast(n), F.lit(True))
    return per.select("method", "model", "windows", (F.col("calls") * F.col("windows")).alias("model_calls"), (F.col("tokens") * F.col("windows")).alias("token_evaluations"), (F.col("ops").cast("double") * F.col("windows")).alias("multiplications"), (F.col("layers") / F.col("of_layers")).alias("share_of_pass"))


def ratios(costs: DataFrame, measure: str) -> DataFrame:
    """Each method and model against the attention scorer with the small model."""
    base = costs.where("method = 'attention' and model = 'small'").select(F.col(measure).alias("base"))
    return costs.join(F.broadcast(base), F.lit(True)).select("method", "model", measure, (F.col(measure) / F.col("base")).alias("ratio"))


# --- proxy model --------------------------------------------------------------------------------------------


def proxy_lm(picked: DataFrame, heldout: DataFrame, k: int, vocabulary: int = 2_000) -> DataFrame:
    """Held-out nats per token of an interpolated unigram, bigram and far-cache model fitted on a choice.

    The vocabulary is the commonest tokens of the choice (at most ``vocabulary``) and one unknown class.  Behind a class
    that the choice holds, bigram and unigram count half each.  The cache's weight is the rate at which a token of the
    choice stood k or more places earlier already, within [0.01, 0.5].
    """
    unknown, c = F.lit(" "), F.col

    def flat(df: DataFrame) -> DataFrame:
        at = F.transform("toks", lambda t, i: F.struct(i.alias("i"), t.alias("tok"), F.when(i > 0, F.try_element_at("toks", i)).alias("prev")))
        return df.select("doc_id", "start", F.inline(at))

    def far(df: DataFrame) -> DataFrame:
        first = Window.partitionBy("doc_id", "start", "tok")
        return df.withColumn("again", (c("i") - F.min("i").over(first) >= k).cast("int"))

    own = flat(picked)
    top = own.groupBy("tok").agg(F.count("*").alias("c")).orderBy(F.desc("c"), "tok").limit(vocabulary)
    known = top.join(F.broadcast(own.agg(F.count("*").alias("n"))), F.lit(True)).select("tok", (c("c") / (c("n") + 1)).alias("p"))
    rest = known.agg((1 - F.sum("p")).alias("p_rest"))
    before = known.select(c("tok").alias("prev"), F.lit(1).alias("prev_known"))

    def classed(df: DataFrame) -> DataFrame:
        met = df.join(F.broadcast(known), "tok", "left").join(F.broadcast(before), "prev", "left")
        return met.withColumns({"now": F.when(c("p").isNotNull(), c("tok")).otherwise(unknown), "last": F.when(c("prev").isNotNull(), F.when(c("prev_known") == 1, c("prev")).otherwise(unknown))})

    pairs = classed(own).where("last is not null").groupBy("last", "now").agg(F.count("*").alias("n2"))
    heads = pairs.groupBy("last").agg(F.sum("n2").alias("n1"))
    weight = far(own).agg(F.greatest(F.lit(0.01), F.least(F.lit(0.5), F.avg("again"))).alias("lam"))
    held = classed(flat(heldout)).join(pairs, ["last", "now"], "left").join(F.broadcast(heads), "last", "left")
    held = held.join(F.broadcast(rest), F.lit(True)).join(F.broadcast(weight), F.lit(True))
    seen = F.count("*").over(Window.partitionBy("doc_id", "start", "tok").orderBy("i").rangeBetween(Window.unboundedPreceding, -k))
    cached = held.withColumn("cache", F.when(c("i") >= k, seen / F.greatest(F.lit(1), c("i") - k + 1)).otherwise(0.0))
    lam = F.when(c("i") >= k, c("lam")).otherwise(0.0)
    one = F.coalesce(c("p"), c("p_rest"))
    context = F.when(c("n1").isNotNull(), 0.5 * one + 0.5 * F.coalesce(c("n2"), F.lit(0)) / c("n1")).otherwise(one)
    p = (1 - lam) * context + lam * c("cache")
    return cached.agg(F.avg(-F.log(F.greatest(p, F.lit(1e-12)))).alias("nats"), F.count("*").alias("tokens"), F.max("lam").alias("far_rate"))


def sink_by_layer(windows: DataFrame, make, layers: int) -> DataFrame:
    """Share of attention on the first token in each layer of a stack; make(layer) gives the profile."""
    profiles = [(j, make(j)) for j in range(1, layers + 1)]
    deepest, schema = profiles[-1][1], "layer int, sink double"
    mean = lambda rows: rows.groupBy("layer").agg(F.avg("sink").alias("sink_share"), F.count("*").alias("windows"))

    def alone(toks: list[str]) -> list[dict]:
        return [{"layer": j, "sink": kernel.token_strengths(p, toks, [0])[2]} for j, p in profiles]

    if not isinstance(deepest, Decoder) or any(p != replace(deepest, layer=j) for j, p in profiles):
        return mean(per_window(windows, alone, schema))

    def together(words: list[str], codes: np.ndarray) -> list[list[dict]]:
        """Layers of one stack: it runs once."""
        found = np.concatenate([deepest.sinks(words, codes[a : a + 16]) for a in range(0, len(codes), 16)])
        return [[{"layer": j, "sink": x} for j, x in enumerate(row, 1)] for row in found.tolist()]

    return mean(per_batch(windows, together, alone, schema))


def cell(x: Column, digits: int = 6) -> Column:
    return F.round(x, digits)
