"""Jaccard self-join of documents by word n-grams, as a blocked sparse product of the incidence matrix.

Rows of the matrix are distinct shingle sets, columns are shingles.

* Column blocks, first pass.  Columns are dealt over the executors and only those entries enter that can still decide
  a link: with the columns ordered rare to frequent, two sets of sizes m and n that overlap in at least
  a(m, n) = ceil(3 (m + n) / 7) shingles (similarity 0.75) share one within the first m - a + 1 and n - a + 1 of them.
  Sizes and places give the row pairs that aren't excluded.  Where all common entries of a pair meet, their number is
  accumulated, and the pair goes if number and remaining places fall short.  A histogram of each row over column
  blocks bounds the overlap from above as well (the sum of block minima).
* Row blocks, second pass.  What is left is multiplied out: a block is one row and some PARTNERS of its partners, all
  as arrays of shingle numbers.  Overlap counts are accumulated over column ranges, and a partner goes as soon as
  count and rest fall below the bound.  No text is moved.

* Copies with equal sets are one row of the matrix, so groups of copies are never expanded.
* The column order comes from a count sketch of fixed size (2**22 counters) over all shingles of all texts.
  Its errors cost time only: any fixed order gives the exact result.
* A column with many entries is not paired out: first every entry meets only the column's most central row,
  frequent columns through salted parts whose number grows with the frequency; the links found merge most rows into
  components, and then only entries of different components are paired, the largest component of a column as one side.
  Where many rows have over three quarters of their shingles in common without a link, that is still quadratic.

Shingles are 64-bit hashes of the A-Z-lower-cased words, which tell two texts apart but for chances of about
m * n / 2**64.  A row is named by 64 bits of its set's 128-bit signature; sets that clash in those are found and named
by the other 64.  Null and empty texts have no shingle and link with nothing; a text of fewer than k words has its
whole word sequence as its one shingle; rows with a null id keep their own (null) component; repeated rows fall into
one class; an empty table gives an empty result; other columns of the input are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from farspan.llm import sketch
from farspan.llm.components import connected_components
from farspan.llm.storage import lean_batches, spread_join, texts, written
from farspan.llm.textbatch import all_chunks, shingle_sets, signed

#: From this frequency class on (excess of at least 2**9 over the sketch's noise) a column is dealt in salted parts.
HOT_CLASS = 10
#: Partners of a row that are multiplied in one block.
PARTNERS = 256
#: Ranges of columns over which a block accumulates overlaps.
RANGES = 4


def set_signature(own: np.ndarray) -> tuple[int, int]:
    digest = hashlib.blake2b(own.tobytes(), digest_size=16).digest()
    return int.from_bytes(digest[:8], "little", signed=True), int.from_bytes(digest[8:], "little", signed=True)


def node_of(own: np.ndarray, clashing: frozenset[int]) -> int:
    first, second = set_signature(own)
    return second if first in clashing else first


def cell_bits(n: int) -> int:
    """Cells of a set's histogram: about half its size, 16 to 4096."""
    return min(12, max(4, (n // 2).bit_length()))


def cell_counts(own: np.ndarray) -> bytes:
    bits = cell_bits(len(own))
    return np.minimum(255, np.bincount((own >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits)).astype(np.uint8).tobytes()


def overlap_bound(x: np.ndarray, y: np.ndarray) -> int | None:
    """Sum of cell minima; the finer histogram is folded. None if a saturated cell makes it no bound."""
    if len(x) == 0 or len(y) == 0 or x.max() == 255 or y.max() == 255:
        return None
    if len(x) != len(y):
        x, y = (a.astype(np.int64).reshape(min(len(x), len(y)), -1).sum(axis=1) for a in (x, y))
    return int(np.minimum(x, y).sum(dtype=np.int64))


def shingle_classes(df: DataFrame, k: int) -> DataFrame:
    """One row (doc_id, n_shingles, first, second, counts, text_hash) per document, and the partial sketches as rows with a block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = sketch.Sketch()
        names = ["doc_id", "n_shingles", "first", "second", "block", "counts", "text_hash"]
        for part, chunk in all_chunks(batches):
            sets = list(shingle_sets(chunk, k))
            if sets:
                seen.add(np.concatenate(sets))
            n, signatures = len(sets), np.array([set_signature(s) for s in sets], np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(signatures[:, 0].copy()), pa.array(signatures[:, 1].copy()), pa.nulls(n, pa.int32()), pa.array([cell_counts(s) for s in sets], pa.binary()), part.column(2)], names=names)
        if (blocks := seen.block_rows()) is not None:
            nothing = pa.nulls(sketch.BLOCKS, pa.int64())
            yield pa.RecordBatch.from_arrays([nothing, nothing, nothing, nothing, *blocks, nothing], names=names)

    hashed = df.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_hash"))
    return hashed.mapInArrow(run, "doc_id long, n_shingles long, first long, second long, block int, counts binary, text_hash long")


def clashing_signatures(documents: DataFrame) -> frozenset[int]:
    """First halves that belong to sets with different second halves: about N**2 / 2**65 of N sets, 3 of 10**10."""
    per = documents.groupBy("first").agg(F.min("second").alias("x"), F.max("second").alias("y"))
    return frozenset(r["first"] for r in per.where("x <> y").select("first").collect())


def needed(m: F.Column, n: F.Column) -> F.Column:
    """Least overlap of two linked sets of these sizes: 100 * o >= 75 * (m + n - o)."""
    return F.floor((3 * (m + n) + 6) / 7)


def within_bounds(size_a: F.Column, pos_a: F.Column, size_b: F.Column, pos_b: F.Column) -> F.Column:
    """Can two sets with a common shingle at these places (from 0) of their orders still be linked?"""
    least = needed(size_a, size_b)
    return (3 * F.greatest(size_a, size_b) <= 4 * F.least(size_a, size_b)) & (size_a - pos_a >= least) & (size_b - pos_b >= least)


def incidence_entries(df: DataFrame, k: int, classes, clashing: frozenset[int]) -> DataFrame:
    """Entries of the product: each distinct set's rarest shingles, as many as can decide a link.

    Repeats of a set within a task are left out; those of other tasks meet in their column.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, seen = classes.value, set()
        for _, chunk in all_chunks(batches):
            cols: list[list[np.ndarray]] = [[], [], [], [], []]
            for own in shingle_sets(chunk, k):
                n = len(own)
                if n == 0 or (node := node_of(own, clashing)) in seen:
                    continue
                if len(seen) > 500_000:
                    seen.clear()
                seen.add(node)
                kind = table[sketch.cell(own)]
                order = np.argsort((kind.astype(np.uint64) << np.uint64(58)) | (own >> np.uint64(6)), kind="stable")[: n - (3 * n + 3) // 4 + 1]
                # parts of about 2**(HOT_CLASS - 1) entries
                parts = 1 << np.clip(kind[order].astype(np.int64) - HOT_CLASS + 1, 0, 30)
                salt = np.where(parts > 1, node % parts, -1).astype(np.int32)
                for c, x in zip(cols, (signed(own[order]), np.full(len(order), node), np.full(len(order), n, np.int32), np.arange(len(order), dtype=np.int32), salt), strict=True):
                    c.append(x)
            if cols[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], names=["h", "node", "n", "pos", "salt"])

    return df.mapInArrow(run, "h long, node long, n int, pos int, salt int")


def shared_columns(entries: DataFrame) -> DataFrame:
    """Entries of columns that hold two rows or more, each beside the most central row of its (salted) column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.RecordBatch | None = None  # the first row of the open run
        names = ["h", "node", "n", "pos", "salt", "center", "center_n", "center_pos"]
        held_out = True
        for batch in batches:
            if batch.num_rows == 0:
                continue
            own = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
            carried = held is not None
            h, node, n, pos, salt = (own.column(i).to_numpy() for i in range(5))
            new = np.concatenate([[True], (h[1:] != h[:-1]) | (salt[1:] != salt[:-1])])
            run_of = np.cumsum(new) - 1
            first = np.flatnonzero(new)[run_of]
            differs = (node != node[first]).astype(np.int64)
            several = np.bincount(run_of, differs)[run_of] > 0
            keep = several | (salt >= 0)
            repeat = np.concatenate([[False], (node[1:] == node[:-1]) & ~new[1:]])
            keep &= ~repeat
            if carried:
                # the carried row itself goes out once, as soon as its run turns out to hold another row
                keep[0] = keep[0] and not held_out
                held_out = held_out or bool(keep[0])
            at = np.flatnonzero(keep)
            tail = int(first[-1])
            if tail != 0 or not carried:
                held_out = bool(keep[tail])
            held = own.slice(tail, 1)
            if len(at):
                yield pa.RecordBatch.from_arrays([pa.array(x[at]) for x in (h, node, n, pos, salt)] + [pa.array(x[first[at]]) for x in (node, n, pos)], names=names)

    dealt = entries.repartition("h", "salt").sortWithinPartitions("h", "salt", "pos", "node")
    return dealt.mapInArrow(run, "h long, node long, n int, pos int, salt int, center long, center_n int, center_pos int")


def _pair(a: str, b: str) -> list[F.Column]:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def central_pairs(shared: DataFrame) -> DataFrame:
    """Every entry with its column's center, and the centers of a column's salted parts with the first of them."""
    ok = within_bounds(F.col("n"), F.col("pos"), F.col("center_n"), F.col("center_pos"))
    near = shared.where(F.col("node") != F.col("center")).where(ok).select(F.col("center").alias("a"), F.col("node").alias("b"))
    heads = shared.where((F.col("salt") >= 0) & (F.col("node") == F.col("center"))).select("h", "node", "n", "pos")
    top = heads.groupBy("h").agg(F.min(F.struct("pos", "node", "n")).alias("top"))
    far = heads.join(top, "h").where((F.col("node") != F.col("top.node")) & within_bounds(F.col("n"), F.col("pos"), F.col("top.n"), F.col("top.pos"))).select(F.col("top.node").alias("a"), F.col("node").alias("b"))
    return near.union(far).distinct()


def crossing_pairs(shared: DataFrame, roots: DataFrame, done: DataFrame) -> DataFrame:
    """Pairs within the bounds whose rows are still in different components, without those of ``done``."""
    entries = shared.select("h", "node", "n", "pos").join(roots, "node", "left").select("h", "node", "n", "pos", F.coalesce("root", "node").alias("root"))
    sizes = entries.groupBy("h", "root").agg(F.count("*").alias("c"))
    mixed = sizes.groupBy("h").agg(F.max_by("root", F.struct("c", "root")).alias("main"), F.count("*").alias("roots")).where("roots > 1").select("h", "main")
    own = entries.join(mixed, "h")
    x, y = own.where("root <> main").alias("x"), own.alias("y")
    c = F.col
    met = x.join(y, (c("x.h") == c("y.h")) & (c("x.root") != c("y.root")) & ((c("y.root") == c("y.main")) | (c("x.node") < c("y.node"))) & within_bounds(c("x.n"), c("x.pos"), c("y.n"), c("y.pos")))
    first = c("x.node") < c("y.node")
    either = lambda name: [F.when(first, c(f"x.{name}")).otherwise(c(f"y.{name}")).alias(f"{name}_a"), F.when(first, c(f"y.{name}")).otherwise(c(f"x.{name}")).alias(f"{name}_b")]
    counted = met.select(*_pair("x.node", "y.node"), *either("n"), *either("pos")).groupBy("a", "b", "n_a", "n_b").agg(F.count("*").alias("met"), F.max("pos_a").alias("at_a"), F.max("pos_b").alias("at_b"))
    # what is common behind the last common place lies behind it in both orders
    pairs = counted.where(c("met") + F.least(c("n_a") - c("at_a"), c("n_b") - c("at_b")) - 1 >= needed(c("n_a"), c("n_b"))).select("a", "b")
    return pairs.join(done.select(*_pair("a", "b")), ["a", "b"], "left_anti")


def within_cell_bound(pairs: DataFrame, cells: DataFrame) -> DataFrame:
    """The pairs whose histograms don't exclude a link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            m, n, x, y = (batch.column(i) for i in range(2, 6))
            for i, (p, q, u, v) in enumerate(zip(m.to_pylist(), n.to_pylist(), x, y, strict=True)):
                bound = overlap_bound(np.frombuffer(u.as_buffer(), np.uint8), np.frombuffer(v.as_buffer(), np.uint8))
                keep[i] = bound is None or 7 * bound >= 3 * (p + q)
            yield batch.select([0, 1]).filter(pa.array(keep))

    one = pairs.join(cells.select(F.col("node").alias("a"), F.col("n_shingles").alias("m"), F.col("counts").alias("x")), "a")
    both = one.join(cells.select(F.col("node").alias("b"), F.col("n_shingles").alias("n"), F.col("counts").alias("y")), "b")
    return both.select("a", "b", "m", "n", "x", "y").mapInArrow(run, "a long, b long")


def incidence_rows(rows: DataFrame, classes: DataFrame, pairs: DataFrame, k: int, clashing: frozenset[int]) -> DataFrame:
    """(node, ids): the shingle numbers, sorted, of every row that is in a pair, read from the text of its class's first document."""
    ends = pairs.select("a").union(pairs.select(F.col("b").alias("a"))).distinct().select(F.col("a").alias("node"))
    chosen = classes.join(ends, "node").select(F.col("class_id").alias("doc_id"), "node")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for part, chunk in all_chunks(batches):
            nodes, ids = [], []
            for node, own in zip(part.column(0).to_pylist(), shingle_sets(chunk, k), strict=True):
                if node in seen or node_of(own, clashing) != node:
                    continue  # a repeated row, or another text under a repeated id
                if len(seen) > 500_000:
                    seen.clear()
                seen.add(node)
                nodes.append(node)
                ids.append(own.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(ids, pa.binary())], names=["node", "ids"])

    return rows.join(chosen, "doc_id").select("node", "text").mapInArrow(run, "node long, ids binary")


def overlapping(center: np.ndarray, flat: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Which rows (of these sizes, end to end in flat, each sorted) overlap with the center as much as a link needs.

    One range of columns after another; a row goes as soon as its count and what is left of it fall short.
    """
    least = -(-3 * (size + len(center)) // 7)
    row = np.repeat(np.arange(len(size)), size)
    column = flat >> np.uint64(64 - RANGES.bit_length() + 1)
    count, left, open_ = np.zeros(len(size), np.int64), size.copy(), np.ones(len(size), bool)
    for x in range(RANGES):
        at = np.flatnonzero((column == x) & open_[row])
        ids, own = flat[at], row[at]
        place = np.searchsorted(center, ids)
        place[place == len(center)] = 0
        count += np.bincount(own, center[place] == ids, len(size)).astype(np.int64)
        left -= np.bincount(own, minlength=len(size))
        open_ &= count + left >= least
    return open_


def verified(pairs: DataFrame, incidence: DataFrame) -> DataFrame:
    """The pairs (a, b) of nodes whose full overlap reaches the threshold, multiplied block by block."""
    total = pairs.count()
    parts = pairs.groupBy("a").agg(F.count("*").alias("c")).withColumn("parts", F.ceil(F.col("c") / PARTNERS).cast("long"))
    dealt = spread_join(pairs, parts, "a", "c", total).select("a", "b", F.pmod(F.xxhash64("b"), "parts").alias("part"))
    members = dealt.join(incidence.select(F.col("node").alias("b"), "ids"), "b").select("a", "part", "b", "ids")
    blocks = parts.select("a", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"))
    centers = blocks.join(incidence.select(F.col("node").alias("a"), "ids"), "a").select("a", "part", F.lit(None).cast("long").alias("b"), "ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        center, center_of = np.zeros(0, np.uint64), None
        for batch in batches:
            a, b = batch.column(0).to_numpy(), batch.column(2)
            is_center = np.asarray(b.is_null())
            ids = batch.column(3)
            # stretches of partners of one center; each center starts a new one
            edges = np.flatnonzero(np.concatenate([[True], is_center[1:] | is_center[:-1] | (a[1:] != a[:-1])])) if len(a) else []
            for lo, hi in zip(edges, [*edges[1:], len(a)], strict=True):
                if is_center[lo]:
                    center, center_of = np.frombuffer(ids[lo].as_buffer(), np.uint64), a[lo]
                elif a[lo] == center_of:
                    own = ids.slice(lo, hi - lo).to_pylist()
                    hit = overlapping(center, np.frombuffer(b"".join(own), np.uint64), np.array([len(x) // 8 for x in own]))
                    if hit.any():
                        yield pa.RecordBatch.from_arrays([pa.array(a[lo:hi][hit]), b.slice(lo, hi - lo).filter(pa.array(hit))], names=["a", "b"])

    sent = lean_batches(centers.union(members)).repartition("a", "part").sortWithinPartitions("a", "part", F.asc_nulls_first("b"))
    return sent.mapInArrow(run, "a long, b long").distinct()


def near_duplicates(df: DataFrame, k: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, text_hash, class_id, root, component_id) for every row: class_id is the smallest doc_id with an
    equal shingle set, component_id the smallest doc_id reachable by links, root a number of the component itself."""
    if not 1 <= k <= 32:
        raise ValueError("k must be 1 to 32")
    spark, rows = df.sparkSession, texts(df, id_col, text_col)
    measured = written(shingle_classes(rows, k), "shingles")
    table = spark.sparkContext.broadcast(sketch.frequency_classes(measured.where("block is not null")))
    linkable = measured.where("block is null and n_shingles > 0 and doc_id is not null")
    clashing = clashing_signatures(linkable)
    node = F.col("first") if not clashing else F.when(F.col("first").isin(list(clashing)), F.col("second")).otherwise(F.col("first"))
    known, own = rows.where("doc_id is not null"), linkable.withColumn("node", node)
    classes = written(own.groupBy("node").agg(F.min("doc_id").alias("class_id"), F.count("*").alias("members"), F.first("n_shingles").alias("n_shingles"), F.first("counts").alias("counts")), "classes")
    shared = written(shared_columns(incidence_entries(known, k, table, clashing)), "entries")
    first = written(central_pairs(shared), "pairs")
    roots, links = None, None
    for found in (lambda: first, lambda: crossing_pairs(shared, roots, first)):
        pairs = written(within_cell_bound(found(), classes), "bounded")
        incidence = written(incidence_rows(known, classes, pairs, k, clashing), "incidence")
        links = verified(pairs, incidence)
        roots = connected_components(links if roots is None else roots.select(F.col("root").alias("a"), F.col("node").alias("b")).union(links))
    rooted = classes.join(roots, "node", "left").select("node", "class_id", "members", F.coalesce("root", "node").alias("root"))
    components = rooted.groupBy("root").agg(F.min("class_id").alias("component_id"), F.count("*").alias("nodes"))
    total = rooted.agg(F.count("*").alias("n"), F.coalesce(F.sum("members"), F.lit(0)).alias("m")).first()
    named = spread_join(rooted, components, "root", "nodes", total.n)
    lone = measured.where("block is null and (n_shingles = 0 or doc_id is null)").select("doc_id", "n_shingles", "text_hash", F.col("doc_id").alias("class_id"), F.lit(None).cast("long").alias("root"), F.col("doc_id").alias("component_id"))
    linked = spread_join(own.select("doc_id", "n_shingles", "text_hash", "node"), named.select("node", "class_id", "root", "component_id", "members"), "node", "members", total.m)
    return linked.select("doc_id", "n_shingles", "text_hash", "class_id", "root", "component_id").union(lone)


def first_of_each_group(df: DataFrame, k: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of df, whole, that come first (by id, then by a hash of the text) in their component.

    Rows without shingles or without an id stay, but for repeated equal rows under one id.
    """
    names = df.columns
    th = F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit("")))
    grouped = written(near_duplicates(df, k, id_col, text_col).where("doc_id is not null").select("doc_id", "root", "text_hash"), "groups")
    chosen = grouped.where("root is not null").groupBy("root").agg(F.min(F.struct("doc_id", "text_hash")).alias("x")).select("x.doc_id", "x.text_hash")
    chosen = chosen.union(grouped.where("root is null").select("doc_id", "text_hash").distinct()).select(F.col("doc_id").alias("kept_id"), F.col("text_hash").alias("kept_hash"))
    rows = df.select(F.struct(*[F.col(c) for c in names]).alias("row"), F.col(id_col).cast("long").alias("own_id"), th.alias("own_hash"))
    stay = rows.join(chosen, (F.col("own_id") == F.col("kept_id")) & (F.col("own_hash") == F.col("kept_hash")), "left_semi")
    once = stay.withColumn("k", F.row_number().over(Window.partitionBy("own_id", "own_hash").orderBy("own_hash"))).where("k = 1")
    return once.select("row").union(rows.where("own_id is null").select("row")).select(*[F.col("row").getField(c).alias(c) for c in names])
