"""Removal of repeated byte strings: every ``LENGTH``-byte string that also starts earlier is cut out.

"Earlier" means a smaller doc_id, or the same document and a smaller start.  A string is treated through the
anchor of its window of text: the least K-gram hash (leftmost on ties) among the LENGTH - K + 1 K-grams in it.
Equal strings have equal anchors at equal places, so only texts around anchors that occur more than once need
comparing.  Neighbouring strings with one anchor form its *context*:

1. all anchors of all texts, with hashes of anchor and context, are dealt by anchor; later copies of a whole
   context are cut at once, and an anchor with one context only is done;
2. the first copies of different contexts of an anchor get their bytes from the texts, are laid out in blocks of
   about BLOCK_BYTES, and the starts of their strings are suffix-sorted bucket by bucket with a difference cover
   (``suffix_array``); of each run of starts that agree in LENGTH bytes the earliest stays.

Frequent anchors (seen in a fixed-size count sketch) never gather in one task: copies of their contexts meet
within each task first, what is left is dealt by context, and their strings are compared by 128-bit hashes
aggregated before the shuffle.  Contexts of one anchor are matched by 96 bits that don't depend on the anchor's hash;
blocks are compared byte by byte.

Null and empty texts have no string; null ids count as the smallest id; equal rows (same id and text) count as
one document and get equal results; rows with the same id and different texts are separate texts at that id, told
apart by a 64-bit hash; an empty table gives an empty result; other columns are not read.  ``length`` is 33 to 16,415.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farspan.llm import sketch
from farspan.llm.storage import lean_batches, written
from farspan.llm.suffix_array import equal_classes, suffix_order
from farspan.llm.textbatch import TextChunk, all_chunks, mix64, signed

LENGTH = 100
K = 32
BLOCK_BYTES = 1 << 20
#: Frequency class (bit length of the excess over the sketch's noise) from which an anchor is dealt by context:
#: below it, all contexts of an anchor (some 2**14 times 170 bytes) still fit in one block of a task.
HOT_CLASS = 15
#: Contexts of a frequent anchor that a task holds before it passes them on.
HELD = 200_000
NULL_ID = -(2**63)
_POSITION = np.uint64((1 << 34) - 1)


def keyed(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, th, text): th tells apart texts under one id."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return lean_batches(df).select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("id"), F.xxhash64(text).alias("th"), text.alias("text"))


def anchors(chunk: TextChunk, length: int) -> tuple[np.ndarray, ...]:
    """For each context: text, first and last start of its strings (chunk positions), anchor position, and hash of the anchor."""
    n, width = len(chunk.data), length - K + 1
    size = np.diff(chunk.off)
    if n < length or not (size >= length).any():
        return (np.zeros(0, np.int64),) * 4 + (np.zeros(0, np.uint64),)
    gram = chunk.gram_hash(K)
    least = (gram & ~_POSITION) | np.arange(n - K + 1, dtype=np.uint64)
    span = 1
    while span * 2 <= width:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if span < width:
        least = np.minimum(least[: len(least) - (width - span)], least[width - span :])
    # least[p] belongs to the string that starts at p; keep those inside one text
    text = np.repeat(np.arange(len(size)), size)[: len(least)]
    valid = np.flatnonzero(np.arange(len(least)) + length <= chunk.off[1:][text])
    spot, text = (least[valid] & _POSITION).astype(np.int64), text[valid]
    new = np.concatenate([[True], (spot[1:] != spot[:-1]) | (text[1:] != text[:-1])])
    first = np.flatnonzero(new)
    last = np.concatenate([first[1:] - 1, [len(valid) - 1]])
    # the least of many hashes lies near zero: mixed again, anchors spread evenly
    return text[first], valid[first], valid[last], spot[first], mix64(gram[spot[first]] + np.uint64(1))


NAMES = ["anchor", "context", "id", "th", "lo", "lead", "width", "kind"]
ENTRY = "anchor long, context long, id long, th long, lo int, lead int, width int, kind int"
#: kind of an entry: an ordinary or frequent anchor's context, or strings already known to be repeated
PLAIN, FREQUENT, CUT = 0, 1, 2
#: Entries on their way: shape is 32 more bits of the context's hash, then kind, lead and width in FIELD bits each.
PACKED = "anchor long, context long, id long, th long, lo int, shape long"
PACKED_NAMES = ["anchor", "context", "id", "th", "lo", "shape"]
FIELD = 14
_FIELD_MASK, _MORE = (1 << FIELD) - 1, 2 * FIELD + 2


def packed(anchor, context, more, d, th, lo, lead, width, kind) -> pa.RecordBatch:
    more, lead, width, kind = (np.asarray(x, np.int64) for x in (more, lead, width, kind))
    shape = more << _MORE | kind << 2 * FIELD | lead << FIELD | width
    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (anchor, context, d, th)] + [pa.array(lo, pa.int32()), pa.array(shape)], names=PACKED_NAMES)


def unpacked(columns: list[np.ndarray]) -> list[np.ndarray]:
    """The columns of NAMES, and the rest of the context's hash."""
    anchor, context, d, th, lo, shape = columns
    lead, width, kind = (x.astype(np.int32) for x in (shape >> FIELD & _FIELD_MASK, shape & _FIELD_MASK, shape >> 2 * FIELD & 3))
    return [anchor, context, d, th, lo, lead, width, kind, shape >> _MORE]


def _id_columns(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    return part.column(0).to_numpy(), part.column(1).to_numpy()


def anchor_sketch(rows: DataFrame, length: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = sketch.Sketch()
        for _, chunk in all_chunks(batches):
            seen.add(anchors(chunk, length)[4])
        if (blocks := seen.block_rows()) is not None:
            yield pa.RecordBatch.from_arrays(list(blocks), names=["block", "counts"])

    return rows.select("text").mapInArrow(run, "block int, counts binary")


def context_entries(rows: DataFrame, length: int, classes) -> DataFrame:
    """One entry for each context; of a frequent anchor's contexts a task sends the earliest, and cuts the others."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = classes.value
        held: dict[tuple[int, int, int], tuple[int, int, int, int, int]] = {}

        def passed_on() -> pa.RecordBatch:
            rows_out = [(*key, d, th, lo, lead, width, FREQUENT) for key, (d, lo, th, lead, width) in held.items()]
            held.clear()
            return packed(*zip(*rows_out, strict=True))

        for part, chunk in all_chunks(batches):
            text, lo, hi, spot, gram = anchors(chunk, length)
            if len(text) == 0:
                continue
            ids, ths = _id_columns(part)
            hot = table[sketch.cell(gram)] >= HOT_CLASS
            lead = spot - lo
            context, more = (mix64(chunk.span_hash(lo, hi + length, seed=x) ^ mix64(lead.astype(np.uint64))) for x in (0, 1))
            columns = [signed(gram), signed(context), (more >> np.uint64(32)).astype(np.int64), ids[text], ths[text], (lo - chunk.off[text]).astype(np.int32), lead, hi - lo]
            cold = ~hot
            if cold.any():
                own = [c[cold] for c in columns]
                yield packed(*own, np.zeros(len(own[0])))
            cut: list[tuple] = []
            for a, c, m, d, th, at, led, width in zip(*(x[hot].tolist() for x in columns), strict=True):
                before = held.get((a, c, m))
                now = (d, at, th, led, width)
                if before is None:
                    held[a, c, m] = now
                    continue
                if now[:2] < before[:2]:
                    held[a, c, m], now, before = now, before, now
                if now[:2] != before[:2]:
                    cut.append((a, c, m, now[0], now[2], now[1], now[3], now[4], CUT))
                elif now[2] != before[2]:  # same id and place in another text: neither is earlier
                    cut.append((a, c, m, now[0], now[2], now[1], now[3], now[4], FREQUENT))
            if cut:
                yield packed(*zip(*cut, strict=True))
            if len(held) >= HELD:
                yield passed_on()
        if held:
            yield passed_on()

    return rows.mapInArrow(run, PACKED)


def first_contexts(entries: DataFrame) -> DataFrame:
    """CUT entries for later copies of a context; first copies where their anchor has several contexts."""

    def resolve(columns: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """columns are sorted; the rows to send, and which of them are cut."""
        anchor, context, d, _, lo, _, _, kind, more = columns
        new = np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (context[1:] != context[:-1]) | (more[1:] != more[:-1])])
        first = np.flatnonzero(new)[np.cumsum(new) - 1]
        later = (d != d[first]) | (lo != lo[first])
        opened = np.concatenate([[True], anchor[1:] != anchor[:-1]])
        contexts = np.bincount(np.cumsum(opened) - 1, new)[np.cumsum(opened) - 1]
        cut = (kind == CUT) | later
        return np.flatnonzero(cut | (contexts > 1) | (kind == FREQUENT)), cut

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        carry: list[np.ndarray] | None = None
        for batch in batches:
            if batch.num_rows == 0:
                continue
            columns = unpacked([c.to_numpy() for c in batch.columns])
            if carry is not None:
                columns = [np.concatenate(x) for x in zip(carry, columns, strict=True)]
            anchor, context, kind, more = columns[0], columns[1], columns[7], columns[8]
            # the last open group: an anchor, or one context of a frequent anchor
            same = (anchor == anchor[-1]) & ((kind[-1] == PLAIN) | ((context == context[-1]) & (more == more[-1])))
            tail = len(same) - int(np.argmin(same[::-1])) if not same.all() else 0
            carry = [c[tail:] for c in columns]
            if tail:
                done = [c[:tail] for c in columns]
                at, cut = resolve(done)
                yield pa.RecordBatch.from_arrays([pa.array(c[at]) for c in done[:7]] + [pa.array(np.where(cut, CUT, done[7]).astype(np.int32)[at])], names=NAMES)
        if carry is not None:
            at, cut = resolve(carry)
            yield pa.RecordBatch.from_arrays([pa.array(c[at]) for c in carry[:7]] + [pa.array(np.where(cut, CUT, carry[7]).astype(np.int32)[at])], names=NAMES)

    kind = F.shiftright("shape", 2 * FIELD).bitwiseAND(3)
    spread = F.when(kind == PLAIN, F.lit(0)).when(kind == FREQUENT, F.col("context")).otherwise(F.xxhash64("id", "lo"))
    dealt = entries.withColumn("spread", F.xxhash64("anchor", spread)).repartition("spread").drop("spread")
    # the order of shape: of one context, entries that are cut already come last
    return dealt.sortWithinPartitions("anchor", "context", "shape", "id", "lo").mapInArrow(run, ENTRY)


def context_bytes(rows: DataFrame, pending: DataFrame, length: int) -> DataFrame:
    """The bytes of the contexts in question, cut out of their texts."""
    wanted = pending.groupBy("id", "th").agg(F.collect_list(F.struct("anchor", "lo", "lead", "width", "kind")).alias("want"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["anchor", "id", "th", "lo", "lead", "width", "kind", "bytes"]
        for part, chunk in all_chunks(batches):
            want = part.column(part.schema.get_field_index("want"))
            if len(want) == 0:
                continue
            number = np.diff(want.offsets.to_numpy()) if want.offset == 0 else np.array([len(x) for x in want])
            flat = want.flatten()
            anchor, lo, lead, width, kind = (flat.field(i) for i in range(5))
            d = np.repeat(np.arange(len(number)), number)
            ids, ths = _id_columns(part)
            begin = chunk.off[d] + lo.to_numpy()
            end = begin + width.to_numpy() + length
            raw = chunk.data.tobytes()
            pieces = pa.array([raw[a:b] for a, b in zip(begin.tolist(), end.tolist(), strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([anchor, pa.array(ids[d]), pa.array(ths[d]), lo, lead, width, kind, pieces], names=names)

    joined = rows.join(wanted, ["id", "th"]).select("id", "th", "text", "want")
    return joined.mapInArrow(run, "anchor long, id long, th long, lo int, lead int, width int, kind int, bytes binary")


def _runs(d: np.ndarray, th: np.ndarray, start: np.ndarray) -> pa.RecordBatch:
    """Marked starts as inclusive intervals."""
    order = np.lexsort((start, th, d))
    d, th, start = d[order], th[order], start[order]
    new = np.concatenate([[True], (d[1:] != d[:-1]) | (th[1:] != th[:-1]) | (start[1:] > start[:-1] + 1)])
    first = np.flatnonzero(new)
    last = np.concatenate([first[1:] - 1, [len(d) - 1]])
    return pa.RecordBatch.from_arrays([pa.array(d[first]), pa.array(th[first]), pa.array(start[first].astype(np.int32)), pa.array(start[last].astype(np.int32))], names=["id", "th", "lo", "hi"])


INTERVAL = "id long, th long, lo int, hi int"


def later_in_block(pieces: list[bytes], ids: np.ndarray, ths: np.ndarray, lo: np.ndarray, lead: np.ndarray, width: np.ndarray, length: int) -> pa.RecordBatch | None:
    """Starts in a block of contexts whose string occurs earlier in the block.

    Each context is laid out so that its anchor falls on a multiple of the cover's modulus: equal strings then
    start at equal residues and one offset decides most ties.
    """
    from farspan.llm.suffix_array import MODULUS

    size = np.array([len(p) for p in pieces])
    begin, at, parts = np.empty(len(pieces), np.int64), 0, []
    for i, (p, led) in enumerate(zip(pieces, lead.tolist(), strict=True)):
        gap = -(at + led) % MODULUS
        parts += [bytes(gap), p]
        begin[i] = at + gap
        at += gap + len(p)
    block = np.frombuffer(b"".join(parts), np.uint8)
    number = width.astype(np.int64) + 1
    of = np.repeat(np.arange(len(pieces)), number)
    start = np.arange(len(of)) - np.repeat(np.cumsum(number) - number, number)
    assert (size == width + length).all()
    position = begin[of] + start
    by_position = np.empty(int(position.max()) + 1, np.int64)
    by_position[position] = np.arange(len(of))
    ordered = suffix_order(block, position, length)
    classes = equal_classes(block, ordered, length)
    of_entry = by_position[ordered]
    d, s, th = ids[of[of_entry]], lo[of[of_entry]] + start[of_entry], ths[of[of_entry]]
    ranked = np.lexsort((s, d, classes))
    d, s, th, classes = d[ranked], s[ranked], th[ranked], classes[ranked]
    new = np.concatenate([[True], classes[1:] != classes[:-1]])
    first = np.flatnonzero(new)[np.cumsum(new) - 1]
    later = (d != d[first]) | (s != s[first])
    return _runs(d[later], th[later], s[later]) if later.any() else None


def sorted_blocks(contexts: DataFrame, length: int) -> DataFrame:
    """Repeated strings among the contexts of ordinary anchors, by suffix sorting block after block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size = 0

        def resolve(table: pa.Table) -> Iterator[pa.RecordBatch]:
            if table.num_rows:
                _, d, th, lo, lead, width, _, pieces = (c.combine_chunks() for c in table.columns)
                out = later_in_block(pieces.to_pylist(), *(x.to_numpy() for x in (d, th, lo, lead, width)), length)
                if out is not None:
                    yield out

        for whole in batches:
            step = max(1, BLOCK_BYTES // (2 * length))
            for a in range(0, whole.num_rows, step):
                batch = whole.slice(a, step)
                held.append(batch)
                size += batch.column(7).nbytes
                if size < BLOCK_BYTES:
                    continue
                table = pa.Table.from_batches(held)
                anchor = table.column(0).to_numpy()
                tail = len(anchor) - int(np.argmin((anchor == anchor[-1])[::-1])) if (anchor != anchor[-1]).any() else 0
                yield from resolve(table.slice(0, tail))
                rest = table.slice(tail).combine_chunks()
                held = rest.to_batches()
                size = rest.nbytes
        if held:
            yield from resolve(pa.Table.from_batches(held))

    dealt = contexts.where(F.col("kind") == PLAIN).repartition("anchor").sortWithinPartitions("anchor", "id", "lo")
    return dealt.mapInArrow(run, INTERVAL)


def hashed_strings(contexts: DataFrame, length: int) -> DataFrame:
    """Repeated strings among the contexts of frequent anchors: each string's earliest start by aggregation."""

    names = ["s1", "s2", "id", "th", "lo", "hi"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, 4096):
                batch = whole.slice(a, 4096)
                ids, ths, lo, width = (batch.column(i).to_numpy() for i in (1, 2, 3, 5))
                pieces = batch.column(7)
                number = width.astype(np.int64) + 1
                of = np.repeat(np.arange(len(number)), number)
                start = np.arange(len(of)) - np.repeat(np.cumsum(number) - number, number)
                flat = b"".join(pieces.to_pylist())
                begin = (np.cumsum(width + length) - (width + length)).astype(np.int64)[of] + start
                digests = b"".join([hashlib.blake2b(flat[x : x + length], digest_size=16).digest() for x in begin.tolist()])
                both = np.frombuffer(digests, np.int64).reshape(-1, 2)
                d, th, at = ids[of], ths[of], lo[of] + start
                order = np.lexsort((at, d, both[:, 1], both[:, 0]))
                both, d, th, at = both[order], d[order], th[order], at[order]
                new = np.concatenate([[True], (both[1:] != both[:-1]).any(axis=1)])
                first = np.flatnonzero(new)[np.cumsum(new) - 1]
                later = (d != d[first]) | (at != at[first])
                if later.any():  # repeated within this portion already
                    nothing = pa.nulls(len(runs := _runs(d[later], th[later], at[later])), pa.int64())
                    yield pa.RecordBatch.from_arrays([nothing, nothing, *runs.columns], names=names)
                own = ~later
                place = pa.array(at[own].astype(np.int32))
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(both[own, 0])), pa.array(np.ascontiguousarray(both[own, 1])), pa.array(d[own]), pa.array(th[own]), place, place], names=names)

    strings = contexts.where(F.col("kind") == FREQUENT).mapInArrow(run, "s1 long, s2 long, " + INTERVAL)
    single = strings.where("s1 is not null")
    earliest = single.groupBy("s1", "s2").agg(F.min(F.struct("id", "lo")).alias("e"), F.count("*").alias("c")).where("c > 1").select("s1", "s2", "e")
    later = single.join(earliest, ["s1", "s2"]).where((F.col("id") != F.col("e.id")) | (F.col("lo") != F.col("e.lo")))
    return later.select("id", "th", "lo", "hi").union(strings.where("s1 is null").select("id", "th", "lo", "hi"))


def repeated_strings(rows: DataFrame, length: int = LENGTH) -> DataFrame:
    """(id, th, starts): sorted array of inclusive intervals of starts of repeated strings, for texts that have any."""
    if not K < length < K + (1 << FIELD):
        raise ValueError(f"length must be {K + 1} to {K + (1 << FIELD) - 1}")
    spark = rows.sparkSession
    classes = spark.sparkContext.broadcast(sketch.frequency_classes(anchor_sketch(rows, length)))
    marked = written(first_contexts(context_entries(rows, length, classes)), "contexts")
    contexts = written(context_bytes(rows, marked.where(F.col("kind") != CUT), length), "context-bytes")
    whole = marked.where(F.col("kind") == CUT).select("id", "th", "lo", (F.col("lo") + F.col("width")).alias("hi"))
    parts = whole.union(sorted_blocks(contexts, length)).union(hashed_strings(contexts, length))
    return written(parts.groupBy("id", "th").agg(F.sort_array(F.collect_set(F.struct("lo", "hi"))).alias("starts")), "repeats")


def cut_out(chunk: TextChunk, starts: pa.Array, length: int) -> tuple[list[list[list[int]]], list[bytes]]:
    """The removed spans of each text, and what is left of it."""
    whole, spans_out, kept_out = chunk.data.tobytes(), [], []
    for d, own in enumerate(starts.to_pylist()):
        raw = whole[chunk.off[d] : chunk.off[d + 1]]
        spans: list[list[int]] = []
        for x in own or ():
            a, b = x["lo"], x["hi"] + length
            if spans and a <= spans[-1][1]:
                spans[-1][1] = max(b, spans[-1][1])
            else:
                spans.append([a, b])
        at, kept = 0, []
        for a, b in spans:
            kept.append(raw[at:a])
            at = b
        spans_out.append(spans)
        kept_out.append(b"".join([*kept, raw[at:]]) if spans else raw)
    return spans_out, kept_out


def remove_repeats(df: DataFrame, length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, spans, kept) for every row: the removed byte runs as array<struct<start, end>>, and the rest."""
    rows = keyed(df, id_col, text_col)
    found = repeated_strings(rows, length)
    spans_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, chunk in all_chunks(batches):
            spans, kept = cut_out(chunk, part.column(3), length)
            shown = [[{"start": a, "end": b} for a, b in own] for own in spans]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.diff(chunk.off), pa.int64()), pa.array(shown, spans_type), pa.array(kept, pa.binary())], names=["id", "n_bytes", "spans", "kept"])

    joined = rows.join(found, ["id", "th"], "left").select("id", "th", "text", "starts")
    out = joined.mapInArrow(run, "id long, n_bytes long, spans array<struct<start: long, end: long>>, kept binary")
    return out.select(F.when(F.col("id") != NULL_ID, F.col("id")).alias("doc_id"), "n_bytes", "spans", "kept")


def without_repeats(df: DataFrame, length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text", chars_col: str = "n_chars") -> DataFrame:
    """df with its texts cut (characters broken by a cut go too) and the number of characters kept up to date;
    rows of whose text nothing is left are dropped."""
    key, names = keyed(df, id_col, text_col), df.columns
    whole = df.select(F.struct(*[F.col(c) for c in names if c != text_col]).alias("rest"), F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("id"), F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit(""))).alias("th"), F.col(text_col).alias("text"))
    joined = whole.join(repeated_strings(key, length), ["id", "th"], "left").select("rest", "text", "starts")
    schema = joined.drop("starts").schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, chunk in all_chunks(batches):
            starts = part.column(2)
            spans, kept = cut_out(chunk, starts, length)
            text = part.column(1).to_pylist()
            cut = [k.decode(errors="ignore") if s else t for s, k, t in zip(spans, kept, text, strict=True)]
            keep = [bool(t) or not s for s, t in zip(spans, cut, strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(cut, pa.string())], names=["rest", "text"]).filter(pa.array(keep, pa.bool_()))

    out = joined.mapInArrow(run, schema)

    def column(c: str):
        if c == text_col:
            return F.col("text").alias(c)
        return F.length("text").cast(df.schema[c].dataType).alias(c) if c == chars_col else F.col("rest").getField(c).alias(c)

    return out.select(*[column(c) for c in names])
