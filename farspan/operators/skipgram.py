"""Token vectors for a vocabulary that no process holds: skip-gram with hierarchical softmax, learned in parts of the corpus.

The model is that of Spark's Word2Vec (one pass, words that occur twice or more, parts that start alike and are averaged by word),
whose driver and tasks hold the whole vocabulary.  Here the Huffman tree is kept as runs of nodes of equal weight, a few for
each distinct count, from which a task works out the paths of its own words; all else is a table.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farspan.operators.batches import coded
from farspan.operators.ranks import ranked
from farspan.sources.intermediate import adopt, lean_batches, scratch, written

#: Neighbours on either side, rate of the first step, and tokens of a step.
WINDOW, RATE, STEP = 5, 0.025, 128
#: Tokens of a block and of a part, about, and words whose parts are averaged together.
BLOCK, PART, AVERAGED = 1 << 17, 1 << 22, 1 << 16
_BLOCK = "block long, words array<string>, rare array<int>, packed binary"


@dataclass(frozen=True)
class Tree:
    """A Huffman tree.  Leaves are numbered from 0 by ascending count, the nodes above them follow, the root is the last one.  From
    a start to the next one, two nodes in a row have one parent (from ``targets`` on), or one node is its parent's ``sides`` child."""

    starts: np.ndarray
    targets: np.ndarray
    sides: np.ndarray
    root: int

    def parents(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Parents of nodes below the root, and which of its children (0, 1) each is."""
        run = np.searchsorted(self.starts, nodes, side="right") - 1
        off = nodes - self.starts[run]
        return self.targets[run] + (off >> 1), (off & 1) ^ self.sides[run]

    def paths(self, leaves: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The nodes above each leaf, leaf after leaf, as which child it is reached, and where each leaf's begin (and the end)."""
        rows, at, found = np.arange(len(leaves), dtype=np.int32), leaves, []
        while len((rows := rows[below := at != self.root])):
            at, side = self.parents(at[below])
            found.append((rows, at, side))
        begin = np.concatenate([[0], np.cumsum(sum((np.bincount(x[0], minlength=len(leaves)) for x in found), np.zeros(len(leaves), np.int64)))])
        nodes, sides = np.empty(begin[-1], np.int64), np.empty(begin[-1], np.int8)
        for level, (rows, at, side) in enumerate(found):
            nodes[begin[rows] + level], sides[begin[rows] + level] = at, side
        return nodes, sides, begin


def tree(sizes: list[tuple[int, int]]) -> Tree:
    """The tree of words by their counts: (count, words that have it), ascending."""
    heap, node = [], 0
    for count, words in sizes:
        heap.append((count, node, words))
        node += words
    heapq.heapify(heap)
    runs = []
    while len(heap) > 1 or (heap and heap[0][2] > 1):
        weight, first, n = heapq.heappop(heap)
        if n > 1:
            runs.append((first, node, 0))
            heapq.heappush(heap, (2 * weight, node, n // 2))
            if n % 2:
                heapq.heappush(heap, (weight, first + n - 1, 1))
            node += n // 2
        else:
            other, second, m = heapq.heappop(heap)
            runs += [(first, node, 0), (second, node, 1)]
            if m > 1:
                heapq.heappush(heap, (other, second + 1, m - 1))
            heapq.heappush(heap, (weight + other, node, 1))
            node += 1
    starts, targets, sides = np.array(sorted(runs), np.int64).reshape(-1, 3).T.copy()
    return Tree(starts, targets, sides, node - 1)


def first_vectors(leaves: np.ndarray, dim: int, seed: int) -> np.ndarray:
    """Where words start: each by its number, from -1/2 to 1/2 over dim, so that all parts start alike."""
    with np.errstate(over="ignore"):
        x = (leaves.astype(np.uint64)[:, None] * np.uint64(dim) + np.arange(dim, dtype=np.uint64) + np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0x9E3779B97F4A7C15)
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
        x ^= x >> np.uint64(31)
    return ((x >> np.uint64(40)).astype(np.float32) / np.float32(1 << 24) - np.float32(0.5)) / np.float32(dim)


def learn(tokens: np.ndarray, docs: np.ndarray, leaves: np.ndarray, grown: Tree, dim: int, seed: int) -> np.ndarray:
    """Vectors (words x dim) learned from tokens (numbers of words whose leaves are given) and the documents they stand in.

    STEP tokens make a step together.  As their gradients are added up, a row's rate stays below half the inverse of a bound on its curvature, so that
    what comes up many times in a step (the root, a common word) doesn't overshoot.
    """
    above, side, begin = grown.paths(leaves)
    left = (1 - side).astype(np.float32)
    numbers, above = np.unique(above, return_inverse=True)
    above = above.astype(np.int32)
    size, n = np.diff(begin), len(tokens)
    x, y = first_vectors(leaves, dim, seed), np.zeros((len(numbers), dim), np.float32)
    here = np.repeat(np.arange(STEP), WINDOW)
    there = here + np.tile(np.arange(1, WINDOW + 1), STEP)
    # each token looks at neighbours within a window of random size
    wide = np.random.default_rng(seed).integers(1, WINDOW + 1, n + WINDOW)
    for a in range(0, n, STEP):
        rate = np.float32(RATE * max(1e-4, 1 - a / n))
        own, place = np.unique(tokens[a : a + STEP + WINDOW], return_inverse=True)
        doc, reach = docs[a : a + STEP + WINDOW], wide[a : a + STEP + WINDOW]
        i, j = (here, there) if len(doc) == STEP + WINDOW else (x[there < len(doc)] for x in (here, there))
        same = doc[i] == doc[j]
        first, second = same & (j - i <= reach[i]), same & (j - i <= reach[j])
        i, j = place[i], place[j]
        met = np.bincount(np.concatenate([j[first] * len(own) + i[first], i[second] * len(own) + j[second]]), minlength=len(own) ** 2)
        pairs = np.flatnonzero(met)
        if not len(pairs):
            continue
        near, centre = np.divmod(pairs, len(own))
        # nodes above the step's words, and each pair's among them
        long = size[own]
        ends = np.cumsum(long)
        flat = np.repeat(begin[own] - (ends - long), long) + np.arange(ends[-1])
        nodes, column = np.unique(above[flat], return_inverse=True)
        each = long[centre]
        at = np.repeat((ends - long)[centre] - (np.cumsum(each) - each), each) + np.arange(int(each.sum()))
        row, weight, column = np.repeat(near, each), np.repeat(met[pairs].astype(np.float32), each), column[at]
        u, v = x[own], y[nodes]
        cell = row * len(nodes) + column
        p = (u @ v.T).ravel()[cell]
        np.exp(np.negative(p, out=p), out=p)
        p += 1
        np.reciprocal(p, out=p)
        np.subtract(left[flat][at], p, out=p)
        p *= weight
        pull = np.bincount(cell, p, len(u) * len(v)).astype(np.float32).reshape(len(u), -1)
        bend_u = np.bincount(row, weight * np.einsum("ij,ij->i", v, v)[column], len(u)).astype(np.float32)
        bend_v = np.bincount(column, weight * np.einsum("ij,ij->i", u, u)[row], len(v)).astype(np.float32)
        x[own] = u + (rate / (1 + rate * bend_u / 2))[:, None] * (pull @ v)
        y[nodes] = v + (rate / (1 + rate * bend_v / 2))[:, None] * (pull.T @ u)
    return x


def blocks(rows: DataFrame, keys: dict[str, str], most_rows: int = 1 << 30, most_tokens: int = BLOCK, known=None) -> DataFrame:
    """Some rows together, as they are read: keys (name: type) as arrays, tokens (toks) as numbers of the block's words.

    rare: the words that are not ``known`` (a broadcast), null for all without it.  packed: see ``unpacked``.
    """
    from pyspark import TaskContext

    kinds = {"long": pa.int64(), "string": pa.string()}

    def packed(number: int, held: list[pa.RecordBatch]) -> pa.RecordBatch:
        whole = pa.Table.from_batches(held).combine_chunks()
        words, codes, ends = coded(whole.column("toks").chunk(0))
        codes = codes.astype(np.uint16 if len(words) <= 1 << 16 else np.uint32)
        rare = None if known is None else [i for i, w in enumerate(words) if w not in known.value[0]]
        columns = [pa.array([number]), pa.array([words], pa.list_(pa.string())), pa.array([rare], pa.list_(pa.int32())), pa.array([_pressed(words, codes, ends)], pa.binary())]
        lists = [pa.array([whole.column(k).to_pylist()], pa.list_(kinds[t])) for k, t in keys.items()]
        return pa.RecordBatch.from_arrays(columns + lists, names=["block", "words", "rare", "packed", *keys])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, tokens, count, number = [], 0, 0, TaskContext.get().partitionId() << 32
        for batch in batches:
            upto, a = np.cumsum(pc.fill_null(pc.list_value_length(batch.column("toks")), 0).to_numpy(zero_copy_only=False), dtype=np.int64), 0
            while a < batch.num_rows:
                before = int(upto[a - 1]) if a else 0
                full = int(np.searchsorted(upto, before + most_tokens - tokens)) + 1
                b = min(batch.num_rows, max(a + 1, full), a + most_rows - count)
                held.append(batch.slice(a, b - a))
                tokens, count, a = tokens + int(upto[b - 1]) - before, count + b - a, b
                if tokens >= most_tokens or count >= most_rows:
                    yield packed(number, held)
                    held, tokens, count, number = [], 0, 0, number + 1
        if held:
            yield packed(number, held)

    schema = ", ".join([_BLOCK, *(f"{k} array<{t}>" for k, t in keys.items())])
    return lean_batches(rows).select("toks", *[F.col(k).cast(t.replace("long", "bigint")).alias(k) for k, t in keys.items()]).mapInArrow(run, schema)


def _pressed(words: list[str], codes: np.ndarray, ends: np.ndarray) -> bytes:
    sink = pa.BufferOutputStream()
    table = pa.table([pa.array([words], pa.list_(pa.string())), pa.array([codes], pa.list_(pa.from_numpy_dtype(codes.dtype))), pa.array([ends], pa.list_(pa.int64()))], names=["words", "codes", "ends"])
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def unpacked(packed: bytes) -> tuple[list[str], np.ndarray, np.ndarray]:
    """words, codes and ends of a block (see ``batches.coded``)."""
    words, codes, ends = (x.combine_chunks().flatten() for x in pa.ipc.open_stream(packed).read_all().columns)
    return words.to_pylist(), codes.to_numpy(zero_copy_only=False).astype(np.int64), ends.to_numpy(zero_copy_only=False)


def vectors(tokens_df: DataFrame, least: int, dim: int, seed: int) -> DataFrame | None:
    """(word, n, half): for every word that stands twice or more in the corpus its vector, as bytes of numbers of half precision;
    None if there are no more than ``least`` such words.

    Only the numbers of words by count are gathered; words, the words of each part and vectors are tables.
    """
    with scratch(tokens_df.sparkSession) as made:
        counts = written(tokens_df.select(F.explode("toks").alias("word")).groupBy("word").agg(F.count("*").alias("n")).where("n >= 2"), "counts")
        sizes = sorted((int(r.n), int(r["count"])) for r in counts.groupBy("n").count().collect())
        if sum(m for _, m in sizes) <= least:
            return None
        grown, parts = tree(sizes), max(1, -(-sum(n * m for n, m in sizes) // PART))
        keyed = counts.withColumns({"all": F.lit(0), "key": F.xxhash64("word")})
        numbered = written(ranked(keyed, "all", F.col("n"), [F.col("n"), F.col("key"), F.col("word")], F.col("key")).select("word", "n", (F.col("rnk") - 1).alias("leaf")), "words")
        held = written(blocks(tokens_df, {}), "blocks").withColumn("part", F.pmod(F.xxhash64("block"), F.lit(parts)))
        asked = held.select("part", F.explode("words").alias("word")).distinct().join(numbered.select("word", "leaf"), "word")
        asked = written(asked.select("part", "word", "leaf"), "asked")

        def train(left: pa.Table, right: pa.Table) -> pa.Table:
            leaves = right.column("leaf").to_numpy()
            order = np.argsort(leaves)
            number = {w: i for i, w in enumerate(right.column("word").take(pa.array(order)).to_pylist())}
            tokens, docs, seen = [], [], 0
            for _, packed in sorted(zip(left.column("block").to_pylist(), left.column("packed").to_pylist(), strict=True)):
                words, codes, ends = unpacked(packed)
                own = np.array([number.get(w, -1) for w in words], np.int32)[codes]
                doc = np.repeat(np.arange(seen, seen + len(ends), dtype=np.int32), np.diff(ends, prepend=0))
                tokens.append(own[own >= 0])
                docs.append(doc[own >= 0])
                seen += len(ends)
            if not number:
                return pa.table({"leaf": pa.array([], pa.int64()), "half": pa.array([], pa.binary())})
            found = learn(np.concatenate(tokens), np.concatenate(docs), leaves[order], grown, dim, seed)
            return pa.table({"leaf": leaves[order], "half": as_halves(found)})

        learned = held.select("part", "block", "packed").groupBy("part").cogroup(asked.groupBy("part")).applyInArrow(train, "leaf long, half binary")
        buckets = max(1, -(-sum(m for _, m in sizes) // AVERAGED))

        def average(left: pa.Table, right: pa.Table) -> pa.Table:
            words = right.sort_by("leaf")
            at = np.searchsorted(words.column("leaf").to_numpy(), left.column("leaf").to_numpy())
            order = np.argsort(at, kind="stable")
            begins = np.searchsorted(at[order], np.arange(words.num_rows))
            values = from_halves(left.column("half").to_pylist(), dim)[order].astype(np.float64)
            found = np.add.reduceat(values, begins, axis=0) / np.bincount(at, minlength=words.num_rows)[:, None]
            return pa.table({"word": words.column("word"), "n": words.column("n"), "half": as_halves(found)})

        bucket = F.pmod("leaf", F.lit(buckets)).alias("bucket")
        out = written(learned.groupBy(bucket).cogroup(numbered.groupBy(bucket)).applyInArrow(average, "word string, n long, half binary"), "vectors")
        kept = made.pop()
    adopt(kept)
    return out


def as_halves(x: np.ndarray) -> pa.Array:
    """Rows of numbers as bytes, in half precision."""
    width = 2 * x.shape[1]
    return pa.FixedSizeBinaryArray.from_buffers(pa.binary(width), len(x), [None, pa.py_buffer(x.astype("<f2").tobytes())]).cast(pa.binary())


def as_floats(dim: int):
    """``from_halves`` of a column."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("array<float>")
    def floats(half: pd.Series) -> pd.Series:
        return pd.Series(list(from_halves(half, dim)))

    return floats


def from_halves(column: Iterable[bytes], dim: int) -> np.ndarray:
    """The rows of ``as_halves``."""
    return np.frombuffer(b"".join(column), "<f2").reshape(-1, dim).astype(np.float32)
