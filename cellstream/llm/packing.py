"""Best-fit packing: few-document length patterns, repeat counts by non-negative least squares, residuals packed.

Only the histogram of piece lengths (at most ``capacity`` rows) reaches the driver. It enumerates every pattern of
one, two or three lengths that fills a sequence exactly, fits repeat counts to the histogram by non-negative least
squares, rounds them within what is there, and packs what is left best fit first. The plan maps (length, rank) ranges
to (sequence, offset); its size is bounded by the patterns, never by the documents.

Null and empty texts become one piece holding the end id. Repeated rows are packed as often as they come. Rows with a
null doc_id are packed like any other. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import bisect
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import encoder, text_bytes, written

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, task int, task_rank long"


def pieces(docs: DataFrame, vocabulary: str, capacity: int, end_id: int = 0) -> DataFrame:
    """Token pieces of each document; ``task_rank`` numbers the pieces of one length within one writing task."""

    def cut(batches):
        codec = encoder(vocabulary, keep_space=False, capacity=250_000)
        end, task = int(end_id).to_bytes(4, "little"), TaskContext.get().partitionId()
        seen: dict[int, int] = {}
        for batch in batches:
            out = [[] for _ in range(7)]
            for doc, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = codec.encode(raw) + end
                for number, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    length = len(part) // 4
                    rank = seen.get(length, 0)
                    seen[length] = rank + 1
                    for column, value in zip(out, (doc, number, at // 4, length, zlib.crc32(part), task, rank), strict=True):
                        column.append(value)
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32", "task", "task_rank"])

    return text_bytes(docs).mapInArrow(cut, PIECES)


def exact_patterns(lengths: np.ndarray, capacity: int) -> np.ndarray:
    """Every multiset of at most three of the given lengths that sums to the capacity (rows padded with zeros)."""
    there = np.zeros(capacity + 1, bool)
    there[lengths] = True
    rows = [np.array([[capacity, 0, 0]])] if there[capacity] else []
    a = np.flatnonzero(there[: capacity // 2 + 1])
    a = a[a > 0]
    two = a[there[capacity - a]]
    rows.append(np.stack([capacity - two, two, 0 * two], 1))
    for c in a[a <= capacity // 3]:
        b = a[(a >= c) & (a <= (capacity - c) // 2)]
        b = b[there[capacity - c - b]]
        rows.append(np.stack([capacity - c - b, b, np.full_like(b, c)], 1))
    return np.concatenate(rows) if rows else np.zeros((0, 3), np.int64)


def fit_counts(patterns: np.ndarray, histogram: np.ndarray, rounds: int = 300) -> np.ndarray:
    """Non-negative least squares of pattern repeats against the histogram, by accelerated projected gradient."""
    x = np.zeros(len(patterns))
    if not len(patterns):
        return x
    size = len(histogram)

    def covered(v):
        total = sum(np.bincount(patterns[:, k], weights=v, minlength=size) for k in range(3))
        total[0] = 0
        return total

    # The largest squared singular value bounds the step; a few power steps find it.
    v = np.ones(len(patterns))
    for _ in range(8):
        v = covered(v)[patterns].sum(1)
        top = np.linalg.norm(v)
        v /= top
    y, momentum = x, 1.0
    for _ in range(rounds):
        gap = histogram - covered(y)
        gap[0] = 0
        after = np.maximum(0, y + gap[patterns].sum(1) / (1.1 * top))
        ahead = (1 + (1 + 4 * momentum * momentum) ** 0.5) / 2
        y = after + (momentum - 1) / ahead * (after - x)
        x, momentum = after, ahead
    return x


def plan_bins(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Bins as (lengths, repeats) that use the histogram up exactly."""
    left = np.zeros(capacity + 1, np.int64)
    for length, n in counts.items():
        left[length] += n
    patterns = exact_patterns(np.flatnonzero(left), capacity)
    repeats = fit_counts(patterns, left.astype(float))
    bins: list[tuple[tuple[int, ...], int]] = []
    for k in np.argsort(-repeats, kind="stable"):
        n = int(round(repeats[k]))
        if n < 1:
            break
        parts = tuple(int(x) for x in patterns[k] if x)
        while n and (n := min(n, min(int(left[p]) // parts.count(p) for p in parts))):
            for p in parts:
                left[p] -= n
            bins.append((parts, n))
            break
    # Residuals: longest first into the fullest open bin with room; equal bins move together.
    open_bins: dict[int, list[tuple[tuple[int, ...], int]]] = {}
    spaces: list[int] = []

    def put(space, parts, n):
        if space not in open_bins:
            bisect.insort(spaces, space)
            open_bins[space] = []
        open_bins[space].append((parts, n))

    for length in range(capacity, 0, -1):
        n = int(left[length])
        while n:
            at = bisect.bisect_left(spaces, length)
            if at == len(spaces):
                fits = capacity // length
                if n >= fits:
                    put(capacity - fits * length, (length,) * fits, n // fits)
                if n % fits:
                    put(capacity - n % fits * length, (length,) * (n % fits), 1)
                break
            space = spaces[at]
            parts, there = open_bins[space].pop()
            if not open_bins[space]:
                del open_bins[space]
                spaces.pop(at)
            used = min(there, n)
            if there > used:
                put(space, parts, there - used)
            put(space - length, (*parts, length), used)
            n -= used
    return bins + [b for at in spaces for b in open_bins[at]]


def plan_table(bins: list[tuple[tuple[int, ...], int]]) -> np.ndarray:
    """Rows (length, first rank, first sequence, offset), sorted by length and rank."""
    rows, used, sequence = [], {}, 0
    for parts, n in bins:
        offset = 0
        for length in parts:
            rank = used.get(length, 0)
            rows.append((length, rank, sequence, offset))
            used[length] = rank + n
            offset += length
        sequence += n
    return np.array(sorted(rows), np.int64).reshape(-1, 4)


def pack(docs: DataFrame, vocabulary: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset) for every piece of every document."""
    spark = docs.sparkSession
    cut = written(pieces(docs, vocabulary, capacity, end_id), "pieces")
    by_task = cut.groupBy("task", "length").agg(F.count(F.lit(1)).alias("n"))
    # At most `capacity` rows: lengths are whole numbers up to it.
    counts = {r["length"]: r["n"] for r in by_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    table = plan_table(plan_bins(counts, capacity))
    shift = 44
    keys = spark.sparkContext.broadcast((table[:, 0] << shift | table[:, 1], table[:, 1:]))
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    bases = by_task.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    ranked = cut.join(bases, ["task", "length"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("task_rank")).alias("rank"))

    def place(batches):
        starts, rest = keys.value
        for batch in batches:
            length, rank = (batch.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in (3, 5))
            row = rest[np.searchsorted(starts, length << shift | rank, "right") - 1] if len(rank) else np.zeros((0, 3), np.int64)
            arrays = [*batch.columns[:5], pa.array(row[:, 1] + rank - row[:, 0], pa.int64()), pa.array(row[:, 2], pa.int64())]
            yield pa.RecordBatch.from_arrays(arrays, ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
