"""Best-fit packing with large-item matching.

Texts are tokenized once in a map over rows; only piece lengths take part in the packing. Pieces of one length are
interchangeable, so the driver packs the histogram of lengths (at most one count for each length up to the capacity,
whatever the number of documents): pieces above one third of the capacity are matched greedily, at most two in a bin,
the largest with the largest that still fits; smaller ones, from the largest down, go to the tightest gap that holds
them. The plan is a list of bin shapes with multiplicities, and each piece finds its place by its rank among the pieces
of its length.

Defined results: a null or empty text is one piece, the end token alone; repeated rows are packed each; only texts
longer than the capacity are cut, the first piece being the shorter one; extra columns are ignored.
"""

from __future__ import annotations

import uuid
import zlib
from bisect import bisect_left, insort

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_batches, texts, written
from .tokens import encoder

CAPACITY = 2048
END_ID = b"\0\0\0\0"


def pieces_of(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a text of n tokens; the first takes the remainder."""
    if n <= capacity:
        return [(0, n)]
    first = n % capacity or capacity
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


class Plan:
    """Bin shapes for a histogram of lengths, as slots that piece ranks are looked up in."""

    def __init__(self, counts: dict[int, int], capacity: int = CAPACITY):
        left = {k: int(v) for k, v in counts.items() if v}
        shapes: dict[tuple[int, ...], int] = {}
        gaps: dict[int, list[tuple[int, ...]]] = {}
        open_gaps: list[int] = []

        def put(shape: tuple[int, ...], times: int) -> None:
            if shape in shapes:
                shapes[shape] += times
                return
            shapes[shape] = times
            gap = capacity - sum(shape)
            if gap:
                if not gaps.get(gap):
                    gaps[gap] = []
                    insort(open_gaps, gap)
                gaps[gap].append(shape)

        def take(shape: tuple[int, ...], times: int) -> None:
            shapes[shape] -= times
            if not shapes[shape]:
                del shapes[shape]
                gap = capacity - sum(shape)
                gaps[gap].remove(shape)
                if not gaps[gap]:
                    open_gaps.remove(gap)

        large = sorted(k for k in left if 3 * k > capacity)
        while large:
            a = large[-1]
            at = bisect_left(large, capacity - a + 1) - 1
            if at < 0:
                put((a,), left.pop(a))
                large.pop()
                continue
            b = large[at]
            times = left[a] // 2 if a == b else min(left[a], left[b])
            if a == b and not times:
                if at == 0:
                    put((a,), left.pop(a))
                    large.pop()
                    continue
                b = large[at - 1]
                times = min(left[a], left[b])
            put((a, b), times)
            for k in (a, b):
                left[k] -= times
            for k in {a, b}:
                if not left[k]:
                    del left[k]
                    large.remove(k)
        for size in sorted(left, reverse=True):
            n = left[size]
            while n:
                at = bisect_left(open_gaps, size)
                if at < len(open_gaps):
                    gap = open_gaps[at]
                    shape = gaps[gap][-1]
                    bins = shapes[shape]
                else:
                    gap, shape, bins = capacity, (), n
                fit = gap // size
                bins = min(bins, n // fit)
                each = fit if bins else n
                bins = bins or 1
                if shape:
                    take(shape, bins)
                put(shape + (size,) * each, bins)
                n -= bins * each
        slots, rank, self.bins = [], {}, 0
        for shape, times in shapes.items():
            offset = 0
            for size in shape:
                slots.append((size, rank.get(size, 0), self.bins, offset))
                rank[size] = rank.get(size, 0) + times
                offset += size
            self.bins += times
        slots.sort()
        table = np.array(slots, np.int64).reshape(-1, 4)
        self.keys, self.first, self.bin, self.offset = (table[:, 0] << 44) + table[:, 1], table[:, 1], table[:, 2], table[:, 3]

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(bin, offset) of pieces by their length and their rank among pieces of that length."""
        at = np.searchsorted(self.keys, (length << 44) + rank, "right") - 1
        return self.bin[at] + rank - self.first[at], self.offset[at]


def cut(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, vocabulary: str | None = None) -> DataFrame:
    """One row a piece: doc_id, piece, start, length, ids_crc32, and its task with its number there for its length."""

    def setup():
        coder, task, numbers = encoder(vocabulary), TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)

        def each(batch):
            ids = batch.column(0).cast(pa.int64()).to_pylist()
            rows = []
            for doc, text in zip(ids, texts(batch), strict=True):
                coded = coder.ids(text) + END_ID
                for piece, (start, length) in enumerate(pieces_of(len(coded) // 4, capacity)):
                    rows.append((doc, piece, start, length, zlib.crc32(coded[4 * start : 4 * (start + length)]), int(numbers[length])))
                    numbers[length] += 1
            d, p, s, n, c, k = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays(
                [pa.array(d, pa.int64()), pa.array(p, pa.int32()), *(pa.array(x, pa.int64()) for x in (s, n, c)), pa.array([task] * len(k), pa.int32()), pa.array(k, pa.int64())],
                names=["doc_id", "piece", "start", "length", "ids_crc32", "task", "number"],
            )

        return each

    return map_batches(
        docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), None, "doc_id long, piece int, start long, length long, ids_crc32 long, task int, number long", setup
    )


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, vocabulary: str | None = None) -> DataFrame:
    """One row a piece with its sequence and its offset there.

    The pieces are written once (ids stay with the text's owner; only their CRC is kept), so that a lost executor cannot
    renumber them. Ranks within a length come from prefix sums over (task, length) counts, without sorting pieces.
    """
    pieces = written(cut(docs, id_col, text_col, capacity, vocabulary), "packing-pieces")
    counts = pieces.groupBy("length", "task").agg(F.count("*").alias("n"))
    base = counts.select("length", "task", (F.sum("n").over(Window.partitionBy("length").orderBy("task")) - F.col("n")).alias("base"))
    plan = Plan({r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}, capacity)
    shared, token = docs.sparkSession.sparkContext.broadcast(plan), uuid.uuid4().hex
    ranked = pieces.join(base, ["length", "task"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("number")).alias("rank"))

    def each(batch):
        own = _plan(shared, token)
        length, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("length", "rank"))
        sequence, offset = own.place(length, rank)
        yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence, pa.int64()), pa.array(offset, pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return map_batches(ranked, each, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


_PLANS: dict[str, Plan] = {}


def _plan(shared, token: str) -> Plan:
    if token not in _PLANS:
        _PLANS.clear()
        _PLANS[token] = shared.value
    return _PLANS[token]
