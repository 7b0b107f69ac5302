"""Exact removal of repeated byte strings by blockwise suffix grouping with a difference cover.

All suffixes that could share their first 200 bytes share the least hashed 48-byte piece among those bytes (leftmost of
equals): their anchor. So suffixes are bucketed by anchor. Neighbouring suffixes of a text with one anchor are one run,
and a run is one row: anchor hash, content hash, place. Runs whose whole content occurs twice need no more work. Where
one anchor has several contents, one run of each content is fetched and its suffixes are settled block by block: within
a block, cover-sample suffixes are ranked by prefix doubling, suffixes are sorted by bucket and hashed ends, and ties are
settled exactly: the first and last bytes directly, the long middle by the ranks at the cover positions that both
suffixes of a pair reach at the same offset. A block holds a bounded number of bytes beyond its largest bucket; an
anchor with very many different runs is split into buckets of suffixes that share three quarters of their bytes.

Defined results: strings never cross texts; a null or empty text has no bytes; texts under 200 bytes lose nothing;
repeated rows count as occurrences of each other's strings; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Written, map_batches, texts

GRAM, PIECE = 200, 48
WINDOW = GRAM - PIECE + 1
SLICE = 1 << 20  # bytes hashed at once
BLOCK = 4 << 20  # bytes of fetched runs settled at once
COVER = 57
HOT, SPAN = 1_000, 50  # different runs of an anchor beyond which it is split, and the starts of a piece of it
NO_ID = -(1 << 63)
_BASE = 0x2545F4914F6CDD1D
_PLACE = (1 << 24) - 1


def difference_cover(v: int) -> list[int]:
    """A small set of residues whose differences give every residue modulo v (greedy)."""
    cover, missing = [0], set(range(1, v))
    while missing:
        gain = lambda c: len(missing & ({(c - d) % v for d in cover} | {(d - c) % v for d in cover}))
        best = max((c for c in range(v) if c not in cover), key=gain)
        missing -= {(best - d) % v for d in cover} | {(d - best) % v for d in cover}
        cover.append(best)
    return sorted(cover)


_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(12, (n + 1).bit_length())
    if size not in _POWERS:
        _POWERS.clear()
        inverse = pow(_BASE, -1, 1 << 64)
        ups = []
        for base in (_BASE, inverse):
            p = np.full(size, base, np.uint64)
            p[0] = 1
            ups.append(np.multiply.accumulate(p))
        _POWERS[size] = (ups[0], ups[1])
    return _POWERS[size]


class Hashes:
    """Polynomial hashes of substrings of one buffer."""

    def __init__(self, data: np.ndarray):
        up, down = _powers(len(data))
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=self.sums[1:])
        self.down = down

    def at(self, start: np.ndarray | slice, size: int, count: int | None = None) -> np.ndarray:
        if isinstance(start, slice):
            h = (self.sums[size : size + count] - self.sums[:count]) * self.down[:count]
        else:
            h = (self.sums[start + size] - self.sums[start]) * self.down[start]
        h ^= h >> np.uint64(31)
        h *= np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        return h


def _runs(buffer: bytes, ends: np.ndarray) -> tuple[np.ndarray, ...]:
    """(start, size, anchor offset, anchor hash) of the runs of a buffer of several texts."""
    n = len(buffer)
    data = np.frombuffer(buffer, np.uint8)
    pieces = Hashes(data).at(slice(None), PIECE, n - PIECE + 1)
    keys = (pieces & np.uint64(~_PLACE & (1 << 64) - 1)) | np.arange(len(pieces), dtype=np.uint64)
    width = 1
    while 2 * width <= WINDOW:
        keys = np.minimum(keys[:-width], keys[width:])
        width *= 2
    if width < WINDOW:
        rest = WINDOW - width
        keys = np.minimum(keys[:-rest], keys[rest:])
    starts = np.concatenate([[0], ends[:-1]])
    sizes = np.maximum(0, ends - starts - GRAM + 1)
    valid = np.repeat(starts - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
    anchor = (keys[valid] & np.uint64(_PLACE)).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (valid[1:] != valid[:-1] + 1)]))
    begin = valid[first]
    return begin, np.diff(np.append(first, len(valid))), anchor[first] - begin, pieces[anchor[first]]


def _slices(raws: list[bytes]) -> Iterator[list[tuple[int, int, bytes]]]:
    """Groups of (row, offset, bytes) of about a slice; long texts are cut with an overlap of 199 bytes."""
    held, size = [], 0
    for row, raw in enumerate(raws):
        if len(raw) < GRAM:
            continue
        for at in range(0, max(1, len(raw) - GRAM + 1), SLICE):
            part = raw[at : at + SLICE + GRAM - 1]
            held.append((row, at, part))
            size += len(part)
            if size >= SLICE:
                yield held
                held, size = [], 0
    if held:
        yield held


RUNS = "doc long, mark long, at long, n int, off int, anchor long, content long"


def _run_rows(docs: DataFrame) -> DataFrame:
    def each(batch):
        ids, raws = batch.column(0).to_pylist(), [t.encode("utf-8", "surrogatepass") for t in texts(batch)]
        marks = [xxhash.xxh3_64_intdigest(r) for r in raws]
        for group in _slices(raws):
            buffer = b"".join(g[2] for g in group)
            ends = np.cumsum([len(g[2]) for g in group])
            begin, size, off, anchor = _runs(buffer, ends)
            owner = np.searchsorted(ends, begin, "right")
            shift = np.array([g[1] for g in group]) - np.concatenate([[0], ends[:-1]])
            digest = xxhash.xxh3_64_intdigest
            content = np.array([digest(buffer[a : a + n + GRAM - 1]) for a, n in zip(begin.tolist(), size.tolist(), strict=True)], np.uint64)
            row = np.array([g[0] for g in group])[owner]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.array(ids, np.int64)[row]), pa.array(np.array(marks, np.uint64).view(np.int64)[row]), pa.array(begin + shift[owner]),
                    pa.array(size.astype(np.int32)), pa.array(off.astype(np.int32)), pa.array(anchor.view(np.int64)), pa.array(content.view(np.int64)),
                ],
                names=["doc", "mark", "at", "n", "off", "anchor", "content"],
            )

    return map_batches(docs, each, RUNS)


class Block:
    """Suffixes of a text block, with the ranks of its cover sample."""

    def __init__(self, data: np.ndarray, depth: int = GRAM, cover: int = COVER):
        self.size, self.v, self.depth = len(data), cover, depth
        self.data = np.concatenate([data, np.zeros(depth + 2 * cover + 16, np.uint8)])
        self.words = np.lib.stride_tricks.as_strided(self.data[:8].view("<u8"), shape=(len(self.data) - 8,), strides=(1,))
        residues = difference_cover(cover)
        member = np.zeros(cover, bool)
        member[residues] = True
        # for a difference r of two places: a cover residue d with (d + r) in the cover too
        self.meet = np.array([next(d for d in residues if member[(d + r) % cover]) for r in range(cover)])
        self.rank = self._ranks(member)

    def _ranks(self, member: np.ndarray) -> np.ndarray:
        """Rank of the first 2 v bytes at each cover position: by words for v bytes, then doubled once."""
        n = self.size + self.v
        place = np.flatnonzero(np.resize(member, n))
        steps = [*range(0, self.v - 7, 8), self.v - 8]
        order = np.lexsort([self.words[place + s].byteswap() for s in reversed(steps)])
        sorted_ = place[order]
        new = np.zeros(len(place), bool)
        for s in steps:
            w = self.words[sorted_ + s]
            new[1:] |= w[1:] != w[:-1]
        rank = np.zeros(n + self.v, np.int64)
        rank[sorted_] = np.cumsum(new) + 1
        pair = rank[place] * (len(place) + 2) + rank[place + self.v]
        _, twice = np.unique(pair, return_inverse=True)
        out = np.full(n, -1, np.int64)
        out[place] = twice
        return out

    def same(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Whether the suffixes at i and j share their first ``depth`` bytes."""
        v, equal = self.v, np.ones(len(i), bool)
        for s in [*range(0, v - 7, 8), v - 8, *range(2 * v, self.depth - 7, 8), self.depth - 8]:
            equal &= self.words[i + s] == self.words[j + s]
        ahead = (self.meet[(j - i) % v] - i) % v
        return equal & (self.rank[i + ahead] == self.rank[j + ahead])

    def repeated(self, starts: np.ndarray, bucket: np.ndarray) -> np.ndarray:
        """Which of the suffixes share their first ``depth`` bytes with another one in the list."""
        h = Hashes(self.data)
        key = bucket ^ h.at(starts, self.v) ^ (h.at(starts + 2 * self.v, self.depth - 2 * self.v) * np.uint64(3))
        order = np.argsort(key, kind="stable")
        starts, key = starts[order], key[order]
        found = np.zeros(len(starts), bool)
        left = np.arange(len(starts))
        while len(left) > 1:
            k = key[left]
            fresh = np.concatenate([[True], k[1:] != k[:-1]])
            head = np.maximum.accumulate(np.where(fresh, np.arange(len(left)), 0))
            rest = np.flatnonzero(~fresh)
            equal = self.same(starts[left[head[rest]]], starts[left[rest]])
            found[left[rest[equal]]] = True
            found[left[head[rest[equal]]]] = True
            left = left[rest[~equal]]
        out = np.zeros(len(starts), bool)
        out[order] = found
        return out


def _settle(rows: list[tuple]) -> pa.RecordBatch:
    """Repeated places of single runs, for whole buckets of fetched runs (doc, mark, at, n, off, anchor, single, bytes)."""
    data = np.frombuffer(b"".join(r[7] for r in rows), np.uint8)
    base = np.concatenate([[0], np.cumsum([len(r[7]) for r in rows])[:-1]])
    size = np.array([r[3] for r in rows])
    owner = np.repeat(np.arange(len(rows)), size)
    step = np.arange(len(owner)) - np.repeat(np.cumsum(size) - size, size)
    bucket = np.array([r[5] for r in rows], np.int64).view(np.uint64)[owner] + (np.array([r[4] for r in rows])[owner] - step).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    hit = Block(data).repeated(base[owner] + step, bucket) & np.array([r[6] for r in rows])[owner]
    o, s = owner[hit], step[hit]
    fresh = np.concatenate([[True], (o[1:] != o[:-1]) | (s[1:] != s[:-1] + 1)]) if len(o) else np.zeros(0, bool)
    first = np.flatnonzero(fresh)
    length = np.diff(np.append(first, len(o)))
    pick = o[first]
    column = lambda k, kind: pa.array(np.array([r[k] for r in rows], kind)[pick])
    return pa.RecordBatch.from_arrays([column(0, np.int64), column(1, np.int64), pa.array(np.array([r[2] for r in rows])[pick] + s[first]), pa.array(length.astype(np.int32))], names=["doc", "mark", "at", "n"])


def _settled(fetched: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, last = [], 0, None
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if size >= BLOCK and row[5] != last:
                    yield _settle(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[7])
                last = row[5]
        if held:
            yield _settle(held)

    return fetched.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(run, "doc long, mark long, at long, n int")


def _split(raw: bytes, run) -> Iterator[tuple[int, int, int, int]]:
    """A run of a crowded anchor by pieces of SPAN starts, each in a bucket of its own: (at, n, off, bucket).

    Starts are cut by their distance to the anchor, so equal suffixes fall into the same piece. All suffixes of a piece
    cover the same GRAM - SPAN + 1 bytes, whose hash therefore belongs into the bucket: what remains together has the
    greater part of its bytes in common."""
    at, n, off = run["at"], run["n"], run["off"]
    step = 0
    while step < n:
        piece = (off - step) // SPAN
        upto = min(n, off - piece * SPAN + 1)
        first = at + off - piece * SPAN - SPAN + 1
        common = raw[first + SPAN - 1 : first + GRAM]
        bucket = xxhash.xxh3_64_intdigest(common, (run["anchor"] ^ piece) & 0xFFFFFFFFFFFFFFFF)
        yield at + step, upto - step, off - step, bucket - ((bucket >> 63) << 64)
        step = upto


def repeated_places(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> tuple[DataFrame, DataFrame]:
    """(places, keyed docs): places (doc, mark, at, n) are runs of starts whose 200 bytes start elsewhere too.

    ``hot``: anchors with more different runs than this are split into finer buckets."""
    own = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc"), F.col(text_col).alias("text"))
    runs = Written(_run_rows(own), "suffix-runs")
    kinds = Written(
        runs.frame.groupBy("anchor", "content").agg(F.count("*").alias("c"), F.min(F.struct("doc", "mark", "at", "n", "off")).alias("r")).withColumn("single", F.col("c") == 1),
        "suffix-kinds",
    )
    several = kinds.frame.groupBy("anchor").agg(F.count("*").alias("d")).where("d > 1").select("anchor", (F.col("d") > hot).alias("hot"))
    whole = Written(runs.frame.join(kinds.frame.where("not single").select("anchor", "content"), ["anchor", "content"]).select("doc", "mark", "at", "n"), "suffix-whole")
    runs.drop()
    asked = kinds.frame.join(several, "anchor").select("r.*", "anchor", "single", "hot").groupBy("doc", "mark").agg(F.collect_list(F.struct("at", "n", "off", "anchor", "single", "hot")).alias("runs"))

    def fetch(batch):
        out = []
        for doc, text, wanted in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
            raw = (text or "").encode("utf-8", "surrogatepass")
            mark = xxhash.xxh3_64_intdigest(raw)
            mark -= (mark >> 63) << 64
            for group in wanted:
                if group["mark"] == mark:
                    for r in group["runs"]:
                        for at, n, off, anchor in _split(raw, r) if r["hot"] else [(r["at"], r["n"], r["off"], r["anchor"])]:
                            out.append((doc, mark, at, n, off, anchor, r["single"], raw[at : at + n + GRAM - 1]))
        kinds_ = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.bool_(), pa.binary())
        columns = zip(*out, strict=True) if out else ([] for _ in kinds_)
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds_, strict=True)], names=["doc", "mark", "at", "n", "off", "anchor", "single", "raw"])

    by_doc = asked.groupBy("doc").agg(F.collect_list(F.struct("mark", "runs")).alias("wanted"))
    fetched = map_batches(own.join(by_doc.hint("shuffle_hash"), "doc").select("doc", "text", "wanted"), fetch, "doc long, mark long, at long, n int, off int, anchor long, single boolean, raw binary")
    rest = Written(_settled(fetched), "suffix-rest")
    kinds.drop()
    return whole.frame.union(rest.frame), own


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> DataFrame:
    """One row a document: doc_id, the kept bytes, the removed spans, and the contract's digests of them."""
    places, _ = repeated_places(docs, id_col, text_col, hot)
    spans = places.groupBy("doc", "mark").agg(F.sort_array(F.collect_list(F.struct("at", "n"))).alias("places")).groupBy("doc").agg(F.collect_list(F.struct("mark", "places")).alias("wanted"))
    keyed = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc"), F.col(text_col).alias("text"))

    def cut(batch):
        rows = []
        for text, wanted in zip(texts(batch), batch.column(2).to_pylist(), strict=True):
            raw = text.encode("utf-8", "surrogatepass")
            gone: list[list[int]] = []
            if wanted:
                mark = xxhash.xxh3_64_intdigest(raw)
                mark -= (mark >> 63) << 64
                for group in wanted:
                    for p in group["places"] if group["mark"] == mark else ():
                        a, b = p["at"], p["at"] + p["n"] - 1 + GRAM
                        if gone and a <= gone[-1][1]:
                            gone[-1][1] = max(gone[-1][1], b)
                        else:
                            gone.append([a, b])
            kept, at = [], 0
            for a, b in gone:
                kept.append(raw[at:a])
                at = b
            left = b"".join([*kept, raw[at:]])
            rows.append((len(raw), len(raw) - len(left), len(gone), hashlib.sha256(left).hexdigest(), [{"from": a, "to": b} for a, b in gone], left))
        span = pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64())]))
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), span, pa.binary())
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), *(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept"])

    joined = keyed.join(spans.hint("shuffle_hash"), "doc", "left").select("doc_id", "text", "wanted")
    return map_batches(joined, cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<from: long, to: long>>, kept binary")


def digest(removed: DataFrame) -> DataFrame:
    """The contract's columns from the operator's own output."""
    return removed.drop("spans", "kept")
