"""Benchmark decontamination by Wu-Manber multi-pattern search.

Texts become byte strings of lower-case words with one blank between and around them, so that a benchmark window
(13 words) occurs exactly where its padded byte string does. Patterns are dealt into classes by length; each class has
a shift table over hashed blocks of bytes, buckets by the hash of the block that ends the first ``m`` bytes, and a
direct comparison. A batch of texts is scanned by many lanes at once: each lane keeps one position, and a numpy step
moves all of them by their shifts.

Defined results: a null or wordless text has no words and no hits; wordless benchmark items never occur; repeated
rows each get their row; items of one id are one item; items without an id count in hit words and verdict and together
as one item, but have no name in the list; extra columns are ignored; an empty benchmark leaves all clean.

A benchmark of more bytes than one set of broadcast patterns may have is dealt into groups of items, and the documents pass
them one after another, each pass adding to the hit runs and items of the ones before.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Written, map_batches, texts

WINDOW = 13
# Bytes of patterns in one set of tables; a larger benchmark is searched set by set.
CHUNK_BYTES = 64 << 20
# Benchmark text of one pass over the documents: its windows take about 13 times as much in every Python worker.
GROUP_BYTES = 32 << 20
_HASH = np.uint64(0x9E3779B97F4A7C15)

_SEPARATE = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def words_of(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_SEPARATE).split()


def windows_of(words: list[bytes], size: int = WINDOW) -> list[bytes]:
    """Padded byte strings of an item's windows."""
    if not words:
        return []
    last = max(1, len(words) - size + 1)
    return [b" " + b" ".join(words[i : i + size]) + b" " for i in range(last)]


class ShiftTables:
    """Wu-Manber tables for patterns of similar length."""

    def __init__(self, patterns: list[bytes]):
        self.patterns = patterns
        self.m = min(map(len, patterns))
        self.block = min(8, self.m)
        self.bits = min(22, max(12, int(len(patterns) * (self.m - self.block + 1)).bit_length() + 3))
        self.mask = np.uint64((1 << (8 * self.block)) - 1)
        heads = np.frombuffer(b"".join(p[: self.m] for p in patterns), np.uint8).reshape(len(patterns), self.m)
        spread = self.m - self.block
        self.shift = np.full(1 << self.bits, spread + 1, np.int32)
        for at in range(spread + 1):
            chunk = np.zeros((len(patterns), 8), np.uint8)
            chunk[:, : self.block] = heads[:, at : at + self.block]
            keys = self._key(chunk.view("<u8")[:, 0])
            np.minimum.at(self.shift, keys, spread - at)
        self.buckets: dict[int, list[int]] = {}
        for i, key in enumerate(keys.tolist()):
            self.buckets.setdefault(key, []).append(i)

    def _key(self, blocks: np.ndarray) -> np.ndarray:
        return ((blocks & self.mask) * _HASH >> np.uint64(64 - self.bits)).astype(np.int64)

    def search(self, buffer: bytes) -> list[tuple[int, int]]:
        """(start, pattern number) of every occurrence in the buffer."""
        n = len(buffer)
        if n < self.m:
            return []
        padded = np.frombuffer(buffer + b"\0" * 8, np.uint8)
        words = np.lib.stride_tricks.as_strided(padded[:8].view("<u8"), shape=(n,), strides=(1,))
        first, lanes = self.m - 1, max(1, min(1 << 15, n // 512))
        edges = np.linspace(first, n, lanes + 1).astype(np.int64)
        at, end = edges[:-1].copy(), edges[1:]
        tests = []
        while at.size:
            live = at < end
            if not live.all():
                at, end = at[live], end[live]
                if not at.size:
                    break
            step = self.shift[self._key(words[at - (self.block - 1)])]
            hit = step == 0
            if hit.any():
                tests.append(at[hit].copy())
            at += np.maximum(step, 1)
        found = []
        if tests:
            ends = np.concatenate(tests)
            keys = self._key(words[ends - (self.block - 1)])
            for stop, key in zip(ends.tolist(), keys.tolist(), strict=True):
                start = stop - first
                for i in self.buckets.get(key, ()):
                    if buffer.startswith(self.patterns[i], start):
                        found.append((start, i))
        return found


class PatternSet:
    """All windows of a benchmark, with the items that own each."""

    def __init__(self, items: list[tuple[str | None, str]], window: int = WINDOW):
        owners: dict[bytes, set[str | None]] = {}
        for item, text in items:
            for pattern in windows_of(words_of(text or ""), window):
                owners.setdefault(pattern, set()).add(item)
        classes: dict[int, list[bytes]] = {}
        for pattern in owners:
            classes.setdefault(len(pattern).bit_length(), []).append(pattern)
        self.tables = []
        for patterns in classes.values():
            held, size = [], 0
            for p in patterns:
                held.append(p)
                size += len(p)
                if size >= CHUNK_BYTES:
                    self.tables.append(ShiftTables(held))
                    held, size = [], 0
            if held:
                self.tables.append(ShiftTables(held))
        self.owners = owners

    def hits(self, words: list[list[bytes]]) -> list[tuple[int, set[str], list[tuple[int, int]]]]:
        """For each text: number of hit words, items that occur, and hit runs of words [from, to)."""
        parts, starts, at = [], [], 0
        for ws in words:
            starts.append(at)
            part = b" " + b" ".join(ws) + b" "
            parts.append(part)
            at += len(part)
        buffer = b"".join(parts)
        origin = np.array(starts, np.int64)
        out: list[tuple[int, set[str], list[tuple[int, int]]]] = [(0, set(), []) for _ in words]
        by_text: dict[int, list[tuple[int, bytes]]] = {}
        for table in self.tables:
            found = table.search(buffer)
            if not found:
                continue
            where = np.searchsorted(origin, np.array([f[0] for f in found]), "right") - 1
            for (start, i), k in zip(found, where.tolist(), strict=True):
                p = table.patterns[i]
                if start + len(p) <= starts[k] + len(parts[k]):
                    by_text.setdefault(k, []).append((start - starts[k], p))
        for k, found in by_text.items():
            ends = np.cumsum([len(w) + 1 for w in words[k]])  # byte offset of the blank after each word
            begin = np.concatenate([[0], ends[:-1]])
            items: set[str] = set()
            mark = np.zeros(len(words[k]) + 1, np.int32)
            for start, p in found:
                i = int(np.searchsorted(begin, start))
                items.update(self.owners[p])
                mark[i] += 1
                mark[i + p.count(b" ") - 1] -= 1
            covered = np.cumsum(mark[:-1]) > 0
            edge = np.flatnonzero(np.diff(np.concatenate([[0], covered.view(np.int8), [0]])))
            out[k] = (int(covered.sum()), items, list(zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True)))
        return out


_RUN = pa.struct([("from", pa.int64()), ("to", pa.int64())])
EXTRA = {"__runs": pa.list_(_RUN), "__items": pa.list_(pa.string()), "__nameless": pa.bool_(), "__words": pa.int64()}
_EXTRA_SQL = "__runs array<struct<from: long, to: long>>, __items array<string>, __nameless boolean, __words long"


def _joined(runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Runs [from, to) that overlap or touch, as one."""
    out: list[list[int]] = []
    for a, b in sorted(runs):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _item_groups(benchmark: DataFrame, text_col: str, item_col: str, limit: int):
    """The benchmark as broadcasts of at most about ``limit`` bytes of text."""
    small = benchmark.select(F.col(item_col).cast("string").alias("item"), F.col(text_col).alias("text"))
    size = small.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    groups = max(1, -(-size // limit))
    for k in range(groups):
        part = small if groups == 1 else small.where(F.pmod(F.xxhash64("text"), F.lit(groups)) == k)
        yield k + 1 == groups, benchmark.sparkSession.sparkContext.broadcast([(r["item"], r["text"]) for r in part.collect()])


def _searched(frame: DataFrame, benchmark: DataFrame, text_col: str, item_col: str, window: int, limit: int, kept: list[str], clean_only: bool = False) -> DataFrame:
    """The columns ``kept`` with hit runs, items, whether an item without a name occurs, and the number of words."""
    columns, first, before = frame.columns, True, None
    for last, shared in _item_groups(benchmark, text_col, item_col, limit):
        out = kept if last else columns
        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in frame.schema if f.name in out)
        done = map_batches(frame, None, f"{fields}, {_EXTRA_SQL}", _pass(shared, uuid.uuid4().hex, window, text_col, [c for c in columns if c in out], first, clean_only and last))
        if last:
            return done
        held = Written(done, "decontaminate")
        if before:
            before.drop()
        frame, first, before = held.frame, False, held


def _pass(shared, token: str, window: int, text_col: str, out: list[str], first: bool, clean_only: bool):
    def setup():
        patterns = _pattern_set(shared, token, window)

        def each(batch):
            known = None if first else [batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("__runs", "__items", "__nameless")]
            for lo, group in _by_bytes(texts(batch, text_col)):
                words = [words_of(t) for t in group]
                hits = patterns.hits(words)
                runs, items = [h[2] for h in hits], [h[1] for h in hits]
                if known:
                    runs = [_joined([*r, *((x["from"], x["to"]) for x in known[0][lo + i])]) for i, r in enumerate(runs)]
                    items = [t | set(known[1][lo + i]) | ({None} if known[2][lo + i] else set()) for i, t in enumerate(items)]
                told = [[[{"from": a, "to": b} for a, b in r] for r in runs], [sorted(t - {None}) for t in items], [None in t for t in items], [len(w) for w in words]]
                part = batch.slice(lo, len(group)).select(out)
                done = pa.RecordBatch.from_arrays([*part.columns, *(pa.array(c, k) for c, k in zip(told, EXTRA.values(), strict=True))], names=[*out, *EXTRA])
                if clean_only:
                    n_hit = [sum(b - a for a, b in r) for r in runs]
                    done = done.filter(pa.array([not (n > 0 and 20 * n >= len(w)) for n, w in zip(n_hit, words, strict=True)], pa.bool_()))
                yield done

        return each

    return setup


def find_contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", window: int = WINDOW, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """One row a document: words, hit words, the items that occur, the hit runs of words, and the verdict.

    The benchmark is read by the driver in groups of a checked size and broadcast; documents are never shuffled.
    """
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    told = _searched(own, benchmark, "text", item_col, window, group_bytes, ["doc_id"])
    n_hit = F.aggregate("__runs", F.lit(0).cast("long"), lambda s, r: s + r["to"] - r["from"])
    counted = told.select("doc_id", F.col("__words").alias("n_words"), n_hit.alias("n_hit"), (F.size("__items") + F.col("__nameless").cast("int")).cast("long").alias("n_items"), F.col("__items").alias("items"), F.col("__runs").alias("runs"))
    return counted.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))


def keep_clean(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", window: int = WINDOW, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """The documents that are not contaminated, with all their columns."""
    return _searched(docs, benchmark, text_col, item_col, window, group_bytes, docs.columns, clean_only=True).select(*docs.columns)


_SETS: dict[str, PatternSet] = {}


def _pattern_set(shared, token: str, window: int) -> PatternSet:
    """Tables are built once a Python worker."""
    if token not in _SETS:
        _SETS.clear()
        _SETS[token] = PatternSet(shared.value, window)
    return _SETS[token]


def _by_bytes(batch: list[str], limit: int = 8 << 20):
    """Runs of texts of about so many characters."""
    lo, size = 0, 0
    for i, t in enumerate(batch):
        size += len(t)
        if size >= limit:
            yield lo, batch[lo : i + 1]
            lo, size = i + 1, 0
    if lo < len(batch):
        yield lo, batch[lo:]


def digest(found: DataFrame) -> DataFrame:
    """The contract's columns from the operator's own output."""
    return found.select(
        "doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), "contaminated", "runs"
    )
