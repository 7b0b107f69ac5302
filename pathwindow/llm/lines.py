"""Line dedup by an exact set-similarity join.

A line is its set of lower-case words. A line goes when an earlier line (by doc_id, then line number) has a Jaccard
similarity of 0.8 or more with it; the first of its kind stays. Words are ordered by rarity (counts in a fixed number of
hash buckets over all texts, so the order that everybody shares has a fixed size), and two similar sets share a word
among the first few of each: these prefixes are the join keys. Positional and length filters drop pairs that cannot
reach the threshold, and the words themselves decide the rest.

Postings carry parity bits of their set, which bound how much two sets can differ, so few other pairs are left to verify.
A group of near copies never emits all its pairs: a line proposes its two nearest earlier partners of each prefix word,
the nearest eight of all are verified first, and lines that they do not settle meet the others in a last round, all that
share a prefix word where they had still more partners. Sets with equal hashes are proposed as pairs too, and their
words decide; of such sets only the first meets others, since it is the earliest of them and as near to everything. Should
words ever disprove an equality of hashes, all is done again with every set meeting. Postings of very frequent words are
dealt to salted groups of bounded size; what lies in different groups meets in the last round.

Defined results: blank lines and null or empty texts have no words and are never removed; lines of the same set of words
count as copies whatever their order; rows of one doc_id are one document and not compared line by line with
themselves if their texts are equal; different texts under one doc_id, or under none, are documents of their own, told
apart by a hash of the text and ordered by it; a null doc_id orders before all others; extra columns are ignored or, in ``rewrite``, kept.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Written, lists_hashed, map_batches, trim

THRESHOLD = 0.8
BUCKETS = 1 << 22
CHUNK = 1 << 12
PIECE = 8 << 20  # bytes of text whose lines are taken at once
BLOCK = 1 << 20  # bytes of text hashed at once
NO_ID = -(1 << 63)
CLASHING = 1_000_000  # repeated ids that are broadcast; more are joined by a shuffle


def words_of(line: str) -> set[bytes]:
    return set(line.encode("utf-8", "surrogatepass").lower().split())


def prefix_size(n: int, threshold: float = THRESHOLD) -> int:
    return n - math.ceil(threshold * n - 1e-9) + 1


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The documents with their key (doc, mark): the id, or NO_ID; and a hash of the text where the id is none or is
    repeated, 0 elsewhere, so that marks cost next to nothing where ids are unique. Only ids are read to tell."""
    doc = F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID))
    owned = docs.where(F.col(id_col).isNotNull()).select(doc.alias("__clash"))
    clashing = Written(owned.groupBy("__clash").agg(F.count("*").alias("n")).where("n > 1").select("__clash"), "lines-clashing").frame
    n = clashing.count()
    marked, keyed = F.col("doc") == NO_ID, docs.withColumn("doc", doc)
    if n:
        keyed = keyed.join(F.broadcast(clashing) if n <= CLASHING else clashing, F.col("doc") == F.col("__clash"), "left")
        marked = marked | F.col("__clash").isNotNull()
    mark = F.when(marked, F.xxhash64(F.coalesce(F.col(text_col), F.lit("")))).otherwise(F.lit(0).cast("long"))
    return keyed.withColumn("mark", mark).drop("__clash")


def _bytes(batch: pa.RecordBatch) -> list[bytes]:
    """The texts of a batch as UTF-8; a null counts as empty."""
    column = batch.column(batch.schema.get_field_index("text"))
    return [t or b"" for t in column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()]


def _pieces(column: pa.Array, size: int) -> Iterator[tuple[int, pa.Array]]:
    """Runs of texts of some bytes, each with the row that it starts at."""
    upto = np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < len(column):
        end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + size, "right")))
        yield at, column.slice(at, end - at)
        at = end


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


_SPACE = np.isin(np.arange(256), list(b" \t\n\v\f\r"))
_HEAD = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)  # the first k bytes of eight


def _hashes(column: pa.Array) -> tuple[np.ndarray, ...]:
    """The lower-cased bytes of a run of texts, where the texts begin and end, the words' first bytes and hashes."""
    low = pc.ascii_lower(column)
    _, offsets, data = low.buffers()
    ends = np.frombuffer(offsets, np.int64 if pa.types.is_large_string(low.type) else np.int32)[low.offset : low.offset + len(low) + 1].astype(np.int64)
    size = int(ends[-1] - ends[0])
    raw = np.zeros(size + 8, np.uint8)
    if size:
        raw[:size] = np.frombuffer(data, np.uint8)[ends[0] : ends[-1]]
    ends -= ends[0]
    blank = np.ones(size + 1, bool)
    blank[:size] = _SPACE[raw[:size]]
    opens, closes = np.append(True, blank[:-1]), blank.copy()
    opens[ends[:-1]] = True
    at_end = ends[1:][ends[1:] > 0] - 1
    closes[:-1] = blank[1:]
    closes[at_end] = True
    first, last = np.flatnonzero(~blank & opens), np.flatnonzero(~blank & closes) + 1
    eight = np.ndarray((size + 1,), "<u8", raw, strides=(1,))
    left, by = last - first, np.uint64(0xD6E8FEB86659FD93)
    hashes = _mixed((_mixed(left.astype(np.uint64) ^ np.uint64(0x5851F42D4C957F2D)) ^ (eight[first] & _HEAD[np.minimum(left, 8)])) * by)
    some = np.flatnonzero(left > 8)
    at, left = first[some] + 8, left[some] - 8
    while len(some):
        hashes[some] = _mixed((hashes[some] ^ (eight[at] & _HEAD[np.minimum(left, 8)])) * by)
        more = left > 8
        some, at, left = some[more], at[more] + 8, left[more] - 8
    return raw[:size], ends, first, hashes


def _tokens(column: pa.Array) -> tuple[np.ndarray, ...]:
    """The lower-cased bytes of a run of texts; row, number, start, end and number of words of each line; the words' hashes."""
    raw, ends, first, hashes = _hashes(column)
    size = len(raw)
    filled, breaks = np.flatnonzero(np.diff(ends)), np.flatnonzero(raw == 10) + 1
    # A break at the very end of a text opens an empty line there, before the next text's first.
    start, row = np.concatenate([ends[filled], breaks]), np.concatenate([filled, np.searchsorted(ends[1:], breaks, "left")])
    order = np.lexsort([row, start])
    start, row = start[order], row[order]
    words = np.diff(np.append(np.searchsorted(first, start), len(first)))
    return raw, row, np.arange(len(row)) - np.searchsorted(row, row), start, np.append(start[1:], size), words, hashes


class _Lines:
    """Lines of a run of texts, by row and number, the number of their words, and the hashes of all words in their order."""

    def __init__(self, column: pa.Array):
        parts, at = [], 0
        for first, block in _pieces(column, BLOCK):
            raw, row, number, start, end, size, hashes = _tokens(block)
            parts.append((raw, row + first, number, start + at, end + at, size, hashes))
            at += len(raw)
        self.raw, self.row, self.number, self.start, self.end, self.size, self.hash = (np.concatenate(c) for c in zip(*parts, strict=True))

    def same(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether lines a and b are equal byte for byte (but for a break at the end)."""
        text = self.raw.tobytes() if len(a) else b""
        line = lambda k: text[self.start[k] : self.end[k]].rstrip(b"\n")
        return np.fromiter((line(i) == line(j) for i, j in zip(a.tolist(), b.tolist(), strict=True)), bool, len(a))


def _rarity(docs: DataFrame) -> np.ndarray:
    """Coded counts (a byte each, logarithmic) of word hash buckets over all texts. Tasks send their sums in short runs
    of buckets, which are added up as they stream by."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(BUCKETS, np.uint32)
        for batch in batches:
            for _, column in _pieces(batch.column(0), BLOCK):
                np.add.at(total, (_hashes(column)[-1] & np.uint64(BUCKETS - 1)).view(np.int64), np.uint32(1))
        trim()
        for i in range(0, BUCKETS, CHUNK):
            run = total[i : i + CHUNK]
            if run.any():
                yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([run.tobytes()], pa.binary())], names=["at", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, total = None, np.zeros(CHUNK, np.uint64)
        for batch in batches:
            for i, part in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if i != at and at is not None:
                    yield coded(at, total)
                    total[:] = 0
                at = i
                total += np.frombuffer(part.as_buffer(), np.uint32)
        if at is not None:
            yield coded(at, total)

    def coded(at: int, total: np.ndarray) -> pa.RecordBatch:
        code = np.minimum(120, np.round(4 * np.log2(total + 1.0))).astype(np.uint8)
        return pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([code.tobytes()], pa.binary())], names=["at", "codes"])

    sums = docs.mapInArrow(count, "at int, counts binary").repartition("at").sortWithinPartitions("at")
    codes = np.zeros(BUCKETS, np.uint8)
    for row in sums.mapInArrow(add, "at int, codes binary").collect():
        codes[row["at"] : row["at"] + CHUNK] = np.frombuffer(row["codes"], np.uint8)
    return codes


_CODES: dict[str, np.ndarray] = {}
PACKED = "part int, rows binary"
# A posting's columns (token, doc, mark, line, ni, s0, s1, whole): each lies in one piece within a packed row.
POSTING = tuple(map(np.dtype, ("<i8", "<i8", "<i8", "<i4", "<i8", "<i8", "<i8", "<i8")))
PART = 2_000_000  # words whose postings share a part, about
MEETING = "kind int, doc long, mark long, line int, ydoc long, ymark long, yline int, apart int, asks boolean, token long, ni long, s0 long, s1 long"
COPY, WHOLE = -2, -1
GONE, PAIR, GROUPED = 0, 1, 2
EQUAL = -1  # in place of the parity distance: sets whose hashes are equal
ONCE = 4  # the code of words that occur once
WIDE = 96  # sets above this size compare 128 parity bits, others 64
GROUP = 2_048  # postings of one token that meet at once; beyond, leaders come first
CROWD = 20_000  # words that occur more often deal their postings to salted groups of about this size
SALT = 12  # low bits of a token that tell its salted groups apart
BESIDE = 13  # bits of a line's number beside a word's, 51 bits, in one sorting key
KEY, YOURS = ["doc", "mark", "line"], ["ydoc", "ymark", "yline"]
NEAREST = 8  # partners of a line, by parity bits, that its words are compared with first
MEETS = 3_000_000  # pairs that a step may look at, beyond its largest group
GATHER = 100_000  # postings of one vectorised step, about


def _parities(flat: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two words of bits a set: bit b tells whether an odd number of its words hash to b; of wide sets the second word
    holds those of one half of the hash range. Sets that differ in d words differ in at most d bits."""
    one = np.left_shift(np.uint64(1), (flat >> np.uint64(SALT)) & np.uint64(63))
    s0 = np.bitwise_xor.reduceat(one, starts)
    half = np.where((flat & np.uint64(64 << SALT)) > 0, one, np.uint64(0))
    s1 = np.where(sizes > WIDE, np.bitwise_xor.reduceat(half, starts), np.uint64(0))
    return s0.view(np.int64), s1.view(np.int64)


def _groups(token: np.ndarray, crowd: int) -> np.ndarray:
    """The number of salted groups that a token's postings are dealt to, by the code of its count."""
    return np.minimum(1 << SALT, np.ceil(np.exp2((token >> 44 + SALT) / 4.0) / crowd)).astype(np.int64)


def _company(columns: list[np.ndarray], crowd: int) -> list[np.ndarray]:
    """The postings by token, without those that are alone with theirs and so meet nobody here: known copies stay, and very frequent words."""
    token, ni = columns[0], columns[4]
    order = np.argsort(token)
    new = token[order[1:]] != token[order[:-1]]
    alone = np.concatenate([[True], new]) & np.append(new, True)[: len(order)]
    single = order[alone]
    crowded = (ni[single] >= 0) & (_groups(np.arange(128) << 44 + SALT, crowd) > 1)[token[single] >> 44 + SALT & 127]
    alone[np.flatnonzero(alone)[crowded | (ni[single] == COPY)]] = False
    order = order[~alone]
    return [c[order] for c in columns]


def _parts(codes: np.ndarray, shuffles: int) -> int:
    """Into how many parts tokens are dealt: some to a shuffle partition, and enough that a part stays small in a task."""
    words = float(np.exp2(codes / 4.0).sum()) - len(codes)
    return min(1 << 16, max(shuffles, min(4 * shuffles, 1_024), math.ceil(words / PART)))


def _packed(columns: list[np.ndarray], parts: int) -> pa.RecordBatch:
    """Postings by the part of their token: (part, rows), a row for each part, so that Spark moves few large rows."""
    part = (_mixed(columns[0].view(np.uint64)) % np.uint64(parts)).astype(np.uint16)
    order = np.argsort(part, kind="stable")
    part, columns = part[order], [np.ascontiguousarray(c[order], t) for c, t in zip(columns, POSTING, strict=True)]
    opens = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]])) if len(part) else np.zeros(0, np.int64)
    ends = np.append(opens, len(part))[1:]
    rows = [b"".join(c[a:b].tobytes() for c in columns) for a, b in zip(opens.tolist(), ends.tolist(), strict=True)]
    return pa.RecordBatch.from_arrays([pa.array(part[opens].astype(np.int32)), pa.array(rows, pa.binary())], names=["part", "rows"])


def _unpacked(rows: list) -> list[np.ndarray]:
    """The columns of the postings in packed rows."""
    width = sum(t.itemsize for t in POSTING)
    found: list[list[np.ndarray]] = [[] for _ in POSTING]
    for row in rows:
        n, at = len(row) // width, 0
        for column, kind in zip(found, POSTING, strict=True):
            column.append(np.frombuffer(row, kind, n, at))
            at += n * kind.itemsize
    return [np.concatenate(c) for c in found]


def _postings(docs: DataFrame, codes: np.ndarray, threshold: float, crowd: int = CROWD, bits: int = 64) -> DataFrame:
    """Packed rows of (token, doc, mark, line, ni, s0, s1, whole): the prefix words of each line with ni = size * 2^32 + position and the hash
    of its whole set, of some bits; that hash as a token with ni = WHOLE; and lines that repeat one of their run of texts, known to go, with ni = COPY and no prefix.

    A token is the code of a word's count, 44 bits of its hash, and a salt where the word is very frequent. Different
    words of one token only meet for nothing. A word that occurs once meets nobody and is not posted."""
    shared, name = docs.sparkSession.sparkContext.broadcast(codes), uuid.uuid4().hex
    parts = _parts(codes, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def each(batch):
        if name not in _CODES:
            _CODES.clear()
            _CODES[name] = shared.value
        doc_of, mark_of = (batch.column(i).to_numpy() for i in (0, 1))
        for at, column in _pieces(batch.column(2), PIECE):
            seen = _Lines(column)
            if len(seen.hash):
                found = list(run(seen, doc_of[at : at + len(column)], mark_of[at : at + len(column)]))
                yield _packed([np.concatenate(c) for c in zip(*found, strict=True)], parts)

    def run(seen: _Lines, doc_of: np.ndarray, mark_of: np.ndarray):
        number = _CODES[name][(seen.hash & np.uint64(BUCKETS - 1)).view(np.int64)].astype(np.uint64) << np.uint64(44) | seen.hash >> np.uint64(20)
        line = np.repeat(np.arange(len(seen.size)), seen.size)
        runs = []
        for a in range(0, len(seen.size), 1 << BESIDE):  # as many lines as fit a key beside the number
            i, j = np.searchsorted(line, [a, a + (1 << BESIDE)])
            key = np.sort((line[i:j] - a).view(np.uint64) << np.uint64(64 - BESIDE) | number[i:j])
            if len(key):
                key = key[np.concatenate([[True], key[1:] != key[:-1]])]
                runs.append(((key >> np.uint64(64 - BESIDE)).view(np.int64) + a, key & np.uint64((1 << 64 - BESIDE) - 1)))
        line, flat = (np.concatenate(c) for c in zip(*runs, strict=True))
        flat <<= np.uint64(SALT)
        starts = np.flatnonzero(np.concatenate([[True], line[1:] != line[:-1]]))
        sizes = np.diff(np.append(starts, len(line)))
        whole = (np.add.reduceat(_mixed(flat), starts) >> np.uint64(64 - bits)).view(np.int64)
        of = line[starts]
        doc, mark, nth = doc_of[seen.row[of]], mark_of[seen.row[of]], seen.number[of]
        # Lines that equal an earlier one of the run byte for byte; sets that only have equal hashes are left for later.
        by = np.lexsort([nth, mark, doc, whole])
        opens = np.flatnonzero(np.concatenate([[True], whole[by[1:]] != whole[by[:-1]]]))
        lead = np.empty(len(by), np.int64)
        lead[by] = np.repeat(by[opens], np.diff(np.append(opens, len(by))))
        mine = np.flatnonzero(lead != np.arange(len(lead)))
        same = np.zeros(len(lead), bool)
        same[mine] = seen.same(of[mine], of[lead[mine]])
        gone = np.flatnonzero(same & ((doc != doc[lead]) | (mark != mark[lead]) | (nth != nth[lead])))
        if len(gone):
            yield whole[gone] ^ (gone << 20), doc[gone], mark[gone], nth[gone], np.full(len(gone), COPY), *np.zeros((3, len(gone)), np.int64)
        left = np.flatnonzero(~same)
        s0, s1 = _parities(flat, starts, sizes)
        yield whole[left], doc[left], mark[left], nth[left], np.full(len(left), WHOLE), *np.zeros((3, len(left)), np.int64)
        n = sizes[left]
        counts = n - np.ceil(threshold * n - 1e-9).astype(np.int64) + 1
        place = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
        row = np.repeat(left, counts)
        token = flat[starts[row] + place]
        kept = np.flatnonzero(token >> np.uint64(44 + SALT) != ONCE)
        row, token, place = row[kept], token[kept], place[kept]
        groups = _groups(token.view(np.int64), crowd)
        many = np.flatnonzero(groups > 1)
        token[many] |= _mixed((doc[row[many]] * 31 + nth[row[many]]).view(np.uint64)) % groups[many].view(np.uint64)
        yield token.view(np.int64), doc[row], mark[row], nth[row], (sizes[row] << 32) | place, s0[row], s1[row], whole[row]

    return map_batches(docs, each, PACKED)


def _firsts(columns: list[np.ndarray]) -> np.ndarray:
    """Of postings by token, those whose set, by its hash, no earlier line of their token has."""
    token, doc, mark, line, ni, _, _, whole = columns
    ids = np.flatnonzero(ni >= 0)
    if not len(ids):
        return np.arange(len(token))
    # The group's number above the hash's upper bits: sets with equal hashes lie side by side.
    group = np.cumsum(np.append(True, token[ids[1:]] != token[ids[:-1]]), dtype=np.uint64)
    room = int(group[-1]).bit_length()
    by = np.argsort(group << np.uint64(64 - room) | whole[ids].view(np.uint64) >> np.uint64(room))
    by, group = ids[by], group[by]
    new = np.append(True, (group[1:] != group[:-1]) | (whole[by[1:]] != whole[by[:-1]]))
    shared = np.flatnonzero(~new | ~np.append(new[1:], True))
    by, of = by[shared], np.cumsum(new)[shared]
    order = np.lexsort([line[by], mark[by], doc[by], of])
    by, of = by[order], of[order]
    stays = np.ones(len(token), bool)
    stays[by[1:][of[1:] == of[:-1]]] = False
    return np.flatnonzero(stays)


class _Meetings:
    """The pairs of one step: columns of postings by token, here sorted by size within it; with ``spare``, of sets with
    equal hashes the first alone."""

    def __init__(self, columns: list[np.ndarray], threshold: float, crowd: int, group: int, spare: bool = True):
        self.threshold, self.crowd, self.group = threshold, crowd, group
        if spare:
            first = _firsts(columns)
            columns = [c[first] for c in columns]
        group = np.cumsum(np.append(True, columns[0][1:] != columns[0][:-1]), dtype=np.uint64)[: len(columns[0])]
        order = np.argsort(group << np.uint64(32) | ((columns[4] >> 32) + 1).view(np.uint64))
        token, self.doc, self.mark, line, self.ni, s0, s1 = (c[order] for c in columns[:7])
        self.line, self.token = line.astype(np.int64), token
        self.n, self.i = self.ni >> 32, self.ni & 0xFFFFFFFF
        self.s0, self.s1 = s0.view(np.uint64), s1.view(np.uint64)

    def apart(self, a, b):
        """Differing parity bits, or -1 where the length, positional or parity filter rules the pair out."""
        n, m, share = self.n[a], self.n[b], self.threshold / (1 + self.threshold)
        need = np.ceil(share * (n + m) - 1e-9)
        may = (np.minimum(n, m) >= self.threshold * np.maximum(n, m) - 1e-9) & (np.minimum(n - self.i[a], m - self.i[b]) >= need)
        d0, d1 = self.s0[a] ^ self.s0[b], self.s1[a] ^ self.s1[b]
        wide = (n > WIDE) & (m > WIDE)
        bits = np.where(wide, np.bitwise_count(d1).astype(np.int64) + np.bitwise_count(d0 ^ d1), np.bitwise_count(d0))
        return np.where(may & (bits <= n + m - 2 * need), bits, -1)

    def other(self, a, b):
        """Whether these are different lines."""
        return (self.doc[a] != self.doc[b]) | (self.mark[a] != self.mark[b]) | (self.line[a] != self.line[b])

    def later_first(self, a, b):
        """Pairs (later, earlier) of different lines."""
        same = self.doc[a] == self.doc[b]
        before = (self.mark[a] < self.mark[b]) | ((self.mark[a] == self.mark[b]) & (self.line[a] < self.line[b]))
        swap = (self.doc[a] < self.doc[b]) | (same & before)
        x, y = np.where(swap, b, a), np.where(swap, a, b)
        return x, y, self.other(x, y)

    def near(self, ids: np.ndarray):
        """All pairs among rows ``ids`` (sorted as the table is) that pass the filters, by growing distance in the order:
        sizes grow within a token, so a row is done once its neighbour is too long."""
        found = [(np.zeros(0, np.int64),) * 3]
        lag, a = 1, np.arange(len(ids))
        while True:
            a = a[a + lag < len(ids)]
            x, y = ids[a], ids[np.minimum(a + lag, len(ids) - 1)]
            alive = (self.token[x] == self.token[y]) & (self.n[x] >= self.threshold * self.n[y] - 1e-9)
            a, x, y = a[alive], x[alive], y[alive]
            if not len(a):
                break
            bits = self.apart(x, y)
            x, y, other = self.later_first(x, y)
            good = (bits >= 0) & other
            found.append((x[good], y[good], bits[good]))
            lag += 1
        return tuple(np.concatenate(c) for c in zip(*found, strict=True))

    def led(self, ids: np.ndarray):
        """Pairs of a large group: a row near an earlier leader meets that one alone and is marked as having met not all;
        a row without one meets the earlier followers too and becomes a leader."""
        ids = ids[np.lexsort([self.line[ids], self.mark[ids], self.doc[ids]])]
        leaders, followers = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
        nl = nf = 0
        found, partly = [(np.zeros(0, np.int64),) * 3], []
        for x in ids.tolist():
            lead = leaders[:nl]
            bits = self.apart(np.full(nl, x), lead)
            best = np.flatnonzero(bits >= 0)
            if len(best):
                best = best[np.argmin(bits[best])]
                found.append((np.array([x]), lead[best : best + 1], bits[best : best + 1]))
                partly.append(x)
                followers[nf] = x
                nf += 1
            else:
                back = followers[:nf]
                bits = self.apart(np.full(nf, x), back)
                good = bits >= 0
                found.append((np.full(int(good.sum()), x), back[good], bits[good]))
                leaders[nl] = x
                nl += 1
        x, y, bits = (np.concatenate(c) for c in zip(*found, strict=True))
        other = self.other(x, y)
        return x[other], y[other], bits[other], np.array(partly, np.int64)

    def rows(self) -> pa.RecordBatch:
        """GONE: copies within a run of texts; PAIR: of each posting its two nearest earlier partners, and of sets with
        equal hashes the first; GROUPED: whole groups in which some posting, marked, has not met all its partners."""
        gone, at = np.flatnonzero(self.ni == COPY), np.flatnonzero(self.ni == WHOLE)
        order = at[np.lexsort([self.line[at], self.mark[at], self.doc[at], self.token[at]])]
        # A repeated row of one document is the same line, not a copy of it.
        opens = np.flatnonzero(np.concatenate([[True], self.token[order[1:]] != self.token[order[:-1]]])) if len(order) else np.zeros(0, np.int64)
        lead = np.repeat(order[opens], np.diff(np.append(opens, len(order))))
        again = self.other(order, lead)
        equal, equal_to = order[again], lead[again]
        ids = np.flatnonzero(self.ni >= 0)
        starts = np.flatnonzero(np.concatenate([[True], self.token[ids[1:]] != self.token[ids[:-1]]])) if len(ids) else np.zeros(0, np.int64)
        sizes = np.diff(np.append(starts, len(ids)))
        asking, parts = [ids[_groups(self.token[ids], self.crowd) > 1]], [(np.zeros(0, np.int64),) * 3]

        def keep(x, y, bits) -> None:
            order = np.lexsort([bits, x])
            x, y, bits = x[order], y[order], bits[order]
            begin = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])) if len(x) else np.zeros(0, np.int64)
            count = np.diff(np.append(begin, len(x)))
            asking.append(x[begin[count > 2]])
            kept = np.arange(len(x)) - np.repeat(begin, count) < 2
            parts.append((x[kept], y[kept], bits[kept]))

        meets = np.where((sizes > 1) & (sizes <= self.group), sizes * (sizes - 1) // 2, 0)
        step = np.repeat(np.where(meets > 0, np.cumsum(meets) // MEETS, -1), sizes)
        for k in np.unique(step[step >= 0]):
            keep(*self.near(ids[step == k]))
        for s, n in zip(starts[sizes > self.group].tolist(), sizes[sizes > self.group].tolist(), strict=True):
            *pairs, more = self.led(ids[s : s + n])
            keep(*pairs)
            asking.append(more)
        x, y, bits = (np.concatenate(c) for c in zip(*parts, strict=True))
        x, y, bits = np.concatenate([equal, x]), np.concatenate([equal_to, y]), np.concatenate([np.full(len(equal), EQUAL), bits])
        asks = np.zeros(len(self.token), bool)
        asks[np.concatenate(asking)] = True
        handed = ids[np.isin(self.token[ids], np.unique(self.token[asks]))]
        kinds = [(GONE, gone), (PAIR, x), (GROUPED, handed)]
        sizes = [len(rows) for _, rows in kinds]
        at = np.concatenate([gone, x, handed])
        pair = np.repeat([kind == PAIR for kind, _ in kinds], sizes)
        group = np.repeat([kind == GROUPED for kind, _ in kinds], sizes)
        to = at.copy()
        to[pair] = y
        apart = np.zeros(len(at), np.int32)
        apart[pair] = bits
        of_group = [pa.array(c, pa.int64(), mask=~group) for c in (self.token[at] >> SALT << SALT, self.ni[at], self.s0.view(np.int64)[at], self.s1.view(np.int64)[at])]
        return pa.RecordBatch.from_arrays(
            [
                pa.array(np.repeat(np.array([GONE, PAIR, GROUPED], np.int32), sizes)),
                pa.array(self.doc[at]),
                pa.array(self.mark[at]),
                pa.array(self.line[at].astype(np.int32)),
                pa.array(self.doc[to], mask=~pair),
                pa.array(self.mark[to], mask=~pair),
                pa.array(self.line[to].astype(np.int32), mask=~pair),
                pa.array(apart),
                pa.array(group & asks[at]),
                *of_group,
            ],
            names=["kind", "doc", "mark", "line", "ydoc", "ymark", "yline", "apart", "asks", "token", "ni", "s0", "s1"],
        )


def _meet(dealt: DataFrame, threshold: float, crowd: int = CROWD, group: int = GROUP, spare: bool = True) -> DataFrame:
    """The meetings of packed postings that lie sorted by part; a task holds one part at a time, and of it some hundred
    thousand rows and the largest group in a step."""

    def met(rows: list) -> Iterator[pa.RecordBatch]:
        columns, at = _company(_unpacked(rows), crowd), 0
        size = len(columns[0])
        while at < size:
            end = size
            if size - at > 2 * GATHER:  # up to the end of a token
                end = int(np.searchsorted(columns[0], columns[0][at + GATHER], "right"))
            yield _Meetings([c[at:end] for c in columns], threshold, crowd, group, spare).rows()
            at = end

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, held = None, []
        for batch in batches:
            for k, rows in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if k != part and held:
                    yield from met(held)
                    held = []
                part = k
                held.append(rows.as_buffer())
        if held:
            yield from met(held)
        trim()

    return dealt.mapInArrow(run, MEETING)


def _may_meet(threshold: float):
    """The length, positional and parity filters on x (ni, s0, s1) and y (yni, ys0, ys1)."""
    n, m = F.shiftright("ni", 32), F.shiftright("yni", 32)
    i, j = F.col("ni").bitwiseAND(0xFFFFFFFF), F.col("yni").bitwiseAND(0xFFFFFFFF)
    need = F.ceil(F.lit(threshold / (1 + threshold)) * (n + m) - 1e-9)
    d0, d1 = F.col("s0").bitwiseXOR(F.col("ys0")), F.col("s1").bitwiseXOR(F.col("ys1"))
    bits = F.when((n > WIDE) & (m > WIDE), F.bit_count(d1) + F.bit_count(d0.bitwiseXOR(d1))).otherwise(F.bit_count(d0))
    return (F.least(n, m) >= threshold * F.greatest(n, m) - 1e-9) & (F.least(n - i, m - j) >= need) & (bits <= n + m - 2 * need)


def _fetched(pairs: DataFrame, docs: DataFrame, few: bool) -> Written:
    """(doc, mark, line, ydoc, ymark, yline, apart, words): each pair with the later line's words, and the earlier lines with theirs, once
    each, where ydoc is null. With ``few``, documents that are not asked are left out before the rest move, if the keys can be broadcast."""
    columns = (*KEY, *YOURS, "apart")
    earlier = pairs.select(F.col("ydoc").alias("doc"), F.col("ymark").alias("mark"), F.struct(F.col("yline").alias("line"), F.lit(0).cast("long").alias("ydoc"), F.lit(0).cast("long").alias("ymark"), F.lit(-1).alias("yline"), F.lit(0).alias("apart")).alias("ask"))
    asked = pairs.select("doc", "mark", F.struct("line", *YOURS, "apart").alias("ask")).union(earlier).groupBy("doc", "mark").agg(F.collect_list("ask").alias("asks"))
    def fetch(batch):
        asks = batch.column(3)
        ask = asks.flatten()
        row = np.repeat(np.arange(len(asks)), pc.list_value_length(asks).to_numpy(zero_copy_only=False).astype(np.int64))
        line, ydoc, ymark, yline, apart = (c.to_numpy() for c in ask.flatten())
        # An earlier line may be asked for by many.
        order = np.lexsort([ymark, ydoc, yline, line, row])
        same = np.concatenate([[False], (row[order[1:]] == row[order[:-1]]) & (line[order[1:]] == line[order[:-1]]) & (yline[order[1:]] < 0) & (yline[order[:-1]] < 0)])
        order = order[~same]
        row, line, ydoc, ymark, yline, apart = (c[order] for c in (row, line, ydoc, ymark, yline, apart))
        words, every, at = [], [], -1
        texts = _bytes(batch)
        for i, k in zip(row.tolist(), line.tolist(), strict=True):
            if i != at:
                every, at = texts[i].split(b"\n"), i
            words.append(every[k].lower() if k < len(every) else None)
        none = yline < 0
        found = pa.RecordBatch.from_arrays(
            [
                batch.column(0).take(pa.array(row)),
                batch.column(1).take(pa.array(row)),
                pa.array(line, pa.int32()),
                *(pa.array(c, t, mask=none) for c, t in ((ydoc, pa.int64()), (ymark, pa.int64()), (yline, pa.int32()), (apart, pa.int32()))),
                pa.array(words, pa.binary()),
            ],
            names=[*columns, "words"],
        )
        yield found.filter(found.column(7).is_valid())

    if few and asked.select("doc", "mark").limit(CLASHING + 1).count() <= CLASHING:
        docs = docs.join(F.broadcast(asked.select("doc", "mark")), ["doc", "mark"], "left_semi")
    asks = docs.join(asked.hint("shuffle_hash"), ["doc", "mark"]).select("doc", "mark", "text", "asks")
    with lists_hashed(docs.sparkSession):
        return Written(map_batches(asks, fetch, "doc long, mark long, line int, ydoc long, ymark long, yline int, apart int, words binary"), "lines-words")


def _verified(pairs: DataFrame, docs: DataFrame, threshold: float, few: bool = False) -> Written:
    """(doc, mark, line, proven): the later lines of the pairs (doc, mark, line, ydoc, ymark, yline, apart) whose words prove the similarity;
    not proven are those whose words disprove an equality of hashes."""
    words = _fetched(pairs, docs, few)
    y = words.frame.where("ydoc IS NULL").select(F.col("doc").alias("ydoc"), F.col("mark").alias("ymark"), F.col("line").alias("yline"), F.col("words").alias("ywords"))
    both = words.frame.where("ydoc IS NOT NULL").join(y, YOURS).select(*KEY, "apart", "words", "ywords")

    def check(batch):
        good = []
        for a, b in zip(batch.column(4).to_pylist(), batch.column(5).to_pylist(), strict=True):
            if a == b:
                good.append(True)
                continue
            s, t = set(a.split()), set(b.split())
            common = len(s & t)
            good.append(common >= threshold * (len(s) + len(t) - common) - 1e-9)
        good = pa.array(good, pa.bool_())
        found = pa.RecordBatch.from_arrays([*batch.columns[:3], good], names=[*KEY, "proven"])
        yield found.filter(pc.or_(good, pc.equal(batch.column(3), EQUAL)))

    out = Written(map_batches(both, check, "doc long, mark long, line int, proven boolean"), "lines-removed")
    words.drop()
    return out


def removed_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, crowd: int = CROWD, group: int = GROUP, bits: int = 64) -> DataFrame:
    """(doc, mark, line) of every line that has an earlier similar one; doc and mark as in ``_keyed``. Sets are told by hashes of some bits."""
    own = _keyed(docs.select(id_col, text_col), id_col, text_col).select("doc", "mark", F.col(text_col).alias("text"))
    codes = _rarity(own.select("text"))
    found = _removed(own, codes, threshold, crowd, group, bits, spare=True)
    if found is None:
        found = _removed(own, codes, threshold, crowd, group, bits, spare=False)
    return found.frame


def _removed(own: DataFrame, codes: np.ndarray, threshold: float, crowd: int, group: int, bits: int, spare: bool) -> Written | None:
    """The lines that go; none where sets were spared meetings by equal hashes and their words then differ."""
    met = Written(_meet(_postings(own, codes, threshold, crowd, bits).repartition("part").sortWithinPartitions("part"), threshold, crowd, group, spare), "lines-met")
    ends = [*KEY, *YOURS]
    proposed = met.frame.where(F.col("kind") == PAIR).select(*ends, "apart")
    nearest = F.row_number().over(Window.partitionBy(*KEY).orderBy("apart", *YOURS)) <= NEAREST
    pairs = Written(proposed.repartition(*KEY).groupBy(*ends).agg(F.min("apart").alias("apart")).withColumn("nearest", nearest), "lines-pairs")
    first = _verified(pairs.frame.where("nearest").drop("nearest"), own, threshold)
    tables = [met, pairs, first]
    out = None
    if not spare or first.frame.where("NOT proven").isEmpty():
        gone = first.frame.where("proven").select(*KEY)
        rest = pairs.frame.where("NOT nearest").select(*ends).join(gone, KEY, "left_anti")
        grouped = met.frame.where(F.col("kind") == GROUPED).select("token", *KEY, "ni", "s0", "s1", "asks")
        asking = grouped.where("asks").drop("asks").join(gone, KEY, "left_anti")
        same_doc, same_mark = F.col("doc") == F.col("ydoc"), F.col("mark") == F.col("ymark")
        later = (F.col("doc") > F.col("ydoc")) | (same_doc & ((F.col("mark") > F.col("ymark")) | (same_mark & (F.col("line") > F.col("yline")))))
        others = grouped.select("token", *(F.col(c).alias(f"y{c}") for c in (*KEY, "ni", "s0", "s1")))
        left = Written(asking.join(others, "token").where(_may_meet(threshold) & later).select(*ends).union(rest).distinct().withColumn("apart", F.lit(0)), "lines-pairs")
        last = _verified(left.frame, own, threshold, few=True)
        again = met.frame.where(F.col("kind") == GONE).select(*KEY)
        out = Written(again.union(gone).union(last.frame.select(*KEY)).distinct(), "lines-removed")
        tables += [left, last]
    for table in tables:
        table.drop()
    return out


def digest(docs: DataFrame, removed: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: doc_id, n_lines, n_removed and the sorted numbers of the removed lines."""
    gone = removed.groupBy("doc", "mark").agg(F.sort_array(F.collect_list("line")).alias("removed"))
    size = F.when(F.octet_length(text_col) > 0, F.size(F.split(text_col, "\n"))).otherwise(0)
    counted = _keyed(docs.select(id_col, text_col), id_col, text_col).select(F.col(id_col).alias("doc_id"), "doc", "mark", size.cast("long").alias("n_lines"))
    return counted.join(gone, ["doc", "mark"], "left").select("doc_id", "n_lines", F.coalesce(F.size("removed"), F.lit(0)).cast("long").alias("n_removed"), F.coalesce(F.array_join("removed", ","), F.lit("")).alias("removed"))


def rewrite(docs: DataFrame, removed: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents without their removed lines, all columns kept in their order."""
    gone = removed.groupBy(F.col("doc").alias("__doc"), F.col("mark").alias("__mark")).agg(F.collect_list("line").alias("__gone"))
    keys = _keyed(docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text"), F.struct(*docs.columns).alias("__row")), "__id", "__text").withColumnsRenamed({"doc": "__doc", "mark": "__mark"})
    joined = keys.join(gone.hint("shuffle_hash"), ["__doc", "__mark"], "left").select("__row.*", "__gone")
    left = F.array_join(F.filter(F.split(text_col, "\n"), lambda _, k: ~F.array_contains("__gone", k)), "\n")
    return joined.withColumn(text_col, F.when(F.col("__gone").isNull(), F.col(text_col)).otherwise(left)).select(*docs.columns)
