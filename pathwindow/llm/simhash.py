"""SimHash near-duplicates through vantage-point trees.

Fingerprints that differ in at most r of 64 bits differ in at most r // 2 bits of one of their halves (or r // 4 of a
quarter, for larger r), and the Hamming distance of a part is a metric too. So each part gets a vantage-point tree,
fitted on a bounded sample of distinct fingerprints: an inner node sends a fingerprint to the near side if it lies within the node's radius of the vantage
point; by the triangle inequality a search may skip the side whose boundary is farther than that. Every fingerprint
is stored in its home leaf and searches each leaf that its ball overlaps; leaves are the shards of a groupBy, and each is
searched exactly by a finer tree of its own. A shard returns a spanning forest of its links, never all pairs.

Defined results: null, empty and blank texts have fingerprint zero and link like any other; equal texts share one
fingerprint and are handled as one; repeated rows each get their row; a null id is kept but never leads a component; an
empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, texts, written
from .components import components
from .shards import TASK, deal

SHINGLE, SEED, RADIUS = 3, 42, 3
# The sample that vantage points are fitted on, and the fingerprints that a shard should be home to.
SAMPLE, SHARD, MAX_DEPTH = 65_536, 1_024, 14
LEAF = 96
BLOCK = 1 << 15


def shingle_hashes(text: str, size: int = SHINGLE) -> np.ndarray:
    """XXH64 of each run of words, of lower-cased (A-Z) text cut at ASCII white space."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    if len(words) <= size:
        return np.array([xxhash.xxh64_intdigest(line, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate([[0], ends[:-size]]).tolist()
    stops = (ends[size - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    return np.array([digest(line[a:b], SEED) for a, b in zip(starts, stops, strict=True)], np.uint64)


def fingerprint(hashes: np.ndarray) -> int:
    """Bits set in over half of the hashes."""
    n = len(hashes)
    if not n:
        return 0
    ones = np.zeros(64, np.int64)
    for lo in range(0, n, BLOCK):
        part = np.ascontiguousarray(hashes[lo : lo + BLOCK]).view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp, n): the fingerprint as a signed 64-bit number, and its number of shingles."""

    def each(batch):
        hashes = [shingle_hashes(t, shingle) for t in texts(batch)]
        own = np.array([fingerprint(h) for h in hashes], np.uint64)
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(own.view(np.int64)), pa.array([len(h) for h in hashes], pa.int32())], names=["doc_id", "fp", "n"])

    return map_batches(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), each, "doc_id long, fp long, n int")


def parts_for(radius: int) -> int:
    """Into how many parts fingerprints are cut, so that one part of a linked pair differs in a bit at most."""
    return 2 if radius <= 3 else 4


def _part(fps: np.ndarray, side: int, parts: int) -> np.ndarray:
    width = 64 // parts
    return (fps >> np.uint64(width * side)) & np.uint64((1 << width) - 1)


class Tree:
    """A complete vantage-point tree over one metric; node i has the near child 2i+1 and the far child 2i+2."""

    def __init__(self, sample: np.ndarray, depth: int, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.depth = depth
        inner = (1 << depth) - 1
        self.vantage, self.within = np.zeros(inner, np.uint64), np.zeros(inner, np.int16)
        held = {0: sample}
        for node in range(inner):
            own = held.pop(node, sample[:0])
            if len(own):
                # of a few candidates the vantage point that spreads the sample most
                picks = own[rng.integers(0, len(own), min(8, len(own)))]
                spreads = [np.bitwise_count(own ^ p) for p in picks]
                best = int(np.argmax([s.std() for s in spreads]))
                far = spreads[best]
                self.vantage[node], self.within[node] = picks[best], int(np.median(far))
                near = far <= self.within[node]
                if node < inner // 2:
                    held[2 * node + 1], held[2 * node + 2] = own[near], own[~near]

    def home(self, values: np.ndarray) -> np.ndarray:
        node = np.zeros(len(values), np.int64)
        for _ in range(self.depth):
            node = 2 * node + 1 + (np.bitwise_count(values ^ self.vantage[node]) > self.within[node])
        return node - ((1 << self.depth) - 1)

    def search(self, values: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf) for every leaf that a ball of the given reach around a row's value overlaps."""
        row, node = np.arange(len(values)), np.zeros(len(values), np.int64)
        for _ in range(self.depth):
            far = np.bitwise_count(values[row] ^ self.vantage[node]).astype(np.int16)
            near, out = far - reach <= self.within[node], far + reach > self.within[node]
            row, node = np.concatenate([row[near], row[out]]), np.concatenate([2 * node[near] + 1, 2 * node[out] + 2])
        return row, node - ((1 << self.depth) - 1)


def _roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least reachable index of each of n nodes, for links (a, b)."""
    root = np.arange(n)
    while len(a):
        low = np.minimum(root[a], root[b])
        np.minimum.at(root, root[a], low)
        np.minimum.at(root, root[b], low)
        while True:
            up = root[root]
            if (up == root).all():
                break
            root = up
        open_ = root[a] != root[b]
        a, b = a[open_], b[open_]
    return root


def _links(fps: np.ndarray, sizes: np.ndarray, stored: np.ndarray, asking: np.ndarray, reach: int, ratio: float) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest (i, root) of the links at full distance between one shard's own fingerprints and its visitors.

    A tree over the shard's own ones is walked down with all that its balls reach; small leaves are compared at once.
    """
    every = np.arange(len(fps))
    root = every.copy()

    def leaf(own: np.ndarray, ask: np.ndarray) -> None:
        nonlocal root
        for lo in range(0, len(ask), 512):
            part = ask[lo : lo + 512]
            i, j = np.nonzero(np.bitwise_count(fps[part][:, None] ^ fps[own][None, :]) <= reach)
            a, b = part[i], own[j]
            new = (root[a] != root[b]) & (np.minimum(sizes[a], sizes[b]) >= ratio * np.maximum(sizes[a], sizes[b]))
            if new.any():
                root = _roots(len(fps), np.concatenate([a[new], every]), np.concatenate([b[new], root]))

    def walk(own: np.ndarray, ask: np.ndarray, level: int) -> None:
        if len(own) * len(ask) <= LEAF * LEAF * 64 or level > 24:
            leaf(own, ask)
            return
        point = fps[own[len(own) // 2]]
        far, asked = np.bitwise_count(fps[own] ^ point).astype(np.int16), np.bitwise_count(fps[ask] ^ point).astype(np.int16)
        within = min(int(np.median(far)), int(far.max()) - 1)
        near = far <= within
        walk(own[near], ask[asked - reach <= within], level + 1)
        walk(own[~near], ask[asked + reach > within], level + 1)

    if stored.any():
        walk(every[stored], every[asking], 0)
    linked = root != every
    return every[linked], root[linked]


def link_fingerprints(distinct: DataFrame, radius: int = RADIUS, ratio: float = 0.0, sample: int = SAMPLE, shard: int = SHARD) -> DataFrame:
    """Links (u, v) whose components are those of all pairs of (fp, n, node) rows within the radius.

    ``ratio``: the least ratio of shingle numbers in a link. A bounded hash-picked sample comes to the driver to fit the
    trees; all fingerprints are searched.
    """
    spark = distinct.sparkSession
    total = distinct.count()
    if total < 2:
        return spark.createDataFrame([], "u long, v long")
    picked = distinct.where(F.pmod(F.xxhash64("fp"), F.lit(1 << 20)) < max(1, int((1 << 20) * min(1.0, sample / total)))).select("fp")
    values = np.sort(np.array([r["fp"] for r in picked.collect()], np.int64)).view(np.uint64)
    depth = int(min(MAX_DEPTH, max(0, np.ceil(np.log2(total / shard)))))
    parts = parts_for(radius)
    trees = [Tree(_part(values, side, parts), depth) for side in range(parts)]
    shared = spark.sparkContext.broadcast(trees)
    reach = radius // parts

    def spread(batch):
        fps = batch.column(0).to_numpy().view(np.uint64)
        for side, tree in enumerate(shared.value):
            own = _part(fps, side, parts)
            row, leaf = tree.search(own, reach)
            take = pa.array(row)
            yield pa.RecordBatch.from_arrays(
                [*(c.take(take) for c in batch.columns), pa.array((leaf * parts + side).astype(np.int32)), pa.array(tree.home(own)[row] == leaf)], names=["fp", "n", "node", "shard", "home"]
            )

    def search(table: pa.Table) -> pa.Table:
        fps, sizes, node, stored, asking = (table.column(c).to_numpy() for c in ("fp", "n", "node", "stored", "asking"))
        i, j = _links(fps.view(np.uint64), sizes, stored, asking, radius, ratio)
        return pa.table({"u": pa.array(node[i], pa.int64()), "v": pa.array(node[j], pa.int64())})

    spread_out = map_batches(distinct.select("fp", "n", "node"), spread, "fp long, n int, node long, shard int, home boolean")
    return deal(spread_out).groupBy(*TASK).applyInArrow(search, "u long, v long")


def group(prints: DataFrame, radius: int = RADIUS, ratio: float = 0.0) -> DataFrame:
    """(doc_id, fp) rows with their component_id, the least doc_id that links reach."""
    prints = prints if ratio else prints.withColumn("n", F.lit(0))
    distinct = written(prints.groupBy("fp", "n").agg(F.min("doc_id").alias("node")).where("node is not null"), "simhash-distinct")
    found = components(link_fingerprints(distinct, radius, ratio))
    of = distinct.join(found, "node", "left").select("fp", "n", F.coalesce("component", "node").alias("component_id"))
    return prints.join(of, ["fp", "n"], "left").select("doc_id", "fp", F.coalesce("component_id", "doc_id").alias("component_id"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, radius: int = RADIUS, ratio: float = 0.0) -> DataFrame:
    """One row a document: doc_id, fp and component_id. Texts are read once; only fingerprints are shuffled."""
    return group(written(fingerprints(docs, id_col, text_col, shingle), "simhash-prints"), radius, ratio)


def digest(grouped: DataFrame) -> DataFrame:
    """The contract's columns from the operator's own output."""
    return grouped.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
