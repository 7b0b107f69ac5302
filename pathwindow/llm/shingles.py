"""Near-duplicates by the similarity of whole shingle sets.

A text is its set of shingles (runs of words, hashed). Each set has a SimHash fingerprint, and vantage-point trees over
the fingerprints (``simhash.link_fingerprints``) propose those within RADIUS bits; of sets with one fingerprint one goes
through the trees, and the others are proposed to it. Sets of a similarity down to 0.8 may lie farther apart, so that
minima of 80 mixings of the hashes, four to a band, propose too: they put similar
sets into common buckets: a pair of similarity 0.8 shares none of the 20 bands with a chance of (1 - 0.8^4)^20 = 3e-5,
a more similar one more rarely. Trees and buckets only propose; every link is proven on the sets themselves. First each set
meets its partners from the trees and one leader of each of its buckets (another one in each bucket), then all pairs of a
bucket that are still in different
components meet, so no proposed pair is left open and a group of near copies need not emit all its pairs.

Defined results: null, empty and blank texts have the same empty set and are copies of each other; texts of equal sets
are one node (a 64-bit hash of the set); repeated rows each get their row; a null id never gives a component its id
where another row of it has one; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Written, map_batches, texts
from .components import components
from .shards import TASK, deal
from .simhash import RADIUS, _roots, fingerprint, link_fingerprints, shingle_hashes

SHINGLE, THRESHOLD = 5, 0.8
BANDS, ROWS = 20, 4
BLOCK = 1 << 14
GRID = 256  # sets of a bucket that meet in one task; larger buckets become grids of blocks
COLUMNS = 4_096
_MIX = np.random.default_rng(11).integers(0, 1 << 64, (2, BANDS * ROWS, 1), dtype=np.uint64)
_MIX[1] |= np.uint64(1)
SETS = "doc_id long, mark long, row long, node long, n int, fp long, hashes binary, bands array<long>"


def set_of(text: str, size: int = SHINGLE) -> np.ndarray:
    """The sorted shingle hashes of a text, each once."""
    return np.unique(shingle_hashes(text, size))


def bands_of(own: np.ndarray) -> list[int]:
    """The buckets of a set, one a band."""
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max)
    for lo in range(0, len(own), BLOCK):
        least = np.minimum(least, ((own[lo : lo + BLOCK] ^ _MIX[0]) * _MIX[1]).min(axis=1))
    raw = least.tobytes()
    return [_signed(xxhash.xxh64_intdigest(raw[8 * ROWS * k : 8 * ROWS * (k + 1)], k)) for k in range(BANDS)]


def _signed(h: int) -> int:
    return h - ((h >> 63) << 64)


def similar(a: np.ndarray, b: np.ndarray, threshold: float = THRESHOLD) -> bool:
    common = len(np.intersect1d(a, b, assume_unique=True))
    return common >= threshold * (len(a) + len(b) - common) - 1e-9


def _hashed(docs: DataFrame, columns: list[str]):
    """A hash of a row's columns; nulls count too."""
    return F.xxhash64(*(x for c in columns for x in (F.col(c), F.col(c).isNull())))


def _sets(docs: DataFrame, id_col: str, text_col: str, shingle: int) -> DataFrame:
    def each(batch):
        own = [set_of(t, shingle) for t in texts(batch)]
        raw = [s.tobytes() for s in own]
        yield pa.RecordBatch.from_arrays(
            [
                batch.column(0).cast(pa.int64()), batch.column(2), batch.column(3),
                pa.array([_signed(xxhash.xxh64_intdigest(r)) for r in raw], pa.int64()), pa.array([len(s) for s in own], pa.int32()),
                pa.array([_signed(fingerprint(s)) for s in own], pa.int64()), pa.array(raw, pa.binary()), pa.array([bands_of(s) if len(s) else [] for s in own], pa.list_(pa.int64())),
            ],
            names=["doc_id", "mark", "row", "node", "n", "fp", "hashes", "bands"],
        )

    return map_batches(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), _hashed(docs, [text_col]).alias("mark"), _hashed(docs, docs.columns).alias("row")), each, SETS)


def _proven(pairs: DataFrame, held: DataFrame, threshold: float) -> DataFrame:
    """The pairs (u, v) whose sets are similar."""

    def check(batch):
        a, b = ([np.frombuffer(x, np.uint64) for x in batch.column(i).to_pylist()] for i in (2, 3))
        kept = batch.filter(pa.array([similar(x, y, threshold) for x, y in zip(a, b, strict=True)], pa.bool_()))
        yield pa.RecordBatch.from_arrays([kept.column(0), kept.column(1)], names=["u", "v"])

    of = lambda end, name: held.select(F.col("node").alias(end), F.col("hashes").alias(name))
    return map_batches(pairs.join(of("u", "a"), "u").join(of("v", "b"), "v").select("u", "v", "a", "b"), check, "u long, v long")


def _forest(table: pa.Table, threshold: float) -> pa.Table:
    """A spanning forest (u, v) of the similar pairs of a stored and an asking set of one block, all of them compared."""
    node, stored, asking = (table.column(c).to_numpy() for c in ("node", "stored", "asking"))
    own = [np.frombuffer(x, np.uint64) for x in table.column("hashes").to_pylist()]
    sizes = np.array([len(x) for x in own], np.int64)
    kinds, at, times = np.unique(np.concatenate(own), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(own)), sizes)
    several = times[at] > 1
    row, at = row[several], (np.cumsum(times > 1) - 1)[at[several]]
    order = np.argsort(at, kind="stable")
    row, at = row[order], at[order]
    common = np.zeros((len(own), len(own)), np.float32)
    for lo in range(0, int(at[-1]) + 1 if len(at) else 0, COLUMNS):
        a, b = np.searchsorted(at, [lo, lo + COLUMNS])
        holds = np.zeros((len(own), COLUMNS), np.float32)
        holds[row[a:b], at[a:b] - lo] = 1
        common += holds @ holds.T  # whole numbers far below 2^24 are exact
    alike = common >= threshold * (sizes[:, None] + sizes[None, :] - common.astype(np.float64)) - 1e-9
    i, j = np.nonzero(alike & stored[:, None] & asking[None, :])
    root = _roots(len(own), i, j)
    linked = root != np.arange(len(own))
    return pa.table({"u": pa.array(node[linked], pa.int64()), "v": pa.array(node[root[linked]], pa.int64())})


def _from_trees(nodes: DataFrame) -> DataFrame:
    """(u, v) of nodes (node, fp) whose fingerprints the trees find within the radius: a spanning forest of them, and of
    each fingerprint its least node with the others."""
    leads = Written(nodes.groupBy("fp").agg(F.min("node").alias("node")), "near-prints")
    same = nodes.join(leads.frame.withColumnRenamed("node", "u"), "fp").where("node <> u").select("u", F.col("node").alias("v"))
    found = Written(link_fingerprints(leads.frame.select("fp", F.lit(0).alias("n"), "node"), RADIUS).union(same).distinct(), "near-trees")
    leads.drop()
    return found.frame


def _links(sets: DataFrame, threshold: float) -> DataFrame:
    """(node, component) of the nodes that have a similar other one."""
    close = lambda n, m: F.least(n, m) >= threshold * F.greatest(n, m) - 1e-9
    pair = lambda x, y: (F.least(x, y).alias("u"), F.greatest(x, y).alias("v"))
    nodes = sets.groupBy("node").agg(F.first("n").alias("n"), F.first("bands").alias("bands"))
    sized = sets.where("n > 0").groupBy("node").agg(F.first("n").alias("n"), F.first("fp").alias("fp"))
    of = lambda end, name: sized.select(F.col("node").alias(end), F.col("n").alias(name))
    trees = _from_trees(sized.select("node", "fp")).join(of("u", "n"), "u").join(of("v", "m"), "v").where(close(F.col("n"), F.col("m"))).select(*pair(F.col("u"), F.col("v")))
    trees = Written(trees.distinct(), "near-trees")
    placed = Written(nodes.select("node", "n", F.explode("bands").alias("bucket")), "near-placed")
    shared = placed.frame.groupBy("bucket").agg(F.count("*").alias("k"), F.min_by(F.struct("node", "n"), F.xxhash64("node", "bucket")).alias("lead")).where("k > 1")
    met = Written(placed.frame.join(shared, "bucket").select("bucket", "node", "n", "lead"), "near-met")
    wanted = met.frame.select("node").union(trees.frame.select("u")).union(trees.frame.select("v"))
    held = Written(sets.join(wanted.distinct(), "node", "left_semi").groupBy("node").agg(F.first("hashes").alias("hashes")), "near-held")
    placed.drop()
    to_lead = met.frame.where((F.col("node") != F.col("lead.node")) & close(F.col("n"), F.col("lead.n")))
    first = Written(_proven(to_lead.select(*pair(F.col("node"), F.col("lead.node"))).union(trees.frame).distinct(), held.frame, threshold), "near-links")
    found = Written(components(first.frame), "near-components")
    here = met.frame.join(found.frame, "node", "left").select("bucket", "node", F.coalesce("component", "node").alias("c"))
    split = here.groupBy("bucket").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("bucket")
    left = Written(here.join(split, "bucket").select(F.col("bucket").alias("shard"), "node", F.lit(True).alias("home")), "near-left")
    dealt = deal(left.frame, GRID).join(held.frame, "node").select(*TASK, "node", "stored", "asking", "hashes")
    more = Written(dealt.groupBy(*TASK).applyInArrow(lambda table: _forest(table, threshold), "u long, v long").distinct(), "near-links")
    if more.frame.isEmpty():
        out = found.frame
    else:
        out = components(first.frame.union(more.frame))
    for table in (met, held, left, trees):
        table.drop()
    return out


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, threshold: float = THRESHOLD) -> DataFrame:
    """One row a document: doc_id, hashes of its text and of its whole row, node, and component_id, the least doc_id of
    all that links reach (null where none of them has one)."""
    sets = Written(_sets(docs, id_col, text_col, shingle), "near-sets").frame
    found = Written(_links(sets, threshold), "near-components").frame
    least = sets.groupBy("node").agg(F.min("doc_id").alias("least")).join(found, "node", "left").select("node", "least", F.coalesce("component", "node").alias("component"))
    named = least.join(least.groupBy("component").agg(F.min("least").alias("component_id")), "component").select("node", "component", "component_id")
    return sets.select("doc_id", "mark", "row", "node").join(named, "node")


def keep_first(docs: DataFrame, grouped: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component, all columns kept: the least id (null last), then the least hashes of text and row.

    An id alone drops nothing: different texts that share one, or have none, stay. Of rows equal in all columns one stays.
    """
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "mark", "row")
    leads = grouped.groupBy("component").agg(F.min(order).alias("l")).select(F.col("l.doc_id").alias("__id"), F.col("l.mark").alias("__mark"), F.col("l.row").alias("__row"))
    keyed = docs.withColumns({"__id1": F.col(id_col).cast("long"), "__mark1": _hashed(docs, [text_col]), "__row1": _hashed(docs, docs.columns)})
    met = F.col("__id1").eqNullSafe(F.col("__id")) & (F.col("__mark1") == F.col("__mark")) & (F.col("__row1") == F.col("__row"))
    return keyed.join(leads, met, "left_semi").dropDuplicates(["__id1", "__mark1", "__row1"]).select(*docs.columns)
