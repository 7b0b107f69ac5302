"""Embedding near-duplicates by lattice hashing.

Each table projects unit vectors at random to eight dimensions, scales them and decodes them to the nearest point of
the E8 lattice: the cell that a vector is stored in. A search looks into its own cell and those neighbouring cells (of
the 240 nearest lattice points) that lie most in the direction of the vector's offset. Cells are gathered by a coarser
decoding of their points into shards, and shards into tasks of some thousand vectors, so that one copy of a vector
serves most of its probes. A pair is verified by its
cosine in double precision, and counted by the first table (and direction) that meets it; shards return sums and a
spanning forest of links, never all pairs. Equal vectors are handled as one with a count.

Defined results: vectors only compare when labels are equal and not null; null, zero or empty vectors and those that
hold null or non-finite components link with nothing; vectors of different lengths don't link; repeated rows are
vectors of their own; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, written
from .components import components
from .shards import TASK, deal
from .simhash import _roots

COSINE = 0.93
TABLES, PROBES, SCALE, COARSE = 5, 60, 5.0, 4.0
PAIRS = 100_000
TASK_ROWS = 4_000


def _minimal() -> np.ndarray:
    """The 240 shortest lattice vectors: two entries of one, or eight halves with an even number of minus signs."""
    found = []
    for i in range(8):
        for j in range(i):
            for a in (-1, 1):
                for b in (-1, 1):
                    v = np.zeros(8)
                    v[i], v[j] = a, b
                    found.append(v)
    for bits in range(256):
        signs = np.array([-0.5 if bits >> k & 1 else 0.5 for k in range(8)])
        if (signs < 0).sum() % 2 == 0:
            found.append(signs)
    return np.array(found)


NEAREST = _minimal()


def _even(y: np.ndarray) -> np.ndarray:
    """Nearest integer points with an even sum."""
    f = np.rint(y)
    off = y - f
    odd = (f.sum(axis=1).astype(np.int64) & 1) == 1
    at = np.abs(off).argmax(axis=1)
    rows = np.flatnonzero(odd)
    f[rows, at[rows]] += np.where(off[rows, at[rows]] >= 0, 1.0, -1.0)
    return f


def decode(y: np.ndarray) -> np.ndarray:
    """Nearest E8 point of each row."""
    whole, half = _even(y), _even(y - 0.5) + 0.5
    nearer = ((y - half) ** 2).sum(axis=1) < ((y - whole) ** 2).sum(axis=1)
    return np.where(nearer[:, None], half, whole)


def _keys(points: np.ndarray, salt: np.ndarray) -> np.ndarray:
    """A 64-bit hash of lattice points (last axis) and a salt."""
    doubled = np.rint(2 * points).astype(np.int64).astype(np.uint64)
    h = np.broadcast_to(salt, points.shape[:-1]).astype(np.uint64)
    for k in range(8):
        h = (h ^ doubled[..., k]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    return h


def _projection(table: int, size: int) -> np.ndarray:
    rng = np.random.default_rng(1000 * size + table)
    return np.linalg.qr(rng.normal(size=(size, 8)))[0] if size >= 8 else np.pad(np.eye(size), ((0, 0), (0, 8 - size)))


class Cells:
    """Home cell and probed cells of unit vectors in one table, with the shards of both."""

    def __init__(self, unit: np.ndarray, salt: np.ndarray, table: int, scale: float, probes: int):
        size = unit.shape[1]
        y = unit @ _projection(table, size) * (scale * np.sqrt(size / 64))
        point = decode(y)
        near = np.argpartition(-((y - point) @ NEAREST.T), probes - 1, axis=1)[:, :probes]
        asked = np.concatenate([point[:, None, :], point[:, None, :] + NEAREST[near]], axis=1)
        salt = salt.view(np.uint64) ^ np.uint64(table + 1)
        self.home = _keys(point, salt)
        self.asked = _keys(asked, salt[:, None])
        self.shard = self._shard(point, salt)
        self.asked_shard = self._shard(asked.reshape(-1, 8), np.repeat(salt, probes + 1)).reshape(len(unit), probes + 1)

    @staticmethod
    def _shard(points: np.ndarray, salt: np.ndarray) -> np.ndarray:
        # a fixed offset keeps lattice points off the coarse cells' borders
        return _keys(decode(points / COARSE + 0.0712), salt ^ np.uint64(0x5BD1E995))


def _vectors(column) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1)


def _unit(v: np.ndarray) -> np.ndarray:
    return v / np.sqrt((v * v).sum(axis=1, keepdims=True))


def link_vectors(distinct: DataFrame, cosine: float = COSINE, tables: int = TABLES, probes: int = PROBES, scale: float = SCALE) -> DataFrame:
    """(u, v, n): rows u = v carry a number of linked vectors of u to add; others are links whose components count.

    ``distinct``: (node, copies, kind, size, embedding), all different; ``kind`` is what must be equal.
    """

    groups = np.uint64(max(1, -(-distinct.count() // TASK_ROWS)))

    def spread(batch):
        sizes = np.array(batch.column(batch.schema.get_field_index("size")).to_numpy())
        for size in np.unique(sizes):
            part = batch.filter(pa.array(sizes == size))
            node, copies, kind, _, vectors = part.columns
            unit, salt = _unit(_vectors(vectors)), kind.to_numpy()
            for table in range(tables):
                cells = Cells(unit, salt, table, scale, probes)
                shards = np.sort(cells.asked_shard % groups, axis=1)
                fresh = np.concatenate([np.ones((len(unit), 1), bool), shards[:, 1:] != shards[:, :-1]], axis=1)
                row, at = np.nonzero(fresh)
                shard = shards[row, at]
                take = pa.array(row)
                yield pa.RecordBatch.from_arrays(
                    [pa.array((shard * np.uint64(tables) + np.uint64(table)).view(np.int64)), pa.array(np.full(len(row), table, np.int32)), node.take(take), copies.take(take), kind.take(take), pa.array(cells.shard[row] % groups == shard), vectors.take(take)],
                    names=["shard", "turn", "node", "copies", "kind", "home", "embedding"],
                )

    def search(data: pa.Table) -> pa.Table:
        u, v, n = [], [], []
        lengths = np.diff(data.column("embedding").combine_chunks().offsets.to_numpy())
        turns = data.column("turn").to_numpy()
        for size, turn in {*zip(lengths.tolist(), turns.tolist(), strict=True)}:
            part = data.filter(pa.array((lengths == size) & (turns == turn)))
            for out, more in zip((u, v, n), _search(part, turn, cosine, scale, probes), strict=True):
                out.append(more)
        join = lambda parts: pa.array(np.concatenate(parts) if parts else [], pa.int64())
        return pa.table({"u": join(u), "v": join(v), "n": join(n)})

    out = map_batches(distinct.select("node", "copies", "kind", "size", "embedding"), spread, "shard long, turn int, node long, copies long, kind long, home boolean, embedding array<float>")
    return deal(out).groupBy(*TASK).applyInArrow(search, "u long, v long, n long")


def _search(part: pa.Table, turn: int, cosine: float, scale: float, probes: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    node, copies, kind = (part.column(c).to_numpy() for c in ("node", "copies", "kind"))
    stored, asking = part.column("stored").to_numpy(), part.column("asking").to_numpy()
    vectors = _vectors(part.column("embedding"))
    unit = _unit(vectors)
    cells = [Cells(unit, kind, t, scale, probes) for t in range(turn + 1)]
    own = np.flatnonzero(stored)
    own = own[np.argsort(cells[turn].home[own], kind="stable")]
    homes = cells[turn].home[own]
    add, root = np.zeros(len(node), np.int64), np.arange(len(node))
    every = root.copy()
    ask = np.flatnonzero(asking)
    lo, hi = (np.searchsorted(homes, cells[turn].asked[ask], side) for side in ("left", "right"))
    row, _ = np.nonzero(hi > lo)
    begin, width = lo[hi > lo], (hi - lo)[hi > lo]
    ends = np.cumsum(width)
    step = 0
    while step < len(width):
        stop = max(step + 1, int(np.searchsorted(ends, (ends[step - 1] if step else 0) + PAIRS, "right")))
        inner = width[step:stop]
        x = np.repeat(ask[row[step:stop]], inner)
        y = own[np.repeat(begin[step:stop] - (ends[step:stop] - inner - (ends[step - 1] if step else 0)), inner) + np.arange(inner.sum())]
        step = stop
        good = (node[x] != node[y]) & (kind[x] == kind[y])
        x, y = x[good], y[good]
        good = (unit[x] * unit[y]).sum(axis=1) >= cosine - 1e-12
        x, y = x[good], y[good]
        # exactly as stated: the product over the norms, in double precision
        good = (vectors[x] * vectors[y]).sum(axis=1) / (np.sqrt((vectors[x] ** 2).sum(axis=1)) * np.sqrt((vectors[y] ** 2).sum(axis=1))) >= cosine
        x, y = x[good], y[good]
        meets = lambda c, a, b: (c.asked[a] == c.home[b][:, None]).any(axis=1)
        fresh = (node[x] < node[y]) | ~meets(cells[turn], y, x)
        for c in cells[:turn]:
            x, y, fresh = x[fresh], y[fresh], fresh[fresh]
            fresh &= ~meets(c, x, y) & ~meets(c, y, x)
        x, y = x[fresh], y[fresh]
        if len(x):
            add += np.bincount(x, weights=copies[y], minlength=len(node)).astype(np.int64) + np.bincount(y, weights=copies[x], minlength=len(node)).astype(np.int64)
            root = _roots(len(node), np.concatenate([x, every]), np.concatenate([y, root]))
    some, linked = np.flatnonzero(add), np.flatnonzero(root != every)
    return np.concatenate([node[some], node[linked]]), np.concatenate([node[some], node[root[linked]]]), np.concatenate([add[some], np.zeros(len(linked), np.int64)])


def near_duplicates(table: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", cosine: float = COSINE) -> DataFrame:
    """One row a vector: vec_id, n_links, component_id, kept."""
    vector = F.col(vector_col)
    sound = F.col(label_col).isNotNull() & vector.isNotNull() & F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(vector, lambda x: x != 0)
    rows = table.select(F.col(id_col).alias("vec_id"), F.when(F.coalesce(sound, F.lit(False)), vector.cast("array<float>")).alias("embedding"), F.xxhash64(label_col).alias("kind"))
    rows = rows.withColumns({"h1": F.xxhash64("kind", "embedding"), "h2": F.xxhash64(F.lit(1), "embedding", "kind")})
    distinct = written(
        rows.where("embedding is not null").groupBy("h1", "h2").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies"), F.first("kind").alias("kind"), F.first("embedding").alias("embedding")).where("node is not null").withColumn("size", F.size("embedding")),
        "embeddings-distinct",
    )
    found = written(link_vectors(distinct, cosine), "embeddings-links")
    sums = found.where("u = v").groupBy(F.col("u").alias("node")).agg(F.sum("n").alias("others"))
    groups = components(found.where("u <> v").select("u", "v"))
    of = distinct.join(sums, "node", "left").join(groups, "node", "left").select("h1", "h2", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "node").alias("component_id"))
    out = rows.where("embedding is not null").select("vec_id", "h1", "h2").join(of, ["h1", "h2"]).select("vec_id", "n_links", "component_id")
    rest = rows.where("embedding is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.unionByName(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
