"""One relaxation round as one Spark job, and the state it works on.

State: (v, deg, dist, hops, parent, fresh), clustered by v; dist is null where nothing has arrived; ``fresh`` marks
lengths that have not been extended yet. A round joins the chosen rows with their adjacency chunks (co-located, no
exchange; a row of arrays for some hundred arcs, so that vertices left alone cost one row and none of their arcs),
unfolds only the arcs that the round asks for, takes the least candidate per target before and after the one exchange,
and merges it into the state (co-located again). Counters ride on the same job.

What a round does is told by bands of lengths and by limits, not by plans, so that the same schedules also run on
``local.LocalSearch``.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from .prepared import PreparedGraph, running_sums


@dataclass(frozen=True)
class Band:
    """Reached vertices with lo <= dist < hi (dist <= hi if closed), the fresh ones only if so told.

    ``counted``: which of them count as extended paths: all, fresh or none.
    """

    lo: float | None = None
    hi: float | None = None
    fresh: bool = False
    closed: bool = False
    counted: str = "all"

    def rows(self) -> Column:
        at = F.col("dist").isNotNull()
        if self.lo is not None:
            at &= F.col("dist") >= self.lo
        if self.hi is not None:
            at &= (F.col("dist") <= self.hi) if self.closed else (F.col("dist") < self.hi)
        return at & F.col("fresh") if self.fresh else at

    def counts(self) -> Column:
        return F.lit(False) if self.counted == "none" else self.rows() & F.col("fresh") if self.counted == "fresh" else self.rows()


FRESH = (Band(fresh=True),)
# Lengths of one bucket that may pass through the driver.
FEW = 10_000


@dataclass
class Counters:
    extended: int = 0
    relaxed: int = 0
    requested: int = 0
    rounds: int = 0
    windows: int = 0
    probes: int = 0  # passes over settled arcs that only look for the next window
    probed: int = 0  # arcs that they look at
    trace: list[tuple] = field(default_factory=list)

    def note(self, kind: str, note: tuple, extended: int, relaxed: int, improved: int) -> None:
        self.extended += extended
        self.relaxed += relaxed
        self.rounds += 1
        self.trace.append((self.windows, self.rounds, kind, *(None if x is None else float(x) for x in (note + (None, None, None))[:3]), extended, relaxed, improved))


@dataclass
class Round:
    improved: int
    fresh: int
    fresh_min: float | None
    top: float | None
    hub: float | None
    relaxed: int
    target: float | None = None


def _any(columns) -> Column:
    return reduce(lambda a, b: a | b, columns)


def _local_rounds(table: pa.Table, lo, hi, stop, upto, limit: int, skip_parent: bool, source: int, keep_leaves: bool):
    """The rounds of ``Search.fused`` within a partition: its rows after them, and candidates for vertices elsewhere."""
    rows = table.select(["v", "deg", "dist", "hops", "parent", "fresh"])
    v = rows.column("v").to_numpy()
    ids, first = np.unique(v, return_index=True)
    rows = rows.take(pa.array(first))
    whole = pa.types.is_integer(rows.schema.field("dist").type)
    none = np.iinfo(np.int64).max // 4 if whole else np.inf
    number = pa.int64() if whole else pa.float64()
    deg = rows.column("deg").to_numpy()
    dist = rows.column("dist").combine_chunks().cast(number).fill_null(none).to_numpy().copy()
    hops, parent = (rows.column(c).combine_chunks().cast(pa.int64()).fill_null(-1).to_numpy().copy() for c in ("hops", "parent"))
    fresh = rows.column("fresh").to_numpy().astype(bool)
    listed = table.column("dsts").combine_chunks()
    size = np.nan_to_num(pc.list_value_length(listed).to_numpy(zero_copy_only=False)).astype(np.int64)
    at = np.repeat(np.searchsorted(ids, v), size)
    dst, w = listed.flatten().to_numpy(), table.column("ws").combine_chunks().flatten().cast(number).to_numpy()
    if upto is not None:
        at, dst, w = at[w <= upto], dst[w <= upto], w[w <= upto]
    order = np.argsort(at, kind="stable")
    at, dst, w = at[order], dst[order], w[order]
    begin = np.searchsorted(at, np.arange(len(ids) + 1))
    home = np.minimum(np.searchsorted(ids, dst), len(ids) - 1)
    inside = ids[home] == dst
    out, extended, relaxed = [], 0, 0
    for _ in range(limit):
        here = fresh & (dist >= lo) & (dist < (none if stop is None else stop))
        fresh &= ~here
        go = np.flatnonzero(here & ((deg > 1) | (ids == source) | keep_leaves))
        if not len(go):
            break
        extended += len(go)
        n = begin[go + 1] - begin[go]
        arc = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(begin[go], n)
        src, length = at[arc], dist[at[arc]] + w[arc]
        kept = length >= lo
        if hi is not None:
            kept &= length < hi
        if skip_parent:
            kept &= dst[arc] != parent[src]
        arc, src, length = arc[kept], src[kept], length[kept]
        relaxed += len(arc)
        away = ~inside[arc]
        out.append((dst[arc[away]], length[away], hops[src[away]] + 1, ids[src[away]]))
        to, length, src = home[arc[~away]], length[~away], src[~away]
        least = dist.copy()
        np.minimum.at(least, to, length)
        won = np.flatnonzero((length == least[to]) & (length < dist[to]))
        won = won[np.lexsort([ids[src[won]], hops[src[won]], to[won]])]
        won = won[np.concatenate([[True], to[won[1:]] != to[won[:-1]]])] if len(won) else won
        dist[to[won]], hops[to[won]], parent[to[won]] = length[won], hops[src[won]] + 1, ids[src[won]]
        fresh[to[won]] = True
    far = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [np.zeros(0, np.int64)] * 4
    reached, n = dist < none, len(far[0])
    known = np.concatenate([reached, np.ones(n, bool)])
    both = lambda own, more: np.concatenate([own, more])
    counts = lambda k: np.concatenate([[k], np.zeros(len(ids) + n - 1, np.int64)])
    yield pa.RecordBatch.from_arrays(
        [
            pa.array(both(ids, far[0]).astype(np.int64)), pa.array(both(np.ones(len(ids), bool), np.zeros(n, bool))), pa.array(both(deg, np.zeros(n)).astype(np.int64)),
            pa.array(both(dist, far[1].astype(dist.dtype)), number, mask=~known), pa.array(both(hops, far[2]).astype(np.int32), mask=~known), pa.array(both(parent, far[3]).astype(np.int64), mask=~known),
            pa.array(both(fresh, np.zeros(n, bool))), pa.array(counts(extended).astype(np.int64)), pa.array(counts(relaxed).astype(np.int64)),
        ],
        names=["v", "own", "deg", "dist", "hops", "parent", "fresh", "extended", "relaxed"],
    )


class Search:
    """The state of one search and the rounds on it."""

    def __init__(self, graph: PreparedGraph, source: int, hub_degree: int = 0, skip_parent: bool = True, keep_leaves: bool = False, target: int | None = None):
        self.graph, self.source, self.hub_degree, self.skip_parent, self.keep_leaves, self.target = graph, source, hub_degree, skip_parent, keep_leaves, target
        at, kind = F.col("v") == source, dict(graph.arcs.dtypes)["w"]
        self.state = graph.vertices.select("v", "deg", F.when(at, 0).cast(kind).alias("dist"), F.when(at, 0).cast("int").alias("hops"), F.when(at, source).cast("long").alias("parent"), at.alias("fresh"))
        self.counters = Counters()
        self.last = Round(1, 1, 0, 0, None, 0)

    def may_extend(self) -> Column:
        """Leaves lead nowhere, except from the source."""
        return F.lit(True) if self.keep_leaves else (F.col("deg") > 1) | (F.col("v") == self.source)

    def push(self, bands: tuple[Band, ...], window: tuple | None = None, weights: tuple | None = None, note: tuple = ()) -> Round:
        """Extend the rows of the bands along arcs whose path length lies in the window [lo, hi) and whose weight lies in
        (above, upto]; None leaves a side open."""
        chosen = F.coalesce(_any(b.rows() for b in bands), F.lit(False))
        front = self.state.where(chosen & self.may_extend()).select("v", "dist", "hops", "parent")
        met = front.join(self.graph.chunks, F.col("v") == F.col("src"))
        lo, hi = window or (None, None)
        above, upto = weights or (None, None)
        if hi is not None:
            met = met.where(F.col("dist") + F.col("wmin") < hi)
        if lo is not None:
            met = met.where(F.col("dist") + F.col("wmax") >= lo)
        if upto is not None:
            met = met.where(F.col("wmin") <= upto)
        if above is not None:
            met = met.where(F.col("wmax") > above)
        arcs = met.select("dist", "hops", "parent", "src", F.explode("adjacent").alias("arc")).select("dist", "hops", "parent", "src", "arc.w", "arc.dst")
        length = F.col("dist") + F.col("w")
        for limit, condition in ((hi, lambda x: length < x), (lo, lambda x: length >= x), (upto, lambda x: F.col("w") <= x), (above, lambda x: F.col("w") > x)):
            if limit is not None:
                arcs = arcs.where(condition(limit))
        if self.skip_parent:
            arcs = arcs.where("dst <> parent")
        found = arcs.groupBy("dst").agg(F.min(F.struct(length.alias("length"), (F.col("hops") + 1).alias("hops"), F.col("src"))).alias("best"), F.count("*").alias("k"))
        return self._merge(found, chosen, _any(b.counts() for b in bands) & self.may_extend(), "push", note)

    def pull(self, lo, hi, cut, strategy: str = "request", note: tuple = ()) -> Round:
        """Open vertices get what settled ones of [cut, lo) can offer below hi.

        request: open vertices ask along arcs lighter than hi - cut. semi: the band's arcs are read instead, which gives
        the same by undirectedness; requests are then counted from the open side's arcs.
        """
        open_rows = self.state.where(F.col("dist").isNull() | (F.col("dist") >= lo))
        band = self.state.where((F.col("dist") >= cut) & (F.col("dist") < lo)).select(F.col("v").alias("u"), F.col("dist").alias("far"), F.col("hops").alias("far_hops"))
        chunks = self.graph.chunks.where(F.col("wmin") < hi - cut)
        unfold = lambda rows, *kept: rows.select(*kept, F.explode("adjacent").alias("arc")).select(*kept, "arc.w", "arc.dst").where(F.col("w") < hi - cut)
        asked = unfold(open_rows.select("v").join(chunks, F.col("v") == F.col("src")), "v")
        told = Observation()
        if strategy == "request":
            asked = asked.observe(told, F.count("*").alias("n"))
            answered = asked.select(F.col("v").alias("dst"), F.col("dst").alias("u"), "w").join(band, "u")
        else:
            self.counters.requested += asked.count()
            answered = unfold(band.join(chunks, F.col("u") == F.col("src")), "u", "far", "far_hops").join(open_rows.select(F.col("v").alias("dst")), "dst", "left_semi")
        length = F.col("far") + F.col("w")
        found = answered.where((length < hi) & (length >= lo)).groupBy("dst").agg(F.min(F.struct(length.alias("length"), (F.col("far_hops") + 1).alias("hops"), F.col("u").alias("src"))).alias("best"), F.count("*").alias("k"))
        result = self._merge(found, F.lit(False), F.lit(False), "pull", note)
        if strategy == "request":
            self.counters.requested += told.get["n"]
        return result

    def fused(self, lo, hi, limit: int, note: tuple = (), extend_to=None, upto=None) -> Round:
        """Up to ``limit`` push rounds of the fresh rows in [lo, extend_to or hi) within each partition, then one exchange of
        what leaves it: lengths for vertices of other partitions.

        State and adjacency rows meet co-located, so arcs are not exchanged; a partition's part of both is held by one
        task, and the changed state is dealt out by vertex once. ``hi`` bounds path lengths, ``upto`` weights.
        """
        stop, skip, source, keep = extend_to if extend_to is not None else hi, self.skip_parent, self.source, self.keep_leaves
        kind = dict(self.graph.arcs.dtypes)["w"]
        met = self.state.join(self.graph.chunks.select("src", "adjacent"), F.col("v") == F.col("src"), "left").select("v", "deg", "dist", "hops", "parent", "fresh", F.transform("adjacent", lambda x: x["dst"]).alias("dsts"), F.transform("adjacent", lambda x: x["w"]).alias("ws"))

        def task(batches):
            table = pa.Table.from_batches(list(batches))
            if table.num_rows:
                yield from _local_rounds(table, lo, hi, stop, upto, limit, skip, source, keep)

        schema = f"v long, own boolean, deg long, dist {kind}, hops int, parent long, fresh boolean, extended long, relaxed long"
        done = met.mapInArrow(task, schema).checkpoint()
        told = done.agg(F.coalesce(F.sum("extended"), F.lit(0)).alias("e"), F.coalesce(F.sum("relaxed"), F.lit(0)).alias("r")).first()
        found = done.where("not own").groupBy(F.col("v").alias("dst")).agg(F.min(F.struct(F.col("dist").alias("length"), "hops", F.col("parent").alias("src"))).alias("best"), F.lit(0).cast("long").alias("k"))
        self.state = done.where("own").select("v", "deg", "dist", "hops", "parent", "fresh").repartition(self.graph.parts, "v")
        self.counters.extended += told["e"]
        self.counters.relaxed += told["r"]
        return self._merge(found, F.lit(False), F.lit(False), "fused", note)

    def _merge(self, found: DataFrame, chosen: Column, counted: Column, kind: str, note: tuple) -> Round:
        better = F.coalesce(F.col("best.length") < F.col("dist"), F.col("best.length").isNotNull())
        merged = self.state.withColumns({"__chosen": chosen, "__counted": F.coalesce(counted, F.lit(False))}).join(found, F.col("v") == F.col("dst"), "left").withColumn("__better", better)
        pick = lambda old, new: F.when(F.col("__better"), F.col(f"best.{new}")).otherwise(F.col(old)).alias(old)
        after = merged.select("v", "deg", pick("dist", "length"), pick("hops", "hops"), pick("parent", "src"), (F.col("__better") | (F.col("fresh") & ~F.col("__chosen"))).alias("fresh"), "__better", "__counted", "k")
        seen, reached = Observation(), F.col("dist").isNotNull()
        after = after.observe(
            seen,
            F.count(F.when(F.col("__better"), 1)).alias("improved"), F.count(F.when(F.col("fresh"), 1)).alias("fresh"), F.min(F.when(F.col("fresh"), F.col("dist"))).alias("fresh_min"),
            F.max("dist").alias("top"), F.min(F.when(reached & (F.col("deg") >= self.hub_degree), F.col("dist"))).alias("hub"), F.coalesce(F.sum("k"), F.lit(0)).alias("relaxed"), F.count(F.when(F.col("__counted"), 1)).alias("extended"),
            F.min(F.when(F.col("v") == (-1 if self.target is None else self.target), F.col("dist"))).alias("target"),
        )
        self.state = after.drop("__better", "__counted", "k").checkpoint()
        got = seen.get
        self.last = Round(got["improved"], got["fresh"], got["fresh_min"], got["top"], got["hub"], got["relaxed"], got["target"])
        self.counters.note(kind, note, got["extended"], got["relaxed"], got["improved"])
        return self.last

    def statistics(self, hi, first: float | None = None, step: float = 1.0, count: int = 0) -> tuple[dict[int, int], np.ndarray]:
        """In one pass: the degree histogram of the vertices open at ``hi``, and the degree sums of settled ones by
        distance on a grid of count + 1 points (those below the first point are left out)."""
        is_open = F.col("dist").isNull() | (F.col("dist") >= hi)
        place = F.lit(-1) if first is None else F.greatest(F.lit(-1), F.least(F.lit(count), F.floor((F.col("dist") - first) / step))).cast("int")
        rows = self.state.groupBy(F.when(is_open, F.col("deg")).alias("deg"), F.when(~is_open, place).alias("place")).agg(F.count("*").alias("n"), F.sum("deg").alias("d")).collect()
        sums = np.zeros(count + 1)
        for r in rows:
            if r["deg"] is None and r["place"] >= 0:
                sums[r["place"]] += r["d"]
        return {r["deg"]: r["n"] for r in rows if r["deg"] is not None}, sums

    def best_cut(self, lo, profit) -> float | None:
        """The settled distance of the largest positive profit among all of them; ``profit`` makes one of (distance,
        degree sum of settled vertices from there on), as a column."""
        sums = self.state.where(F.col("dist") < lo).groupBy("dist").agg(F.sum("deg").alias("d"))
        ranked = running_sums(sums, "dist", "d")
        whole = ranked.agg(F.max("upto")).first()[0] or 0
        at = ranked.withColumn("profit", profit(F.col("dist").cast("double"), F.lit(float(whole)) - F.col("upto") + F.col("d")))
        best = at.agg(F.max(F.struct("profit", (-F.col("dist")).alias("back"))).alias("b")).first()["b"]
        return -best["back"] if best and best["profit"] > 0 else None

    def jump(self, lo):
        """The least length that any settled vertex offers an open one, where a window brought nothing."""
        settled = self.state.where(F.col("dist") < lo).select("v", "dist")
        closed, told = settled.select(F.col("v").alias("dst")), Observation()
        arcs = settled.join(self.graph.chunks, F.col("v") == F.col("src")).select("dist", F.explode("adjacent").alias("arc")).select("dist", "arc.w", "arc.dst").observe(told, F.count("*").alias("n"))
        offers = arcs.join(closed, "dst", "left_anti").agg(F.min(F.col("dist") + F.col("w"))).first()[0]
        waiting = self.state.where(F.col("dist") >= lo).agg(F.min("dist")).first()[0]
        self.counters.probes += 1
        self.counters.probed += told.get["n"]
        return min((x for x in (offers, waiting) if x is not None), default=None)

    def degree_sums(self, lo, reach) -> tuple[int, int]:
        """Degree sums of the vertices settled within ``reach`` below lo, and of the open ones."""
        band = (F.col("dist") >= lo - reach) & (F.col("dist") < lo)
        got = self.state.agg(F.sum(F.when(band, F.col("deg"))).alias("band"), F.sum(F.when(F.col("dist").isNull() | (F.col("dist") >= lo), F.col("deg"))).alias("open")).first()
        return got["band"] or 0, got["open"] or 0

    def nearest_fresh(self, count: int):
        """The least length that ``count`` fresh vertices stay at or below: counts by bucket, refined until a bucket is small."""
        fresh = self.state.where("fresh").select(F.col("dist").cast("double").alias("x"))
        lo, hi, below = float(self.last.fresh_min), float(self.last.top), 0
        while lo < hi:
            place = F.least(F.lit(1023), F.floor((F.col("x") - lo) / ((hi - lo) / 1024)))
            rows = fresh.where((F.col("x") >= lo) & (F.col("x") <= hi)).groupBy(place.alias("k")).agg(F.count("*").alias("n"), F.min("x").alias("least"), F.max("x").alias("top")).orderBy("k").collect()
            for r in rows:
                if below + r["n"] >= count:
                    break
                below += r["n"]
            else:
                return rows[-1]["top"]
            lo, hi = r["least"], r["top"]
            if lo < hi and r["n"] <= FEW:
                held = fresh.where((F.col("x") >= lo) & (F.col("x") <= hi)).orderBy("x").collect()
                return held[count - below - 1]["x"]
        return hi
