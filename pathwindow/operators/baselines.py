"""The classical searches, as schedules of the same rounds."""

from __future__ import annotations

import heapq
import math
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.stepping import QuantileTable, choose_width
from ..plans.engine import Result, run, run_each
from ..plans.prepared import PreparedGraph
from ..plans.rounds import FRESH, Band

ALL = {"skip_parent": False, "keep_leaves": True}


def bellman_ford_loop(search) -> None:
    while search.last.fresh:
        search.push(FRESH)


def bellman_ford(graph: PreparedGraph, source: int) -> Result:
    """Every round extends all lengths that improved in the one before."""
    return run(graph, source, bellman_ford_loop, ALL)


def dijkstra_loop(search, max_rounds: int) -> None:
    while search.last.fresh:
        if search.counters.rounds >= max_rounds:
            raise RuntimeError("too many rounds")
        search.push((Band(hi=search.last.fresh_min, fresh=True, closed=True),))


def dijkstra_rounds(graph: PreparedGraph, source: int, max_rounds: int | None = None) -> Result:
    """Every round settles all vertices at the least open length: no path is extended twice, so that rounds
    are as many as vertices at most (the default cap leaves twice that)."""
    return run(graph, source, dijkstra_loop, ALL, max_rounds=max_rounds or 2 * graph.n + 1)


def dijkstra_local(edges: list[tuple], source: int) -> dict[int, float]:
    """Exact distances of a small graph in one process, for tests."""
    around: dict[int, list] = {}
    for a, b, w in edges:
        around.setdefault(a, []).append((b, w))
        around.setdefault(b, []).append((a, w))
    best, queue = {source: 0}, [(0, source)]
    while queue:
        d, u = heapq.heappop(queue)
        if d == best[u]:
            for v, w in around.get(u, ()):
                if d + w < best.get(v, math.inf):
                    best[v] = d + w
                    heapq.heappush(queue, (d + w, v))
    return best


def dijkstra_components(edges: DataFrame, components: DataFrame, sources: DataFrame) -> DataFrame:
    """(source, v, dist): exact searches in one process for each component that holds a source, a group of rows each.

    For graphs of many small components (v, component): a component has to fit a task."""
    import pandas as pd

    kind = dict(edges.dtypes)["w"]
    of_source = components.select(F.col("v").alias("source"), F.col("component").alias("part"))
    of_edge = components.select(F.col("v").alias("a"), F.col("component").alias("part"))
    asked = sources.select(F.col("source").cast("long").alias("source")).join(of_source, "source").select("part", "source")
    wanted = asked.select("part").distinct()
    held = edges.join(of_edge, "a").join(wanted, "part", "left_semi").select("part", "a", "b", "w")

    def each(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        edge_list = list(left[["a", "b", "w"]].itertuples(index=False, name=None))
        return pd.DataFrame([(s, v, d) for s in right["source"] for v, d in dijkstra_local(edge_list, s).items()], columns=["source", "v", "dist"])

    return held.groupBy("part").cogroup(asked.groupBy("part")).applyInPandas(each, f"source long, v long, dist {kind}")


def _delta(graph, delta):
    return delta or max(0.1 * graph.wmax, 1 if isinstance(graph.wmax, int) else 0) or 1.0


def delta_loop(search, delta, adaptive: bool, fused: int) -> None:
    graph, lo = search.graph, 0
    delta = _delta(graph, delta)
    while search.last.fresh:
        lo = max(lo, search.last.fresh_min)
        if adaptive:
            delta = choose_width(search.statistics(lo)[0], graph.two_m, graph.table).width or 1
        else:
            at, lo = lo, math.floor(lo / delta) * delta
            if not lo <= at < lo + delta:  # a length that is a bucket's bound but for rounding: the bucket begins there
                lo = at
        hi = lo + delta
        while search.last.fresh and search.last.fresh_min < hi:
            if fused and hasattr(search, "fused"):
                search.fused(lo, None, fused, (lo, hi), extend_to=hi, upto=delta)
            else:
                search.push((Band(lo, hi, fresh=True),), None, (None, delta), (lo, hi))
        search.push((Band(lo, hi, counted="none"),), None, (delta, None), (lo, hi))
        search.counters.windows += 1
        lo = hi


def delta_stepping(graph: PreparedGraph, source: int, delta=None, adaptive: bool = False, fused: bool = False, local_rounds: int = 256) -> Result:
    """Buckets of width delta (a tenth of the largest weight by default): light arcs to a fixed point, then heavy ones.

    ``adaptive``: each bucket's width is the window choice's. ``fused``: light rounds run on within partitions first (a
    distributed search; within one task every round is local).
    """
    return run(graph, source, delta_loop, {"skip_parent": False}, delta=delta, adaptive=adaptive, fused=local_rounds if fused else 0)


def delta_star_loop(search, delta) -> None:
    threshold, delta = 0, _delta(search.graph, delta)
    while search.last.fresh:
        threshold = max(threshold, search.last.fresh_min) + delta
        search.push((Band(hi=threshold, fresh=True),), note=(0, threshold))


def delta_star_stepping(graph: PreparedGraph, source: int, delta=None) -> Result:
    """A threshold that moves on by delta in every round, whether or not a bucket is done."""
    return run(graph, source, delta_star_loop, {"skip_parent": False}, delta=delta)


def rho_loop(search, rho: int) -> None:
    while search.last.fresh:
        limit = max(search.nearest_fresh(rho), search.last.fresh_min) if search.last.fresh > rho else None
        search.push(FRESH if limit is None else (Band(hi=limit, fresh=True, closed=True),))


def rho_stepping(graph: PreparedGraph, source: int, rho: int | None = None) -> Result:
    """Every round extends about the rho nearest fresh vertices (ties with the last one too)."""
    return run(graph, source, rho_loop, {"skip_parent": False}, rho=rho or max(64, graph.n // 8))


def pruned_delta_loop(search, delta, max_windows: int) -> None:
    lo, wmax = 0, search.graph.wmax
    delta = _delta(search.graph, delta)
    delta = int(math.ceil(delta)) if isinstance(wmax, int) else delta
    slack = 0 if isinstance(wmax, int) else 1e-9 * (1 + float(wmax))
    r = search.last
    while r.top + wmax >= lo:
        if search.counters.windows >= max_windows:
            raise RuntimeError("too many windows")
        hi = lo + delta
        pushed, left = search.degree_sums(lo, wmax)
        if not left:
            break
        pull = pushed > left
        if pull:
            search.pull(lo, hi, max(0, lo - wmax - slack), note=(lo, hi))
        short = Band(lo, hi, counted="fresh")
        r = search.push((short,) if pull else (Band(lo - wmax - slack, lo, counted="none"), short), (lo, hi), note=(lo, hi))
        while r.fresh and r.fresh_min is not None and r.fresh_min < hi:
            r = search.push((Band(lo, hi, fresh=True),), (lo, hi), note=(lo, hi))
        search.counters.windows += 1
        lo = hi


def pruned_delta_stepping(graph: PreparedGraph, source: int, delta=None, max_windows: int = 100_000) -> Result:
    """Fixed windows in which only arcs whose length falls into the window are relaxed; per window, settled vertices
    either all push or are all pulled from, by the smaller degree sum."""
    return run(graph, source, pruned_delta_loop, None, delta=delta, max_windows=max_windows)


def bfs(graph: PreparedGraph, source: int) -> Result:
    """Fewest hops: the search with all weights one."""
    one = F.lit(1).cast("long")
    chunks = lambda: graph.chunks.select("src", one.alias("wmin"), one.alias("wmax"), F.transform("adjacent", lambda x: F.struct(one.alias("w"), x["dst"].alias("dst"))).alias("adjacent"))
    ones = replace(graph, arcs=graph.arcs.withColumn("w", one), chunks=chunks, table=QuantileTable((1, 1)), cache={})
    return bellman_ford(ones, source)


SHARES = (0.02, 0.05, 0.1, 0.2, 0.5, 1.0)


def tune_delta(graph: PreparedGraph, source: int, shares: tuple[float, ...] = SHARES) -> DataFrame:
    """Counters of delta-stepping over widths, as shares of the largest weight."""
    widths = [max(share * graph.wmax, 1) if isinstance(graph.wmax, int) else share * graph.wmax for share in shares]
    found = run_each(graph, [(source, {"delta": w, "adaptive": False, "fused": 0}) for w in widths], delta_loop, {"skip_parent": False}, states=False)
    rows = [(share, c.rounds, c.relaxed, c.extended) for share, c in zip(shares, (r.counters for r in found), strict=True)]
    return graph.arcs.sparkSession.createDataFrame(rows, "share double, rounds int, relaxed long, extended long")


def tuned_delta_stepping(graph: PreparedGraph, source: int, shares: tuple[float, ...] = SHARES, sync_cost: int | None = None) -> Result:
    """Fused delta-stepping with the width of the least work: traversals, and a synchronisation as so many of them."""
    cost = graph.n if sync_cost is None else sync_cost
    best = min(tune_delta(graph, source, shares).collect(), key=lambda r: (r["relaxed"] + cost * r["rounds"], r["share"]))
    return delta_stepping(graph, source, max(best["share"] * graph.wmax, 1) if isinstance(graph.wmax, int) else best["share"] * graph.wmax, fused=True)
