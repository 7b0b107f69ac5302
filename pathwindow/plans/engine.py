"""The adaptive window search and the fixed-schedule searches, all on the same rounds.

A schedule is a loop over rounds of a search object: ``rounds.Search`` on distributed frames, or ``local.LocalSearch``
within one task where the graph's checked size allows it. ``run`` chooses.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.stepping import balance_degree, choose_cut, choose_width, cut_profit, open_degree
from .local import fits, search_locally
from .prepared import Late, PreparedGraph, fixed_plans
from .rounds import FRESH, Band, Counters, Search

SLACK = 1e-9


@dataclass(frozen=True)
class Config:
    alpha: float | str = 3  # a number, or "auto": the largest degree where degrees hardly differ
    beta: float = 0.9
    st_num: int = 1024
    pull: str = "auto"  # auto, off, semi, always
    cut_mode: str = "grid"  # grid, all, cdf
    width: float | None = None  # a fixed width in place of the chosen one
    jump_empty: bool = True
    fused: int = 256  # local rounds before an exchange where the width is the largest weight (distributed search); 0: none
    max_windows: int | None = None  # None: what a search that goes on can need, see caps
    max_rounds: int | None = None

    def caps(self, n: int) -> tuple[int, int]:
        """(windows, rounds) that a search may take: by default several a vertex, which only an endless loop exceeds."""
        return self.max_windows or 3 * n + 20_000, self.max_rounds or 10 * n + 50_000


@dataclass
class Result:
    state: DataFrame = Late()  # v, dist, hops, parent, deg of reached vertices
    counters: Counters
    graph: PreparedGraph
    source: int
    seconds: float | None = None  # of the search alone, where it ran within a task
    others: dict = field(default_factory=dict)
    elapsed: float = 0.0  # seconds from the first round to the last, wherever the search ran

    def trace(self) -> DataFrame:
        schema = "window int, round int, kind string, lo double, hi double, cut double, extended long, relaxed long, improved long"
        return self.state.sparkSession.createDataFrame(self.counters.trace, schema)


def _alone(graph: PreparedGraph, source: int) -> Result:
    """A source without edges reaches itself."""
    kind = dict(graph.arcs.dtypes)["w"]
    row = graph.arcs.sparkSession.range(1).select(F.lit(source).cast("long").alias("v"), F.lit(0).cast(kind).alias("dist"), F.lit(0).alias("hops"), F.lit(source).cast("long").alias("parent"), F.lit(0).cast("long").alias("deg"))
    return Result(row, Counters(), graph, source)


def run(graph: PreparedGraph, source: int, loop: Callable, options: dict | None = None, **args) -> Result:
    """One search by a schedule, within a task or distributed."""
    return run_all(graph, [source], loop, options, **args)[source]


def run_all(graph: PreparedGraph, sources: list[int], loop: Callable, options: dict | None = None, states: bool = True, **args) -> dict[int, Result]:
    """Searches from several sources on the shared preprocessing: tasks of one job where the graph fits a task, otherwise
    one distributed search after another. Without ``states``, tasks keep their distances to themselves, and what is told of a
    search are its counters and sums; a state that is asked for after all is searched for again."""
    asked = list(dict.fromkeys(sources))
    return dict(zip(asked, run_each(graph, [(s, args) for s in asked], loop, options, states), strict=True))


def run_each(graph: PreparedGraph, trials: list[tuple[int, dict]], loop: Callable, options: dict | None = None, states: bool = True) -> list[Result]:
    """As ``run_all``, for a list of (source, arguments of the schedule)."""
    return run_trials(graph, [(s, loop, options or {}, args) for s, args in trials], states)


def run_trials(graph: PreparedGraph, trials: list[tuple[int, Callable, dict, dict]], states: bool = True) -> list[Result]:
    """As ``run_all``, for a list of (source, schedule, options of a search, arguments of the schedule)."""
    there = {r["v"] for r in graph.vertices.where(F.col("v").isin([s for s, *_ in trials])).select("v").collect()} if graph.n else set()
    asked = [t for t in trials if t[0] in there]
    found: list[Result] = []
    if asked and fits(graph):
        rows, counters, seconds, reached = search_locally(graph, asked, states)
        for tag, (s, *_) in enumerate(asked):
            state = rows.where(F.col("tag") == tag).drop("tag") if states else lambda trial=asked[tag]: run_trials(graph, [trial])[0].state
            found.append(Result(state, counters[tag], graph, s, seconds[tag], {"reached": reached[tag]}, seconds[tag]))
    else:
        for s, loop, options, args in asked:
            search = Search(graph, s, **options)
            with fixed_plans(graph.arcs.sparkSession, graph.parts):
                began = time.perf_counter()
                loop(search, **args)
                elapsed = time.perf_counter() - began
            found.append(Result(search.state.where("dist is not null").select("v", "dist", "hops", "parent", "deg"), search.counters, graph, s, elapsed=elapsed))
    of = iter(found)
    return [next(of) if s in there else _alone(graph, s) for s, *_ in trials]


def adaptive_loop(search, cfg: Config = Config(), stop_at_target: bool = False) -> None:
    """Windows [lo, hi) whose widths follow degrees and weights.

    Settled vertices below ``cut`` push their arcs into the window; those of [cut, lo) are pulled from. The first window
    ends at the nearest vertex of at least the balance degree; a source of such degree closes it at zero, after its own
    arcs are relaxed once, and the second window starts there.
    """
    graph, c = search.graph, search.counters
    wmax, whole = graph.wmax, isinstance(graph.wmax, int)
    max_windows, max_rounds = cfg.caps(graph.n)
    alpha = cfg.alpha
    if alpha == "auto":
        alpha = max(graph.histogram) if max(graph.histogram) <= min(8, 2 * balance_degree(graph.histogram)) else 3
    slack = 0 if whole else SLACK * (1 + float(wmax))
    # first window: open-ended until a hub is met
    hi = math.inf
    while True:
        before = hi
        r = search.push((Band(hi=None if hi == math.inf else hi, fresh=True),), None if hi == math.inf else (None, hi), note=(0, hi))
        hi = min(hi, r.hub if r.hub is not None else math.inf)
        if r.fresh == 0 or (r.fresh_min is not None and r.fresh_min >= hi):
            break
        if hi == before and not r.improved and r.fresh_min is None:
            break
        if c.rounds > max_rounds:
            raise RuntimeError("too many rounds")
    c.windows += 1
    if hi == math.inf:
        return
    previous_full, st0, st1 = False, hi, None
    while search.last.top + wmax >= hi:
        if stop_at_target and search.last.target is not None and search.last.target < hi:
            return
        first, step = (None, 1.0) if st1 is None else (float(st0), (float(st1) - float(st0)) / cfg.st_num or 1.0)
        histogram, sums = search.statistics(hi, first, step, cfg.st_num)
        if not histogram:
            break
        if c.windows >= max_windows:
            raise RuntimeError("too many windows")
        lo, total = hi, open_degree(histogram)
        choice = choose_width(histogram, graph.two_m, graph.table, alpha, cfg.beta)
        width = cfg.width or choice.width or 1
        full = width >= wmax
        hi = lo + width
        if hi <= lo:
            raise RuntimeError("a window must have a width")
        if st1 is None and 2 * total <= graph.two_m:
            st1 = lo
            step = (float(st1) - float(st0)) / cfg.st_num or 1.0
            if cfg.cut_mode != "all":
                _, sums = search.statistics(lo, float(st0), step, cfg.st_num)
        cut = lo
        if cfg.pull == "always":
            cut = max(0, lo - wmax)
        elif cfg.pull != "off" and 2 * total < graph.two_m and not previous_full:
            if full:
                cut = max(0, lo - wmax)
            elif cfg.cut_mode == "all":
                found = search.best_cut(lo, lambda x, d, lo=lo, hi=hi, total=total: cut_profit(x, d, float(lo), float(hi), total, graph.two_m, float(wmax)))
                cut = lo if found is None else found
            else:
                points = float(st0) + step * np.arange(cfg.st_num + 1)
                at = total + np.cumsum(sums[::-1])[::-1]
                cut = choose_cut(points, at, float(lo), float(hi), total, graph.two_m, graph.table, cfg.cut_mode == "cdf")
            cut = max(0, min(cut, lo))
        previous_full = full
        if whole and cut < lo:
            cut = int(math.floor(cut))
        note = (lo, hi, cut)
        if cut < lo:
            search.pull(lo, hi, cut, "semi" if cfg.pull == "semi" else "request", note)
        # settled vertices that push reach back one maximum weight at most; they are no new paths
        settled, short = Band(lo - wmax - slack, cut, counted="none"), Band(lo, hi, counted="fresh")
        r = search.push((settled, short), (lo, hi), note=note)
        gained = r.improved
        while r.fresh and r.fresh_min is not None and r.fresh_min < hi:
            if full and cfg.fused and hasattr(search, "fused"):
                r = search.fused(lo, hi, cfg.fused, note)
            else:
                r = search.push((Band(lo, hi, fresh=True),), (lo, hi), note=note)
            gained += r.improved
            if c.rounds > max_rounds:
                raise RuntimeError("too many rounds")
        c.windows += 1
        if cfg.jump_empty and not gained:
            ahead = search.jump(hi)
            if ahead is None:
                break
            hi = max(hi, ahead)


def _options(graph: PreparedGraph, **more) -> dict:
    return {"hub_degree": balance_degree(graph.histogram)} | more


def adaptive_sssp(graph: PreparedGraph, source: int, cfg: Config = Config()) -> Result:
    """Exact shortest paths by the adaptive windows."""
    return run(graph, source, adaptive_loop, _options(graph), cfg=cfg)


def adaptive_all(graph: PreparedGraph, sources: list[int], cfg: Config = Config(), states: bool = True) -> dict[int, Result]:
    return run_all(graph, sources, adaptive_loop, _options(graph), states, cfg=cfg)


def adaptive_each(graph: PreparedGraph, sources: list[int], cfgs: list[Config], states: bool = True) -> list[dict[int, Result]]:
    """The searches of ``adaptive_all`` under several configurations, in one job where the graph fits a task."""
    asked = list(dict.fromkeys(sources))
    found = iter(run_each(graph, [(s, {"cfg": cfg}) for cfg in cfgs for s in asked], adaptive_loop, _options(graph), states))
    return [{s: next(found) for s in asked} for _ in cfgs]


def windowed_loop(search, thresholds: list) -> None:
    wmax = search.graph.wmax
    slack = 0 if isinstance(wmax, int) else SLACK * (1 + float(wmax))
    edges = sorted({0, *thresholds})
    for lo, hi in zip(edges, [*edges[1:], None], strict=True):
        short = Band(lo, hi, counted="fresh")
        r = search.push((Band(lo - wmax - slack, lo, counted="none"), short), (lo, hi), note=(lo, hi))
        while r.fresh and r.fresh_min is not None and (hi is None or r.fresh_min < hi):
            r = search.push((Band(lo, hi, fresh=True),), (lo, hi), note=(lo, hi))
        search.counters.windows += 1
        if hi is not None and r.top is not None and r.top + wmax < hi:
            break


def windowed_sssp(graph: PreparedGraph, source: int, thresholds: list) -> Result:
    """Windows between given ascending thresholds; beyond the last one the search runs to its end."""
    return run(graph, source, windowed_loop, thresholds=thresholds)


def push_only(graph: PreparedGraph, source: int, cfg: Config = Config()) -> Result:
    """The window choice alone: every settled vertex pushes."""
    return adaptive_sssp(graph, source, replace(cfg, pull="off"))


def point_to_point(graph: PreparedGraph, source: int, target: int, cfg: Config = Config()) -> Result:
    """The search up to the window that settles the target; only vertices up to its distance are given, all of them
    final. An unreached target gives no rows."""
    found = run(graph, source, adaptive_loop, _options(graph, target=target), cfg=cfg, stop_at_target=True)
    limit = found.state.where(F.col("v") == target).select(F.col("dist").alias("limit"))
    found.state = found.state.join(F.broadcast(limit)).where("dist <= limit").drop("limit")
    return found


__all__ = ["FRESH", "Band", "Config", "Result", "adaptive_all", "adaptive_each", "adaptive_loop", "adaptive_sssp", "point_to_point", "push_only", "run", "run_all", "run_each", "run_trials", "windowed_sssp"]
