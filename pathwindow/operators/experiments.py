"""The evaluation's workloads: searches averaged over random sources, parameter sweeps, rivals and speedups."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.stepping import balance_degree
from ..plans.engine import Config, Result, adaptive_all, adaptive_each, adaptive_loop, run_trials
from ..plans.prepared import PreparedGraph
from . import apps, audit, baselines

TRIALS = 64
# The constants of the method, but that graphs whose degrees hardly differ take their largest degree for alpha. Rounds are
# the schedule's own, never fused within partitions: measures do not depend on how large a graph is and how it is dealt.
METHOD = Config(alpha="auto", fused=0)
BETAS = (0.85, 0.875, 0.9, 0.925, 0.95)
Graphs = Iterable[tuple[str, Callable[[], PreparedGraph]]]


def trials(graph: PreparedGraph, count: int = TRIALS, seed: int = 42) -> list[int]:
    """Random vertices that have edges; fewer where the graph has fewer."""
    return apps.random_sources(graph, count, seed)


def _table(spark: SparkSession, rows: list[tuple[str, str, dict[str, float]]]) -> DataFrame:
    return spark.createDataFrame([(g, m, k, float(v)) for g, m, told in rows for k, v in told.items()], "graph string, method string, measure string, value double")


def window_measures(spark: SparkSession, graphs: Graphs, count: int = TRIALS) -> DataFrame:
    """Extended paths, synchronisations, traversals and hops of both heuristics together and of the windows alone."""
    rows = []
    for name, make in graphs:
        graph = make()
        sources = trials(graph, count)
        for method, found in zip(("adaptive", "windows_only"), adaptive_each(graph, sources, [METHOD, replace(METHOD, pull="off")], states=False), strict=True):
            rows.append((name, method, audit.average_measures(graph, found)))
    return _table(spark, rows)


def beta_sweep(spark: SparkSession, graphs: Graphs, betas: tuple[float, ...] = BETAS, count: int = TRIALS) -> DataFrame:
    rows = []
    for name, make in graphs:
        graph = make()
        sources = trials(graph, count)
        for beta, found in zip(betas, adaptive_each(graph, sources, [replace(METHOD, beta=beta) for beta in betas], states=False), strict=True):
            rows.append((name, f"beta_{beta:g}", audit.average_measures(graph, found)))
    return _table(spark, rows)


# Each method's schedule, options of its searches, and arguments.
SCHEDULES: dict[str, Callable[[PreparedGraph], tuple[Callable, dict, dict]]] = {
    "adaptive": lambda g: (adaptive_loop, {"hub_degree": balance_degree(g.histogram)}, {"cfg": METHOD}),
    "bellman_ford": lambda g: (baselines.bellman_ford_loop, baselines.ALL, {}),
    "delta_stepping": lambda g: (baselines.delta_loop, {"skip_parent": False}, {"delta": None, "adaptive": False, "fused": 0}),
    "delta_star": lambda g: (baselines.delta_star_loop, {"skip_parent": False}, {"delta": None}),
    "rho_stepping": lambda g: (baselines.rho_loop, {"skip_parent": False}, {"rho": max(64, g.n // 8)}),
}
RIVALS: dict[str, Callable[[PreparedGraph, list[int]], dict[int, Result]]] = {
    name: (lambda g, s, of=of: dict(zip(s, run_trials(g, [(v, *of(g)) for v in s], states=False), strict=True))) for name, of in SCHEDULES.items()
}


def _widths(graph: PreparedGraph) -> list[tuple[Callable, dict, dict]]:
    """Delta-stepping over the widths to choose from; its rounds are counted one by one, as those of all methods."""
    widths = [max(s * graph.wmax, 1) if isinstance(graph.wmax, int) else s * graph.wmax for s in baselines.SHARES]
    return [(baselines.delta_loop, {"skip_parent": False}, {"delta": width, "adaptive": False, "fused": 0}) for width in widths]


def _tuned(graph: PreparedGraph, sources: list[int], first: list[Result] | None = None) -> dict[int, Result]:
    """Delta-stepping with the width that takes the least time from the first source; ``first``: the searches over all
    widths, where they are done already."""
    widths = _widths(graph)
    first = first or run_trials(graph, [(sources[0], *w) for w in widths], states=False)
    best = widths[min(range(len(widths)), key=lambda k: first[k].elapsed)]
    return dict(zip(sources, run_trials(graph, [(s, *best) for s in sources], states=False), strict=True))


def rivals(spark: SparkSession, graphs: Graphs, count: int = TRIALS) -> DataFrame:
    """The measures of every method, the tuned one included. All but the tuned searches share a job on a graph that fits a task."""
    rows = []
    for name, make in graphs:
        graph = make()
        sources = trials(graph, count)
        asked = [(s, *of(graph)) for of in SCHEDULES.values() for s in sources] + [(sources[0], *w) for w in _widths(graph)]
        found = run_trials(graph, asked, states=False)
        for k, method in enumerate(SCHEDULES):
            rows.append((name, method, audit.average_measures(graph, dict(zip(sources, found[k * len(sources) :], strict=False)))))
        rows.append((name, "delta_tuned", audit.average_measures(graph, _tuned(graph, sources, found[len(SCHEDULES) * len(sources) :]))))
    return _table(spark, rows)


def speedup_table(measured: DataFrame, preprocess: dict[str, float], own: str = "adaptive") -> DataFrame:
    """(graph, best_rival, search, preprocess, most, least): the best rival's seconds over the search's, and over those of
    preprocessing and one search."""
    spark = measured.sparkSession
    seconds = measured.where("measure = 'seconds'")
    cost = spark.createDataFrame(list(preprocess.items()), "graph string, preprocess double")
    best = seconds.where(F.col("method") != own).groupBy("graph").agg(F.min_by("method", "value").alias("best_rival"), F.min("value").alias("rival"))
    mine = seconds.where(F.col("method") == own).select("graph", F.col("value").alias("search"))
    return best.join(mine, "graph").join(cost, "graph").select("graph", "best_rival", "rival", "search", "preprocess", (F.col("rival") / F.col("search")).alias("most"), (F.col("rival") / (F.col("search") + F.col("preprocess"))).alias("least"))


def time_by_traversals(measured: DataFrame) -> DataFrame:
    """(graph, correlation, slope): how seconds follow traversals over the methods of each graph."""
    wide = measured.where("measure IN ('seconds', 'n_trav')").groupBy("graph", "method").pivot("measure", ["seconds", "n_trav"]).agg(F.first("value"))
    return wide.groupBy("graph").agg(F.corr("seconds", "n_trav").alias("correlation"), F.regr_slope("seconds", "n_trav").alias("slope"))


def amortisation(spark: SparkSession, graph: PreparedGraph, preprocess: float, counts: tuple[int, ...] = (1, 4, 16, 64)) -> DataFrame:
    """(sources, seconds_a_source): preprocessing and searches over the number of sources that share it."""
    found = list(adaptive_all(graph, trials(graph, max(counts)), METHOD, states=False).values())
    rows = [(k, (preprocess + sum(r.elapsed for r in found[:k])) / k) for k in counts if k <= len(found)]
    return spark.createDataFrame(rows, "sources int, seconds_a_source double")
