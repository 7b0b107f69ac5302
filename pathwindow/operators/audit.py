"""Audits of finished searches and the paper's cost measures."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..functions.stepping import balance_degree
from ..functions.weights import edge_class
from ..plans.engine import Result
from ..plans.prepared import PreparedGraph


def _with_ends(arcs: DataFrame, state: DataFrame) -> DataFrame:
    ends = state.select("v", "dist")
    return arcs.join(ends.select(F.col("v").alias("src"), F.col("dist").alias("du")), "src").join(ends.select(F.col("v").alias("dst"), F.col("dist").alias("dv")), "dst", "left")


def classify_edges(arcs: DataFrame, state: DataFrame, lo, hi) -> DataFrame:
    """Each arc of a reached vertex with its class for the window, and whether a short one leads back."""
    told = _with_ends(arcs, state).withColumn("class", edge_class(F.col("du"), F.col("dv"), F.col("w"), lo, hi))
    return told.select("src", "dst", "w", "class", ((F.col("class") == "short") & (F.col("dv") < lo)).alias("backward"))


def exact_traversals(arcs: DataFrame, state: DataFrame, lo, hi, cut, wmax) -> DataFrame:
    """What the estimates stand for: arcs pushed from [cut, lo), pulled by the open part, and needed."""
    told = _with_ends(arcs, state)
    length = F.col("du") + F.col("w")
    band = (F.col("du") >= cut) & (F.col("du") < lo) & (length >= lo) & (length < hi)
    asked = (F.col("du") >= lo) & (F.col("w") < hi - cut)
    count = lambda c, name: F.count(F.when(c, 1)).alias(name)
    return told.agg(count(band, "pushed"), count(asked, "pulled"), count(band & (F.col("dv") >= lo), "long_arcs"))


def skippable_edges(edges: DataFrame, state: DataFrame) -> DataFrame:
    """Edges of the reached part that no shortest path uses in either direction."""
    ends = state.select("v", "dist")
    told = edges.join(ends.select(F.col("v").alias("a"), F.col("dist").alias("da")), "a").join(ends.select(F.col("v").alias("b"), F.col("dist").alias("db")), "b")
    return told.where("da + w > db and db + w > da").select("a", "b", "w")


def tight_arcs(arcs: DataFrame, state: DataFrame) -> DataFrame:
    return _with_ends(arcs, state).where("du + w = dv").select("src", "dst", "w")


def canonical_parents(arcs: DataFrame, state: DataFrame, source: int) -> DataFrame:
    """(v, parent): the least tight predecessor; zero-weight ties inside a distance are left to the least id too."""
    found = tight_arcs(arcs, state).where(F.col("dst") != source).groupBy(F.col("dst").alias("v")).agg(F.min("src").alias("parent"))
    return found


def window_of(length: Column, bounds: list) -> Column:
    """The number of the last bound at or below a length (-1: none), by binary search; bounds ascend."""
    held = np.array(bounds, float)

    @pandas_udf("long")
    def place(x: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(held, x.to_numpy(float), "right") - 1)

    return place(length.cast("double"))


def windows_of(result: Result) -> list[tuple]:
    """(lo, hi, cut) of the windows after the first, in their order."""
    found: dict[int, list] = {}
    for window, _, _, lo, hi, cut, *_ in result.counters.trace:
        if cut is not None:
            found.setdefault(window, [lo, hi, lo])[2] = cut
    return [tuple(found[k]) for k in sorted(found)]


def skipped_edges(result: Result) -> DataFrame:
    """(window, kind, skipped, arcs): irrelevant arcs by the window that their length falls into.

    Kinds, by when their ends were settled: ``before`` the first window that was pulled into; by ``same`` if the far end was
    settled no later than the near end's window closed; ``later`` if it was settled in a window after that. An arc is
    skipped if its near end lies at or above the window's cut, where pulling never looks at it.
    """
    windows = windows_of(result)
    spark = result.state.sparkSession
    if not windows:
        return spark.createDataFrame([], "window long, kind string, skipped boolean, arcs long")
    pulled = [lo for lo, _, cut in windows if cut < lo]
    table = spark.createDataFrame([(k, float(lo), float(hi), float(cut)) for k, (lo, hi, cut) in enumerate(windows)], "window long, lo double, hi double, cut double")
    lows = [lo for lo, _, _ in windows]
    told = _with_ends(result.graph.arcs, result.state).withColumn("window", window_of(F.col("du") + F.col("w"), lows)).withColumn("own", window_of(F.col("du"), lows)).withColumn("far", window_of(F.col("dv"), lows))
    met = told.join(F.broadcast(table), "window").where("du + w < hi and du < lo and dv < lo")
    kind = F.when(F.col("du") < (min(pulled) if pulled else math.inf), "before").when(F.col("far") <= F.col("own"), "same").otherwise("later")
    return met.groupBy("window", kind.alias("kind"), (F.col("du") >= F.col("cut")).alias("skipped")).agg(F.count("*").alias("arcs"))


def window_claims(result: Result, beta: float = 0.9) -> DataFrame:
    """(window, open_lo, open_hi, share, held): the degrees open at both ends of each window, and whether the window left
    at most the share of them open that its width was chosen for."""
    graph, windows = result.graph, windows_of(result)
    spark = result.state.sparkSession
    if not windows:
        return spark.createDataFrame([], "window long, open_lo long, open_hi long, share double, held boolean")
    bounds = sorted({x for lo, hi, _ in windows for x in (lo, hi)})
    sums = {r["k"]: r["d"] for r in result.state.withColumn("k", window_of(F.col("dist"), bounds)).groupBy("k").agg(F.sum("deg").alias("d")).collect()}
    # degrees open at a bound: those not settled below it
    settled, opened = sums.get(-1, 0), {}
    for k, x in enumerate(bounds):
        opened[x] = graph.two_m - settled
        settled += sums.get(k, 0)
    rows = []
    for k, (lo, hi, _) in enumerate(windows):
        share = min(beta, max(opened[lo], graph.two_m - opened[lo]) / graph.two_m)
        rows.append((k, opened[lo], opened[hi], share, opened[hi] <= share * opened[lo]))
    return spark.createDataFrame(rows, "window long, open_lo long, open_hi long, share double, held boolean")


def load_imbalance(graph: PreparedGraph) -> DataFrame:
    """(partitions, arcs, largest, imbalance): arcs by partition, the largest over the mean."""
    parts = graph.chunks.groupBy(F.spark_partition_id().alias("p")).agg(F.sum(F.size("adjacent")).alias("n"))
    return parts.agg(F.lit(graph.parts).cast("long").alias("partitions"), F.sum("n").alias("arcs"), F.max("n").alias("largest"), (F.max("n") * graph.parts / F.sum("n")).alias("imbalance"))


def repeated_arcs(result: Result) -> DataFrame:
    """(relaxed, tight, repeated): relaxations and requests of a search, arcs that a shortest path may use, and work beyond
    one traversal of each reached vertex's last arc."""
    c = result.counters
    tight = tight_arcs(result.graph.arcs, result.state).count()
    reached = result.state.count()
    return result.state.sparkSession.createDataFrame([(c.relaxed + c.requested, tight, c.relaxed + c.requested - (reached - 1))], "relaxed long, tight long, repeated long")


def measures(result: Result) -> dict[str, float]:
    """The normalised measures of one search."""
    return average_measures(result.graph, {result.source: result})


def average_measures(graph: PreparedGraph, found: dict[int, Result]) -> dict[str, float]:
    """The normalised measures, as means over searches from several sources."""
    results = list(found.values())
    told = {r.source: r.others["reached"] for r in results if "reached" in r.others}  # where the search's task has summed up
    states = [r.state.select(F.lit(r.source).cast("long").alias("source"), "v", "hops", "deg") for r in results if r.source not in told]
    inner = F.count(F.when((F.col("deg") > 1) | (F.col("v") == F.col("source")), 1))
    if states:
        told |= {r["source"]: r for r in reduce(DataFrame.unionByName, states).groupBy("source").agg(F.count("*").alias("reached"), inner.alias("inner"), F.avg("hops").alias("hops"), F.max("hops").alias("top")).collect()}
    scale, m, rows = max(1.0, math.log2(max(2, graph.n))), graph.two_m / 2, []
    for r in results:
        t, c = told[r.source], r.counters
        traversals, reached = c.relaxed + c.requested, t["reached"]
        rows.append(
            {
                "n_frontier": c.extended / max(1, t["inner"]), "n_sync": c.rounds / scale, "n_trav": traversals / max(1, reached), "average_en": (t["hops"] or 0) / scale, "max_en": (t["top"] or 0) / scale,
                "work_saving": m / max(1, graph.n) - traversals / max(1, reached), "traversals_a_sync": traversals / max(1, c.rounds), "redundant": 1 - (reached - 1) / max(1, traversals),
                "probed": c.probed / max(1, reached), "seconds": r.elapsed,
            }
        )
    out = {k: sum(x[k] for x in rows) / len(rows) for k in rows[0]}
    if graph.n:
        out |= {"degree_skew": math.log2(max(graph.histogram) / balance_degree(graph.histogram)), "edges_a_vertex": m / graph.n, "skippable_bound": (m - graph.n) / m}
    return out


def measure_table(spark, results: dict[str, Result]) -> DataFrame:
    rows = [(name, measure, float(value)) for name, r in results.items() for measure, value in measures(r).items()]
    return spark.createDataFrame(rows, "run string, measure string, value double")


def graph_profile(edges: DataFrame) -> DataFrame:
    """n, m, the largest degree, the balance degree, skew and the bound on skippable edges, all in SQL."""
    ends = edges.select(F.col("a").alias("v")).union(edges.select("b"))
    degrees = ends.groupBy("v").agg(F.count("*").alias("deg"))
    histogram = degrees.groupBy("deg").agg(F.count("*").alias("cnt"))
    histogram.createOrReplaceTempView("__degree_histogram")
    spark = edges.sparkSession
    return spark.sql("""
        WITH t AS (SELECT deg, deg * cnt AS total, cnt FROM __degree_histogram),
        r AS (SELECT deg, sum(total) OVER () AS whole, coalesce(sum(total) OVER (ORDER BY deg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM t),
        b AS (SELECT min_by(deg, struct(abs(whole - 2 * below), deg)) AS balance FROM r)
        SELECT CAST(sum(cnt) AS BIGINT) AS n, CAST(sum(total) / 2 AS BIGINT) AS m, CAST(max(deg) AS BIGINT) AS max_degree, CAST(max(balance) AS BIGINT) AS balance_degree,
               round(log2(max(deg) / max(balance)), 6) AS degree_skew, round((sum(total) / 2 - sum(cnt)) / (sum(total) / 2), 6) AS skippable_bound
        FROM t CROSS JOIN b""")


def validate(result: Result) -> DataFrame:
    """Arcs that a shorter path would use, and reached vertices without a tight arc: no rows when distances are exact."""
    told = _with_ends(result.graph.arcs, result.state)
    broken = told.where("dv is null or du + w < dv").select(F.col("dst").alias("v"))
    tight = tight_arcs(result.graph.arcs, result.state).select(F.col("dst").alias("v")).distinct()
    orphans = result.state.where(F.col("v") != result.source).join(tight, "v", "left_anti").select("v")
    return broken.union(orphans)


def speedups(times: dict[str, dict[str, float]], own: str = "search", preprocess: str = "preprocess") -> dict[str, tuple[float, float]]:
    """(least, largest) speedup by graph: the best rival over preprocess + search, and over search alone."""
    out = {}
    for graph, row in times.items():
        best = min(v for k, v in row.items() if k not in (own, preprocess))
        out[graph] = (best / (row[own] + row[preprocess]), best / row[own])
    return out
