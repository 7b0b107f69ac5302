"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Two graphs and six methods, the tuned width of delta-stepping among them, each over the same eight random sources on shared
preprocessing. ``queries`` holds wall seconds of one job that searches from all sources (Spark's overhead included);
``search`` the mean seconds that a search itself took within its task, in the manner of the published times; ``spread`` the
wall seconds of one source by distributed rounds.
"""

from __future__ import annotations

import json
import os
import time
from dataclasses import replace

SOURCES = 8
GRAPHS = ("customer_part", "part_supplier_price")


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g")).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from pathwindow.operators import apps, audit, baselines, experiments
    from pathwindow.plans.engine import adaptive_sssp
    from pathwindow.plans.prepared import prepare
    from pathwindow.sources import graphs

    times: dict[str, float] = {}
    work: dict[str, dict[str, float]] = {}

    def timed(name, f):
        start = time.time()
        out = f()
        times[name] = round(time.time() - start, 3)
        return out

    spread: dict[str, float] = {}
    for name in GRAPHS:
        graph = timed(f"{name}_prepare", lambda name=name: prepare(graphs.GRAPHS[name](spark, sf_dir)))
        sources = apps.random_sources(graph, SOURCES)
        experiments.RIVALS["adaptive"](graph, sources[:1])  # sends the graph to the executors once
        methods = experiments.RIVALS | {"delta_tuned": experiments._tuned}
        for method, search in methods.items():
            found = timed(f"{name}_{method}", lambda search=search, graph=graph, sources=sources: search(graph, sources))
            told = audit.average_measures(graph, found)
            work[f"{name}_{method}"] = {k: round(told[k], 4) for k in ("seconds", "n_frontier", "n_sync", "n_trav")}
        wide = replace(graph, local_arcs=0)
        for method, run in (("adaptive", adaptive_sssp), ("bellman_ford", baselines.bellman_ford)):
            began = time.time()
            run(wide, sources[0])
            spread[f"{name}_{method}"] = round(time.time() - began, 3)
    best = {g: min(work[f"{g}_{m}"]["seconds"] for m in methods if m != "adaptive") for g in GRAPHS}
    speedups = {g: {"search": round(best[g] / work[f"{g}_adaptive"]["seconds"], 3), "with_preprocessing": round(best[g] / (work[f"{g}_adaptive"]["seconds"] + times[f"{g}_prepare"]), 5)} for g in GRAPHS}
    print(json.dumps({"metric": "search and preprocessing seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf_dir.rpartition("sf")[2], "sources": SOURCES, "work": work, "best_rival_over_adaptive": speedups, "distributed_one_source": spread}))


if __name__ == "__main__":
    main()
