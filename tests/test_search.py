"""Exactness of every method on a graph that can be checked by hand, and of the statistics."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathwindow.functions.stepping import QuantileTable, balance_degree, choose_width, open_degree
from pathwindow.operators import apps, audit, baselines
from pathwindow.plans import prepared
from pathwindow.plans.engine import Config, adaptive_sssp, point_to_point, push_only, windowed_sssp
from pathwindow.plans.prepared import prepare, weight_quantiles

TOY = [(1, 2, 1), (1, 3, 4), (2, 3, 2), (2, 4, 6), (3, 4, 3), (3, 5, 5), (4, 5, 1), (4, 6, 7), (5, 6, 2), (6, 7, 1), (2, 5, 9), (8, 9, 1)]


@pytest.fixture(scope="module", params=["within a task", "distributed"])
def toy(spark, request):
    return prepare(spark.createDataFrame(TOY, "a long, b long, w long"), local_arcs=0 if request.param == "distributed" else 1000)


def got(result):
    return {r.v: r.dist for r in result.state.collect()}


def test_statistics(toy):
    assert toy.n == 9 and toy.two_m == 24 and toy.wmax == 9
    assert open_degree(toy.histogram) == 24 and balance_degree(toy.histogram) == 4
    choice = choose_width(toy.histogram, toy.two_m, toy.table)
    assert choice.width == 2 and abs(choice.share - 0.4725) < 1e-3


@pytest.mark.parametrize("source", [1, 2, 8])
def test_adaptive_is_exact_from_hub_leaf_and_small_component(toy, source):
    assert got(adaptive_sssp(toy, source)) == baselines.dijkstra_local(TOY, source)


@pytest.mark.parametrize("method", [baselines.bellman_ford, baselines.delta_stepping, baselines.delta_star_stepping, baselines.rho_stepping, baselines.dijkstra_rounds, lambda g, s: baselines.delta_stepping(g, s, fused=True), push_only])
def test_other_methods_are_exact(toy, method):
    assert got(method(toy, 7)) == baselines.dijkstra_local(TOY, 7)


@pytest.mark.parametrize("local_arcs", [0, 1000])
def test_any_thresholds_and_cuts_are_exact(spark, local_arcs):
    rng = random.Random(3)
    edges = [(a, b, w) for a, b, w in {(min(p), max(p)): (min(p), max(p), rng.randint(0, 9)) for p in ((rng.randrange(20), rng.randrange(20)) for _ in range(60)) if p[0] != p[1]}.values()]
    graph = prepare(spark.createDataFrame(edges, "a long, b long, w long"), local_arcs=local_arcs)
    source = edges[0][0]
    want = baselines.dijkstra_local(edges, source)
    assert got(windowed_sssp(graph, source, [2, 3, 7])) == want
    for pull in ("always", "semi", "off"):
        assert got(adaptive_sssp(graph, source, Config(pull=pull, alpha=1))) == want


@pytest.mark.parametrize("local_arcs", [0, 1000])
def test_float_weights_keep_every_arc(spark, local_arcs):
    rng = random.Random(5)
    edges = [(i, j, rng.choice([0.1, 0.3, 0.7, 1.0])) for i in range(9) for j in range(i + 1, 9) if rng.random() < 0.5]
    graph = prepare(spark.createDataFrame(edges, "a long, b long, w double"), local_arcs=local_arcs)
    assert got(adaptive_sssp(graph, edges[0][0], Config(alpha=1, pull="always"))) == baselines.dijkstra_local(edges, edges[0][0])


def test_both_ways_of_running_do_the_same_work(spark):
    rng = random.Random(11)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(60), rng.randrange(60)) for _ in range(500)) if p[0] != p[1]}
    frame = spark.createDataFrame([(a, b, rng.randint(1, 1000)) for a, b in pairs], "a long, b long, w long")
    small, large = prepare(frame, local_arcs=10_000), prepare(frame, local_arcs=0)
    methods = [adaptive_sssp, lambda g, s: adaptive_sssp(g, s, Config(cut_mode="all")), baselines.delta_stepping, baselines.pruned_delta_stepping]
    for method in methods:
        one, two = method(small, 7), method(large, 7)
        assert one.seconds is not None and two.seconds is None
        rows = lambda r: sorted(map(tuple, r.state.select("v", "dist", "hops", "parent", "deg").collect()))
        work = lambda r: vars(r.counters) | {"probed": 0}  # probes may read either side of the front
        assert rows(one) == rows(two) and work(one) == work(two)


@pytest.mark.parametrize("local_arcs", [0, 1000])
def test_zero_weights_missing_sources_and_empty_graphs(spark, local_arcs):
    for kind in ("long", "double"):
        zero = prepare(spark.createDataFrame([(1, 2, 0), (2, 3, 0)], "a long, b long, w long").selectExpr("a", "b", f"CAST(w AS {kind}) AS w"), local_arcs=local_arcs)
        for method in (adaptive_sssp, baselines.delta_stepping, baselines.delta_star_stepping, baselines.pruned_delta_stepping):
            assert got(method(zero, 1)) == {1: 0, 2: 0, 3: 0}
        assert got(adaptive_sssp(zero, 99)) == {99: 0}
    empty = prepare(spark.createDataFrame([], "a long, b long, w long"), local_arcs=local_arcs)
    assert empty.n == 0 and got(adaptive_sssp(empty, 5)) == {5: 0}


def test_bad_edges_are_refused(spark):
    for bad in ((1, 2, None), (1, None, 3.0), (1, 2, -1.0), (1, 2, float("nan"))):
        with pytest.raises(ValueError):
            prepare(spark.createDataFrame([(3, 4, 1.0), bad], "a long, b long, w double"))


def test_long_chains_by_fused_rounds(spark):
    edges = [(i, i + 1, 1 + i % 3) for i in range(400)]
    graph = prepare(spark.createDataFrame(edges, "a long, b long, w long"), local_arcs=0)
    found = adaptive_sssp(graph, 0)
    assert got(found) == baselines.dijkstra_local(edges, 0) and audit.validate(found).count() == 0
    plain = prepare(spark.createDataFrame(edges, "a long, b long, w long"), local_arcs=10_000)
    assert found.counters.rounds < adaptive_sssp(plain, 0).counters.rounds


def test_point_to_point_stops_early(spark):
    edges = [(i, i + 1, 1) for i in range(200)] + [(0, i, 500) for i in range(2, 200)]
    graph = prepare(spark.createDataFrame(edges, "a long, b long, w long"))
    whole, near = adaptive_sssp(graph, 0), point_to_point(graph, 0, 5)
    assert got(near) == {v: d for v, d in got(whole).items() if d <= 5} and near.counters.rounds <= whole.counters.rounds


def test_quantiles(spark):
    edges = spark.createDataFrame([(i, i + 1, i + 1) for i in range(100)], "a long, b long, w long")
    table = weight_quantiles(edges, 11, "exact")
    assert table.values[0] == 1 and table.values[5] == 50 and table.wmax == 100
    assert QuantileTable((0, 0, 2, 3)).at(0.0) == 2


def test_audits(spark, toy):
    result = adaptive_sssp(toy, 1)
    kinds = {(r.src, r.dst): (r["class"], r.backward) for r in audit.classify_edges(toy.arcs, result.state, 3, 7).collect()}
    assert kinds[1, 3][0] == kinds[2, 3][0] == "long" and kinds[3, 4] == ("short", False) and kinds[3, 2] == ("short", True)
    edges = spark.createDataFrame(TOY, "a long, b long, w long")
    assert {(r.a, r.b) for r in audit.skippable_edges(edges, result.state).collect()} == {(1, 3), (2, 4), (3, 5), (4, 6), (2, 5)}
    assert audit.validate(result).count() == 0
    parents = audit.canonical_parents(toy.arcs, result.state, 1)
    path = apps.extract_paths(parents, spark.createDataFrame([(7,)], "target long"), 1).first().path
    assert path[0] == 1 and path[-1] == 7 and len(path) == 7


def test_speedups_of_printed_times():
    times = {"graph": {"search": 0.368, "preprocess": 0.654, "rival": 2.147, "other": 2.266}}
    least, most = audit.speedups(times)["graph"]
    assert round(most, 2) == 5.83 and round(least, 2) == 2.10


def test_a_cap_with_open_work_raises(toy):
    with pytest.raises(RuntimeError):
        adaptive_sssp(toy, 7, Config(width=1, max_windows=2))
    with pytest.raises(RuntimeError):
        baselines.dijkstra_rounds(toy, 7, max_rounds=2)


def test_sampled_quantiles_keep_the_exact_maximum(spark, monkeypatch):
    monkeypatch.setattr(prepared, "SAMPLE", 200, raising=False)
    edges = spark.range(5000).selectExpr("id AS a", "id + 1 AS b", "IF(id = 4321, 1000000, id % 100 + 1) AS w")
    table = weight_quantiles(edges, 11, "sample")
    assert table.wmax == 1000000 and None not in table.values and 20 <= table.values[5] <= 80


def test_windows_are_audited(spark):
    rng = random.Random(2)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(80), rng.randrange(80)) for _ in range(900)) if p[0] != p[1]}
    edges = [(a, b, rng.randint(1, 500)) for a, b in pairs]
    result = adaptive_sssp(prepare(spark.createDataFrame(edges, "a long, b long, w long")), edges[0][0])
    d, windows = baselines.dijkstra_local(edges, edges[0][0]), audit.windows_of(result)
    want = {}
    pulled = [lo for lo, _, cut in windows if cut < lo]
    number = lambda x: max((k for k, w in enumerate(windows) if w[0] <= x), default=-1)
    for a, b, w in edges:
        for u, v in ((a, b), (b, a)):
            for k, (lo, hi, cut) in enumerate(windows):
                if lo <= d[u] + w < hi and d[u] < lo and d[v] < lo:
                    kind = "before" if d[u] < min(pulled, default=10**9) else "same" if number(d[v]) <= number(d[u]) else "later"
                    want[k, kind, d[u] >= cut] = want.get((k, kind, d[u] >= cut), 0) + 1
    assert {(r.window, r.kind, r.skipped): r.arcs for r in audit.skipped_edges(result).collect()} == want
    two_m = 2 * len(edges)
    deg = {}
    for a, b, _ in edges:
        deg[a], deg[b] = deg.get(a, 0) + 1, deg.get(b, 0) + 1
    opened = lambda x: two_m - sum(n for v, n in deg.items() if v in d and d[v] < x)
    assert [(r.open_lo, r.open_hi) for r in audit.window_claims(result).orderBy("window").collect()] == [(opened(lo), opened(hi)) for lo, hi, _ in windows]


def test_rounds_read_the_arcs_where_they_lie(spark):
    """A round's plan exchanges candidates only: neither the adjacency nor the state."""
    from pathwindow.plans.prepared import fixed_plans
    from pathwindow.plans.rounds import FRESH, Search

    graph = prepare(spark.createDataFrame(TOY, "a long, b long, w long"), local_arcs=0)
    with fixed_plans(spark, graph.parts):
        search = Search(graph, 1)
        search.push(FRESH)
        front = search.state.where("fresh").join(graph.chunks, search.state.v == graph.chunks.src)
        assert front._jdf.queryExecution().executedPlan().toString().count("Exchange") == 0


def test_small_graphs_are_prepared_without_adjacency_and_with_the_same_quantiles(spark):
    from pathwindow.plans.prepared import local_quantiles, weight_quantiles

    graph = prepare(spark.createDataFrame(TOY, "a long, b long, w long"))
    assert callable(graph.__dict__["_chunks"])
    assert graph.chunks.count() == graph.n and graph.chunks is graph.chunks
    rng = np.random.default_rng(4)
    for kind, w in (("long", rng.integers(0, 60, 500).tolist()), ("double", rng.random(300).tolist()), ("long", [5]), ("long", [])):
        edges = spark.createDataFrame([(k, k + 1, x) for k, x in enumerate(w)], f"a long, b long, w {kind}")
        for num in (2, 7, 101, 4096):
            assert local_quantiles(edges, num) == weight_quantiles(edges, num)


def test_running_sums_over_ranges(spark):
    frame = spark.range(1000).selectExpr("id * 7 % 1000 AS k", "id % 5 AS x")
    rows = prepared.running_sums(frame, "k", "x").orderBy("k").collect()
    total = 0
    for r in rows:
        total += r.x
        assert r.upto == total


@pytest.mark.parametrize("local_arcs", [0, 10_000])
def test_fewest_hops_of_graphs_of_any_size(spark, local_arcs):
    """Many equal lengths, and zero weights: hops are those of a search by (length, hops). No number of vertices is refused."""
    from dataclasses import replace

    rng = random.Random(4)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(60), rng.randrange(60)) for _ in range(260)) if p[0] != p[1]}
    edges = [(a, b, rng.randint(0, 3)) for a, b in pairs]
    graph = prepare(spark.createDataFrame(edges, "a long, b long, w long"), local_arcs=local_arcs)
    source = edges[0][0]
    want = {v: d % 1000 for v, d in baselines.dijkstra_local([(a, b, 1000 * w + 1) for a, b, w in edges], source).items()}
    assert {r.v: r.hops for r in apps.fewest_hops(graph, adaptive_sssp(graph, source)).collect()} == want
    told = apps.hop_stats(replace(graph, n=1 << 21), source).first()
    assert tuple(told) == (len(want), sum(want.values()), max(want.values()))


def _held(edges):
    """A graph as one task holds it."""
    import numpy as np

    from pathwindow.plans.local import LocalGraph
    from pathwindow.plans.prepared import Facts

    src, dst, w = (np.array(x) for x in zip(*[t for a, b, w in edges for t in ((a, b, w), (b, a, w))], strict=True))
    degrees = np.unique(src, return_counts=True)[1]
    deg, n = np.unique(degrees, return_counts=True)
    table = QuantileTable(tuple(np.sort(w)[np.linspace(0, len(w) - 1, 101).astype(int)].tolist()))
    return LocalGraph(Facts(len(degrees), len(src), dict(zip(deg.tolist(), n.tolist(), strict=True)), table), src, dst, w)


@pytest.mark.parametrize("whole", [True, False])
def test_every_schedule_is_exact_within_a_task(whole):
    """Queued fresh vertices, arcs found by bisection and statistics kept up to date, against brute force."""
    from pathwindow.plans.engine import adaptive_loop, windowed_loop
    from pathwindow.plans.local import LocalSearch

    loops = [baselines.bellman_ford_loop, lambda s: baselines.dijkstra_loop(s, 10**6), lambda s: baselines.delta_loop(s, None, False, 0), lambda s: baselines.delta_loop(s, None, True, 0)]
    loops += [lambda s: baselines.delta_star_loop(s, None), lambda s: baselines.rho_loop(s, 7), lambda s: baselines.pruned_delta_loop(s, None, 10**6), lambda s: windowed_loop(s, [2, 30, 70])]
    loops += [lambda s, c=c: adaptive_loop(s, c) for c in (Config(alpha=1), Config(alpha=1, pull="always"), Config(pull="off"), Config(cut_mode="all", alpha=1), Config(cut_mode="cdf", alpha=1))]
    rng = random.Random(8)
    for n, m in ((12, 20), (300, 500), (300, 3000)):
        pairs = {(min(p), max(p)) for p in ((rng.randrange(n), rng.randrange(n)) for _ in range(m)) if p[0] != p[1]}
        edges = [(a, b, rng.randint(0, 100) if whole else rng.random() ** 4) for a, b in pairs]
        graph, source = _held(edges), edges[0][0]
        want = baselines.dijkstra_local(edges, source)
        for loop in loops:
            search = LocalSearch(graph, source, hub_degree=balance_degree(graph.histogram))
            loop(search)
            found = {int(v): d for v, d in zip(graph.ids, search.dist.tolist(), strict=True) if d < search.none}
            assert found == want if whole else found == pytest.approx(want)
            assert search.last.top == max(search.dist[search.dist < search.none]) and search.last.fresh == search.fresh.sum()


def test_searches_of_many_windows_run_to_their_end():
    from pathwindow.plans.engine import adaptive_loop
    from pathwindow.plans.local import LocalSearch

    rng = random.Random(3)
    edges = [(i, i + 1, rng.randint(1, 100_000)) for i in range(25_000)]
    search = LocalSearch(_held(edges), 0, hub_degree=2)
    adaptive_loop(search, Config(alpha=1, jump_empty=False))
    assert search.counters.windows > 20_000 and search.dist[-1] == sum(w for _, _, w in edges)


def test_nearest_vectors_in_blocks(spark, tmp_path, monkeypatch):
    """Small blocks, many equal vectors, missing labels and vectors: as brute force ranks them by (rounded length, id)."""
    from pathwindow.sources import graphs

    monkeypatch.setattr(graphs, "ASKING", 16)
    monkeypatch.setattr(graphs, "STORED", 32)
    rng = random.Random(9)
    rows = [(i, [float(rng.randint(0, 2)) for _ in range(3)], rng.choice([1, 1, 1, 2, None])) for i in range(150)] + [(150, None, 1), (151, [9.0, 9.0, 9.0], 3)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    want = set()
    for a, x, label in rows:
        near = sorted((round(1e6 * sum((p - q) ** 2 for p, q in zip(x, y, strict=True)) ** 0.5), b) for b, y, other in rows if b != a and y and x and label is not None and other == label)[:5]
        want |= {(min(a, b), max(a, b), w) for w, b in near}
    assert {tuple(r) for r in graphs.knn_vectors(spark, str(tmp_path), 5).collect()} == want
    plan = graphs.knn_vectors(spark, str(tmp_path), 5)._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan  # no join of all pairs on rows


@pytest.mark.parametrize("kind", ["long", "double"])
def test_packed_graphs_give_the_same_rows_and_count_the_same_work(spark, monkeypatch, kind):
    """Graphs that never pass through the driver, in rounds of several blocks and with hubs that no block holds."""
    from pathwindow.plans import local
    from pathwindow.plans.engine import adaptive_all

    rng = random.Random(12)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(200), rng.randrange(200)) for _ in range(1500)) if p[0] != p[1]} | {(0, k) for k in range(1, 200)}
    edges = [(a, b, rng.randint(0, 40) if kind == "long" else rng.choice([0.0, 0.5, 1.25, 3.0])) for a, b in sorted(pairs)]
    frame = spark.createDataFrame(edges, f"a long, b long, w {kind}")
    methods = [lambda g: adaptive_all(g, [7, 0, 31]), lambda g: {7: baselines.bellman_ford(g, 7)}, lambda g: {7: adaptive_sssp(g, 7, Config(pull="always", alpha=1))}, lambda g: {7: baselines.delta_stepping(g, 7)}]
    told = []
    for sent in (10**6, 0):
        monkeypatch.setattr(local, "SENT_ARCS", sent)
        monkeypatch.setattr(local, "PACK", 10**6 if sent else 50)
        graph = prepare(frame)
        told.append([{s: (sorted(map(tuple, r.state.select("v", "dist", "hops", "parent", "deg").collect())), vars(r.counters)) for s, r in method(graph).items()} for method in methods])
        assert ("packed" in graph.cache) != bool(sent)
    assert told[0] == told[1]
    assert {v: d for v, d, *_ in told[1][0][31][0]} == pytest.approx(baselines.dijkstra_local(edges, 31))


def test_rounds_in_blocks_are_the_same_rounds(monkeypatch):
    from pathwindow.plans import local
    from pathwindow.plans.engine import adaptive_loop

    rng = random.Random(13)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(150), rng.randrange(150)) for _ in range(1200)) if p[0] != p[1]} | {(3, k) for k in range(4, 150)}
    graph = _held([(a, b, rng.randint(0, 9)) for a, b in sorted(pairs)])
    for loop in (baselines.bellman_ford_loop, lambda s: baselines.pruned_delta_loop(s, None, 10**6), lambda s: adaptive_loop(s, Config(alpha=1, pull="always"))):
        told = []
        for block in (1 << 21, 7):
            monkeypatch.setattr(local, "BLOCK", block)
            search = local.LocalSearch(graph, 5, hub_degree=balance_degree(graph.histogram))
            loop(search)
            told.append((search.dist.tolist(), search.hops.tolist(), search.parent.tolist(), vars(search.counters)))
        assert told[0] == told[1]


def test_measures_without_states_are_those_of_the_states(spark):
    from pathwindow.plans.engine import adaptive_all

    for local_arcs in (0, 1000):
        graph = prepare(spark.createDataFrame(TOY, "a long, b long, w long"), local_arcs=local_arcs)
        whole, brief = adaptive_all(graph, [1, 8, 7]), adaptive_all(graph, [1, 8, 7], states=False)
        for r in whole.values():
            r.others.clear()
        one, two = audit.average_measures(graph, whole), audit.average_measures(graph, brief)
        assert {k: v for k, v in one.items() if k != "seconds"} == {k: v for k, v in two.items() if k != "seconds"}
        assert got(brief[7]) == baselines.dijkstra_local(TOY, 7)


def test_widths_are_tuned_in_one_job(spark):
    """All widths at once count what searches one by one do."""
    graph = prepare(spark.createDataFrame(TOY, "a long, b long, w long"))
    for r in baselines.tune_delta(graph, 1).collect():
        c = baselines.delta_stepping(graph, 1, max(r.share * graph.wmax, 1)).counters
        assert (r.rounds, r.relaxed, r.extended) == (c.rounds, c.relaxed, c.extended)


def test_variants_of_weights_are_prepared_as_if_anew(spark):
    """The arcs' order, quantiles and distances of every variant, without another shuffle of the arcs."""
    from pathwindow import catalog
    from pathwindow.functions.weights import rescaled
    from pathwindow.plans.prepared import reweighted

    rng = random.Random(14)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(40), rng.randrange(40)) for _ in range(300)) if p[0] != p[1]}
    edges = spark.createDataFrame([(a, b, rng.randint(90, 9_000)) for a, b in sorted(pairs)], "a long, b long, w long")
    base = prepare(edges)
    for name, weight in catalog.WEIGHTS.items():
        anew = prepare(rescaled(edges).select("a", "b", weight(F.col("w")).alias("w")))
        shared = reweighted(base, lambda w, weight=weight: weight(w / base.wmax))
        assert (shared.n, shared.two_m, shared.histogram, shared.table, shared.arcs.dtypes) == (anew.n, anew.two_m, anew.histogram, anew.table, anew.arcs.dtypes), name
        rows = lambda g: [(r.src, r.w) for r in g.arcs.collect()]
        assert rows(shared) == rows(anew)
        assert "Exchange" not in shared.arcs._jdf.queryExecution().executedPlan().toString()


def test_configurations_share_a_job(spark):
    from pathwindow.plans.engine import adaptive_all, adaptive_each

    for local_arcs in (0, 1000):
        graph = prepare(spark.createDataFrame(TOY, "a long, b long, w long"), local_arcs=local_arcs)
        cfgs = [Config(alpha=1), Config(alpha=1, pull="off")]
        for cfg, found in zip(cfgs, adaptive_each(graph, [8, 99, 8], cfgs), strict=True):
            one = adaptive_all(graph, [8, 99], cfg)
            assert {s: (got(r), vars(r.counters)) for s, r in found.items()} == {s: (got(r), vars(r.counters)) for s, r in one.items()}


def test_rivals_of_one_job_measure_as_one_by_one(spark):
    from pathwindow.operators import experiments

    for kind in ("long", "double"):
        graph = prepare(spark.createDataFrame(TOY, "a long, b long, w long").selectExpr("a", "b", f"CAST(w AS {kind}) AS w"))
        table = {(r.method, r.measure): r.value for r in experiments.rivals(spark, [("toy", lambda graph=graph: graph)], 3).collect()}
        assert {m for m, _ in table} == {*experiments.RIVALS, "delta_tuned"}
        for method, search in experiments.RIVALS.items():
            for measure, value in audit.average_measures(graph, search(graph, experiments.trials(graph, 3))).items():
                assert measure == "seconds" or table[method, measure] == value


def test_measures_do_not_depend_on_the_way_of_running(spark, monkeypatch):
    """Distributed searches are timed too, and count what searches within a task count, by every method."""
    from pathwindow.operators import experiments
    from pathwindow.plans import rounds

    rng = random.Random(15)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(40), rng.randrange(40)) for _ in range(60)) if p[0] != p[1]}
    frame = spark.createDataFrame([(a, b, rng.randint(1, 9)) for a, b in sorted(pairs)], "a long, b long, w long")
    monkeypatch.setattr(rounds, "FEW", 3)
    told = []
    for local_arcs in (10_000, 0):
        graph = prepare(frame, local_arcs=local_arcs)
        found = {m: audit.average_measures(graph, experiments.RIVALS[m](graph, experiments.trials(graph, 1))) for m in ("adaptive", "delta_stepping")}
        found["rho_5"] = audit.measures(baselines.rho_stepping(graph, sorted(pairs)[0][0], 5))
        assert all(f["seconds"] > 0 for f in found.values())
        told.append({(m, k): v for m, f in found.items() for k, v in f.items() if k not in ("seconds", "probed")})
    assert told[0] == pytest.approx(told[1])
    rows = experiments.amortisation(spark, graph, 0.0, (1,)).collect()
    assert len(rows) == 1 and rows[0].seconds_a_source > 0
    # a chain, on which rounds within partitions would be counted as one
    chain = spark.createDataFrame([(i, i + 1, 1 + i % 3) for i in range(12)], "a long, b long, w long")
    one, two = (experiments.RIVALS["adaptive"](prepare(chain, local_arcs=k), [0])[0].counters for k in (1000, 0))
    assert (one.rounds, one.relaxed) == (two.rounds, two.relaxed)


@pytest.mark.parametrize("delta, lengths", [(129597.70000000001, (1295977,)), (1.4000000000000001, (21, 42)), (25.900000000000002, (777,))])
def test_buckets_of_a_fractional_width_go_on(spark, monkeypatch, delta, lengths):
    """A length that is a multiple of the width but for rounding falls into a bucket: the search once went on for ever."""
    from pathwindow.plans import local

    edges = [(i, i + 1, length) for i, length in enumerate(lengths)]
    push, left = local.LocalSearch.push, [100]

    def counted(self, *args, **more):
        left[0] -= 1
        assert left[0], "the search goes on for ever"
        return push(self, *args, **more)

    monkeypatch.setattr(local.LocalSearch, "push", counted)
    search = local.LocalSearch(_held(edges), 0, skip_parent=False)
    baselines.delta_loop(search, delta, False, 0)
    assert dict(enumerate(search.dist.tolist())) == baselines.dijkstra_local(edges, 0)


def test_ranked_offers_win_as_sorted_ones(monkeypatch):
    """Ties of lengths, hops and sources fall alike whether offers are sorted or ranked by vertex."""
    from pathwindow.plans import local
    from pathwindow.plans.engine import adaptive_loop

    rng = random.Random(16)
    pairs = {(min(p), max(p)) for p in ((rng.randrange(120), rng.randrange(120)) for _ in range(900)) if p[0] != p[1]}
    graph = _held([(a, b, rng.randint(0, 3)) for a, b in sorted(pairs)])
    for loop in (baselines.bellman_ford_loop, lambda s: baselines.delta_loop(s, 1.5, False, 0), lambda s: adaptive_loop(s, Config(alpha=1, pull="always"))):
        told = []
        for few, block in ((10**6, 1 << 21), (0, 1 << 21), (0, 7)):
            monkeypatch.setattr(local, "FEW", few)
            monkeypatch.setattr(local, "BLOCK", block)
            search = local.LocalSearch(graph, 5, hub_degree=balance_degree(graph.histogram), skip_parent=False)
            loop(search)
            told.append((search.dist.tolist(), search.hops.tolist(), search.parent.tolist(), vars(search.counters)))
        assert told[0] == told[1] == told[2]
