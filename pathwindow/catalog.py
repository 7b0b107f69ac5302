"""All queries of the shortest-path side, with their DuckDB oracles."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles
from .functions.stepping import choose_width, estimate_traversals
from .functions.weights import converge, discretize, rescaled
from .operators import apps, audit, baselines, experiments, relational, udfs
from .oracles import EDGES
from .plans.engine import Config, Result, adaptive_sssp, point_to_point, push_only, windowed_sssp
from .plans.prepared import PreparedGraph, prepare, reweighted, weight_quantiles
from .sources import graphs, synth
from .streaming import events

Query = Callable[[SparkSession, str], DataFrame]

# Sources at sf0.01: hubs, vertices of the lowest degree, ordinary ones.
HUBS = {"part_supplier_price": 197, "part_supplier_qty": 197, "customer_part": 2756, "customer_supplier": 33, "user_action": 1, "geo_tree": 1}
LOW = {"part_supplier_price": 2442, "customer_part": 858, "customer_supplier": 858, "user_action": 0}


def distances_sql(graph: str, source, tail: str = "SELECT CAST(v AS BIGINT) AS v, CAST(d AS BIGINT) AS dist FROM t") -> str:
    return oracles.search(EDGES[graph], source, tail)


_PREPARED: dict[tuple[str, str, str], PreparedGraph] = {}


def prepared(spark: SparkSession, sf_dir: str, name: str) -> PreparedGraph:
    """Preprocessing is shared by the searches of one application on a graph; variants of weights share that of their graph."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _PREPARED:
        for old in [k for k in _PREPARED if k[0] != key[0]]:
            del _PREPARED[old]
        base = prepared(spark, sf_dir, VARIED) if name in WEIGHTS else None
        began = time.perf_counter()
        _PREPARED[key] = reweighted(base, lambda w: WEIGHTS[name](w / base.wmax)) if base and base.two_m else prepare(BUILDERS[name](spark, sf_dir))
        SECONDS[name] = time.perf_counter() - began
    return _PREPARED[key]


SECONDS: dict[str, float] = {}  # of preprocessing
SYNTHETIC: dict[str, Query] = {
    **{f"kron_10_{k}": (lambda spark, _, k=k: synth.kron(spark, 10, k)) for k in (4, 8, 16, 32)},
    "unif_10_16": lambda spark, _: synth.unif(spark, 10, 16),
    "lattice_30_30": lambda spark, _: synth.lattice(spark, 30, 30),
    "brick_wall_30_30": lambda spark, _: synth.lattice(spark, 30, 30, brick=True),
    "star_200": lambda spark, _: synth.star(spark, 200),
    "path_300": lambda spark, _: synth.path(spark, 300),
}
# The same families over the keys of given tables; their names keep the sizes of the generated ones.
TABLED: dict[str, Query] = {
    **{f"kron_10_{k}": (lambda spark, sf_dir, k=k: synth.kron(spark, 10, k, ids=synth.draws(spark, sf_dir, "customer", "c_custkey", k))) for k in (4, 8, 16, 32)},
    "unif_10_16": lambda spark, sf_dir: synth.unif(spark, 10, 16, ids=synth.draws(spark, sf_dir, "customer", "c_custkey", 16)),
    "lattice_30_30": lambda spark, sf_dir: synth.table_lattice(spark, sf_dir, 30),
    "brick_wall_30_30": lambda spark, sf_dir: synth.table_lattice(spark, sf_dir, 30, brick=True),
    "star_200": synth.table_star,
    "path_300": synth.table_path,
}
POWERS, PIVOTS = (1, 2, 3, 4, 6, 8, 10), tuple(k / 10 for k in range(1, 10))
VARIED = "part_supplier_price"


def _varied(weight: Callable) -> Query:
    return lambda spark, sf_dir: rescaled(graphs.GRAPHS[VARIED](spark, sf_dir)).select("a", "b", weight(F.col("w")).alias("w"))


# From weights over their maximum; none of them falls where weights rise.
WEIGHTS: dict[str, Callable] = {
    **{f"power_{p}": (lambda w, p=p: discretize(w, p)) for p in POWERS},
    **{f"pivot_{round(10 * p)}": (lambda w, p=p: converge(w, p)) for p in PIVOTS},
}
VARIANTS: dict[str, Query] = {name: _varied(weight) for name, weight in WEIGHTS.items()}
BUILDERS: dict[str, Query] = graphs.GRAPHS | SYNTHETIC | VARIANTS


def _scaled_sql(weight: str) -> str:
    return f"SELECT a, b, {weight} AS w FROM (SELECT a, b, w / CAST(max(w) OVER () AS DOUBLE) AS w FROM ({EDGES[VARIED]}))"


def _variant_sql(name: str) -> tuple[str, str]:
    """The edges of a variant, and the type of its weights."""
    kind, _, k = name.partition("_")
    if kind == "power":
        return _scaled_sql(f"CAST(floor(1 + w * {2 ** int(k) - 2} + 0.5) AS BIGINT)"), "BIGINT"
    p, pull = f"CAST({int(k) / 10!r} AS DOUBLE)", "((1 - 2 * w) * (1 - 2 * w))"
    return _scaled_sql(f"CASE WHEN w <= 0.5 THEN {p} - {p} * {pull} ELSE {p} + (1 - {p}) * {pull} END"), "DOUBLE"


def hub(graph: PreparedGraph) -> int:
    """The vertex of the largest degree, the least of them."""
    return graph.vertices.orderBy(F.desc("deg"), "v").first()["v"]


def edge_of(graph: PreparedGraph) -> int:
    """The vertex of the least degree, the last of them."""
    return graph.vertices.orderBy("deg", F.desc("v")).first()["v"]


# What the evaluation runs over: the graphs that stand for its dense, skewed, sparse, high-diameter and synthetic ones.
BASE = ("customer_part", "part_supplier_price", "doc_word", "turn_word", "page_link", "event_chain", "kron_10_16", "unif_10_16", "brick_wall_30_30")
SWEPT = ("customer_part", "part_supplier_price", "kron_10_16", "unif_10_16")


def _graphs(spark: SparkSession, sf_dir: str, names) -> experiments.Graphs:
    return [(name, lambda name=name: prepared(spark, sf_dir, name)) for name in names]


_RIVALS: dict[tuple[str, str], DataFrame] = {}


def _rivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _RIVALS:
        _RIVALS.clear()
        _RIVALS[key] = experiments.rivals(spark, _graphs(spark, sf_dir, BASE), 8)
    return _RIVALS[key]


def _workloads() -> dict[str, tuple[Query, str | None]]:
    found: dict[str, tuple[Query, str | None]] = {}
    rounded = "SELECT CAST(v AS BIGINT) AS v, round(d, 9) AS dist FROM t"

    def distances(name, source_of, method=adaptive_sssp, whole=True):
        def run(spark, sf_dir):
            graph = prepared(spark, sf_dir, name)
            state = method(graph, source_of(graph)).state
            return state.select("v", (F.col("dist").cast("long") if whole else F.round(F.col("dist"), 9)).alias("dist"))

        return run

    for name in ("event_chain", "page_link", "host_page", "doc_word", "turn_word", "knn_vectors"):
        found[f"sssp_adaptive_{name}"] = distances(name, hub), distances_sql(name, oracles.HUB)
    found["sssp_small_component"] = distances("page_link", edge_of), distances_sql("page_link", oracles.EDGE)
    found["sssp_low_degree_alpha_auto"] = distances("event_chain", hub, lambda g, s: adaptive_sssp(g, s, Config(alpha="auto"))), distances_sql("event_chain", oracles.HUB)
    for name, edges in oracles.SYNTHETIC.items():
        found[f"sssp_{name}"] = distances(name, hub, whole=False), oracles.search(edges, oracles.HUB, rounded, "DOUBLE")
        found[f"edges_{name}"] = (lambda spark, sf_dir, name=name: TABLED[name](spark, sf_dir).select("a", "b", F.round("w", 9).alias("w"))), f"SELECT a, b, round(w, 9) AS w FROM ({oracles.TABLED[name]})"
    for name in VARIANTS:
        edges, kind = _variant_sql(name)
        whole = kind == "BIGINT"
        found[f"sssp_{name}"] = distances(name, hub, whole=whole), oracles.search(edges, oracles.HUB, "SELECT CAST(v AS BIGINT) AS v, d AS dist FROM t" if whole else rounded, kind)
    for method in ("bellman_ford", "delta_stepping", "delta_star", "rho_stepping", "pruned_delta", "dijkstra_rounds"):
        found[f"{method}_customer_part"] = distances("customer_part", hub, METHODS[method]), distances_sql("customer_part", oracles.HUB)
        found[f"{method}_page_link"] = distances("page_link", hub, METHODS[method]), distances_sql("page_link", oracles.HUB)
    found["delta_tuned"] = distances("customer_part", hub, baselines.tuned_delta_stepping), distances_sql("customer_part", oracles.HUB)
    # the same searches without the way through a single task
    spread = lambda graph: replace(graph, local_arcs=0)
    found["sssp_adaptive_distributed"] = distances("user_action", hub, lambda g, s: adaptive_sssp(spread(g), s)), distances_sql("user_action", oracles.HUB)
    found["sssp_fused_distributed"] = distances("brick_wall_30_30", hub, lambda g, s: adaptive_sssp(spread(g), s), whole=False), oracles.search(oracles.SYNTHETIC["brick_wall_30_30"], oracles.HUB, rounded, "DOUBLE")
    found["delta_fused_distributed"] = distances("user_action", hub, lambda g, s: baselines.delta_stepping(spread(g), s, fused=True)), distances_sql("user_action", oracles.HUB)

    def hop_stats(spark, sf_dir, name="customer_part"):
        return apps.hop_stats(prepared(spark, sf_dir, name), hub(prepared(spark, sf_dir, name)))

    longest = 1 << 20
    found["hop_stats"] = hop_stats, oracles.search(f"SELECT a, b, w * {longest} + 1 AS w FROM ({EDGES['customer_part']})", oracles.HUB, f"SELECT count(*) AS reached, CAST(sum(d % {longest}) AS BIGINT) AS hops, CAST(max(d % {longest}) AS BIGINT) AS most FROM t")
    found["distinct_weights"] = (
        lambda spark, sf_dir: reduce(DataFrame.union, [graphs.GRAPHS[g](spark, sf_dir).agg(F.lit(g).alias("graph"), F.countDistinct("w").alias("weights")) for g in EDGES]),
        " UNION ALL ".join(f"SELECT '{g}' AS graph, count(DISTINCT w) AS weights FROM ({sql})" for g, sql in EDGES.items()),
    )
    found["unreached_vertices"] = (
        lambda spark, sf_dir: (g := prepared(spark, sf_dir, "page_link")).vertices.join(adaptive_sssp(g, hub(g)).state.select("v"), "v", "left_anti").select("v"),
        distances_sql("page_link", oracles.HUB, "SELECT DISTINCT src AS v FROM arc WHERE src NOT IN (SELECT v FROM t)"),
    )
    found["nearest_supplier"] = (
        lambda spark, sf_dir: apps.nearest_facility(prepared(spark, sf_dir, "customer_supplier"), [1, 3, 5]).select("v", "facility", F.col("dist").cast("long").alias("dist")),
        "SELECT v, CAST(facility AS BIGINT) AS facility, dist FROM (SELECT v, facility, dist, row_number() OVER (PARTITION BY v ORDER BY dist, facility) AS r FROM ("
        + " UNION ALL ".join(f"SELECT * FROM ({distances_sql('customer_supplier', s, f'SELECT CAST(v AS BIGINT) AS v, {s} AS facility, CAST(d AS BIGINT) AS dist FROM t')})" for s in (1, 3, 5))
        + ")) WHERE r = 1",
    )
    found["eccentricity"] = (
        lambda spark, sf_dir: apps.eccentricity(prepared(spark, sf_dir, "user_action"), [0, 1, 3]),
        " UNION ALL ".join(f"SELECT * FROM ({distances_sql('user_action', s, f'SELECT CAST({s} AS BIGINT) AS source, CAST(max(d) AS BIGINT) AS eccentricity, round(count(*) / CAST(sum(d) AS DOUBLE), 9) AS closeness FROM t')})" for s in (0, 1, 3)),
    )
    found["k_nearest"] = (
        lambda spark, sf_dir: apps.k_nearest(adaptive_sssp(g := prepared(spark, sf_dir, "customer_part"), hub(g)).state, 20).select("v", F.col("dist").cast("long").alias("dist")),
        distances_sql("customer_part", oracles.HUB, "SELECT CAST(v AS BIGINT) AS v, CAST(d AS BIGINT) AS dist FROM t ORDER BY d, v LIMIT 20"),
    )
    found["ego_network"] = (
        lambda spark, sf_dir: apps.ego_network(g := prepared(spark, sf_dir, "customer_part"), adaptive_sssp(g, hub(g)).state, 1_000_000),
        distances_sql("customer_part", oracles.HUB, "SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, w FROM e WHERE a IN (SELECT v FROM t WHERE d <= 1000000) AND b IN (SELECT v FROM t WHERE d <= 1000000)"),
    )
    found["path_to_target"] = (
        lambda spark, sf_dir: apps.path_lengths(g := prepared(spark, sf_dir, VARIED), adaptive_sssp(g, HUBS[VARIED]), [2442, 20, 33]),
        distances_sql(VARIED, HUBS[VARIED], "SELECT CAST(v AS BIGINT) AS target, CAST(d AS BIGINT) AS length FROM t WHERE v IN (2442, 20, 33)"),
    )
    found["dijkstra_components"] = (
        lambda spark, sf_dir: baselines.dijkstra_components(e := graphs.host_page(spark, sf_dir), apps.components(e), spark.createDataFrame([(hub(prepared(spark, sf_dir, "host_page")),)], "source long")).select("v", "dist"),
        distances_sql("host_page", oracles.HUB),
    )
    found["components_page_link"] = (
        lambda spark, sf_dir: apps.components(graphs.page_link(spark, sf_dir)),
        f"WITH RECURSIVE e AS MATERIALIZED ({EDGES['page_link']}), arc AS MATERIALIZED (SELECT a AS src, b AS dst FROM e UNION ALL SELECT b, a FROM e), t(v, c) USING KEY (v) AS (SELECT DISTINCT src, src FROM arc UNION SELECT n.v, n.c FROM (SELECT dst AS v, min(t.c) AS c FROM t JOIN arc ON src = t.v GROUP BY dst) n JOIN recurring.t r ON r.v = n.v WHERE n.c < r.c) SELECT v, c AS component FROM t",
    )
    # the evaluation; what depends on the algorithm's own course has no SQL
    found["exp_windows"] = (lambda spark, sf_dir: experiments.window_measures(spark, _graphs(spark, sf_dir, BASE)), None)
    found["exp_variants"] = (lambda spark, sf_dir: experiments.window_measures(spark, _graphs(spark, sf_dir, VARIANTS), 16), None)
    found["exp_beta"] = (lambda spark, sf_dir: experiments.beta_sweep(spark, _graphs(spark, sf_dir, SWEPT), count=16), None)
    found["exp_rivals"] = (_rivals, None)
    found["speedup_table"] = (lambda spark, sf_dir: experiments.speedup_table(_rivals(spark, sf_dir), {g: SECONDS.get(g, 0.0) for g in BASE}), None)
    found["agg_corr_time_traversals"] = (lambda spark, sf_dir: experiments.time_by_traversals(_rivals(spark, sf_dir)), None)
    found["exp_amortisation"] = (lambda spark, sf_dir: experiments.amortisation(spark, prepared(spark, sf_dir, "customer_part"), SECONDS.get("customer_part", 0.0)), None)
    found["window_claims"] = (lambda spark, sf_dir: audit.window_claims(adaptive_sssp(g := prepared(spark, sf_dir, "customer_part"), hub(g))), None)
    found["load_imbalance"] = (lambda spark, sf_dir: audit.load_imbalance(prepared(spark, sf_dir, "customer_part")), None)
    found["repeated_arcs"] = (lambda spark, sf_dir: audit.repeated_arcs(searched(spark, sf_dir, VARIED, HUBS[VARIED])), None)
    found["tune_delta"] = (lambda spark, sf_dir: baselines.tune_delta(g := prepared(spark, sf_dir, "customer_part"), hub(g)), None)
    found["validate_adaptive"] = (lambda spark, sf_dir: audit.validate(searched(spark, sf_dir, VARIED, HUBS[VARIED])), "SELECT CAST(0 AS BIGINT) AS v WHERE false")
    return found


_SEARCHED: dict[tuple[str, str, str, int], Result] = {}


def searched(spark: SparkSession, sf_dir: str, name: str, source: int) -> Result:
    """One adaptive search serves all audits of an application."""
    key = (spark.sparkContext.applicationId, sf_dir, name, source)
    if key not in _SEARCHED:
        _SEARCHED.clear()
        _SEARCHED[key] = adaptive_sssp(prepared(spark, sf_dir, name), source)
    return _SEARCHED[key]


def _distances(result: Result) -> DataFrame:
    return result.state.select("v", F.col("dist").cast("long").alias("dist"))


def _search(graph: str, source: int, method: Callable[[PreparedGraph, int], Result]) -> tuple[Query, str]:
    return (lambda spark, sf_dir: _distances(method(prepared(spark, sf_dir, graph), source))), distances_sql(graph, source)


METHODS: dict[str, Callable[[PreparedGraph, int], Result]] = {
    "bellman_ford": baselines.bellman_ford,
    "dijkstra_rounds": baselines.dijkstra_rounds,
    "delta_stepping": baselines.delta_stepping,
    "delta_fused": lambda g, s: baselines.delta_stepping(g, s, fused=True),
    "delta_adaptive_width": lambda g, s: baselines.delta_stepping(g, s, adaptive=True),
    "delta_star": baselines.delta_star_stepping,
    "rho_stepping": baselines.rho_stepping,
    "pruned_delta": baselines.pruned_delta_stepping,
    "sssp_push_only": push_only,
    "sssp_pull_semi": lambda g, s: adaptive_sssp(g, s, Config(pull="semi")),
    "sssp_pull_always": lambda g, s: adaptive_sssp(g, s, Config(pull="always")),
    "sssp_cut_all": lambda g, s: adaptive_sssp(g, s, Config(cut_mode="all")),
    "sssp_cut_cdf": lambda g, s: adaptive_sssp(g, s, Config(cut_mode="cdf")),
    "sssp_fixed_width": lambda g, s: adaptive_sssp(g, s, Config(width=max(1, int(g.wmax) // 10))),
    "sssp_fixed_thresholds": lambda g, s: windowed_sssp(g, s, [int(g.wmax) // 8, int(g.wmax) // 4, int(g.wmax) // 2]),
}


def _catalog() -> dict[str, tuple[Query, str | None]]:
    found: dict[str, tuple[Query, str | None]] = {}
    for name, source in HUBS.items():
        found[f"sssp_adaptive_{name}"] = _search(name, source, adaptive_sssp)
    for name, source in LOW.items():
        found[f"sssp_leaf_source_{name}"] = _search(name, source, adaptive_sssp)
    for name, method in METHODS.items():
        found[name] = _search(VARIED, HUBS[VARIED], method)

    base, source = "part_supplier_price", HUBS["part_supplier_price"]
    search = lambda spark, sf_dir: searched(spark, sf_dir, base, source)
    arc_tail = "d AS (SELECT v, d FROM t)"
    chain = lambda tail: oracles.search(EDGES[base], source, tail, more=f", {arc_tail}")

    found["bfs"] = (
        lambda spark, sf_dir: _distances(baselines.bfs(prepared(spark, sf_dir, base), source)),
        distances_sql(base, source).replace("AS w FROM lineitem", "* 0 + 1 AS w FROM lineitem"),
    )
    found["canonical_parents"] = (
        lambda spark, sf_dir: audit.canonical_parents(prepared(spark, sf_dir, base).arcs, search(spark, sf_dir).state, source),
        chain("SELECT CAST(dst AS BIGINT) AS v, CAST(min(src) AS BIGINT) AS parent FROM arc JOIN d x ON x.v = src JOIN d y ON y.v = dst WHERE x.d + w = y.d AND dst <> 197 GROUP BY dst"),
    )
    found["tight_edges"] = (
        lambda spark, sf_dir: audit.tight_arcs(prepared(spark, sf_dir, base).arcs, search(spark, sf_dir).state),
        chain("SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, w FROM arc JOIN d x ON x.v = src JOIN d y ON y.v = dst WHERE x.d + w = y.d"),
    )
    found["skippable_edges"] = (
        lambda spark, sf_dir: audit.skippable_edges(graphs.part_supplier_price(spark, sf_dir), search(spark, sf_dir).state),
        chain("SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, w FROM e JOIN d x ON x.v = a JOIN d y ON y.v = b WHERE x.d + w > y.d AND y.d + w > x.d"),
    )
    lo, hi, cut = 1_000_000, 1_500_000, 600_000
    classes = "CASE WHEN NOT (x.d + w >= {lo} AND x.d + w < {hi}) THEN 'not indexed' WHEN x.d >= {lo} THEN 'short' WHEN y.d >= {lo} THEN 'long' ELSE 'irrelevant' END".format(lo=lo, hi=hi)
    found["edge_classes_window"] = (
        lambda spark, sf_dir: audit.classify_edges(prepared(spark, sf_dir, base).arcs, search(spark, sf_dir).state, lo, hi).groupBy("class", "backward").agg(F.count("*").alias("n")),
        chain(f"SELECT class, class = 'short' AND yd < {lo} AS backward, count(*) AS n FROM (SELECT {classes} AS class, y.d AS yd FROM arc JOIN d x ON x.v = src JOIN d y ON y.v = dst) GROUP BY 1, 2"),
    )
    found["exact_traversals_window"] = (
        lambda spark, sf_dir: audit.exact_traversals(prepared(spark, sf_dir, base).arcs, search(spark, sf_dir).state, lo, hi, cut, None),
        chain(
            f"SELECT count(*) FILTER (x.d >= {cut} AND x.d < {lo} AND x.d + w >= {lo} AND x.d + w < {hi}) AS pushed, count(*) FILTER (x.d >= {lo} AND w < {hi} - {cut}) AS pulled, count(*) FILTER (x.d >= {cut} AND x.d < {lo} AND x.d + w >= {lo} AND x.d + w < {hi} AND y.d >= {lo}) AS long_arcs FROM arc JOIN d x ON x.v = src JOIN d y ON y.v = dst"
        ),
    )
    found["reach_within_budget"] = (lambda spark, sf_dir: audit_cast(apps.within(search(spark, sf_dir).state, 2_000_000)), distances_sql(base, source) + " WHERE d <= 2000000")
    found["distance_histogram"] = (
        lambda spark, sf_dir: apps.distance_histogram(search(spark, sf_dir).state, 500_000),
        distances_sql(base, source, "SELECT CAST(floor(d / 500000.0) AS BIGINT) AS bucket, count(*) AS n FROM t GROUP BY 1"),
    )
    found["open_degree_curve"] = (
        lambda spark, sf_dir: search(spark, sf_dir).state.groupBy(F.floor(F.col("dist") / 500_000).alias("bucket")).agg(F.sum("deg").alias("degree")),
        chain("SELECT CAST(floor(d.d / 500000.0) AS BIGINT) AS bucket, CAST(count(*) AS BIGINT) AS degree FROM d JOIN arc ON arc.src = d.v GROUP BY 1"),
    )
    found["point_to_point"] = (
        lambda spark, sf_dir: _distances(point_to_point(prepared(spark, sf_dir, base), source, 2442)).where("v = 2442"),
        distances_sql(base, source) + " WHERE v = 2442",
    )
    found["multi_source_sssp"] = (
        lambda spark, sf_dir: apps.multi_source(prepared(spark, sf_dir, "user_action"), [0, 1, 3]).select("source", "v", F.col("dist").cast("long").alias("dist")),
        " UNION ALL ".join(f"SELECT * FROM ({distances_sql('user_action', s, f'SELECT CAST({s} AS BIGINT) AS source, CAST(v AS BIGINT) AS v, CAST(d AS BIGINT) AS dist FROM t')})" for s in (0, 1, 3)),
    )
    profiled = "brick_wall_30_30"
    for name, sql in (EDGES | oracles.SYNTHETIC | {profiled: oracles.TABLED[profiled]}).items():
        build = TABLED[name] if name == profiled else BUILDERS[name]
        found[f"graph_profile_{name}"] = (
            lambda spark, sf_dir, build=build: audit.graph_profile(build(spark, sf_dir)),
            f"""WITH e AS ({sql}), g AS (SELECT v, count(*) AS deg FROM (SELECT a AS v FROM e UNION ALL SELECT b FROM e) GROUP BY v),
h AS (SELECT deg, count(*) AS cnt FROM g GROUP BY deg), r AS (SELECT deg, cnt, sum(deg * cnt) OVER () AS whole, coalesce(sum(deg * cnt) OVER (ORDER BY deg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM h),
b AS (SELECT deg AS balance FROM r ORDER BY abs(whole - 2 * below), deg LIMIT 1)
SELECT CAST(sum(cnt) AS BIGINT) AS n, CAST(sum(deg * cnt) // 2 AS BIGINT) AS m, CAST(max(deg) AS BIGINT) AS max_degree, CAST(max(balance) AS BIGINT) AS balance_degree,
round(log2(max(deg) / max(balance)), 6) AS degree_skew, round((sum(deg * cnt) / 2 - sum(cnt)) / (sum(deg * cnt) / 2), 6) AS skippable_bound FROM r, b""",
        )
    found["weight_quantiles_exact"] = (
        lambda spark, sf_dir: spark.createDataFrame(list(enumerate(int(v) for v in weight_quantiles(graphs.part_supplier_price(spark, sf_dir), 101, "exact").values)), "i int, w long"),
        f"WITH e AS ({EDGES[base]}), r AS (SELECT w, row_number() OVER (ORDER BY w) AS k, count(*) OVER () AS m FROM e) SELECT CAST(i AS INTEGER) AS i, (SELECT min(w) FROM r WHERE k * 100 >= i * m) AS w FROM range(0, 101) AS t(i)",
    )

    def first_width(spark, sf_dir):
        g = prepared(spark, sf_dir, base)
        c = choose_width(g.histogram, g.two_m, g.table)
        return spark.createDataFrame([(c.balance, c.open_sum, round(c.share, 9))], "balance long, open_sum long, share double")

    found["first_width"] = (
        first_width,
        f"""WITH e AS ({EDGES[base]}), g AS (SELECT v, count(*) AS deg FROM (SELECT a AS v FROM e UNION ALL SELECT b FROM e) GROUP BY v), h AS (SELECT deg, count(*) AS cnt FROM g GROUP BY deg),
r AS (SELECT deg, sum(deg * cnt) OVER () AS whole, coalesce(sum(deg * cnt) OVER (ORDER BY deg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM h),
b AS (SELECT deg AS balance, whole FROM r ORDER BY abs(whole - 2 * below), deg LIMIT 1)
SELECT balance, CAST(whole AS BIGINT) AS open_sum, round(1 - power(1 - 0.9, 1 / (0.9 * balance)), 9) AS share FROM b""",
    )

    def estimates(spark, sf_dir):
        g = prepared(spark, sf_dir, base)
        x = [200_000.0, 600_000.0, 900_000.0]
        t = estimate_traversals(x, [90_000.0, 80_000.0, 70_000.0], 1e6, 1.5e6, 60_000.0, g.two_m, g.table)
        return spark.createDataFrame([(a, *(round(float(v), 3) for v in row)) for a, row in zip(x, zip(t.pushed, t.pulled, t.long, strict=True), strict=True)], "x double, pushed double, pulled double, long_arcs double")

    found["cut_estimates"] = (
        estimates,
        f"""WITH e AS ({EDGES[base]}), s AS (SELECT CAST(max(w) AS DOUBLE) AS wmax, 2.0 * count(*) AS two_m FROM e), p AS (SELECT CAST(x AS DOUBLE) AS x, CAST(dx AS DOUBLE) AS dx FROM (VALUES (200000, 90000), (600000, 80000), (900000, 70000)) AS t(x, dx))
SELECT x, round(500000 * (dx - 60000) / wmax, 3) AS pushed, round((1500000 - x) * 60000 / wmax, 3) AS pulled, round((1500000 - x) * 60000 / wmax * (dx - 60000) / two_m, 3) AS long_arcs FROM p, s""",
    )
    found["n_measures"] = (lambda spark, sf_dir: audit.measure_table(spark, {"adaptive": search(spark, sf_dir), "bellman_ford": baselines.bellman_ford(prepared(spark, sf_dir, base), source)}), None)
    found["trace_windows"] = (lambda spark, sf_dir: search(spark, sf_dir).trace(), None)
    found["skipped_edges"] = (lambda spark, sf_dir: audit.skipped_edges(search(spark, sf_dir)), None)
    found["components_user_action"] = (
        lambda spark, sf_dir: apps.components(graphs.user_action(spark, sf_dir)),
        f"WITH e AS ({EDGES['user_action']}) SELECT CAST(v AS BIGINT) AS v, CAST((SELECT min(a) FROM e) AS BIGINT) AS component FROM (SELECT a AS v FROM e UNION SELECT b FROM e)",
    )
    for mode in ("approx", "sketch", "sample"):
        found[f"weight_quantiles_{mode}"] = (lambda spark, sf_dir, mode=mode: spark.createDataFrame(list(enumerate(float(v) for v in weight_quantiles(graphs.part_supplier_price(spark, sf_dir), 101, mode).values)), "i int, w double"), None)
    found.update(_workloads())
    found.update(relational.CATALOG)
    found.update(udfs.CATALOG)
    found.update(events.QUERIES)
    return found


def audit_cast(frame: DataFrame) -> DataFrame:
    return frame.select("v", F.col("dist").cast("long").alias("dist"))


CATALOG = _catalog()


def queries() -> dict[str, Query]:
    return {name: q for name, (q, _) in CATALOG.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in CATALOG.items() if sql}


def entry(spark: SparkSession) -> DataFrame:
    """The flagship: adaptive windows on customers and parts."""
    graph = prepared(spark, "/root/testdata/sf0.001", "customer_part")
    return _distances(adaptive_sssp(graph, apps.random_sources(graph, 1)[0]))
