"""What users ask of shortest paths: paths, reach, nearest facilities, components, many sources."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.engine import Config, Result, adaptive_all, adaptive_sssp
from ..plans.prepared import PreparedGraph, ensure_checkpoint_dir, fixed_plans
from ..plans.rounds import FRESH, Search
from .audit import tight_arcs


def random_sources(graph: PreparedGraph, count: int = 64, seed: int = 42) -> list[int]:
    """Vertices of non-zero degree in the order of a seeded hash."""
    rows = graph.vertices.select("v").orderBy(F.xxhash64(F.lit(seed), "v"), "v").limit(count).collect()
    return [r["v"] for r in rows]


def multi_source(graph: PreparedGraph, sources: list[int], cfg: Config = Config()) -> DataFrame:
    """(source, v, dist): searches on the shared preprocessing; tasks of one job where the graph fits a task."""
    found = adaptive_all(graph, sources, cfg)
    return reduce(DataFrame.union, (found[s].state.select(F.lit(s).cast("long").alias("source"), "v", "dist") for s in dict.fromkeys(sources)))


def nearest_facility(graph: PreparedGraph, facilities: list[int], cfg: Config = Config()) -> DataFrame:
    """(v, facility, dist): the nearest of a few facilities, the least id on ties."""
    return multi_source(graph, facilities, cfg).groupBy("v").agg(F.min(F.struct("dist", "source")).alias("best")).select("v", F.col("best.source").alias("facility"), F.col("best.dist").alias("dist"))


def extract_paths(parents: DataFrame, targets: DataFrame, source: int) -> DataFrame:
    """(target, path): vertices from the source to each target, by one join a hop for as long as paths go on."""
    spark = parents.sparkSession
    ensure_checkpoint_dir(spark)
    step = parents.select(F.col("v").alias("__v"), F.col("parent").alias("__parent"))
    walk = targets.select("target", F.col("target").alias("at"), F.array("target").alias("path"))
    while walk.where(F.col("at") != source).limit(1).count():
        walk = walk.join(step, F.col("at") == F.col("__v"), "left").where((F.col("at") == source) | F.col("__parent").isNotNull()).select(
            "target",
            F.when(F.col("at") == source, F.col("at")).otherwise(F.col("__parent")).alias("at"),
            F.when(F.col("at") == source, F.col("path")).otherwise(F.concat(F.array("__parent"), "path")).alias("path"),
        ).checkpoint()
    return walk.select("target", "path")


def within(state: DataFrame, budget) -> DataFrame:
    return state.where(F.col("dist") <= budget).select("v", "dist")


def distance_histogram(state: DataFrame, step) -> DataFrame:
    return state.groupBy(F.floor(F.col("dist") / step).alias("bucket")).agg(F.count("*").alias("n")).orderBy("bucket")


def components(edges: DataFrame) -> DataFrame:
    """(v, component) by least label, with pointer jumping so that rounds grow with the logarithm of the diameter."""
    spark = edges.sparkSession
    ensure_checkpoint_dir(spark)
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select("b", "a")).checkpoint()
    label = both.select("u").distinct().select(F.col("u").alias("v"), F.col("u").alias("c")).checkpoint()
    while True:
        around = both.join(label, "v").groupBy("u").agg(F.min("c").alias("m"))
        low = label.join(around, F.col("v") == F.col("u")).select("v", F.least("c", "m").alias("c"), F.col("c").alias("old"))
        of = low.select(F.col("v").alias("c"), F.col("c").alias("up"))
        jumped = low.join(of, "c", "left").select("v", F.least("c", F.coalesce("up", "c")).alias("c"), "old").checkpoint()
        if not jumped.where("c <> old").limit(1).count():
            return jumped.select("v", F.col("c").alias("component"))
        label = jumped.select("v", "c")


def fewest_hops(graph: PreparedGraph, found: Result) -> DataFrame:
    """(v, hops): the fewest hops among the shortest paths to each reached vertex, of a graph of any size.

    The search's own hops belong to some shortest path each, so they only have to come down along tight arcs."""
    spark = graph.arcs.sparkSession
    ensure_checkpoint_dir(spark)
    tight = tight_arcs(graph.arcs, found.state).select("src", "dst").checkpoint()
    label = found.state.select("v", "hops").checkpoint()
    while True:
        offers = tight.join(label, F.col("src") == F.col("v")).groupBy("dst").agg(F.min(F.col("hops") + 1).alias("offer"))
        label = label.drop("fewer").join(offers, F.col("v") == F.col("dst"), "left").select("v", F.least("hops", "offer").alias("hops"), (F.col("offer") < F.col("hops")).alias("fewer")).checkpoint()
        if label.where("fewer").isEmpty():
            return label.select("v", "hops")


def hop_stats(graph: PreparedGraph, source: int) -> DataFrame:
    """(reached, hops, most): the fewest hops of shortest paths, summed and at most."""
    hops = fewest_hops(graph, adaptive_sssp(graph, source)).select(F.col("hops").cast("long").alias("hops"))
    return hops.agg(F.count("*").alias("reached"), F.sum("hops").alias("hops"), F.max("hops").alias("most"))


def eccentricity(graph: PreparedGraph, sources: list[int], cfg: Config = Config()) -> DataFrame:
    """(source, eccentricity, closeness): the largest distance, and reached vertices over the sum of distances."""
    return multi_source(graph, sources, cfg).groupBy("source").agg(F.max("dist").cast("long").alias("eccentricity"), F.round(F.count("*") / F.sum("dist"), 9).alias("closeness"))


def k_nearest(state: DataFrame, k: int) -> DataFrame:
    """The k vertices nearest to the source, the least ids on ties."""
    return state.select("v", "dist").orderBy("dist", "v").limit(k)


def ego_network(graph: PreparedGraph, state: DataFrame, radius) -> DataFrame:
    """The edges (a, b, w) between vertices within a distance of the source."""
    near = within(state, radius).select("v")
    edges = graph.arcs.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"), "w")
    return edges.join(near.withColumnRenamed("v", "a"), "a", "left_semi").join(near.withColumnRenamed("v", "b"), "b", "left_semi").select("a", "b", "w")


def path_lengths(graph: PreparedGraph, found: Result, targets: list[int]) -> DataFrame:
    """(target, length): the summed weights along the extracted path to each target."""
    asked = graph.arcs.sparkSession.createDataFrame([(t,) for t in targets], "target long")
    parents = found.state.where(F.col("v") != found.source).select("v", "parent")
    steps = extract_paths(parents, asked, found.source).select("target", F.explode(F.arrays_zip(F.col("path").alias("src"), F.slice("path", 2, F.size("path")).alias("dst"))).alias("s")).select("target", "s.src", "s.dst").where("dst is not null")
    return steps.join(graph.arcs, ["src", "dst"]).groupBy("target").agg(F.sum("w").cast("long").alias("length"))


def repair(graph: PreparedGraph, found: DataFrame, source: int, inserted: DataFrame) -> DataFrame:
    """(v, dist, hops, parent, deg) after edges (a, b, w) came in or became cheaper: only what they change is searched again.

    ``graph`` holds the new edges already. Rounds start from their ends with the distances that were known."""
    search = Search(graph, source, skip_parent=False, keep_leaves=True)
    ends = inserted.select(F.col("a").alias("v")).union(inserted.select("b")).distinct().withColumn("touched", F.lit(True))
    known = found.select("v", F.col("dist").alias("d"), F.col("hops").alias("h"), F.col("parent").alias("p"))
    with fixed_plans(graph.arcs.sparkSession, graph.parts):
        seeded = search.state.join(known, "v", "left").join(ends, "v", "left")
        pick = lambda old, new: F.coalesce(F.col(new), F.col(old)).alias(old)
        search.state = seeded.select("v", "deg", pick("dist", "d"), pick("hops", "h"), pick("parent", "p"), (F.col("touched").isNotNull() & F.coalesce("d", "dist").isNotNull()).alias("fresh")).repartition(graph.parts, "v").checkpoint()
        while search.last.fresh:
            search.push(FRESH)
    return search.state.where("dist is not null").select("v", "dist", "hops", "parent", "deg")
