"""Preprocessing that all searches on a graph share: clustered arcs, degrees, weight quantiles."""

from __future__ import annotations

import tempfile
from collections.abc import Callable
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.stepping import QuantileTable
from ..sources.graphs import symmetrize

QUANTILES = 4096
SAMPLE = 1_000_000
# Small graphs get fewer partitions than the session's number, so that a round is not all overhead.
ARCS_A_PART = 250_000
# Arcs in one adjacency row; a hub has several.
CHUNK = 512
# Graphs of at most this many arcs (8 bytes each, 12 with real weights) and vertices (about 100 bytes each) may be searched
# within single tasks, see plans.local.
LOCAL_ARCS, LOCAL_VERTICES = 80_000_000, 8_000_000
# Graphs of at most this many arcs may pass through the driver.
SENT_ARCS = 1_000_000
DRIVER_ARCS = 12_000_000


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Checkpoints go to the cluster's shared folder; a local session without one gets a folder of its own."""
    if spark.sparkContext.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))


@contextmanager
def settings(spark: SparkSession, wanted: dict[str, str]):
    """The session's settings changed inside, for plans that are made and run there."""
    before = {k: spark.conf.get(k, None) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


def fixed_plans(spark: SparkSession, parts: int | None = None):
    """No adaptive re-planning inside, and one number of partitions: only then a checkpoint's hash partitioning serves
    the next round's join."""
    wanted = {"spark.sql.adaptive.enabled": "false"}
    return settings(spark, wanted | ({"spark.sql.shuffle.partitions": str(parts)} if parts else {}))


@dataclass
class Facts:
    """What schedules need to know of a graph; small whatever its size."""

    n: int
    two_m: int
    histogram: dict[int, int]
    table: QuantileTable

    @property
    def wmax(self):
        return self.table.wmax


class Late:
    """A field that may be given as a function without arguments; it is called where the field is first read."""

    def __set_name__(self, owner, name: str) -> None:
        self.name = f"_{name}"

    def __get__(self, held, owner=None):
        if held is None:
            raise AttributeError(self.name)  # a field without a default
        value = held.__dict__[self.name]
        if not isinstance(value, DataFrame):
            value = held.__dict__[self.name] = value()
        return value

    def __set__(self, held, value) -> None:
        held.__dict__[self.name] = value


@dataclass
class PreparedGraph(Facts):
    arcs: DataFrame  # src, dst, w: clustered by src and sorted by (src, w)
    chunks: DataFrame = Late()  # only distributed rounds read it; src, wmin, wmax, adjacent: array of (w, dst) in the order of weight; clustered by src
    vertices: DataFrame  # v, deg: clustered by v
    parts: int
    local_arcs: int = LOCAL_ARCS
    cache: dict = field(default_factory=dict)


def running_sums(frame: DataFrame, order: str, value: str) -> DataFrame:
    """The frame with ``upto``, the sum of a value over all rows up to this one in an order that has no ties.

    Rows go to ranges of the order; sums run within a range, and the totals of the ranges before (a number a range, added
    up on the driver) come on top. The ranges are checkpointed, so that totals and rows agree.
    """
    ensure_checkpoint_dir(frame.sparkSession)
    # a single range stands for itself as its own partition
    ranged = frame.repartitionByRange(order).withColumn("__range", F.spark_partition_id()).checkpoint()
    totals = {r["__range"]: r["t"] for r in ranged.groupBy("__range").agg(F.sum(value).alias("t")).collect()}
    before, sums = 0, []
    for k in sorted(totals):
        sums += [F.lit(k), F.lit(before)]
        before += totals[k]
    base = F.element_at(F.create_map(*sums), F.col("__range")) if sums else F.lit(0)
    return ranged.withColumn("upto", F.sum(value).over(Window.partitionBy("__range").orderBy(order)) + base).drop("__range")


def weight_quantiles(edges: DataFrame, num: int = QUANTILES, mode: str = "exact", m: int | None = None) -> QuantileTable:
    """Weights at num equally spaced shares: the least weight that at least the share of edges stays at or below.

    Modes: exact (per-weight counts and their running sum over ranges of weights), approx (one percentile sketch), sketch
    (KLL) or sample (of about SAMPLE edges). Only speed depends on the table, but for its maximum, which is always exact,
    since look-back and stop tests rely on it.
    """
    told = edges.agg(F.count("*").alias("m"), F.max("w").alias("top")).first()
    m, top = told["m"], told["top"]
    if not m:
        return QuantileTable((0, 0))
    if mode == "sample" and m > SAMPLE:
        edges = edges.sample(SAMPLE / m, seed=42)
        m = edges.count()
    if mode == "sketch":
        shares = F.array(*(F.lit(i / (num - 1)) for i in range(num)))
        values = edges.select(F.col("w").cast("double").alias("w")).agg(F.kll_sketch_agg_double("w").alias("s")).select(F.kll_sketch_get_quantile_double("s", shares).alias("q")).first()["q"]
    elif mode == "approx":
        values = edges.agg(F.percentile_approx("w", [i / (num - 1) for i in range(num)], 10 * num)).first()[0]
    elif mode in ("exact", "sample"):
        ranked = running_sums(edges.groupBy("w").agg(F.count("*").alias("c")), "w", "c")
        # each share picks one of the distinct weights, so the driver gets num rows at most
        first = F.ceil((F.col("upto") - F.col("c")) * (num - 1) / F.lit(m)).cast("long")
        last = F.floor(F.col("upto") * (num - 1) / F.lit(m)).cast("long")
        spans = ranked.select("w", F.greatest(first, F.lit(0)).alias("i0"), last.alias("i1")).where("i0 <= i1").orderBy("w").collect()
        values = [None] * num
        for r in spans:
            for i in range(r["i0"], min(num - 1, r["i1"]) + 1):
                if values[i] is None:
                    values[i] = r["w"]
    else:
        raise ValueError(f"unknown mode of weight quantiles: {mode}")
    values = list(values)
    values[-1] = top
    return QuantileTable(tuple(values))


def local_quantiles(edges: DataFrame, num: int = QUANTILES) -> QuantileTable:
    """As the exact ``weight_quantiles``, on the driver: for edges that are few enough to be held there."""
    counts = edges.groupBy("w").agg(F.count("*").alias("c")).toArrow()
    w, c = (counts.column(name).to_numpy() for name in ("w", "c"))
    if not len(w):
        return QuantileTable((0, 0))
    order = np.argsort(w)
    w, upto = w[order], np.cumsum(c[order])
    at = np.searchsorted(upto * (num - 1), np.arange(num) * upto[-1])
    return QuantileTable(tuple(w[at].tolist()))


def check_edges(edges: DataFrame) -> int:
    """The number of edges; raises where an end or a weight is missing or a weight is negative or no number."""
    w = F.col("w").cast("double")
    told = edges.agg(F.count("*").alias("m"), F.count(F.when(F.col("a").isNull() | F.col("b").isNull() | w.isNull() | F.isnan(w) | (w < 0), 1)).alias("bad")).first()
    if told["bad"]:
        raise ValueError(f"{told['bad']} edges have a missing end or weight, or a weight that is negative or no number")
    return told["m"]


def adjacency(arcs: DataFrame, parts: int) -> DataFrame:
    """Adjacency rows of arcs that are clustered by src."""
    with fixed_plans(arcs.sparkSession, parts):
        number = F.floor((F.row_number().over(Window.partitionBy("src").orderBy("w", "dst")) - 1) / CHUNK)
        listed = arcs.withColumn("chunk", number).groupBy("src", "chunk").agg(F.array_sort(F.collect_list(F.struct("w", "dst"))).alias("adjacent"), F.min("w").alias("wmin"), F.max("w").alias("wmax"))
        return listed.select("src", "wmin", "wmax", "adjacent").sortWithinPartitions("src").checkpoint().persist(StorageLevel.MEMORY_AND_DISK)


def prepare(edges: DataFrame, num: int = QUANTILES, quantiles: str = "exact", local_arcs: int = LOCAL_ARCS) -> PreparedGraph:
    """One full shuffle of the arcs; later rounds never exchange them again.

    Arcs, adjacency chunks and vertices are checkpointed and kept in memory as far as it goes; a lost copy is read again.
    ``local_arcs``: graphs of at most so many arcs are searched within single tasks (0: never). Adjacency chunks are
    only built if something reads them, as distributed rounds do.
    """
    spark = edges.sparkSession
    ensure_checkpoint_dir(spark)
    kept = edges.checkpoint()
    m = check_edges(kept)
    parts = max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-2 * m // ARCS_A_PART)))
    small = 2 * m <= min(local_arcs, DRIVER_ARCS)
    with fixed_plans(spark, parts):
        arcs = symmetrize(kept).repartition(parts, "src").sortWithinPartitions("src", "w").checkpoint()

    with fixed_plans(spark, parts):
        vertices = arcs.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")).checkpoint()
        histogram = {r["deg"]: r["n"] for r in vertices.groupBy("deg").agg(F.count("*").alias("n")).collect()}
        two_m = sum(d * n for d, n in histogram.items())
        table = local_quantiles(kept, num) if small and quantiles == "exact" else weight_quantiles(kept, num, quantiles)
    return PreparedGraph(sum(histogram.values()), two_m, histogram, table, arcs, lambda: adjacency(arcs, parts), vertices, parts, local_arcs)


def reweighted(graph: PreparedGraph, weight: Callable[[Column], Column]) -> PreparedGraph:
    """The graph with other weights, which never fall where the old ones rise: the arcs stay where and in the order they are,
    and a quantile of the new weights is the new weight of the old quantile."""
    spark = graph.arcs.sparkSession
    arcs = graph.arcs.select("src", "dst", weight(F.col("w")).alias("w"))
    kind = dict(graph.arcs.dtypes)["w"]
    told = spark.createDataFrame(list(enumerate(graph.table.values)), f"i int, w {kind}").select("i", weight(F.col("w")).alias("w")).orderBy("i").collect()
    table = QuantileTable(tuple(r["w"] for r in told))
    return PreparedGraph(graph.n, graph.two_m, graph.histogram, table, arcs, lambda: adjacency(arcs, graph.parts), graph.vertices, graph.parts, graph.local_arcs)
