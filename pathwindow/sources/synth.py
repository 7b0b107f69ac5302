"""Generated graphs. All draw from hashes of row numbers, so partitioning never changes a graph."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .graphs import canonical
from .tables import load

# Quadrant probabilities of the recursive generator.
QUADRANTS = (0.57, 0.19, 0.19, 0.05)


def unit_hash(*columns: Column) -> Column:
    """A number in [0, 1): the first 40 bits of the MD5 of the columns as text, so that any SQL engine can draw the same."""
    return F.conv(F.substring(F.md5(F.concat_ws(",", *columns)), 1, 10), 16, 10).cast("long") / F.lit(float(1 << 40))


def weights_from_hash(edges: DataFrame, seed: int = 1) -> DataFrame:
    """Weights in (0, 1], by ends and seed."""
    return edges.withColumn("w", 1 - unit_hash(F.lit("w"), F.lit(seed), F.least("a", "b"), F.greatest("a", "b")))


def draws(spark: SparkSession, sf_dir: str, table: str, key: str, each: int) -> DataFrame:
    """Numbers (id) to draw from, ``each`` of them for a row of a table."""
    keys = load(spark, sf_dir, table).select(F.col(key).alias("k")).repartition(spark.sparkContext.defaultParallelism)
    return keys.select("k", F.explode(F.sequence(F.lit(0), F.lit(each - 1))).alias("i")).select((F.col("k") * each + F.col("i")).cast("long").alias("id"))


def kron(spark: SparkSession, scale: int, edge_factor: int, seed: int = 1, ids: DataFrame | None = None) -> DataFrame:
    """Recursive-matrix graph of 2^scale possible vertices: one quadrant draw for each bit of both ends. ``ids``: the numbers
    to draw from, row numbers by default."""
    a, b = F.lit(0).cast("long"), F.lit(0).cast("long")
    p, q, r, _ = QUADRANTS
    for bit in range(scale):
        u = F.col(f"u{bit}")
        down = (u >= p + q).cast("long")
        right = (((u >= p) & (u < p + q)) | (u >= p + q + r)).cast("long")
        a, b = a * 2 + down, b * 2 + right
    ids = spark.range(edge_factor << scale) if ids is None else ids
    drawn = ids.select(*(unit_hash(F.lit(seed), F.lit(bit), F.col("id")).alias(f"u{bit}") for bit in range(scale)))  # each once
    return canonical(weights_from_hash(drawn.select(a.alias("a"), b.alias("b")), seed))


def unif(spark: SparkSession, scale: int, edge_factor: int, seed: int = 1, ids: DataFrame | None = None) -> DataFrame:
    """Both ends uniform."""
    end = lambda salt: F.floor(unit_hash(F.lit(salt), F.lit(seed), F.col("id")) * (1 << scale)).cast("long")
    return canonical(weights_from_hash((spark.range(edge_factor << scale) if ids is None else ids).select(end("a").alias("a"), end("b").alias("b")), seed))


def lattice(spark: SparkSession, rows: int, columns: int, seed: int = 1, brick: bool = False) -> DataFrame:
    """A grid; as a brick wall every other vertical edge is missing, so degrees are three at most."""
    cell = spark.range(rows * columns).select("id", F.floor(F.col("id") / columns).alias("r"), (F.col("id") % columns).alias("c"))
    right = cell.where(F.col("c") < columns - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    down = cell.where((F.col("r") < rows - 1) & (((F.col("r") + F.col("c")) % 2 == 0) if brick else F.lit(True))).select("id", F.col("id") + columns)
    return canonical(weights_from_hash(right.union(down), seed))


def star(spark: SparkSession, leaves: int) -> DataFrame:
    return canonical(weights_from_hash(spark.range(1, leaves + 1).select(F.lit(0).cast("long").alias("a"), F.col("id").alias("b"))))


def path(spark: SparkSession, length: int) -> DataFrame:
    return canonical(weights_from_hash(spark.range(length).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))))


def _steps(cell: DataFrame, by: int) -> DataFrame:
    """(a, b) of the cells whose number plus ``by`` is there too."""
    return cell.join(cell.select((F.col("id") - by).alias("id")), "id").select(F.col("id").alias("a"), (F.col("id") + by).alias("b"))


def table_lattice(spark: SparkSession, sf_dir: str, columns: int, brick: bool = False) -> DataFrame:
    """The grid of the parts, row by row in the order of their keys; edges lead to the parts that are there."""
    cell = load(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("id"))
    right = _steps(cell, 1).where(F.col("a") % columns < columns - 1)
    down = _steps(cell, columns)
    odd = (F.floor(F.col("a") / columns) + F.col("a") % columns) % 2 == 0
    return canonical(weights_from_hash(right.union(down.where(odd) if brick else down)))


def table_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A star whose leaves are the customers."""
    return canonical(weights_from_hash(load(spark, sf_dir, "customer").select(F.lit(0).cast("long").alias("a"), F.col("c_custkey").cast("long").alias("b"))))


def table_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events in the order of their ids, a path wherever the next id is there."""
    return canonical(weights_from_hash(_steps(load(spark, sf_dir, "events").select(F.col("event_id").cast("long").alias("id")), 1)))
