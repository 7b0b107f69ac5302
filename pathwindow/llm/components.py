"""Connected components of link tables by alternating star contraction, on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Written

MAX_ROUNDS = 60


def _stars(edges: DataFrame) -> DataFrame:
    """Each node of (u, v) rows with the least of itself and its neighbours."""
    return edges.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))


def _large(edges: DataFrame) -> DataFrame:
    """Link every neighbour above a node to the least node around it."""
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return both.join(_stars(both), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small(edges: DataFrame) -> DataFrame:
    """Link a node and all its neighbours below it to the least of those."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def components(links: DataFrame) -> DataFrame:
    """(node, component) for every node of a link table (u, v), the component being its least node.

    Rounds grow with the logarithm of a component's size. Each round is a written table, so a lost executor costs that
    round at most; sums are taken before shuffles, and joins on a star's centre may be split by AQE. No links: no rows.
    """
    now = Written(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct(), "links")
    mark = None
    for _ in range(MAX_ROUNDS):
        told = now.frame.agg(F.count("*").alias("n"), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40))).alias("h")).first()
        if told["n"] == 0 or (told["n"], told["h"]) == mark:
            break
        mark = (told["n"], told["h"])
        after = Written(_small(_large(now.frame)), "links")
        now.drop()
        now = after
    else:
        raise RuntimeError("components did not settle")
    return now.frame.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.frame.select(F.col("v"), F.col("v")).distinct())
