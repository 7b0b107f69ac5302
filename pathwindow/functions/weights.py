"""Weight variants and distances as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def discretize(w: Column, power: int) -> Column:
    """An integer of 1 .. 2^power - 1 from a weight in [0, 1], rounding half up."""
    return F.floor(1 + w * (2**power - 2) + 0.5).cast("long")


def converge(w: Column, pivot: float) -> Column:
    """A weight drawn towards the pivot: half of uniform weights stay below it."""
    pull = (1 - 2 * w) * (1 - 2 * w)
    return F.when(w <= 0.5, pivot - pivot * pull).otherwise(pivot + (1 - pivot) * pull)


def rescaled(edges: DataFrame) -> DataFrame:
    """Weights over their maximum, in (0, 1]."""
    top = edges.agg(F.max("w").alias("top"))
    return edges.join(F.broadcast(top)).select("a", "b", (F.col("w") / F.col("top")).alias("w"))


def bucket_of(dist: Column, delta: float) -> Column:
    return F.floor(dist / F.lit(delta))


def edge_class(du: Column, dv: Column, w: Column, lo, hi) -> Column:
    """Class of an arc for a window, by final distances of its ends."""
    length = du + w
    indexed = (length >= lo) & (length < hi)
    return F.when(~F.coalesce(indexed, F.lit(False)), "not indexed").when(du >= lo, "short").when(dv >= lo, "long").otherwise("irrelevant")


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
