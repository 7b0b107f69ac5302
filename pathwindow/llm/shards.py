"""Dealing out searches: a shard with too many rows becomes a grid of block pairs, so that no task grows with it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SHARD_ROWS = 40_000


def deal(spread: DataFrame, rows: int = SHARD_ROWS) -> DataFrame:
    """Rows (shard, node, home, ...) with block_a, block_b, stored and asking.

    A row is stored in its home shard and asks in every shard that it came to. A shard of n rows gets g = ceil(n / rows)
    blocks and g * g tasks (shard, a, b): the stored rows of block a meet the asking rows of block b. Every pair of a
    stored and an asking row still meets exactly once, and no task holds more than about two blocks.
    """
    sizes = spread.groupBy("shard").agg(F.count("*").alias("n")).where(F.col("n") > rows).select("shard", F.ceil(F.col("n") / rows).cast("int").alias("g"))
    sized = spread.join(sizes, "shard", "left").withColumn("g", F.coalesce("g", F.lit(1)))
    own = F.pmod(F.xxhash64("node"), F.col("g")).cast("int")
    cells = F.explode(F.expr("sequence(0, g - 1)"))
    as_asking = sized.withColumn("block_b", own).withColumn("block_a", cells).withColumn("stored", F.col("home") & (F.col("block_a") == F.col("block_b"))).withColumn("asking", F.lit(True))
    as_stored = sized.where("home and g > 1").withColumn("block_a", own).withColumn("block_b", cells).where("block_a <> block_b").withColumn("stored", F.lit(True)).withColumn("asking", F.lit(False))
    return as_asking.unionByName(as_stored).drop("g", "home")


TASK = ("shard", "block_a", "block_b")
