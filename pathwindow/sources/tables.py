"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "a long, b long, w double"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, separator: str = " ") -> tuple[DataFrame, DataFrame]:
    """(edges, rejects) of lines ``a b w``; lines that don't parse or have a negative weight are rejected, not dropped."""
    parts = F.split("value", separator)
    told = spark.read.text(path).select("value", *(F.expr(f"try_cast(get(split(value, '{separator}'), {i}) AS {kind})").alias(c) for i, (c, kind) in enumerate((("a", "bigint"), ("b", "bigint"), ("w", "double")))), F.size(parts).alias("fields"))
    good = F.coalesce((F.col("fields") == 3) & F.col("a").isNotNull() & F.col("b").isNotNull() & (F.col("w") >= 0), F.lit(False))
    return told.where(good).select("a", "b", "w"), told.where(~good).select("value")


def write_edge_list(edges: DataFrame, path: str) -> None:
    edges.select(F.concat_ws(" ", "a", "b", "w").alias("value")).write.mode("overwrite").text(path)


def read_any(spark: SparkSession, path: str, form: str, schema: str) -> DataFrame:
    """Parquet, ORC, CSV (with a header) or JSON under an explicit schema."""
    reader = spark.read.schema(schema)
    return reader.csv(path, header=True) if form == "csv" else reader.format(form).load(path)


def write_bucketed(arcs: DataFrame, table: str, buckets: int = 8, path: str | None = None) -> None:
    """Arcs as a table bucketed by source and sorted by weight, so that joins on the source need no exchange."""
    writer = arcs.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "w")
    (writer.option("path", path) if path else writer).saveAsTable(table)


def write_adjacency(arcs: DataFrame, path: str) -> None:
    """One line of JSON for each vertex: its id and its arcs in the order of weight."""
    arcs.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("w", "dst"))).alias("arcs")).write.mode("overwrite").json(path)


def read_adjacency(spark: SparkSession, path: str, kind: str = "double") -> DataFrame:
    lists = spark.read.schema(f"src long, arcs array<struct<w:{kind},dst:bigint>>").json(path)
    return lists.select("src", F.explode("arcs").alias("arc")).select("src", "arc.dst", "arc.w")


def read_jdbc(spark: SparkSession, url: str, table: str, **options: str) -> DataFrame:
    """A table of a database; options as Spark's reader has them (partitionColumn, lowerBound, numPartitions...)."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, **options).load()


def read_kafka(spark: SparkSession, servers: str, topic: str, **options: str) -> DataFrame:
    """A stream of a topic's messages; it needs the connector's package on the cluster."""
    return spark.readStream.format("kafka").options(**{"kafka.bootstrap.servers": servers, "subscribe": topic}, **options).load()


def write_state(state: DataFrame, path: str) -> None:
    """A path state partitioned by its window of settlement where it has one."""
    writer = state.write.mode("overwrite")
    (writer.partitionBy("window") if "window" in state.columns else writer).parquet(path)
