"""Undirected weighted graphs from the given tables: edges (a, b, w) with a < b, unique, least weight of parallels.

The vertices of a bipartite graph are ``2 * left`` and ``2 * right + 1``. Money weights are cents in BIGINT.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .tables import load


def canonical(edges: DataFrame) -> DataFrame:
    """Loops dropped, ends ordered, parallels reduced to their least weight; missing or negative weights and missing ends
    are refused."""
    bad = F.col("w").isNull() | (F.col("w") < 0) | F.isnan(F.col("w").cast("double")) | F.col("a").isNull() | F.col("b").isNull()
    checked = F.when(bad, F.raise_error(F.lit("an edge has a missing end or weight, or a negative weight"))).otherwise(F.col("w"))
    edges = edges.withColumn("w", checked)
    return edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "w").groupBy("a", "b").agg(F.min("w").alias("w"))


def symmetrize(edges: DataFrame) -> DataFrame:
    """Both arcs (src, dst, w) of each edge."""
    return edges.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w").union(edges.select("b", "a", "w"))


def bipartite(frame: DataFrame, left: str, right: str, w: Column) -> DataFrame:
    return frame.select((F.col(left) * 2).alias("a"), (F.col(right) * 2 + 1).alias("b"), w.alias("w")).groupBy("a", "b").agg(F.min("w").alias("w")).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "w")


def _cents(column: str) -> Column:
    return F.round(F.col(column) * 100).cast("long")


def part_supplier_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(load(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey", _cents("l_extendedprice"))


def part_supplier_qty(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(load(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey", F.col("l_quantity").cast("long"))


def _ordered(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return load(spark, sf_dir, "lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def customer_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(_ordered(spark, sf_dir), "o_custkey", "l_partkey", _cents("l_extendedprice"))


def customer_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(_ordered(spark, sf_dir), "o_custkey", "l_suppkey", _cents("l_extendedprice"))


def user_action(spark: SparkSession, sf_dir: str) -> DataFrame:
    kinds = F.array(*(F.lit(k) for k in ("click", "error", "purchase", "signup", "view")))
    events = load(spark, sf_dir, "events").withColumn("kind", F.array_position(kinds, F.col("event_type")) - 1)
    return bipartite(events.where("kind >= 0"), "user_id", "kind", _cents("value"))


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Region, nation, customer and supplier as a tree; id * 4 + kind."""
    t = lambda name: load(spark, sf_dir, name)
    parts = [
        t("nation").select((F.col("n_regionkey") * 4).cast("long").alias("a"), (F.col("n_nationkey") * 4 + 1).cast("long").alias("b"), F.lit(1).cast("long").alias("w")),
        t("customer").select((F.col("c_nationkey") * 4 + 1).cast("long"), F.col("c_custkey") * 4 + 2, F.lit(1).cast("long")),
        t("supplier").select((F.col("s_nationkey") * 4 + 1).cast("long"), F.col("s_suppkey") * 4 + 3, F.lit(1).cast("long")),
    ]
    return canonical(parts[0].union(parts[1]).union(parts[2]))


def event_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event with the next one of all, and the next one of its user; weight: seconds between. High diameter."""
    e = load(spark, sf_dir, "events").select("event_id", "user_id", F.unix_timestamp("ts").alias("s"))
    # buckets of time keep the global order out of one task: the next event of all is the next id (ids follow time)
    nxt = e.select((F.col("event_id") - 1).alias("event_id"), F.col("event_id").alias("b"), F.col("s").alias("t"))
    of_all = e.join(nxt, "event_id").select(F.col("event_id").alias("a"), "b", F.abs(F.col("t") - F.col("s")).alias("w"))
    own = Window.partitionBy("user_id").orderBy("s", "event_id")
    of_user = e.select(F.col("event_id").alias("a"), F.lead("event_id").over(own).alias("b"), (F.lead("s").over(own) - F.col("s")).alias("w")).where("b is not null")
    return canonical(of_all.union(of_user))


def name_id(*names: Column) -> Column:
    """An id of 60 bits for a name: the head of its MD5. ``name_clashes`` tells whether names share one."""
    return F.conv(F.substring(F.md5(F.concat(*names)), 1, 15), 16, 10).cast("long")


def name_clashes(names: DataFrame, name: str) -> DataFrame:
    """(id, first, last) of ids that more than one name has; no rows as long as ids may stand for names."""
    told = names.select(F.col(name).alias("name")).groupBy(name_id(F.col("name")).alias("id")).agg(F.min("name").alias("first"), F.max("name").alias("last"))
    return told.where("first <> last")


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the targets of their links, unit weights."""
    pages = load(spark, sf_dir, "pages")
    found = pages.select("url", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)")).alias("target"))
    return canonical(found.select(name_id(F.col("url")).alias("a"), name_id(F.col("target")).alias("b"), F.lit(1).cast("long").alias("w")).where("a is not null and b is not null"))


def host_page(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A star for each host."""
    pages = load(spark, sf_dir, "pages").where("url is not null")
    return canonical(pages.select(name_id(F.lit("host "), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).alias("a"), name_id(F.col("url")).alias("b"), F.lit(1).cast("long").alias("w")))


def _word_graph(frame: DataFrame, key: str) -> DataFrame:
    words = frame.select(F.col(key).alias("k"), F.explode(F.expr("regexp_extract_all(lower(text), '(\\\\p{L}+)', 1)")).alias("word")).where("k is not null")
    counts = words.groupBy("k", "word").agg(F.count("*").alias("c"))
    return canonical(counts.select((F.col("k") * 2).alias("a"), (name_id(F.col("word")) * 2 + 1).alias("b"), F.floor(F.lit(1000000) / F.col("c")).cast("long").alias("w")))


def doc_word(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and their words; weight: a million over the count. Skewed."""
    return _word_graph(load(spark, sf_dir, "documents"), "doc_id")


def turn_word(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _word_graph(load(spark, sf_dir, "conversations"), "conv_id")


ASKING, STORED = 4_096, 16_384  # vectors of a label that meet in one task


def _nearest(table: pa.Table, k: int, margin: float = 1.5e-6) -> pa.Table:
    """(a, b, far) of one block: for each asking vector at least those of its k nearest stored ones under any rounding to
    millionths with ties by id. Products of matrices propose; lengths are then summed component by component."""
    ids = table.column("vec_id").to_numpy()
    stored = table.column("stored").to_numpy()
    x = table.column("e").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
    at, asks = np.flatnonzero(stored), np.flatnonzero(~stored)
    y, norms = x[at], (x * x).sum(1)
    found = []
    for lo in range(0, len(asks) if len(at) else 0, 256):
        own = asks[lo : lo + 256]
        square = norms[own][:, None] + norms[at][None, :] - 2 * (x[own] @ y.T)
        blur = 1e-12 * (norms[own] + norms[at].max())
        square[ids[own][:, None] == ids[at][None, :]] = np.inf
        kth = np.partition(square, min(k, len(at)) - 1, axis=1)[:, min(k, len(at)) - 1]
        limit = (np.sqrt(np.maximum(kth, 0) + blur) + margin) ** 2 + blur
        i, j = np.nonzero((square <= limit[:, None]) & np.isfinite(square))
        total = np.zeros(len(i))
        for c in range(x.shape[1]):
            total += (x[own[i], c] - y[j, c]) ** 2
        far, b = np.sqrt(total), ids[at[j]]
        # of equal lengths only the k least ids can be asked for
        order = np.lexsort([b, far, i])
        i, b, far = i[order], b[order], far[order]
        new = np.concatenate([[True], (i[1:] != i[:-1]) | (far[1:] != far[:-1])]) if len(i) else np.zeros(0, bool)
        rank = np.arange(len(i)) - np.maximum.accumulate(np.where(new, np.arange(len(i)), 0))
        found.append((ids[own[i]][rank < k], b[rank < k], far[rank < k]))
    a, b, far = (np.concatenate(c) for c in zip(*found, strict=True)) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
    return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "far": pa.array(far, pa.float64())})


def nearest_candidates(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """(a, b, far): each vector's nearest of its label by L2 distance, the k nearest and perhaps some more. Every vector
    meets all of its label, in blocks, so that a label of any size is many tasks. Vectors are of one length, without gaps."""
    v = load(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), "label", F.col("embedding").cast("array<double>").alias("e")).where("label is not null and embedding is not null")
    sized = v.join(v.groupBy("label").agg(F.ceil(F.count("*") / ASKING).cast("int").alias("qs"), F.ceil(F.count("*") / STORED).cast("int").alias("ss")), "label")
    of = lambda n: F.pmod(F.xxhash64("vec_id"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    asking = sized.select("label", of("qs").alias("q"), every("ss").alias("s"), "vec_id", "e", F.lit(False).alias("stored"))
    stored = sized.select("label", every("qs").alias("q"), of("ss").alias("s"), "vec_id", "e", F.lit(True).alias("stored"))
    return asking.union(stored).groupBy("label", "q", "s").applyInArrow(lambda table: _nearest(table, k), "a long, b long, far double")


def knn_vectors(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """Each vector's k nearest of its label by L2 distance, in millionths."""
    near = nearest_candidates(spark, sf_dir, k).select("a", "b", F.round(F.col("far") * 1000000).cast("long").alias("w"))
    ranked = near.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy("w", "b"))).where(F.col("r") <= k)
    return canonical(ranked.select("a", "b", "w"))


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (part_supplier_price, part_supplier_qty, customer_part, customer_supplier, user_action, geo_tree, event_chain, page_link, host_page, doc_word, turn_word, knn_vectors)
}
