"""Python functions of every kind, for what users write themselves; the library's own paths stay with native columns.
Also k nearest vectors, and tables written and read back in every format."""

from __future__ import annotations

import heapq
import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udf, udtf

from ..oracles import EDGES, search
from ..plans.prepared import ensure_checkpoint_dir
from ..sources import graphs, tables
from ..sources.tables import load

CATALOG: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}
SMALL = 1_000_000  # edges that the SQL table function takes


def entry(sql: str | None):
    def add(f):
        CATALOG[f.__name__] = (f, sql)
        return f

    return add


def _converge(w: float | None, pivot: float) -> float | None:
    if w is None:
        return None
    pull = (1 - 2 * w) * (1 - 2 * w)
    return pivot - pivot * pull if w <= 0.5 else pivot + (1 - pivot) * pull


@entry("SELECT l_orderkey, l_linenumber, round(CASE WHEN l_discount * 10 <= 0.5 THEN CAST(0.3 AS DOUBLE) - CAST(0.3 AS DOUBLE) * ((1 - 2 * (l_discount * 10)) * (1 - 2 * (l_discount * 10))) ELSE CAST(0.3 AS DOUBLE) + (1 - CAST(0.3 AS DOUBLE)) * ((1 - 2 * (l_discount * 10)) * (1 - 2 * (l_discount * 10))) END, 6) AS w FROM lineitem")
def udf_scalar_converge(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.round(udf(_converge, "double")(F.col("l_discount") * 10, F.lit(0.3)), 6).alias("w"))


@entry("SELECT x.vec_id, round(list_distance(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])), 6) AS far FROM embeddings x JOIN embeddings y ON y.vec_id = x.vec_id + 1")
def udf_pandas_l2(spark, sf_dir):
    import numpy as np

    @pandas_udf("double")
    def far(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(np.sqrt(((np.asarray(x, float) - np.asarray(y, float)) ** 2).sum())) for x, y in zip(a, b, strict=True)])

    v = load(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    following = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    return v.join(following, "vec_id").select("vec_id", F.round(far("embedding", "other"), 6).alias("far"))


_SIDES = "SELECT 'part' AS side, deg, count(*) AS cnt FROM (SELECT l_partkey, count(*) AS deg FROM lineitem GROUP BY 1) GROUP BY 2 UNION ALL SELECT 'supplier', deg, count(*) FROM (SELECT l_suppkey, count(*) AS deg FROM lineitem GROUP BY 1) GROUP BY 2"


@entry(
    f"WITH h AS ({_SIDES}), r AS (SELECT side, deg, sum(deg * cnt) OVER (PARTITION BY side) AS whole, coalesce(sum(deg * cnt) OVER (PARTITION BY side ORDER BY deg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM h),"
    " k AS (SELECT side, deg, row_number() OVER (PARTITION BY side ORDER BY abs(whole - 2 * below), deg) AS n FROM r) SELECT side, CAST(deg AS BIGINT) AS balance FROM k WHERE n = 1"
)
def udaf_balance_degree(spark, sf_dir):
    """The balance degree of both sides' line counts, aggregated over their histograms (one row a degree)."""
    from ..functions.stepping import balance_degree

    @pandas_udf("long")
    def balance(deg: pd.Series, cnt: pd.Series) -> int:
        return int(balance_degree(dict(zip(deg.tolist(), cnt.tolist(), strict=True))))

    lines = load(spark, sf_dir, "lineitem")
    sides = [lines.groupBy(key).agg(F.count("*").alias("deg")).groupBy("deg").agg(F.count("*").alias("cnt")).withColumn("side", F.lit(side)) for side, key in (("part", "l_partkey"), ("supplier", "l_suppkey"))]
    return sides[0].unionByName(sides[1]).groupBy("side").agg(balance("deg", "cnt").alias("balance"))


@udtf(returnType="a long, b long")
class LatticeEdges:
    """The edges of a grid, row by row."""

    def eval(self, rows: int, columns: int):
        for r in range(rows):
            for c in range(columns):
                at = r * columns + c
                if c + 1 < columns:
                    yield at, at + 1
                if r + 1 < rows:
                    yield at, at + columns


@entry("SELECT id AS a, id + 1 AS b FROM range(80) t(id) WHERE id % 10 < 9 UNION ALL SELECT id, id + 10 FROM range(70) t(id)")
def udtf_lattice(spark, sf_dir):
    return LatticeEdges(F.lit(8), F.lit(10))


@udtf(returnType="step int, v long")
class UnrollPath:
    """The vertices of a path from a target back to a vertex without a parent."""

    def eval(self, parents: dict, target: int):
        step, seen = 0, set()
        while target is not None and target not in seen:
            seen.add(target)
            yield step, target
            target, step = parents.get(target), step + 1


@entry(
    "SELECT CAST(c_custkey AS BIGINT) AS c_custkey, CAST(0 AS INTEGER) AS step, CAST(c_custkey * 4 + 2 AS BIGINT) AS v FROM customer UNION ALL SELECT c_custkey, 1, c_nationkey * 4 + 1 FROM customer"
    " UNION ALL SELECT c_custkey, 2, n_regionkey * 4 FROM customer JOIN nation ON n_nationkey = c_nationkey"
)
def udtf_path(spark, sf_dir):
    spark.udtf.register("unroll_path", UnrollPath)
    load(spark, sf_dir, "customer").createOrReplaceTempView("customer")
    load(spark, sf_dir, "nation").createOrReplaceTempView("nation")
    return spark.sql("""SELECT c_custkey, step, v FROM (SELECT c_custkey, map(c_custkey * 4 + 2, CAST(c_nationkey * 4 + 1 AS BIGINT), CAST(c_nationkey * 4 + 1 AS BIGINT), CAST(n_regionkey * 4 AS BIGINT)) AS parents
        FROM customer JOIN nation ON n_nationkey = c_nationkey), LATERAL unroll_path(parents, c_custkey * 4 + 2)""")


@udtf(returnType="v long, dist double")
class ShortestPaths:
    """Distances from a source over a table of edges (a, b, w) that one task holds; refuses more than SMALL edges."""

    def __init__(self):
        self.around: dict = {}
        self.edges, self.source = 0, None

    def eval(self, row, source: int):
        self.edges, self.source = self.edges + 1, source
        if self.edges > SMALL:
            raise ValueError("too many edges for one task: use adaptive_sssp")
        for a, b in ((row["a"], row["b"]), (row["b"], row["a"])):
            self.around.setdefault(a, []).append((b, float(row["w"])))

    def terminate(self):
        if self.source is None:
            return
        best, queue = {self.source: 0.0}, [(0.0, self.source)]
        while queue:
            d, u = heapq.heappop(queue)
            if d > best[u]:
                continue
            yield u, d
            for v, w in self.around.get(u, ()):
                if d + w < best.get(v, float("inf")):
                    best[v] = d + w
                    heapq.heappush(queue, (d + w, v))


@entry(search(EDGES["user_action"], 1, "SELECT CAST(v AS BIGINT) AS v, CAST(d AS DOUBLE) AS dist FROM t"))
def sql_shortest_paths(spark, sf_dir):
    """SHORTEST_PATHS over a table argument, for small graphs."""
    spark.udtf.register("shortest_paths", ShortestPaths)
    graphs.user_action(spark, sf_dir).createOrReplaceTempView("user_action_edges")
    return spark.sql("SELECT DISTINCT v, dist FROM shortest_paths(TABLE(SELECT a, b, w FROM user_action_edges) WITH SINGLE PARTITION, 1L)")


@entry(
    "SELECT a, CAST(r AS INTEGER) AS rank, b, far FROM (SELECT x.vec_id AS a, y.vec_id AS b, round(list_distance(x.e, y.e), 6) AS far, row_number() OVER (PARTITION BY x.vec_id ORDER BY round(list_distance(x.e, y.e), 6), y.vec_id) AS r"
    " FROM (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) x JOIN (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) y ON x.label = y.label AND x.vec_id <> y.vec_id) WHERE r <= 3"
)
def knn_topk(spark, sf_dir):
    """The three nearest vectors of the same label."""
    near = graphs.nearest_candidates(spark, sf_dir, 3).select("a", "b", F.round("far", 6).alias("far"))
    return near.withColumn("rank", F.row_number().over(Window.partitionBy("a").orderBy("far", "b"))).where("rank <= 3").select("a", "rank", "b", "far")


def _folder(spark: SparkSession, tag: str) -> str:
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{tag}-{uuid.uuid4().hex}"


_LINES = "l_orderkey long, l_linenumber int, l_extendedprice double, l_returnflag string"


def _roundtrip(form: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark, sf_dir):
        path = _folder(spark, f"roundtrip-{form}")
        frame = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice", "l_returnflag")
        writer = frame.write
        writer.csv(path, header=True) if form == "csv" else writer.format(form).save(path)
        return tables.read_any(spark, path, form, _LINES)

    return run


for _form in ("parquet", "csv", "json", "orc"):
    CATALOG[f"io_roundtrip_{_form}"] = (_roundtrip(_form), "SELECT l_orderkey, l_linenumber, l_extendedprice, l_returnflag FROM lineitem")


@entry(f"SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, CAST(w AS DOUBLE) AS w FROM ({EDGES['part_supplier_qty']})")
def io_roundtrip_text(spark, sf_dir):
    """An edge list as lines of text, read back with its rejects left out."""
    path = _folder(spark, "roundtrip-text")
    tables.write_edge_list(graphs.part_supplier_qty(spark, sf_dir), path)
    return tables.read_edge_list(spark, path)[0]


@entry("SELECT count(*) AS rejected FROM events WHERE event_type IN ('error', 'signup') OR (event_type = 'view' AND value > 0) OR user_id IS NULL OR event_id IS NULL OR value IS NULL")
def edge_list_rejects(spark, sf_dir):
    """Events as lines of an edge list; errors lack a field, signups hold a word, views a negative weight. Lines that are no
    edges go to a frame of their own."""
    path = _folder(spark, "rejects")
    kind, value = F.col("event_type"), F.col("value").cast("double")
    fields = F.when(kind == "error", F.concat_ws(" ", "user_id", "event_id")).when(kind == "signup", F.concat_ws(" ", "user_id", F.lit("x"), value)).when(kind == "view", F.concat_ws(" ", "user_id", "event_id", -value)).otherwise(F.concat_ws(" ", "user_id", "event_id", value))
    load(spark, sf_dir, "events").select(fields.alias("value")).write.text(path)
    return tables.read_edge_list(spark, path)[1].agg(F.count("*").alias("rejected"))


@entry(f"SELECT CAST(a AS BIGINT) AS src, CAST(b AS BIGINT) AS dst, w FROM ({EDGES['user_action']}) UNION ALL SELECT b, a, w FROM ({EDGES['user_action']})")
def io_adjacency_json(spark, sf_dir):
    """Adjacency lists, a line of JSON for each vertex, read back as arcs."""
    path = _folder(spark, "adjacency")
    tables.write_adjacency(graphs.symmetrize(graphs.user_action(spark, sf_dir)), path)
    return tables.read_adjacency(spark, path, "bigint")


@entry(f"SELECT CAST(a AS BIGINT) AS src, count(*) AS n FROM (SELECT a FROM ({EDGES['part_supplier_qty']}) UNION ALL SELECT b FROM ({EDGES['part_supplier_qty']})) GROUP BY 1")
def io_bucketed_table(spark, sf_dir):
    """Arcs in a table bucketed by source: degrees need no exchange."""
    name = f"arcs_{uuid.uuid4().hex}"
    tables.write_bucketed(graphs.symmetrize(graphs.part_supplier_qty(spark, sf_dir)), name, path=_folder(spark, "bucketed"))
    return spark.table(name).groupBy("src").agg(F.count("*").alias("n"))


def minhash(tokens, size: int = 16):
    """The least hashes of a column of token arrays, under ``size`` seeds."""
    return F.array(*(F.array_min(F.transform(tokens, lambda t, k=k: F.xxhash64(F.lit(k), t))) for k in range(size)))
