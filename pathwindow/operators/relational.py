"""The relational surface around the path methods: each entry is a Spark query and its DuckDB counterpart."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.weights import converge, discretize, l2
from ..sources.tables import load

CATALOG: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def entry(sql: str | None):
    """Register a query with its oracle."""

    def add(f):
        CATALOG[f.__name__] = (f, sql)
        return f

    return add


def both(name: str, sql: str, oracle: str | None = None) -> None:
    """Register a query that one SQL text expresses in both engines (or nearly: then with the other's text)."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        for table in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages", "embeddings", "conversations"):
            if table in sql:
                load(spark, sf_dir, table).createOrReplaceTempView(table)
        return spark.sql(sql)

    CATALOG[name] = (run, oracle or sql)


def cents() -> Column:
    return F.round(F.col("l_extendedprice") * 100).cast("long")

_CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"


# scans, filters, encodings
both("scan_project_filter", "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')")
both("null_and_negative_screen", "SELECT c_custkey, coalesce(c_acctbal, 0) AS balance, nullif(c_mktsegment, 'BUILDING') AS segment FROM customer WHERE c_acctbal IS NULL OR c_acctbal < 0")
both("case_bucket_weights", f"SELECT CASE WHEN {_CENTS} < 1000000 THEN 'light' WHEN {_CENTS} < 5000000 THEN 'middle' ELSE 'heavy' END AS kind, count(*) AS n FROM lineitem GROUP BY 1")


@entry("SELECT CAST(c_custkey * 2 AS BIGINT) AS code, CAST(c_custkey AS BIGINT) AS key, CAST(0 AS BIGINT) AS kind FROM customer UNION ALL SELECT p_partkey * 2 + 1, p_partkey, 1 FROM part")
def encode_vertex_ids(spark, sf_dir):
    codes = load(spark, sf_dir, "customer").select((F.col("c_custkey") * 2).alias("code")).union(load(spark, sf_dir, "part").select(F.col("p_partkey") * 2 + 1))
    return codes.select("code", F.shiftright("code", 1).alias("key"), F.col("code").bitwiseAND(1).alias("kind"))


# joins
_OL = "SELECT o_orderpriority, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority"


def _orders_lines(spark, sf_dir, hint):
    joined = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority").join(load(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity").hint(hint), F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


@entry(_OL)
def join_inner_hash(spark, sf_dir):
    return _orders_lines(spark, sf_dir, "shuffle_hash")


@entry(_OL)
def join_sort_merge(spark, sf_dir):
    return _orders_lines(spark, sf_dir, "merge")


@entry("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def join_broadcast(spark, sf_dir):
    # nation and region have a fixed size
    nations = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return load(spark, sf_dir, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", "n_name").agg(F.count("*").alias("n"))


both("join_left_outer", "SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
both("join_full_outer", "SELECT count(p_partkey) AS parts, count(l_partkey) AS lines, count(*) AS n FROM part FULL OUTER JOIN (SELECT DISTINCT l_partkey FROM lineitem WHERE l_quantity > 49) ON p_partkey = l_partkey")
both("join_semi_open_targets", "SELECT p_partkey, p_size FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity >= 50)")
both("join_anti_unreached", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
both("join_theta_nested_loop", "SELECT n_name, count(*) AS n FROM nation JOIN supplier ON s_nationkey < n_nationkey GROUP BY n_name")
both(
    "join_range_windows",
    f"WITH w AS (SELECT * FROM (VALUES (1, 0, 1000000), (2, 1000000, 3000000), (3, 3000000, 100000000)) AS t(window_id, lo, hi)) SELECT window_id, count(*) AS n, CAST(sum({_CENTS}) AS BIGINT) AS total FROM lineitem JOIN w ON {_CENTS} >= lo AND {_CENTS} < hi GROUP BY window_id",
)


@entry("SELECT a.event_id AS event_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR GROUP BY a.event_id")
def join_interval_events(spark, sf_dir):
    """Events of a user within an hour: an equi-join on hour buckets and their neighbours, so a busy user is dealt out."""
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.floor(F.unix_timestamp("ts") / 3600).alias("hour"))
    near = e.select(F.col("user_id").alias("u"), F.col("ts").alias("t"), F.explode(F.array(F.col("hour") - 1, F.col("hour"), F.col("hour") + 1)).alias("h"))
    hour = F.expr("INTERVAL 1 HOUR")
    return e.join(near, (F.col("user_id") == F.col("u")) & (F.col("hour") == F.col("h")) & (F.col("t") >= F.col("ts") - hour) & (F.col("t") <= F.col("ts") + hour)).groupBy("event_id").agg(F.count("*").alias("n"))


@entry("SELECT event_id, e.user_id AS user_id, date_diff('second', p.ts, e.ts) AS age FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN (SELECT user_id, ts FROM events WHERE event_type = 'click') p ON e.user_id = p.user_id AND e.ts >= p.ts")
def join_asof_latest(spark, sf_dir):
    """Each purchase with the latest click of its user: one sorted pass over the union."""
    e = load(spark, sf_dir, "events").where(F.col("event_type").isin("purchase", "click"))
    own = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("ts")), ignorenulls=True).over(own)
    return e.withColumn("at", last).where("event_type = 'purchase'").select("event_id", "user_id", (F.unix_seconds(F.col("ts").cast("timestamp")) - F.unix_seconds(F.col("at").cast("timestamp"))).alias("age"))


both("join_cross_trials", "SELECT trial, r_name FROM (VALUES (1), (2), (3), (4)) AS t(trial) CROSS JOIN region")
both("join_lateral_topk", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON c_custkey = o_custkey) WHERE r <= 3")


@entry("SELECT a.user_id AS user_id, count(*) AS n FROM events a JOIN (SELECT user_id, max(ts) AS t FROM events GROUP BY user_id) b ON a.user_id = b.user_id GROUP BY a.user_id")
def join_skewed_salted(spark, sf_dir):
    """The big side salted, the small side once for each salt."""
    salts = 8
    e = load(spark, sf_dir, "events").select("user_id", "event_id", F.pmod("event_id", F.lit(salts)).alias("salt"))
    last = load(spark, sf_dir, "events").groupBy("user_id").agg(F.max("ts").alias("t")).withColumn("salt", F.explode(F.expr(f"sequence(0L, {salts - 1}L)")))
    return e.join(last, ["user_id", "salt"]).groupBy("user_id").agg(F.count("*").alias("n"))


# aggregates
@entry(f"SELECT l_suppkey, min({_CENTS}) AS w, min(CASE WHEN c = m THEN l_partkey END) AS nearest FROM (SELECT *, {_CENTS} AS c, min({_CENTS}) OVER (PARTITION BY l_suppkey) AS m FROM lineitem) GROUP BY l_suppkey")
def agg_partial_final_min_struct(spark, sf_dir):
    least = load(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.min(F.struct(cents().alias("w"), "l_partkey")).alias("m"))
    return least.select("l_suppkey", F.col("m.w").alias("w"), F.col("m.l_partkey").alias("nearest"))


both("agg_basic", "SELECT o_orderstatus, count(*) AS n, round(avg(o_totalprice), 2) AS mean, min(o_totalprice) AS least, max(o_totalprice) AS most, round(stddev_samp(o_totalprice), 2) AS spread FROM orders GROUP BY o_orderstatus HAVING count(*) > 10")
both("agg_distinct", f"SELECT count(DISTINCT {_CENTS}) AS weights, count(DISTINCT l_partkey) AS parts FROM lineitem")


@entry(None)
def agg_approx_distinct(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").agg(F.approx_count_distinct(cents(), 0.02).alias("weights"))


both(
    "agg_percentile_exact",
    "SELECT l_returnflag, round(percentile(l_quantity, 0.25), 6) AS q1, round(percentile(l_quantity, 0.5), 6) AS q2 FROM lineitem GROUP BY l_returnflag",
    "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.25), 6) AS q1, round(quantile_cont(l_quantity, 0.5), 6) AS q2 FROM lineitem GROUP BY l_returnflag",
)


@entry(None)
def agg_percentile_approx(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").agg(F.percentile_approx(cents(), [0.1, 0.5, 0.9], 10000).alias("q"))


@entry(None)
def agg_kll(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").agg(F.kll_sketch_agg_double("l_extendedprice").alias("s")).select(F.kll_sketch_get_quantile_double("s", F.lit(0.5)).alias("median"))


_SUM = "CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity, count(*) AS n"
both("agg_rollup", f"SELECT l_returnflag, l_linestatus, {_SUM} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
both("agg_cube", f"SELECT l_returnflag, l_linestatus, {_SUM} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
both("agg_grouping_sets", f"SELECT l_returnflag, l_linestatus, {_SUM} FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


@entry("SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY user_id")
def agg_pivot(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count().select("user_id", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("click", "view")))


@entry("SELECT l_suppkey, string_agg(CAST(l_partkey AS VARCHAR), ',' ORDER BY l_partkey) AS parts FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem WHERE l_quantity >= 45) GROUP BY l_suppkey")
def agg_collect_sorted(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").where("l_quantity >= 45").groupBy("l_suppkey").agg(F.array_join(F.sort_array(F.collect_set("l_partkey")), ",").alias("parts"))


# windows
both(
    "win_rank_family",
    "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)",
)
both(
    "win_lag_lead_gap",
    "SELECT event_id, unix_seconds(CAST(ts AS TIMESTAMP)) - unix_seconds(CAST(lag(ts) OVER w AS TIMESTAMP)) AS since, lead(event_id) OVER w AS next_event FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "SELECT event_id, CAST(floor(epoch(ts)) AS BIGINT) - CAST(floor(epoch(lag(ts) OVER w)) AS BIGINT) AS since, lead(event_id) OVER w AS next_event FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
)
_HIST = "WITH d AS (SELECT l_partkey, count(*) AS deg FROM lineitem GROUP BY l_partkey), h AS (SELECT deg, count(*) AS cnt FROM d GROUP BY deg)"
both("win_running_degree", f"{_HIST} SELECT deg, cnt, CAST(coalesce(sum(deg * cnt) OVER (ORDER BY deg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS below FROM h")
both("win_suffix_degree", f"{_HIST} SELECT deg, CAST(sum(deg * cnt) OVER (ORDER BY deg DESC ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS from_here FROM h")
both(
    "win_range_frame",
    "SELECT l_orderkey, l_linenumber, l_partkey, count(*) OVER (PARTITION BY l_suppkey ORDER BY datediff(l_shipdate, DATE '1992-01-01') RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS n FROM lineitem",
    "SELECT l_orderkey, l_linenumber, l_partkey, count(*) OVER (PARTITION BY l_suppkey ORDER BY date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS n FROM lineitem",
)
both("win_first_last_nth", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS first_event, last_value(event_id) OVER w AS last_event, nth_value(event_id, 2) OVER w AS second_event FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")

# order and limits
both("sort_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey")
both("topk_hubs", "SELECT l_suppkey, count(DISTINCT l_partkey) AS deg FROM lineitem GROUP BY l_suppkey ORDER BY deg DESC, l_suppkey LIMIT 20")
both("topk_per_group", f"SELECT l_suppkey, l_partkey, w FROM (SELECT l_suppkey, l_partkey, {_CENTS} AS w, row_number() OVER (PARTITION BY l_suppkey ORDER BY {_CENTS}, l_partkey, l_orderkey, l_linenumber) AS r FROM lineitem) WHERE r <= 3")
both("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 50 OFFSET 100")

# sets
for _name, _op in (("set_union_all", "UNION ALL"), ("set_union", "UNION"), ("set_intersect", "INTERSECT"), ("set_except", "EXCEPT")):
    both(_name, f"SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 5000 {_op} SELECT s_nationkey FROM supplier WHERE s_acctbal > 0")


@entry("SELECT c_nationkey AS k, 'customer' AS kind FROM customer UNION ALL SELECT s_nationkey, 'supplier' FROM supplier")
def set_union_by_name(spark, sf_dir):
    a = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k"), F.lit("customer").alias("kind"))
    return a.unionByName(load(spark, sf_dir, "supplier").select(F.lit("supplier").alias("kind"), F.col("s_nationkey").alias("k")))


# subqueries
both("sub_scalar_max", f"SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE {_CENTS} > 0.98 * (SELECT max({_CENTS}) FROM lineitem)")
both("sub_exists", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity = 50)")
both("sub_not_in", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_partkey IS NOT NULL AND l_quantity > 40)")
both("sub_correlated", "SELECT o_orderkey, (SELECT count(*) FROM lineitem WHERE l_orderkey = o_orderkey) AS n FROM orders")
both("cte_chain", f"WITH e AS (SELECT l_partkey, l_suppkey, min({_CENTS}) AS w FROM lineitem GROUP BY 1, 2), d AS (SELECT l_partkey, count(*) AS deg FROM e GROUP BY 1) SELECT deg, count(*) AS parts FROM d GROUP BY deg")

# strings, dates, numbers
both(
    "str_tokens",
    "SELECT lower(w) AS word, count(*) AS n FROM (SELECT explode(split(p_name, ' ')) AS w FROM part) GROUP BY 1",
    "SELECT lower(w) AS word, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS w FROM part) GROUP BY 1",
)
both(
    "str_hrefs",
    "SELECT page_id, size(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS links FROM pages",
    "SELECT page_id, CAST(len(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS INTEGER) AS links FROM pages",
)
both("str_url_host", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages")
both("str_like_case", "SELECT p_partkey, upper(p_brand) AS brand, substring(p_type, 1, 5) AS head FROM part WHERE p_type LIKE '%S%'")
both("str_concat_split", "SELECT p_partkey, concat_ws('|', p_brand, p_type) AS joined FROM part")
both("date_trunc_month", "SELECT CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS STRING) AS month, count(*) AS n FROM orders GROUP BY 1")
both(
    "date_gap_days",
    "SELECT o_orderkey, l_linenumber, l_partkey, datediff(l_shipdate, o_orderdate) AS gap FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "SELECT o_orderkey, l_linenumber, l_partkey, CAST(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS INTEGER) AS gap FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
)
both("interval_add", "SELECT o_orderkey, CAST(CAST(o_orderdate + INTERVAL 30 DAY AS DATE) AS STRING) AS due FROM orders")
both("math_log_pow_floor", "SELECT p_partkey, floor(p_retailprice / 100) AS bucket, round(log2(p_retailprice), 6) AS lg, round(power(p_size, 2), 2) AS sq, greatest(p_size, 10) AS at_least, round(sqrt(p_size), 6) AS root FROM part")


# arrays, maps, JSON, vectors
@entry(f"SELECT l_suppkey, CAST(count(*) AS BIGINT) AS n, CAST(sum(w) AS BIGINT) AS total, CAST(count(*) FILTER (w < 1000000) AS BIGINT) AS light FROM (SELECT l_suppkey, l_partkey, min({_CENTS}) AS w FROM lineitem GROUP BY 1, 2) GROUP BY 1")
def arr_adjacency_ops(spark, sf_dir):
    edges = load(spark, sf_dir, "lineitem").groupBy("l_suppkey", "l_partkey").agg(F.min(cents()).alias("w"))
    near = edges.groupBy("l_suppkey").agg(F.sort_array(F.collect_list(F.struct("w", "l_partkey"))).alias("adj"))
    return near.select("l_suppkey", F.size("adj").cast("long").alias("n"), F.aggregate("adj", F.lit(0).cast("long"), lambda s, x: s + x["w"]).alias("total"), F.size(F.filter("adj", lambda x: x["w"] < 1000000)).cast("long").alias("light"))


@entry("SELECT a.vec_id AS a, b.vec_id AS b, round(list_distance(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 4) AS d FROM embeddings a JOIN embeddings b ON a.label = b.label AND b.vec_id = a.vec_id + 1")
def arr_vector_distance(spark, sf_dir):
    v = load(spark, sf_dir, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("e"))
    return v.join(v.select((F.col("vec_id") - 1).alias("k"), F.col("vec_id").alias("b"), F.col("label").alias("l"), F.col("e").alias("f")), (F.col("vec_id") == F.col("k")) & (F.col("label") == F.col("l"))).select(F.col("vec_id").alias("a"), "b", F.round(l2(F.col("e"), F.col("f")), 4).alias("d"))


@entry("WITH d AS (SELECT l_returnflag AS f, count(*) AS n FROM lineitem GROUP BY 1) SELECT f, n FROM d WHERE n > 100")
def map_degree_lookup(spark, sf_dir):
    counts = load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"))
    held = counts.agg(F.map_from_entries(F.collect_list(F.struct("l_returnflag", "n"))).alias("m"))  # three flags
    return held.select(F.map_filter("m", lambda k, v: v > 100).alias("m")).select(F.explode("m").alias("f", "n"))


both(
    "json_props",
    "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events",
    "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events",
)


@entry(None)
def hash_sampling(spark, sf_dir):
    """A tenth of the orders, by a hash of the key: a sampling operator."""
    return load(spark, sf_dir, "lineitem").where(F.pmod(F.xxhash64("l_orderkey"), F.lit(10)) == 0).select("l_orderkey", "l_partkey")


# graph tables in SQL
_EDGES = f"SELECT least(l_partkey * 2, l_suppkey * 2 + 1) AS a, greatest(l_partkey * 2, l_suppkey * 2 + 1) AS b, min({_CENTS}) AS w FROM lineitem GROUP BY 1, 2"
both("dedupe_edges", _EDGES)
both("symmetrize_edges", f"WITH e AS ({_EDGES}) SELECT a AS src, b AS dst, w FROM e UNION ALL SELECT b, a, w FROM e")
both("drop_isolated", f"WITH e AS ({_EDGES}) SELECT v, count(*) AS deg FROM (SELECT a AS v FROM e UNION ALL SELECT b FROM e) GROUP BY v")
both("degree_histogram", f"WITH e AS ({_EDGES}), d AS (SELECT v, count(*) AS deg FROM (SELECT a AS v FROM e UNION ALL SELECT b FROM e) GROUP BY v) SELECT deg, count(*) AS cnt FROM d GROUP BY deg")
_SCALED = f"WITH e AS ({_EDGES}), x AS (SELECT a, b, w / CAST((SELECT max(w) FROM e) AS DOUBLE) AS w FROM e)"


def _variants() -> None:
    from ..functions.weights import rescaled
    from ..sources.graphs import part_supplier_price

    for power in (1, 2, 3, 4, 6, 8, 10):
        run = lambda spark, sf_dir, p=power: rescaled(part_supplier_price(spark, sf_dir)).select("a", "b", discretize(F.col("w"), p).alias("w"))
        CATALOG[f"discretize_power_{power}"] = (run, f"{_SCALED} SELECT a, b, CAST(floor(1 + w * {2**power - 2} + 0.5) AS BIGINT) AS w FROM x")
    for tenth in range(1, 10):
        p = tenth / 10
        run = lambda spark, sf_dir, p=p: rescaled(part_supplier_price(spark, sf_dir)).select("a", "b", F.round(converge(F.col("w"), p), 9).alias("w"))
        sql = f"{_SCALED} SELECT a, b, round(CASE WHEN w <= 0.5 THEN CAST({p} AS DOUBLE) - CAST({p} AS DOUBLE) * ((1 - 2 * w) * (1 - 2 * w)) ELSE CAST({p} AS DOUBLE) + (1 - CAST({p} AS DOUBLE)) * ((1 - 2 * w) * (1 - 2 * w)) END, 9) AS w FROM x"
        CATALOG[f"converge_pivot_{tenth}"] = (run, sql)


_variants()
