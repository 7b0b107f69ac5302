"""Event streams: windowed counts under a watermark, a join with a table, and late rows, run until the input is used up."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..oracles import EDGES, search
from ..plans.prepared import ensure_checkpoint_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as a file stream; watermarks need a timestamp with a zone (the session's, UTC)."""
    stream = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def _folder(spark: SparkSession, tag: str) -> str:
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{tag}-{uuid.uuid4().hex}"


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """All results of a stream over the input that is there now, by way of tables: one a batch, of which the last counts
    where every batch gives the complete result."""
    spark, out, done = stream.sparkSession, _folder(stream.sparkSession, "stream-out"), []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch-{number}")
        done.append(number)

    query = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", _folder(spark, "stream-state")).trigger(availableNow=True).start()
    query.awaitTermination()
    paths = [f"{out}/batch-{k}" for k in (sorted(done)[-1:] if mode == "complete" else sorted(set(done)))]
    return spark.read.parquet(*paths) if paths else spark.createDataFrame([], stream.schema)


def _windowed(spark: SparkSession, sf_dir: str, window, key: str = "event_type") -> DataFrame:
    counts = read_events(spark, sf_dir).withWatermark("ts", "10 minutes").groupBy(window.alias("w"), key).agg(F.count("*").alias("n"))
    return drain(counts).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), key, "n")


def tumbling_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windowed(spark, sf_dir, F.window("ts", "1 hour"))


def sliding_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windowed(spark, sf_dir, F.window("ts", "1 hour", "30 minutes"))


def session_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windowed(spark, sf_dir, F.session_window("ts", "30 minutes"), "user_id")


def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with a table of their kinds' shares of all events, counted per kind."""
    kinds = spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("event_type").agg(F.count("*").alias("total"))
    return drain(read_events(spark, sf_dir).join(F.broadcast(kinds), "event_type").groupBy("event_type", "total").agg(F.count("*").alias("n")))


def stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clicks and the same user's purchases within an hour after them, both as streams."""
    side = lambda kind, at: read_events(spark, sf_dir).where(F.col("event_type") == kind).select(F.col("event_id").alias(f"{kind}_id"), F.col("user_id").alias(f"{kind}_user"), F.col("ts").alias(at))
    clicks, bought = side("click", "clicked").withWatermark("clicked", "1 hour"), side("purchase", "bought").withWatermark("bought", "1 hour")
    near = (F.col("click_user") == F.col("purchase_user")) & (F.col("bought") >= F.col("clicked")) & (F.col("bought") <= F.col("clicked") + F.expr("INTERVAL 1 HOUR"))
    return drain(clicks.join(bought, near).select("click_id", "purchase_id"), "append")


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(counted, late): events whose later half comes first; what then lies behind the watermark is left out of the windows."""
    folder, events = _folder(spark, "late"), spark.read.parquet(f"{sf_dir}/events.parquet")
    middle = events.agg(F.percentile("event_id", 0.5).alias("m")).first()["m"]
    later = events.where(F.col("event_id") > middle).coalesce(1)
    later.write.parquet(folder)
    first = read_files(spark, folder)
    state, out = _folder(spark, "late-state"), _folder(spark, "late-out")
    counts = first.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    for part in (None, events.where(F.col("event_id") <= middle).coalesce(1)):
        if part is not None:
            part.write.mode("append").parquet(folder)
        counts.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    latest = spark.read.schema("w struct<start:timestamp,end:timestamp>, n long").parquet(f"{out}/batch=*").groupBy("w").agg(F.max("n").alias("n"))
    return latest.agg(F.sum("n").alias("counted")).join(events.agg(F.count("*").alias("whole"))).select("counted", (F.col("whole") - F.col("counted")).alias("late"))


def read_files(spark: SparkSession, folder: str) -> DataFrame:
    return spark.readStream.schema(SCHEMA).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def least_by_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's least value and number of events, kept in arbitrary state across batches."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def each(key, batches, state: GroupState):
        least, n = state.get if state.exists else (float("inf"), 0)
        for batch in batches:
            least, n = min(least, float(batch["value"].min())), n + len(batch)
        state.update((least, n))
        yield pd.DataFrame({"user_id": [key[0]], "least": [least], "n": [n]})

    kept = read_events(spark, sf_dir).select("user_id", "value").groupBy("user_id").applyInPandasWithState(each, "user_id long, least double, n long", "least double, n long", "update", GroupStateTimeout.NoTimeout)
    told = drain(kept, "update")
    return told.groupBy("user_id").agg(F.min("least").alias("least"), F.max("n").alias("n"))


def incremental_search(spark: SparkSession, sf_dir: str, source: int = 1, batches: int = 2) -> DataFrame:
    """(v, dist) on the user-action graph as its events stream in: each batch's edges repair the distances known so far."""
    from ..operators import apps
    from ..plans.engine import adaptive_sssp
    from ..plans.prepared import prepare
    from ..sources import graphs

    folder, state, now = _folder(spark, "edges-in"), _folder(spark, "edges-state"), {}
    edges = graphs.user_action(spark, sf_dir)

    def absorb(batch: DataFrame, _: int) -> None:
        if batch.isEmpty():
            return
        new = batch.checkpoint()
        whole = graphs.canonical(now["edges"].unionByName(new) if now else new).checkpoint()
        graph = prepare(whole)
        known = now.get("state")
        there = known is not None and graph.vertices.where(F.col("v") == source).limit(1).count()
        now["state"] = apps.repair(graph, known, source, new) if there else adaptive_sssp(graph, source).state.checkpoint()
        now["edges"] = whole

    for k in range(batches):
        edges.where(F.pmod(F.hash("a", "b"), F.lit(batches)) == k).write.mode("append").parquet(folder)
        stream = spark.readStream.schema(edges.schema).parquet(folder)
        stream.writeStream.foreachBatch(absorb).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return now["state"].select("v", F.col("dist").cast("long").alias("dist"))


_HOUR = "strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S')"
QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "tumbling_counts": (tumbling_counts, f"SELECT {_HOUR} AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "sliding_counts": (
        sliding_counts,
        "SELECT strftime(time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events, range(0, 2) AS t(k) GROUP BY 1, 2",
    ),
    "session_counts": (
        session_counts,
        """WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM g)
SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k""",
    ),
    "stream_static_join": (stream_static_join, "SELECT event_type, count(*) AS total, count(*) AS n FROM events GROUP BY 1"),
    "stream_stream_join": (
        stream_stream_join,
        "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON p.user_id = c.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'",
    ),
    "late_rows": (
        late_rows,
        "WITH m AS (SELECT quantile_cont(event_id, 0.5) AS m, max(ts) AS top FROM events) SELECT CAST(count(*) FILTER (event_id > m OR time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR > top - INTERVAL 10 MINUTE) AS BIGINT) AS counted, CAST(count(*) FILTER (event_id <= m AND time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR <= top - INTERVAL 10 MINUTE) AS BIGINT) AS late FROM events, m",
    ),
    "least_by_user": (least_by_user, "SELECT user_id, min(value) AS least, count(*) AS n FROM events GROUP BY user_id"),
    "incremental_search": (incremental_search, search(EDGES["user_action"], 1, "SELECT CAST(v AS BIGINT) AS v, CAST(d AS BIGINT) AS dist FROM t")),
}
