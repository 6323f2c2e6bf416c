"""Streams: queries answered from a static index, quality by window, buffered inserts, tombstones, and joins of streams."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import IntegerType, StructField, StructType

from annspark.operators.build import Router
from annspark.operators.search import search_index
from annspark.plans.session import path_exists, ship_package, staging_path
from annspark.sources.store import IndexStore
from annspark.sources.tables import table


def answer_stream(queries: DataFrame, index: DataFrame, k: int, width: int, out: str, checkpoint: str, router: Router | None = None, probes: int = 1):
    """Start a query that answers each micro-batch of ``queries(q_id, qvec)`` under ``out/batch=<id>``.

    A batch's folder is overwritten if it runs again, so each is there once.
    """

    def one(batch: DataFrame, epoch: int) -> None:
        found = search_index(index, batch, k, [max(k, width)], router, probes)
        found.write.mode("overwrite").parquet(f"{out}/batch={epoch}")

    return queries.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed(events: DataFrame, ts: str, value: str, kind: str = "tumbling", late: str = "2 hours") -> DataFrame:
    """(start, end, n, mean) of ``value`` by hour: tumbling, sliding by a quarter of an hour, or sessions with half an hour's gap."""
    window = {"tumbling": F.window(ts, "1 hour"), "sliding": F.window(ts, "1 hour", "15 minutes"), "session": F.session_window(ts, "30 minutes")}[kind]
    stream = events.withWatermark(ts, late) if events.isStreaming else events
    return stream.groupBy(window.alias("w")).agg(F.count("*").alias("n"), F.avg(value).alias("mean")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "mean")


def count_late(events: DataFrame, ts: str, out: str, checkpoint: str, delay_s: int = 7200):
    """Start a query that writes (rows, late, newest) of each micro-batch under ``out/batch=<id>``.

    A row is late if it is more than ``delay_s`` older than the newest row of all earlier batches.
    """

    def one(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        before = None
        if path_exists(spark, out):
            seen = spark.read.schema("rows long, late long, newest double, batch int").parquet(out)
            before = seen.where(F.col("batch") < epoch).agg(F.max("newest")).first()[0]
        second = F.unix_micros(F.col(ts).cast("timestamp")) / 1e6
        late = F.count_if(second < before - delay_s) if before is not None else F.lit(0).cast("long")
        batch.agg(F.count("*").alias("rows"), late.alias("late"), F.max(second).alias("newest")).write.mode("overwrite").parquet(f"{out}/batch={epoch}")

    return events.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def insert_buffer(inserts: DataFrame, limit: int = 1000) -> DataFrame:
    """(shard, pending, flushed): pending vectors per shard, kept as state and flushed when a shard has ``limit``.

    ``inserts`` has shard, vec_id, deleted; a deletion takes a pending insert away.
    """
    ship_package(inserts.sparkSession)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        pending = set(state.get[0]) if state.exists else set()
        flushed = 0
        for rows in batches:
            for i, dead in zip(rows["vec_id"], rows["deleted"]):
                (pending.discard if dead else pending.add)(int(i))
        if len(pending) >= limit:
            flushed, pending = len(pending), set()
        state.update((sorted(pending),))
        yield pd.DataFrame({"shard": [int(key[0])], "pending": [len(pending)], "flushed": [flushed]})

    return inserts.groupBy("shard").applyInPandasWithState(step, "shard int, pending long, flushed long", "ids array<long>", "update", GroupStateTimeout.NoTimeout)


def first_deletions(deletions: DataFrame, ts: str = "ts", late: str = "2 hours") -> DataFrame:
    """``deletions(vec_id, ts)`` without repeats of an id; a stream forgets an id when its watermark is ``late`` past it."""
    if not deletions.isStreaming:
        return deletions.dropDuplicates(["vec_id"])
    return deletions.withWatermark(ts, late).dropDuplicatesWithinWatermark(["vec_id"])


def tombstone_stream(deletions: DataFrame, store: IndexStore, checkpoint: str, ts: str = "ts", late: str = "2 hours"):
    """Start a query that adds the ids of ``deletions`` to the store's tombstones.

    A batch that runs again, or an id that the stream has forgotten, adds an id twice, which changes no search.
    """

    def one(batch: DataFrame, epoch: int) -> None:
        store.delete(batch)

    return first_deletions(deletions, ts, late).writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def join_streams(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, seconds: int, late: str = "2 hours") -> DataFrame:
    """Pairs of the same key with the right time in (left, left + seconds].

    Of two streams, rows wait as state until no partner within the interval can come any more; rows later than ``late`` may be lost, as are rows
    at or before 1970, where a stream's watermark begins.
    """
    if left.isStreaming:
        left, right = left.withWatermark(left_ts, late), right.withWatermark(right_ts, late)
    other = right.withColumnRenamed(key, "_key")
    near = (F.col(right_ts) > F.col(left_ts)) & (F.col(right_ts) <= F.col(left_ts) + F.expr(f"INTERVAL {int(seconds)} SECONDS"))
    return left.join(other, (F.col(key) == F.col("_key")) & near).drop("_key")


def stream_of(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def drain(stream: DataFrame, base: str, mode: str = "append") -> DataFrame:
    """Run ``stream`` to its end under ``base``; returns its rows and the batch they came in.

    A batch's folder is overwritten if it runs again.
    """
    spark = stream.sparkSession

    def one(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={epoch}")

    stream.writeStream.outputMode(mode).foreachBatch(one).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    schema = StructType([*stream.schema.fields, StructField("batch", IntegerType())])
    return spark.read.schema(schema).parquet(f"{base}/out") if path_exists(spark, f"{base}/out") else spark.createDataFrame([], schema)


def replay_events(spark: SparkSession, sf_dir: str, base: str, copies: int = 1) -> list[DataFrame]:
    """All events, written in order of time under ``base``, as so many streams."""
    cast = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"), "value")
    cast.repartitionByRange(4, "ts").write.parquet(f"{base}/in")
    return [stream_of(spark, f"{base}/in", cast.schema, 100) for _ in range(copies)]


def stream_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tumbling hours over all events, run as a stream to completion and read back."""
    base = staging_path(spark, "stream-windows")
    rows = drain(windowed(replay_events(spark, sf_dir, base)[0], "ts", "value"), base, "update")
    # In update mode a later batch replaces a window's earlier row.
    last = rows.groupBy("start").agg(F.max_by("n", "batch").alias("n"))
    return last.select(F.unix_seconds("start").alias("start_s"), "n")


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within two hours of a user's click, as a join of two streams run to completion."""
    base = staging_path(spark, "stream-join")
    a, b = replay_events(spark, sf_dir, base, 2)
    a = a.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts"))
    b = b.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("purchase_ts"))
    return drain(join_streams(a, b, "user_id", "click_ts", "purchase_ts", 7200), base).select("click_id", "purchase_id")


def stream_tombstones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The users of error events as deletions, each id once over the whole stream."""
    base = staging_path(spark, "stream-tombstones")
    dead = replay_events(spark, sf_dir, base)[0].where("event_type = 'error'").select(F.col("user_id").alias("vec_id"), "ts")
    return drain(first_deletions(dead, late="60 days"), base).select("vec_id")


def session_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user by half an hour's gap: how many, and events in the longest."""
    e = table(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    s = e.groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


QUERIES = {
    "stream_tumbling_windows": (stream_windows, "SELECT CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01')) AS BIGINT) AS start_s, count(*) AS n FROM events GROUP BY 1"),
    "stream_join": (
        stream_join,
        "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR",
    ),
    "stream_tombstones": (stream_tombstones, "SELECT DISTINCT user_id AS vec_id FROM events WHERE event_type = 'error'"),
    "session_windows": (
        session_windows,
        "WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
        "s AS (SELECT user_id, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g), c AS (SELECT user_id, s, count(*) AS n FROM s GROUP BY ALL) "
        "SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY user_id",
    ),
}

__all__ = ["QUERIES", "answer_stream", "count_late", "drain", "first_deletions", "insert_buffer", "join_streams", "stream_of", "tombstone_stream", "windowed"]
