"""Streaming forms, replayed from files until all of them are read; batch SQL is what they must equal."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..engine import minimum_union
from ..lineage import shared_dir
from ..sources.tables import Catalog


def events_stream(c: Catalog) -> DataFrame:
    """events as a stream, with ts as an instant."""
    schema = c.table("events").schema
    return c.spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(_files(c)).withColumn("ts", F.col("ts").cast("timestamp"))


def _files(c: Catalog) -> str:
    """A glob of the table alone: a stream needs a folder or a pattern."""
    return f"{c.folder}/event[s].parquet"


def replay(spark: SparkSession, stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over what its source has and returns the rows it has written, as files of the shared folder.

    A batch that is run again writes its own files again, so rows are there once. In complete mode the last batch holds all.
    """
    folder = f"{shared_dir(spark)}/replay-{uuid.uuid4().hex}"
    columns, rows = stream.columns, f"{folder}/rows"
    spark.createDataFrame([], stream.schema).write.parquet(rows if mode == "complete" else f"{rows}/batch=-1")

    def write(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(rows if mode == "complete" else f"{rows}/batch={batch}")

    query = stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{folder}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(rows).select(*columns)


def best_match_stream(spark: SparkSession, stream: DataFrame, keys: list[str]) -> DataFrame:
    """The rows of a stream of optional answers without those that a later one subsumes: (keys, null) goes once (keys, x) is there.

    Each batch reads the answers of the keys it touches from the state before it, and writes the state after it, so a
    batch that is run again starts from the same state.
    """
    folder = f"{shared_dir(spark)}/best-{uuid.uuid4().hex}"
    spark.createDataFrame([], stream.schema).write.parquet(f"{folder}/0")
    done = [0]

    def write(df: DataFrame, batch: int) -> None:
        before = spark.read.schema(stream.schema).parquet(f"{folder}/{batch}")
        touched = df.select(*keys).distinct()
        made = minimum_union([before.join(touched, keys, "left_semi"), df.select(*stream.columns)])
        before.join(touched, keys, "left_anti").select(*stream.columns).unionByName(made).write.mode("overwrite").parquet(f"{folder}/{batch + 1}")
        done[0] = batch + 1

    query = stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/{done[0]}")


def best_match_events(c: Catalog) -> DataFrame:
    """Users with their purchases, or with none if they have only viewed, as rows arrive."""
    rows = events_stream(c).filter("event_type IN ('view', 'purchase')").select("user_id", F.when(F.col("event_type") == "purchase", F.col("event_id")).alias("bought"))
    return best_match_stream(c.spark, rows, ["user_id"])


def sliding(c: Catalog) -> DataFrame:
    s = events_stream(c).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "2 days", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return replay(c.spark, s, "complete").select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")


def windowed(c: Catalog) -> DataFrame:
    s = events_stream(c).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return replay(c.spark, s, "complete").select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")


def sessions(c: Catalog) -> DataFrame:
    s = events_stream(c).withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", "2 hours"), "user_id").agg(F.count("*").alias("n"))
    return replay(c.spark, s, "complete").select("user_id", "n")


def semi(c: Catalog) -> DataFrame:
    """A stream reduced by static keys: safe, since they don't change."""
    keys = c.table("customer").filter("c_nationkey = 7").select(F.col("c_custkey").alias("user_id"))
    return replay(c.spark, events_stream(c).join(keys, "user_id", "left_semi").select("event_id"), "append")


def optional_static(c: Catalog) -> DataFrame:
    """A stream with an optional static part: misses are final at once."""
    right = c.table("customer").filter("c_nationkey = 7").select(F.col("c_custkey").alias("user_id"), "c_name")
    return replay(c.spark, events_stream(c).join(right, "user_id", "left").select("event_id", "c_name"), "append")


def optional_stream(c: Catalog) -> DataFrame:
    """All views with the purchases of the same user within an hour, both as streams.

    Both sides end with a row far behind the last one, from a stream of its own. It moves the watermark past every hour, so all misses become final.
    """
    events = c.table("events")
    base = shared_dir(c.spark)
    folder = f"{base if ':' in base else 'file://' + base}/stream-end-{uuid.uuid4().hex}"
    end = F.coalesce(F.max(F.col("ts").cast("timestamp")), F.lit(0).cast("timestamp")) + F.expr("INTERVAL 30 DAYS")
    last = events.agg(end.alias("ts")).select("ts", F.lit(0).cast(events.schema["user_id"].dataType).alias("user_id"), F.explode(F.array(F.lit("view"), F.lit("purchase"))).alias("event_type"))
    last.write.parquet(folder)
    rows = events_stream(c).select("event_id", "user_id", "ts", "event_type").unionByName(c.spark.readStream.schema(last.schema).parquet(folder), allowMissingColumns=True)
    side = lambda kind, id_, ts, user: rows.filter(F.col("event_type") == kind).select(F.col("event_id").alias(id_), F.col("ts").alias(ts), F.col("user_id").alias(user)).withWatermark(ts, "10 minutes")
    near = F.expr("user_id = other_user AND other_ts > ts AND other_ts <= ts + INTERVAL 1 HOUR")
    joined = side("view", "event_id", "ts", "user_id").join(side("purchase", "other_id", "other_ts", "other_user"), near, "left")
    return replay(c.spark, joined.select("event_id", "other_id"), "append").filter("event_id is not null")


def distinct_users(c: Catalog) -> DataFrame:
    s = events_stream(c).withWatermark("ts", "36500 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return replay(c.spark, s, "append")


OPERATORS = {
    "stream_o73_source": (lambda c: replay(c.spark, events_stream(c).select("event_id", "event_type"), "append"), "SELECT event_id, event_type FROM events"),
    "stream_o74_windowed": (windowed, "SELECT epoch(date_trunc('day', ts))::BIGINT AS start, event_type, count(*) n FROM events GROUP BY 1, 2"),
    "stream_o74_sliding": (sliding, "SELECT epoch(date_trunc('day', ts) - INTERVAL 1 DAY * k)::BIGINT AS start, event_type, count(*) n FROM events, (VALUES (0), (1)) t(k) GROUP BY 1, 2"),
    "stream_o80_best_match": (
        best_match_events,
        "SELECT DISTINCT user_id, event_id AS bought FROM events WHERE event_type = 'purchase' UNION ALL SELECT DISTINCT user_id, NULL::BIGINT FROM events WHERE event_type = 'view' AND user_id NOT IN (SELECT user_id FROM events WHERE event_type = 'purchase')",
    ),
    "stream_o75_sessions": (
        sessions,
        "WITH a AS (SELECT *, ts >= lag(ts) OVER w + INTERVAL 2 HOUR AS gap FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT *, sum(coalesce(gap, false)::INT) OVER (PARTITION BY user_id ORDER BY ts) k FROM a) SELECT user_id, count(*) n FROM b GROUP BY user_id, k",
    ),
    "stream_o76_semi": (semi, "SELECT event_id FROM events WHERE user_id IN (SELECT c_custkey FROM customer WHERE c_nationkey = 7)"),
    "stream_o77_optional_static": (optional_static, "SELECT event_id, c_name FROM events LEFT JOIN (SELECT * FROM customer WHERE c_nationkey = 7) ON c_custkey = user_id"),
    "stream_o78_optional": (
        optional_stream,
        """SELECT v.event_id, p.event_id AS other_id FROM (SELECT * FROM events WHERE event_type = 'view') v LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p
        ON v.user_id = p.user_id AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR""",
    ),
    "stream_o79_distinct": (distinct_users, "SELECT DISTINCT user_id, event_type FROM events"),
}
