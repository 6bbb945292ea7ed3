"""Structured Streaming: users are objects, their events are arriving points."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from objann.operators.hashing import Projections, collision_counts, inverted
from objann.plans.search_sql import Sql, floor_div
from objann.plans.workloads import QUERIES, projections
from objann.sources.families import USER, event_vector, points
from objann.sources.tables import work_folder

EVENT_SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str) -> DataFrame:
    return spark.readStream.schema(EVENT_SCHEMA).option("pathGlobFilter", "events.parquet").parquet(folder)


def event_points(events: DataFrame) -> DataFrame:
    return events.select(F.col("user_id").alias("object_id"), F.col("event_id").alias("point_id"), event_vector().alias("vec"), "ts")


def append_to_index(events: DataFrame, proj: Projections, path: str, checkpoint: str):
    """Arriving points are hashed and appended; a batch that runs again replaces its own files."""

    def write(batch: DataFrame, number: int) -> None:
        inverted(event_points(batch), proj).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return events.writeStream.option("checkpointLocation", checkpoint).foreachBatch(write).trigger(availableNow=True).start()


def tumbling_counts(events: DataFrame, size: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Events by window and type; events later than the watermark are dropped."""
    source = events.withWatermark("ts", late) if events.isStreaming else events
    return source.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding_counts(events: DataFrame, size: str = "2 hours", step: str = "1 hour", late: str = "1 hour") -> DataFrame:
    source = events.withWatermark("ts", late) if events.isStreaming else events
    return source.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def session_objects(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """A user's session is an object; its events are the points."""
    source = events.withWatermark("ts", late) if events.isStreaming else events
    return source.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n_points")).select("user_id", F.col("w.start").alias("start"), "n_points")


def _folders(spark: SparkSession, name: str) -> tuple[str, str]:
    base = f"{work_folder(spark)}/objann-streams/{name}-{uuid.uuid4().hex}"
    return f"{base}/out", f"{base}/checkpoint"


def stream_index(spark: SparkSession, folder: str) -> DataFrame:
    """(proj, bucket, n) of the index that the arriving events of all users were appended to."""
    out, checkpoint = _folders(spark, "index")
    append_to_index(event_stream(spark, folder), projections("user"), out, checkpoint).awaitTermination()
    return spark.read.parquet(out).groupBy("proj", "bucket").agg(F.count("*").alias("n"))


def keep_sizes(events: DataFrame) -> DataFrame:
    """(object_id, n_points, total) after every batch: each object's running size, kept as state."""

    def update(key, frames, state: GroupState):
        n, total = state.get if state.exists else (0, 0)
        for frame in frames:
            n, total = n + len(frame), total + int(frame["point_id"].sum())
        state.update((n, total))
        yield pd.DataFrame({"object_id": [key[0]], "n_points": [n], "total": [total]})

    arriving = events.select(F.col("user_id").alias("object_id"), F.col("event_id").alias("point_id"))
    return arriving.groupBy("object_id").applyInPandasWithState(update, "object_id long, n_points long, total long", "n long, total long", "update", GroupStateTimeout.NoTimeout)


def stream_state(spark: SparkSession, folder: str) -> DataFrame:
    """The sizes after the last batch."""
    out, checkpoint = _folders(spark, "state")

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    keep_sizes(event_stream(spark, folder)).writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(write).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).groupBy("object_id").agg(F.max("n_points").alias("n_points"), F.max("total").alias("total"))


def stream_collisions(spark: SparkSession, folder: str, level: int = 1) -> DataFrame:
    """(q_obj, object_id, num): the running collision index of a standing query.

    A point's collisions are complete when it arrives, so every batch adds its close pairs to the
    numerator; the denominator follows from the sizes.
    """
    out, checkpoint = _folders(spark, "standing")
    proj = projections("user")
    standing = points(spark, folder, USER).where(QUERIES["user"])

    def count(batch: DataFrame, number: int) -> None:
        counts = collision_counts(event_points(batch), standing, proj, level).where(F.col("cc") >= proj.params.l)
        counts.groupBy("q_obj", "object_id").agg(F.count("*").alias("num")).write.mode("overwrite").parquet(f"{out}/batch={number}")

    event_stream(spark, folder).writeStream.option("checkpointLocation", checkpoint).foreachBatch(count).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).groupBy("q_obj", "object_id").agg(F.sum("num").alias("num"))


def stream_windows(spark: SparkSession, folder: str, mode: str) -> DataFrame:
    """Hourly counts of the stream by output mode: complete and update hold all windows, append those that the watermark has closed."""
    out, checkpoint = _folders(spark, mode)

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    counted = tumbling_counts(event_stream(spark, folder))
    counted.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).foreachBatch(write).trigger(availableNow=True).start().awaitTermination()
    held = spark.read.parquet(out)
    if mode == "complete":
        return held.where(F.col("batch") == held.agg(F.max("batch")).first()[0]).drop("batch")
    return held.groupBy("start", "event_type").agg(F.max("n").alias("n"))


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events without those that repeat an id within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def late_rows(query) -> int:
    """Rows that a finished stream dropped as later than its watermark."""
    return sum(op.numRowsDroppedByWatermark for progress in query.recentProgress for op in progress.stateOperators)


def queries() -> dict:
    return {
        "stream_index_append": stream_index,
        "stream_object_state": stream_state,
        "stream_standing_query": stream_collisions,
        "stream_windows_complete": lambda spark, sf: stream_windows(spark, sf, "complete"),
        "stream_windows_update": lambda spark, sf: stream_windows(spark, sf, "update"),
    }


def oracles() -> dict[str, str]:
    user, proj = Sql(USER, QUERIES["user"]), projections("user")
    cell = floor_div("bucket", 2)
    windows = "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"
    return {
        "stream_index_append": f"WITH {user.points}, {user.hashes(proj)} SELECT proj, bucket, count(*) AS n FROM h GROUP BY 1, 2",
        "stream_object_state": "SELECT user_id AS object_id, count(*) AS n_points, CAST(sum(event_id) AS BIGINT) AS total FROM events GROUP BY 1",
        "stream_standing_query": f"""WITH {user.points}, {user.hashes(proj)}, cc AS (SELECT q.object_id AS q_obj, q.point_id AS q_id, x.object_id, x.point_id, count(*) AS cc
          FROM (SELECT *, {cell} AS cell FROM h) q JOIN (SELECT *, {cell} AS cell FROM h) x USING (proj, cell) WHERE q.{user.queries} GROUP BY ALL)
          SELECT q_obj, object_id, count(*) AS num FROM cc WHERE cc >= {proj.params.l} GROUP BY 1, 2""",
        "stream_windows_complete": windows,
        "stream_windows_update": windows,
    }
