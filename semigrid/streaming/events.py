"""Incidence matrices, degrees and products kept up to date from a stream of events."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semigrid.plans.scratch import scratch_root

#: Columns of the events table.
EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events table as a stream of files."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)


def user_hours(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """(i, j, v): events of a user in an hour of the month; hours close once the watermark has passed."""
    w = F.window("ts", "1 hour")
    hour = (F.dayofmonth("w.start") * 24 + F.hour("w.start") - 24).cast("long")
    counted = events.withWatermark("ts", late).groupBy("user_id", w.alias("w")).agg(F.count(F.lit(1)).alias("v"))
    return counted.select(F.col("user_id").alias("i"), hour.alias("j"), "v")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", "1 hour").groupBy("user_id", w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def degrees(events: DataFrame) -> DataFrame:
    """(user_id, degree): a running count for each user."""
    return events.groupBy("user_id").agg(F.count(F.lit(1)).alias("degree"))


def degrees_by_state(events: DataFrame) -> DataFrame:
    """The same from a state of one number for each user, kept by a function: for counts that no aggregate gives."""

    def count(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        total = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((total,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [total]})

    return events.select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(count, "user_id long, degree long", "n long", "update", "NoTimeout")


def run_to_end(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over all there is now; its last result (complete) or all rows it gave (update, append), as a table in the shared folder.

    Each batch has a folder of its own, so a batch that is run again replaces its rows.
    """
    spark, root = stream.sparkSession, f"{scratch_root(stream.sparkSession)}/stream_{uuid.uuid4().hex}"
    done: list[int] = []

    def write(batch: DataFrame, k: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/rows/{k}")
        done.append(k)

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*[f"{root}/rows/{k}" for k in (sorted(set(done)) if mode != "complete" else [max(done)])])


def incremental_product(stream: DataFrame, merge: Callable[[DataFrame, int], None]):
    """Hands each batch's new entries to ``merge``, which adds their products to a stored result."""
    return stream.writeStream.foreachBatch(merge).option("checkpointLocation", f"{scratch_root(stream.sparkSession)}/inc_{uuid.uuid4().hex}").trigger(availableNow=True).start()


def stream_product(stream: DataFrame) -> DataFrame:
    """(i, j, v): A'A for A = user by event type, brought up to date batch by batch from new entries alone.

    With new entries D, A'D + D'A + D'D is added. Entries and sums are tables in the
    shared folder, one folder for each batch, so a batch run again replaces its own.
    """
    spark, root = stream.sparkSession, f"{scratch_root(stream.sparkSession)}/product_{uuid.uuid4().hex}"
    entry = "i long, j string, v long"

    def read(what: str, before: int) -> DataFrame:
        """What all earlier batches have stored."""
        if not before:
            return spark.createDataFrame([], entry if what == "entries" else "i string, j string, v long")
        return spark.read.parquet(*[f"{root}/{what}/{k}" for k in range(before)])

    def times(a: DataFrame, b: DataFrame) -> DataFrame:
        right = b.select("i", F.col("j").alias("k"), F.col("v").alias("y"))
        return a.join(right, "i").select(F.col("j").alias("i"), F.col("k").alias("j"), (F.col("v") * F.col("y")).alias("v"))

    done: list[int] = []

    def merge(batch: DataFrame, k: int) -> None:
        new = batch.groupBy(F.col("user_id").alias("i"), F.col("event_type").alias("j")).agg(F.count(F.lit(1)).alias("v"))
        new.write.mode("overwrite").parquet(f"{root}/entries/{k}")
        new, old = spark.read.parquet(f"{root}/entries/{k}"), read("entries", k)
        change = times(old, new).unionByName(times(new, old)).unionByName(times(new, new))
        change.groupBy("i", "j").agg(F.sum("v").alias("v")).write.mode("overwrite").parquet(f"{root}/sums/{k}")
        done.append(k)

    incremental_product(stream, merge).awaitTermination()
    return read("sums", max(done, default=-1) + 1).groupBy("i", "j").agg(F.sum("v").cast("long").alias("v"))


def queries() -> dict:
    return {
        "stream_product": lambda s, d: stream_product(event_stream(s, d)),
        "stream_user_hours": lambda s, d: run_to_end(user_hours(event_stream(s, d))),
        "stream_sessions": lambda s, d: run_to_end(sessions(event_stream(s, d))).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").cast("long").alias("n")),
        "stream_dedup": lambda s, d: run_to_end(without_repeats(event_stream(s, d)).select("event_id"), "append"),
        "stream_degrees": lambda s, d: run_to_end(degrees(event_stream(s, d))),
        "stream_degrees_state": lambda s, d: run_to_end(degrees_by_state(event_stream(s, d)), "update").groupBy("user_id").agg(F.max("degree").alias("degree")),
    }


def oracle_sql() -> dict[str, str]:
    from semigrid.sources.fixtures import SQL

    ue = "SELECT user_id AS u, event_type AS e, count(*) AS v FROM events GROUP BY 1, 2"
    return {
        "stream_product": f"SELECT a.e AS i, b.e AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM ({ue}) a JOIN ({ue}) b ON a.u = b.u GROUP BY 1, 2",
        "stream_user_hours": SQL["UH"],
        "stream_sessions": "SELECT user_id, CAST(sum(fresh) AS BIGINT) AS sessions, count(*) AS n FROM (SELECT user_id, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) t GROUP BY user_id",
        "stream_dedup": "SELECT DISTINCT event_id FROM events",
        "stream_degrees": "SELECT user_id, count(*) AS degree FROM events GROUP BY user_id",
        "stream_degrees_state": "SELECT user_id, count(*) AS degree FROM events GROUP BY user_id",
    }
