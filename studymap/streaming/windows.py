"""Streaming forms over the events table. Each query runs the stream to its end (availableNow) and returns what the sink holds, to be compared with the batch twin."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.lineage import cut, fresh_path

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream, their time as a timestamp that can carry a watermark."""
    return spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a bounded stream to its end into Parquet files of the shared folder: all batches in append mode, the last one in complete mode. A repeated batch overwrites its own files."""
    spark, folder, done = stream.sparkSession, fresh_path(stream.sparkSession, "sink"), []

    def write(df: DataFrame, batch: int):
        df.write.mode("overwrite").parquet(f"{folder}/batch={batch}")
        done.append(batch)

    q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{folder}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema)
    held = spark.read.schema(stream.schema)
    return held.parquet(f"{folder}/batch={max(done)}") if mode == "complete" else held.parquet(folder).select(*stream.columns)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sliding(events: DataFrame, width: str = "2 hours", slide: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width, slide)).agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def open_studies(events: DataFrame, gap_ms: int) -> DataFrame:
    """(user_id, start, n, label): a study is a run of a user's events without a gap of `gap_ms`; its events vote by their type, and the one most frequent type decides (null on ties).

    A study leaves when a later event of the same user follows a gap, inside a batch too, or when the watermark has passed its last event by the gap. Studies still open
    when the input ends stay in the state for the next run. Rows with a null user, time or type take no part. Needs a watermark on ts. State is a count for each type.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def decided(user, study):
        first, _, votes = study
        best = max(votes.values())
        winners = [v for v, k in votes.items() if k == best]
        return user, first, sum(votes.values()), winners[0] if len(winners) == 1 else None

    def table(rows):
        return pd.DataFrame(rows, columns=["user_id", "start_us", "n", "label"])

    def step(key, batches, state: GroupState):
        first, last, votes = state.get if state.exists else (0, 0, "{}")
        study = [first, last, json.loads(votes)] if state.exists else None
        if state.hasTimedOut:
            state.remove()
            yield table([decided(key[0], study)])
            return
        out, x = [], pd.concat([b[["us", "event_type"]] for b in batches]).sort_values("us")
        for us, kind in zip(x["us"].tolist(), x["event_type"].tolist()):
            if study and us - study[1] >= gap_ms * 1000:
                out.append(decided(key[0], study))
                study = None
            study = study or [us, us, {}]
            study[0], study[1] = min(study[0], us), max(study[1], us)
            study[2][kind] = study[2].get(kind, 0) + 1
        state.update((study[0], study[1], json.dumps(study[2])))
        state.setTimeoutTimestamp(max(study[1] // 1000 + gap_ms, state.getCurrentWatermarkMs() + 1))
        if out:
            yield table(out)

    x = events.where("user_id IS NOT NULL AND ts IS NOT NULL AND event_type IS NOT NULL").withColumn("us", F.unix_micros("ts"))
    x = x.groupBy("user_id").applyInPandasWithState(step, "user_id long, start_us long, n long, label string", "first long, last long, votes string", "append", GroupStateTimeout.EventTimeTimeout)
    return x.select("user_id", F.timestamp_micros("start_us").alias("start"), "n", "label")


def for_each_batch(stream: DataFrame, per_batch, folder: str) -> DataFrame:
    """Run a batch function on every micro-batch; results are written under their batch id, so a repeated batch overwrites its own rows only."""
    def write(df: DataFrame, batch: int):
        per_batch(df).write.mode("overwrite").parquet(f"{folder}/batch={batch}")

    q = stream.writeStream.foreachBatch(write).trigger(availableNow=True).option("checkpointLocation", f"{folder}-state").start()
    q.awaitTermination()
    return cut(stream.sparkSession.read.parquet(folder).drop("batch"))
