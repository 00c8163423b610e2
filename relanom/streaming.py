"""Event streams: windowed counts with late rows, pair novelty with state, scoring by frozen rules."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relanom.sources import shared

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """File stream of events with an explicit schema; time becomes a TIMESTAMP, which watermarks need."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def finished(df: DataFrame, mode: str, spark: SparkSession) -> DataFrame:
    """Run a stream over what there is and return its result table, which tasks write to the shared folder and nothing brings to the driver."""
    at = f"{shared(spark)}/stream-{uuid.uuid4().hex}"
    out = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{at}/state")
    if mode == "append":
        out = out.format("parquet").option("path", f"{at}/rows")
    else:
        # Every batch gives the whole result anew, so the last one stays.
        out = out.foreachBatch(lambda rows, _: rows.write.mode("overwrite").parquet(f"{at}/rows"))
    spark.createDataFrame([], df.schema).write.parquet(f"{at}/rows")
    out.start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{at}/rows")


def windows(events: DataFrame, kind: str = "tumbling") -> DataFrame:
    """Counts per type in tumbling or sliding windows, or per user in sessions."""
    late = events.withWatermark("ts", "1 hour")
    if kind == "session":
        g = late.groupBy(F.session_window("ts", "2 hours").alias("w"), "user_id")
    else:
        g = late.groupBy(F.window("ts", "1 day", "12 hours" if kind == "sliding" else "1 day").alias("w"), "event_type")
    return g.agg(F.count("*").alias("n"))


def novelty(events: DataFrame) -> DataFrame:
    """(event_id, novel): whether the user's machine is new to the user; state is one set of machines per user."""

    def run(key, frames, state):
        seen = set(state.get[0]) if state.exists else set()
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for event, machine in zip(rows["event_id"], rows["machine"]):
            out.append((event, machine not in seen))
            seen.add(machine)
        state.update((sorted(seen),))
        yield pd.DataFrame(out, columns=["event_id", "novel"])

    rows = events.withColumn("machine", F.get_json_object("props", "$.k").cast("int")).select("event_id", "ts", "user_id", "machine")
    return rows.groupBy("user_id").applyInPandasWithState(run, "event_id long, novel boolean", "machines array<int>", "append", "NoTimeout")


def joined_logs(events: DataFrame, minutes: int = 10) -> DataFrame:
    """(event_id, before_id): authentications with the same user's process rows of the ``minutes`` before, as two joined streams.

    Repeated events are dropped within the watermark; the time condition bounds the state of both sides.
    """
    once = events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    auth = once.filter(F.col("event_type").isin("signup", "purchase")).select("event_id", F.col("user_id").alias("u"), F.col("ts").alias("t"))
    process = once.filter("event_type = 'click'").select(F.col("event_id").alias("before_id"), "user_id", "ts")
    near = (F.col("u") == F.col("user_id")) & (F.col("ts") <= F.col("t")) & (F.col("ts") >= F.col("t") - F.expr(f"interval {minutes} minutes"))
    return auth.join(process, near).select("event_id", "before_id")


def scored(events: DataFrame, rule_set) -> DataFrame:
    """Frozen rules on each event: stateless, the rules are literals of the plan."""
    return events.select("event_id", rule_set.score().alias("score"))
