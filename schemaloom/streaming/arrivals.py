"""Structured Streaming over arriving events and tables, run until what is there is read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from schemaloom.sources.shared import shared_path


def arriving(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """A file stream of the rows."""
    path = shared_path(spark, name)
    df.write.parquet(path)
    return spark.readStream.schema(df.schema).parquet(path)


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """What the stream has written once all input is read. Append and complete modes alone: the sink is a table of
    files in the shared folder, written batch by batch under the batch's number, so a repeated batch replaces itself."""
    spark = stream.sparkSession
    out, state = shared_path(spark, f"{name}-out"), shared_path(spark, f"{name}-state")

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={number}")

    stream.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    found = spark.read.schema(stream.schema).parquet(out)
    return found.select(stream.columns)


def timed(events: DataFrame) -> DataFrame:
    """Watermarks need an instant, not a local time."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    return stream.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"))


def sliding(stream: DataFrame, width: str = "1 hour", step: str = "30 minutes") -> DataFrame:
    return stream.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n"))


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


def first_sightings(stream: DataFrame, key: str, delay: str = "10 days") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def edge_weights(paths: DataFrame) -> DataFrame:
    """Weights of is-a edges as tables arrive: counts, so any order of arrival gives the same."""
    from schemaloom.operators.hierarchy import merge_edges, path_edges

    return merge_edges(path_edges(paths))


def follow_ups(signups: DataFrame, purchases: DataFrame, within: str = "1 day") -> DataFrame:
    """(signup_id, event_id) of purchases by the same user within a time of a signup. State older than that is let go."""
    s = signups.where("event_type = 'signup'").select(F.col("event_id").alias("signup_id"), F.col("user_id").alias("u"), F.col("ts").alias("at")).withWatermark("at", "1 hour")
    p = purchases.where("event_type = 'purchase'").select("event_id", "user_id", "ts").withWatermark("ts", "1 hour")
    return p.join(s, F.expr(f"user_id = u AND ts >= at AND ts <= at + INTERVAL {within}")).select("signup_id", "event_id")


def profiles(stream: DataFrame, key: str, counted: str, checked: str, parts: int = 64) -> DataFrame:
    """(key, part, cells, missing, users) after each batch: rows, rows without `checked`, distinct values of `counted`, of
    one part of a key's rows. Equal values are in one part, so a key's counts are the sums of its parts' last ones, and no
    state holds more than its share of the values: two counts and a hash of 16 bytes for each distinct one."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def run(of, frames, state: GroupState):
        cells, missing, held = state.get if state.exists else (0, 0, b"")
        seen = [np.frombuffer(bytes(held), "V16")]
        for frame in frames:
            cells += len(frame)
            missing += int(frame["gap"].sum())
            seen.append(np.frombuffer(b"".join(frame["digest"].dropna().unique()), "V16"))
        known = np.array(sorted(set(np.concatenate(seen).tolist())), "V16")
        state.update((cells, missing, known.tobytes()))
        yield pd.DataFrame({key: [of[0]], "part": [of[1]], "cells": [cells], "missing": [missing], "users": [len(known)]})

    value = F.col(counted).cast("string")
    rows = stream.select(key, F.pmod(F.xxhash64(counted), F.lit(parts)).cast("int").alias("part"), F.unhex(F.md5(value)).alias("digest"), F.col(checked).isNull().alias("gap"))
    return rows.groupBy(key, "part").applyInPandasWithState(run, f"{key} string, part int, cells long, missing long, users long", "cells long, missing long, held binary", "Append", GroupStateTimeout.NoTimeout)
