"""Operators on streams; each takes and returns a DataFrame, streaming or not."""

from __future__ import annotations

import time
from uuid import uuid4

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupStateTimeout

from fuzzyfeat.operators.fcm import FcmModel, advance, round_sums
from fuzzyfeat.session import prepare, remove, shared_folder


def tumbling(events: DataFrame, width: str = "1 day", late: str = "2 days") -> DataFrame:
    """Rows and mean value of each window and type."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean_value")).select(F.col("w.start").alias("window_start"), "event_type", "n", "mean_value")


def alert_rate(scored: DataFrame, width: str = "2 days", slide: str = "1 day", late: str = "2 days") -> DataFrame:
    """Share of alerts of each sliding window."""
    return scored.withWatermark("ts", late).groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n"), F.avg(F.col("alert").cast("double")).alias("alert_rate")).select(F.col("w.start").alias("window_start"), "n", "alert_rate")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """Bursts of each user: events no farther apart than the gap."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("session_start"), "n")


def dedup(events: DataFrame, keys: list[str], late: str = "10 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys) if events.isStreaming else events.dropDuplicates(keys)


def rolling_rates(predictions: DataFrame, truth: DataFrame, within: str = "1 day") -> DataFrame:
    """Predictions beside the truth that arrives at most `within` later."""
    p, t = predictions.withWatermark("ts", within).alias("p"), truth.withWatermark("truth_ts", within).alias("t")
    return p.join(t, F.expr(f"p.event_id = t.truth_id AND truth_ts BETWEEN ts AND ts + interval {within}"))


def drift(scored: DataFrame, width: str = "1 day", late: str = "2 days") -> DataFrame:
    """Mean strength and cluster counts of each window, to hold against training."""
    return scored.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "z").agg(F.count("*").alias("n"), F.avg("b").alias("mean_b")).select(F.col("w.start").alias("window_start"), "z", "n", "mean_b")


USER_STATE = T.StructType([T.StructField("user_id", T.LongType()), T.StructField("n", T.LongType()), T.StructField("last_seen", T.TimestampType()), T.StructField("top", T.DoubleType())])


def user_state(events: DataFrame) -> DataFrame:
    """Running totals of each user over the whole stream; a row for each user that a batch touches."""
    rows = events.filter("user_id IS NOT NULL").select(F.col("user_id").cast("long").alias("user_id"), "ts", F.col("value").cast("double").alias("value"))

    def step(key, parts, state):
        n, last, top = state.get if state.exists else (0, None, None)
        for part in parts:
            n += len(part)
            last = max(x for x in (last, part["ts"].max().to_pydatetime()) if x is not None)
            top = max(x for x in (top, float(part["value"].max())) if x is not None)
        state.update((n, last, top))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_seen": [last], "top": [top]})

    return rows.groupBy("user_id").applyInPandasWithState(step, USER_STATE, "n long, last_seen timestamp, top double", "update", GroupStateTimeout.NoTimeout)


def refresh(packed: DataFrame, model: FcmModel, n_levels: list[int], decay: float = 0.8) -> FcmModel:
    """Centroids that follow a stream of packed rows (row_id, x, s): each micro-batch adds its sums to the decayed ones of those before."""
    spark = prepare(packed.sparkSession)
    moved = FcmModel(model.centroids, model.gains_num, model.gains_cat, model.alpha, model.unknown)
    held: list[np.ndarray] = []

    def step(batch: DataFrame, number: int) -> None:
        total = round_sums(batch.withColumn("weight", F.lit(1.0)), {moved.centroids.k: moved.centroids}, moved, n_levels)[moved.centroids.k]
        held[:] = [total + (decay * held[0] if held else 0)]
        advance(moved, held[0], n_levels, 0.0, "objective")

    folder = f"{shared_folder(spark).rstrip('/')}/stream-{uuid4().hex}"
    packed.writeStream.option("checkpointLocation", folder).trigger(availableNow=True).foreachBatch(step).start().awaitTermination()
    remove(spark, folder)
    return moved


def replay(batches: list[DataFrame]) -> DataFrame:
    """The tables as a stream, one micro-batch each, in their order."""
    spark: SparkSession = batches[0].sparkSession
    folder = f"{shared_folder(spark).rstrip('/')}/stream-{uuid4().hex}"
    for number, df in enumerate(batches):
        df.coalesce(1).write.mode("append").parquet(folder)
        if number + 1 < len(batches):
            time.sleep(1.1)  # files are taken in order of their times, which some stores keep in seconds
    return spark.readStream.schema(batches[0].schema).option("maxFilesPerTrigger", 1).parquet(folder)


def score(stream: DataFrame, model) -> DataFrame:
    """The operation phase: stateless, the same projection as in batch."""
    return model.transform(stream)


def run_once(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Drain what a source holds and return the table that came out. Final for windows too: they close when the stream ends."""
    spark: SparkSession = stream.sparkSession
    folder = f"{shared_folder(spark).rstrip('/')}/stream-{uuid4().hex}"
    collected: list[int] = []
    if mode == "update":
        # the last row of each key holds: batches are numbered as they come
        def add(batch: DataFrame, number: int) -> None:
            batch.withColumn("__batch", F.lit(number)).write.mode("overwrite").parquet(f"{folder}/out/{number}")
            collected.append(number)

        stream.writeStream.outputMode("update").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).foreachBatch(add).start().awaitTermination()
        if not collected:
            return spark.createDataFrame([], stream.schema)
        rows = spark.read.parquet(*(f"{folder}/out/{n}" for n in sorted(set(collected))))
        last = F.max_by(F.struct(*stream.columns), "__batch").alias("r")
        return rows.groupBy(stream.columns[0]).agg(last).select("r.*")
    if mode == "append":
        stream.writeStream.outputMode("append").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).format("parquet").option("path", f"{folder}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/{number}")
        collected[:] = [number]

    stream.writeStream.outputMode("complete").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out/{collected[0]}") if collected else spark.createDataFrame([], stream.schema)
