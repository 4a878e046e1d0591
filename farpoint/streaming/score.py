"""Streams: scores by fitted models, windowed features, running deviations by user.

Sinks write to the shared folder, and availableNow triggers process what is there and stop, so a batch query can read the result.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from farpoint.session import fresh_path


def read_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's files as a stream; its time columns become TIMESTAMP, which watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    df = spark.readStream.schema(schema).parquet(f"{sf_dir}/{name}.parquet*")
    return df.withColumns({f.name: F.col(f.name).cast("timestamp") for f in schema if f.dataType == T.TimestampNTZType()})


def drain(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run over all there is and read the written result back. Update mode goes through foreachBatch, which adds a batch number."""
    spark = stream.sparkSession
    out, mark = fresh_path(spark, f"stream-{name}"), fresh_path(spark, f"mark-{name}")
    writer = stream.writeStream.option("checkpointLocation", mark).trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        query = writer.format("parquet").option("path", out).start()
    else:
        query = writer.foreachBatch(lambda df, n: df.withColumn("_batch", F.lit(n)).write.mode("append").parquet(out)).start()
    query.awaitTermination()
    schema = stream.schema if mode == "append" else T.StructType([*stream.schema.fields, T.StructField("_batch", T.IntegerType())])
    return spark.read.schema(schema).parquet(out)


def with_event_time(stream: DataFrame, column: str = "ts", delay: str = "1 hour") -> DataFrame:
    return stream.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, delay)


def score_stream(model, stream: DataFrame, ids: list[str], features: list[str]) -> DataFrame:
    """A fitted map-only model over a stream: the same projection as in batch."""
    from farpoint.model import FeatureFrame

    wide = stream.select(*ids, *(F.col(f).cast("double").alias(f) for f in features))
    return model.score(FeatureFrame(wide, tuple(ids), tuple(features)))


def windowed_features(stream: DataFrame, window: Column, by: list[str], value: str = "value") -> DataFrame:
    """Count, mean and maximum in event-time windows."""
    v = F.col(value).cast("decimal(18,4)")
    return stream.groupBy(window.alias("w"), *by).agg(F.count("*").alias("n"), F.sum(v).cast("double").alias("total"), F.max(value).alias("top")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n", "total", "top")


def window_zscores(stream: DataFrame, width: str, by: str, value: str = "value", id_col: str = "event_id") -> DataFrame:
    """(start, by, id, z) of every event of the closed event-time windows: its deviation from its window's mean in population standard deviations, null where these are 0.
    A window's events are collected as (id, value) pairs, so windows and groups must be of a size that fits a task."""
    events = F.collect_list(F.struct(F.col(id_col), F.col(value).alias("v")))
    closed = stream.groupBy(F.window("ts", width).alias("w"), by).agg(F.avg(value).alias("mean"), F.stddev_pop(value).alias("sd"), events.alias("events"))
    return closed.select(F.col("w.start").alias("start"), by, "mean", "sd", F.explode("events").alias("e")).select("start", by, F.col(f"e.{id_col}").alias(id_col), F.try_divide(F.col("e.v") - F.col("mean"), "sd").alias("z"))


def late_rows(query) -> int:
    """Rows that a stateful query left out because they came behind its watermark, over all its batches."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


STATE = "n long, mean double, m2 double"


def running_deviation(stream: DataFrame, least: int = 10) -> DataFrame:
    """(event_id, user_id, n_before, mean_before, flagged): each event against the running moments of its user's earlier events; flagged beyond three deviations once there are ``least`` of them. State is three numbers a user; a batch's events are taken in time order."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, mean, m2 = state.get if state.exists else (0, 0.0, 0.0)
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for event, value in zip(rows["event_id"], rows["value"]):  # each step needs the one before: Welford's update
            sd = (m2 / n) ** 0.5 if n else 0.0
            out.append((event, key[0], n, mean if n else None, bool(n >= least and abs(value - mean) > 3 * sd)))
            n += 1
            delta = value - mean
            mean += delta / n
            m2 += delta * (value - mean)
        state.update((n, mean, m2))
        yield pd.DataFrame(out, columns=["event_id", "user_id", "n_before", "mean_before", "flagged"])

    return stream.select("event_id", "user_id", "ts", "value").groupBy("user_id").applyInPandasWithState(step, "event_id long, user_id long, n_before long, mean_before double, flagged boolean", STATE, "append", GroupStateTimeout.NoTimeout)
