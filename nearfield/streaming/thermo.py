"""Streams of readings: windowed temperatures, late data, and a thermostat that keeps state for each system."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..sources.tables import utc


def readings(spark, sf_dir: str, stream: bool = True) -> DataFrame:
    """The events table as a stream (or batch) of user_id, ts with a zone, value."""
    path = f"{sf_dir}/events.parquet"
    batch = spark.read.parquet(path)
    df = spark.readStream.schema(batch.schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir) if stream else batch
    return df.select("event_id", "user_id", utc("ts").alias("ts"), "value")


def temperature(df: DataFrame, window, late: str = "1 hour") -> DataFrame:
    """(start, end, n, temperature): mean of value^2 (half kB T a degree of freedom, kB = 1, unit mass) by window."""
    w = df.withWatermark("ts", late).groupBy(window.alias("w"))
    out = w.agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("value") * F.col("value")).alias("temperature"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "temperature")


def tumbling(df: DataFrame, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    return temperature(df, F.window("ts", length), late)


def sliding(df: DataFrame, length: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    return temperature(df, F.window("ts", length, step), late)


def sessions(df: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """(user_id, start, end, n, temperature) of stretches of readings with no longer gap."""
    w = df.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w"))
    out = w.agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("value") * F.col("value")).alias("temperature"))
    return out.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "temperature")


def with_masses(df: DataFrame, masses: DataFrame) -> DataFrame:
    """Stream-static join: (user_id, mass) beside each reading; 1 where it has none."""
    return df.join(masses, "user_id", "left").withColumn("mass", F.coalesce("mass", F.lit(1.0)))


def paired_readings(a: DataFrame, b: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join of readings of one user at most ``within`` apart, the second no earlier than the first."""
    left = a.withWatermark("ts", within).select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), F.col("event_id").alias("e1"), F.col("value").alias("v1"))
    right = b.withWatermark("ts", within).select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("e2"), F.col("value").alias("v2"))
    return left.join(right, F.expr(f"u = user_id AND t2 >= t1 AND t2 <= t1 + INTERVAL {within} AND e1 <> e2"))


STATE = "n long, sum_v2 double, gamma double"
OUT = "user_id long, n long, temperature double, gamma double"


def thermostat(df: DataFrame, target: float, rate: float = 0.01) -> DataFrame:
    """(user_id, n, temperature, gamma) after each batch of a user's readings: running temperature and friction.

    State is three numbers a user. Friction rises while the running temperature is above the target, never below 0.
    Within a batch readings count in time order.
    """

    def update(key: tuple, frames: Iterable[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total, gamma = state.get if state.exists else (0, 0.0, 0.0)
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        for v in rows["value"]:
            n, total = n + 1, total + v * v
            gamma = max(0.0, gamma + rate * (total / n / target - 1))
        state.update((n, total, gamma))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "temperature": [total / n], "gamma": [gamma]})

    return df.groupBy("user_id").applyInPandasWithState(update, OUT, STATE, "update", GroupStateTimeout.NoTimeout)


def upsert_by_step(path: str):
    """A foreachBatch sink that writes each batch into a folder of its own number: a repeated batch replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def run_to_memory(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return its result table."""
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)
