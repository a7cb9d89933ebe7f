"""Monitoring jobs over a stream of response logs, and the batch queries they must agree with.

A row of ``events`` stands for one response: an error is a failed one, its value a latency, its user a question group.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LATE, GAP = "1 day", "12 hours"


def source(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """``path``: a folder, or a single file written as a pattern (``events.parque[t]``), which streams also take."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path)


def _marked(df: DataFrame) -> DataFrame:
    """State of a stream ends a day after the latest time seen; a batch needs no watermark."""
    return df.withWatermark("ts", LATE) if df.isStreaming else df


def tumbling(df: DataFrame) -> DataFrame:
    return _marked(df).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("sd"), F.count("*").alias("n")).select(
        F.col("w.start").alias("start"), "mean", "sd", "n")


def sliding(df: DataFrame) -> DataFrame:
    return _marked(df).groupBy(F.window("ts", "1 hour", "15 minutes").alias("w")).agg(F.avg((F.col("event_type") == "error").cast("double")).alias("error_rate"), F.count("*").alias("n")).select(
        F.col("w.start").alias("start"), "error_rate", "n")


def sessions(df: DataFrame, gap: str = GAP) -> DataFrame:
    return _marked(df).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"), F.max("value").alias("slowest")).select(
        "user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "slowest")


def closed(df: DataFrame, batch: DataFrame, end: F.Column) -> DataFrame:
    """The rows of a batch result that a stream in append mode has written: those whose window ended a day before the
    latest time. One row goes to all tasks."""
    latest = df.agg(F.max("ts").alias("__latest"))
    return batch.join(F.broadcast(latest), end <= F.col("__latest") - F.expr(f"INTERVAL {LATE}")).drop("__latest")


def deduplicated(df: DataFrame) -> DataFrame:
    return _marked(df).dropDuplicatesWithinWatermark(["event_id"]) if df.isStreaming else df.dropDuplicates(["event_id"])


def bought_after_signup(df: DataFrame) -> DataFrame:
    """Purchases within an hour of the same user's signup."""
    a = df.where("event_type = 'signup'").select(F.col("user_id").alias("u"), F.col("ts").alias("signed"))
    b = df.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought"), "event_id")
    if df.isStreaming:
        a, b = a.withWatermark("signed", LATE), b.withWatermark("bought", LATE)
    return a.join(b, F.expr("u = user_id AND bought > signed AND bought <= signed + INTERVAL 1 HOUR")).select("user_id", "signed", "bought", "event_id")


def with_segment(df: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream rows beside a static table's: each event with its user's segment; users that are no customers keep none."""
    known = customers.select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return df.join(known, "user_id", "left").select("event_id", "user_id", "segment")


def runs_of_three(df: DataFrame) -> DataFrame:
    """Users with three responses in a row that were no errors, as a stateful operator: first such moment per user."""
    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        run, done = state.get if state.exists else (0, False)
        hit = None
        for e in pd.concat(list(frames)).sort_values(["ts", "event_id"]).itertuples():
            run = 0 if e.event_type == "error" else run + 1
            if run >= 3 and not done:
                done, hit = True, e.ts
        state.update((run, done))
        if hit is not None:
            yield pd.DataFrame({"user_id": [key[0]], "reached": [hit]})

    return df.groupBy("user_id").applyInPandasWithState(step, "user_id long, reached timestamp", "run long, done boolean", "append", GroupStateTimeout.NoTimeout)


def runs_of_three_batch(df: DataFrame) -> DataFrame:
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    ok = df.withColumn("ok", (F.count("*").over(w) == 3) & (F.max((F.col("event_type") == "error").cast("int")).over(w) == 0))
    return ok.where("ok").groupBy("user_id").agg(F.min("ts").alias("reached"))


def late_rows(df: DataFrame, limit: str = LATE, span: int = 65_536) -> DataFrame:
    """Rows behind the highest time seen before them in order of arrival (id), by more than the watermark: those a
    stream would drop. The highest time runs over spans of ids first (a row each), then inside each span."""
    from pyspark.sql import Window

    parts = df.withColumn("part", F.floor(F.col("event_id") / span))
    upto = parts.groupBy("part").agg(F.max("ts").alias("top")).withColumn("base", F.max("top").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))
    inside = F.max("ts").over(Window.partitionBy("part").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1))
    rows = parts.withColumn("seen", inside).join(upto.select("part", "base"), "part").withColumn("high", F.greatest("seen", "base"))
    return rows.agg(F.sum(F.coalesce(F.col("ts") < F.col("high") - F.expr(f"INTERVAL {limit}"), F.lit(False)).cast("long")).alias("late"), F.count("*").alias("n"))


def drained(spark: SparkSession, stream: DataFrame, path: str) -> DataFrame:
    """Runs a stream over all that is there, in append mode into files, and returns what it wrote; a repeated run goes on
    where the last one stopped. No row passes the driver."""
    q = (stream.writeStream.format("parquet").outputMode("append").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start())
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def scored_batches(stream: DataFrame, score, path: str, checkpoint: str):
    """Scores each micro-batch with ``score`` (a DataFrame function) and appends it under its batch number, so that a
    repeated batch replaces itself."""
    def one(df: DataFrame, number: int) -> None:
        score(df).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
