"""Streams over the repository: windows over events, and key histograms kept up to date."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.files import shared_folder


def file_stream(spark: SparkSession, path: str, schema: T.StructType, files_per_batch: int = 1) -> DataFrame:
    """Parquet files of a folder as a stream; timestamps without zone get the session's."""
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    zoned = [F.col(f.name).cast("timestamp").alias(f.name) if isinstance(f.dataType, T.TimestampNTZType) else F.col(f.name) for f in schema.fields]
    return stream.select(*zoned)


def run_to_end(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """The stream run over all that is there, written to the shared folder and read as a table.

    Complete results overwrite their table with every batch; appended and updated ones
    collect.  ``complete_by_update`` collects updates and keeps the last one of a window.
    """
    spark = stream.sparkSession
    out, state = shared_folder(spark, f"{name}-out"), shared_folder(spark, f"{name}-state")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    elif mode == "complete":
        write: Callable = lambda df, _: df.write.mode("overwrite").parquet(out)
        stream.writeStream.foreachBatch(write).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    else:
        add: Callable = lambda df, batch: df.withColumn("batch", F.lit(int(batch))).write.mode("append").parquet(out)
        stream.writeStream.foreachBatch(add).option("checkpointLocation", state).outputMode("update").trigger(availableNow=True).start().awaitTermination()
        rows = spark.read.parquet(out)
        if mode == "complete_by_update":
            keys = [c for c in stream.columns if c != "n"]
            return rows.groupBy(*keys).agg(F.max_by("n", "batch").alias("n"))
        return rows
    return spark.read.schema(stream.schema).parquet(out)


def run_batches(stream: DataFrame, name: str, batches: int) -> DataFrame:
    """The first ``batches`` micro batches of an endless stream, written and read as a table."""
    spark = stream.sparkSession
    out, state = shared_folder(spark, f"{name}-out"), shared_folder(spark, f"{name}-state")

    def write(df: DataFrame, batch: int) -> None:
        if batch < batches:
            df.write.mode("append").parquet(out)

    running = stream.writeStream.foreachBatch(write).option("checkpointLocation", state).trigger(processingTime="100 milliseconds").start()
    while running.isActive and (running.lastProgress is None or running.lastProgress["batchId"] + 1 < batches):
        running.awaitTermination(1)
    running.stop()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(events: DataFrame, width: str, late: str) -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 3).alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str, step: str, late: str) -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str, late: str) -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def without_repeats(events: DataFrame, late: str) -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join."""
    return events.join(customers, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")


def key_counts(events: DataFrame) -> DataFrame:
    """The key histogram of a growing table: what edge statistics need of it, merged batch by batch."""
    return events.groupBy(F.col("user_id").alias("k")).agg(F.count(F.lit(1)).alias("c"))


def daily(events: DataFrame, late: str) -> DataFrame:
    """Events a day; a day that the watermark has passed takes no more."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def followed_by(left: DataFrame, right: DataFrame, width: str, late: str) -> DataFrame:
    """Stream-stream join: events with later ones of the same user within an interval; state older than it goes."""
    a = left.withWatermark("ts", late).select(F.col("user_id").alias("user_a"), F.col("ts").alias("ts_a"))
    b = right.withWatermark("ts", late).select(F.col("user_id").alias("user_b"), F.col("ts").alias("ts_b"), "value")
    return a.join(b, F.expr(f"user_a = user_b AND ts_b > ts_a AND ts_b <= ts_a + INTERVAL {width}")).select(F.col("user_a").alias("user_id"), "ts_a", "ts_b", "value")


def user_state(events: DataFrame) -> DataFrame:
    """(user_id, n, total, top) of each user whenever a batch has events of theirs: state kept by key."""
    import pandas as pd

    def step(key, batches, state):
        n, total, top = state.get if state.exists else (0, 0.0, float("-inf"))
        for pdf in batches:
            n, total, top = n + len(pdf), total + float(pdf["value"].sum()), max(top, float(pdf["value"].max()))
        state.update((n, total, top))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total], "top": [top]})

    schema = "user_id long, n long, total double, top double"
    return events.select("user_id", "value").groupBy("user_id").applyInPandasWithState(step, schema, "n long, total double, top double", "update", "NoTimeout")
