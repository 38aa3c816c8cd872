"""Windows, dedup and joins over a stream of events, as functions of streaming (or batch) DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import schemas
from ..sources.pages import shared_path


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Events of a folder of Parquet files, with a timestamp that watermarks accept."""
    stream = spark.readStream.schema(schemas.EVENT).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "30 days") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "30 minutes", late: str = "30 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "30 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def first_of_key(events: DataFrame, keys: list[str], late: str = "365 days") -> DataFrame:
    """Each key once, state kept for as long as the watermark says."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def with_static(events: DataFrame, table: DataFrame, on: str) -> DataFrame:
    return events.join(F.broadcast(table), on)


def interval_pairs(events: DataFrame, first: str, second: str, within: str = "6 hours", late: str = "30 days") -> DataFrame:
    """Stream-stream join: pairs of events of one user, the second at most ``within`` after the first."""
    a = events.where(F.col("event_type") == first).select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta")).withWatermark("ta", late)
    b = events.where(F.col("event_type") == second).select(F.col("user_id").alias("user_b"), F.col("event_id").alias("b"), F.col("ts").alias("tb")).withWatermark("tb", late)
    return a.join(b, F.expr(f"user_id = user_b AND tb > ta AND tb <= ta + INTERVAL {within}")).select("a", "b")


def running_first(events: DataFrame) -> DataFrame:
    """Explicit state: for each user the first time seen and the number of events, after every batch."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, batches, state):
        first, n = state.get if state.exists else (None, 0)
        for pdf in batches:
            low = pdf["ts"].min()
            first, n = low if first is None else min(first, low), n + len(pdf)
        state.update((first, n))
        yield pd.DataFrame({"user_id": [key[0]], "first": [first], "n": [n]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, first timestamp, n long", "first timestamp, n long", "update", GroupStateTimeout.NoTimeout)


def collect_stream(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all files that are there, into Parquet in the shared folder, and return what it wrote: the last result of a
    stream that gives its whole result with every batch ("complete"), all rows of the others. No rows come to the driver."""
    spark = stream.sparkSession
    checkpoint, path = shared_path(spark, "stream-state"), shared_path(spark, "stream-out")
    writer = stream.writeStream.option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", path).start().awaitTermination()
    else:
        how = "overwrite" if mode == "complete" else "append"
        spark.createDataFrame([], stream.schema).write.parquet(path)  # a stream without files has no batch
        writer.foreachBatch(lambda batch, _: batch.write.mode(how).parquet(path)).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)
