"""Shards that arrive one by one: dedup against a growing index of keys, scoring by frozen models, routing by bucket."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import dedup, paragraphs
from ..sources.pages import shared_path


def shard_stream(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


class IncrementalDedup:
    """Keep-first over batches: a paragraph stays if its key is in no earlier batch and first in its own. Keys and survivors
    of a batch go to a folder of the batch's number, which a repeated batch overwrites, so restarts give no duplicates."""

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.root = root or shared_path(spark, "key-index")

    def __call__(self, batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        keys = dedup.keyed(paragraphs.explode(batch, shard=F.col("shard_id")))
        fresh = dedup.build_index(keys, dedup.All()).select("h64", F.col("first_pos").alias("pos"))
        earlier = [f"{self.root}/batch={i}" for i in range(number)]
        if earlier:
            fresh = fresh.join(spark.read.schema("h64 long, pos long").parquet(*earlier).select("h64"), "h64", "left_anti")
        fresh.write.mode("overwrite").parquet(f"{self.root}/batch={number}")

    def survivors(self, spark: SparkSession) -> DataFrame:
        return spark.read.schema("h64 long, pos long").parquet(self.root).select("pos")

    def run(self, stream: DataFrame) -> "IncrementalDedup":
        checkpoint = shared_path(stream.sparkSession, "dedup-state")
        stream.writeStream.foreachBatch(self).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
        return self


def route(stream: DataFrame, score: Callable[[DataFrame], DataFrame], cuts: DataFrame, path: str) -> None:
    """Frozen models: each batch is scored (doc_id, lang, ppl, text), bucketed by broadcast cuts and appended by language and bucket."""
    from ..operators import buckets

    def write(batch: DataFrame, number: int) -> None:
        out = buckets.assign(score(batch), cuts)
        out.write.mode("overwrite").partitionBy("lang", "bucket").parquet(f"{path}/batch={number}")

    checkpoint = shared_path(stream.sparkSession, "route-state")
    stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
