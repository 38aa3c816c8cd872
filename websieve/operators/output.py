"""Plans for files: how many, in which chunks, within which budget."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def file_plan(docs: DataFrame, modelled: list[str]) -> DataFrame:
    """(shard_id, files): three files of a shard for each language with a model, one for each other language."""
    langs = docs.select("shard_id", "lang").distinct()
    return langs.groupBy("shard_id").agg(F.sum(F.when(F.col("lang").isin(*modelled), 3).otherwise(1)).alias("files"))


def chunk_plan(files: DataFrame, by: list[str], name_col: str, bytes_col: str, target: int) -> DataFrame:
    """``files`` with the number of the chunk of about ``target`` bytes that each joins, in order of name. A listing of files
    is small; rows of data are never numbered this way."""
    before = F.sum(bytes_col).over(W.partitionBy(*by).orderBy(name_col)) - F.col(bytes_col)
    return files.withColumn("chunk", F.floor(before / target).cast("long"))


def cap_corpus(docs: DataFrame, by: list[str], order: list[str], budgets: DataFrame, text_col: str = "text") -> DataFrame:
    """The first documents of each group, in the given order, whose bytes add up to the group's budget (``budget``) at most.
    The running sum sorts each group; only sizes and order columns need to be in ``docs`` for that, text may follow by a join."""
    sized = docs.withColumn("__bytes", F.octet_length(text_col).cast("long")).join(F.broadcast(budgets), by)
    run = F.sum("__bytes").over(W.partitionBy(*by).orderBy(*order))
    return sized.withColumn("__run", run).where(F.col("__run") <= F.col("budget")).drop("__bytes", "__run", "budget")
