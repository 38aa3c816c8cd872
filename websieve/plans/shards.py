"""Assignment of rows and files to shards."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def assign_by_id(df: DataFrame, id_col: str, n: int) -> DataFrame:
    return df.withColumn("shard_id", F.pmod(F.col(id_col), F.lit(n)).cast("int"))


def assign_by_hash(df: DataFrame, cols: list[str], n: int) -> DataFrame:
    return df.withColumn("shard_id", F.pmod(F.xxhash64(*cols), F.lit(n)).cast("int"))


def assign_by_bytes(files: DataFrame, name_col: str, bytes_col: str, target: int = 5_000_000_000) -> DataFrame:
    """Files in order of name are filled into shards of about ``target`` bytes. For listings of files, which are small;
    the running sum is over one partition."""
    before = F.sum(bytes_col).over(W.orderBy(name_col)) - F.col(bytes_col)
    return files.select(name_col, bytes_col, F.floor(before / target).cast("int").alias("shard_id"))
