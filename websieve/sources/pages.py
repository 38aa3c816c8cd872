"""Pages as JSON lines, one entry for each page, compressed; and the corpus sink by language and bucket."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import schemas


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share, from ``spark.checkpoint.dir``. Where none is set, a local master gets a temporary one; on a
    cluster, whose machines would not see it, that is an error."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return (where or "file://" + tempfile.mkdtemp(prefix="websieve-")).rstrip("/")


def shared_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/websieve-{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str) -> DataFrame:
    """Write to the shared folder and read again: cuts lineage. What was shuffled for it is deleted once the driver collects its garbage, so it does that here."""
    path = shared_path(df.sparkSession, label)
    df.write.option("compression", "zstd").parquet(path)
    df.sparkSession.sparkContext._jvm.System.gc()
    return df.sparkSession.read.schema(df.schema).parquet(path)


def free_shuffles(spark: SparkSession) -> None:
    """Lets the driver find which tables nobody holds any more, so that what was shuffled for them is deleted."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def write_pages_json(pages: DataFrame, path: str) -> None:
    pages.write.mode("overwrite").json(path, compression="gzip")


def read_pages_json(spark: SparkSession, path: str) -> DataFrame:
    """Pages with a fixed schema; lines that do not parse keep their text in ``_corrupt``."""
    return spark.read.schema(schemas.PAGE_JSON).option("columnNameOfCorruptRecord", "_corrupt").json(path)


def json_roundtrip(pages: DataFrame) -> DataFrame:
    path = shared_path(pages.sparkSession, "pages-json")
    write_pages_json(pages, path)
    return read_pages_json(pages.sparkSession, path)


def write_corpus(corpus: DataFrame, path: str, *, records_per_file: int = 0, text_format: str = "json") -> None:
    """One folder for each (lang, bucket). Rows of a folder are brought together first, split evenly where one is large, so
    that no task writes a sliver to every folder."""
    writer = corpus.repartition("lang", "bucket", F.pmod(F.xxhash64(*[c for c in corpus.columns if c not in ("lang", "bucket", "text")]), F.lit(8)))
    out = writer.write.mode("overwrite").partitionBy("lang", "bucket")
    if records_per_file:
        out = out.option("maxRecordsPerFile", records_per_file)
    out.format(text_format).option("compression", "gzip" if text_format == "json" else "zstd").save(path)


def sink_bytes(spark: SparkSession, path: str) -> DataFrame:
    """(file, bytes) of a written sink, listed by Spark's file source without reading contents."""
    listed = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", "length")
    return listed.select(F.col("path").alias("file"), F.col("length").alias("bytes"))
