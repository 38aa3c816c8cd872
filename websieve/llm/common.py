"""Shared plumbing of the training-data operators: tables, written intermediates, worker set-up."""

from __future__ import annotations

import ctypes
import gc
import os
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

REPO_ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def workers_see_package(spark: SparkSession) -> None:
    """Python workers import this package by name; add the repository to their path when it is not there."""
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", os.environ.get("PYTHONPATH", ""))
    if REPO_ROOT not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (have, REPO_ROOT) if x)


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``. Where none is set, a local master gets a temporary one; on a cluster that is an
    error, for such a folder would be seen by one machine only."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        where = "file://" + tempfile.mkdtemp(prefix="websieve-")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(where)
    return where.rstrip("/")


def shared_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/websieve-{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str) -> DataFrame:
    """Write a table to the shared folder and read it again: cuts lineage and survives lost executors."""
    path = shared_path(df.sparkSession, label)
    bound_batches(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small_enough(df: DataFrame, rows: int) -> bool:
    """True when ``df`` has at most ``rows`` rows. Reads one row more than that and no further."""
    return df.limit(rows + 1).count() <= rows


def without_ids(df: DataFrame, id_col: str, ids: DataFrame, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Rows of ``df`` whose id is not in ``ids`` (one column, no nulls); the ids are broadcast when they are few."""
    gone = fresh("gone", df.columns)
    ids = written(ids.toDF(gone), "ids")
    side = F.broadcast(ids) if small_enough(ids, broadcast_rows) else ids
    return df.join(side, F.col(f"`{id_col}`") == F.col(gone), "left_anti")


def without_rows(df: DataFrame, id_col: str, text_col: str, rows: DataFrame, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Rows of ``df`` that are not in ``rows`` (doc_id, own), ``own`` being the text's xxhash64: rows of one id with other texts, and
    rows without id, are told apart."""
    gone, own = fresh("gone", df.columns), fresh("gone_own", df.columns)
    rows = written(rows.select(F.col("doc_id").alias(gone), F.col("own").alias(own)).distinct(), "rows")
    side = F.broadcast(rows) if small_enough(rows, broadcast_rows) else rows
    same = (F.xxhash64(F.col(f"`{text_col}`")) == F.col(own)) & F.col(f"`{id_col}`").eqNullSafe(F.col(gone))
    return df.join(side, same, "left_anti")


def ascii_lower(text: Column) -> Column:
    """Letters A to Z in lower case. Where a text has no others, the faster general function does the same."""
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value computed once, also where ``use`` names it many times or inside a lambda."""
    return F.transform(F.array(value), use)[0]


def fresh(name: str, taken: list[str]) -> str:
    """A column name like ``name`` that is not taken, whatever the input's columns are called."""
    lower = {c.lower() for c in taken}
    while name.lower() in lower:
        name += "_"
    return name


def id_residue(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id written as text, modulo ``modulus``; a null id has residue null."""
    return F.crc32(doc_id.cast("string").cast("binary")) % modulus


_LOADED: dict[str, dict] = {}


def loaded(owner: str) -> dict:
    """What a worker keeps between the tasks of one operator."""
    return _LOADED.setdefault(owner, {})


def forget_others(owner: str | None) -> None:
    """Drop what a worker keeps for other operators."""
    for other in [x for x in _LOADED if x != owner]:
        del _LOADED[other]


def map_batches(df: DataFrame, function: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: StructType | str, owner: str | None = None) -> DataFrame:
    """``df.mapInArrow`` in batches of bounded bytes, whose workers give their free memory back when a task ends: they live on beside
    the next tasks. Of what workers keep, only that ``loaded(owner)`` outlives the start of a task."""
    workers_see_package(df.sparkSession)
    bound_batches(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_others(owner)
        try:
            yield from function(batches)
        finally:
            give_back_memory()

    return df.mapInArrow(run, schema)


# Rows a batch of the Parquet reader, and bytes a batch between the JVM and Python workers: texts are long, so the defaults (4096 rows,
# 64 MB) make arrays of tens of megabytes for each task.
BATCH_SETTINGS = {"spark.sql.parquet.columnarReaderBatchSize": 1024, "spark.sql.execution.arrow.maxBytesPerBatch": 4 << 20}


def bound_batches(spark: SparkSession) -> None:
    """Lower the session's batch settings where they are higher; a single long text still makes a batch of its own."""
    for name, most in BATCH_SETTINGS.items():
        now = spark.conf.get(name, None)
        if now is None or not now.rstrip("bB").isdigit() or int(now.rstrip("bB")) > most:
            spark.conf.set(name, str(most))


def give_back_memory() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def give_back_heap(spark: SparkSession) -> None:
    """Executors collect their garbage and give free heap back to the system. A heap that an earlier stage has grown is else kept beside the
    Python workers of the next. One task a core; an executor that gets none keeps its heap, which costs memory and nothing else."""
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.reflect(F.lit("java.lang.System"), F.lit("gc")).alias("x")).write.format("noop").mode("overwrite").save()


def slices(batch: pa.RecordBatch, text: int, most_bytes: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Cut a batch where its texts (column ``text``) add up to about ``most_bytes``; one long text stays whole."""
    sizes = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False)
    ends, begun, at = np.cumsum(sizes, dtype=np.int64), 0, 0
    while at < batch.num_rows:
        end = max(at + 1, int(np.searchsorted(ends, begun + most_bytes, side="right")))
        yield batch.slice(at, end - at)
        begun, at = int(ends[end - 1]), end


class Words:
    """The words of a column of texts, each distinct word once.

    ``distinct`` holds the distinct words, ``codes`` their numbers in text order, and the words of text
    ``i`` are ``codes[bounds[i]:bounds[i + 1]]``. Nulls count as empty texts. Texts are cut at single
    spaces, so runs of spaces give empty words; with ``lines``, each line end is a word of its own.
    """

    def __init__(self, texts: pa.Array, lines: bool = False):
        texts = pc.fill_null(texts, "").cast(pa.large_string())
        if lines:
            texts = pc.replace_substring(texts, "\n", " \n ")
        parts = pc.split_pattern(texts, " ")
        coded = parts.flatten().dictionary_encode()
        self.distinct = coded.dictionary
        self.codes = coded.indices.to_numpy()
        self.bounds = np.concatenate([[0], np.cumsum(pc.list_value_length(parts).to_numpy(zero_copy_only=False))]).astype(np.int64)

    def sums(self, of_distinct: np.ndarray) -> np.ndarray:
        """For each text the sum over its words of a value given for each distinct word."""
        total = np.concatenate([[0], np.cumsum(of_distinct[self.codes])])
        return total[self.bounds[1:]] - total[self.bounds[:-1]]


class BoundedCache(dict):
    """A dict of strings to small values that holds about ``most_bytes``, each entry being taken for the length of its key and ``entry_bytes``. Where it
    is full, the eighth that was put first goes; a working set that fits is never put twice."""

    def __init__(self, most_bytes: int, entry_bytes: int = 180):
        super().__init__()
        self.most, self.entry_bytes, self.held = most_bytes, entry_bytes, 0

    def put(self, key, value) -> None:
        cost = self.entry_bytes + len(key)
        if self.held + cost > self.most:
            for gone in list(islice(self, 1 + len(self) // 8)):
                del self[gone]
                self.held -= self.entry_bytes + len(gone)
        if self.held + cost <= self.most:
            self[key] = value
            self.held += cost
