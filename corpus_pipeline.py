"""The corpus pipeline: stages over ``documents``, each written as Parquet and read again.

Every stage works on all that its predecessor kept, and each is judged by the rows it gets:
toxic documents go; lines that are boilerplate of their source go from the texts; of each group of near copies the
document with the smallest id stays; documents that hold a window of a benchmark item go; the rest is packed. All stages
but the last return the columns of ``documents``, with ``n_chars`` following the text.

Edge cases, in every stage: an empty table gives an empty one; null and empty texts are clean, are nobody's copy and stay; rows with a
null id, or that repeat an id, are told apart by their texts; further columns come along, whatever their names; a text is held whole by
one task.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from websieve.llm import decontamination, line_dedup, ngram_join, packing, toxicity
from websieve.llm.common import fresh, give_back_heap, table, without_rows, written
from websieve.llm.queries import TOXIC_FROM, tokenizer_file, toxicity_classifier


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity query does not call toxic; the classifier learns as the toxicity query's does."""
    probability = fresh("toxicity", docs.columns)
    scored = toxicity.score(docs, toxicity_classifier(spark, sf_dir), out=probability)
    return scored.where(F.col(probability) < TOXIC_FROM).drop(probability)


def drop_boilerplate_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that repeat in their source beyond chance; one left with no text goes if it had some."""
    had = fresh("had", docs.columns)
    found = line_dedup.repeated(docs, "source", "text")
    cleaned = line_dedup.drop_boilerplate(docs.withColumn(had, F.trim(F.coalesce("text", F.lit(""))) != ""), "doc_id", "source", "text", found=found)
    kept = cleaned.where(~F.col(had) | (F.trim("text") != "")).drop(had)
    return kept.withColumn("n_chars", F.length("text").cast("long"))


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each component of near copies (of rows without id, or that share one, the one whose text has
    the smallest hash); documents without words stay."""
    report = ngram_join.NearDuplicates(docs).report().where("n_shingles > 0").select("doc_id", F.col("text_hash").alias("own"), "component_key")
    rows = written(report, "pipeline-groups")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "own")).alias("first")
    firsts = rows.groupBy("component_key").agg(first, F.count(F.lit(1)).alias("members")).where("members > 1")
    others = rows.join(firsts, "component_key").where(~F.col("doc_id").eqNullSafe(F.col("first.doc_id")) | (F.col("own") != F.col("first.own")))
    kept = without_rows(docs, "doc_id", "text", others)
    # Rows equal in id and text are left; only where there are such is more than a count needed.
    repeats = rows.groupBy("doc_id", "own").count().where("count > 1").select("doc_id", "own")
    if repeats.isEmpty():
        return kept
    own = fresh("own", docs.columns)
    keyed = kept.withColumn(own, F.when(F.trim("text") != "", F.xxhash64("text")).otherwise(F.monotonically_increasing_id()))
    return keyed.dropDuplicates(["doc_id", own]).drop(own)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no window of a benchmark item occurs."""
    index = decontamination.TestIndex(docs, table(spark, sf_dir, "benchmark"))
    return without_rows(docs, "doc_id", "text", index.phrases().select("doc_id", "own"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of at most 2048 tokens."""
    return packing.pack(docs, tokenizer_file("word_bpe_49k.json"))


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def with_free_heap(stage: Stage) -> Stage:
    """``stage``, begun by executors that do not keep the heap of the stage before."""

    @wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        give_back_heap(spark)
        return stage(spark, docs, sf_dir)

    return run


STAGES = [
    ("toxicity", with_free_heap(drop_toxic)),
    ("line_dedup", with_free_heap(drop_boilerplate_lines)),
    ("ngram_join", with_free_heap(keep_one_of_each_group)),
    ("decontamination", with_free_heap(drop_contaminated)),
    ("packing", with_free_heap(packed)),
]

#: Language models and tokenizers are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
