"""Tables, derived fixtures and SQL fragments that the query modules share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import dedup, paragraphs


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shard():
    return F.regexp_extract("source", r"(\d+)$", 1).cast("int")


def paras(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    return paragraphs.explode(docs, shard=shard(), keep=("lang",))


def keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup.keyed(paras(spark, sf_dir))


def r6(c) -> F.Column:
    """Doubles as both engines are compared: six digits, no negative zero."""
    return F.round(c, 6) + F.lit(0.0)


# Paragraphs and keys as DuckDB sees them, written apart from the Spark plans.
SQL_PARAS = r"""
lines AS (
  SELECT doc_id, lang, regexp_extract(source, '(\d+)$', 1)::INTEGER AS shard_id, (i - 1)::INTEGER AS para_no, parts[i] AS para
  FROM (SELECT doc_id, lang, source, parts, unnest(range(1, len(parts) + 1)) AS i
        FROM (SELECT doc_id, lang, source, string_split(text, chr(10)) AS parts FROM documents))
), paras AS (
  SELECT * FROM lines WHERE trim(para, ' ') <> ''
)"""

SQL_NORM = r"regexp_replace(regexp_replace(strip_accents(lower(para)), '\p{Nd}+', '0', 'g'), '\p{P}+', '', 'g')"

SQL_KEYS = SQL_PARAS + rf""", keys AS (
  SELECT doc_id, lang, shard_id, para_no, para, length(para)::BIGINT AS n_chars, {SQL_NORM} AS norm, substr(sha1({SQL_NORM}), 1, 16) AS h64
  FROM paras
)"""


def sql_kept(block: str) -> str:
    """Keep-first within blocks, by a window and not by an index."""
    return f"""{SQL_KEYS}, ranked AS (
  SELECT *, row_number() OVER (PARTITION BY {block}, h64 ORDER BY shard_id, doc_id, para_no) AS nth,
         count(*) OVER (PARTITION BY {block}, h64) AS copies FROM keys
)"""
