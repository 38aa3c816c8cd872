"""Pre-processing: shards, JSON pages, HTML blocks, paragraphs, snapshots."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import html
from ..operators import metrics, paragraphs
from ..plans import shards
from ..sources import pages as page_io
from .common import SQL_KEYS, SQL_PARAS, keys, paras, table


def p_html_blocks(spark, sf):
    pages = table(spark, sf, "pages").select("page_id", F.posexplode(html.blocks(F.col("html"))).alias("no", "block"))
    return pages.select("page_id", F.col("no").cast("int").alias("block_no"), "block")


def p_shard_assign(spark, sf):
    return shards.assign_by_id(table(spark, sf, "documents").select("doc_id"), "doc_id", 100)


def p_shard_sizes(spark, sf):
    sized = table(spark, sf, "documents").groupBy("source").agg(F.sum(F.octet_length("text")).cast("long").alias("bytes"))
    return shards.assign_by_bytes(sized, "source", "bytes", 100_000)


def p_json_roundtrip(spark, sf):
    pages = table(spark, sf, "pages").select("page_id", "url", "html")
    return page_io.json_roundtrip(pages).select("page_id", "url", F.sha2("html", 256).alias("digest"))


def p_paragraphs(spark, sf):
    return paras(spark, sf).select("doc_id", "shard_id", "para_no", F.sha2("para", 256).alias("digest"))


def p_turn_paragraphs(spark, sf):
    turns = paragraphs.from_turns(table(spark, sf, "conversations"))
    return turns.select("conv_id", "para_no", "role", F.length("para").cast("long").alias("n_chars"))


def p_reassemble(spark, sf):
    whole = paragraphs.assemble(paras(spark, sf).select("doc_id", "para_no", "para"))
    return whole.select("doc_id", F.sha2("text", 256).alias("digest"), F.size("para_nos").cast("long").alias("n_paras"))


def p_snapshot_counts(spark, sf):
    docs = table(spark, sf, "documents").select(F.pmod("doc_id", F.lit(4)).cast("int").alias("snapshot"), "text")
    return docs.groupBy("snapshot").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length("text")).cast("long").alias("chars"))


def _snapshot_keys(spark, sf):
    return keys(spark, sf).withColumn("snapshot", F.pmod("doc_id", F.lit(4)).cast("int"))


def p_snapshot_overlap(spark, sf):
    return metrics.snapshot_overlap(_snapshot_keys(spark, sf))


def p_snapshot_overlap_sketch(spark, sf):
    return metrics.snapshot_overlap_sketch(_snapshot_keys(spark, sf))


CALLS = {f.__name__: f for f in (p_html_blocks, p_shard_assign, p_shard_sizes, p_json_roundtrip, p_paragraphs, p_turn_paragraphs, p_reassemble, p_snapshot_counts, p_snapshot_overlap, p_snapshot_overlap_sketch)}

ORACLES = {
    "p_html_blocks": f"""
SELECT page_id, (i - 1)::INTEGER AS block_no, b[i] AS block
FROM (SELECT page_id, b, unnest(range(1, len(b) + 1)) AS i FROM (SELECT page_id, {html.sql_blocks("html")} AS b FROM pages))""",
    "p_shard_assign": "SELECT doc_id, (doc_id % 100)::INTEGER AS shard_id FROM documents",
    "p_shard_sizes": """
WITH s AS (SELECT source, sum(strlen(text))::BIGINT AS bytes FROM documents GROUP BY source)
SELECT source, bytes, floor((sum(bytes) OVER (ORDER BY source) - bytes) / 100000)::INTEGER AS shard_id FROM s""",
    "p_json_roundtrip": "SELECT page_id, url, sha256(html) AS digest FROM pages",
    "p_paragraphs": f"WITH {SQL_PARAS} SELECT doc_id, shard_id, para_no, sha256(para) AS digest FROM paras",
    "p_turn_paragraphs": "SELECT conv_id, turn::INTEGER AS para_no, role, length(text)::BIGINT AS n_chars FROM conversations WHERE trim(text, ' ') <> ''",
    "p_reassemble": f"WITH {SQL_PARAS} SELECT doc_id, sha256(string_agg(para, chr(10) ORDER BY para_no)) AS digest, count(*) AS n_paras FROM paras GROUP BY doc_id",
    "p_snapshot_counts": "SELECT (doc_id % 4)::INTEGER AS snapshot, count(*) AS docs, sum(length(text))::BIGINT AS chars FROM documents GROUP BY 1",
    "p_snapshot_overlap": f"""
WITH {SQL_KEYS}, u AS (SELECT DISTINCT (doc_id % 4)::INTEGER AS s, h64 FROM keys), n AS (SELECT s, count(*) AS n FROM u GROUP BY s),
j AS (SELECT x.s AS a, y.s AS b, count(*) AS shared FROM u x JOIN u y ON x.h64 = y.h64 AND x.s < y.s GROUP BY 1, 2)
SELECT na.s AS a, nb.s AS b, coalesce(shared, 0) AS shared, round(coalesce(shared, 0) / (na.n + nb.n - coalesce(shared, 0)), 6) AS jaccard
FROM n na JOIN n nb ON na.s < nb.s LEFT JOIN j ON j.a = na.s AND j.b = nb.s""",
}
