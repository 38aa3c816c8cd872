"""Queries over the given tables that apply each training-data operator, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontamination, language_mixture, line_dedup, ngram_join, packing, secrets, token_counts, toxicity, vector_search, warc
from .common import id_residue, shared_path, table


def tokenizer_file(name: str) -> str:
    """Where the public tokenizer files lie; the path is a parameter of the operators."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = decontamination.TestIndex(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    listed = F.sha2(F.array_join("item_ids", ","), 256)
    return index.report().select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), listed.alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op2_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.NearDuplicates(table(spark, sf_dir, "documents")).report().select("doc_id", "n_shingles", "component_id")


#: A document counts as toxic from this probability, in the query and in the pipeline.
TOXIC_FROM = 0.3


def toxicity_classifier(spark: SparkSession, sf_dir: str) -> toxicity.Classifier:
    """Learned from labelled rows of the given tables whose residue modulo 4 is not 2; residue 3 calibrates."""
    residue = id_residue(F.col("doc_id"), 4)
    return toxicity.fit(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), residue != 2, residue == 3)


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = toxicity.score(docs, toxicity_classifier(spark, sf_dir), out="score")
    held_out = F.coalesce(id_residue(F.col("doc_id"), 4) == 2, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= TOXIC_FROM).cast("int").alias("predicted"))


def op4_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = secrets.scan(docs, secrets.fit(docs))

    def count(kind: str) -> Column:
        return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    def listed(spans: Column) -> Column:
        return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")

    base = listed(F.filter("spans", lambda s: s["kind"] != "markov"))
    return found.select("doc_id", count("assign"), count("access"), count("hex"), F.sha2(base, 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_file("word_bpe_49k.json"))


# How a page's lines and host are taken from html and url, the same in SQL below.
HTML_STEPS = (
    ("(?is)<(script|style|head)[^>]*>.*?</(script|style|head)>|<!--.*?-->", "\n"),
    ("(?i)<(p|br|li|ul|ol|h[1-6]|div|nav|article|footer|header|tr|table|section)[^>]*>|</(p|li|ul|ol|h[1-6]|div|nav|article|footer|header|tr|table|section)>", "\n"),
    ("<[^>]*>", ""),
    ("[ \\t\\r]+", " "),
    ("( ?\n ?)+", "\n"),
)
HOST = "^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)"


def page_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as (page_id, host, text): one line for each block of the html."""
    text = F.col("html")
    for pattern, by in HTML_STEPS:
        text = F.regexp_replace(text, pattern, by)
    pages = table(spark, sf_dir, "pages")
    return pages.select("page_id", F.lower(F.regexp_extract("url", HOST, 1)).alias("host"), F.trim(text).alias("text"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = page_lines(spark, sf_dir)
    kept = line_dedup.drop_boilerplate(pages.withColumn("before", F.length("text").cast("long")))
    return kept.select("page_id", "host", F.coalesce("before", F.lit(0)).cast("long").alias("chars_before"), F.coalesce(F.length("text"), F.lit(0)).cast("long").alias("chars_after"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"))


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_path(spark, "warc")
    warc.write(table(spark, sf_dir, "pages"), path)
    return warc.read(spark, path).select(F.col("key").alias("page_id"), "payload_bytes", "payload_digest", "record_type", "refers_to")


def op8_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    residue = id_residue(F.col("doc_id"), 5)
    model = language_mixture.fit(docs.where(residue != 0))
    keep = {"held_out": F.coalesce(residue == 0, F.lit(False))}
    return language_mixture.identify(docs, model, keep=keep).select("doc_id", "held_out", "lang_pred", "score")


def op9_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_search.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))


CALLS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_decontamination": op1_decontamination,
    "op2_ngram_join": op2_ngram_join,
    "op3_toxicity": op3_toxicity,
    "op4_secrets": op4_secrets,
    "op5_packing": op5_packing,
    "op6_line_dedup": op6_line_dedup,
    "op7_warc": op7_warc,
    "op8_language_mixture": op8_language_mixture,
    "op9_vector_search": op9_vector_search,
    "op10_token_counts": op10_token_counts,
}

OP1_SQL = r"""
WITH d AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w
  FROM documents
), b AS (
  SELECT item_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w
  FROM benchmark
), win AS (
  SELECT DISTINCT item_id, list_slice(w, s, s + 9) AS words
  FROM (SELECT item_id, w, unnest(range(1, greatest(2, len(w) - 8))) AS s FROM b WHERE len(w) > 0)
), sizes AS (
  SELECT DISTINCT len(words) AS n FROM win
), grams AS (
  SELECT doc_id, s, n, list_slice(w, s, s + n - 1) AS words
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, sizes WHERE len(w) >= n)
), hit AS (
  SELECT g.doc_id, g.s, g.n, win.item_id FROM grams g JOIN win ON g.words = win.words
), places AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hit) GROUP BY doc_id
), items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS listed
  FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS i FROM hit) GROUP BY doc_id
)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(listed, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN places USING (doc_id) LEFT JOIN items USING (doc_id)
"""


def _html_sql(column: str) -> str:
    for pattern, by in HTML_STEPS:
        column = f"regexp_replace({column}, '{pattern}', {'chr(10)' if by == chr(10) else repr(by)}, 'g')"
    return f"trim({column}, ' ')"


OP6_SQL = rf"""
WITH p AS (
  SELECT page_id, lower(regexp_extract(url, '{HOST}', 1)) AS host, {_html_sql("html")} AS text FROM pages
), l AS (
  SELECT page_id, host, unnest(range(1, len(parts) + 1)) AS no, unnest(parts) AS line
  FROM (SELECT page_id, host, string_split(text, chr(10)) AS parts FROM p)
), c AS (
  SELECT host, trim(line, ' ') AS line, count(DISTINCT page_id) AS n FROM l WHERE trim(line, ' ') <> '' GROUP BY ALL
), h AS (
  SELECT host, count(*) AS n FROM p GROUP BY host
), bad AS (
  SELECT c.host, c.line FROM c JOIN h USING (host) WHERE c.n >= 5 AND c.n > 0.2 * h.n
), kept AS (
  SELECT page_id, string_agg(line, chr(10) ORDER BY no) AS text
  FROM l WHERE NOT EXISTS (SELECT 1 FROM bad WHERE bad.host = l.host AND bad.line = trim(l.line, ' ')) GROUP BY page_id
)
SELECT p.page_id, p.host, length(p.text)::BIGINT AS chars_before, length(coalesce(k.text, ''))::BIGINT AS chars_after, sha256(coalesce(k.text, '')) AS text_sha256
FROM p LEFT JOIN kept k USING (page_id)
"""

OP7_SQL = """
WITH p AS (
  SELECT page_id, coalesce(html, '') AS payload FROM pages
), d AS (
  SELECT page_id, strlen(payload)::BIGINT AS payload_bytes, sha256(payload) AS payload_digest FROM p
), m AS (
  SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first_id FROM d
)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN first_id END AS refers_to
FROM m
"""

OP9_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS q FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT a.vec_id AS query_id, b.vec_id, list_inner_product(a.q::DOUBLE[], b.q::DOUBLE[])::BIGINT AS score
  FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id AND len(a.q) = len(b.q)
), r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS place FROM s
)
SELECT query_id, place::INTEGER AS rank, vec_id, score FROM r WHERE place <= 5
"""

ORACLES: dict[str, str] = {"op1_decontamination": OP1_SQL, "op6_line_dedup": OP6_SQL, "op7_warc": OP7_SQL, "op9_vector_search": OP9_SQL}
