"""Whole pipelines, output plans, replay, baselines and the measures of order and cost."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import html, urls
from ..operators import baselines, buckets, dedup, evaluation, lid, lm, metrics, output, paragraphs, replay, subword
from ..plans import pipeline
from ..sources import pages as page_io
from ..sources.pages import materialize
from . import models as q
from .common import SQL_KEYS, SQL_PARAS, keys, paras, r6, shard, sql_kept, table

ALL = pipeline.CurateOptions(lm_order=3)
JOINED = pipeline.CurateOptions(lm_order=3, scoring="join")


# --- pipelines -------------------------------------------------------------------------------------------------


def _docs(spark, sf):
    return table(spark, sf, "documents").select("doc_id", shard().alias("shard_id"), "text")


def _models(spark, sf, perplexity=True):
    return pipeline.Models(q.flat_language(spark, sf), q.word_model(spark, sf) if perplexity else None)


def _summary(corpus):
    """What is compared: document, language, bucket, rounded perplexity, and a digest of the text."""
    return corpus.select("doc_id", "lang", F.round("ppl", 3).alias("ppl"), "bucket", F.sha2("text", 256).alias("digest"), F.size("para_nos").cast("long").alias("n_paras"))


def pipeline_curate(spark, sf):
    return _summary(pipeline.curate(_docs(spark, sf), _models(spark, sf), ALL))


def pipeline_curate_arrays(spark, sf):
    return _summary(pipeline.curate(_docs(spark, sf), _models(spark, sf), pipeline.CurateOptions(lm_order=3, scoring="arrays")))


def pipeline_curate_joined(spark, sf):
    return _summary(pipeline.curate(_docs(spark, sf), _models(spark, sf), JOINED))


def pipeline_subword(spark, sf):
    """The quality score in full: subword pieces under a 5-gram model of the target corpus."""
    pieces = q.subword_models(spark, sf)
    model = materialize(lm.fit_sentences(subword.encode(lm.sentences(q.target(spark, sf)), pieces), 5), "subword-model")
    models = pipeline.Models(q.flat_language(spark, sf), model, pieces)
    return _summary(pipeline.curate(_docs(spark, sf), models, pipeline.CurateOptions()))


def pipeline_no_lm(spark, sf):
    corpus = pipeline.curate(_docs(spark, sf), _models(spark, sf, False), ALL)
    return corpus.select("doc_id", "lang", "bucket", F.sha2("text", 256).alias("digest"))


def pipeline_lid_first(spark, sf):
    opts = pipeline.CurateOptions(lm_order=0, order="lid_first")
    return pipeline.curate(_docs(spark, sf), _models(spark, sf, False), opts).select("doc_id", "lang", "bucket", F.sha2("text", 256).alias("digest"))


def pipeline_two_passes(spark, sf):
    path = page_io.shared_path(spark, "pass-one")
    pipeline.pass_hash(_docs(spark, sf), path)
    return pipeline.pass_process(_docs(spark, sf), path, _models(spark, sf, False), ALL).select("doc_id", "lang", "bucket", F.sha2("text", 256).alias("digest"))


def pipeline_snapshots(spark, sf):
    docs = _docs(spark, sf).withColumn("snapshot", F.pmod("doc_id", F.lit(4)).cast("int"))
    corpus = pipeline.curate_many(docs, [0, 1, 2, 3], _models(spark, sf, False), ALL)
    return corpus.select("snapshot", "doc_id", "lang", F.sha2("text", 256).alias("digest"))


def pipeline_conversations(spark, sf):
    """Turns are paragraphs; repeated turns go, over all conversations."""
    turns = paragraphs.from_turns(table(spark, sf, "conversations"))
    rows = turns.select(F.col("conv_id").alias("doc_id"), F.lit(0).alias("shard_id"), "para_no", paragraphs.packed_position(F.lit(0), F.col("conv_id"), F.col("para_no")).alias("pos"), "para")
    return dedup.decoded(dedup.survivors(dedup.keyed(rows), dedup.All())).groupBy(F.col("doc_id").alias("conv_id")).agg(F.count(F.lit(1)).alias("turns_kept"))


# --- output ----------------------------------------------------------------------------------------------------


def w_file_plan(spark, sf):
    return output.file_plan(table(spark, sf, "documents").select(shard().alias("shard_id"), "lang"), ["en", "fr", "de"])


def w_chunk_plan(spark, sf):
    files = table(spark, sf, "documents").groupBy("lang", "source").agg(F.sum(F.octet_length("text")).cast("long").alias("bytes"))
    return output.chunk_plan(files, ["lang"], "source", "bytes", 50_000)


def w_cap_corpus(spark, sf):
    budgets = spark.createDataFrame([("en", 200_000), ("fr", 100_000), ("de", 100_000), ("es", 50_000)], "lang string, budget long")
    return output.cap_corpus(table(spark, sf, "documents").select("doc_id", "lang", "text"), ["lang"], ["doc_id"], budgets).select("doc_id", "lang")


def _page_docs(spark, sf):
    return table(spark, sf, "pages").select("page_id", "url", F.array_join(html.blocks(F.col("html")), "\n").alias("text"))


def _manifest(spark, sf):
    pages = _page_docs(spark, sf)
    rows = paragraphs.explode(pages, "page_id", shard=F.pmod("page_id", F.lit(20)))
    kept = dedup.documents(dedup.survivors(dedup.keyed(rows), dedup.All()), pages, "page_id")
    return materialize(replay.manifest(kept, pages, keep=()), "manifest"), pages


def w_manifest(spark, sf):
    m, _ = _manifest(spark, sf)
    return m.select("page_id", "url", "page_digest", F.array_join(F.transform("para_nos", lambda x: x.cast("string")), ",").alias("para_nos"))


def w_rebuild(spark, sf):
    m, pages = _manifest(spark, sf)
    return replay.rebuild(m, pages).select("page_id", F.sha2("text", 256).alias("digest"))


def w_audit(spark, sf):
    """Every tenth page has changed since and every eleventh is missing."""
    m, pages = _manifest(spark, sf)
    later = pages.where("page_id % 11 <> 0").withColumn("text", F.when(F.col("page_id") % 10 == 0, F.concat("text", F.lit("!"))).otherwise(F.col("text")))
    return replay.audit(m, later)


def w_sink_roundtrip(spark, sf):
    docs = table(spark, sf, "documents").select("doc_id", "lang", F.lit("all").alias("bucket"), "text")
    path = page_io.shared_path(spark, "corpus")
    page_io.write_corpus(docs, path)
    back = spark.read.schema("doc_id long, text string, lang string, bucket string").json(path)
    return back.groupBy("lang", "bucket").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.octet_length("text")).cast("long").alias("bytes"))


# --- baselines -------------------------------------------------------------------------------------------------


def bl_line_corpus(spark, sf):
    langs = paras(spark, sf).select("doc_id", "para_no", "lang")
    return baselines.line_corpus(paras(spark, sf), langs).select("lang", dedup.hex_key(F.col("h64")).alias("h64"), "docs")


def bl_curated(spark, sf):
    extra = table(spark, sf, "benchmark").select(F.lit("en").alias("lang"), "text")
    return baselines.curated_concat(q.target(spark, sf), extra).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length("text")).cast("long").alias("chars"))


def bl_url_allowlist(spark, sf):
    pages = table(spark, sf, "pages").select("page_id", "url")
    return baselines.url_allowlist(pages, pages.where("page_id % 7 = 0")).select("page_id")


def bl_rules(spark, sf):
    return baselines.rules(table(spark, sf, "documents").where("lang = 'en'")).select("doc_id")


def bl_raw(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length("text")).cast("long").alias("chars"))


def bl_random_split(spark, sf):
    docs = table(spark, sf, "documents").select("doc_id", F.pmod(F.conv(F.substring(F.sha1(F.encode(F.col("doc_id").cast("string"), "UTF-8")), 1, 8), 16, 10).cast("long"), F.lit(3)).alias("third"))
    return docs.groupBy("third").agg(F.count(F.lit(1)).alias("docs"))


def bl_doc_dedup(spark, sf):
    return baselines.doc_dedup(table(spark, sf, "documents").select("doc_id", "text"))


# --- measures --------------------------------------------------------------------------------------------------

SCOPES = [1, 2, 5, 10, 20, 50, 100]


def x_remaining_curve(spark, sf):
    return metrics.remaining(keys(spark, sf), SCOPES)


def x_remaining_drop_all(spark, sf):
    return metrics.remaining(keys(spark, sf), SCOPES, "drop_all")


def x_duplicate_share(spark, sf):
    return metrics.duplicate_share(keys(spark, sf))


def x_docs_removed(spark, sf):
    return metrics.docs_removed(keys(spark, sf), [1, 5, 20])


def x_hashset_cost(spark, sf):
    return metrics.hashset_cost(keys(spark, sf), [1, 2, 5, 10, 20])


def x_hashset_cost_sketch(spark, sf):
    return metrics.hashset_cost_sketch(keys(spark, sf), [1, 2, 5, 10, 20])


def _orders(spark, sf):
    before = materialize(q.flat_language(spark, sf)(_docs(spark, sf).select("doc_id", "text")), "lid-before")
    kept = materialize(pipeline.deduped(_docs(spark, sf), ALL), "dedup-first")
    after = materialize(q.flat_language(spark, sf)(kept.select("doc_id", "text")), "lid-after")
    return lid.accept(before), lid.accept(after)


def x_order_ratio(spark, sf):
    before, after = _orders(spark, sf)
    left = materialize(pipeline.deduped(_docs(spark, sf).join(before.select("doc_id"), "doc_id", "left_semi"), ALL), "lid-first")
    return metrics.order_ratio(after, before.join(left.select("doc_id"), "doc_id", "left_semi"))


def x_order_transitions(spark, sf):
    before, after = _orders(spark, sf)
    return metrics.order_transitions(before, after)


def x_capacity_plan(spark, sf):
    """Shards are the table's own, one a source; rates are documents a second, workers, processes and cores those of a cluster."""
    docs = table(spark, sf, "documents").agg(F.count_distinct("source").alias("shards"), F.count(F.lit(1)).alias("docs"))
    rates = {"hash_rate": F.lit(600.0), "score_rate": F.lit(40.0), "workers": F.lit(16), "processes": F.lit(17), "cores": F.lit(5000)}
    plan = docs.select("shards", (F.col("docs") / F.col("shards")).alias("docs_per_shard"), *(v.alias(k) for k, v in rates.items()))
    return metrics.capacity_plan(plan)


def x_stage_share(spark, sf):
    events = table(spark, sf, "events").select("event_type", "value")
    return metrics.cpu_share(events, "event_type", "value").select("stage", F.round("cpu_s", 3).alias("cpu_s"), "share")


def _stats(spark, sf):
    return metrics.language_stats(table(spark, sf, "documents"))


def x_language_stats(spark, sf):
    return _stats(spark, sf)


def x_languages_over(spark, sf):
    return metrics.languages_over(_stats(spark, sf), [100, 130, 500], [10_000, 50_000, 200_000])


def x_log_histogram(spark, sf):
    return metrics.log_histogram(_stats(spark, sf), "tokens")


def x_top_languages(spark, sf):
    return metrics.top_languages(_stats(spark, sf), "tokens", 3)


def x_size_vs_target(spark, sf):
    return metrics.size_vs_target(table(spark, sf, "documents"), q.target(spark, sf))


def x_benchmark_hits(spark, sf):
    """Paragraphs of benchmark passages met in the corpus."""
    own = dedup.keyed(paragraphs.explode(table(spark, sf, "benchmark"), "item_id")).select("h64").distinct()
    return keys(spark, sf).join(own, "h64", "left_semi").select("doc_id", "para_no")


def e_analogy_vectors(spark, sf):
    return _analogies(spark, table(spark, sf, "embeddings").where("vec_id < 200"))


def e_analogy_vectors_all(spark, sf):
    return _analogies(spark, table(spark, sf, "embeddings"))


def _analogies(spark, embeddings):
    vectors = embeddings.select(F.col("vec_id").cast("string").alias("word"), F.col("embedding").cast("array<double>").alias("vec"))
    ask = spark.createDataFrame([(str(a), str(a + 1), str(a + 2), "any") for a in range(0, 30, 3)], "a string, b string, c string, kind string")
    return evaluation.analogy_nearest(vectors, ask).select("a", "b", "c", "word")


def e_suffix_pairs(spark, sf):
    return evaluation.suffix_pairs(table(spark, sf, "documents").where("lang = 'en'"), 20)


def _by_language(run):
    """The union of ``run`` (lang) over both languages, with the language in front."""
    parts = [run(lang).select(F.lit(lang).alias("lang"), "*") for lang in ("en", "fr")]
    return parts[0].unionByName(parts[1])


def e_bucket_table(spark, sf):
    docs = materialize(q.bucketed(spark, sf).join(q.lid_test(spark, sf).select("doc_id", "text"), "doc_id").select("doc_id", "lang", "text", "bucket"), "bucketed")
    return _by_language(lambda lang: evaluation.bucket_table(docs.where(F.col("lang") == lang), dim=300))


def _head_crawl(spark, sf, target):
    """(doc_id, lang, text) of the head bucket of even documents outside the target corpus, cut by perplexity under its model."""
    crawl = lm.outside(q.lid_train(spark, sf), target).select("doc_id", "lang", "text")
    scores = materialize(lm.document_ppl(lm.score_trained(lm.sentences(crawl), lm.sentences(target), 3)), "crawl-scores")
    head = buckets.select(buckets.assign(scores, buckets.thresholds(scores)), ("head",)).select("doc_id")
    return crawl.join(head, "doc_id", "left_semi")


def e_transfer(spark, sf):
    """The learner on the target corpus and on the head of the filtered crawl, which gets as many bytes as the target corpus has."""
    target = materialize(q.target(spark, sf), "target")
    head = materialize(_head_crawl(spark, sf, target), "head-crawl")
    dev = table(spark, sf, "labels").join(q.lid_test(spark, sf), "doc_id").select("lang", "text", F.col("quality").alias("label"))
    n_bytes = {r.lang: r.n for r in target.groupBy("lang").agg(F.sum(F.octet_length("text")).alias("n")).collect()}

    def run(lang):
        mine = [df.where(F.col("lang") == lang) for df in (target, head, dev)]
        return evaluation.transfer({"target": mine[0], "crawl": mine[1]}, mine[2], cap_bytes=n_bytes.get(lang, 0), steps=10, dim=300)

    return _by_language(run)


CALLS = {f.__name__: f for f in (
    pipeline_curate, pipeline_curate_arrays, pipeline_curate_joined, pipeline_subword, pipeline_no_lm, pipeline_lid_first, pipeline_two_passes, pipeline_snapshots, pipeline_conversations, w_file_plan, w_chunk_plan, w_cap_corpus, w_manifest, w_rebuild, w_audit, w_sink_roundtrip,
    bl_line_corpus, bl_curated, bl_url_allowlist, bl_rules, bl_raw, bl_random_split, bl_doc_dedup, x_remaining_curve, x_remaining_drop_all, x_duplicate_share, x_docs_removed, x_hashset_cost, x_hashset_cost_sketch,
    x_order_ratio, x_order_transitions, x_capacity_plan, x_stage_share, x_language_stats, x_languages_over, x_log_histogram, x_top_languages, x_size_vs_target, x_benchmark_hits, e_analogy_vectors, e_analogy_vectors_all, e_suffix_pairs, e_bucket_table, e_transfer,
)}

_KEPT = f"""{sql_kept('1')}, kept AS (
  SELECT doc_id, string_agg(para, chr(10) ORDER BY para_no) AS text, count(*) AS n_paras FROM ranked WHERE nth = 1 GROUP BY doc_id)"""
_PAGE = f"pg AS (SELECT page_id, url, array_to_string({html.sql_blocks('html')}, chr(10)) AS text FROM pages)"
_PAGE_KEPT = rf"""{_PAGE}, pl AS (
  SELECT page_id, (i - 1)::INTEGER AS no, parts[i] AS para FROM (SELECT page_id, parts, unnest(range(1, len(parts) + 1)) AS i FROM (SELECT page_id, string_split(text, chr(10)) AS parts FROM pg)) WHERE trim(parts[i], ' ') <> ''
), pk AS (
  SELECT *, row_number() OVER (PARTITION BY regexp_replace(regexp_replace(strip_accents(lower(para)), '\p{{Nd}}+', '0', 'g'), '\p{{P}}+', '', 'g') ORDER BY page_id % 20, page_id, no) AS nth FROM pl
), pm AS (SELECT page_id, string_agg(para, chr(10) ORDER BY no) AS kept, string_agg(no::VARCHAR, ',' ORDER BY no) AS para_nos FROM pk WHERE nth = 1 GROUP BY page_id)"""
_ACCEPTED_AFTER = f"{_KEPT}, {q.sql_lid('kept', 'aft')}"
_WORDS = "list_filter(regexp_split_to_array(text, '[ \\n]+'), lambda w: w <> '')"


def _curve(policy: str) -> str:
    kept = "sum(n_chars) FILTER (nth = 1)" if policy == "keep" else "sum(n_chars) FILTER (copies = 1)"
    return f"""WITH {SQL_KEYS}, s AS (SELECT unnest({SCOPES})::INTEGER AS scope), r AS (
  SELECT scope, n_chars, row_number() OVER (PARTITION BY scope, shard_id // scope, h64 ORDER BY shard_id, doc_id, para_no) AS nth,
         count(*) OVER (PARTITION BY scope, shard_id // scope, h64) AS copies FROM keys CROSS JOIN s)
SELECT scope, {kept}::BIGINT AS kept_chars, sum(n_chars)::BIGINT AS all_chars, round({kept} / sum(n_chars), 6) AS kept_share FROM r GROUP BY scope"""


_STATS = r"""lines_s AS (
  SELECT lang, doc_id, unnest(string_split(text, chr(10))) AS line FROM documents
), sent AS (
  SELECT doc_id, count(*) AS paragraphs, sum(greatest(1, len(regexp_extract_all(regexp_replace(line, '(?i)(^|[^a-z])(mr|mrs|dr|prof|st|vs|etc|no|fig|al)\.', '\1\2', 'g'), '[.!?]+(\s|$)')))) AS sentences
  FROM lines_s WHERE trim(line, ' ') <> '' GROUP BY doc_id
), stats AS (
  SELECT lang, count(*) AS docs, sum(coalesce(paragraphs, 0))::BIGINT AS paragraphs, sum(coalesce(sentences, 0))::BIGINT AS sentences,
         sum(len(regexp_extract_all(text, '[^ \n]+')))::BIGINT AS tokens, sum(strlen(text))::BIGINT AS bytes
  FROM documents LEFT JOIN sent USING (doc_id) GROUP BY lang
)"""

ORACLES = {
    "pipeline_curate": f"""
WITH {_ACCEPTED_AFTER}, crawl AS (SELECT kept.doc_id, lang, text, n_paras FROM kept JOIN aft_best USING (doc_id) WHERE score > 0.5),
{q.SQL_TARGET}, {q.sql_sentences('target', 'ts')}, {q.sql_model('ts')}, {q.sql_sentences('crawl', 'os')}, {q.sql_scores('os')},
cuts AS (SELECT lang, quantile_cont(ppl, 1.0 / 3) AS cut_head, quantile_cont(ppl, 2.0 / 3) AS cut_tail FROM doc_scores GROUP BY lang)
SELECT c.doc_id, c.lang, round(ppl, 3) AS ppl, {q.SQL_BUCKET} AS bucket, sha256(text) AS digest, n_paras
FROM crawl c LEFT JOIN doc_scores s USING (doc_id) LEFT JOIN cuts ON cuts.lang = c.lang""",
    "pipeline_no_lm": f"WITH {_ACCEPTED_AFTER} SELECT kept.doc_id, lang, 'all' AS bucket, sha256(text) AS digest FROM kept JOIN aft_best USING (doc_id) WHERE score > 0.5",
    "pipeline_two_passes": f"WITH {_ACCEPTED_AFTER} SELECT kept.doc_id, lang, 'all' AS bucket, sha256(text) AS digest FROM kept JOIN aft_best USING (doc_id) WHERE score > 0.5",
    "pipeline_lid_first": f"""
WITH {SQL_KEYS}, {q.sql_lid('documents', 'bef')}, ok AS (SELECT doc_id, lang FROM bef_best WHERE score > 0.5),
r AS (SELECT k.*, ok.lang AS own, row_number() OVER (PARTITION BY h64 ORDER BY shard_id, k.doc_id, para_no) AS nth FROM keys k JOIN ok ON ok.doc_id = k.doc_id)
SELECT doc_id, own AS lang, 'all' AS bucket, sha256(string_agg(para, chr(10) ORDER BY para_no)) AS digest FROM r WHERE nth = 1 GROUP BY doc_id, own""",
    "pipeline_snapshots": f"""
WITH {sql_kept('doc_id % 4')}, kept AS (SELECT doc_id, string_agg(para, chr(10) ORDER BY para_no) AS text FROM ranked WHERE nth = 1 GROUP BY doc_id), {q.sql_lid('kept', 'aft')}
SELECT (doc_id % 4)::INTEGER AS snapshot, doc_id, lang, sha256(text) AS digest FROM kept JOIN aft_best USING (doc_id) WHERE score > 0.5""",
    "pipeline_conversations": r"""
WITH r AS (SELECT conv_id, row_number() OVER (PARTITION BY regexp_replace(regexp_replace(strip_accents(lower(text)), '\p{Nd}+', '0', 'g'), '\p{P}+', '', 'g') ORDER BY conv_id, turn) AS nth
  FROM conversations WHERE trim(text, ' ') <> '') SELECT conv_id, count(*) AS turns_kept FROM r WHERE nth = 1 GROUP BY conv_id""",
    "w_file_plan": r"SELECT shard_id, sum(CASE WHEN lang IN ('en', 'fr', 'de') THEN 3 ELSE 1 END)::BIGINT AS files FROM (SELECT DISTINCT regexp_extract(source, '(\d+)$', 1)::INTEGER AS shard_id, lang FROM documents) GROUP BY 1",
    "w_chunk_plan": """
WITH f AS (SELECT lang, source, sum(strlen(text))::BIGINT AS bytes FROM documents GROUP BY ALL)
SELECT lang, source, bytes, floor((sum(bytes) OVER (PARTITION BY lang ORDER BY source) - bytes) / 50000)::BIGINT AS chunk FROM f""",
    "w_cap_corpus": """
SELECT doc_id, lang FROM (SELECT doc_id, lang, sum(strlen(text)) OVER (PARTITION BY lang ORDER BY doc_id) AS run FROM documents)
WHERE run <= CASE lang WHEN 'en' THEN 200000 WHEN 'es' THEN 50000 ELSE 100000 END""",
    "w_manifest": f"WITH {_PAGE_KEPT} SELECT page_id, url, sha256(text) AS page_digest, para_nos FROM pm JOIN pg USING (page_id)",
    "w_rebuild": f"WITH {_PAGE_KEPT} SELECT page_id, sha256(kept) AS digest FROM pm",
    "w_audit": f"""WITH {_PAGE_KEPT}, s AS (SELECT CASE WHEN pm.page_id IS NULL THEN CASE WHEN pg.page_id % 11 <> 0 THEN 'new' END WHEN pg.page_id % 11 = 0 THEN 'missing' WHEN pg.page_id % 10 = 0 THEN 'changed' ELSE 'unchanged' END AS status FROM pg LEFT JOIN pm USING (page_id))
SELECT status, count(*) AS pages FROM s WHERE status IS NOT NULL GROUP BY status""",
    "w_sink_roundtrip": "SELECT lang, 'all' AS bucket, count(*) AS docs, sum(strlen(text))::BIGINT AS bytes FROM documents GROUP BY lang",
    "bl_line_corpus": f"WITH {SQL_KEYS} SELECT lang, h64, count(DISTINCT doc_id) AS docs FROM keys GROUP BY lang, h64",
    "bl_curated": f"WITH {q.SQL_TARGET}, u AS (SELECT lang, text FROM target UNION ALL SELECT 'en', text FROM benchmark) SELECT lang, count(*) AS docs, sum(length(text))::BIGINT AS chars FROM u GROUP BY lang",
    "bl_url_allowlist": rf"SELECT page_id FROM pages WHERE lower(regexp_extract(url, '{urls.HOST}', 1)) IN (SELECT lower(regexp_extract(url, '{urls.HOST}', 1)) FROM pages WHERE page_id % 7 = 0)",
    "bl_rules": r"""
WITH f AS (SELECT doc_id, text, list_filter(string_split(text, chr(10)), lambda x: trim(x, ' ') <> '') AS l, list_filter(regexp_split_to_array(lower(text), '[ \n]+'), lambda w: w <> '') AS w FROM documents WHERE lang = 'en')
SELECT doc_id FROM f WHERE len(w) >= 20 AND len(list_filter(l, lambda x: regexp_matches(trim(x, ' '), '[.!?]$'))) >= 0.5 * len(l) AND len(regexp_extract_all(text, '[#{}<>|*$%&]')) <= 0.1 * len(w)
AND len(list_intersect(list_distinct(w), ['the', 'of', 'and', 'to', 'in', 'that', 'is', 'for'])) >= 2""",
    "bl_raw": "SELECT lang, count(*) AS docs, sum(length(text))::BIGINT AS chars FROM documents GROUP BY lang",
    "bl_random_split": "SELECT (('0x' || substr(sha1(doc_id::VARCHAR), 1, 8))::BIGINT % 3) AS third, count(*) AS docs FROM documents GROUP BY 1",
    "bl_doc_dedup": "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY text",
    "x_remaining_curve": _curve("keep"),
    "x_remaining_drop_all": _curve("drop").replace("sum(n_chars) FILTER (copies = 1)", "coalesce(sum(n_chars) FILTER (copies = 1), 0)"),
    "x_duplicate_share": f"""WITH {sql_kept('1')} SELECT count(*) AS paras, count(*) FILTER (nth = 1) AS distinct_paras, round(1 - count(*) FILTER (nth = 1) / count(*), 6) AS repeated_paras,
round(1 - sum(n_chars) FILTER (nth = 1) / sum(n_chars), 6) AS repeated_chars FROM ranked""",
    "x_docs_removed": f"""WITH {SQL_KEYS}, r AS (SELECT s.scope, doc_id, row_number() OVER (PARTITION BY scope, shard_id // scope, h64 ORDER BY shard_id, doc_id, para_no) AS nth FROM keys CROSS JOIN (SELECT unnest([1, 5, 20])::INTEGER AS scope) s)
SELECT scope, count(DISTINCT doc_id) AS docs, count(DISTINCT doc_id) - count(DISTINCT doc_id) FILTER (nth = 1) AS removed FROM r GROUP BY scope""",
    "x_hashset_cost": f"""WITH {SQL_KEYS}, b AS (SELECT scope, shard_id // scope AS block, count(DISTINCT h64) AS n FROM keys CROSS JOIN (SELECT unnest([1, 2, 5, 10, 20])::INTEGER AS scope) GROUP BY 1, 2)
SELECT scope, count(*) AS blocks, max(n) AS keys_max, round(max(n) * 9.0::DOUBLE, 6) AS disk_bytes, round(max(n) * 26.7::DOUBLE, 6) AS memory_bytes FROM b GROUP BY scope""",
    "x_order_ratio": f"""
WITH {_ACCEPTED_AFTER}, {q.sql_lid('documents', 'bef')}, ok AS (SELECT doc_id, lang FROM bef_best WHERE score > 0.5),
r AS (SELECT k.doc_id, ok.lang AS own, row_number() OVER (PARTITION BY h64 ORDER BY shard_id, k.doc_id, para_no) AS nth FROM keys k JOIN ok ON ok.doc_id = k.doc_id),
b AS (SELECT own AS lang, count(DISTINCT doc_id) AS n FROM r WHERE nth = 1 GROUP BY 1), a AS (SELECT lang, count(*) AS n FROM aft_best WHERE score > 0.5 GROUP BY 1)
SELECT coalesce(a.lang, b.lang) AS lang, coalesce(a.n, 0) AS docs_dedup_first, coalesce(b.n, 0) AS docs_lid_first, round(a.n / b.n, 6) AS ratio FROM a FULL JOIN b ON a.lang = b.lang""",
    "x_order_transitions": f"""
WITH {_ACCEPTED_AFTER}, {q.sql_lid('documents', 'bef')}, a AS (SELECT doc_id, lang FROM aft_best WHERE score > 0.5), b AS (SELECT doc_id, lang FROM bef_best WHERE score > 0.5)
SELECT coalesce(b.lang, '-') AS lang_before, coalesce(a.lang, '-') AS lang_after, count(*) AS docs FROM b FULL JOIN a ON a.doc_id = b.doc_id GROUP BY 1, 2""",
    "x_capacity_plan": """WITH d AS (SELECT count(DISTINCT source) AS shards, count(*) / count(DISTINCT source) AS docs FROM documents)
SELECT shards, round(docs / 600.0::DOUBLE / 3600, 6) AS hash_hours_per_shard, round(docs / 640.0::DOUBLE / 3600, 6) AS score_hours_per_shard, ceil(shards * 17 / 5000.0::DOUBLE)::BIGINT AS waves,
round(ceil(shards / 5000.0::DOUBLE) * (docs / 600.0::DOUBLE / 3600) + shards * 17 / 5000.0::DOUBLE * (docs / 640.0::DOUBLE / 3600), 6) AS hours FROM d""",
    "x_stage_share": "SELECT event_type AS stage, round(sum(value), 3) AS cpu_s, round(sum(value) / sum(sum(value)) OVER (), 6) AS share FROM events GROUP BY event_type",
    "x_language_stats": f"WITH {_STATS} SELECT * FROM stats",
    "x_languages_over": f"""WITH {_STATS}, o AS (SELECT 'docs' AS measure, unnest([100, 130, 500])::BIGINT AS over UNION ALL SELECT 'tokens', unnest([10000, 50000, 200000])::BIGINT)
SELECT measure, o.over, sum((CASE WHEN measure = 'docs' THEN docs ELSE tokens END > o.over)::INTEGER)::BIGINT AS languages FROM stats CROSS JOIN o GROUP BY ALL""".replace("AS over", 'AS "over"').replace("o.over", 'o."over"'),
    "x_log_histogram": f"WITH {_STATS} SELECT lang, tokens AS value, floor(log10(tokens))::BIGINT AS power FROM stats",
    "x_top_languages": f"WITH {_STATS} SELECT lang, tokens AS value, row_number() OVER (ORDER BY tokens DESC, lang)::INTEGER AS rank FROM stats ORDER BY rank LIMIT 3",
    "x_size_vs_target": f"""WITH {q.SQL_TARGET}, a AS (SELECT lang, sum(strlen(text))::BIGINT AS corpus_bytes FROM documents GROUP BY lang), b AS (SELECT lang, sum(strlen(text))::BIGINT AS target_bytes FROM target GROUP BY lang)
SELECT lang, corpus_bytes, target_bytes, round(corpus_bytes / target_bytes, 6) AS ratio FROM a JOIN b USING (lang)""",
    "x_benchmark_hits": rf"""WITH {SQL_KEYS}, b AS (SELECT DISTINCT regexp_replace(regexp_replace(strip_accents(lower(p)), '\p{{Nd}}+', '0', 'g'), '\p{{P}}+', '', 'g') AS norm FROM (SELECT unnest(string_split(text, chr(10))) AS p FROM benchmark) WHERE trim(p, ' ') <> '')
SELECT doc_id, para_no FROM keys WHERE norm IN (SELECT norm FROM b)""",
    "e_analogy_vectors": """
WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings WHERE vec_id < 200), k AS (SELECT unnest(range(0, 30, 3)) AS a),
t AS (SELECT k.a, list_transform(range(1, len(va.e) + 1), lambda i: vb.e[i] - va.e[i] + vc.e[i]) AS e FROM k JOIN v va ON va.vec_id = k.a JOIN v vb ON vb.vec_id = k.a + 1 JOIN v vc ON vc.vec_id = k.a + 2),
s AS (SELECT t.a, v.vec_id, row_number() OVER (PARTITION BY t.a ORDER BY list_cosine_similarity(t.e, v.e) DESC, v.vec_id::VARCHAR) AS nth FROM t JOIN v ON v.vec_id NOT IN (t.a, t.a + 1, t.a + 2))
SELECT a::VARCHAR AS a, (a + 1)::VARCHAR AS b, (a + 2)::VARCHAR AS c, vec_id::VARCHAR AS word FROM s WHERE nth = 1""",
    "e_suffix_pairs": r"""
WITH w AS (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS w FROM documents WHERE lang = 'en'),
p AS (SELECT a.w AS stem, substr(b.w, length(a.w) + 1) AS suffix FROM w a JOIN w b ON length(b.w) BETWEEN length(a.w) + 1 AND length(a.w) + 4 AND a.w = substr(b.w, 1, length(a.w)) AND length(a.w) >= 3)
SELECT suffix, count(*) AS stems FROM p GROUP BY suffix ORDER BY stems DESC, suffix LIMIT 20""",
}
ORACLES |= {name: ORACLES["pipeline_curate"] for name in ("pipeline_curate_arrays", "pipeline_curate_joined")}  # scoring changes no result
