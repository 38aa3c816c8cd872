"""Language id, language model, buckets: queries, and the SQL that computes the same from the base tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import buckets, lid, lm, metrics, subword
from ..sources.pages import materialize
from .common import SQL_PARAS, r6, table

TEMPERATURE = 0.25


# --- fixtures --------------------------------------------------------------------------------------------------


def documents(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "lang", "text", "source")


def lid_train(spark, sf):
    return documents(spark, sf).where("doc_id % 2 = 0")


def lid_test(spark, sf):
    return documents(spark, sf).where("doc_id % 2 = 1")


def flat_scores(spark, sf, docs):
    model = lid.fit_flat(lid_train(spark, sf))
    return lid.score_flat(docs, model, temperature=TEMPERATURE)


def flat_language(spark, sf):
    """(doc_id, text) -> (doc_id, lang, score), learned from even documents."""
    return lambda docs: lid.best(flat_scores(spark, sf, docs))


def target(spark, sf):
    return lm.target_corpus(documents(spark, sf), table(spark, sf, "labels"), F.col("doc_id") % 2 == 0)


def word_model(spark, sf, order=3, corpus=None):
    return materialize(lm.train_target(target(spark, sf) if corpus is None else corpus, order), "ngram-model")


def paragraph_scores(spark, sf, order=3):
    return lm.score_trained(lm.sentences(lid_test(spark, sf)), lm.sentences(target(spark, sf)), order)


def subword_models(spark, sf, vocabulary=400):
    """A unigram model of subword pieces for each language of the target corpus."""
    words = materialize(subword.word_table(target(spark, sf)), "words")
    return {r.lang: subword.fit_unigram(words.where(F.col("lang") == r.lang), vocabulary)[0] for r in words.select("lang").distinct().collect()}


def document_scores(spark, sf, order=3):
    return materialize(lm.document_ppl(paragraph_scores(spark, sf, order)), "document-scores")


# --- SQL fragments ---------------------------------------------------------------------------------------------


def sql_lid(source: str, prefix: str = "lid") -> str:
    """CTEs ``{prefix}_scores`` (doc_id, lang, score) and ``{prefix}_best`` of the flat trigram classifier over ``source`` (doc_id, text)."""
    p = prefix
    return f"""
{p}_tg AS (
  SELECT lang, gram, count(*) AS n FROM (
    SELECT lang, unnest(list_transform(range(1, length(text) - 1), lambda i: substr(lower(text), i, 3))) AS gram
    FROM documents WHERE doc_id % 2 = 0) GROUP BY ALL
), {p}_v AS (SELECT count(DISTINCT gram) AS v FROM {p}_tg
), {p}_t AS (SELECT lang, sum(n)::DOUBLE AS total FROM {p}_tg GROUP BY lang
), {p}_dg AS (
  SELECT doc_id, gram, count(*) AS n FROM (
    SELECT doc_id, unnest(list_transform(range(1, length(text) - 1), lambda i: substr(lower(text), i, 3))) AS gram FROM {source}) GROUP BY ALL
), {p}_ll AS (
  SELECT d.doc_id, t.lang, sum(d.n * ln((coalesce(g.n, 0) + 0.5) / (t.total + 0.5 * v.v))) / sum(d.n) AS ll
  FROM {p}_dg d CROSS JOIN {p}_t t CROSS JOIN {p}_v v LEFT JOIN {p}_tg g ON g.lang = t.lang AND g.gram = d.gram GROUP BY 1, 2
), {p}_e AS (
  SELECT doc_id, lang, exp((ll - max(ll) OVER (PARTITION BY doc_id)) / {TEMPERATURE}) AS e FROM {p}_ll
), {p}_scores AS (SELECT doc_id, lang, e / sum(e) OVER (PARTITION BY doc_id) AS score FROM {p}_e
), {p}_best AS (
  SELECT doc_id, lang, score FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, lang) AS nth FROM {p}_scores) WHERE nth = 1
)"""


SQL_TARGET = """target AS (
  SELECT lang, text, min(doc_id) AS doc_id FROM documents WHERE doc_id % 2 = 0 AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1) GROUP BY lang, text
)"""


def sql_sentences(source: str, name: str) -> str:
    """CTE ``name`` (doc_id, lang, para_no, toks) from ``source`` (doc_id, lang, text)."""
    return rf"""{name} AS (
  SELECT doc_id, lang, para_no, toks FROM (
    SELECT doc_id, lang, (i - 1)::INTEGER AS para_no, regexp_extract_all(lower(parts[i]), '[\p{{L}}\p{{N}}]+') AS toks
    FROM (SELECT doc_id, lang, parts, unnest(range(1, len(parts) + 1)) AS i FROM (SELECT doc_id, lang, string_split(text, chr(10)) AS parts FROM {source})))
  WHERE len(toks) > 0
)"""


def sql_model(sentences: str) -> str:
    """CTEs of the smoothed model of order 3 over ``sentences``: c1..c3, a1..a3, d1..d3, p1..p3, g1..g3, unk."""

    def discount(n: int) -> str:
        return f"""d{n} AS (
  SELECT lang, CASE WHEN ok THEN greatest(0.05, least(1.0, 1 - 2 * y * n2 / n1)) ELSE 0.5 END AS x1,
         CASE WHEN ok THEN greatest(0.05, least(2.0, 2 - 3 * y * n3 / n2)) ELSE 1.0 END AS x2,
         CASE WHEN ok THEN greatest(0.05, least(3.0, 3 - 4 * y * n4 / n3)) ELSE 1.5 END AS x3
  FROM (SELECT *, n1 / (n1 + 2.0 * n2) AS y, n1 > 0 AND n2 > 0 AND n3 > 0 AND n4 > 0 AS ok FROM (
    SELECT lang, count(*) FILTER (a = 1) AS n1, count(*) FILTER (a = 2) AS n2, count(*) FILTER (a = 3) AS n3, count(*) FILTER (a = 4) AS n4 FROM a{n} GROUP BY lang))
)"""

    def context(n: int, ctx: str) -> str:
        taken = "CASE WHEN a = 1 THEN x1 WHEN a = 2 THEN x2 ELSE x3 END"
        keys = ", ".join(["lang", *([ctx] if ctx else [])])
        return f"""t{n} AS (SELECT a{n}.*, {taken} AS taken FROM a{n} JOIN d{n} USING (lang)
), g{n} AS (SELECT {keys}, sum(a)::DOUBLE AS total, sum(taken) / sum(a) AS gamma FROM t{n} GROUP BY {keys})"""

    return f"""
framed AS (SELECT lang, list_concat(['<s>'], toks, ['</s>']) AS t FROM {sentences}
), spots AS (SELECT lang, t, unnest(range(2, len(t) + 1)) AS i FROM framed
), c1 AS (SELECT lang, t[i] AS z, count(*) AS n FROM spots GROUP BY ALL
), c2 AS (SELECT lang, t[i - 1] AS y, t[i] AS z, count(*) AS n FROM spots GROUP BY ALL
), c3 AS (SELECT lang, t[i - 2] AS x, t[i - 1] AS y, t[i] AS z, count(*) AS n FROM spots WHERE i > 2 GROUP BY ALL
), a1 AS (SELECT lang, z, count(*) AS a FROM c2 GROUP BY ALL
), l2 AS (SELECT lang, y, z, count(*) AS l FROM c3 GROUP BY ALL
), a2 AS (SELECT c2.lang, c2.y, c2.z, CASE WHEN c2.y = '<s>' THEN c2.n ELSE l2.l END AS a FROM c2 LEFT JOIN l2 USING (lang, y, z)
), a3 AS (SELECT lang, x, y, z, n AS a FROM c3
), {discount(1)}, {discount(2)}, {discount(3)}, {context(1, "")}, {context(2, "y")}, {context(3, "x, y")},
kinds AS (SELECT lang, 1.0 / (count(*) + 1) AS floor FROM c1 GROUP BY lang
), unk AS (SELECT lang, gamma * floor AS p FROM g1 JOIN kinds USING (lang)
), p1 AS (SELECT lang, z, (a - taken) / total + gamma * floor AS p FROM t1 JOIN g1 USING (lang) JOIN kinds USING (lang)
), p2 AS (SELECT t2.lang, t2.y, t2.z, (a - taken) / total AS own, (a - taken) / total + gamma * p1.p AS p
  FROM t2 JOIN g2 USING (lang, y) JOIN p1 USING (lang, z)
), p3 AS (SELECT t3.lang, t3.x, t3.y, t3.z, (a - taken) / total AS own, (a - taken) / total + gamma * p2.p AS p
  FROM t3 JOIN g3 USING (lang, x, y) JOIN p2 USING (lang, y, z)
)"""


def sql_scores(sentences: str) -> str:
    """CTE ``para_scores`` (doc_id, lang, para_no, log10_sum, n_tokens) by full interpolation, not by backing off."""
    return f"""
pos AS (
  SELECT doc_id, lang, para_no, i, t[i] AS z, t[i - 1] AS y, CASE WHEN i > 2 THEN t[i - 2] END AS x
  FROM (SELECT doc_id, lang, para_no, t, unnest(range(2, len(t) + 1)) AS i FROM (
    SELECT doc_id, lang, para_no, list_concat(['<s>'], toks, ['</s>']) AS t FROM {sentences}))
), q1 AS (SELECT pos.*, coalesce(p1.p, unk.p) AS v1 FROM pos JOIN unk USING (lang) LEFT JOIN p1 USING (lang, z)
), q2 AS (SELECT q1.*, CASE WHEN g2.gamma IS NULL THEN v1 ELSE coalesce(p2.own, 0) + g2.gamma * v1 END AS v2
  FROM q1 LEFT JOIN g2 USING (lang, y) LEFT JOIN p2 USING (lang, y, z)
), q3 AS (SELECT q2.*, CASE WHEN g3.gamma IS NULL THEN v2 ELSE coalesce(p3.own, 0) + g3.gamma * v2 END AS v3
  FROM q2 LEFT JOIN g3 USING (lang, x, y) LEFT JOIN p3 USING (lang, x, y, z)
), para_scores AS (SELECT doc_id, lang, para_no, sum(log10(v3)) AS log10_sum, count(*) AS n_tokens FROM q3 GROUP BY ALL
), doc_scores AS (SELECT doc_id, lang, pow(10, -sum(log10_sum) / sum(n_tokens)) AS ppl, sum(n_tokens)::BIGINT AS n_tokens FROM para_scores GROUP BY ALL
)"""


SQL_ODD = "odd AS (SELECT doc_id, lang, text FROM documents WHERE doc_id % 2 = 1)"
SQL_DOC_SCORES = f"{SQL_TARGET}, {sql_sentences('target', 'ts')}, {sql_model('ts')}, {SQL_ODD}, {sql_sentences('odd', 'os')}, {sql_scores('os')}"
SQL_CUTS = f"{SQL_DOC_SCORES}, cuts AS (SELECT lang, quantile_cont(ppl, 1.0 / 3) AS cut_head, quantile_cont(ppl, 2.0 / 3) AS cut_tail FROM doc_scores GROUP BY lang)"
SQL_BUCKET = "CASE WHEN ppl IS NULL OR cut_head IS NULL THEN 'all' WHEN ppl <= cut_head THEN 'head' WHEN ppl > cut_tail THEN 'tail' ELSE 'middle' END"
SQL_BUCKETED = f"{SQL_CUTS}, bucketed AS (SELECT s.*, {SQL_BUCKET} AS bucket FROM doc_scores s LEFT JOIN cuts USING (lang))"


# --- language id -----------------------------------------------------------------------------------------------


def l_char_ngrams(spark, sf):
    return _gram_sums(documents(spark, sf).where("doc_id < 200"))


def l_char_ngrams_all(spark, sf):
    return _gram_sums(documents(spark, sf))


def _gram_sums(docs):
    return lid.char_ngrams(docs, 2, 3).groupBy("doc_id").agg(F.count(F.lit(1)).alias("kinds"), F.sum("n").alias("n"))


def l_ngram_topk(spark, sf):
    return lid.gram_counts(documents(spark, sf), 3, 3).groupBy("gram").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "gram").limit(50)


def l_train_counts(spark, sf):
    return lid_train(spark, sf).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length("text")).cast("long").alias("chars"))


def l_flat_scores(spark, sf):
    return flat_scores(spark, sf, lid_test(spark, sf)).select("doc_id", "lang", r6("score").alias("score"))


def l_tree_scores(spark, sf):
    model = lid.fit_tree_counts(lid_train(spark, sf))
    return lid.score_tree_counts(lid_test(spark, sf), model).select("doc_id", "lang", r6("score").alias("score"))


def l_tree_logistic(spark, sf):
    model = lid.fit_tree_logistic(lid_train(spark, sf))
    return lid.score_tree_logistic(lid_test(spark, sf), model)


def l_score_map(spark, sf):
    return lid.score_map(flat_scores(spark, sf, lid_test(spark, sf))).select("doc_id", F.explode("scores").alias("lang", "score")).select("doc_id", "lang", r6("score").alias("score"))


def _best(spark, sf):
    return flat_language(spark, sf)(lid_test(spark, sf))


def l_best(spark, sf):
    return _best(spark, sf).select("doc_id", "lang", r6("score").alias("score"))


def l_accept(spark, sf):
    return lid.accept(_best(spark, sf)).select("doc_id", "lang")


def l_discarded(spark, sf):
    top = materialize(_best(spark, sf), "best")
    return top.join(lid.accept(top).select("doc_id"), "doc_id", "left_anti").select("doc_id", "lang")


def l_split_counts(spark, sf):
    return lid.accept(_best(spark, sf)).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"))


def _para_docs(spark, sf):
    lines = lid_test(spark, sf).select("doc_id", F.posexplode(F.split("text", "\n")).alias("para_no", "text")).where(F.length("text") >= 3)
    return lines.select((F.col("doc_id") * 100_000 + F.col("para_no")).alias("doc_id"), F.col("doc_id").alias("whole"), "text")


def l_paragraph_level(spark, sf):
    rows = materialize(_para_docs(spark, sf), "lines")
    top = flat_language(spark, sf)(rows).join(rows.select("doc_id", "whole", F.length("text").cast("long").alias("n_chars")), "doc_id")
    return lid.by_paragraph(top.select("whole", "lang", "n_chars"), "whole").select(F.col("whole").alias("doc_id"), "lang", r6("share").alias("share"))


def l_confusion(spark, sf):
    truth = lid_test(spark, sf).select("doc_id", F.col("lang").alias("truth"))
    return metrics.confusion(_best(spark, sf).select("doc_id", F.col("lang").alias("predicted")).join(truth, "doc_id"))


# --- language model --------------------------------------------------------------------------------------------


def t_word_tokens(spark, sf):
    return lm.sentences(lid_test(spark, sf)).select("doc_id", "para_no", F.array_join("toks", " ").alias("tokens"))


def t_char_tokens(spark, sf):
    return _char_sums(lid_test(spark, sf).where("doc_id < 200"))


def t_word_tokens_all(spark, sf):
    return lm.sentences(documents(spark, sf)).select("doc_id", "para_no", F.array_join("toks", " ").alias("tokens"))


def t_char_tokens_all(spark, sf):
    return _char_sums(documents(spark, sf))


def _char_sums(docs):
    return lm.sentences(docs, lm.chars).groupBy("doc_id").agg(F.sum(F.size("toks")).cast("long").alias("n_tokens"))


def t_pair_counts(spark, sf):
    """Neighbouring letters of the target corpus, weighted by word counts: what the first merge chooses from."""
    return subword.pair_counts(subword.spelled(subword.word_table(target(spark, sf))))


def t_subword(spark, sf):
    """Pieces of odd documents; joined they are the words again."""
    rows = subword.encode(lm.sentences(lid_test(spark, sf)), subword_models(spark, sf))
    return rows.select("doc_id", "para_no", F.array_join("toks", " ").alias("pieces"))


def m_paragraph_ppl_joined(spark, sf):
    rows = lm.score_dealt(lm.sentences(lid_test(spark, sf)), word_model(spark, sf), 3)
    return lm.paragraph_ppl(rows).select("doc_id", "lang", "para_no", r6("log10_sum").alias("log10_sum"), "n_tokens", F.round("ppl", 4).alias("ppl"))


def _counts(spark, sf, order=3):
    return lm.ngrams(lm.sentences(target(spark, sf)), order)


def m_ngram_counts(spark, sf):
    return _counts(spark, sf).select("lang", "n", "key", "cnt")


def m_adjusted_counts(spark, sf):
    return lm.adjusted(_counts(spark, sf), 3).select("lang", "n", "key", "a")


def m_discounts(spark, sf):
    return lm.discounts(lm.adjusted(_counts(spark, sf), 3)).select("lang", "n", *(r6(c).alias(c) for c in ("d1", "d2", "d3")))


def m_discounts_single(spark, sf):
    return lm.discounts(lm.adjusted(_counts(spark, sf), 3), "single").select("lang", "n", r6("d1").alias("d"))


def m_kn_model(spark, sf):
    return word_model(spark, sf).where("log10_p IS NOT NULL").select("lang", "n", "key", r6("log10_p").alias("log10_p"))


def m_kn_model_5(spark, sf):
    return lm.train_target(target(spark, sf), 5)


def m_kn_single(spark, sf):
    return lm.fit(_counts(spark, sf), 3, "single")


def m_kn_pruned(spark, sf):
    return lm.fit(_counts(spark, sf), 3, prune=(0, 0, 1))


def m_addk_model(spark, sf):
    return lm.fit_add_k(_counts(spark, sf), 3, 0.5).select("lang", "n", "key", r6("log10_p").alias("log10_p"))


def m_ml_model(spark, sf):
    return lm.fit_add_k(_counts(spark, sf), 3, 0.0).select("lang", "n", "key", r6("log10_p").alias("log10_p"))


def m_paragraph_ppl(spark, sf):
    return lm.paragraph_ppl(paragraph_scores(spark, sf)).select("doc_id", "lang", "para_no", r6("log10_sum").alias("log10_sum"), "n_tokens", F.round("ppl", 4).alias("ppl"))


def m_paragraph_ppl_arrays(spark, sf):
    rows = lm.score_in_place(lm.sentences(lid_test(spark, sf)), word_model(spark, sf), 3)
    return lm.paragraph_ppl(rows).select("doc_id", "lang", "para_no", r6("log10_sum").alias("log10_sum"), "n_tokens", F.round("ppl", 4).alias("ppl"))


def m_document_ppl(spark, sf):
    return document_scores(spark, sf).select("doc_id", "lang", F.round("ppl", 4).alias("ppl"), "n_tokens")


def m_document_ppl_variants(spark, sf):
    scores = materialize(paragraph_scores(spark, sf), "paragraph-scores")
    out = None
    for agg in ("mean_para", "max_para", "median_para"):
        one = lm.document_ppl(scores, agg).select("doc_id", F.lit(agg).alias("agg"), F.round("ppl", 4).alias("ppl"))
        out = one if out is None else out.unionByName(one)
    return out


def m_custom_target(spark, sf):
    """A user's own target corpus: the benchmark passages, with cuts of their own."""
    own = table(spark, sf, "benchmark").select(F.col("item_id").alias("doc_id"), F.lit("en").alias("lang"), "text")
    model = word_model(spark, sf, corpus=own)
    scores = materialize(lm.document_ppl(lm.score(lm.sentences(lid_test(spark, sf).where("lang = 'en'")), model, 3)), "own-scores")
    cuts = buckets.thresholds(scores)
    return cuts.select("lang", F.round("cut_head", 4).alias("cut_head"), F.round("cut_tail", 4).alias("cut_tail"))


# --- buckets ---------------------------------------------------------------------------------------------------


def _cuts_query(**options):
    def call(spark, sf):
        cuts = buckets.thresholds(document_scores(spark, sf), **options)
        return cuts.select("lang", F.round("cut_head", 4).alias("cut_head"), F.round("cut_tail", 4).alias("cut_tail"))

    return call


def bucketed(spark, sf):
    scores = document_scores(spark, sf)
    return buckets.assign(scores, buckets.thresholds(scores))


def b_ntile(spark, sf):
    scores = document_scores(spark, sf).select("doc_id", "lang", F.round("ppl", 4).alias("ppl"))
    return buckets.by_rank(scores).groupBy("lang", "bucket").agg(F.count(F.lit(1)).alias("docs"))


def b_assign(spark, sf):
    return bucketed(spark, sf).select("doc_id", "lang", "bucket")


def b_sizes(spark, sf):
    return bucketed(spark, sf).groupBy("lang", "bucket").agg(F.count(F.lit(1)).alias("docs"))


def b_by_chars(spark, sf):
    chars = lid_test(spark, sf).select("doc_id", F.length("text").cast("long").alias("n_chars"))
    cuts = buckets.thresholds(document_scores(spark, sf).join(chars, "doc_id"), weight="chars")
    return cuts.select("lang", F.round("cut_head", 4).alias("cut_head"), F.round("cut_tail", 4).alias("cut_tail"))


def b_by_tokens(spark, sf):
    cuts = buckets.thresholds(document_scores(spark, sf), weight="tokens")
    return cuts.select("lang", F.round("cut_head", 4).alias("cut_head"), F.round("cut_tail", 4).alias("cut_tail"))


def b_keep_head(spark, sf):
    return buckets.select(bucketed(spark, sf), ("head",)).select("doc_id", "lang")


def b_max_ppl(spark, sf):
    return buckets.select(bucketed(spark, sf), max_ppl=200.0).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"))


def b_no_model(spark, sf):
    """One language has no model: its documents are not split."""
    scores = document_scores(spark, sf).withColumn("ppl", F.when(F.col("lang") != "es", F.col("ppl")))
    return buckets.assign(scores, buckets.thresholds(scores)).groupBy("lang", "bucket").agg(F.count(F.lit(1)).alias("docs"))


def x_ppl_histogram(spark, sf):
    scores = document_scores(spark, sf)
    h = metrics.ppl_histogram(scores, buckets.thresholds(scores))
    return h.select("lang", "bin", "docs", F.round("cut_head", 4).alias("cut_head"), F.round("cut_tail", 4).alias("cut_tail"))


def x_ppl_spread(spark, sf):
    s = metrics.ppl_spread(document_scores(spark, sf))
    return s.select("lang", *(F.round(c, 4).alias(c) for c in ("q25", "q50", "q75", "iqr", "std", "spikiness")))


def x_bucket_profile(spark, sf):
    return metrics.bucket_profile(bucketed(spark, sf).join(lid_test(spark, sf).select("doc_id", "text"), "doc_id"))


def _quality_truth(spark, sf):
    """Labels of odd documents whose text is not in the target corpus."""
    fresh = lm.outside(lid_test(spark, sf), target(spark, sf)).select("doc_id")
    return table(spark, sf, "labels").join(fresh, "doc_id", "left_semi")


def x_bucket_quality(spark, sf):
    return metrics.bucket_quality(bucketed(spark, sf), _quality_truth(spark, sf))


def x_auc(spark, sf):
    rows = bucketed(spark, sf).join(_quality_truth(spark, sf), "doc_id").select("lang", (-F.round("ppl", 4)).alias("score"), "quality")
    return metrics.auc(rows, ["lang"], "score", "quality")


def x_auc_binned(spark, sf):
    rows = bucketed(spark, sf).join(_quality_truth(spark, sf), "doc_id").select("lang", "ppl", "quality")
    return metrics.auc_binned(rows, ["lang"], 1 / (1 + F.log10("ppl")), "quality")


def x_macro_accuracy(spark, sf):
    top = _best(spark, sf).select("doc_id", F.col("lang").alias("predicted"))
    return metrics.macro_accuracy(lid_test(spark, sf).select("doc_id", "lang", F.col("lang").alias("label")).join(top, "doc_id"))


def x_lm_train_size(spark, sf):
    rows = lm.sentences(target(spark, sf)).groupBy("lang").agg(F.sum(F.size("toks")).cast("long").alias("tokens"))
    size = target(spark, sf).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length("text")).cast("long").alias("chars"))
    return size.join(rows, "lang")


CALLS = {f.__name__: f for f in (
    l_char_ngrams, l_ngram_topk, l_train_counts, l_flat_scores, l_tree_scores, l_tree_logistic, l_score_map, l_best, l_accept, l_discarded, l_split_counts, l_paragraph_level, l_confusion,
    l_char_ngrams_all, t_word_tokens_all, t_char_tokens_all, t_word_tokens, t_char_tokens, t_pair_counts, t_subword, m_ngram_counts, m_adjusted_counts, m_discounts, m_discounts_single, m_kn_model, m_kn_model_5, m_kn_single, m_kn_pruned, m_addk_model, m_ml_model, m_paragraph_ppl, m_paragraph_ppl_arrays, m_paragraph_ppl_joined,
    m_document_ppl, m_document_ppl_variants, m_custom_target, b_ntile, b_assign, b_sizes, b_by_chars, b_by_tokens, b_keep_head, b_max_ppl, b_no_model, x_ppl_histogram, x_ppl_spread, x_bucket_profile, x_bucket_quality, x_auc, x_auc_binned, x_macro_accuracy, x_lm_train_size,
)} | {"b_thresholds_exact": _cuts_query(), "b_thresholds_sketch": _cuts_query(method="sketch"), "b_global_cut": _cuts_query(per_language=False)}

_TEST = "test AS (SELECT doc_id, lang, text FROM documents WHERE doc_id % 2 = 1)"
_LID = f"WITH {_TEST}, {sql_lid('test')}"
_MODEL = f"WITH {SQL_TARGET}, {sql_sentences('target', 'ts')}, {sql_model('ts')}"
_SCORES = f"WITH {SQL_DOC_SCORES}"
_ROUND = "round(cut_head, 4) AS cut_head, round(cut_tail, 4) AS cut_tail"
_TRUTH = "truth AS (SELECT * FROM labels WHERE doc_id % 2 = 1 AND doc_id IN (SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM target t WHERE t.text = d.text)))"

ORACLES = {
    "l_char_ngrams": """
WITH g AS (
  SELECT doc_id, unnest(list_concat(list_transform(range(1, length(text)), lambda i: substr(lower(text), i, 2)), list_transform(range(1, length(text) - 1), lambda i: substr(lower(text), i, 3)))) AS gram
  FROM documents WHERE doc_id < 200)
SELECT doc_id, count(DISTINCT gram) AS kinds, count(*) AS n FROM g GROUP BY doc_id""",
    "l_ngram_topk": """
SELECT gram, count(*) AS n FROM (SELECT unnest(list_transform(range(1, length(text) - 1), lambda i: substr(lower(text), i, 3))) AS gram FROM documents)
GROUP BY gram ORDER BY n DESC, gram LIMIT 50""",
    "l_train_counts": "SELECT lang, count(*) AS docs, sum(length(text))::BIGINT AS chars FROM documents WHERE doc_id % 2 = 0 GROUP BY lang",
    "l_flat_scores": f"{_LID} SELECT doc_id, lang, round(score, 6) AS score FROM lid_scores",
    "l_score_map": f"{_LID} SELECT doc_id, lang, round(score, 6) AS score FROM lid_scores",
    "l_best": f"{_LID} SELECT doc_id, lang, round(score, 6) AS score FROM lid_best",
    "l_accept": f"{_LID} SELECT doc_id, lang FROM lid_best WHERE score > 0.5",
    "l_discarded": f"{_LID} SELECT doc_id, lang FROM lid_best WHERE score <= 0.5",
    "l_split_counts": f"{_LID} SELECT lang, count(*) AS docs FROM lid_best WHERE score > 0.5 GROUP BY lang",
    "l_paragraph_level": f"""
WITH odd_lines AS (
  SELECT doc_id AS whole, i - 1 AS para_no, parts[i] AS text FROM (SELECT doc_id, parts, unnest(range(1, len(parts) + 1)) AS i FROM (
    SELECT doc_id, string_split(text, chr(10)) AS parts FROM documents WHERE doc_id % 2 = 1))
), rows AS (SELECT whole * 100000 + para_no AS doc_id, whole, text FROM odd_lines WHERE length(text) >= 3), {sql_lid('rows')},
s AS (SELECT whole, lang, sum(length(text)) AS c FROM rows JOIN lid_best USING (doc_id) GROUP BY 1, 2)
SELECT whole AS doc_id, lang, round(c / total, 6) AS share FROM (
  SELECT *, sum(c) OVER (PARTITION BY whole) AS total, row_number() OVER (PARTITION BY whole ORDER BY c DESC, lang) AS nth FROM s) WHERE nth = 1""",
    "l_confusion": f"""
{_LID}, c AS (SELECT t.lang AS truth, b.lang AS predicted, count(*) AS docs FROM test t JOIN lid_best b USING (doc_id) GROUP BY 1, 2)
SELECT truth, predicted, docs, round(coalesce(sum(docs) FILTER (truth = predicted) OVER (PARTITION BY truth), 0) / sum(docs) OVER (PARTITION BY truth), 6) AS recall FROM c""",
    "l_tree_scores": f"""
WITH {_TEST}, {sql_lid('test')}, size AS (SELECT lang, row_number() OVER (ORDER BY count(*), lang) AS r, count(*) AS n FROM documents WHERE doc_id % 2 = 0 GROUP BY lang),
-- four languages: the two rarest are joined, then the third unless it is rarer than the fourth's rival
side AS (
  SELECT 0 AS node, lang, r = 1 AS first FROM size WHERE r <= 2
  UNION ALL SELECT 1, lang, CASE WHEN (SELECT sum(n) FROM size WHERE r <= 2) < (SELECT n FROM size WHERE r = 3) THEN r <= 2 ELSE r = 3 END FROM size WHERE r <= 3
  UNION ALL SELECT 2, lang, CASE WHEN (SELECT sum(n) FROM size WHERE r <= 3) < (SELECT n FROM size WHERE r = 4) THEN r <= 3 ELSE r = 4 END FROM size
), tot AS (SELECT node, first, sum(total) + 0.5 * any_value(v) AS t FROM side JOIN lid_t USING (lang) CROSS JOIN lid_v GROUP BY 1, 2
), ng AS (SELECT node, gram, sum(n) FILTER (first) AS na, sum(n) FILTER (NOT first) AS nb FROM side JOIN lid_tg USING (lang) GROUP BY 1, 2
), nodes AS (SELECT a.node, a.t AS ta, b.t AS tb FROM tot a JOIN tot b ON a.node = b.node AND a.first AND NOT b.first
), dd AS (
  SELECT doc_id, nodes.node, sum(d.n * (ln((coalesce(na, 0) + 0.5) / ta) - ln((coalesce(nb, 0) + 0.5) / tb))) / sum(d.n) AS d
  FROM lid_dg d CROSS JOIN nodes LEFT JOIN ng ON ng.node = nodes.node AND ng.gram = d.gram GROUP BY 1, 2
), pp AS (SELECT doc_id, node, 1 / (1 + exp(-4 * d)) AS p FROM dd)
SELECT doc_id, lang, round(product(CASE WHEN first THEN p ELSE 1 - p END), 6) AS score FROM pp JOIN side USING (node) GROUP BY 1, 2""",
    "t_word_tokens": f"WITH {_TEST}, {sql_sentences('test', 's')} SELECT doc_id, para_no, array_to_string(toks, ' ') AS tokens FROM s",
    "t_char_tokens": """
SELECT doc_id, sum(length(part))::BIGINT AS n_tokens FROM (SELECT doc_id, unnest(string_split(lower(text), chr(10))) AS part FROM documents WHERE doc_id % 2 = 1 AND doc_id < 200) WHERE length(part) > 0 GROUP BY doc_id""",
    "t_pair_counts": f"""WITH {SQL_TARGET}, {sql_sentences('target', 'ts')}, w AS (SELECT unnest(toks) AS word FROM ts),
c AS (SELECT word, unnest(range(1, length(word))) AS i FROM w) SELECT substr(word, i, 1) AS a, substr(word, i + 1, 1) AS b, count(*) AS cnt FROM c GROUP BY 1, 2""",
    "m_ngram_counts": f"""{_MODEL}
SELECT lang, 1::INTEGER AS n, z AS key, n AS cnt FROM c1 UNION ALL SELECT lang, 2, y || ' ' || z, n FROM c2 UNION ALL SELECT lang, 3, x || ' ' || y || ' ' || z, n FROM c3""",
    "m_adjusted_counts": f"""{_MODEL}
SELECT lang, 1::INTEGER AS n, z AS key, a FROM a1 UNION ALL SELECT lang, 2, y || ' ' || z, a FROM a2 UNION ALL SELECT lang, 3, x || ' ' || y || ' ' || z, a FROM a3""",
    "m_discounts": f"{_MODEL} " + " UNION ALL ".join(f"SELECT lang, {n}::INTEGER AS n, round(x1, 6) AS d1, round(x2, 6) AS d2, round(x3, 6) AS d3 FROM d{n}" for n in (1, 2, 3)),
    "m_discounts_single": f"{_MODEL} " + " UNION ALL ".join(f"SELECT lang, {n}::INTEGER AS n, round(count(*) FILTER (a = 1) / (count(*) FILTER (a = 1) + 2.0 * count(*) FILTER (a = 2)), 6) AS d FROM a{n} GROUP BY lang" for n in (1, 2, 3)),
    "m_kn_model": f"""{_MODEL}
SELECT lang, 1::INTEGER AS n, z AS key, round(log10(p), 6) AS log10_p FROM p1 UNION ALL SELECT lang, 1, '<unk>', round(log10(p), 6) FROM unk
UNION ALL SELECT lang, 2, y || ' ' || z, round(log10(p), 6) FROM p2 UNION ALL SELECT lang, 3, x || ' ' || y || ' ' || z, round(log10(p), 6) FROM p3""",
    "m_paragraph_ppl": f"{_SCORES} SELECT doc_id, lang, para_no, round(log10_sum, 6) AS log10_sum, n_tokens, round(pow(10, -log10_sum / n_tokens), 4) AS ppl FROM para_scores",
    "m_paragraph_ppl_arrays": f"{_SCORES} SELECT doc_id, lang, para_no, round(log10_sum, 6) AS log10_sum, n_tokens, round(pow(10, -log10_sum / n_tokens), 4) AS ppl FROM para_scores",
    "m_paragraph_ppl_joined": f"{_SCORES} SELECT doc_id, lang, para_no, round(log10_sum, 6) AS log10_sum, n_tokens, round(pow(10, -log10_sum / n_tokens), 4) AS ppl FROM para_scores",
    "m_document_ppl": f"{_SCORES} SELECT doc_id, lang, round(ppl, 4) AS ppl, n_tokens FROM doc_scores",
    "m_document_ppl_variants": f"""{_SCORES}, pp AS (SELECT doc_id, pow(10, -log10_sum / n_tokens) AS ppl FROM para_scores)
SELECT doc_id, 'mean_para' AS agg, round(avg(ppl), 4) AS ppl FROM pp GROUP BY 1 UNION ALL SELECT doc_id, 'max_para', round(max(ppl), 4) FROM pp GROUP BY 1
UNION ALL SELECT doc_id, 'median_para', round(median(ppl), 4) FROM pp GROUP BY 1""",
    "m_custom_target": f"""
WITH target AS (SELECT item_id AS doc_id, 'en' AS lang, text FROM benchmark), {sql_sentences('target', 'ts')}, {sql_model('ts')},
odd AS (SELECT doc_id, lang, text FROM documents WHERE doc_id % 2 = 1 AND lang = 'en'), {sql_sentences('odd', 'os')}, {sql_scores('os')}
SELECT lang, round(quantile_cont(ppl, 1.0 / 3), 4) AS cut_head, round(quantile_cont(ppl, 2.0 / 3), 4) AS cut_tail FROM doc_scores GROUP BY lang""",
    "b_thresholds_exact": f"WITH {SQL_CUTS} SELECT lang, {_ROUND} FROM cuts",
    "b_global_cut": f"{_SCORES} SELECT '*' AS lang, round(quantile_cont(ppl, 1.0 / 3), 4) AS cut_head, round(quantile_cont(ppl, 2.0 / 3), 4) AS cut_tail FROM doc_scores",
    "b_ntile": f"""{_SCORES}, r AS (SELECT lang, ntile(3) OVER (PARTITION BY lang ORDER BY round(ppl, 4), doc_id) AS t FROM doc_scores)
SELECT lang, ['head', 'middle', 'tail'][t] AS bucket, count(*) AS docs FROM r GROUP BY 1, 2""",
    "b_assign": f"WITH {SQL_BUCKETED} SELECT doc_id, lang, bucket FROM bucketed",
    "b_sizes": f"WITH {SQL_BUCKETED} SELECT lang, bucket, count(*) AS docs FROM bucketed GROUP BY ALL",
    "b_keep_head": f"WITH {SQL_BUCKETED} SELECT doc_id, lang FROM bucketed WHERE bucket = 'head'",
    "b_max_ppl": f"{_SCORES} SELECT lang, count(*) AS docs FROM doc_scores WHERE ppl <= 200 GROUP BY lang",
    "b_by_tokens": f"""{_SCORES}, r AS (SELECT lang, ppl, sum(n_tokens) OVER (PARTITION BY lang ORDER BY ppl) / sum(n_tokens) OVER (PARTITION BY lang) AS run FROM doc_scores)
SELECT lang, round(min(ppl) FILTER (run >= 1.0 / 3), 4) AS cut_head, round(min(ppl) FILTER (run >= 2.0 / 3), 4) AS cut_tail FROM r GROUP BY lang""",
    "b_by_chars": f"""{_SCORES}, w AS (SELECT s.lang, ppl, length(text) AS n FROM doc_scores s JOIN documents USING (doc_id)),
r AS (SELECT lang, ppl, sum(n) OVER (PARTITION BY lang ORDER BY ppl) / sum(n) OVER (PARTITION BY lang) AS run FROM w)
SELECT lang, round(min(ppl) FILTER (run >= 1.0 / 3), 4) AS cut_head, round(min(ppl) FILTER (run >= 2.0 / 3), 4) AS cut_tail FROM r GROUP BY lang""",
    "b_no_model": f"WITH {SQL_BUCKETED} SELECT lang, CASE WHEN lang = 'es' THEN 'all' ELSE bucket END AS bucket, count(*) AS docs FROM bucketed GROUP BY 1, 2",
    "x_ppl_histogram": f"WITH {SQL_CUTS} SELECT lang, floor(log10(ppl) / 0.1)::BIGINT AS bin, count(*) AS docs, {_ROUND} FROM doc_scores JOIN cuts USING (lang) GROUP BY ALL",
    "x_ppl_spread": f"""{_SCORES}, q AS (SELECT lang, quantile_cont(ppl, 0.25) AS q25, quantile_cont(ppl, 0.5) AS q50, quantile_cont(ppl, 0.75) AS q75, stddev_samp(ppl) AS sd FROM doc_scores GROUP BY lang)
SELECT lang, round(q25, 4) AS q25, round(q50, 4) AS q50, round(q75, 4) AS q75, round(q75 - q25, 4) AS iqr, round(any_value(sd), 4) AS std, round(avg((abs(ppl - q50) <= 0.1 * q50)::DOUBLE), 4) AS spikiness
FROM doc_scores JOIN q USING (lang) GROUP BY lang, q25, q50, q75""",
    "x_bucket_profile": rf"""WITH {SQL_BUCKETED}, f AS (
  SELECT bucket, len(regexp_extract_all(text, '[|,;:>•]')) / greatest(length(text), 1) AS s, list_filter(regexp_split_to_array(lower(text), '[ \n]+'), lambda w: w <> '') AS w FROM bucketed JOIN documents USING (doc_id))
SELECT bucket, count(*) AS docs, round(avg(s), 6) AS separator_density, round(avg(len(list_distinct(w)) / greatest(len(w), 1)), 6) AS type_token_ratio FROM f GROUP BY bucket""",
    "x_bucket_quality": f"WITH {SQL_BUCKETED}, {_TRUTH} SELECT lang, bucket, count(*) AS docs, round(avg(quality), 6) AS quality_share, round(avg(toxic), 6) AS toxic_share FROM bucketed JOIN truth USING (doc_id) GROUP BY ALL",
    "x_auc": f"""WITH {SQL_BUCKETED}, {_TRUTH}, r AS (SELECT lang, quality, -round(ppl, 4) AS score FROM bucketed JOIN truth USING (doc_id)),
m AS (SELECT lang, quality, rank() OVER (PARTITION BY lang ORDER BY score) + (count(*) OVER (PARTITION BY lang, score) - 1) / 2.0 AS mid FROM r)
SELECT lang, sum(quality)::BIGINT AS n_pos, (count(*) - sum(quality))::BIGINT AS n_neg, round((sum(mid) FILTER (quality = 1) - sum(quality) * (sum(quality) + 1) / 2.0) / (sum(quality) * (count(*) - sum(quality))), 6) AS auc FROM m GROUP BY lang""",
    "x_macro_accuracy": f"""{_LID}, e AS (SELECT t.lang, count(*) AS docs, avg((t.lang = b.lang)::INTEGER) AS a FROM test t JOIN lid_best b USING (doc_id) GROUP BY t.lang)
SELECT lang, docs, round(a, 6) AS accuracy FROM e UNION ALL SELECT 'avg', sum(docs)::BIGINT, round(avg(a), 6) FROM e""",
    "x_lm_train_size": f"""WITH {SQL_TARGET}, {sql_sentences('target', 'ts')}, n AS (SELECT lang, sum(len(toks))::BIGINT AS tokens FROM ts GROUP BY lang)
SELECT t.lang, count(*) AS docs, sum(length(text))::BIGINT AS chars, any_value(tokens) AS tokens FROM target t JOIN n USING (lang) GROUP BY t.lang""",
    "m_addk_model": f"""{_MODEL}, v AS (SELECT lang, count(*) AS v FROM c1 GROUP BY lang), s1 AS (SELECT lang, sum(n) AS s FROM c1 GROUP BY lang), s2 AS (SELECT lang, y, sum(n) AS s FROM c2 GROUP BY 1, 2), s3 AS (SELECT lang, x, y, sum(n) AS s FROM c3 GROUP BY 1, 2, 3)
SELECT lang, 1::INTEGER AS n, z AS key, round(log10((n + 0.5) / (s + 0.5 * v)), 6) AS log10_p FROM c1 JOIN s1 USING (lang) JOIN v USING (lang)
UNION ALL SELECT lang, 2, y || ' ' || z, round(log10((n + 0.5) / (s + 0.5 * v)), 6) FROM c2 JOIN s2 USING (lang, y) JOIN v USING (lang)
UNION ALL SELECT lang, 3, x || ' ' || y || ' ' || z, round(log10((n + 0.5) / (s + 0.5 * v)), 6) FROM c3 JOIN s3 USING (lang, x, y) JOIN v USING (lang)""",
    "m_ml_model": f"""{_MODEL}
SELECT lang, 1::INTEGER AS n, z AS key, round(log10(n / sum(n) OVER (PARTITION BY lang)), 6) AS log10_p FROM c1
UNION ALL SELECT lang, 2, y || ' ' || z, round(log10(n / sum(n) OVER (PARTITION BY lang, y)), 6) FROM c2
UNION ALL SELECT lang, 3, x || ' ' || y || ' ' || z, round(log10(n / sum(n) OVER (PARTITION BY lang, x, y)), 6) FROM c3""",
}
