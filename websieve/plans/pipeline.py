"""Whole pipelines over documents: dedup, language id, perplexity, buckets, in either order of the first two."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import buckets, dedup, lid, lm, paragraphs, subword
from ..sources.pages import materialize


@dataclass(frozen=True)
class CurateOptions:
    scope: object = field(default_factory=dedup.All)  # None: no dedup
    policy: str = "keep_first"
    order: str = "dedup_first"  # or "lid_first"
    threshold: float = 0.5
    lm_order: int = 5  # 0: no perplexity, all documents go to the bucket "all"
    tokens: Callable[[Column], Column] = lm.words
    aggregate: str = "token_weighted"
    cuts: str = "exact"
    min_chars: int = 1
    scoring: str = "auto"  # "arrays": broadcast, "join", or arrays where the model's size allows


@dataclass
class Models:
    """What a run needs besides the pages."""

    language: Callable[[DataFrame], DataFrame]  # (doc_id, text) -> (doc_id, lang, score) of the best language
    perplexity: DataFrame | None = None  # n-gram model table
    subwords: dict[str, subword.Unigram | subword.Merges] | None = None  # by language, where the n-grams are of subword pieces


def deduped(docs: DataFrame, opts: CurateOptions) -> DataFrame:
    """(doc_id, text, para_nos) of documents that keep text. ``docs`` has doc_id, shard_id and text."""
    paras = paragraphs.explode(docs, shard=F.col("shard_id"))
    if opts.scope is None:
        positions = paras.select("pos")
    else:
        positions = dedup.survivors(dedup.keyed(paras), opts.scope, opts.policy)
    return dedup.documents(positions, docs, min_chars=opts.min_chars).select("doc_id", "text", "para_nos")


def identified(docs: DataFrame, models: Models, opts: CurateOptions) -> DataFrame:
    """(doc_id, lang, lang_score) of accepted documents."""
    return lid.accept(models.language(docs.select("doc_id", "text")), opts.threshold).select("doc_id", "lang", F.col("score").alias("lang_score"))


def languages(docs: DataFrame, models: Models, opts: CurateOptions) -> DataFrame:
    """(doc_id, text, para_nos, lang, lang_score) after dedup and language id in the chosen order."""
    if opts.order == "dedup_first":
        kept = materialize(deduped(docs, opts), "deduped")
        return kept.join(identified(kept, models, opts), "doc_id")
    langs = materialize(identified(docs, models, opts), "identified")
    return deduped(docs.join(langs.select("doc_id"), "doc_id", "left_semi"), opts).join(langs, "doc_id")


def scored(kept: DataFrame, models: Models, opts: CurateOptions) -> DataFrame:
    """(doc_id, ppl) of documents in a language that has a model; the others never reach the tokenizer."""
    known = models.perplexity.select("lang").distinct()
    rows = lm.sentences(kept.join(F.broadcast(known), "lang", "left_semi"), opts.tokens)
    if models.subwords:
        rows = subword.encode(rows, models.subwords)
    if opts.scoring == "arrays":
        scores = lm.score_in_place(rows, models.perplexity, opts.lm_order)
        if scores is None:
            raise ValueError("the model has too many single tokens for arrays")
    else:
        arrays = lm.freeze(models.perplexity) if opts.scoring == "auto" else None
        scores = lm.score_dealt(rows, models.perplexity, opts.lm_order) if arrays is None else lm.score_by_arrays(rows, arrays, opts.lm_order)
    return lm.document_ppl(scores, opts.aggregate).select("doc_id", "ppl")


def curate(docs: DataFrame, models: Models, opts: CurateOptions = CurateOptions()) -> DataFrame:
    """(doc_id, lang, lang_score, ppl, bucket, text, para_nos) of the corpus made from documents (doc_id, shard_id, text)."""
    kept = materialize(languages(docs, models, opts), "languages")
    if not opts.lm_order or models.perplexity is None:
        return kept.select("doc_id", "lang", "lang_score", F.lit(None).cast("double").alias("ppl"), F.lit("all").alias("bucket"), "text", "para_nos")
    scores = materialize(kept.select("doc_id", "lang").join(scored(kept, models, opts), "doc_id", "left"), "perplexities")
    bucketed = buckets.assign(scores, buckets.thresholds(scores, opts.cuts)).select("doc_id", "ppl", "bucket")
    return kept.join(bucketed, "doc_id").select("doc_id", "lang", "lang_score", "ppl", "bucket", "text", "para_nos")


def curate_many(docs: DataFrame, snapshots: list[int], models: Models, opts: CurateOptions = CurateOptions()) -> DataFrame:
    """Every snapshot by itself, then their union with the snapshot's number."""
    out = None
    for s in snapshots:
        one = curate(docs.where(F.col("snapshot") == s).drop("snapshot"), models, opts).withColumn("snapshot", F.lit(s))
        out = one if out is None else out.unionByName(one)
    return out


# --- the two passes of a cluster that hashes first ---------------------------------------------------------------


def pass_hash(docs: DataFrame, path: str, opts: CurateOptions = CurateOptions()) -> None:
    """Pass one: the keys of all paragraphs to disk, no text."""
    dedup.keyed(paragraphs.explode(docs, shard=F.col("shard_id"))).write.mode("overwrite").parquet(path)


def pass_process(docs: DataFrame, path: str, models: Models, opts: CurateOptions = CurateOptions()) -> DataFrame:
    """Pass two: everything else, from the keys on disk. Restarts here if it is lost."""
    keys = docs.sparkSession.read.parquet(path)
    kept = dedup.documents(dedup.survivors(keys, opts.scope, opts.policy), docs, min_chars=opts.min_chars).select("doc_id", "text", "para_nos")
    kept = kept.withColumn("shard_id", F.lit(0))
    done = replace(opts, scope=None)
    out = curate(kept.drop("para_nos"), models, done)
    return out.drop("para_nos").join(kept.select("doc_id", "para_nos"), "doc_id")
