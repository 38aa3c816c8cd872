"""Measures of reduction, cost, order, language statistics, perplexity and quality. Plan builders: no actions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.normalize import key64, normalize
from ..functions.sentences import count_sentences
from . import dedup


def r6(c: Column) -> Column:
    return F.round(c, 6) + F.lit(0.0)


# --- reduction -------------------------------------------------------------------------------------------------


def shard_sums(keys: DataFrame) -> DataFrame:
    """(shard_id, h64): first position, its characters, copies and characters of all. Every coarser scope follows from
    this table, as minimum and sums are associative; the characters of the first copy travel with its position."""
    return keys.groupBy("shard_id", "h64").agg(
        F.min("pos").alias("pos"), F.min_by("n_chars", "pos").alias("first_chars"), F.count(F.lit(1)).alias("copies"), F.sum("n_chars").alias("chars")
    )


def remaining(keys: DataFrame, scopes: list[int], policy: str = "keep_first") -> DataFrame:
    """(scope, kept_chars, all_chars, kept_share) for blocks of each number of shards; one pass over the paragraphs."""
    base = shard_sums(keys)
    blocks = base.select("*", F.explode(F.array(*(F.lit(n) for n in scopes))).alias("scope"))
    rolled = blocks.groupBy("scope", F.floor(F.col("shard_id") / F.col("scope")).alias("block"), "h64").agg(F.min_by("first_chars", "pos").alias("first_chars"), F.sum("copies").alias("copies"), F.sum("chars").alias("chars"))
    kept = F.when(F.col("copies") == 1, F.col("chars")).otherwise(0) if policy == "drop_all" else F.col("first_chars")
    sums = rolled.groupBy("scope").agg(F.sum(kept).cast("long").alias("kept_chars"), F.sum("chars").cast("long").alias("all_chars"))
    return sums.withColumn("kept_share", r6(F.col("kept_chars") / F.col("all_chars")))


def duplicate_share(keys: DataFrame) -> DataFrame:
    """Share of paragraphs and of characters that repeat an earlier paragraph, over everything."""
    first = keys.groupBy("h64").agg(F.min_by("n_chars", "pos").alias("first"), F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))
    sums = first.agg(F.sum("n").alias("paras"), F.count(F.lit(1)).alias("distinct_paras"), F.sum("chars").cast("long").alias("chars"), F.sum("first").cast("long").alias("first_chars"))
    return sums.select("paras", "distinct_paras", r6(1 - F.col("distinct_paras") / F.col("paras")).alias("repeated_paras"), r6(1 - F.col("first_chars") / F.col("chars")).alias("repeated_chars"))


def docs_removed(keys: DataFrame, scopes: list[int]) -> DataFrame:
    """(scope, docs, removed): documents with no paragraph left."""
    out = None
    for n in scopes:
        left = dedup.survivors(keys, dedup.Shards(n)).select(dedup.doc_of(F.col("pos")).alias("doc_id")).agg(F.count_distinct("doc_id").alias("left"))
        row = keys.agg(F.count_distinct("doc_id").alias("docs")).crossJoin(left).select(F.lit(n).alias("scope"), "docs", (F.col("docs") - F.col("left")).alias("removed"))
        out = row if out is None else out.unionByName(row)
    return out


def hashset_cost(keys: DataFrame, scopes: list[int], disk_bytes: float = 9.0, memory_bytes: float = 26.7) -> DataFrame:
    """(scope, blocks, keys_max, disk_bytes, memory_bytes): unique keys of the largest block and what they take."""
    base = keys.select("shard_id", "h64").distinct()
    blocks = base.select("h64", F.explode(F.array(*(F.struct(F.lit(n).alias("scope"), F.floor(F.col("shard_id") / n).alias("block")) for n in scopes))).alias("b"))
    sizes = blocks.select("h64", "b.scope", "b.block").distinct().groupBy("scope", "block").agg(F.count(F.lit(1)).alias("n"))
    most = sizes.groupBy("scope").agg(F.count(F.lit(1)).alias("blocks"), F.max("n").alias("keys_max"))
    return most.select("scope", "blocks", "keys_max", r6(F.col("keys_max") * disk_bytes).alias("disk_bytes"), r6(F.col("keys_max") * memory_bytes).alias("memory_bytes"))


def hashset_cost_sketch(keys: DataFrame, scopes: list[int]) -> DataFrame:
    """Unique keys of each block by mergeable sketches: one for each shard, unions for the blocks."""
    shards = keys.groupBy("shard_id").agg(F.hll_sketch_agg("h64").alias("s"))
    blocks = shards.select("s", F.explode(F.array(*(F.struct(F.lit(n).alias("scope"), F.floor(F.col("shard_id") / n).alias("block")) for n in scopes))).alias("b"))
    return blocks.groupBy("b.scope", "b.block").agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("keys"))


def snapshot_overlap(keys: DataFrame) -> DataFrame:
    """(a, b, shared, jaccard) of the key sets of each two snapshots. A key meets the snapshots it occurs in, of which there
    are few, instead of itself."""
    where = keys.groupBy("h64").agg(F.collect_set("snapshot").alias("s"))
    sizes = where.select(F.explode("s").alias("snapshot")).groupBy("snapshot").agg(F.count(F.lit(1)).alias("n"))
    pair = where.select("s", F.explode("s").alias("a")).select("a", F.explode(F.filter("s", lambda x: x > F.col("a"))).alias("b"))
    shared = pair.groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))
    of = lambda c: sizes.select(F.col("snapshot").alias(c), F.col("n").alias(f"n_{c}"))
    every = of("a").join(of("b"), F.col("a") < F.col("b")).join(shared, ["a", "b"], "left")
    n = F.coalesce("shared", F.lit(0).cast("long"))
    return every.select("a", "b", n.alias("shared"), r6(n / (F.col("n_a") + F.col("n_b") - n)).alias("jaccard"))


def snapshot_overlap_sketch(keys: DataFrame) -> DataFrame:
    """The same by theta sketches, one for each snapshot: one pass over the keys."""
    sketches = keys.groupBy("snapshot").agg(F.theta_sketch_agg("h64").alias("s"))
    of = lambda c: sketches.select(F.col("snapshot").alias(c), F.col("s").alias(f"s_{c}"))
    pairs = of("a").join(of("b"), F.col("a") < F.col("b"))
    shared = F.theta_sketch_estimate(F.theta_intersection("s_a", "s_b"))
    return pairs.select("a", "b", shared.alias("shared"), (shared / F.theta_sketch_estimate(F.theta_union("s_a", "s_b"))).alias("jaccard"))


def boilerplate(keys: DataFrame, k: int) -> DataFrame:
    """The k most repeated keys: copies and documents."""
    sums = keys.groupBy("h64", "doc_id").agg(F.count(F.lit(1)).alias("n")).groupBy("h64").agg(F.sum("n").alias("copies"), F.count(F.lit(1)).alias("docs"))
    return sums.select(dedup.hex_key(F.col("h64")).alias("h64"), "copies", "docs").orderBy(F.desc("copies"), "h64").limit(k)


def cross_language(keys: DataFrame) -> DataFrame:
    """Keys met in documents of more than one language."""
    sums = keys.groupBy("h64").agg(F.collect_set("lang").alias("l"), F.count_distinct("doc_id").alias("docs")).where(F.size("l") > 1)
    return sums.select(dedup.hex_key(F.col("h64")).alias("h64"), F.size("l").cast("long").alias("n_langs"), "docs", F.array_join(F.array_sort("l"), ",").alias("langs"))


def key_collisions(paras: DataFrame) -> DataFrame:
    """Keys that stand for more than one normal form; expected number for u keys: u * u / 2**65."""
    norm = normalize(F.col("para"))
    forms = paras.select(key64(norm).alias("h64"), norm.alias("norm")).distinct().groupBy("h64").agg(F.count(F.lit(1)).alias("forms"))
    return forms.where("forms > 1")


def collision_bound(unique_keys: int, bits: int = 64) -> float:
    return unique_keys * unique_keys / 2.0 ** (bits + 1)


# --- order of steps --------------------------------------------------------------------------------------------


def order_ratio(dedup_first: DataFrame, lid_first: DataFrame) -> DataFrame:
    """(lang, docs_dedup_first, docs_lid_first, ratio) of two results (doc_id, lang)."""
    a = dedup_first.groupBy("lang").agg(F.count(F.lit(1)).alias("docs_dedup_first"))
    b = lid_first.groupBy("lang").agg(F.count(F.lit(1)).alias("docs_lid_first"))
    both = a.join(b, "lang", "full")
    return both.select("lang", F.coalesce("docs_dedup_first", F.lit(0)).cast("long").alias("docs_dedup_first"), F.coalesce("docs_lid_first", F.lit(0)).cast("long").alias("docs_lid_first"), r6(F.col("docs_dedup_first") / F.col("docs_lid_first")).alias("ratio"))


def order_transitions(before: DataFrame, after: DataFrame) -> DataFrame:
    """(lang_before, lang_after, docs): what became of each document (doc_id, lang); "-" where it was discarded."""
    a, b = before.select("doc_id", F.col("lang").alias("lang_before")), after.select("doc_id", F.col("lang").alias("lang_after"))
    both = a.join(b, "doc_id", "full").select(F.coalesce("lang_before", F.lit("-")).alias("lang_before"), F.coalesce("lang_after", F.lit("-")).alias("lang_after"))
    return both.groupBy("lang_before", "lang_after").agg(F.count(F.lit(1)).alias("docs"))


# --- cost ------------------------------------------------------------------------------------------------------


def throughput(telemetry: DataFrame) -> DataFrame:
    """(stage, docs, cpu_s, wall_s, docs_per_core_s, docs_per_s)."""
    sums = telemetry.groupBy("stage").agg(F.sum("docs").alias("docs"), F.sum("cpu_s").alias("cpu_s"), F.sum("wall_s").alias("wall_s"))
    return sums.select("*", r6(F.col("docs") / F.col("cpu_s")).alias("docs_per_core_s"), r6(F.col("docs") / F.col("wall_s")).alias("docs_per_s"))


def cpu_share(telemetry: DataFrame, stage: str = "stage", cpu: str = "cpu_s") -> DataFrame:
    sums = telemetry.groupBy(F.col(stage).alias("stage")).agg(F.sum(cpu).alias("cpu_s"))
    return sums.select("stage", r6("cpu_s").alias("cpu_s"), r6(F.col("cpu_s") / F.sum("cpu_s").over(W.partitionBy())).alias("share"))


def capacity_plan(plan: DataFrame) -> DataFrame:
    """From (shards, docs_per_shard, hash_rate, score_rate, workers, processes, cores): hours of both passes and of the whole."""
    hash_h = F.col("docs_per_shard") / F.col("hash_rate") / 3600
    score_h = F.col("docs_per_shard") / (F.col("score_rate") * F.col("workers")) / 3600
    waves = F.ceil(F.col("shards") * F.col("processes") / F.col("cores"))
    first = F.ceil(F.col("shards") / F.col("cores")) * hash_h
    return plan.select("shards", r6(hash_h).alias("hash_hours_per_shard"), r6(score_h).alias("score_hours_per_shard"), waves.cast("long").alias("waves"), r6(first + F.col("shards") * F.col("processes") / F.col("cores") * score_h).alias("hours"))


# --- language statistics ---------------------------------------------------------------------------------------


def language_stats(docs: DataFrame, text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """(lang, docs, paragraphs, sentences, tokens, bytes); tokens are runs of non-space."""
    lines = F.filter(F.split(text_col, "\n"), lambda x: F.trim(x) != "")
    row = docs.select(F.col(lang_col).alias("lang"), F.octet_length(text_col).alias("bytes"), lines.alias("l"), F.regexp_count(text_col, F.lit(r"[^ \n]+")).alias("tokens"))
    row = row.select("lang", "bytes", "tokens", F.size("l").alias("paragraphs"), F.aggregate("l", F.lit(0), lambda acc, x: acc + count_sentences(x)).alias("sentences"))
    return row.groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), *(F.sum(c).cast("long").alias(c) for c in ("paragraphs", "sentences", "tokens", "bytes")))


def languages_over(stats: DataFrame, docs: list[int], tokens: list[int]) -> DataFrame:
    """(measure, over, languages): how many languages exceed each size."""
    rows = [F.struct(F.lit(m).alias("measure"), F.lit(n).cast("long").alias("over"), (F.col(m) > n).cast("long").alias("hit")) for m, sizes in (("docs", docs), ("tokens", tokens)) for n in sizes]
    return stats.select(F.explode(F.array(*rows)).alias("r")).groupBy("r.measure", "r.over").agg(F.sum("r.hit").alias("languages"))


def log_histogram(stats: DataFrame, measure: str) -> DataFrame:
    """(lang, value, power): the power of ten in which each language's value lies."""
    return stats.select("lang", F.col(measure).alias("value"), F.floor(F.log10(measure)).cast("long").alias("power"))


def top_languages(stats: DataFrame, measure: str, k: int) -> DataFrame:
    ranked = stats.select("lang", F.col(measure).alias("value"), F.row_number().over(W.orderBy(F.desc(measure), "lang")).alias("rank"))
    return ranked.where(F.col("rank") <= k)


def size_vs_target(corpus: DataFrame, target: DataFrame) -> DataFrame:
    """(lang, corpus_bytes, target_bytes, ratio)."""
    a = corpus.groupBy("lang").agg(F.sum(F.octet_length("text")).cast("long").alias("corpus_bytes"))
    b = target.groupBy("lang").agg(F.sum(F.octet_length("text")).cast("long").alias("target_bytes"))
    return a.join(b, "lang").select("lang", "corpus_bytes", "target_bytes", r6(F.col("corpus_bytes") / F.col("target_bytes")).alias("ratio"))


# --- perplexity and quality ------------------------------------------------------------------------------------


def ppl_histogram(scores: DataFrame, cuts: DataFrame, width: float = 0.1) -> DataFrame:
    """(lang, bin, docs, cut_head, cut_tail): bins of log10 perplexity."""
    bins = scores.groupBy("lang", F.floor(F.log10("ppl") / width).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("docs"))
    return bins.join(F.broadcast(cuts), "lang").select("lang", "bin", "docs", r6("cut_head").alias("cut_head"), r6("cut_tail").alias("cut_tail"))


def ppl_spread(scores: DataFrame) -> DataFrame:
    """(lang, q25, q50, q75, iqr, std, spikiness): the last is the share of documents within a tenth of the median."""
    q = scores.groupBy("lang").agg(F.percentile("ppl", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("q"), F.stddev_samp("ppl").alias("std"))
    near = scores.join(F.broadcast(q), "lang").groupBy("lang").agg(F.avg((F.abs(F.col("ppl") - F.col("q")[1]) <= 0.1 * F.col("q")[1]).cast("double")).alias("spikiness"))
    return q.join(near, "lang").select("lang", r6(F.col("q")[0]).alias("q25"), r6(F.col("q")[1]).alias("q50"), r6(F.col("q")[2]).alias("q75"), r6(F.col("q")[2] - F.col("q")[0]).alias("iqr"), F.round("std", 4).alias("std"), r6("spikiness").alias("spikiness"))


def bucket_profile(docs: DataFrame) -> DataFrame:
    """(bucket, docs, separator_density, type_token_ratio): keyword lists have many separators and few repeats. ``docs`` has
    text and bucket."""
    words = F.filter(F.split(F.lower("text"), "[ \n]+"), lambda w: w != "")
    row = docs.select("bucket", (F.regexp_count("text", F.lit(r"[|,;:>•]")) / F.greatest(F.length("text"), F.lit(1))).alias("s"), (F.size(F.array_distinct(words)) / F.greatest(F.size(words), F.lit(1))).alias("t"))
    return row.groupBy("bucket").agg(F.count(F.lit(1)).alias("docs"), r6(F.avg("s")).alias("separator_density"), r6(F.avg("t")).alias("type_token_ratio"))


def bucket_quality(bucketed: DataFrame, labels: DataFrame) -> DataFrame:
    """(lang, bucket, docs, quality_share, toxic_share) over labelled documents."""
    return bucketed.join(labels, "doc_id").groupBy("lang", "bucket").agg(F.count(F.lit(1)).alias("docs"), r6(F.avg(F.col("quality").cast("double"))).alias("quality_share"), r6(F.avg(F.col("toxic").cast("double"))).alias("toxic_share"))


def auc(scored: DataFrame, by: list[str], score: str, label: str) -> DataFrame:
    """(*by, n_pos, n_neg, auc) by the rank sum with mean ranks for ties. Scores are first counted by value, so the window
    runs over distinct scores."""
    values = scored.groupBy(*by, score).agg(F.sum(F.col(label).cast("long")).alias("pos"), F.count(F.lit(1)).alias("n"))
    below = F.sum("n").over(W.partitionBy(*by).orderBy(score).rowsBetween(W.unboundedPreceding, -1))
    ranked = values.withColumn("rank", F.coalesce(below, F.lit(0)) + (F.col("n") + 1) / 2)
    sums = ranked.groupBy(*by).agg(F.sum("pos").alias("n_pos"), F.sum(F.col("n") - F.col("pos")).alias("n_neg"), F.sum(F.col("rank") * F.col("pos")).alias("s"))
    return sums.select(*by, "n_pos", "n_neg", r6((F.col("s") - F.col("n_pos") * (F.col("n_pos") + 1) / 2) / (F.col("n_pos") * F.col("n_neg"))).alias("auc"))


def auc_binned(scored: DataFrame, by: list[str], score: Column, label: str, bins: int = 10_000) -> DataFrame:
    """The same with scores (0 to 1) in bins: bounded work for each group, error below one bin."""
    return auc(scored.withColumn("__bin", F.floor(score * bins)), by, "__bin", label)


def macro_accuracy(predictions: DataFrame) -> DataFrame:
    """(lang, docs, accuracy) of (lang, label, predicted), and the mean over languages as lang "avg"."""
    each = predictions.groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.avg((F.col("label") == F.col("predicted")).cast("double")).alias("accuracy"))
    total = each.agg(F.lit("avg").alias("lang"), F.sum("docs").alias("docs"), F.avg("accuracy").alias("accuracy"))
    return each.unionByName(total).select("lang", "docs", r6("accuracy").alias("accuracy"))


def confusion(predictions: DataFrame) -> DataFrame:
    """(truth, predicted, docs, recall): recall of the truth's language on each row."""
    counts = predictions.groupBy("truth", "predicted").agg(F.count(F.lit(1)).alias("docs"))
    total = F.sum("docs").over(W.partitionBy("truth"))
    right = F.sum(F.when(F.col("truth") == F.col("predicted"), F.col("docs")).otherwise(0)).over(W.partitionBy("truth"))
    return counts.select("truth", "predicted", "docs", r6(right / total).alias("recall"))
