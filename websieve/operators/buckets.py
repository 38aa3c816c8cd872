"""Head, middle and tail: cuts of perplexity by language and their use."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

THIRDS = (1 / 3, 2 / 3)


def thresholds(scores: DataFrame, method: str = "exact", weight: str = "documents", per_language: bool = True, accuracy: int = 10_000) -> DataFrame:
    """(lang, cut_head, cut_tail). ``exact`` interpolates between documents; ``sketch`` is one mergeable pass with a rank
    error of at most 1/accuracy; with ``weight`` "chars" or "tokens" the parts are equal in that column."""
    by = ["lang"] if per_language else []
    if weight != "documents":
        return weighted_thresholds(scores, {"chars": "n_chars", "tokens": "n_tokens"}[weight], by)
    cuts = F.array(*(F.lit(x) for x in THIRDS))
    q = F.percentile("ppl", cuts) if method == "exact" else F.percentile_approx("ppl", cuts, accuracy)
    rows = scores.where(F.col("ppl").isNotNull()).groupBy(*by).agg(q.alias("q"))
    lang = F.col("lang") if per_language else F.lit("*")
    return rows.select(lang.alias("lang"), F.col("q")[0].alias("cut_head"), F.col("q")[1].alias("cut_tail"))


def weighted_thresholds(scores: DataFrame, weight_col: str, by: list[str]) -> DataFrame:
    """Cuts at the first perplexity where a third and two thirds of the weight are reached. Weights are first added up by
    perplexity, so the window runs over distinct values."""
    values = scores.where(F.col("ppl").isNotNull()).groupBy(*by, "ppl").agg(F.sum(weight_col).alias("w"))
    run = F.sum("w").over(W.partitionBy(*by).orderBy("ppl")) / F.sum("w").over(W.partitionBy(*by))
    rows = values.withColumn("run", run)
    cut = lambda x: F.min(F.when(F.col("run") >= x, F.col("ppl")))
    out = rows.groupBy(*by).agg(cut(THIRDS[0]).alias("cut_head"), cut(THIRDS[1]).alias("cut_tail"))
    return out.select((F.col("lang") if by else F.lit("*")).alias("lang"), "cut_head", "cut_tail")


def bucket_of(ppl: Column, head: Column, tail: Column) -> Column:
    return F.when(ppl.isNull() | head.isNull(), "all").when(ppl <= head, "head").when(ppl > tail, "tail").otherwise("middle")


def assign(scores: DataFrame, cuts: DataFrame) -> DataFrame:
    """``scores`` with a bucket; languages without cuts (no model) get the bucket "all". Cuts are one row a language."""
    if cuts.select("lang").limit(1).where("lang = '*'").isEmpty():
        joined = scores.join(F.broadcast(cuts), "lang", "left")
    else:
        joined = scores.crossJoin(F.broadcast(cuts.drop("lang")))  # one row
    return joined.withColumn("bucket", bucket_of(F.col("ppl"), F.col("cut_head"), F.col("cut_tail"))).drop("cut_head", "cut_tail")


def by_rank(scores: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Buckets whose sizes differ by one document at most, ties divided by id. For tables small enough to sort by language."""
    third = F.ntile(3).over(W.partitionBy("lang").orderBy("ppl", id_col))
    return scores.withColumn("bucket", F.element_at(F.array(F.lit("head"), F.lit("middle"), F.lit("tail")), third))


def select(bucketed: DataFrame, names: tuple[str, ...] | None = None, max_ppl: float | None = None) -> DataFrame:
    """Optional removal; by default nothing goes."""
    out = bucketed.where(F.col("bucket").isin(*names)) if names else bucketed
    return out.where(F.col("ppl") <= max_ppl) if max_ppl is not None else out


def random_split(df: DataFrame, *cols: str) -> DataFrame:
    """Three parts that do not depend on perplexity: the control for buckets."""
    third = F.pmod(F.xxhash64(*cols), F.lit(3)).cast("int") + 1
    return df.withColumn("bucket", F.element_at(F.array(F.lit("head"), F.lit("middle"), F.lit("tail")), third))


class DriftingCuts:
    """Cuts of a stream of snapshots from mergeable sketches of log10 perplexity, one row a language and batch."""

    @staticmethod
    def sketch(scores: DataFrame) -> DataFrame:
        return scores.where("ppl > 0").groupBy("lang").agg(F.kll_sketch_agg_double(F.log10("ppl")).alias("sketch"))

    @staticmethod
    def cuts(sketches: DataFrame) -> DataFrame:
        merged = sketches.groupBy("lang").agg(F.kll_merge_agg_double("sketch").alias("s")) if hasattr(F, "kll_merge_agg_double") else sketches.groupBy("lang").agg(F.reduce(F.collect_list("sketch"), F.lit(None).cast("binary"), lambda a, b: F.when(a.isNull(), b).otherwise(F.kll_sketch_merge_double(a, b))).alias("s"))
        q = lambda x: F.pow(F.lit(10.0), F.kll_sketch_get_quantile_double("s", F.lit(x)))
        return merged.select("lang", q(THIRDS[0]).alias("cut_head"), q(THIRDS[1]).alias("cut_tail"))
