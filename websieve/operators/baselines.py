"""What the pipeline is compared with."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import urls
from . import dedup


def line_corpus(paras: DataFrame, langs: DataFrame) -> DataFrame:
    """(lang, h64, docs): language first, then each distinct line once for each language; documents are lost. ``langs`` has the
    language of each line (doc_id, para_no, lang)."""
    keys = dedup.keyed(paras.select("doc_id", "shard_id", "para_no", "pos", "para"))
    return keys.join(langs, ["doc_id", "para_no"]).groupBy("lang", "h64").agg(F.count_distinct("doc_id").alias("docs"))


def curated_only(target: DataFrame) -> DataFrame:
    return target.select("lang", "text")


def curated_concat(target: DataFrame, others: DataFrame) -> DataFrame:
    """Trusted sources put together; ``others`` has lang and text."""
    return target.select("lang", "text").unionByName(others.select("lang", "text"))


def url_allowlist(pages: DataFrame, links: DataFrame, most_hosts: int = 1_000_000) -> DataFrame:
    """Pages whose host is on a list of shared links; the list is broadcast up to a number of hosts."""
    hosts = links.select(urls.host(F.col("url")).alias("__host")).distinct()
    side = F.broadcast(hosts) if hosts.limit(most_hosts + 1).count() <= most_hosts else hosts
    return pages.join(side, urls.host(F.col("url")) == F.col("__host"), "left_semi")


@dataclass(frozen=True)
class RuleSet:
    """Hand-written rules for one language."""

    min_words: int = 20
    end_share: float = 0.5  # of lines that end a sentence
    max_symbol_share: float = 0.1
    stop_words: tuple[str, ...] = ("the", "of", "and", "to", "in", "that", "is", "for")
    min_stop_words: int = 2


def rules(docs: DataFrame, r: RuleSet = RuleSet()) -> DataFrame:
    lines = F.filter(F.split("text", "\n"), lambda x: F.trim(x) != "")
    ended = F.size(F.filter(lines, lambda x: F.trim(x).rlike(r"[.!?]$")))
    tokens = F.filter(F.split(F.lower("text"), "[ \n]+"), lambda w: w != "")
    symbols = F.regexp_count("text", F.lit(r"[#{}<>|*$%&]"))
    stops = F.size(F.array_intersect(F.array_distinct(tokens), F.array(*(F.lit(w) for w in r.stop_words))))
    return docs.where((F.size(tokens) >= r.min_words) & (ended >= r.end_share * F.size(lines)) & (symbols <= r.max_symbol_share * F.size(tokens)) & (stops >= r.min_stop_words))


def doc_dedup(docs: DataFrame) -> DataFrame:
    """(doc_id, copies) of the first of equal texts; only digests are shuffled."""
    return docs.groupBy(F.sha2("text", 256).alias("d")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies")).select("doc_id", "copies")
