"""The manifest of a finished run, and the corpus rebuilt from it and the raw pages. Pages are known by their ids: several may have one url."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .paragraphs import pick_lines


def digest(text: Column) -> Column:
    return F.sha2(text, 256)


def manifest(corpus: DataFrame, pages: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("lang", "lang_score", "ppl", "bucket")) -> DataFrame:
    """(page_id, url, page_digest, para_nos, *keep). ``corpus`` has page_id and para_nos, ``pages`` page_id, url and the text as
    it was split."""
    raw = pages.select("page_id", "url", digest(F.col(text_col)).alias("page_digest"))
    return corpus.select("page_id", "para_nos", *keep).join(raw, "page_id").select("page_id", "url", "page_digest", "para_nos", *keep)


def rebuild(entries: DataFrame, pages: DataFrame, text_col: str = "text") -> DataFrame:
    """``entries`` with their text; pages that changed since, or are missing, give no row."""
    raw = pages.select("page_id", F.col(text_col).alias("__text"))
    met = entries.join(raw, "page_id").where(digest(F.col("__text")) == F.col("page_digest"))
    return met.select(*entries.columns, pick_lines(F.col("__text"), F.col("para_nos")).alias("text"))


def audit(entries: DataFrame, pages: DataFrame, text_col: str = "text") -> DataFrame:
    """(status, pages): entries that are unchanged, changed or missing, and pages without an entry ("new")."""
    raw = pages.select("page_id", digest(F.col(text_col)).alias("__now"))
    status = F.when(F.col("page_digest").isNull(), "new").when(F.col("__now").isNull(), "missing").when(F.col("__now") == F.col("page_digest"), "unchanged").otherwise("changed")
    return entries.select("page_id", "page_digest").join(raw, "page_id", "full").groupBy(status.alias("status")).agg(F.count(F.lit(1)).alias("pages"))


def audit_log(entries: DataFrame, pages: DataFrame, text_col: str = "text") -> DataFrame:
    """(url) of the entries that cannot be rebuilt."""
    raw = pages.select("page_id", digest(F.col(text_col)).alias("__now"))
    return entries.select("page_id", "url", "page_digest").join(raw, "page_id", "left").where(F.col("__now").isNull() | (F.col("__now") != F.col("page_digest"))).select("url")
