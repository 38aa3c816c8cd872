"""Sentence counts: a sentence ends at . ! or ? before white space or the end, but not after a known abbreviation."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Fixed value: abbreviations after which a full stop ends no sentence.
ABBREVIATIONS = ("mr", "mrs", "dr", "prof", "st", "vs", "etc", "no", "fig", "al")
PATTERN_ABBREVIATION = r"(?i)(^|[^a-z])(" + "|".join(ABBREVIATIONS) + r")\."
PATTERN_END = r"[.!?]+(\s|$)"


def count_sentences(paragraph: Column) -> Column:
    """Sentence ends of a paragraph, at least one where there is any text."""
    plain = F.regexp_replace(paragraph, PATTERN_ABBREVIATION, "$1$2")
    n = F.regexp_count(plain, F.lit(PATTERN_END))
    return F.when(F.trim(paragraph) == "", F.lit(0)).otherwise(F.greatest(n, F.lit(1)))
