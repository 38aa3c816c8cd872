"""Registration of the column functions for SQL users, as SQL functions that Catalyst inlines, and of table functions."""

from __future__ import annotations

import re
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult, udtf
from pyspark.sql.types import IntegerType, LongType, StringType, StructType

from . import html, urls
from .normalize import accent_map


def quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


class ParagraphsOf:
    """Rows (doc_id, para_no, para) of a table with a text column: one for each non-blank line."""

    @staticmethod
    def analyze(documents: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(StructType().add("doc_id", LongType()).add("para_no", IntegerType()).add("para", StringType()))

    def eval(self, row) -> Iterator[tuple]:
        fields = row.asDict()
        for i, line in enumerate((fields["text"] or "").split("\n")):
            if line.strip(" "):
                yield fields["doc_id"], i, line


class NgramsOf:
    """Rows (doc_id, ngram) of a table with a text column: every run of n words."""

    @staticmethod
    def analyze(documents: AnalyzeArgument, n: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(StructType().add("doc_id", LongType()).add("ngram", StringType()))

    def eval(self, row, n: int) -> Iterator[tuple]:
        fields = row.asDict()
        words = re.findall(r"\S+", fields["text"] or "")
        for i in range(len(words) - n + 1):
            yield fields["doc_id"], " ".join(words[i : i + n])


def register(spark: SparkSession) -> None:
    """``norm_para``, ``para_key``, ``html_blocks``, ``url_host``, ``ppl``, ``bucket_of``, ``paragraphs_of(TABLE(...))`` and
    ``ngrams_of(TABLE(...), n)``."""
    accented, plain = accent_map()
    norm = f"lower(s)"
    norm = f"regexp_replace(translate({norm}, {quoted(accented)}, {quoted(plain)}), {quoted(chr(92) + 'p{Mn}+')}, '')"
    norm = f"regexp_replace(regexp_replace({norm}, {quoted(chr(92) + 'p{Nd}+')}, '0'), {quoted(chr(92) + 'p{P}+')}, '')"
    block = "s"
    for pattern, by in html.STEPS:
        block = f"regexp_replace({block}, {quoted(pattern)}, {quoted(by)})"
    for entity, character in html.ENTITIES:
        block = f"replace({block}, {quoted(entity)}, {quoted(character)})"
    block = f"regexp_replace({block}, {quoted('[ ' + chr(92) + 't' + chr(92) + 'r]+')}, ' ')"
    functions = {
        "norm_para(s STRING) RETURNS STRING": norm,
        "para_key(s STRING) RETURNS STRING": "substring(sha1(encode(norm_para(s), 'UTF-8')), 1, 16)",
        "html_blocks(s STRING) RETURNS ARRAY<STRING>": f"filter(transform(split({block}, '\\n'), x -> trim(x)), x -> x <> '')",
        "url_host(s STRING) RETURNS STRING": f"lower(regexp_extract(s, {quoted(urls.HOST)}, 1))",
        "ppl(log10_sum DOUBLE, n BIGINT) RETURNS DOUBLE": "CASE WHEN n > 0 THEN pow(10D, -log10_sum / n) END",
        "bucket_of(p DOUBLE, cut_head DOUBLE, cut_tail DOUBLE) RETURNS STRING": "CASE WHEN p IS NULL THEN 'all' WHEN p <= cut_head THEN 'head' WHEN p > cut_tail THEN 'tail' ELSE 'middle' END",
    }
    for signature, body in functions.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {signature} RETURN {body}")
    spark.udtf.register("paragraphs_of", udtf(ParagraphsOf))
    spark.udtf.register("ngrams_of", udtf(NgramsOf))
