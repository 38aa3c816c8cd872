"""Subword tokenizers and the text-extract source."""

from __future__ import annotations

from pyspark.sql import functions as F

from websieve.operators import subword
from websieve.sources import textextract


def test_merges(spark):
    table = spark.createDataFrame([("en", "abab", 5), ("en", "abc", 3), ("en", "cc", 1)], "lang string, word string, cnt long")
    counts = {(r.a, r.b): r.cnt for r in subword.pair_counts(subword.spelled(table)).collect()}
    assert counts == {("a", "b"): 13, ("b", "a"): 5, ("b", "c"): 3, ("c", "c"): 1}
    model = subword.fit_merges(table, 2)
    assert model.pairs == [("a", "b"), ("ab", "ab")] and model.encode("ababc") == ["abab", "c"]


def test_unigram_never_loses_likelihood_within_a_round_and_is_lossless(spark):
    words = ["banana", "bandana", "ananas", "band", "ban"]
    table = spark.createDataFrame([("en", w, 3) for w in words], "lang string, word string, cnt long")
    model, history = subword.fit_unigram(table, 12, em_rounds=2)
    assert len(model.pieces) <= 12 and history[1] >= history[0] - 1e-9
    assert all("".join(model.encode(w)) == w for w in [*words, "xyz"])
    docs = spark.createDataFrame([("en", ["banana", "ban"])], "lang string, toks array<string>")
    assert "".join(subword.encode(docs, {"en": model}).select(F.explode("toks").alias("t")).toPandas()["t"]) == "bananaban"


def test_text_extracts(spark, tmp_path):
    text = "Un\r\n\r\nWARC/1.0 inside\n".encode()
    record = b"WARC/1.0\r\nWARC-Type: conversion\r\nWARC-Target-URI: http://x/1\r\nWARC-Date: d\r\nWARC-Block-Digest: s\r\nContent-Length: %d\r\n\r\n%s\r\n\r\n" % (len(text), text)
    (tmp_path / "a.wet").write_bytes(b"WARC/1.0\r\nWARC-Type: warcinfo\r\nContent-Length: 2\r\n\r\nhi\r\n\r\n" + record * 2)
    for df in (textextract.read_wet(spark, f"{tmp_path}/*.wet"), textextract.read_binary(spark, f"file://{tmp_path}/*.wet")):
        assert [(r.url, r.text) for r in df.collect()] == [("http://x/1", text.decode())] * 2
