"""Queries over whole tables, held against brute force: rows beyond the ids of their reduced forms count."""

from __future__ import annotations

import math
from collections import Counter

import pytest
from pyspark.sql import functions as F

from websieve.operators import evaluation, lm
from websieve.queries import CALLS
from websieve.queries import models as q

TEXTS = {3: "Ab ab", 4: "One two\nthree", 250: "xyzxyz", 901: "Short\nlines here", 902: ""}


def test_text_queries_read_every_document(spark, tmp_path):
    sf = f"file://{tmp_path}"
    spark.createDataFrame([(i, t, "en", "src1", len(t)) for i, t in TEXTS.items()], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{sf}/documents.parquet")
    grams = {i: Counter(t.lower()[k : k + n] for n in (2, 3) for k in range(len(t) - n + 1)) for i, t in TEXTS.items() if t}
    assert {r.doc_id: (r.kinds, r.n) for r in CALLS["l_char_ngrams_all"](spark, sf).collect()} == {i: (len(c), sum(c.values())) for i, c in grams.items()}
    assert {r.doc_id: r.n_tokens for r in CALLS["t_char_tokens_all"](spark, sf).collect()} == {i: len(t.replace("\n", "")) for i, t in TEXTS.items() if t}
    assert {(r.doc_id, r.para_no) for r in CALLS["t_word_tokens_all"](spark, sf).collect()} == {(i, k) for i, t in TEXTS.items() if t for k, _ in enumerate(t.split("\n"))}


def test_analogies_search_every_vector(spark, tmp_path):
    sf = f"file://{tmp_path}"
    vecs = {i: [math.sin(i * 1.7), math.cos(i * 2.3), math.sin(i * 0.9 + 1)] for i in range(40)}
    vecs[777] = [y - x + z for x, y, z in zip(vecs[0], vecs[1], vecs[2])]
    spark.createDataFrame(list(vecs.items()), "vec_id long, embedding array<float>").write.parquet(f"{sf}/embeddings.parquet")
    assert {r.a: r.word for r in CALLS["e_analogy_vectors_all"](spark, sf).collect()}["0"] == "777"


def test_joins_take_every_row(spark, tmp_path):
    sf = f"file://{tmp_path}"
    spark.createDataFrame([(c,) for c in range(1, 7)], "c_custkey long").write.parquet(f"{sf}/customer.parquet")
    orders = [(o, o % 9) for o in range(20)]
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long").write.parquet(f"{sf}/orders.parquet")
    both = {(c, o) for o, c in orders if 1 <= c <= 6}
    right = both | {(None, o) for o, c in orders if not 1 <= c <= 6}
    for how, want in (("inner", both), ("left", both), ("right", right), ("full", right)):
        assert {tuple(r) for r in CALLS[f"r_join_{how}_all"](spark, sf).collect()} == want


SMALL = "/root/testdata/sf0.001"


def test_transfer_compares_with_the_head_at_the_size_of_the_target(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(evaluation, "transfer", lambda corpora, dev, **given: seen.append((corpora, given)) or spark.createDataFrame([("target", 0.0)], "corpus string, accuracy double"))
    assert {r.lang for r in CALLS["e_transfer"](spark, SMALL).collect()} == {"en", "fr"}
    target = q.target(spark, SMALL)
    outside = lm.outside(q.lid_train(spark, SMALL), target)
    ppl = lm.document_ppl(lm.score_by_join(lm.sentences(outside), q.word_model(spark, SMALL), 3))
    rows = {(r.lang, r.doc_id): r.ppl for r in ppl.collect()}
    for lang, (given, options) in zip(("en", "fr"), seen):
        mine = sorted((p, i) for (of, i), p in rows.items() if of == lang)
        head = {r.doc_id for r in given["crawl"].collect()}
        assert head and abs(len(head) - len(mine) / 3) <= 1 and head == {i for _, i in mine[: len(head)]}
        n_bytes = target.where(F.col("lang") == lang).agg(F.sum(F.octet_length("text"))).first()[0]
        assert options["cap_bytes"] == n_bytes and options["dim"] == 300


def test_bucket_table_has_both_languages_at_full_width(spark, monkeypatch):
    dims = []
    monkeypatch.setattr(evaluation, "bucket_table", lambda docs, dim: dims.append(dim) or docs.select("bucket").distinct())
    assert {r.lang for r in CALLS["e_bucket_table"](spark, SMALL).collect()} == {"en", "fr"} and dims == [300, 300]


def test_capacity_plan_counts_the_documents_it_is_given(spark, tmp_path):
    rows = [(i, f"source{i % 4}") for i in range(72_000)]
    spark.createDataFrame(rows, "doc_id long, source string").write.parquet(f"file://{tmp_path}/documents.parquet")
    plan = CALLS["x_capacity_plan"](spark, f"file://{tmp_path}").first()
    assert (plan.shards, plan.hash_hours_per_shard, plan.waves) == (4, pytest.approx(18_000 / 600 / 3600, abs=1e-6), 1)
