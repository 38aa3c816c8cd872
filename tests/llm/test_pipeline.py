"""The pipeline's stages over a small table: planted cases go, clean documents stay."""

from __future__ import annotations

import random

import corpus_pipeline
from websieve.llm import toxicity

from .test_operators import prose


def test_stages_catch_planted_cases(spark, tmp_path):
    rng = random.Random(9)
    docs, labels = [], []
    for i in range(400):
        text = "\n".join(prose(rng, 25, "abcdefghij") for _ in range(2))
        if i % 4 == 0:
            text += " " + " ".join("zzkro" + prose(rng, 1) for _ in range(4))
        docs.append((i, text, "en", f"src{i % 3}", len(text)))
        labels.append((i, 1, int(i % 4 == 0)))
    passage = prose(rng, 30)
    clean = [i for i in range(400) if i % 4]
    docs += [(1000, docs[1][1], "en", "src1", 1), (1001, docs[2][1].replace("\n", " extra\n", 1), "en", "src1", 1), (1002, prose(rng, 40) + " " + passage, "en", "src1", 1), (1003, None, "en", "src1", None), (1004, "", "en", "src1", 0)]
    boiler = "Subscribe to the newsletter of this site for more"
    docs = [(i, t + "\n" + boiler if t and s == "src2" else t, lang, s, n) for i, t, lang, s, n in docs]
    sf = f"file://{tmp_path}"
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    spark.createDataFrame([(1, passage)], "item_id long, text string").write.parquet(f"{sf}/benchmark.parquet")
    table = spark.read.parquet(f"{sf}/documents.parquet")
    kept = []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, table, sf)
        assert out.columns == table.columns
        table = corpus_pipeline.written(out, name)
        kept.append({r.doc_id: r.text for r in table.collect()})
    toxic, lines, joined, last = kept
    assert len([i for i in toxic if i % 4 == 0 and i < 400]) <= 2 and len([i for i in clean if i in toxic]) >= 297
    assert not any(t and boiler in t for t in lines.values()) and set(lines) == set(toxic)
    assert {1000, 1001} & set(joined) == set() and 1 in joined and 1003 in joined and 1004 in joined
    assert 1002 in joined and 1002 not in last and set(joined) - set(last) == {1002}
    pieces = corpus_pipeline.STAGES[-1][1](spark, table, sf)
    assert {r.doc_id for r in pieces.select("doc_id").collect()} == set(last)


DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def test_line_stage_finds_passages_on_few_per_cent_of_a_source(spark):
    rng = random.Random(4)
    passage, other = prose(rng, 60), prose(rng, 12)
    docs = []
    for i in range(600):
        lines = [prose(rng, 30), prose(rng, 20)]
        lines += [passage] * (i % 33 == 0) + [other] * (i % 100 == 1) + ["Share"] * (i % 60 == 2)
        docs.append((i, "\n".join(lines), "en", "hot", 1))
    docs += [(1000 + i, passage + "\n" + prose(rng, 20), "en", "else", 1) for i in range(4)]
    out = {r.doc_id: r.text for r in corpus_pipeline.drop_boilerplate_lines(spark, spark.createDataFrame(docs, DOCS), "").collect()}
    gone = {line for i, t, *_ in docs for line in t.split("\n") if line not in out[i].split("\n")}
    assert gone == {passage, other} and len(out) == len(docs)
    assert all(out[i] == t for i, t, *_ in docs if i >= 1000)
    assert all(passage not in t and other not in t for i, t in out.items() if i < 1000)


def test_line_stage_leaves_one_of_a_group_of_copies_to_the_next(spark):
    rng = random.Random(5)
    clean, near = prose(rng, 40) + "\n" + prose(rng, 30), [prose(rng, 100) for _ in range(3)]
    boiler = prose(rng, 10)
    docs = [(i, clean, "en", "small", 1) for i in range(5)] + [(i, prose(rng, 60) + "\n" + prose(rng, 30), "en", "small", 1) for i in range(5, 24)]
    docs += [(100 + i, "\n".join([*near, prose(rng, 2)]), "en", "near", 1) for i in range(40)] + [(200 + i, prose(rng, 60) + "\n" + boiler, "en", "near", 1) for i in range(8)]
    docs += [(300 + i, docs[-1][1], "en", "near", 1) for i in range(50)]
    lines = corpus_pipeline.written(corpus_pipeline.drop_boilerplate_lines(spark, spark.createDataFrame(docs, DOCS), ""), "copies")
    out = {r.doc_id: r.text for r in lines.collect()}
    assert len(out) == len(docs) and all(out[i] == t for i, t, *_ in docs if i < 200)
    assert not any(boiler in t for i, t in out.items() if i >= 200)
    kept = {r.doc_id: r.text for r in corpus_pipeline.keep_one_of_each_group(spark, lines, "").collect()}
    assert kept[0] == clean and not {1, 2, 3, 4} & set(kept) and set(range(5, 24)) <= set(kept)
    assert kept[100] == out[100] and set(kept) & set(range(101, 140)) == set() and set(kept) & set(range(300, 350)) == set()


def test_pipeline_rejects_what_the_toxicity_query_calls_toxic(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "some words", "en", "s", 10)], DOCS)
    for probability, left in ((0.29, 1), (0.3, 0), (0.4, 0)):
        monkeypatch.setattr(corpus_pipeline, "toxicity_classifier", lambda *_, p=probability: toxicity.Classifier(None, p))
        assert corpus_pipeline.drop_toxic(spark, docs, "").count() == left


def test_stages_with_nulls_repeats_clashing_names_and_nothing(spark, tmp_path):
    rng = random.Random(21)
    passage, copied = prose(rng, 30), prose(rng, 80)
    docs = [(i, prose(rng, 60), "en", "s", 1, "g", "h", 2.0) for i in range(40)]
    docs += [(None, prose(rng, 20) + " " + passage, None, None, None, None, None, None), (None, copied, "en", "s", 1, "g", "h", 1.0), (None, copied + " end", "en", "s", 1, "g", "h", 1.0)]
    docs += [(3, prose(rng, 50) + " " + passage, "en", "s", 1, "g", "h", 1.0), (5, None, "en", "s", None, "g", "h", 1.0), (5, "", "en", "s", 0, "g", "h", 1.0), (7, docs[7][1], "en", "s", 1, "x", "h", 1.0)]
    schema = DOCS + ", gone string, had string, toxicity double"
    sf = f"file://{tmp_path}"
    spark.createDataFrame(docs, schema).write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame([(i, 1, int(i % 5 == 0)) for i in range(40)], "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    spark.createDataFrame([(1, passage)], "item_id long, text string").write.parquet(f"{sf}/benchmark.parquet")
    table = spark.read.parquet(f"{sf}/documents.parquet")
    lines = corpus_pipeline.drop_boilerplate_lines(spark, table, sf)
    assert lines.columns == table.columns and lines.count() == len(docs)
    scored = corpus_pipeline.drop_toxic(spark, table, sf)
    assert scored.columns == table.columns
    joined = corpus_pipeline.keep_one_of_each_group(spark, table, sf)
    assert joined.columns == table.columns
    rows = [(r.doc_id, r.text) for r in joined.collect()]
    assert len(rows) == len(docs) - 2 and sum(t is not None and t.startswith(copied) for _, t in rows) == 1 and sum(i == 7 for i, _ in rows) == 1
    clean = corpus_pipeline.drop_contaminated(spark, table, sf)
    assert clean.columns == table.columns
    left = [(r.doc_id, r.text) for r in clean.collect()]
    assert len(left) == len(docs) - 2 and not any(t and passage in t for _, t in left) and (3, docs[3][1]) in left
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, table.limit(0), sf).count() == 0


def test_stages_begin_without_the_heap_of_the_stage_before(spark, tmp_path):
    def whole_collections():
        beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
        return sum(b.getCollectionCount() for b in beans if "Old" in b.getName() or "MarkSweep" in b.getName())

    docs = spark.createDataFrame([(1, "a b", "en", "s", 3)], "doc_id long, text string, lang string, source string, n_chars long")
    before = whole_collections()
    for _, stage in corpus_pipeline.STAGES[-1:]:
        assert stage(spark, docs, f"file://{tmp_path}").columns[0] == "doc_id"
    assert whole_collections() > before
