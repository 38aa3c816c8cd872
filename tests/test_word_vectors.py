"""Word vectors are trained in tasks, and their evaluation is whole."""

import numpy as np
from pyspark.sql import functions as F

from websieve.operators import evaluation


def _topics(spark, n=400):
    rng = np.random.default_rng(0)
    texts = [" ".join(f"{'abcd'[k % 4]}{i}x" for i in rng.integers(0, 12, 30)) for k in range(n)]
    return spark.createDataFrame([(t,) for t in texts], "text string").repartition(3)


def test_no_vector_comes_to_the_driver(spark, monkeypatch):
    from pyspark.ml.feature import Word2Vec

    monkeypatch.setattr(Word2Vec, "fit", lambda *_: (_ for _ in ()).throw(AssertionError("MLlib gathers all vectors on the driver")))
    docs = _topics(spark).unionByName(spark.createDataFrame([("once",), (None,), ("",)], "text string"))
    rows = evaluation.word_vectors(docs, 16, min_count=2, iterations=8, share_tokens=2500).collect()
    assert sorted(r.word for r in rows) == sorted(f"{t}{i}x" for t in "abcd" for i in range(12))
    v = np.array([r.vec for r in rows])
    assert v.shape == (48, 16) and np.isfinite(v).all()
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    near = v @ v.T
    np.fill_diagonal(near, -2)
    assert np.mean([rows[i].word[0] == rows[j].word[0] for i, j in enumerate(near.argmax(1))]) > 0.9


def test_a_word_that_fills_its_text_stays_finite(spark):
    docs = spark.createDataFrame([("la " * 20_000 + "di da " * 2000,), ("la di " * 9000,), ("da la " * 9000,)], "text string")
    rows = evaluation.word_vectors(docs, 20, min_count=2, iterations=3).collect()
    assert {r.word for r in rows} == {"la", "di", "da"} and np.abs(np.array([r.vec for r in rows])).max() < 100


def test_nearest_takes_the_smallest_word_of_equal_vectors_and_none_of_zeros(spark):
    vecs = {"a": [1.0, 0.0], "b": [1.0, 1.0], "c": [0.5, 0.25], "z": [0.0, 0.0], "y": [1.0, 2.5], "é": [2.0, 5.0], "w": [-1.0, 3.0]}
    vectors = spark.createDataFrame(list(vecs.items()), "word string, vec array<double>").repartition(3)
    asked = spark.createDataFrame([("a", "b", "c", "y", "k"), ("a", "b", "none", "y", "k")], "a string, b string, c string, d string, kind string")
    found = evaluation.analogy_nearest(vectors, asked).collect()
    assert [(r.c, r.word) for r in found] == [("c", "y")]
    scored = {r.kind: (r.n, r.correct) for r in evaluation.analogy_score(vectors, asked, oov="wrong").collect()}
    assert scored == {"k": (2, 1), "total": (2, 1)}
    assert evaluation.analogy_nearest(vectors, asked.where(F.lit(False))).count() == 0


def test_transfer_tells_texts_apart_without_mllib_vectors(spark, monkeypatch):
    from pyspark.ml.feature import Word2Vec

    monkeypatch.setattr(Word2Vec, "fit", lambda *_: (_ for _ in ()).throw(AssertionError("MLlib gathers all vectors on the driver")))
    docs = _topics(spark, 80).select(F.monotonically_increasing_id().alias("doc_id"), F.lit("en").alias("lang"), "text")
    dev = _topics(spark, 120).select(F.lit("en").alias("lang"), "text", F.substr("text", F.lit(1), F.lit(1)).isin("a", "b").cast("int").alias("label"))
    rows = {r.corpus: r.accuracy for r in evaluation.transfer({"target": docs, "crawl": docs.where("doc_id % 2 = 0")}, dev, 100_000, 10, 12).collect()}
    assert set(rows) == {"target", "crawl", "random"} and min(rows.values()) > 0.9
