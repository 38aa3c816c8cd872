"""Extrinsic evaluations: word vectors by bucket with analogies, and a learner on two corpora."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.pages import free_shuffles, materialize
from .lm import words
from .output import cap_corpus


WINDOW, BLOCK, NEGATIVES, RATE, STEP = 5, 64, 20, 0.025, np.float32(0.5)


def _start(words: list[str], dim: int, seed: int) -> np.ndarray:
    """A word's first vector, which depends on nothing but the word and the seed: every share of a corpus starts from the same ones."""
    import xxhash

    h = np.array([xxhash.xxh3_64_intdigest(w.encode(), seed) for w in words], np.uint64)
    out = np.empty((len(words), dim), np.float32)
    steps = np.arange(1, dim + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for i in range(0, len(words), 4096):
        x = h[i : i + 4096, None] + steps
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        out[i : i + 4096] = ((x >> np.uint64(40)).astype(np.float32) / (1 << 24) - 0.5) / dim
    return out


def _add(table: np.ndarray, rows: np.ndarray, what: np.ndarray) -> None:
    """Adds to rows of a table, also where a row is named more than once; a row moves by ``STEP`` at most, else a word that fills a block would grow without end."""
    some, at = np.unique(rows, return_inverse=True)
    step = (np.arange(len(some))[:, None] == at).astype(np.float32) @ what
    long = np.sqrt(np.einsum("ij,ij->i", step, step))
    table[some] += step * (STEP / np.maximum(long, STEP))[:, None]


def _skip_gram(ids: np.ndarray, sentence: np.ndarray, counts: np.ndarray, vectors: np.ndarray, iterations: int, seed: int) -> None:
    """Trains ``vectors`` in place by skip-gram with negative samples on tokens ``ids``; a window stays in its sentence. A block of tokens meets its windows as one
    product of matrices, and shares its negative samples, which weigh as five a pair."""
    rng = np.random.default_rng(seed)
    context = np.zeros_like(vectors)
    cumulative = np.cumsum(counts**0.75)
    steps, done = iterations * max(1, -(-len(ids) // BLOCK)), 0
    for _ in range(iterations):
        for low in range(0, len(ids), BLOCK):
            rate = RATE * max(1e-4, 1 - done / steps)
            done += 1
            at = np.arange(low, min(low + BLOCK, len(ids)))
            near = np.arange(max(0, low - WINDOW), min(at[-1] + 1 + WINDOW, len(ids)))
            far = np.abs(at[:, None] - near)
            met = (far > 0) & (far <= rng.integers(1, WINDOW + 1, len(at))[:, None]) & (sentence[at][:, None] == sentence[near])
            drawn = np.minimum(np.searchsorted(cumulative, rng.random(NEGATIVES) * cumulative[-1], side="right"), len(counts) - 1)
            named = np.concatenate([ids[near], drawn])
            own, other = vectors[ids[at]], context[named]
            guess = 1 / (1 + np.exp(-np.clip(own @ other.T, -30, 30)))
            weight = met.sum(1, keepdims=True, dtype=np.float32) * np.float32(5 / NEGATIVES)
            gap = np.concatenate([met * (1 - guess[:, : len(near)]), -weight * (drawn != ids[at][:, None]) * guess[:, len(near) :]], axis=1).astype(np.float32) * np.float32(rate)
            _add(vectors, ids[at], gap @ other)
            _add(context, named, gap.T @ own)


def _trained(rows: DataFrame, dim: int, min_count: int, iterations: int, seed: int, share_tokens: int) -> DataFrame:
    """(word, vec): vectors of each share of ``rows`` (share, toks), meaned by word. A share's task gets the share's own words before its texts, so what it holds is bounded
    by the tokens of a share; the driver holds none of it."""
    import pyarrow as pa
    import pyarrow.compute as pc

    total = rows.agg(F.sum(F.size("toks"))).first()[0] or 0
    shares = max(4, -(-total // share_tokens))
    rows = rows.withColumn("share", F.pmod(F.xxhash64("row"), F.lit(shares)).cast("int"))
    counts = rows.select("share", F.explode("toks").alias("word")).groupBy("share", "word").agg(F.count(F.lit(1)).alias("n"))
    counts = materialize(counts, "share-words")
    often = counts.groupBy("word").agg(F.sum("n").alias("all")).where(F.col("all") >= min_count).select("word")
    words_of = counts.join(often, "word", "left_semi").select("share", F.lit(0).alias("kind"), F.xxhash64("word").alias("nth"), "word", "n", F.lit(None).cast("array<string>").alias("toks"))
    texts = rows.select("share", F.lit(1).alias("kind"), F.xxhash64("toks").alias("nth"), F.lit(None).cast("string").alias("word"), F.lit(None).cast("long").alias("n"), "toks")

    def run(batches):
        share, names, counted, lists, sizes = None, [], [], [], []

        def ended():
            if not names:
                return
            known, count = pa.concat_arrays(names), np.concatenate(counted)
            vectors = _start(known.to_pylist(), dim, seed)
            if lists:
                lengths = np.concatenate(sizes)
                _skip_gram(np.concatenate(lists), np.repeat(np.arange(len(lengths)), lengths), count, vectors, iterations, seed + share)
            for i in range(0, len(known), 2000):
                part = vectors[i : i + 2000]
                yield pa.RecordBatch.from_arrays([known[i : i + 2000], pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1) * dim, pa.int32()), pa.array(part.ravel()))], ["word", "vec"])

        for batch in batches:
            for one in sorted(set(batch.column("share").to_pylist())):
                if one != share:
                    yield from ended()
                    share, names, counted, lists, sizes = one, [], [], [], []
                mine = batch.filter(pc.equal(batch.column("share"), one))
                met = mine.filter(pc.equal(mine.column("kind"), 0))
                if len(met):
                    names.append(met.column("word"))
                    counted.append(met.column("n").to_numpy().astype(float))
                toks = mine.filter(pc.equal(mine.column("kind"), 1)).column("toks")
                if len(toks) and names:
                    names = [pa.concat_arrays(names)]
                    place = pc.fill_null(pc.index_in(toks.flatten(), names[0]), -1).to_numpy().astype(np.int64)
                    row = np.repeat(np.arange(len(toks)), toks.value_lengths().to_numpy())[place >= 0]
                    lists.append(place[place >= 0])
                    sizes.append(np.bincount(row, minlength=len(toks)))
        yield from ended()

    def mean(batches):
        """Of rows in order of words."""
        held = None
        for batch in batches:
            if not len(batch):
                continue
            names, values = batch.column("word").to_pylist(), batch.column("vec").flatten().to_numpy().reshape(-1, dim).astype(float)
            firsts = np.array([i for i, x in enumerate(names) if i == 0 or x != names[i - 1]])
            found = [names[i] for i in firsts]
            sums, n = np.add.reduceat(values, firsts, axis=0), np.diff(firsts, append=len(names))
            if held and held[0] == found[0]:
                sums[0], n[0] = sums[0] + held[1], n[0] + held[2]
            elif held:
                yield rows_of([held[0]], held[1][None] / held[2])
            yield rows_of(found[:-1], sums[:-1] / n[:-1, None])
            held = found[-1], sums[-1], n[-1]
        if held:
            yield rows_of([held[0]], held[1][None] / held[2])

    def rows_of(names, values):
        return pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.ListArray.from_arrays(pa.array(np.arange(len(names) + 1) * dim, pa.int32()), pa.array(values.ravel()))], ["word", "vec"])

    dealt = words_of.unionByName(texts).repartitionById(shares, "share").sortWithinPartitions("share", "kind", "nth")
    parts = dealt.mapInArrow(run, "word string, vec array<float>")
    return parts.repartition("word").sortWithinPartitions("word").mapInArrow(mean, "word string, vec array<double>")


def word_vectors(corpus: DataFrame, dim: int = 300, *, min_count: int = 5, iterations: int = 1, subword: bool = False, seed: int = 7, share_tokens: int = 2_000_000) -> DataFrame:
    """(word, vec) by skip-gram, for words that occur ``min_count`` times; with ``subword`` the mean of the vectors of words that share a letter trigram is
    added, so that rare forms lean on common ones. Shares of the corpus of about ``share_tokens`` tokens, four at least, are trained side by side from the same
    first vectors and meaned by word."""
    rows = materialize(corpus.select(F.monotonically_increasing_id().alias("row"), words(F.col("text")).alias("toks")).where(F.size("toks") > 0), "share-texts")
    vectors = _trained(rows, dim, min_count, iterations, seed, share_tokens)
    if not subword:
        return vectors
    grams = vectors.select("word", "vec", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length("word") - 2, F.lit(1))), lambda i: F.substr("word", i, F.lit(3))))).alias("g"))
    dims = [F.avg(F.col("vec")[i]).alias(f"m{i}") for i in range(dim)]
    means = grams.groupBy("g").agg(*dims)
    own = grams.select("word", "g").join(means, "g").groupBy("word").agg(F.array(*(F.avg(f"m{i}") for i in range(dim))).alias("part"))
    return vectors.join(own, "word").select("word", F.zip_with("vec", "part", lambda a, b: a + b).alias("vec"))


def random_vectors(vectors: DataFrame, dim: int, seed: int = 1) -> DataFrame:
    """The floor: a random vector for each word."""
    unit = [((F.xxhash64("word", F.lit(seed), F.lit(i)) % 10_000) / 10_000.0) for i in range(dim)]
    return vectors.select("word", F.array(*unit).alias("vec"))


def _in_order(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Inner products of rows of x with rows of y, summed in the order of dimensions as SQL does."""
    out = np.zeros((len(x), len(y)))
    for i in range(x.shape[1]):
        out += x[:, i, None] * y[:, i]
    return out


def _squares(x: np.ndarray) -> np.ndarray:
    out = np.zeros(len(x))
    for i in range(x.shape[1]):
        out += x[:, i] * x[:, i]
    return out


def analogy_nearest(vectors: DataFrame, questions: DataFrame) -> DataFrame:
    """``questions`` (a, b, c, ...) with the word whose vector is nearest to b - a + c by cosine, none of the three. Questions are
    few and broadcast to the blocks of the vocabulary; each block reduces to its best word for each question. A vector of zeros is near to nothing."""
    import pyarrow as pa

    of = lambda name: vectors.select(F.col("word").alias(name), F.col("vec").alias(f"v_{name}"))
    full = questions.join(of("a"), "a").join(of("b"), "b").join(of("c"), "c")
    add = F.zip_with(F.zip_with("v_b", "v_a", lambda x, y: x - y), "v_c", lambda x, y: x + y)
    asked = full.select(*questions.columns, add.alias("t")).collect()
    spark = vectors.sparkSession
    if not asked:
        return questions.limit(0).withColumn("word", F.lit(None).cast("string"))
    wanted, taken = np.array([r.t for r in asked], float), [{r.a, r.b, r.c} for r in asked]
    sent = spark.sparkContext.broadcast((wanted, _squares(wanted), taken))

    def run(batches):
        targets, squares, taken = sent.value
        for batch in batches:
            names = batch.column("word").to_pylist()
            x = batch.column("vec").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(names), -1)
            with np.errstate(invalid="ignore", divide="ignore"):
                far = -(_in_order(x, targets) / np.sqrt(_squares(x)[:, None] * squares))
            place = {w: i for i, w in enumerate(names)} if len(set(names)) == len(names) else None
            for k, words in enumerate(taken):
                for i in [place[w] for w in words if w in place] if place is not None else [i for i, w in enumerate(names) if w in words]:
                    far[i, k] = np.nan
            far = np.where(np.isnan(far), np.inf, far)
            least = far.min(axis=0, initial=np.inf)
            some = np.flatnonzero(np.isfinite(least))
            best = [min((names[i] for i in np.flatnonzero(far[:, k] == least[k])), key=str.encode) for k in some]
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(least[some]), pa.array(best, pa.string())], ["nth", "s", "word"])

    blocks = vectors.where(F.size("vec") == wanted.shape[1]).select("word", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "nth long, s double, word string")
    best = blocks.groupBy("nth").agg(F.min(F.struct("s", "word")).alias("m"))
    kept = spark.createDataFrame([(i, *r[:-1]) for i, r in enumerate(asked)], T.StructType([T.StructField("nth", T.LongType()), *questions.schema.fields]))
    return kept.join(best, "nth").select(*questions.columns, "m.word")


def analogy_score(vectors: DataFrame, questions: DataFrame, oov: str = "skip") -> DataFrame:
    """(kind, n, correct, accuracy) of questions (a, b, c, d, kind), each kind and "total" over all questions."""
    known = analogy_nearest(vectors, questions)
    rows = questions.join(known, questions.columns, "inner" if oov == "skip" else "left").select("kind", F.coalesce((F.col("word") == F.col("d")).cast("int"), F.lit(0)).alias("ok"))
    each = rows.groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.sum("ok").alias("correct"))
    total = rows.agg(F.lit("total").alias("kind"), F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("ok"), F.lit(0)).alias("correct"))
    return each.unionByName(total).withColumn("accuracy", F.col("correct") / F.col("n"))


def stem_pairs(docs: DataFrame) -> DataFrame:
    """(stem, word, suffix): words that are another word of at least three letters with a suffix of one to four. A word meets its own
    possible stems by an equi-join."""
    vocabulary = docs.select(F.explode(words(F.col("text"))).alias("w")).distinct()
    cuts = vocabulary.select("w", F.explode(F.sequence(F.lit(1), F.lit(4))).alias("n")).where(F.length("w") - F.col("n") >= 3)
    cuts = cuts.select("w", F.expr("substr(w, 1, length(w) - n)").alias("stem"), F.expr("substr(w, length(w) - n + 1)").alias("suffix"))
    return cuts.join(vocabulary.withColumnRenamed("w", "stem"), "stem", "left_semi").select("stem", F.col("w").alias("word"), "suffix")


def suffix_pairs(docs: DataFrame, k: int) -> DataFrame:
    """(suffix, stems): the k suffixes that most stems take."""
    return stem_pairs(docs).groupBy("suffix").agg(F.count(F.lit(1)).alias("stems")).orderBy(F.desc("stems"), "suffix").limit(k)


def make_questions(docs: DataFrame, n: int = 50) -> DataFrame:
    """(a, b, c, d, kind): syntactic questions from stems that share a suffix; semantic ones from neighbours in text."""
    pairs = stem_pairs(docs)
    nth = F.row_number().over(W.partitionBy("suffix").orderBy(F.xxhash64("word")))
    numbered = pairs.withColumn("nth", nth).where(F.col("nth") <= 2 * n)
    left, right = numbered.where("nth % 2 = 1"), numbered.where("nth % 2 = 0")
    right = right.select("suffix", F.col("stem").alias("c"), F.col("word").alias("d"), (F.col("nth") - 1).alias("nth"))
    syntactic = left.select("suffix", F.col("stem").alias("a"), F.col("word").alias("b"), "nth").join(right, ["suffix", "nth"]).select("a", "b", "c", "d", F.lit("syntactic").alias("kind"))
    t = docs.select(words(F.col("text")).alias("t"))
    two = t.select(F.explode(F.arrays_zip(F.slice("t", 1, 1_000_000), F.slice("t", 2, 1_000_000))).alias("p")).select(F.col("p.0").alias("x"), F.col("p.1").alias("y")).where("y IS NOT NULL AND x <> y")
    top = two.groupBy("x", "y").agg(F.count(F.lit(1)).alias("m")).orderBy(F.desc("m"), "x", "y").limit(2 * n).withColumn("nth", F.row_number().over(W.orderBy(F.desc("m"), "x", "y")))
    one, other = top.where("nth % 2 = 1"), top.where("nth % 2 = 0").select(F.col("x").alias("c"), F.col("y").alias("d"), (F.col("nth") - 1).alias("nth"))
    semantic = one.select(F.col("x").alias("a"), F.col("y").alias("b"), "nth").join(other, "nth").select("a", "b", "c", "d", F.lit("semantic").alias("kind"))
    return syntactic.orderBy(F.xxhash64("a", "b")).limit(n).unionByName(semantic)


def bucket_table(docs: DataFrame, dim: int = 300, n_questions: int = 30) -> DataFrame:
    """(bucket, total, semantic, syntactic): accuracies of vectors trained on each bucket of ``docs`` (text, bucket)."""
    questions = make_questions(docs, n_questions).persist()
    out = None
    for name in ("head", "middle", "tail"):
        vectors = word_vectors(docs.where(F.col("bucket") == name), dim, min_count=2).persist()
        one = materialize(analogy_score(vectors, questions, oov="wrong").select(F.lit(name).alias("bucket"), "kind", "accuracy"), "analogies")
        vectors.unpersist()
        del vectors
        free_shuffles(docs.sparkSession)  # else those of all buckets lie on disk together
        out = one if out is None else out.unionByName(one)
    return out.groupBy("bucket").pivot("kind", ["total", "semantic", "syntactic"]).agg(F.first("accuracy"))


def transfer(corpora: dict[str, DataFrame], dev: DataFrame, cap_bytes: int, steps: int, dim: int = 100) -> DataFrame:
    """(corpus, accuracy): the same learner, with the same number of steps, on vectors from each capped corpus and on random ones.
    ``dev`` has lang, text and label (0 or 1); half of it, by hash, trains the learner and half tests it."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    spark = dev.sparkSession
    rows = dev.withColumn("id", F.xxhash64("text")).select("id", "label", F.explode(words(F.col("text"))).alias("word"))
    results = []
    sources: list[tuple[str, DataFrame]] = []
    for name, corpus in corpora.items():
        budget = corpus.select("lang").distinct().withColumn("budget", F.lit(cap_bytes))
        sources.append((name, word_vectors(cap_corpus(corpus, ["lang"], ["doc_id"], budget), dim, min_count=2).persist()))
    sources.append(("random", random_vectors(sources[0][1], dim)))
    for name, vectors in sources:
        # Sums and one count: an average keeps a count for each dimension, which doubles what is shuffled.
        sums = rows.join(vectors, "word").groupBy("id", "label").agg(F.count(F.lit(1)).alias("n"), *(F.sum(F.col("vec")[i]).alias(f"s{i}") for i in range(dim)))
        mean = sums.select("id", "label", F.array(*(F.col(f"s{i}") / F.col("n") for i in range(dim))).alias("v"))
        x = mean.select("id", F.col("label").cast("double").alias("label"), array_to_vector("v").alias("features")).persist()
        model = LogisticRegression(maxIter=steps).fit(x.where("id % 2 = 0"))
        right = model.transform(x.where("id % 2 <> 0")).select(F.avg((F.col("prediction") == F.col("label")).cast("double"))).first()[0]
        results.append((name, right))
        x.unpersist()
        del sums, mean, x, model
        free_shuffles(spark)
    for _, vectors in sources:
        vectors.unpersist()
    return spark.createDataFrame(results, "corpus string, accuracy double")
