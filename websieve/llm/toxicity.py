"""Toxicity by two class-conditional Kneser-Ney models over the letters of words.

The models of toxic and of ordinary texts have their own counts of letter 5-grams; when a 5-gram is rare
both back off to the same lower orders, which count in how many contexts a shorter n-gram occurs in the
texts of both classes. So an expression that neither class knows scores alike under both, and one that only
toxic texts use is known by its parts. Counts are kept for each distinct n-gram, so the model grows with their number. A word's score is the log-likelihood ratio; a text's features are the mean
ratio (log-likelihoods normalised by length), the largest one, and the mass of high ones. A logistic
regression over these turns them into a probability; it is fitted on labelled texts that the counts left out,
and then the counts are taken anew over all labelled texts.

Edge cases: null and empty texts have no words, all features 0, and get the score of such a text; rows
without label are not learned from; with fewer than two classes to learn from the score is the share of
toxic labels (0 without any); repeated rows and null ids come back as they are; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import Words, map_batches, slices, small_enough, written

ORDER = 5
TRIM = ".,;:!?|()[]{}\"'*#$%&-"
STEPS = [np.uint64(pow(0x9E3779B97F4A7C15, t, 1 << 64)) for t in range(1, ORDER + 1)]
MIX = np.uint64(0xD6E8FEB86659FD93)
N_FEATURES = 5
RATIO_WORDS = 16_384  # distinct words that are scored together


def letter_grams(words: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the n-grams that end at each letter and at each word's end: (order x position) for the
    n-grams, the same for their contexts, and the word of each position."""
    gap = "\0" * (ORDER - 1)
    joined = gap.join(["", *words.to_pylist(), ""])
    codes = np.frombuffer(joined.encode("utf-32-le", "replace"), "<u4").astype(np.uint64)
    here = np.flatnonzero((codes[1:] != 0) | (codes[:-1] != 0)) + 1
    begins = (codes[here - 1] == 0) & (codes[here] != 0)
    owner = np.cumsum(begins) - 1
    grams, contexts = np.zeros((ORDER, len(here)), np.uint64), np.zeros((ORDER, len(here)), np.uint64)
    total, before = np.zeros(len(here), np.uint64), np.zeros(len(here), np.uint64)
    for t in range(ORDER):
        if t:
            before = before + (codes[here - t] + np.uint64(1)) * STEPS[t - 1]
            contexts[t] = before * MIX
        total = total + (codes[here - t] + np.uint64(1)) * STEPS[t]
        grams[t] = (total ^ np.uint64(t + 1)) * MIX
    return grams, contexts, owner


@dataclass
class KneserNey:
    """Tables by n-gram: ``keys`` has the rising hashes of each order's n-grams and contexts, the others a value for each and a last
    one, 0, for those not met. ``own`` has for each class the counts of 5-grams, of their contexts and the number of kinds
    that follow a context; ``shared`` has for each lower order the same for context-type counts."""

    keys: dict[str, np.ndarray] = field(default_factory=dict)
    own: dict[str, np.ndarray] = field(default_factory=dict)
    shared: dict[str, np.ndarray] = field(default_factory=dict)
    discount: float = 0.75

    def places(self, name: str, hashes: np.ndarray) -> np.ndarray:
        keys = self.keys[name]
        at = np.searchsorted(keys, hashes)
        met = keys[np.minimum(at, len(keys) - 1)] == hashes if len(keys) else np.zeros(len(hashes), bool)
        return np.where(met, at, len(keys))

    def ratios(self, words: pa.Array) -> np.ndarray:
        """Log-likelihood ratio, toxic to ordinary, of each word."""
        out = np.zeros(len(words))
        grams, contexts, owner = letter_grams(words)
        if not len(owner):
            return out
        d = self.discount
        p = np.full(len(owner), 1.0 / 512)
        for k in range(1, ORDER):
            count, context = self.places(f"gram{k}", grams[k - 1]), self.places(f"context{k}", contexts[k - 1])
            total = np.maximum(self.shared[f"total{k}"][context], 1.0)
            kinds = self.shared[f"kinds{k}"][context]
            p = np.maximum(self.shared[f"count{k}"][count] - d, 0.0) / total + np.where(kinds > 0, d * kinds / total, 1.0) * p
        count, context = self.places(f"gram{ORDER}", grams[ORDER - 1]), self.places(f"context{ORDER}", contexts[ORDER - 1])
        logs = []
        for c in ("toxic", "ordinary"):
            total = np.maximum(self.own[f"total_{c}"][context], 1.0)
            kinds = self.own[f"kinds_{c}"][context]
            logs.append(np.log(np.maximum(self.own[f"count_{c}"][count] - d, 0.0) / total + np.where(kinds > 0, d * kinds / total, 1.0) * p))
        spoken = np.flatnonzero(pc.not_equal(pc.binary_length(words), 0).to_numpy(zero_copy_only=False))
        first = np.flatnonzero(np.diff(owner, prepend=-1))
        out[spoken] = np.add.reduceat(logs[0] - logs[1], first)
        return out


def normal_words(texts: pa.Array) -> tuple[Words, pa.Array, np.ndarray]:
    """The words of texts, their distinct normal forms, and for each distinct word the number of its form."""
    words = Words(texts, lines=True)
    forms = pc.utf8_trim(pc.utf8_lower(pc.utf8_trim_whitespace(pc.replace_substring(words.distinct, "\0", ""))), TRIM).dictionary_encode()
    return words, forms.dictionary, forms.indices.to_numpy(zero_copy_only=False)


def features(texts: pa.Array, model: KneserNey) -> np.ndarray:
    words, forms, form_of = normal_words(texts)
    # A part of the words at a time: their letters take many times their bytes.
    parts = [model.ratios(forms.slice(i, RATIO_WORDS)) for i in range(0, len(forms), RATIO_WORDS)]
    ratio = np.concatenate([np.zeros(0), *parts])[form_of]
    spoken = (pc.binary_length(forms).to_numpy(zero_copy_only=False) > 0)[form_of]
    n = words.sums(spoken.astype(np.int64))
    mean = words.sums(ratio) / np.maximum(n, 1)
    high = words.sums(np.maximum(ratio - 2.0, 0.0))
    largest = np.zeros(len(texts))
    some = np.flatnonzero(n)
    if len(some):
        largest[some] = np.maximum.reduceat(ratio[words.codes], words.bounds[:-1][some])
    return np.column_stack([np.clip(mean, -2, 2), np.clip(largest, -2, 20), np.log1p(high), np.log1p(n), np.log1p(high) - np.log1p(n / 100.0)])


@dataclass
class Classifier:
    language_models: KneserNey | None
    prior: float
    centre: np.ndarray = field(default_factory=lambda: np.zeros(N_FEATURES))
    scale: np.ndarray = field(default_factory=lambda: np.ones(N_FEATURES))
    weights: np.ndarray = field(default_factory=lambda: np.zeros(N_FEATURES + 1))

    def score(self, texts: pa.Array) -> np.ndarray:
        if self.language_models is None:
            return np.full(len(texts), self.prior)
        x = (features(texts, self.language_models) - self.centre) / self.scale
        return 1.0 / (1.0 + np.exp(-np.clip(x @ self.weights[1:] + self.weights[0], -30, 30)))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 30) -> np.ndarray:
    """Weights of a ridge-penalised logistic regression by Newton's method; the first is the constant."""
    x = np.column_stack([np.ones(len(x)), x])
    w, pull = np.zeros(x.shape[1]), np.diag([1e-6, *[ridge] * (x.shape[1] - 1)])
    for _ in range(rounds):
        p = 1.0 / (1.0 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + pull, x.T @ (p - y) + pull @ w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def count_grams(labelled: DataFrame) -> DataFrame:
    """One row for each distinct letter 5-gram of the texts (t) with its count by class (y)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, 0):
                words, forms, form_of = normal_words(part.column(0))
                toxic = np.repeat(part.column(1).to_numpy(zero_copy_only=False) == 1, np.diff(words.bounds))
                grams, contexts, owner = letter_grams(forms)
                spoken = np.flatnonzero(pc.binary_length(forms).to_numpy(zero_copy_only=False))
                _, at, kind = np.unique(grams[-1], return_index=True, return_inverse=True)
                n = []
                for mine in (toxic, ~toxic):
                    times = np.bincount(form_of[words.codes[mine]], minlength=len(forms))
                    n.append(np.bincount(kind, times[spoken][owner], len(at)).astype(np.int64))
                keys = [pa.array(a[k][at].view(np.int64)) for k in range(ORDER) for a in (grams, contexts)]
                yield pa.RecordBatch.from_arrays([*keys, pa.array(n[0]), pa.array(n[1])], [*GRAM_COLUMNS, "toxic", "ordinary"])

    schema = ", ".join(f"{c} long" for c in [*GRAM_COLUMNS, "toxic", "ordinary"])
    return map_batches(labelled.select("t", "y"), count, schema).groupBy(*GRAM_COLUMNS).agg(F.sum("toxic").alias("toxic"), F.sum("ordinary").alias("ordinary"))


GRAM_COLUMNS = [f"{kind}{k}" for k in range(1, ORDER + 1) for kind in ("gram", "context")]


def fit_language_models(labelled: DataFrame) -> KneserNey:
    """Both models from every labelled row. The driver gets sums by n-gram, one row for each distinct one."""
    kinds = written(count_grams(labelled), "letter-grams")
    keys: dict[str, np.ndarray] = {}

    def tables(df: DataFrame, key: str, values: dict[str, Column]) -> dict[str, np.ndarray]:
        got = df.groupBy(key).agg(*(c.alias(name) for name, c in values.items())).toArrow()
        hashes = got[key].to_numpy().astype(np.int64).view(np.uint64)
        rising = np.argsort(hashes)
        keys[key] = hashes[rising]
        return {name: np.append(got[name].to_numpy()[rising], 0).astype(np.float32) for name in values}

    own = tables(kinds, f"gram{ORDER}", {f"count_{c}": F.sum(c) for c in ("toxic", "ordinary")})
    sums = {f"total_{c}": F.sum(c) for c in ("toxic", "ordinary")} | {f"kinds_{c}": F.count_if(F.col(c) > 0) for c in ("toxic", "ordinary")}
    own |= tables(kinds, f"context{ORDER}", sums)
    shared: dict[str, np.ndarray] = {}
    for k in range(ORDER - 1, 0, -1):
        columns = GRAM_COLUMNS[: 2 * k]
        kinds = written(kinds.groupBy(*columns).agg(F.count(F.lit(1)).alias("n")), f"letter-grams-{k}")
        shared |= tables(kinds, f"gram{k}", {f"count{k}": F.sum("n")})
        shared |= tables(kinds, f"context{k}", {f"total{k}": F.sum("n"), f"kinds{k}": F.count(F.lit(1))})
    return KneserNey(keys, own, shared)


def fit(docs: DataFrame, labels: DataFrame, usable: Column, calibrating: Column, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", *, calibration_rows: int = 40_000, broadcast_rows: int = 5_000_000) -> Classifier:
    """Learn from the labelled rows of ``docs`` whose id fulfils ``usable``.

    Rows that also fulfil ``calibrating`` fit the logistic regression (at most ``calibration_rows`` of them,
    those whose ids have the smallest hashes) by models of all others. The models that score count every row, without a bound. ``usable`` and
    ``calibrating`` are conditions on the column named by ``id_col``. The labels (16 bytes a row) are
    broadcast when there are at most ``broadcast_rows`` of them, and joined by a shuffle beyond.
    """
    y = labels.where(usable & F.col(label_col).isNotNull()).groupBy(id_col).agg(F.max(F.col(label_col)).cast("int").alias("y"))
    side = F.broadcast(y) if small_enough(y, broadcast_rows) else y
    seen = {r.y: r["count"] for r in y.groupBy((F.col("y") == 1).cast("int").alias("y")).count().collect()}
    prior = seen.get(1, 0) / max(1, sum(seen.values()))
    if len(seen) < 2:
        return Classifier(None, prior)
    rows = docs.select(F.col(id_col), F.col(text_col).alias("t")).where(F.col("t").isNotNull()).join(side, id_col)
    models = fit_language_models(rows.where(~calibrating))
    sent = docs.sparkSession.sparkContext.broadcast(models)

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, 0):
                yield pa.RecordBatch.from_arrays([pa.array(list(features(part.column(0), sent.value)), pa.list_(pa.float64())), part.column(1)], ["x", "y"])

    chosen = y.where(calibrating).orderBy(F.xxhash64(id_col)).limit(calibration_rows)
    chosen = docs.select(F.col(id_col), F.col(text_col).alias("t")).where(F.col("t").isNotNull()).join(F.broadcast(chosen), id_col)
    got = map_batches(chosen.select("t", "y"), measure, "x array<double>, y int").toPandas()
    if got["y"].nunique() < 2:
        return Classifier(None, prior)
    x = np.vstack(got["x"].to_list())
    centre, scale = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-6)
    models = fit_language_models(rows)
    return Classifier(models, prior, centre, scale, logistic((x - centre) / scale, (got["y"].to_numpy() == 1).astype(float)))


def score(docs: DataFrame, classifier: Classifier, text_col: str = "text", *, out: str = "toxicity") -> DataFrame:
    """``docs`` with a column ``out``, the probability that the text is toxic."""
    sent = docs.sparkSession.sparkContext.broadcast(classifier)
    fields = [f for f in docs.schema if f.name != out]
    at = [f.name for f in fields].index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, at):
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(sent.value.score(part.column(at)))], [*part.schema.names, out])

    schema = StructType([*fields, StructField(out, DoubleType())])
    return map_batches(docs.select(*(f"`{f.name}`" for f in fields)), run, schema)
