"""Language identification from character n-grams: a flat count classifier, a tree of binary decisions in two forms, and
acceptance, splitting and checking of its answers."""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def char_ngrams(docs: DataFrame, n_min: int, n_max: int, id_col: str = "doc_id", text_col: str = "text", max_chars: int | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep, gram, n): counts of lower-cased character n-grams of each text; ``max_chars`` cuts texts for training on
    a budget."""
    rows = _gram_rows(docs, n_min, n_max, text_col, id_col, *keep, max_chars=max_chars)
    return rows.groupBy(id_col, *keep, "gram").agg(F.count(F.lit(1)).alias("n"))


def _gram_rows(docs: DataFrame, n_min: int, n_max: int, text_col: str, *keep: str | Column, max_chars: int | None = None) -> DataFrame:
    text = F.lower(F.col(text_col))
    text = F.substring(text, 1, max_chars) if max_chars else text
    # Characters as an array: places in a string are found by counting bytes from its start, in an array directly.
    rows = docs.select(*keep, F.filter(F.split(text, ""), lambda c: c != "").alias("__c"))

    def of(n: int) -> Column:
        last = F.size("__c") - n
        gram = lambda i: F.concat(*(F.get("__c", i + k) for k in range(n)))
        return F.when(last >= 0, F.transform(F.sequence(F.lit(0), F.greatest(last, F.lit(0))), gram)).otherwise(F.array().cast("array<string>"))

    names = [c for c in rows.columns if c != "__c"]
    return rows.select(*names, F.explode(F.concat(*(of(n) for n in range(n_min, n_max + 1)))).alias("gram"))


def gram_counts(train: DataFrame, n_min: int, n_max: int, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """(lang, gram, n) over all training texts; grams are added up within tasks before anything is shuffled."""
    rows = _gram_rows(train, n_min, n_max, text_col, F.col(lang_col).alias("lang"))
    return rows.groupBy("lang", "gram").agg(F.count(F.lit(1)).alias("n"))


# --- flat classifier -------------------------------------------------------------------------------------------


@dataclass
class FlatModel:
    """Smoothed log-probabilities of n-grams by language, as a table, and each language's value for unseen ones."""

    table: DataFrame  # gram, w: map<lang, log p>
    floors: DataFrame  # floors: map<lang, log p>
    n_min: int
    n_max: int


def fit_flat(train: DataFrame, n_min: int = 3, n_max: int = 3, alpha: float = 0.5, min_count: int = 1) -> FlatModel:
    counts = gram_counts(train, n_min, n_max).where(F.col("n") >= min_count)
    vocabulary = counts.agg(F.count_distinct("gram").alias("v"))
    totals = counts.groupBy("lang").agg(F.sum("n").alias("total")).crossJoin(vocabulary)  # one row
    bottom = F.log(alpha / (F.col("total") + alpha * F.col("v")))
    floors = totals.agg(F.map_from_entries(F.collect_list(F.struct("lang", bottom.alias("f")))).alias("floors"))
    weights = counts.join(F.broadcast(totals), "lang").select("gram", "lang", F.log((F.col("n") + alpha) / (F.col("total") + alpha * F.col("v"))).alias("lp"))
    table = weights.groupBy("gram").agg(F.map_from_entries(F.collect_list(F.struct("lang", "lp"))).alias("w"))
    return FlatModel(table, floors, n_min, n_max)


def score_flat(docs: DataFrame, model: FlatModel, id_col: str = "doc_id", text_col: str = "text", temperature: float = 1.0) -> DataFrame:
    """(id, lang, score): softmax over languages of the mean log-probability of a text's n-grams, divided by the temperature. Texts
    without an n-gram have no row. Weights of a checked size are broadcast and each text is scored where it is; larger ones are met by
    a join, with the same result."""
    weights = _weights(model)
    if weights is not None:
        return _score_in_place(docs, weights, model.n_min, model.n_max, id_col, text_col, temperature)
    grams = char_ngrams(docs, model.n_min, model.n_max, id_col, text_col)
    met = grams.join(model.table, "gram", "left").crossJoin(F.broadcast(model.floors))  # one row
    each = met.select(id_col, "n", F.explode("floors").alias("lang", "floor"), "w")
    value = F.coalesce(F.element_at("w", F.col("lang")), F.col("floor"))
    sums = each.groupBy(id_col, "lang").agg((F.sum(F.col("n") * value) / F.sum("n")).alias("ll"))
    top = F.max("ll").over(W.partitionBy(id_col))
    e = sums.select(id_col, "lang", F.exp((F.col("ll") - top) / temperature).alias("e"))
    return e.select(id_col, "lang", (F.col("e") / F.sum("e").over(W.partitionBy(id_col))).alias("score"))


@dataclass
class Weights:
    """Values of n-grams by language: sorted codes, a row of values each, and a last row for n-grams that are none of them."""

    languages: list[str]
    codes: np.ndarray
    values: np.ndarray

    def means(self, text: str, n_min: int, n_max: int) -> np.ndarray | None:
        """Mean value by language over the n-grams of a lower-cased text; None if it has none."""
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        codes = np.concatenate([_codes(points, n) for n in range(n_min, n_max + 1)])
        if not len(codes):
            return None
        codes, n = np.unique(codes, return_counts=True)
        at = np.minimum(np.searchsorted(self.codes, codes), max(len(self.codes) - 1, 0))
        at = np.where(self.codes[at] == codes, at, len(self.codes)) if len(self.codes) else np.zeros(len(codes), int)
        return n @ self.values[at] / n.sum()


def _codes(points: np.ndarray, n: int) -> np.ndarray:
    """One number for each n-gram of up to three characters: 21 bits a character, none of which is 0."""
    last = max(len(points) - n + 1, 0)
    out = np.zeros(last, np.int64)
    for k in range(n):
        out = (out << 21) | (points[k : k + last].astype(np.int64) + 1)
    return out


def _weights(model: FlatModel, most_bytes: int = 64 << 20) -> Weights | None:
    """The model as arrays, or None if n-grams are longer than a code holds or the arrays larger than ``most_bytes``."""
    if model.n_max > 3:
        return None
    floors = model.floors.first().floors or {}
    languages = sorted(floors)
    most = most_bytes // (8 * (len(languages) + 1))
    values = F.array(*(F.coalesce(F.element_at("w", F.lit(x)), F.lit(floors[x])) for x in languages)).alias("v")
    rows = model.table.select("gram", values).limit(most + 1).toPandas()
    if len(rows) > most or not languages:
        return None
    codes = np.array([_codes(np.frombuffer(g.encode("utf-32-le", "surrogatepass"), np.uint32), len(g))[0] for g in rows["gram"]], np.int64)
    order = np.argsort(codes)
    table = np.vstack([*rows["v"].iloc[order], [floors[x] for x in languages]])
    return Weights(languages, codes[order], table)


def _score_in_place(docs: DataFrame, weights: Weights, n_min: int, n_max: int, id_col: str, text_col: str, temperature: float) -> DataFrame:
    sent = docs.sparkSession.sparkContext.broadcast(weights)
    rows = docs.select(F.col(id_col).alias("id"), F.lower(F.col(text_col)).alias("text")).where("text IS NOT NULL")
    kind = rows.schema["id"].dataType.simpleString()

    def run(batches):
        w = sent.value
        for batch in batches:
            found = [w.means(t, n_min, n_max) for t in batch.column("text").to_pylist()]
            own = [i for i, m in enumerate(found) if m is not None]
            if not own:
                continue
            e = np.vstack([found[i] for i in own])
            e = np.exp((e - e.max(axis=1, keepdims=True)) / temperature)
            e /= e.sum(axis=1, keepdims=True)
            ids = batch.column("id").take(pa.array(np.repeat(own, len(w.languages))))
            yield pa.RecordBatch.from_arrays([ids, pa.array(w.languages * len(own), pa.string()), pa.array(e.ravel())], ["id", "lang", "score"])

    return rows.mapInArrow(run, f"id {kind}, lang string, score double").withColumnRenamed("id", id_col)


# --- tree ------------------------------------------------------------------------------------------------------


@dataclass
class Tree:
    """Frequency-coded binary tree over languages: for each inner node the languages under its two branches."""

    nodes: list[tuple[tuple[str, ...], tuple[str, ...]]] = field(default_factory=list)

    @property
    def languages(self) -> list[str]:
        return sorted(set().union(*(set(a) | set(b) for a, b in self.nodes))) if self.nodes else []

    def path(self, lang: str) -> list[tuple[int, bool]]:
        """(node, whether on its first branch) from any node that holds the language."""
        return [(i, lang in a) for i, (a, b) in enumerate(self.nodes) if lang in a or lang in b]


def huffman(sizes: dict[str, int]) -> Tree:
    """Repeatedly joins the two rarest groups; languages number in the hundreds, so this runs on the driver."""
    heap = [(n, (lang,)) for lang, n in sizes.items()]
    heapq.heapify(heap)
    tree = Tree()
    while len(heap) > 1:
        (n, a), (m, b) = heapq.heappop(heap), heapq.heappop(heap)
        tree.nodes.append((tuple(sorted(a)), tuple(sorted(b))))
        heapq.heappush(heap, (n + m, tuple(sorted(a + b))))
    return tree


@dataclass
class CountTree:
    tree: Tree
    table: DataFrame  # gram, d: array of the node's log-probability differences
    floors: list[float]
    n_min: int
    n_max: int


def fit_tree_counts(train: DataFrame, n_min: int = 3, n_max: int = 3, alpha: float = 0.5) -> CountTree:
    """Every node decides by smoothed counts of its two branches: the closed form of one pass over the training texts."""
    counts = gram_counts(train, n_min, n_max)
    sizes = {r.lang: r.n for r in train.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    tree = huffman(sizes)
    totals = {r.lang: r.n for r in counts.groupBy("lang").agg(F.sum("n").alias("n")).collect()}
    v = counts.agg(F.count_distinct("gram")).first()[0]
    wide = counts.groupBy("gram").agg(*(F.coalesce(F.sum(F.when(F.col("lang") == lang, F.col("n"))), F.lit(0)).alias(f"n_{i}") for i, lang in enumerate(sorted(sizes))))
    at = {lang: i for i, lang in enumerate(sorted(sizes))}
    columns, floors = [], []
    for a, b in tree.nodes:
        ta, tb = (sum(totals.get(x, 0) for x in side) + alpha * v for side in (a, b))
        na, nb = (sum((F.col(f"n_{at[x]}") for x in side), F.lit(0)) for side in (a, b))
        columns.append(F.log((na + alpha) / ta) - F.log((nb + alpha) / tb))
        floors.append(math.log(alpha / ta) - math.log(alpha / tb))
    return CountTree(tree, wide.select("gram", F.array(*columns).alias("d")), floors, n_min, n_max)


def score_tree_counts(docs: DataFrame, model: CountTree, id_col: str = "doc_id", text_col: str = "text", sharpness: float = 4.0) -> DataFrame:
    """(id, lang, score): products of node probabilities along each language's path; they add up to 1."""
    grams = char_ngrams(docs, model.n_min, model.n_max, id_col, text_col).join(model.table, "gram", "left")
    means = [F.sum(F.col("n") * F.coalesce(F.col("d")[i], F.lit(f))) / F.sum("n") for i, f in enumerate(model.floors)]
    sums = grams.groupBy(id_col).agg(*(m.alias(f"d_{i}") for i, m in enumerate(means)))
    return _leaves(sums, model.tree, lambda i: 1 / (1 + F.exp(-F.lit(sharpness) * F.col(f"d_{i}"))), id_col)


def _leaves(sums: DataFrame, tree: Tree, node_probability, id_col: str) -> DataFrame:
    leaves = []
    for lang in tree.languages:
        p = F.lit(1.0)
        for i, first in tree.path(lang):
            p = p * (node_probability(i) if first else 1 - node_probability(i))
        leaves.append(F.struct(F.lit(lang).alias("lang"), p.alias("score")))
    return sums.select(id_col, F.explode(F.array(*leaves)).alias("x")).select(id_col, "x.lang", "x.score")


@dataclass
class LogisticTree:
    tree: Tree
    models: list
    features: object
    text_col: str


def fit_tree_logistic(train: DataFrame, n_min: int = 2, n_max: int = 3, buckets: int = 1 << 14, epochs: int = 20, text_col: str = "text") -> LogisticTree:
    """Every node is a logistic regression over hashed n-grams scaled to unit sum (their average)."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, Normalizer, SQLTransformer

    parts = lambda n: ", ".join(f"get(__c, i + {k})" for k in range(n))
    grams = ", ".join(f"CASE WHEN size(__c) >= {n} THEN transform(sequence(0, size(__c) - {n}), i -> concat({parts(n)})) ELSE array() END" for n in range(n_min, n_max + 1))
    chars = f"SELECT *, filter(split(lower({text_col}), ''), c -> c <> '') AS __c FROM __THIS__"
    features = Pipeline(stages=[SQLTransformer(statement=chars), SQLTransformer(statement=f"SELECT *, concat({grams}) AS __grams FROM __THIS__"), HashingTF(numFeatures=buckets, inputCol="__grams", outputCol="__tf"), Normalizer(p=1.0, inputCol="__tf", outputCol="__x")]).fit(train)
    sizes = {r.lang: r.n for r in train.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    tree = huffman(sizes)
    rows = features.transform(train).select("lang", "__x").persist()
    models = []
    for a, b in tree.nodes:
        own = rows.where(F.col("lang").isin(*a, *b)).select("__x", F.col("lang").isin(*a).cast("double").alias("y"))
        models.append(LogisticRegression(featuresCol="__x", labelCol="y", maxIter=epochs, regParam=1e-6, standardization=False).fit(own))
    rows.unpersist()
    return LogisticTree(tree, models, features, text_col)


def score_tree_logistic(docs: DataFrame, model: LogisticTree, id_col: str = "doc_id") -> DataFrame:
    from pyspark.ml.functions import vector_to_array

    rows = model.features.transform(docs)
    for i, m in enumerate(model.models):
        m = m.copy()
        m.setFeaturesCol("__x").setPredictionCol(f"__p{i}").setRawPredictionCol(f"__r{i}").setProbabilityCol(f"__q{i}")
        rows = m.transform(rows)
    sums = rows.select(id_col, *(vector_to_array(f"__q{i}")[1].alias(f"d_{i}") for i in range(len(model.models))))
    return _leaves(sums, model.tree, lambda i: F.col(f"d_{i}"), id_col)


# --- answers ---------------------------------------------------------------------------------------------------


def score_map(scores: DataFrame, id_col: str = "doc_id") -> DataFrame:
    return scores.groupBy(id_col).agg(F.map_from_entries(F.collect_list(F.struct("lang", "score"))).alias("scores"))


def best(scores: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, lang, score) of the highest score; equal scores go to the language first in the alphabet."""
    top = scores.groupBy(id_col).agg(F.min(F.struct((-F.col("score")).alias("s"), "lang")).alias("t"))
    return top.select(id_col, "t.lang", (-F.col("t.s")).alias("score"))


def accept(top: DataFrame, threshold: float = 0.5) -> DataFrame:
    """Documents whose best score is above the threshold, strictly."""
    return top.where(F.col("score") > threshold)


def split(docs: DataFrame, path: str) -> None:
    docs.write.mode("overwrite").partitionBy("lang").parquet(path)


def by_paragraph(scored: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, lang, share): the language of most characters, from (id, lang, n_chars) of paragraphs."""
    sums = scored.groupBy(id_col, "lang").agg(F.sum("n_chars").alias("c"))
    top = sums.groupBy(id_col).agg(F.min(F.struct((-F.col("c")).alias("m"), "lang")).alias("t"), F.sum("c").alias("all"))
    return top.select(id_col, "t.lang", (-F.col("t.m") / F.col("all")).alias("share"))
