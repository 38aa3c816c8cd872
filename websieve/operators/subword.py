"""Subword tokenizers trained on a table of distinct words with counts: pair merging, and a unigram model by EM.

Both loops run on the word table, whose size follows the vocabulary and not the corpus. Symbols of a word are kept in one
string, each between marks, so that merging a pair is a literal replacement.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.pages import materialize
from .lm import words

OPEN, CLOSE = "\u0001", "\u0002"


def word_table(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """(lang, word, cnt)."""
    return docs.select("lang", F.explode(words(F.col(text_col))).alias("word")).groupBy("lang", "word").agg(F.count(F.lit(1)).alias("cnt"))


def spelled(table: DataFrame) -> DataFrame:
    """(word, cnt, s): words as marked symbols, one for each character."""
    letters = F.transform(F.filter(F.split("word", ""), lambda c: c != ""), lambda c: F.concat(F.lit(OPEN), c, F.lit(CLOSE)))
    return table.select("word", "cnt", F.array_join(letters, "").alias("s"))


def pair_counts(symbols: DataFrame) -> DataFrame:
    """(a, b, cnt) of neighbouring symbols, weighted by the counts of their words."""
    parts = F.transform(F.filter(F.split("s", CLOSE), lambda x: x != ""), lambda x: F.substr(x, F.lit(2)))
    rows = symbols.select("cnt", parts.alias("p")).where(F.size("p") > 1)
    pairs = rows.select("cnt", F.explode(F.transform(F.sequence(F.lit(0), F.size("p") - 2), lambda i: F.struct(F.get("p", i).alias("a"), F.get("p", i + 1).alias("b")))).alias("x"))
    return pairs.groupBy("x.a", "x.b").agg(F.sum("cnt").alias("cnt"))


@dataclass
class Merges:
    """Ordered merges of one language."""

    pairs: list[tuple[str, str]]

    def encode(self, word: str) -> list[str]:
        rank = {p: i for i, p in enumerate(self.pairs)}
        symbols = list(word)
        while len(symbols) > 1:
            best = min(zip(symbols, symbols[1:]), key=lambda p: rank.get(p, math.inf))
            if best not in rank:
                break
            out, i = [], 0
            while i < len(symbols):
                if i + 1 < len(symbols) and (symbols[i], symbols[i + 1]) == best:
                    out.append(symbols[i] + symbols[i + 1])
                    i += 2
                else:
                    out.append(symbols[i])
                    i += 1
            symbols = out
        return symbols


def fit_merges(table: DataFrame, merges: int, each_round: int = 1) -> Merges:
    """The most frequent pair is joined, ``merges`` times; ``each_round`` joins that many pairs without a symbol in common before
    pairs are counted again. Ties go to the pair first in the alphabet."""
    symbols, chosen = materialize(spelled(table), "symbols"), []
    while len(chosen) < merges:
        top = pair_counts(symbols).orderBy(F.desc("cnt"), "a", "b").limit(4 * each_round).collect()
        used: set[str] = set()
        batch = []
        for r in top:
            if len(batch) < min(each_round, merges - len(chosen)) and not {r.a, r.b} & used:
                batch.append((r.a, r.b))
                used |= {r.a, r.b}
        if not batch:
            break
        s = F.col("s")
        for a, b in batch:
            s = F.replace(s, F.lit(f"{OPEN}{a}{CLOSE}{OPEN}{b}{CLOSE}"), F.lit(f"{OPEN}{a}{b}{CLOSE}"))
        symbols = materialize(symbols.withColumn("s", s), "symbols")
        chosen += batch
    return Merges(chosen)


@dataclass
class Unigram:
    """Log-probabilities of pieces of one language."""

    pieces: dict[str, float]
    longest: int

    def encode(self, word: str) -> list[str]:
        """The likeliest segmentation; characters that are no piece stand alone at a low probability."""
        low = min(self.pieces.values(), default=0.0) - 10.0
        best, back = [0.0] + [-math.inf] * len(word), [0] * (len(word) + 1)
        for end in range(1, len(word) + 1):
            for begin in range(max(0, end - self.longest), end):
                p = self.pieces.get(word[begin:end], low if end - begin == 1 else None)
                if p is not None and best[begin] + p > best[end]:
                    best[end], back[end] = best[begin] + p, begin
        out, end = [], len(word)
        while end:
            out.append(word[back[end] : end])
            end = back[end]
        return out[::-1]

    def expected(self, word: str) -> tuple[dict[str, float], float]:
        """Expected uses of each piece over all segmentations, and the word's log-likelihood."""
        n = len(word)
        low = min(self.pieces.values(), default=0.0) - 10.0
        edges = [(b, e, p) for e in range(1, n + 1) for b in range(max(0, e - self.longest), e) for p in [self.pieces.get(word[b:e], low if e - b == 1 else None)] if p is not None]
        ahead, behind = [0.0] + [-math.inf] * n, [-math.inf] * n + [0.0]
        for b, e, p in edges:
            ahead[e] = _log_add(ahead[e], ahead[b] + p)
        for b, e, p in sorted(edges, key=lambda x: -x[0]):
            behind[b] = _log_add(behind[b], behind[e] + p)
        uses: dict[str, float] = {}
        for b, e, p in edges:
            uses[word[b:e]] = uses.get(word[b:e], 0.0) + math.exp(ahead[b] + p + behind[e] - ahead[n])
        return uses, ahead[n]


def _log_add(a: float, b: float) -> float:
    high, low = max(a, b), min(a, b)
    return high if low == -math.inf else high + math.log1p(math.exp(low - high))


def seed_pieces(table: DataFrame, most: int, longest: int = 6) -> dict[str, float]:
    """Frequent substrings of words, scored by count times length; all single characters stay."""
    cuts = [F.transform(F.sequence(F.lit(1), F.greatest(F.length("word") - n + 1, F.lit(1))), lambda i, n=n: F.substr("word", i, F.lit(n))) for n in range(1, longest + 1)]
    rows = table.select("cnt", F.explode(F.concat(*cuts)).alias("piece")).groupBy("piece").agg(F.sum("cnt").alias("n"))
    rows = rows.withColumn("single", F.length("piece") == 1).orderBy(F.desc("single"), F.desc(F.col("n") * F.length("piece")), "piece").limit(most)
    found = {r.piece: float(r.n) for r in rows.collect()}
    total = sum(found.values())
    return {p: math.log(n / total) for p, n in found.items()}


def fit_unigram(table: DataFrame, vocabulary: int, seed_factor: int = 4, prune: float = 0.75, em_rounds: int = 2) -> tuple[Unigram, list[float]]:
    """The model, and the log-likelihood of the words in each round; rounds of EM alternate with dropping the pieces of least
    expected use until ``vocabulary`` are left. Pieces (a bounded number) are the only thing that returns to the driver."""
    pieces, history = seed_pieces(table, vocabulary * seed_factor), []
    while True:
        for _ in range(em_rounds):
            model = Unigram(pieces, max(map(len, pieces)))
            sent = table.sparkSession.sparkContext.broadcast(model)

            def expect(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
                uses: dict[str, float] = {}
                likelihood = 0.0
                for batch in batches:
                    for word, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                        own, ll = sent.value.expected(word)
                        likelihood += n * ll
                        for piece, x in own.items():
                            uses[piece] = uses.get(piece, 0.0) + n * x
                yield pa.RecordBatch.from_arrays([pa.array([*uses, ""]), pa.array([*uses.values(), likelihood])], ["piece", "x"])

            rows = table.select("word", "cnt").mapInArrow(expect, "piece string, x double").groupBy("piece").agg(F.sum("x").alias("x")).collect()
            sums = {r.piece: r.x for r in rows}
            history.append(sums.pop(""))
            total = sum(sums.values())
            pieces = {p: math.log(x / total) for p, x in sums.items() if x > 1e-9}
        if len(pieces) <= vocabulary:
            return Unigram(pieces, max(map(len, pieces))), history
        keep = max(vocabulary, int(len(pieces) * prune))
        order = sorted(pieces, key=lambda p: (len(p) > 1, -pieces[p], p))
        pieces = {p: pieces[p] for p in order[: max(keep, sum(len(p) == 1 for p in pieces))]}
        if len(pieces) > vocabulary and len(pieces) == sum(len(p) == 1 for p in pieces):
            return Unigram(pieces, 1), history


def encode(docs: DataFrame, models: dict[str, Unigram | Merges], tokens: str = "toks") -> DataFrame:
    """``docs`` (lang, toks, ...) with the subword pieces of each token array; each worker remembers the words it has cut."""
    sent = docs.sparkSession.sparkContext.broadcast(models)
    names = docs.columns

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo: dict[tuple[str, str], list[str]] = {}
        for batch in batches:
            out = []
            for lang, toks in zip(batch.column("lang").to_pylist(), batch.column(tokens).to_pylist()):
                row = []
                for w in toks:
                    if (lang, w) not in memo:
                        if len(memo) > 200_000:
                            memo.clear()
                        memo[lang, w] = sent.value[lang].encode(w) if lang in sent.value else [w]
                    row += memo[lang, w]
                out.append(row)
            columns = [pa.array(out, pa.list_(pa.string())) if n == tokens else batch.column(n) for n in names]
            yield pa.RecordBatch.from_arrays(columns, names)

    return docs.mapInArrow(cut, docs.schema)
