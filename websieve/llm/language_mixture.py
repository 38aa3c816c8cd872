"""Language identification as inference of a mixture.

Each language has a distribution over letter trigrams (a letter and its two neighbours inside a word, the
word's ends being marks of their own), counted over all training texts in a fixed number of hashed slots.
A document is a mixture of languages: expectation-maximisation over its words finds the proportions, a
word's likelihood under a language being the product over its trigrams. Sets of one, two, ... of the
likeliest languages, as many as improve it, are then compared by likelihood less a penalty for each language, and the largest
share in the chosen set is the prediction.

Edge cases: null texts and texts without a letter are ``und`` with score 0; rows without language are not
learned from; with nothing to learn from, every text is ``und``; ties go to the language first in
alphabetical order; repeated rows and null ids come back as they are; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Words, map_batches, slices

SLOT_BITS = 17
UNKNOWN = "und"
_LETTER: list[np.ndarray] = []


def is_letter(codes: np.ndarray) -> np.ndarray:
    """Whether each code point is a letter; one table for the first plane, others looked up singly."""
    if not _LETTER:
        _LETTER.append(np.fromiter((chr(i).isalpha() for i in range(0x10000)), bool, 0x10000))
    out = _LETTER[0][np.minimum(codes, 0xFFFF)]
    for i in np.flatnonzero(codes > 0xFFFF):
        out[i] = chr(codes[i]).isalpha()
    return out


def trigram_slots(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """For each letter of each (lower-cased) word the slot of its trigram, and the word it belongs to."""
    joined = "\0".join(["", *pc.utf8_lower(pc.replace_substring(words, "\0", "")).to_pylist(), ""])
    codes = np.frombuffer(joined.encode("utf-32-le", "replace"), "<u4")
    ends = np.cumsum(codes == 0) - 1
    codes = np.where(is_letter(codes), codes, 0).astype(np.uint64)
    middle = np.flatnonzero(codes)
    key = codes[middle - 1] * np.uint64(0x9E3779B97F4A7C15) + codes[middle] * np.uint64(0xC2B2AE3D27D4EB4F) + codes[middle + 1] * np.uint64(0x165667B19E3779F9)
    key ^= key >> np.uint64(29)
    key *= np.uint64(0xBF58476D1CE4E5B9)
    return (key >> np.uint64(64 - SLOT_BITS)).astype(np.int64), ends[middle]


class MixtureModel:
    """Log-probabilities of the trigram slots under each language."""

    def __init__(self, languages: list[str], counts: np.ndarray, smoothing: float):
        self.languages = languages
        total = counts.sum(axis=0, keepdims=True)
        self.log_p = np.log((counts + smoothing) / (total + smoothing * counts.shape[0])).astype(np.float32)  # slot x language

    def infer(self, texts: pa.Array, rounds: int, penalty: float) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Predicted language, its share, and all shares (text x language) of each text."""
        words = Words(texts, lines=True)
        slots, owner = trigram_slots(words.distinct)
        n_words, n_lang = len(words.distinct), len(self.languages)
        log_word = np.zeros((n_words, n_lang), np.float64)
        present = np.zeros(n_words, bool)
        if len(slots):
            first = np.flatnonzero(np.diff(owner, prepend=-1))
            log_word[owner[first]] = np.add.reduceat(self.log_p[slots], first, axis=0, dtype=np.float64)
            present[owner[first]] = True
        top = log_word.max(axis=1)
        word_p = np.exp(log_word - top[:, None])
        text_of = np.repeat(np.arange(len(texts)), np.diff(words.bounds))
        kept = present[words.codes]
        codes, text_of = words.codes[kept], text_of[kept]
        n = np.bincount(text_of, minlength=len(texts))
        some = np.flatnonzero(n)
        share = np.zeros((len(texts), n_lang))
        names, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
        if len(some):
            starts = np.concatenate([[0], np.cumsum(n[some])])[:-1]
            row = np.repeat(np.arange(len(some)), n[some])
            found = choose_set(word_p[codes], row, starts, n[some], rounds, penalty)
            share[some] = found
            best = found.argmax(axis=1)
            score[some] = np.clip(found[np.arange(len(some)), best], 0.0, 1.0)
            for i, k in zip(some.tolist(), best.tolist()):
                names[i] = self.languages[k]
        return names, score, share


def maximise(p: np.ndarray, row: np.ndarray, starts: np.ndarray, n: np.ndarray, share: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """Expectation-maximisation for many texts at once: shares and log-likelihoods after ``rounds`` rounds."""
    for _ in range(rounds):
        weight = p * share[row]
        weight /= np.maximum(weight.sum(axis=1, keepdims=True), 1e-300)
        share = np.add.reduceat(weight, starts, axis=0) / n[:, None]
    return share, np.add.reduceat(np.log(np.maximum((p * share[row]).sum(axis=1), 1e-300)), starts)


def choose_set(p: np.ndarray, row: np.ndarray, starts: np.ndarray, n: np.ndarray, rounds: int, penalty: float) -> np.ndarray:
    """Shares under the language set whose penalised likelihood is highest. Sets of up to three are always tried, larger ones for the
    texts that the last size still improved."""
    n_lang = p.shape[1]
    full, _ = maximise(p, row, starts, n, np.full((len(n), n_lang), 1.0 / n_lang), rounds)
    order = np.argsort(-full, axis=1, kind="stable")
    best, best_value = np.zeros_like(full), np.full(len(n), -np.inf)
    at = np.arange(len(n))  # the texts that are still open
    for size in range(1, n_lang + 1):
        if size > 3:
            going = better
            if not going.any():
                break
            p, row = p[going[row]], (np.cumsum(going) - 1)[row[going[row]]]
            at, n = at[going], n[going]
            starts = np.concatenate([[0], np.cumsum(n)])[:-1]
        inside = np.zeros((len(at), n_lang))
        np.put_along_axis(inside, order[at, :size], 1.0, axis=1)
        begin = inside * np.maximum(full[at], 1e-6)
        begin /= begin.sum(axis=1, keepdims=True)
        share, value = maximise(p, row, starts, n, begin, 0 if size == 1 else max(1, rounds // 3))
        value = value - penalty * (size - 1) * np.log(n + 1.0)
        better = value > best_value[at]
        best[at[better]], best_value[at[better]] = share[better], value[better]
    return best


def fit(training: DataFrame, text_col: str = "text", lang_col: str = "lang", smoothing: float = 0.05) -> MixtureModel | None:
    """Count trigram slots by language over every training row. What returns to the driver is at most one
    row for each language and slot. None when there is nothing to learn from."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for part in slices(batch, 0):
                words = Words(part.column(0), lines=True)
                slots, owner = trigram_slots(words.distinct)
                langs = part.column(1).to_pylist()
                sizes = np.diff(words.bounds)
                for lang in set(langs):
                    mine = np.repeat(np.fromiter((x == lang for x in langs), bool, len(langs)), sizes)
                    times = np.bincount(words.codes[mine], minlength=len(words.distinct))
                    counts = total.setdefault(lang, np.zeros(1 << SLOT_BITS, np.int64))
                    counts += np.bincount(slots, times[owner], 1 << SLOT_BITS).astype(np.int64)
        for lang, counts in total.items():
            used = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(used), pa.string()), pa.array(used, pa.int64()), pa.array(counts[used])], ["lang", "slot", "n"])

    rows = training.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(text_col).alias("t"), F.col(lang_col).cast("string").alias("l"))
    table = map_batches(rows, count, "lang string, slot long, n long").groupBy("lang", "slot").agg(F.sum("n").alias("n")).toPandas()
    if not len(table):
        return None
    languages = sorted(table["lang"].unique())
    counts = np.zeros((1 << SLOT_BITS, len(languages)))
    counts[table["slot"].to_numpy(), np.searchsorted(languages, table["lang"].to_numpy())] = table["n"].to_numpy()
    return MixtureModel(languages, counts, smoothing)


def identify(docs: DataFrame, model: MixtureModel | None, id_col: str = "doc_id", text_col: str = "text", *, keep: dict[str, Column] | None = None, rounds: int = 9, penalty: float = 1.0) -> DataFrame:
    """(id, lang_pred, score, shares) for every row, with further columns ``keep`` carried along."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    keep = keep or {}
    inputs = docs.select(F.col(id_col).alias("key"), F.col(text_col).alias("t"), *(c.alias(name) for name, c in keep.items()))
    names_kept = list(keep)
    carried = "".join(f", {name} {inputs.schema[name].dataType.simpleString()}" for name in keep)

    def predict(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fitted = sent.value
        for batch in batches:
            for part in slices(batch, 1):
                if fitted is None:
                    names, score, shares = [UNKNOWN] * part.num_rows, np.zeros(part.num_rows), [{}] * part.num_rows
                else:
                    names, score, share = fitted.infer(part.column(1), rounds, penalty)
                    shares = [[(fitted.languages[k], float(row[k])) for k in np.flatnonzero(row > 0.005)] for row in share]
                columns = [part.column(0), pa.array(names, pa.string()), pa.array(score), pa.array(shares, pa.map_(pa.string(), pa.float64())), *part.columns[2:]]
                yield pa.RecordBatch.from_arrays(columns, ["key", "lang_pred", "score", "shares", *names_kept])

    key = docs.schema[id_col].dataType.simpleString()
    return map_batches(inputs, predict, f"key {key}, lang_pred string, score double, shares map<string,double>{carried}").withColumnRenamed("key", id_col)
