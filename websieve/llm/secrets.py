"""Secrets in texts: fixed patterns, and strings that a character Markov model takes for random.

Two models of character pairs, one of random strings and one of ordinary identifiers and words, are counted
over all texts from labelled samples: values that the patterns find are random strings (with a prior of
uniformly random ones of the usual alphabets), all other words of fewer than 20 characters are ordinary. A string of the alphabet of
keys that is long enough is a secret when its log-likelihood ratio exceeds a threshold for each character
and in total. Spans found by a pattern stay; the models only add spans that touch none of them.

Spans are (kind, start, end) in code points, the end exclusive, over the pattern's whole match.

Edge cases: null text counts as empty and has no span; repeated rows and null ids come back as they are;
an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, map_batches, slices

# The patterns, each with the group whose length counts and the least length.
KINDS = ("assign", "access", "hex", "markov")
PATTERNS = {
    "assign": (re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 2, 6),
    "access": (re.compile(r"AKIA[A-Z0-9]+"), 0, 20),
    "hex": (re.compile(r"[0-9a-f]+"), 0, 24),
}
HINTS = {
    "assign": "(?i)password|passwd|secret|token|api_?key",
    "access": "AKIA[A-Z0-9]{16}",
    "hex": "[0-9a-f]{24}",
}
LEAST = 20  # characters of a string that the models judge; shorter words are the ordinary sample
KEY_STRING = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
WORD = re.compile(r"[A-Za-z0-9+/_=-]{6,}")
ALPHABETS = ("0123456789abcdef", "0123456789ABCDEF", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", "abcdefghijklmnopqrstuvwxyz0123456789")
STATES = 96  # printable ASCII, and 95 for all else


def base_spans(text: str, kinds: tuple[str, ...] = ("assign", "access", "hex")) -> list[tuple[int, int, int, str]]:
    """(start, number of the kind, end, value) of every match that is long enough."""
    out = []
    for kind in kinds:
        pattern, group, least = PATTERNS[kind]
        out += [(m.start(), KINDS.index(kind), m.end(), m.group(group)) for m in pattern.finditer(text) if m.end(group) - m.start(group) >= least]
    return out


def hinted(texts: pa.Array) -> dict[str, np.ndarray]:
    """For each kind, which texts can have a match at all."""
    return {kind: pc.fill_null(pc.match_substring_regex(texts, hint), False).to_numpy(zero_copy_only=False) for kind, hint in HINTS.items()}


def pair_states(strings: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of the character pairs of the strings, and the string each belongs to."""
    raw = np.frombuffer("\n".join(["", *strings, ""]).encode("latin-1", "replace"), np.uint8)
    owner = np.cumsum(raw == 10) - 1
    state = np.where((raw >= 32) & (raw < 127), raw - 32, 95).astype(np.int64)
    inside = np.flatnonzero((raw[1:] != 10) & (raw[:-1] != 10))
    return state[inside] * STATES + state[inside + 1], owner[inside]


def random_prior(weight: float) -> np.ndarray:
    """Expected pair counts of uniformly random strings over the usual alphabets."""
    counts = np.zeros((STATES, STATES))
    for letters in ALPHABETS:
        at = [ord(c) - 32 for c in letters]
        counts[np.ix_(at, at)] += weight / len(at) ** 2
    return counts


class PairModels:
    """Log-likelihood ratio of character pairs, random to ordinary."""

    def __init__(self, random: np.ndarray, ordinary: np.ndarray, pull: float = 5.0, smoothing: float = 0.5):
        def log_p(counts: np.ndarray) -> np.ndarray:
            """Pairs lean on how frequent their second character is, so that what a sample lacks is unlikely under it."""
            single = counts.sum(axis=0)
            single = (single + smoothing) / (single.sum() + smoothing * STATES)
            return np.log((counts + pull * single) / (counts.sum(axis=1, keepdims=True) + pull))

        self.ratio = (log_p(random) - log_p(ordinary)).ravel()

    def ratios(self, strings: list[str]) -> np.ndarray:
        pairs, owner = pair_states(strings)
        return np.bincount(owner, self.ratio[pairs], len(strings))


def fit(docs: DataFrame, text_col: str = "text", prior_weight: float = 20_000.0) -> PairModels:
    """Count character pairs of both samples over all texts; at most two times 96 x 96 sums reach the driver."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, STATES * STATES), np.int64)
        for batch in batches:
            for part in slices(batch, 0):
                texts = part.column(0)
                found: list[str] = []
                able = hinted(texts)
                for i in np.flatnonzero(np.logical_or.reduce(list(able.values()))):
                    kinds = tuple(k for k in able if able[k][i])
                    found += [x[3] for x in base_spans(texts[int(i)].as_py(), kinds)]
                total[0] += np.bincount(pair_states(found)[0], minlength=STATES * STATES)
                words = Words(texts, lines=True)
                times = np.bincount(words.codes, minlength=len(words.distinct))
                taken = set(found)
                size = pc.binary_length(words.distinct).to_numpy(zero_copy_only=False)
                index = np.flatnonzero(size >= 6)
                ordinary, weight = [], []
                for word, n in zip(words.distinct.take(pa.array(index)).to_pylist(), times[index].tolist()):
                    if word.isalpha() and len(word) < LEAST:
                        ordinary.append(word)
                        weight.append(n)
                        continue
                    for piece in WORD.findall(word):
                        if len(piece) < LEAST and piece not in taken:
                            ordinary.append(piece)
                            weight.append(n)
                pairs, owner = pair_states(ordinary)
                total[1] += np.bincount(pairs, np.asarray(weight, np.float64)[owner] if len(owner) else None, STATES * STATES).astype(np.int64)
        for label in (0, 1):
            used = np.flatnonzero(total[label])
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(used), label, np.int32)), pa.array(used, pa.int64()), pa.array(total[label][used])], ["label", "pair", "n"])

    rows = map_batches(docs.select(F.col(text_col).alias("t")), count, "label int, pair long, n long").groupBy("label", "pair").agg(F.sum("n").alias("n")).toPandas()
    sums = np.zeros((2, STATES * STATES))
    sums[rows["label"].to_numpy(np.int64), rows["pair"].to_numpy(np.int64)] = rows["n"].to_numpy(np.float64)
    return PairModels(sums[0].reshape(STATES, STATES) + random_prior(prior_weight), sums[1].reshape(STATES, STATES))


def scan(docs: DataFrame, models: PairModels, id_col: str = "doc_id", text_col: str = "text", *, per_char: float = 0.7, in_total: float = 16.0) -> DataFrame:
    """(id, spans array<struct<kind, start, end>>) for every row; spans by start, then kind as listed."""
    sent = docs.sparkSession.sparkContext.broadcast(models)
    key = docs.schema[id_col].dataType.simpleString()

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pair_models = sent.value
        for batch in batches:
            for part in slices(batch, 1):
                texts = part.column(1)
                able = hinted(texts)
                words = Words(texts, lines=True)
                long = np.flatnonzero(pc.binary_length(words.distinct).to_numpy(zero_copy_only=False) >= LEAST)
                odd = np.zeros(len(words.distinct), bool)
                pieces = [(int(i), p) for i, w in zip(long, words.distinct.take(pa.array(long)).to_pylist()) for p in KEY_STRING.findall(w)]
                ratios = pair_models.ratios([p for _, p in pieces])
                keys = {p for (_, p), r in zip(pieces, ratios) if r >= max(in_total, per_char * len(p))}
                odd[[i for i, p in pieces if p in keys]] = True
                has_key = words.sums(odd.astype(np.int64)) > 0
                spans: list[list] = [[] for _ in range(part.num_rows)]
                for i in np.flatnonzero(np.logical_or.reduce([*able.values(), has_key])):
                    text = texts[int(i)].as_py()
                    own = base_spans(text, tuple(k for k in able if able[k][i]))
                    if has_key[i]:
                        added = [(m.start(), 3, m.end(), "") for m in KEY_STRING.finditer(text) if m.group() in keys]
                        own += [a for a in added if not any(a[0] < b[2] and b[0] < a[2] for b in own)]
                    spans[i] = [{"kind": KINDS[k], "start": s, "end": e} for s, k, e, _ in sorted(own)]
                kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(spans, kind)], ["key", "spans"])

    return map_batches(docs.select(F.col(id_col).alias("key"), F.col(text_col).alias("t")), find, f"key {key}, spans array<struct<kind:string,start:long,end:long>>").withColumnRenamed("key", id_col)
