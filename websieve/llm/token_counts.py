"""Token counts by a map-side two-tier lookup.

A text is cut before every run of spaces. No piece of the vocabulary has a space mark after another
character, so merges never cross such a cut and the token counts of the pre-tokens add up to the
count of the text (``SpaceCutTokenizer`` checks the vocabulary when it loads and encodes whole texts
if that ever fails). The first tier is a broadcast table of the most frequent pre-tokens and their
token counts; the second is a cache in each Python worker, whose misses go to the library. Pre-tokens
are never shuffled: only each task's short summary of frequent ones is.

Edge cases: null text counts as empty (0 bytes, 0 tokens); repeated rows and null ids come back as they
are; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BoundedCache, Words, map_batches, slices

SPACE_RUN = re.compile(" +[^ ]+| +$")
MARK = "▁"
_LOADED: dict[str, "SpaceCutTokenizer"] = {}


class SpaceCutTokenizer:
    """Counts tokens of texts, remembering the counts of pre-tokens it has met."""

    def __init__(self, model_path: str, cache_bytes: int = 24 << 20):
        import sentencepiece

        self.library = sentencepiece.SentencePieceProcessor(model_file=model_path)
        pieces = (self.library.id_to_piece(i) for i in range(self.library.vocab_size()))
        self.additive = not any(MARK in piece.lstrip(MARK) for piece in pieces)
        self.cache = BoundedCache(cache_bytes)

    @classmethod
    def of(cls, model_path: str) -> "SpaceCutTokenizer":
        """One tokenizer for each worker process and model."""
        if model_path not in _LOADED:
            _LOADED[model_path] = cls(model_path)
        return _LOADED[model_path]

    def encode_sizes(self, texts: list[str]) -> list[int]:
        return [len(ids) for ids in self.library.encode(texts, num_threads=1)]

    def counts(self, texts: pa.Array, frequent: dict[str, int]) -> np.ndarray:
        """Token counts of texts: frequent pre-tokens from the table, others from the cache, the rest encoded."""
        words = Words(texts)
        parts = words.distinct.to_pylist()
        hot, cache = frequent.get, self.cache
        sizes = [hot(p) or cache.get(p) for p in parts]
        missing = [i for i, size in enumerate(sizes) if size is None]
        for i, size in zip(missing, self.encode_sizes([parts[i] for i in missing])):
            sizes[i] = size
            cache.put(parts[i], size)
        out = words.sums(np.asarray(sizes, np.int64))
        out[pc.fill_null(pc.equal(pc.binary_length(texts), 0), True).to_numpy(zero_copy_only=False)] = 0
        self._apart(texts, out)
        return out

    def _apart(self, texts: pa.Array, out: np.ndarray) -> None:
        """Texts with runs of spaces, or with the space mark itself, are cut with the runs kept together or not at all."""
        odd = pc.or_(pc.match_substring(texts, "  "), pc.match_substring(texts, MARK))
        odd = pc.or_(odd, pc.or_(pc.starts_with(texts, " "), pc.ends_with(texts, " "))) if self.additive else pc.is_valid(texts)
        for i in np.flatnonzero(pc.fill_null(odd, False).to_numpy(zero_copy_only=False)):
            text = texts[int(i)].as_py()
            if MARK in text or not self.additive:
                out[i] = self.encode_sizes([text])[0]
                continue
            parts = [p[1:] for p in SPACE_RUN.findall(" " + text)]
            distinct = list(set(parts))
            size = dict(zip(distinct, self.encode_sizes(distinct)))
            out[i] = sum(size[p] for p in parts)


def frequent_pre_tokens(docs: DataFrame, text_col: str, entries: int, per_task: int, held: int = 40_000) -> list[str]:
    """The most frequent pre-tokens, at most ``entries`` of them. Every text is read; each task hands on its
    ``per_task`` most frequent ones, so what is shuffled follows the tasks and not the words."""

    def summarise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: Counter[str] = Counter()
        for batch in batches:
            for part in slices(batch, 0):
                words = Words(part.column(0))
                n = np.bincount(words.codes, minlength=len(words.distinct))
                often = np.argsort(-n, kind="stable")[: held // 4]
                counts.update(dict(zip(words.distinct.take(pa.array(often)).to_pylist(), n[often].tolist())))
                if len(counts) > held:
                    counts = Counter(dict(counts.most_common(held // 4)))
        top = [(w, n) for w, n in counts.most_common(per_task) if 0 < len(w) <= 64]
        yield pa.RecordBatch.from_arrays([pa.array([w for w, _ in top], pa.string()), pa.array([n for _, n in top], pa.int64())], ["word", "n"])

    sums = map_batches(docs.select(F.col(text_col).alias("t")), summarise, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return [r.word for r in sums.orderBy(F.desc("n"), "word").limit(entries).collect()]


def count_tokens(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", *, frequent: int = 20_000, per_task: int = 2_000, limit: int = 4096) -> DataFrame:
    """(id, n_bytes, n_tokens, over_limit) for every row of ``docs``.

    ``frequent`` bounds the broadcast table (about 2 MB at 20,000 entries); it only decides which lookups
    are answered by the first tier.
    """
    tokenizer = SpaceCutTokenizer(model_path)
    words = frequent_pre_tokens(docs, text_col, frequent, per_task)
    sent = docs.sparkSession.sparkContext.broadcast(dict(zip(words, tokenizer.encode_sizes(words))) if words else {})

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, hot = SpaceCutTokenizer.of(model_path), sent.value
        for batch in batches:
            for part in slices(batch, 2):
                sizes = pa.array(tok.counts(part.column(2), hot), pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), sizes], ["key", "n_bytes", "n_tokens"])

    n_bytes: Column = F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long")
    key_type = docs.schema[id_col].dataType.simpleString()
    counted = map_batches(docs.select(F.col(id_col).alias("key"), n_bytes.alias("n_bytes"), F.col(text_col).alias("t")), count, f"key {key_type}, n_bytes long, n_tokens long")
    return counted.select(F.col("key").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
