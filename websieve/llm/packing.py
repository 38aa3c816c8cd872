"""Order-preserving packing of documents into fixed-length windows by dynamic programming.

Documents keep the order in which a task reads them. Their tokens form one stream with three kinds of
possible cuts: between documents (free), between sentences, and, inside a sentence longer than a window,
at any token. The program chooses the cuts that minimise padding plus truncation penalties. For a cut at
``i`` the best earlier cut is the minimum of ``cost[j] + pos[j]`` over a sliding range, kept in a monotone
queue, so the work is linear in the number of possible cuts. A window whose length is a power of two
needs no padding; such earlier cuts are looked up by position.

A task works through its documents in blocks of about ``block_tokens`` tokens and carries the open window
into the next block, so memory follows the block and the longest document, not the task.

Edge cases: a null or empty text is a document of the single closing id; repeated rows are packed as often
as they occur; null ids come back null; an empty table packs to nothing; other columns are ignored.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BoundedCache, Words, loaded, map_batches, slices

ODD_SPACE = "[\x1c-\x1f]"
SENTENCE_ENDS = r"(^\n|[.!?])$"
PLAIN = re.compile("([A-Za-zß-öø-ÿÀ-ÖØ-Þ]+)([!-&(-/:-@[-`{-~]*)")
APART = 20_000  # chunks that are encoded together
DOCUMENT, SENTENCE, FORCED = 0, 1, 2


class ChunkTokenizer:
    """Token ids of texts, remembered by white-space-delimited chunk.

    A tokenizer that splits at white space before merging, and keeps none of it, encodes a text as it encodes its chunks. Chunks of
    letters with closing punctuation go to the merge model itself, letters and punctuation apart, and are remembered by these; other
    chunks that are not remembered are encoded together, in one text, and told apart by where their tokens begin. Whether this tokenizer
    allows either is probed when it loads; what it does not allow is left to the whole library.
    """

    PROBE = "Ab, c  (d)\n\nÉtude 12.5%\t<s> end.\n x"

    def __init__(self, path: str, letter_bytes: int = 64 << 20, chunk_bytes: int = 16 << 20):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.letters, self.chunks = BoundedCache(letter_bytes), BoundedCache(chunk_bytes)
        self.byte_chars = {i: self._byte_char(i) for i in range(256)}
        parts = Words(pa.array([self.PROBE]), lines=True)
        distinct = parts.distinct.to_pylist()
        coded = self.apart(distinct)
        self.by_chunk = b"".join(coded[c] for c in parts.codes) == self.whole(self.PROBE) and coded == [self.whole(c) for c in distinct]
        self.merges = self.by_chunk and self._merges_alike()

    def _merges_alike(self) -> bool:
        """Whether the merge model gives what the library does, for every letter and punctuation mark that goes to it."""
        probes = [x for c in map(chr, range(33, 256)) for x in (c, f"a{c}", f"{c}b", f"Word{c}{c}", f"ma{c}na.") if PLAIN.fullmatch(x)]
        try:
            return [self._plain(PLAIN.fullmatch(x)) for x in probes] == self.apart(probes)
        except Exception:  # a model without merges of this kind
            return False

    @staticmethod
    def _byte_char(i: int) -> str:
        """The printable character that byte-level vocabularies write for byte ``i``."""
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        return chr(i) if i in shown else chr(256 + sum(1 for b in range(i) if b not in shown))

    def _merge(self, word: str) -> bytes:
        if (known := self.letters.get(word)) is None:
            table = self.byte_chars
            shown = word if word.isascii() else "".join([table[b] for b in word.encode()])
            ids = [t.id for t in self.model.tokenize(shown)]
            known = struct.pack(f"<{len(ids)}I", *ids)
            self.letters.put(word, known)
        return known

    def _plain(self, m: re.Match) -> bytes:
        letters, marks = m[1].lower(), m[2]
        known = self.letters.get(letters) or self._merge(letters)
        return known + (self.letters.get(marks) or self._merge(marks)) if marks else known

    @classmethod
    def of(cls, path: str) -> "ChunkTokenizer":
        kept = loaded("packing")
        if path not in kept:
            kept[path] = cls(path)
        return kept[path]

    def whole(self, text: str) -> bytes:
        return np.asarray(self.library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def apart(self, chunks: list[str]) -> list[bytes]:
        """The ids of each chunk, from one call of the library."""
        done = self.library.encode(" ".join(chunks), add_special_tokens=False)
        raw = np.asarray(done.ids, "<u4").tobytes()
        lengths = np.fromiter(map(len, chunks), np.int64, len(chunks)) + 1
        starts = np.fromiter((o[0] for o in done.offsets), np.int64, len(raw) // 4)
        ends = (4 * np.searchsorted(starts, np.cumsum(lengths))).tolist()
        return [raw[low:high] for low, high in zip([0, *ends], ends)]

    def encode(self, texts: pa.Array) -> Iterator[tuple[bytes, list[int]]]:
        """For each text its ids as little-endian 32-bit words, and how many ids stand before each sentence end."""
        words = Words(texts, lines=True)
        parts = words.distinct.to_pylist()
        if self.merges:
            plain, like = self._plain, PLAIN.fullmatch
            coded = [plain(m) if (m := like(c)) else None for c in parts]
        else:
            coded = [None if self.by_chunk else b""] * len(parts)
        recall = self.chunks.get
        missing = []
        for i in [i for i, known in enumerate(coded) if known is None]:
            if (known := recall(parts[i])) is None:
                missing.append(i)
            coded[i] = known
        for first in range(0, len(missing), APART):
            some = missing[first : first + APART]
            for i, known in zip(some, self.apart([parts[i] for i in some])):
                coded[i] = known
                self.chunks.put(parts[i], known)
        sizes = np.fromiter(map(len, coded), np.int64, len(coded)) >> 2
        firsts, ids = np.cumsum(sizes) - sizes, np.frombuffer(b"".join(coded), "<u4")
        ends = np.cumsum(sizes[words.codes])
        take = np.repeat(firsts[words.codes] - ends + sizes[words.codes], sizes[words.codes]) + np.arange(ends[-1] if len(ends) else 0)
        stream = ids[take]
        closes = pc.match_substring_regex(words.distinct, SENTENCE_ENDS).to_numpy(zero_copy_only=False)[words.codes]
        places = ends[closes]
        limits = np.concatenate([[0], ends])[words.bounds]
        odd = pc.fill_null(pc.match_substring_regex(texts, ODD_SPACE), False).to_pylist()
        for i, (low, high) in enumerate(zip(limits[:-1].tolist(), limits[1:].tolist())):
            if odd[i] or not self.by_chunk:
                yield self.whole(texts[i].as_py() or ""), []
            else:
                own = places[np.searchsorted(places, low, "right") : np.searchsorted(places, high, "left")]
                yield stream[low:high].tobytes(), np.unique(own - low).tolist()


def choose_cuts(ends: list[int], kinds: list[int], window: int, sentence_penalty: float, forced_penalty: float, sequence_cost: float) -> tuple[list[int], list[float]]:
    """For each possible cut the index of the best cut before it (-1: the stream's start), and its cost.

    ``ends`` are strictly increasing token positions, no two more than ``window`` apart; ``kinds`` says
    what each cut divides.
    """
    penalty = (0.0, sentence_penalty, forced_penalty)
    powers = [1 << k for k in range(8, window.bit_length()) if 1 << k <= window]
    before, cost = [0] * len(ends), [0.0] * len(ends)
    at_pos = {0: -1}
    queue: deque[tuple[float, int, int]] = deque([(0.0, 0, -1)])  # (cost + position, position, index), rising
    for i, pos in enumerate(ends):
        low = pos - window
        while queue[0][1] < low:
            queue.popleft()
        best, j = queue[0][0] + window - pos, queue[0][2]
        for p in powers:
            if (k := at_pos.get(pos - p)) is not None and (c := cost[k] if k >= 0 else 0.0) <= best:
                best, j = c, k
        best += sequence_cost + penalty[kinds[i]]
        before[i], cost[i], at_pos[pos] = j, best, i
        key = best + pos
        while queue and queue[-1][0] >= key:
            queue.pop()
        queue.append((key, pos, i))
    return before, cost


class Packer:
    """Packs a stream of documents; ``add`` and ``finish`` yield pieces (key, start, length, crc, doc_tokens, sequence, offset)."""

    def __init__(self, window: int, closing_id: int, first_sequence: int, block_tokens: int, sentence_penalty: float, forced_penalty: float, sequence_cost: float):
        self.window, self.block_tokens = window, block_tokens
        self.closing = np.asarray([closing_id], "<u4").tobytes()
        self.costs = (sentence_penalty, forced_penalty, sequence_cost)
        self.sequence = first_sequence
        self.docs: list[tuple[object, bytes, int]] = []  # key, ids, first token still to be packed
        self.ends: list[int] = []
        self.kinds: list[int] = []
        self.length = 0

    def add(self, key: object, ids: bytes, sentence_ends: list[int]) -> Iterator[tuple]:
        ids += self.closing
        size, before = len(ids) // 4, 0
        for end in [*sentence_ends, size]:
            if end == size - 1:  # the closing id stays with the last sentence
                continue
            while end - before > self.window:
                before += self.window
                self._cut(self.length + before, FORCED)
            before = end
            self._cut(self.length + end, DOCUMENT if end == size else SENTENCE)
        self.length += size
        self.docs.append((key, ids, 0))
        if self.length >= self.block_tokens:
            yield from self._pack(final=False)

    def _cut(self, at: int, kind: int) -> None:
        self.ends.append(at)
        self.kinds.append(kind)

    def finish(self) -> Iterator[tuple]:
        if self.ends:
            yield from self._pack(final=True)

    def _pack(self, final: bool) -> Iterator[tuple]:
        before, cost = choose_cuts(self.ends, self.kinds, self.window, *self.costs)
        last = len(self.ends) - 1
        if not final:  # any cut less than a window from the end may be the last one settled now
            i = last
            while i >= 0 and self.ends[i] > self.length - self.window:
                last = i if cost[i] <= cost[last] else last
                i -= 1
        cuts, i = [], last
        while i >= 0:
            cuts.append(self.ends[i])
            i = before[i]
        cuts.reverse()
        settled, d, begun, start = cuts[-1], 0, 0, 0
        for end in cuts:
            offset = 0
            while start < end:
                key, ids, done = self.docs[d]
                size = len(ids) // 4
                n = min(size - done - (start - begun), end - start)
                at = done + start - begun
                yield key, at, n, zlib.crc32(ids[4 * at : 4 * (at + n)]), size, self.sequence, offset
                start, offset = start + n, offset + n
                if at + n == size:
                    d, begun = d + 1, start
            self.sequence += 1
        rest = self.docs[d:]
        if rest and begun < settled:
            key, ids, done = rest[0]
            rest[0] = (key, ids, done + settled - begun)
        self.docs = rest
        self.ends, self.kinds = [e - settled for e in self.ends[last + 1 :]], self.kinds[last + 1 :]
        self.length -= settled


def pack(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", *, window: int = 2048, closing_id: int = 1, block_tokens: int = 1 << 19, sentence_penalty: float = 24.0, forced_penalty: float = 96.0, sequence_cost: float = 4.0) -> DataFrame:
    """Pieces of all documents: (id, start, length, ids_crc32, doc_tokens, sequence_id, offset).

    ``sequence_id`` is the number of the task times 2**32 plus the window's number in it.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        tok = ChunkTokenizer.of(tokenizer_path)
        task = TaskContext.get().partitionId()
        packer = Packer(window, closing_id, task << 32, block_tokens, sentence_penalty, forced_penalty, sequence_cost)
        key_type = None
        for batch in batches:
            for part in slices(batch, 1):
                key_type = part.schema.field(0).type
                rows: list[tuple] = []
                for key, (ids, ends) in zip(part.column(0).to_pylist(), tok.encode(part.column(1))):
                    rows += packer.add(key, ids, ends)
                if rows:
                    yield as_batch(rows, key_type)
        if rows := list(packer.finish()):
            yield as_batch(rows, key_type)

    key = docs.schema[id_col].dataType.simpleString()
    schema = f"key {key}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    return map_batches(docs.select(F.col(id_col).alias("key"), F.col(text_col).alias("t")), run, schema, "packing").withColumnRenamed("key", id_col)


def as_batch(rows: list[tuple], key_type: pa.DataType) -> pa.RecordBatch:
    key, *numbers = zip(*rows)
    return pa.RecordBatch.from_arrays([pa.array(key, key_type), *(pa.array(c, pa.int64()) for c in numbers)], ["key", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])
