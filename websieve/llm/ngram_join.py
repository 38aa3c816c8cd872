"""Near duplicates by a Jaccard join over word n-grams with prefix filtering.

A text's set is its distinct n-word shingles. Texts with equal sets form a class and go on as one. Shingles are
put in one global order, rare first: by a count over all documents, on a logarithmic scale and kept in a table of fixed size (1 byte
for each of 2**22 slots), then by hash; any order gives the same links. Two sets whose Jaccard similarity reaches the threshold share a shingle among the first few of each (the
prefix), so only classes that share a prefix shingle are candidates. Candidates pass the length filter, the positional
filter (what can still be shared after the first common shingle) and the suffix filter (a lower bound of the sets' difference
from counts between pivots, for which each class carries a signature of a byte for some 8 shingles). Only then texts are moved,
and each pair is verified once, exactly.

What is asked for is which documents are connected, so a pair that is known to be connected already needs no
verification. Rounds first verify, for each class, the pair with the leader of most of its prefix shingles; the links found
are joined to components, and the next round looks only at prefix shingles where different components meet. After a fixed number of
rounds, the same at every size, all pairs that are left are verified; the length and positional filters are part of that join, so
a shingle of a passage that many unlike texts share does not pair them all. Groups of near copies therefore cost about a pair for each copy and not one
for each pair of copies, and no link between components is missed, at any number of rounds.

Edge cases: null, empty and blank texts have no shingles and are components of their own; texts of fewer words than a shingle
are one shingle; rows that repeat an id are rows of their own, each joined by its own text; rows with a null id are joined like others
but name a component only when alone (null); ties in rarity go by hash; a very long text is held whole by one task, once as text and
once as 8 bytes a shingle; an empty table gives an empty result; other columns, whatever their names, are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, map_batches, slices, small_enough, written
from .components import components

MULTIPLIERS = [np.uint64(pow(0x9E3779B97F4A7C15, t, 1 << 64)) for t in range(1, 34)]
BLOCKS = 64  # of the rarity table
MIX_A, MIX_B = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mixed(x: np.ndarray, by: np.uint64) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * by
    return x ^ (x >> np.uint64(29))


def shingle_sets(texts: pa.Array, width: int) -> list[np.ndarray]:
    """The distinct shingle hashes of each text, rising."""
    # Lower-casing comes last: this library's ascii_lower misreads a sliced array of large strings, and replacing copies.
    spaced = pc.replace_substring_regex(pc.fill_null(texts, ""), "[\t-\r]", " ")
    words = Words(pc.ascii_lower(spaced))
    hashes = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in words.distinct.cast(pa.large_binary()).to_pylist()), np.uint64, len(words.distinct))
    filled = (pc.binary_length(words.distinct).to_numpy(zero_copy_only=False) > 0)[words.codes]
    stream = hashes[words.codes[filled]]
    bounds = np.concatenate([[0], np.cumsum(filled)])[words.bounds]
    n = len(stream)
    rolled = np.zeros(n, np.uint64)
    for t in range(min(width, n)):
        rolled[: n - t] += stream[t:] * MULTIPLIERS[t]
    rolled = mixed(rolled, MIX_A)
    out = []
    for low, high in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
        size = high - low
        if size >= width:
            out.append(np.unique(rolled[low : high - width + 1]))
        elif size:
            # The size takes part, so that a short text is no prefix of a longer one.
            ends = np.concatenate([stream[low:high], np.array([size], np.uint64)]) * np.array([*MULTIPLIERS[:size], MULTIPLIERS[32]])
            out.append(mixed(ends.sum(dtype=np.uint64, keepdims=True), MIX_A))
        else:
            out.append(np.empty(0, np.uint64))
    return out


def required(n_a, n_b, percent: int):
    """The least overlap of sets of these sizes whose Jaccard similarity reaches ``percent``."""
    return -(-percent * (n_a + n_b) // (100 + percent))


def prefix_size(n: int, percent: int) -> int:
    return n + percent * n // -100 + 1


def far_apart(a: np.ndarray, b: np.ndarray, most: int, pivots: int = 16) -> bool:
    """Suffix filter: whether the sets differ in more than ``most`` elements for certain, from how many of each lie
    between pivots."""
    at = np.linspace(0, len(a) - 1, min(pivots, len(a))).astype(np.int64)
    in_a, in_b = at, np.searchsorted(b, a[at])
    between = np.diff(np.concatenate([[0], in_a, [len(a)]])) - np.diff(np.concatenate([[0], in_b, [len(b)]]))
    return int(np.abs(between).sum()) > most


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Exactly: 100 * |a and b| >= percent * |a or b|."""
    least = required(len(a), len(b), percent)
    if least > min(len(a), len(b)) or far_apart(a, b, len(a) + len(b) - 2 * least):
        return False
    return len(np.intersect1d(a, b, assume_unique=True)) >= least


def signature(s: np.ndarray) -> bytes:
    """How many shingles of a set lie in each of equal ranges of hashes, about 8 to a range: the counts between pivots that the
    suffix filter compares, for pivots that are the same in all sets."""
    bits = signature_bits(len(s))
    return np.minimum(np.bincount((s >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits), 255).astype(np.uint8).tobytes()


def signature_bits(n: int) -> int:
    return max(1, min(16, (n // 8).bit_length()))


def surely_different(a: bytes, b: bytes, most: int) -> bool:
    """Suffix filter: whether sets with these signatures differ in more than ``most`` elements for certain. The finer signature is
    made as coarse as the other; counts that stop at 255 can only bring the bound down."""
    x, y = np.frombuffer(a, np.uint8).astype(np.int32), np.frombuffer(b, np.uint8).astype(np.int32)
    if len(x) != len(y):
        if 255 in (x if len(x) > len(y) else y):  # a count that stopped may not be added up
            return False
        x, y = (x.reshape(len(y), -1).sum(axis=1), y) if len(x) > len(y) else (x, y.reshape(len(x), -1).sum(axis=1))
        x, y = np.minimum(x, 255), np.minimum(y, 255)
    return int(np.abs(x - y).sum()) > most


class NearDuplicates:
    """The join of one table of documents with itself."""

    def __init__(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, width: int = 5, percent: int = 80, rarity_bits: int = 22, broadcast_rows: int = 1_000_000, settle_after: int = 3):
        self.docs = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("t"), F.xxhash64(text_col).alias("own"))
        self.id_type = self.docs.schema["doc_id"].dataType.simpleString()
        self.id_col, self.width, self.percent, self.rarity_bits, self.broadcast_rows, self.settle_after = id_col, width, percent, rarity_bits, broadcast_rows, settle_after
        both = written(self._sets(), "shingle-sets")
        self.sets = both.where("block IS NULL").drop("block", "counts")
        self.order = docs.sparkSession.sparkContext.broadcast(self._rarity(both))
        # A class goes by one of its rows: the text of that row is found again by the row's id and the hash of its text.
        row = F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "own", "n_shingles", "signature")).alias("row")
        self.classes = self.sets.where("n_shingles > 0").groupBy("key").agg(F.min("doc_id").alias("first_id"), row)
        self.entries = written(self._shared_entries(), "shared-prefixes")
        #: (key, row_id, row_own, n_shingles, signature) of the classes that have a shared prefix shingle.
        candidates = self.entries.select("key").distinct().join(self.classes, "key")
        self.candidates = written(candidates.select("key", F.col("row.doc_id").alias("row_id"), F.col("row.own").alias("row_own"), "row.n_shingles", "row.signature"), "candidates")

    def _sets(self) -> DataFrame:
        """(doc_id, own, n_shingles, key, signature) of each document, and for each task some rows (block, counts) with how many of its
        shingles fall in each slot of the rarity table, a block of the table in each row."""
        width, bits = self.width, self.rarity_bits
        names = ["doc_id", "own", "n_shingles", "key", "signature", "block", "counts"]

        def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            counts, id_type = np.zeros(1 << bits, np.uint32), pa.int64()
            for batch in batches:
                id_type = batch.schema.field(0).type
                for part in slices(batch, 1):
                    sets = shingle_sets(part.column(1), width)
                    for s in sets:
                        np.add.at(counts, (s >> np.uint64(64 - bits)).astype(np.int64), 1)
                    keys = np.array([set_key(s) for s in sets], np.uint64).view(np.int64)
                    signatures = pa.array([signature(s) for s in sets], pa.binary())
                    yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array([len(s) for s in sets], pa.int64()), pa.array(keys), signatures, pa.nulls(len(sets), pa.int32()), pa.nulls(len(sets), pa.binary())], names)
            blocks = [(i, packed(c)) for i, c in enumerate(np.split(counts, BLOCKS)) if c.any()]
            nothing = [pa.nulls(len(blocks), t) for t in (id_type, pa.int64(), pa.int64(), pa.int64(), pa.binary())]
            yield pa.RecordBatch.from_arrays([*nothing, pa.array([i for i, _ in blocks], pa.int32()), pa.array([c for _, c in blocks], pa.binary())], names)

        return map_batches(self.docs, measure, f"doc_id {self.id_type}, own long, n_shingles long, key long, signature binary, block int, counts binary")

    def _rarity(self, both: DataFrame) -> np.ndarray:
        """The rank of each slot by its count over all documents, on a logarithmic scale (one byte a slot). Blocks are added up by tasks
        of their own, so the driver gets one table, whatever the number of tasks."""
        size = (1 << self.rarity_bits) // BLOCKS

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[int, np.ndarray] = {}
            for batch in batches:
                for block, blob in zip(batch.column(0).to_pylist(), batch.column(1)):
                    total.setdefault(block, np.zeros(size, np.uint64))[:] += np.frombuffer(zlib.decompress(blob.as_py()), "<u4")
            ranks = [np.minimum(np.rint(8 * np.log2(c + 1.0)), 255).astype(np.uint8).tobytes() for c in total.values()]
            yield pa.RecordBatch.from_arrays([pa.array(total, pa.int32()), pa.array(ranks, pa.binary())], ["block", "ranks"])

        dealt = both.where("block IS NOT NULL").select("block", "counts").repartition("block")
        ranks = np.zeros(1 << self.rarity_bits, np.uint8)
        for row in map_batches(dealt, add, "block int, ranks binary").collect():
            ranks[row.block * size : (row.block + 1) * size] = np.frombuffer(row.ranks, np.uint8)
        return ranks

    def _prefixes(self) -> DataFrame:
        """(token, key, place): the prefix shingles of each text; ``place`` holds the set's size and the position."""
        width, bits, percent, order = self.width, self.rarity_bits, self.percent, self.order

        def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ranks = order.value
            for batch in batches:
                for part in slices(batch, 0):
                    tokens, keys, places = [], [], []
                    for s in shingle_sets(part.column(0), width):
                        if not len(s):
                            continue
                        size = prefix_size(len(s), percent)
                        # Rank first, then the hash; s is rising, so a stable sort leaves equal ones in the same order in every text.
                        first = np.argsort(ranks[(s >> np.uint64(64 - bits)).astype(np.int64)], kind="stable")[:size]
                        tokens.append(s[first])
                        keys.append(np.full(size, set_key(s), np.uint64))
                        places.append((len(s) << 32) + np.arange(size, dtype=np.int64))
                    if tokens:
                        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(tokens).view(np.int64)), pa.array(np.concatenate(keys).view(np.int64)), pa.array(np.concatenate(places))], ["token", "key", "place"])

        return map_batches(self.docs.select("t"), cut, "token long, key long, place long")

    def _shared_entries(self) -> DataFrame:
        """(token, key, n, pos, shared) for the prefix shingles that more than one text has, each class once; ``shared`` is how many
        entries the class has here."""
        frequent = self._prefixes().groupBy("token").agg(F.count(F.lit(1)).alias("texts")).where("texts > 1").select("token")
        shared = written(self._prefixes().join(frequent, "token").distinct(), "prefixes")
        by_class = shared.groupBy("key").agg(F.count(F.lit(1)).alias("shared"))
        return shared.join(by_class, "key").select("token", "key", F.shiftright("place", 32).cast("int").alias("n"), F.col("place").bitwiseAND((1 << 32) - 1).cast("int").alias("pos"), "shared")

    def _bounded(self, df: DataFrame) -> DataFrame:
        return F.broadcast(df) if small_enough(df, self.broadcast_rows) else df

    def _texts(self) -> DataFrame:
        """(key, text): one text of each candidate class. Ids may repeat with other texts or be null, so rows are found by id and
        hash of the text together."""
        rows = self._bounded(self.candidates.select("key", "row_id", "row_own"))
        found = self.docs.join(rows, (F.col("own") == F.col("row_own")) & F.col("doc_id").eqNullSafe(F.col("row_id")))
        texts = written(found.select("key", F.col("t").alias("text")), "candidate-texts")
        once = texts.groupBy("key").count().where("count > 1").isEmpty()
        return texts if once else written(texts.dropDuplicates(["key"]), "candidate-texts")

    def _pairs(self, met: DataFrame) -> DataFrame:
        """(a, b, tokens) of pairs (a, n_a, pos_a, b, n_b, pos_b, ...) that pass the length and positional filters. The
        bound of the first common shingle is the highest one, whatever the order of rows."""
        rest = F.least(F.col("n_a") - F.col("pos_a"), F.col("n_b") - F.col("pos_b"))
        p = self.percent
        lengths = (100 * F.least("n_a", "n_b") >= p * F.greatest("n_a", "n_b")) & (F.col("a") != F.col("b"))
        pairs = met.where(lengths).groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        pairs = pairs.agg(F.max(rest).alias("rest"), F.max(F.col("n_a") + F.col("n_b")).alias("sizes"), F.count(F.lit(1)).alias("tokens"))
        return pairs.where(F.col("rest") * (100 + p) >= p * F.col("sizes")).select("a", "b", "tokens")

    @staticmethod
    def _side(entries: DataFrame, c: str, *more: str) -> DataFrame:
        return entries.select("token", F.col("key").alias(c), F.col("n").alias(f"n_{c}"), F.col("pos").alias(f"pos_{c}"), F.col("component").alias(f"c_{c}"), *more)

    def _met_leaders(self, entries: DataFrame, leaders: DataFrame) -> DataFrame:
        """Each entry beside the leader of its shingle: no more rows than entries."""
        lengths = 100 * F.least("n_a", "n_b") >= self.percent * F.greatest("n_a", "n_b")
        return self._side(entries, "a").join(self._side(leaders, "b"), "token").where((F.col("c_a") != F.col("c_b")) & lengths)

    def _met_all(self, entries: DataFrame) -> DataFrame:
        """Entries of a shingle that can belong to a similar pair whose first common shingle it is.

        The smaller set of such a pair has the shingle so early that it could reach the threshold with a set of its own size, so only
        such entries (a, a little over half of a prefix) look for partners, and only for sets as large or larger, by the largest ratio of
        sizes that the threshold allows. Sizes fall in bands of somewhat more than that ratio, so partners are of the same band or
        the next one; band and shingle are the key together. The positional filter holds for each row: the first common shingle has
        the highest bound, so a pair whose rows all fail it has none that passes. A passage that many texts share lies behind their own
        rarer shingles, where it makes nobody look for partners, unless it is so much of the texts that they are similar."""
        p, step = self.percent, float(np.log(101 / self.percent))
        band = F.floor(F.log("n") / step)
        seekers = entries.where((F.col("n") - F.col("pos")) * (100 + p) >= 2 * p * F.col("n"))
        left = self._side(seekers, "a", F.explode(F.array(band, band + 1)).alias("band"))
        right = self._side(entries, "b", band.alias("band"))
        larger = (F.col("n_a") < F.col("n_b")) | ((F.col("n_a") == F.col("n_b")) & (F.col("a") < F.col("b")))
        rest = F.least(F.col("n_a") - F.col("pos_a"), F.col("n_b") - F.col("pos_b"))
        possible = (100 * F.col("n_a") >= p * F.col("n_b")) & (rest * (100 + p) >= p * (F.col("n_a") + F.col("n_b")))
        return left.join(right, ["token", "band"]).where(larger & (F.col("c_a") != F.col("c_b")) & possible)

    def _plausible(self, pairs: DataFrame) -> DataFrame:
        """The pairs whose signatures leave them a chance: the suffix filter, before any text is moved."""
        percent = self.percent

        def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                n, m = batch.column(2).to_pylist(), batch.column(4).to_pylist()
                chance = [not surely_different(x, y, i + j - 2 * required(i, j, percent)) for i, x, j, y in zip(n, batch.column(3).to_pylist(), m, batch.column(5).to_pylist())]
                kept = pa.array(chance, pa.bool_())
                yield pa.RecordBatch.from_arrays([batch.column(0).filter(kept), batch.column(1).filter(kept)], ["a", "b"])

        of = lambda c: self.candidates.select(F.col("key").alias(c), F.col("n_shingles").alias(f"n_{c}"), F.col("signature").alias(f"s_{c}"))
        both = pairs.join(of("a"), "a").join(of("b"), "b").select("a", "b", "n_a", "s_a", "n_b", "s_b")
        return map_batches(both, keep, "a long, b long")

    def _verified(self, pairs: DataFrame, texts: DataFrame) -> DataFrame:
        """(a, b, linked) of each pair."""
        width, percent = self.width, self.percent

        def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for part in slices(batch, 2, 1 << 20):
                    sides = [shingle_sets(part.column(c), width) for c in (2, 3)]
                    linked = [similar(x, y, percent) for x, y in zip(*sides)]
                    yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(linked, pa.bool_())], ["a", "b", "linked"])

        asked = pairs.select(F.col("a").alias("key")).unionByName(pairs.select(F.col("b").alias("key"))).distinct()
        texts = texts.join(self._bounded(written(asked, "asked")), "key", "left_semi")
        of = lambda c: texts.select(F.col("key").alias(c), F.col("text").alias(f"text_{c}"))
        both = pairs.select("a", "b").join(of("a"), "a").join(of("b"), "b").select("a", "b", "text_a", "text_b")
        return map_batches(both, verify, "a long, b long, linked boolean")

    def links(self) -> tuple[DataFrame, DataFrame]:
        """Verified links (a, b) between class keys that connect all similar classes, and the components of keys
        (node, component) that they make."""
        spark = self.docs.sparkSession
        entries, texts = self.entries, self._texts()
        checked = linked = spark.range(0).select(F.col("id").alias("a"), F.col("id").alias("b"))
        groups = spark.range(0).select(F.col("id").alias("node"), F.col("id").alias("component"))
        for turn in range(self.settle_after + 1):
            if turn:
                labelled = entries.join(groups.withColumnRenamed("node", "key"), "key", "left").withColumn("component", F.coalesce("component", "key"))
            else:
                labelled = entries.withColumn("component", F.col("key"))
            # The leader of a shingle: first the class with the most shared entries, for an edited copy's own shingles, being rare, take
            # places in its prefix, while the text that it stems from shares all of them; in later turns another one, by hash.
            by_hash = F.shiftrightunsigned(F.xxhash64("key", F.lit(turn)), 21)
            rank = by_hash if turn else F.shiftleft(F.greatest(F.lit((1 << 20) - 1) - F.col("shared"), F.lit(0)), 43).bitwiseOR(by_hash)
            sides = labelled.groupBy("token", "component").agg(F.min(rank).alias("lead"))
            tokens = sides.groupBy("token").agg(F.count(F.lit(1)).alias("sides"), F.min("lead").alias("lead"))
            tokens = written(tokens.where("sides > 1").select("token", "lead"), "mixed-tokens")
            if tokens.isEmpty():
                break
            settle = turn == self.settle_after  # the same rounds at every size
            # Components only grow, so a shingle that has one component now is settled for good.
            open_entries = written(labelled.join(tokens, "token").select("token", "key", "n", "pos", "shared", "component", "lead"), "open-prefixes")
            entries = open_entries.select("token", "key", "n", "pos", "shared")
            met = self._met_all(open_entries) if settle else self._met_leaders(open_entries, open_entries.where(rank == F.col("lead")))
            pairs = self._pairs(met).join(checked, ["a", "b"], "left_anti")
            if not settle:  # for each class the leader with which it shares most
                ends = pairs.select(F.col("a").alias("k"), "a", "b", "tokens").unionByName(pairs.select(F.col("b").alias("k"), "a", "b", "tokens"))
                pairs = ends.groupBy("k").agg(F.max_by(F.struct("a", "b"), F.struct("tokens", "a", "b")).alias("p")).select("p.a", "p.b").distinct()
            pairs = written(pairs.select("a", "b"), "pairs")
            found = written(self._verified(written(self._plausible(pairs), "plausible-pairs"), texts), "verified")
            checked = checked.unionByName(pairs)
            linked = linked.unionByName(found.where("linked").select("a", "b"))
            groups = written(self._joined(groups, found.where("linked")), "groups")
            if settle:
                break
        return linked, groups

    @staticmethod
    def _joined(groups: DataFrame, links: DataFrame) -> DataFrame:
        """Components after further links: the components they touch are joined, nodes follow theirs."""
        of = lambda c: groups.select(F.col("node").alias(c), F.col("component").alias(f"c_{c}"))
        between = links.join(of("a"), "a", "left").join(of("b"), "b", "left")
        merged = components(between.select(F.coalesce("c_a", "a").alias("a"), F.coalesce("c_b", "b").alias("b")))
        nodes = groups.unionByName(merged.select("node", F.col("node").alias("component"))).dropDuplicates(["node"])
        by = merged.select(F.col("node").alias("component"), F.col("component").alias("to"))
        return nodes.join(by, "component", "left").select("node", F.coalesce("to", "component").alias("component"))

    def report(self) -> DataFrame:
        """(id, n_shingles, component_id, class_key, component_key, text_hash) of every document. A component is named by its smallest id
        and, for those that have none, told apart by ``component_key``; both are null or the row's own for rows without shingles."""
        _, groups = self.links()
        firsts = groups.join(self.classes.withColumnRenamed("key", "node"), "node")
        named = firsts.groupBy("component").agg(F.min("first_id").alias("least"))
        names = groups.join(named, "component").select(F.col("node").alias("key"), "component", "least")
        ids = self.classes.join(names, "key", "left").select("key", F.coalesce("least", "first_id").alias("component_id"), F.coalesce("component", "key").alias("component_key"))
        out = self.sets.join(ids, "key", "left").withColumn("component_id", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")))
        return out.select(F.col("doc_id").alias(self.id_col), "n_shingles", "component_id", F.col("key").alias("class_key"), "component_key", F.col("own").alias("text_hash"))


def packed(counts: np.ndarray) -> bytes:
    return zlib.compress(counts.astype("<u4").tobytes(), 1)


def set_key(s: np.ndarray) -> np.uint64:
    """A 64-bit name of a set; two different sets among n have the same one with a chance of about n * n / 2**65."""
    return mixed(s, MIX_B).sum(dtype=np.uint64) ^ np.uint64(len(s)) if len(s) else np.uint64(0)
