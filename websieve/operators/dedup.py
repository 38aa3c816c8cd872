"""Paragraph dedup with a selectable scope of comparison.

Only keys and packed positions are shuffled; text meets the surviving positions by document id. The index of a scope
holds for each (block, key) the first position and the number of copies. Both are partial aggregates of longs, so a
paragraph that millions of pages share costs one row for each task.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.normalize import NormOptions, key64, normalize
from .paragraphs import doc_of, para_of, pick_lines, shard_of


MOST_PAIRS = 1_000_000  # pairs of shards that are broadcast; more are joined by a shuffle


@dataclass(frozen=True)
class Shards:
    """Disjoint blocks of n consecutive shards."""

    n: int = 1

    def block(self) -> Column:
        return F.floor(F.col("shard_id") / self.n).cast("int")


@dataclass(frozen=True)
class All:
    """One block: the whole snapshot."""

    def block(self) -> Column:
        return F.lit(0)


@dataclass(frozen=True)
class Snapshots:
    """One block for each snapshot, or one over all with ``together``. Paragraphs carry ``snapshot``."""

    together: bool = False

    def block(self) -> Column:
        return F.lit(0) if self.together else F.col("snapshot").cast("int")


@dataclass(frozen=True)
class Pairs:
    """Any table (shard_id, ref_shard) of shards and the shards each is compared with. ``external`` says what a hit in
    another shard needs: "earlier": the other shard comes before this one; "any": nothing more."""

    table: DataFrame
    external: str = "earlier"


@dataclass(frozen=True)
class Sample:
    """Each shard against itself and n others, chosen by hash."""

    n: int
    seed: int = 0

    def pairs(self, shards: DataFrame) -> Pairs:
        a, b = shards.select("shard_id").distinct(), shards.select(F.col("shard_id").alias("ref_shard")).distinct()
        both = a.join(b, F.col("shard_id") != F.col("ref_shard"))  # shards are few
        order = F.array_sort(F.collect_list(F.struct(F.xxhash64("shard_id", "ref_shard", F.lit(self.seed)).alias("h"), "ref_shard")))
        chosen = both.groupBy("shard_id").agg(F.slice(order, 1, self.n).alias("c"))
        return Pairs(chosen.select("shard_id", F.explode("c.ref_shard").alias("ref_shard")))


def keyed(paras: DataFrame, opts: NormOptions = NormOptions()) -> DataFrame:
    """Paragraphs reduced to keys: the text column is replaced by ``h64`` (long) and ``n_chars``."""
    rest = [c for c in paras.columns if c != "para"]
    return paras.select(*rest, key64(normalize(F.col("para"), opts), "long").alias("h64"), F.length("para").cast("long").alias("n_chars"))


def hex_key(h64: Column) -> Column:
    return F.lower(F.lpad(F.hex(h64), 16, "0"))


def build_index(keys: DataFrame, scope: Shards | All | Snapshots = Shards(1)) -> DataFrame:
    """(block_id, h64, first_pos, copies)."""
    return keys.groupBy(scope.block().alias("block_id"), "h64").agg(F.min("pos").alias("first_pos"), F.count(F.lit(1)).alias("copies"))


def write_index(index: DataFrame, path: str, partitions: int | None = None) -> None:
    """The index as Parquet, clustered by key so that readers prune by key range."""
    ranged = index.repartitionByRange(partitions, "h64") if partitions else index.repartitionByRange("h64")
    ranged.sortWithinPartitions("h64").write.mode("overwrite").parquet(path)


def survivors(keys: DataFrame, scope: Shards | All | Snapshots | Pairs | Sample = Shards(1), policy: str = "keep_first") -> DataFrame:
    """(pos) of every paragraph that stays.

    With blocks, the first positions of the index are the survivors; no join back is needed. With a pairs table, a key
    of a shard is held against the same key in the shards it refers to.
    """
    if isinstance(scope, Sample):
        scope = scope.pairs(keys)
    if isinstance(scope, Pairs):
        return _survivors_by_pairs(keys, scope, policy)
    index = build_index(keys, scope)
    index = index.where("copies = 1") if policy == "drop_all" else index
    return index.select(F.col("first_pos").alias("pos"))


def _survivors_by_pairs(keys: DataFrame, scope: Pairs, policy: str) -> DataFrame:
    own = keys.groupBy("shard_id", "h64").agg(F.min("pos").alias("pos"), F.count(F.lit(1)).alias("copies"))
    refs = scope.table.where("shard_id <> ref_shard")
    if scope.external == "earlier" and policy == "keep_first":
        refs = refs.where("ref_shard < shard_id")
    few = refs.limit(MOST_PAIRS + 1).count() <= MOST_PAIRS
    wanted = own.select("shard_id", "h64").join(F.broadcast(refs) if few else refs, "shard_id")
    seen = own.select(F.col("shard_id").alias("ref_shard"), "h64")
    hit = wanted.join(seen, ["ref_shard", "h64"], "left_semi").select("shard_id", "h64").distinct()
    own = own.where("copies = 1") if policy == "drop_all" else own
    return own.join(hit, ["shard_id", "h64"], "left_anti").select("pos")


def lookup(keys: DataFrame, index: DataFrame) -> DataFrame:
    """The plain set lookup: paragraphs whose key is in no given index, all of them."""
    return keys.join(index.select("h64"), "h64", "left_anti")


def decoded(positions: DataFrame) -> DataFrame:
    """(doc_id, shard_id, para_no) of packed positions."""
    return positions.select(doc_of(F.col("pos")).alias("doc_id"), shard_of(F.col("pos")).alias("shard_id"), para_of(F.col("pos")).alias("para_no"))


def documents(positions: DataFrame, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, min_chars: int = 1, keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep, text, para_nos, kept_chars, orig_chars) of documents with enough text left. Only numbers of surviving
    paragraphs travel; each document's text is filtered where it is."""
    nos = positions.groupBy(doc_of(F.col("pos")).alias(id_col)).agg(F.sort_array(F.collect_list(para_of(F.col("pos")))).alias("para_nos"))
    rows = docs.select(id_col, *keep, F.col(text_col).alias("__text")).join(nos, id_col)
    rows = rows.select(id_col, *keep, pick_lines(F.col("__text"), F.col("para_nos")).alias("text"), "para_nos", F.length("__text").cast("long").alias("orig_chars"))
    return rows.withColumn("kept_chars", F.length("text").cast("long")).where(F.col("kept_chars") >= min_chars)


class BloomFilter:
    """Bit arrays over key ranges, built where the keys are. ``maybe`` keeps every key that was added; of others about
    ``2 ** -hashes`` pass, so an exact step has to follow."""

    def __init__(self, keys: DataFrame, *, bits_per_key: int = 10, hashes: int = 4, keys_per_part: int = 2_000_000):
        import pyarrow as pa

        self.hashes = hashes
        self.parts = max(1, -(-keys.count() // keys_per_part))
        size = 8 * max(1, bits_per_key * keys_per_part // 8)
        self.size = size
        parts = self.parts

        def build(table: pa.Table) -> pa.Table:
            import numpy as np

            bits = np.zeros(size, bool)
            for x in _probes(table.column("h64").to_numpy(), size, hashes):
                bits[x] = True
            part = table.column("part")[0].as_py()
            return pa.table({"part": [part], "bits": pa.array([np.packbits(bits).tobytes()], pa.binary())})

        dealt = keys.select("h64", F.pmod("h64", F.lit(parts)).alias("part"))
        self.table = dealt.groupBy("part").applyInArrow(build, "part long, bits binary")

    def maybe(self, keys: DataFrame) -> DataFrame:
        """Rows of ``keys`` whose h64 may have been added."""
        import pyarrow as pa

        size, hashes = self.size, self.hashes
        fields = keys.schema

        def probe(group: pa.Table, bits: pa.Table) -> pa.Table:
            import numpy as np

            if not group.num_rows or not bits.num_rows:
                return group.drop_columns(["part"]).slice(0, 0)
            packed = np.frombuffer(bits.column("bits")[0].as_py(), np.uint8)
            hit = np.ones(group.num_rows, bool)
            for x in _probes(group.column("h64").to_numpy(), size, hashes):
                hit &= (packed[x >> 3] >> (7 - (x & 7)) & 1).astype(bool)
            return group.drop_columns(["part"]).filter(pa.array(hit))

        dealt = keys.withColumn("part", F.pmod("h64", F.lit(self.parts)))
        return dealt.groupBy("part").cogroup(self.table.groupBy("part")).applyInArrow(probe, fields)


def _probes(h64, size: int, hashes: int):
    import numpy as np

    x = h64.astype(np.int64).view(np.uint64)
    for k in range(hashes):
        y = (x ^ np.uint64(0x9E3779B97F4A7C15 * (k + 1) & (1 << 64) - 1)) * np.uint64(0xBF58476D1CE4E5B9)
        yield ((y ^ (y >> np.uint64(32))) % np.uint64(size)).astype(np.int64)


def prefiltered(keys: DataFrame, scope: Shards | All = All(), **bloom) -> DataFrame:
    """Survivors by keep-first with a Bloom filter of the repeated keys: keys that surely occur once skip the exact
    step, which runs on the others."""
    repeated = build_index(keys, scope).where("copies > 1").select("h64").distinct()
    suspects = BloomFilter(repeated, **bloom).maybe(keys)
    return keys.join(suspects.select("pos"), "pos", "left_anti").select("pos").unionByName(survivors(suspects, scope))
