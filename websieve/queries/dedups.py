"""Paragraph dedup: normal form, keys, scopes, policies, lookups and reports."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import normalize
from ..operators import dedup, metrics
from .common import SQL_KEYS, SQL_PARAS, keys, paras, shard, sql_kept, table


def _distinct_paras(spark, sf):
    return paras(spark, sf).select("para").distinct()


def d_strip_accents(spark, sf):
    return _distinct_paras(spark, sf).select("para", normalize.strip_accents(F.lower("para")).alias("plain"))


def d_mask_run(spark, sf):
    return _distinct_paras(spark, sf).select("para", normalize.mask_numbers(F.col("para"), "run").alias("masked"))


def d_mask_each(spark, sf):
    return _distinct_paras(spark, sf).select("para", normalize.mask_numbers(F.col("para"), "each").alias("masked"))


def d_strip_punct(spark, sf):
    return _distinct_paras(spark, sf).select("para", normalize.strip_punct(F.col("para")).alias("plain"))


def d_normalize(spark, sf):
    return _distinct_paras(spark, sf).select("para", normalize.normalize(F.col("para")).alias("norm"))


def d_key64(spark, sf):
    return _distinct_paras(spark, sf).select("para", normalize.key64(normalize.normalize(F.col("para"))).alias("h64"))


def d_shard_index(spark, sf):
    index = dedup.build_index(keys(spark, sf), dedup.Shards(1))
    return index.select(F.col("block_id").alias("shard_id"), dedup.hex_key(F.col("h64")).alias("h64"), dedup.doc_of(F.col("first_pos")).alias("doc_id"), dedup.para_of(F.col("first_pos")).alias("para_no"), "copies")


def _scope(scope, policy="keep_first"):
    def call(spark, sf):
        return dedup.decoded(dedup.survivors(keys(spark, sf), scope, policy))

    return call


def _pairs_table(spark, sf):
    """Each shard refers to the two shards before it, around the circle of 20."""
    shards = table(spark, sf, "documents").select(shard().alias("shard_id")).distinct()
    return shards.select("shard_id", F.explode(F.array(*(F.pmod(F.col("shard_id") + k, F.lit(20)).cast("int") for k in (19, 18)))).alias("ref_shard"))


def d_scope_pairs(spark, sf):
    return dedup.decoded(dedup.survivors(keys(spark, sf), dedup.Pairs(_pairs_table(spark, sf), external="any")))


def d_scope_sample(spark, sf):
    return dedup.decoded(dedup.survivors(keys(spark, sf), dedup.Sample(5)))


def d_lookup_anti(spark, sf):
    """Shards 10 to 19 held against the loaded keys of shards 0 to 9."""
    k = keys(spark, sf)
    index = dedup.build_index(k.where("shard_id < 10"), dedup.All())
    return dedup.lookup(k.where("shard_id >= 10"), index).select("doc_id", "shard_id", "para_no")


def d_bloom_prefilter(spark, sf):
    return dedup.decoded(dedup.prefiltered(keys(spark, sf), keys_per_part=20_000))


def d_cross_snapshot(spark, sf):
    k = keys(spark, sf).withColumn("snapshot", F.pmod("doc_id", F.lit(4)).cast("int"))
    alone = dedup.survivors(k, dedup.Snapshots()).select("pos", F.lit(1).alias("alone"), F.lit(0).alias("together"))
    both = alone.unionByName(dedup.survivors(k, dedup.Snapshots(together=True)).select("pos", F.lit(0).alias("alone"), F.lit(1).alias("together")))
    sums = both.groupBy("pos").agg(F.max("alone").alias("alone"), F.max("together").alias("together"))
    return sums.groupBy(F.pmod(dedup.doc_of(F.col("pos")), F.lit(4)).cast("int").alias("snapshot")).agg(F.sum("alone").alias("kept_alone"), F.sum("together").alias("kept_together"))


def d_documents_after(spark, sf):
    """Flagship of dedup: documents that keep text after dedup over the whole snapshot."""
    docs = dedup.documents(dedup.survivors(keys(spark, sf), dedup.All()), table(spark, sf, "documents"))
    return docs.select("doc_id", F.sha2("text", 256).alias("digest"), F.size("para_nos").cast("long").alias("n_paras"), "kept_chars", "orig_chars")


def d_boilerplate_topk(spark, sf):
    return metrics.boilerplate(keys(spark, sf), 20)


def d_crosslang_paras(spark, sf):
    return metrics.cross_language(keys(spark, sf))


def d_key_collisions(spark, sf):
    return metrics.key_collisions(paras(spark, sf))


CALLS = {
    f.__name__: f
    for f in (d_strip_accents, d_mask_run, d_mask_each, d_strip_punct, d_normalize, d_key64, d_shard_index, d_scope_pairs, d_scope_sample, d_lookup_anti, d_bloom_prefilter, d_cross_snapshot, d_documents_after, d_boilerplate_topk, d_crosslang_paras, d_key_collisions)
} | {f"d_scope_{n}": _scope(dedup.Shards(n)) for n in (1, 2, 5, 10, 20, 50, 100)} | {"d_scope_all": _scope(dedup.All()), "d_keep_first": _scope(dedup.Shards(5)), "d_drop_all": _scope(dedup.Shards(5), "drop_all")}

_ONCE = f"WITH {SQL_PARAS}, p AS (SELECT DISTINCT para FROM paras)"

ORACLES = {
    "d_strip_accents": f"{_ONCE} SELECT para, strip_accents(lower(para)) AS plain FROM p",
    "d_mask_run": rf"{_ONCE} SELECT para, regexp_replace(para, '\p{{Nd}}+', '0', 'g') AS masked FROM p",
    "d_mask_each": rf"{_ONCE} SELECT para, regexp_replace(para, '\p{{Nd}}', '0', 'g') AS masked FROM p",
    "d_strip_punct": rf"{_ONCE} SELECT para, regexp_replace(para, '\p{{P}}', '', 'g') AS plain FROM p",
    "d_normalize": f"WITH {SQL_KEYS} SELECT DISTINCT para, norm FROM keys",
    "d_key64": f"WITH {SQL_KEYS} SELECT DISTINCT para, h64 FROM keys",
    "d_shard_index": f"WITH {sql_kept('shard_id')} SELECT shard_id, h64, doc_id, para_no, copies FROM ranked WHERE nth = 1",
    "d_scope_all": f"WITH {sql_kept('1')} SELECT doc_id, shard_id, para_no FROM ranked WHERE nth = 1",
    "d_bloom_prefilter": f"WITH {sql_kept('1')} SELECT doc_id, shard_id, para_no FROM ranked WHERE nth = 1",
    "d_keep_first": f"WITH {sql_kept('shard_id // 5')} SELECT doc_id, shard_id, para_no FROM ranked WHERE nth = 1",
    "d_drop_all": f"WITH {sql_kept('shard_id // 5')} SELECT doc_id, shard_id, para_no FROM ranked WHERE copies = 1",
    "d_scope_pairs": f"""
WITH {sql_kept('shard_id')}
SELECT doc_id, shard_id, para_no FROM ranked r WHERE nth = 1
AND NOT EXISTS (SELECT 1 FROM keys k WHERE k.h64 = r.h64 AND k.shard_id IN ((r.shard_id + 19) % 20, (r.shard_id + 18) % 20))""",
    "d_lookup_anti": f"WITH {SQL_KEYS} SELECT doc_id, shard_id, para_no FROM keys k WHERE shard_id >= 10 AND NOT EXISTS (SELECT 1 FROM keys x WHERE x.shard_id < 10 AND x.h64 = k.h64)",
    "d_cross_snapshot": f"""
WITH {SQL_KEYS}, a AS (
  SELECT doc_id % 4 AS s, row_number() OVER (PARTITION BY doc_id % 4, h64 ORDER BY shard_id, doc_id, para_no) AS own,
         row_number() OVER (PARTITION BY h64 ORDER BY shard_id, doc_id, para_no) AS every FROM keys)
SELECT s::INTEGER AS snapshot, count(*) FILTER (own = 1) AS kept_alone, count(*) FILTER (every = 1) AS kept_together FROM a GROUP BY s""",
    "d_documents_after": f"""
WITH {sql_kept('1')}, d AS (
  SELECT doc_id, string_agg(para, chr(10) ORDER BY para_no) AS text, count(*) AS n_paras FROM ranked WHERE nth = 1 GROUP BY doc_id)
SELECT doc_id, sha256(d.text) AS digest, n_paras, length(d.text)::BIGINT AS kept_chars, length(o.text)::BIGINT AS orig_chars
FROM d JOIN documents o USING (doc_id)""",
    "d_boilerplate_topk": f"""
WITH {SQL_KEYS} SELECT h64, count(*) AS copies, count(DISTINCT doc_id) AS docs FROM keys GROUP BY h64 ORDER BY copies DESC, h64 LIMIT 20""",
    "d_crosslang_paras": f"""
WITH {SQL_KEYS} SELECT h64, count(DISTINCT lang) AS n_langs, count(DISTINCT doc_id) AS docs, string_agg(DISTINCT lang, ',' ORDER BY lang) AS langs
FROM keys GROUP BY h64 HAVING count(DISTINCT lang) > 1""",
    "d_key_collisions": f"WITH {SQL_KEYS} SELECT h64, count(DISTINCT norm) AS forms FROM keys GROUP BY h64 HAVING count(DISTINCT norm) > 1",
} | {f"d_scope_{n}": f"WITH {sql_kept(f'shard_id // {n}')} SELECT doc_id, shard_id, para_no FROM ranked WHERE nth = 1" for n in (1, 2, 5, 10, 20, 50, 100)}
