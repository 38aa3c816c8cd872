"""Exact top-k search by inner product with one KD-tree for each shard of the candidates.

Candidates are dealt by id to shards of bounded size; each shard becomes a tree of median splits whose nodes
keep tight bounding boxes. A box bounds the inner product of a query with every vector inside it, so a
best-first traversal visits boxes by falling bound and stops when no bound reaches the query's current kth
score. Blocks of queries first visit one shard; the kth scores found there go along to all other shards,
which then open only boxes that can still matter. The work is in exact integers throughout.

The stated queries meet all shards, in blocks; a task holds one shard and one block at a time.

Edge cases: vectors that are null, empty, or hold null or non-finite components take no part; vectors of
different lengths do not meet; rows with the query's own id are not its candidates; ties go to the smaller
id, and repeated rows of an id are results of their own; null ids take no part; no candidates, no rows.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import workers_see_package, written

LEAF = 128


@dataclass
class Node:
    low: np.ndarray
    high: np.ndarray
    first: int
    last: int
    children: tuple["Node", "Node"] | None = None


class KdTree:
    """Vectors in leaf order under boxes; ``points`` and ``boxes`` hold exact integers as float64."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, leaf: int = LEAF):
        order = np.arange(len(ids))
        self.leaf, self.order, self.source = leaf, order, vectors
        self.root = self._build(0, len(ids))
        self.ids, self.points = ids[self.order], np.ascontiguousarray(vectors[self.order], dtype=np.float64)
        del self.source

    def _build(self, first: int, last: int) -> Node:
        own = self.source[self.order[first:last]]
        low, high = own.min(axis=0), own.max(axis=0)
        node = Node(low.astype(np.float64), high.astype(np.float64), first, last)
        axis = int(np.argmax(high - low))
        if last - first > self.leaf and high[axis] > low[axis]:
            middle = (last - first) // 2
            self.order[first:last] = self.order[first:last][np.argpartition(own[:, axis], middle, kind="introselect")]
            node.children = (self._build(first, first + middle), self._build(first + middle, last))
        return node

    def search(self, queries: np.ndarray, own_ids: np.ndarray, k: int, floor: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """For each query the (scores, ids) of up to k best candidates whose score is at least ``floor``."""
        positive, negative = np.maximum(queries, 0.0), np.minimum(queries, 0.0)
        out = []
        for q in range(len(queries)):
            out.append(self._one(queries[q], positive[q], negative[q], own_ids[q], k, floor[q]))
        return out

    def _one(self, query: np.ndarray, positive: np.ndarray, negative: np.ndarray, own_id: int, k: int, floor: float) -> tuple[np.ndarray, np.ndarray]:
        def bound(node: Node) -> float:
            return float(positive @ node.high + negative @ node.low)

        scores, ids, kth = np.empty(0), np.empty(0, np.int64), floor
        waiting, number = [(-bound(self.root), 0, self.root)], 1
        while waiting and -waiting[0][0] >= kth:
            _, _, node = heapq.heappop(waiting)
            if node.children:
                for child in node.children:
                    if (b := bound(child)) >= kth:
                        heapq.heappush(waiting, (-b, number, child))
                        number += 1
                continue
            got, whose = self.points[node.first : node.last] @ query, self.ids[node.first : node.last]
            fit = (got >= kth) & (whose != own_id)
            if fit.any():
                scores, ids = np.concatenate([scores, got[fit]]), np.concatenate([ids, whose[fit]])
                if len(scores) > k:
                    best = np.lexsort((ids, -scores))[:k]
                    scores, ids = scores[best], ids[best]
                if len(scores) == k:
                    kth = max(kth, float(scores.min()))
        return scores, ids


def usable(vectors: DataFrame, id_col: str, vector_col: str, scale: int) -> DataFrame:
    """(id, v: whole numbers, dim): floor(scale * x) of every vector that takes part."""
    v = F.col(vector_col).cast("array<double>")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    whole = F.transform(v, lambda x: F.floor(x * F.lit(float(scale))).cast("long"))
    return vectors.where(F.col(id_col).isNotNull() & v.isNotNull() & (F.size(v) > 0) & finite).select(F.col(id_col).alias("id"), whole.alias("v"), F.size(v).alias("dim"))


def matrix(column: pd.Series) -> np.ndarray:
    return np.vstack(column.to_list()).astype(np.float64)


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", *, scale: int = 256, shard_rows: int = 16_384, block_rows: int = 1024) -> DataFrame:
    """(query_id, rank, id, score) of the k highest inner products of each query. ``is_query`` is a condition on
    the column named by ``id_col``."""
    workers_see_package(vectors.sparkSession)
    rows = written(usable(vectors, id_col, vector_col, scale), "vectors")
    # Names of their own: both sides of the meetings below descend from the same table.
    queries = rows.withColumnRenamed("id", id_col).where(is_query).select(F.col(id_col).alias("query_id"), F.col("v").alias("query"), F.col("dim").alias("length"))
    shards = {r.dim: -(-r.n // shard_rows) for r in rows.groupBy("dim").agg(F.count(F.lit(1)).alias("n")).collect()}
    blocks = {r.length: -(-r.n // block_rows) for r in queries.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}

    def number_of(by: dict[int, int], length: str) -> Column:
        return F.coalesce(F.create_map(*(F.lit(x) for pair in by.items() for x in pair))[F.col(length)], F.lit(1)) if by else F.lit(1)

    def dealt(key: str, number: Column) -> Column:
        return F.pmod(F.xxhash64(key), number).cast("int")

    candidates = rows.withColumn("shard", dealt("id", number_of(shards, "dim")))
    queries = queries.withColumn("block", dealt("query_id", number_of(blocks, "length")))
    shards_met = number_of(shards, "length")
    home = F.pmod(F.col("block"), shards_met).cast("int")

    def visit(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        found = []
        if len(left) and len(right):
            tree = KdTree(left["id"].to_numpy(np.int64), matrix(left["v"]))
            for _, block in right.groupby("block", sort=False):
                asked = block["query_id"].to_numpy(np.int64)
                for q, (scores, ids) in zip(asked, tree.search(matrix(block["query"]), asked, k, block["floor"].to_numpy(np.float64))):
                    found += [(q, i, int(s)) for s, i in zip(scores, ids)]
        return pd.DataFrame(found, columns=["query_id", "id", "score"]).astype("int64")

    def meet(who: DataFrame) -> DataFrame:
        return candidates.groupBy("dim", "shard").cogroup(who.groupBy("length", "visited")).applyInPandas(visit, "query_id long, id long, score long")

    lowest = F.lit(float("-inf"))
    first = written(meet(queries.withColumn("visited", home).withColumn("floor", lowest)), "nearest-at-home")
    kth = first.groupBy("query_id").agg(F.sort_array(F.collect_list("score"), asc=False).alias("s")).select("query_id", F.when(F.size("s") >= k, F.element_at("s", k)).cast("double").alias("floor"))
    others = queries.join(kth, "query_id", "left").withColumn("floor", F.coalesce("floor", lowest))
    others = others.withColumn("visited", F.explode(F.filter(F.sequence(F.lit(0), shards_met - 1), lambda s: s != home)))
    found = first.unionByName(meet(others))
    best = F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), F.col("id").alias("i")))), 1, k)
    ranked = found.groupBy("query_id").agg(best.alias("best")).select("query_id", F.posexplode("best").alias("at", "hit"))
    return ranked.select("query_id", (F.col("at") + 1).alias("rank"), F.col("hit.i").alias(id_col), (-F.col("hit.s")).alias("score"))
