"""Connected components of a table of links: in one task while links are few, as joins beyond a checked number."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, small_enough, written


def components(links: DataFrame, one_task_links: int = 500_000) -> DataFrame:
    """(node, component): the smallest node that links (a, b) reach, for every node that has a link.

    Up to ``one_task_links`` links (16 bytes each) are joined by one task; the result is the same either way.
    """
    links = written(links.select("a", "b").where("a <> b").distinct(), "links")
    if small_enough(links, one_task_links):
        return map_batches(links.coalesce(1), join_all, "node long, component long")
    return components_by_joins(links)


def join_all(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parent: dict[int, int] = {}

    def find(x: int) -> int:
        root = x
        while parent.setdefault(root, root) != root:
            root = parent[root]
        while parent[x] != root:
            parent[x], x = root, parent[x]
        return root

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            a, b = find(a), find(b)
            parent[max(a, b)] = min(a, b)
    nodes = list(parent)
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(np.fromiter(map(find, nodes), np.int64, len(nodes)))], ["node", "component"])


def components_by_joins(links: DataFrame) -> DataFrame:
    """The same by rounds of joins, for any number of links.

    Each round takes the smallest label among a node's neighbours and then the label of that label, so
    the reach doubles; a node with very many links costs one partial minimum for each task. Labels are written to the
    shared folder each round, which cuts the lineage.
    """
    edges = written(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct(), "edges")
    labels = written(edges.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("least")).select("node", F.least("node", "least").alias("component"), F.lit(True).alias("changed")), "labels")
    while not labels.where("changed").isEmpty():
        near = edges.join(labels.select(F.col("node").alias("b"), F.col("component").alias("c")), "b").groupBy(F.col("a").alias("node")).agg(F.min("c").alias("near"))
        met = labels.select("node", F.col("component").alias("old")).join(near, "node").withColumn("mid", F.least("old", "near"))
        jump = labels.select(F.col("node").alias("mid"), F.col("component").alias("far"))
        labels = written(met.join(jump, "mid").select("node", F.least("mid", "far").alias("component"), (F.least("mid", "far") < F.col("old")).alias("changed")), "labels")
    return labels.select("node", "component")
