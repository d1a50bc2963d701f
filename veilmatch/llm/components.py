"""Connected components by alternating star contraction, in joins and grouped minima.

A graph of at most ``DIRECT`` links, counted before, is finished by one task on the executors instead: its memory has
that bound, and a small graph takes no rounds of jobs. Results are equal.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilmatch.llm.common import durable, released, tidy

DIRECT = 1 << 20  # links of 16 bytes


def least_nodes(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All nodes of the links (u, v), ascending, and the smallest node of the component of each."""
    nodes, at = np.unique(np.concatenate((u, v)), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    parent = np.arange(len(nodes))
    while True:
        low, high = np.minimum(parent[a], parent[b]), np.maximum(parent[a], parent[b])
        open_ = low != high
        if not open_.any():
            return nodes, nodes[parent]
        a, b = a[open_], b[open_]
        np.minimum.at(parent, high[open_], low[open_])
        while True:  # every node points at its root again
            further = parent[parent]
            if np.array_equal(further, parent):
                break
            parent = further


def _direct(edges: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [[c.to_numpy() for c in batch.columns] for batch in batches if batch.num_rows]
        if held:
            nodes, labels = least_nodes(*(np.concatenate(c) for c in zip(*held)))
            yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(labels)], names=["node", "label"])

    return durable(edges.coalesce(1).mapInArrow(tidy(run), "node long, label long"))


def components(links: DataFrame, rounds: int = 60, direct: int = DIRECT) -> DataFrame:
    """Links (a, b) of longs to (node, label), label the smallest node of the component.

    Nodes without a link have no row. Each round points every node's larger neighbours and
    then its smaller ones at the least neighbour, and is written to the shared checkpoint
    folder; rounds grow with the logarithm of the longest path.
    """
    edges = durable(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    if edges.count() <= direct:
        return _direct(edges)
    last = None
    for _ in range(rounds):
        # Large star: every neighbour above a node moves to the least of its neighbourhood.
        both = edges.union(edges.select(F.col("v"), F.col("u"))).toDF("u", "v")
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        # Small star: every neighbour below a node, and the node, move to its least neighbour.
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).distinct()
        edges = released(durable(small))
        state = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")).cast("string").alias("s")).first()
        if state == last:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("label")).union(edges.select(F.col("v"), F.col("v")).distinct()).toDF("node", "label")
        last = state
    raise RuntimeError("components did not settle")
