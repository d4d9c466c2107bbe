"""Connected components of a link table: by union-find in one task while links are few, else by alternating star contractions on DataFrames.

Up to ONE_TASK links (16 bytes each, counted as they are written) a task joins their classes; that saves the dozens of small shuffles that contractions take, and the
task's memory is bounded by the constant. Beyond it no task holds more than its share. A large star hangs every larger neighbour of a node on the node's smallest neighbour; a small star hangs the smaller
ones. Each keeps the components and shortens the trees; the loop ends when a round changes nothing. Minima are
aggregated before the shuffle and joined back, so no node's neighbours are ever gathered in a list.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waypoint.llm.store import counted, kept

#: Links that one task may join.
ONE_TASK = 1_000_000


def union_find(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct nodes of the links, rising, and the smallest node that each reaches."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while True:
        x, y = root[a], root[b]
        low, high = np.minimum(x, y), np.maximum(x, y)
        open_ = low < high
        if not open_.any():
            return nodes, nodes[root]
        np.minimum.at(root, high[open_], low[open_])
        while (up := root[root]).tobytes() != root.tobytes():
            root = up


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    if parts:
        nodes, least = union_find(*(np.concatenate(x) for x in zip(*parts, strict=True)))
        yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(least)], names=["node", "component"])


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """``edges`` (u, v) with u > v, each once."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))) if large else edges
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    joined = both.join(least, "u")
    if large:
        out = joined.filter(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return out.filter(F.col("u") != F.col("v")).distinct()


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """``node, component`` (smallest node reachable) of every node that occurs in ``links`` (u, v) with a different partner."""
    edges, n = counted(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u <> v").distinct(), "cc")
    if n <= ONE_TASK:
        return edges.coalesce(1).mapInArrow(_joined, "node long, component long")
    for _ in range(rounds):
        edges = kept(_star(_star(edges, True), False), "cc")
        ends = edges.select(F.col("u").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("root")).unionByName(edges.select(F.col("v").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("root")))
        # stars alone: every node hangs on one root, and no root hangs on another
        if ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("root").alias("root")).filter("up > 1 or (up = 1 and root = 1)").isEmpty():
            break
    else:
        raise RuntimeError("components did not settle")
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
