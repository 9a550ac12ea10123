"""Connected components of an edge table by alternating star contraction.

Each round moves every node's larger neighbours, then its smaller ones, to the
least neighbour, until the edges are stars around the least node of each
component. Before the first round and after each every task replaces the edges it holds, some at a time, by a
spanning star of each of their components. Rounds read and write the shared folder; nothing is collected but the
count and checksum that tell whether a round changed anything.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise


def least_labels(u: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
    """For each of ``n`` places the least place of its component under the links (u, v)."""
    parent = np.arange(n)
    while len(u):
        a, b = parent[u], parent[v]
        apart = a != b
        u, v, a, b = u[apart], v[apart], a[apart], b[apart]
        np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))
        while (parent[parent] != parent).any():
            parent = parent[parent]
    return parent


def _stars(edges: DataFrame) -> DataFrame:
    """Fewer edges (u, v), u > v, with the same components."""

    def contract(held: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        u, v = (np.concatenate(x) for x in zip(*held, strict=True))
        nodes, at = np.unique(np.append(u, v), return_inverse=True)
        label = least_labels(at[: len(u)], at[len(u) :], len(nodes))
        moved = np.flatnonzero(label != np.arange(len(nodes)))
        return pa.RecordBatch.from_arrays([pa.array(nodes[moved]), pa.array(nodes[label[moved]])], ["u", "v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            rows += batch.num_rows
            if rows > HELD:
                yield contract(held)
                held, rows = [], 0
        if held:
            yield contract(held)

    return edges.mapInArrow(run, "u bigint, v bigint")


#: Edges that a task contracts at once.
HELD = 1 << 19
#: Parts into which the neighbours of a node are dealt: the root of a large star is no single key.
SALTS = 8


def _least(pairs: DataFrame) -> DataFrame:
    """(u, v) with the least of v and u itself for each u beside every v."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("m", "u"))
    dealt = least.withColumn("salt", F.explode(F.array(*map(F.lit, range(SALTS)))))
    salt = F.pmod(F.xxhash64("v"), F.lit(SALTS)).cast("int")
    return pairs.withColumn("salt", salt).join(dealt, ["u", "salt"]).drop("salt")


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def star_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of ``edges(u, v)`` (longs, no nulls); the component is its least node.

    Loops, repeated and reversed edges are harmless; a node that only has loops is left out.
    """
    # the exchange of distinct parts this worker from the one that has made the links: a task holds one at a time
    now = materialise(_stars(edges.where("u <> v").select("u", "v").distinct()), "edges")
    state = _state(now)
    for _ in range(max_rounds):
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _least(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        found = _least(large)
        small = found.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(found.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        now = materialise(_stars(small), "edges")  # once a round: the next one reads its edges several times
        before, state = state, _state(now)
        if state == before:
            break
    else:
        raise RuntimeError("components did not settle")
    roots = now.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)
