"""Connected components of a graph given as a DataFrame of edges, for graphs that fit no single machine."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, own_exchange, tidy

#: A graph of so many edges (two longs each, 32 MB) is finished by one task; a larger one takes turns until it is as small.
LOCAL_EDGES = 2_000_000


def _signature(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("a", "b")), F.lit(0))).first()
    return tuple(row)


def forest_of(left: np.ndarray, right: np.ndarray, n: int) -> np.ndarray:
    """The least member of each of n nodes' component, by passing minima along the links until they rest."""
    root = np.arange(n)
    while True:
        new = root.copy()
        np.minimum.at(new, left, root[right])
        np.minimum.at(new, right, root[left])
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _finished(edges: DataFrame) -> DataFrame:
    """(node, root) of a graph that one task holds."""

    def run(batches: Iterator[pa.RecordBatch]):
        held = [tuple(batch.column(k).to_numpy() for k in (0, 1)) for batch in batches]
        if held:
            a, b = (np.concatenate(x) for x in zip(*held))
            values, number = np.unique(np.concatenate((a, b)), return_inverse=True)
            root = forest_of(number[: len(a)], number[len(a) :], len(values))
            for i in range(0, len(values), 65536):
                yield pa.RecordBatch.from_arrays([pa.array(values[i : i + 65536]), pa.array(values[root[i : i + 65536]])], names=["node", "root"])

    return edges.select("a", "b").coalesce(1).mapInArrow(run, "node long, root long")


def components(edges: DataFrame, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """(node, root) for each node of edges (a, b: long), root the smallest node of its component.

    A graph of at most local_edges is left to one task, which spares the driver dozens of jobs. A larger one goes in turns:
    Turns of two steps until nothing changes: every node's larger neighbours, then its smaller ones, are tied to the
    smallest node it sees. Minima are aggregated before the shuffle and the joins are plain, so that a node with very many
    neighbours is split. Each turn's edges are checkpointed. Loops (a = b) are no edges; no edges give no rows.
    """
    now = cut(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    seen = _signature(now)
    while seen[0] > local_edges:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(own_exchange(least, "a"), "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(own_exchange(least, "a"), "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").unionByName(least.select("a", F.col("m").alias("b"))).distinct()
        now = cut(small)
        tidy(now.sparkSession)
        fresh = _signature(now)
        if fresh == seen:
            break
        seen = fresh
    else:
        return _finished(now)
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
