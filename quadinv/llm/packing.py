"""Best-fit packing under conflicts: documents into bins of a fixed number of tokens (words).

A bin never holds two documents of one duplicate cluster, nor more than `per_source` of one source. Every bin carries bitmaps:
one of the clusters that it holds, and for each k one of the sources that it holds at least k times. Bins are ordered by what
room they have left; for a document, largest first, the search starts at the least sufficient room and goes on to the next
until it meets a bin without conflict, the tightest compatible one; only where there is none a new bin is opened. The search
has no limit of bins tried. Documents are packed in independent groups of about `group_docs` that a hash deals out, so that a
hot source or cluster is spread evenly and no task grows with the input.

A document longer than a bin fills whole bins by itself and only its rest is packed with others. Documents of no words
(null and empty texts too) are returned without a bin. Ties in length go by id, then by cluster, so the same rows give the
same bins; repeated rows are copies and so never share a bin. A null source is a source like any other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

CAPACITY = 2048
GROUP_DOCS = 2048
PER_SOURCE = 3
WORD = r"[^\x20\x09-\x0D]+"


class Bins:
    """Open bins of one group, ordered by residual room."""

    def __init__(self, capacity: int, per_source: int):
        self.capacity, self.per_source = capacity, per_source
        self.room: list[dict[int, None]] = [{} for _ in range(capacity + 1)]  # bins by residual, oldest first
        self.present = 0  # bitmap of residuals that some bin has
        self.left: list[int] = []
        self.clusters: list[int] = []
        self.sources: list[list[int]] = []

    def _file(self, b: int, residual: int) -> None:
        self.left[b] = residual
        self.room[residual][b] = None
        self.present |= 1 << residual

    def place(self, size: int, source: int, cluster: int | None) -> tuple[int, int]:
        """(bin, offset) for a piece; cluster is None for a document that no other of the group equals."""
        mark = 1 << source
        same = 0 if cluster is None else 1 << cluster
        higher = self.present >> size
        residual = size - 1
        while higher:
            step = (higher & -higher).bit_length()
            residual += step
            higher >>= step
            for b in self.room[residual]:
                if not (self.clusters[b] & same or self.sources[b][-1] & mark):
                    del self.room[residual][b]
                    if not self.room[residual]:
                        self.present &= ~(1 << residual)
                    return self._put(b, residual, size, mark, same)
        self.left.append(self.capacity)
        self.clusters.append(0)
        self.sources.append([0] * self.per_source)
        return self._put(len(self.left) - 1, self.capacity, size, mark, same)

    def _put(self, b: int, residual: int, size: int, mark: int, same: int) -> tuple[int, int]:
        self.clusters[b] |= same
        planes = self.sources[b]
        for k in range(self.per_source):  # into the first plane that lacks the source
            if not planes[k] & mark:
                planes[k] |= mark
                break
        self._file(b, residual - size)
        return b, self.capacity - residual


def packed_group(sizes: np.ndarray, sources: list, clusters: np.ndarray, capacity: int, per_source: int) -> list[tuple[int, int]]:
    """(bin, offset) for each piece of a group, in the order given."""
    names: dict = {}
    values, count = np.unique(clusters, return_counts=True)
    shared = {int(v): k for k, v in enumerate(values[count > 1])}
    bins = Bins(capacity, per_source)
    return [bins.place(int(n), names.setdefault(s, len(names)), shared.get(int(c))) for n, s, c in zip(sizes, sources, clusters)]


def packed(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", source: str = "source", cluster: str | None = None, capacity: int = CAPACITY, group_docs: int = GROUP_DOCS, per_source: int = PER_SOURCE) -> DataFrame:
    """(doc_id, piece, first_word, n_words, bin_id, bin_offset): where each piece of each document lies.

    cluster: a long column of duplicate clusters, null for a document in none; without one, texts equal but for case and white space form a cluster.
    """
    same = F.xxhash64(F.lower(F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " "))) if cluster is None else F.col(cluster).cast("long")
    items = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long").alias("n"), F.col(source).cast("string").alias("source"), F.coalesce(same, F.xxhash64(F.col(doc_id), F.lit("alone"))).alias("cluster"))
    groups = max(1, -(-docs.count() // group_docs))
    items = items.withColumn("group", F.pmod(F.xxhash64("doc_id", "cluster"), F.lit(groups)).cast("long"))
    dealt = items.repartition(F.col("group")).sortWithinPartitions("group", (F.col("n") % capacity).desc(), "doc_id", "cluster", "n", "source")

    def run(batches: Iterator[pa.RecordBatch]):
        held: list[pa.RecordBatch] = []

        def flush(rows: pa.Table) -> pa.RecordBatch:
            n = rows.column("n").to_numpy()
            rest = n % capacity
            group = rows.column("group")[0].as_py()
            some = np.flatnonzero(rest > 0)
            chosen = rows.take(pa.array(some))
            placed = packed_group(rest[some], chosen.column("source").to_pylist(), chosen.column("cluster").to_numpy(), capacity, per_source)
            full = (n // capacity).astype(np.int64)
            opened = max((b for b, _ in placed), default=-1) + 1
            at = np.concatenate((np.repeat(np.arange(len(n)), full), some, np.flatnonzero(n == 0)))
            piece = np.concatenate((np.arange(full.sum()) - np.repeat(np.cumsum(full) - full, full), full[some], np.zeros((n == 0).sum(), np.int64)))
            words = np.concatenate((np.full(full.sum(), capacity), rest[some], np.zeros((n == 0).sum(), np.int64)))
            number = np.concatenate((opened + np.arange(full.sum()), np.array([b for b, _ in placed], np.int64).reshape(-1), np.zeros((n == 0).sum(), np.int64)))
            offset = np.concatenate((np.zeros(full.sum(), np.int64), np.array([o for _, o in placed], np.int64).reshape(-1), np.zeros((n == 0).sum(), np.int64)))
            none = words == 0
            ids = rows.column("doc_id").combine_chunks().take(pa.array(at))
            return pa.RecordBatch.from_arrays(
                [ids, pa.array(piece.astype(np.int32)), pa.array(piece * capacity), pa.array(words), pa.array((group << 32) + number, mask=none), pa.array(offset, mask=none)],
                names=["doc_id", "piece", "first_word", "n_words", "bin_id", "bin_offset"],
            )

        for batch in batches:
            if not batch.num_rows:
                continue
            group = batch.column("group").to_numpy()
            edges = np.flatnonzero(group[1:] != group[:-1]) + 1
            begin = 0
            for edge in [*edges.tolist(), batch.num_rows]:
                piece = batch.slice(begin, edge - begin)
                if held and held[-1].column("group")[0].as_py() != group[begin]:
                    yield flush(pa.Table.from_batches(held))
                    held = []
                if piece.num_rows:
                    held.append(piece)
                begin = edge
        if held:
            yield flush(pa.Table.from_batches(held))

    kind = items.schema["doc_id"].dataType.simpleString()
    return dealt.mapInArrow(run, f"doc_id {kind}, piece int, first_word long, n_words long, bin_id long, bin_offset long")


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(table(spark, sf_dir, "documents"))
