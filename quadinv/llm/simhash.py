"""SimHash near-duplicates: 64-bit fingerprints, linked by BK-trees within a Hamming radius, then components.

Only distinct fingerprints are linked. Two that differ in at most r of 64 bits agree in two of r + 2 blocks of bits, so that each
pair of blocks gives a shard key under which every link is found: six keys for r = 2. A shard of more than `shard_rows` fingerprints
is cut into slices; each slice's BK-tree is sent to each slice of queries of the same shard and no tree outgrows a task.
Of the links that a tree yields, only a spanning forest leaves the task, never all pairs.

Null and empty texts have no words and the fingerprint zero, linked like any other. Repeated rows have equal fingerprints
and so one component. A null doc_id takes part but never names a component unless all its ids are null.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, extended, own_exchange, renamed, table, unnamed, utf8, with_columns
from .components import components, forest_of

SHINGLE = 3
RADIUS = 2
SHARD_ROWS = 1024
SEED = 42


def fingerprint(text: bytes | None, shingle: int = SHINGLE) -> int:
    """Majority of the bits of the shingles' XXH64, as an unsigned number."""
    import xxhash

    digest = xxhash.xxh64_intdigest
    words = (text or b"").lower().split()  # on bytes: A-Z only, and \x20 \x09-\x0D only
    if not words:
        return 0
    joined = b" ".join(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    width = min(shingle, len(words))
    begins = (ends - lengths)[: len(words) - width + 1].tolist()
    hashes = np.fromiter([digest(joined[b:e], SEED) for b, e in zip(begins, ends[width - 1 :].tolist())], np.uint64, len(begins))
    counts = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 65536):
        counts += np.unpackbits(hashes[i : i + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * counts > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, text: str = "text", keep: list[str] | None = None, shingle: int = SHINGLE) -> DataFrame:
    """docs (or its columns in keep) with fp, the fingerprint as a signed long."""
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() != "fp"]

    def run(batches):
        for batch in batches:
            values = np.fromiter((fingerprint(t, shingle) for t in utf8(batch.column(text))), np.uint64, batch.num_rows)
            yield with_columns(batch, {"fp": pa.array(values.view(np.int64))}, kept)

    return docs.select(*dict.fromkeys([*kept, text])).mapInArrow(run, extended(docs, "fp long", kept))


class Forest:
    """A BK-tree for each group of distinct values, all built together, level by level."""

    def __init__(self, values: np.ndarray, groups: np.ndarray):
        """groups: ascending; each group's first value is its root."""
        self.values = values
        self.groups, self.roots = np.unique(groups, return_index=True)
        below = self.roots[np.searchsorted(self.groups, groups)]
        pending = np.setdiff1d(np.arange(len(values)), self.roots, assume_unique=True)
        below = below[pending]
        edges, children = [], []
        while pending.size:
            edge = below * 65 + np.bitwise_count(values[pending] ^ values[below]).astype(np.int64)
            key, first, which = np.unique(edge, return_index=True, return_inverse=True)
            child = pending[first]
            edges.append(key)
            children.append(child)
            rest = np.ones(len(pending), bool)
            rest[first] = False
            pending, below = pending[rest], child[which[rest]]
        key = np.concatenate(edges) if edges else np.empty(0, np.int64)
        child = np.concatenate(children) if children else np.empty(0, np.int64)
        order = np.argsort(key)
        self.edge, self.child = key[order], child[order]

    def within(self, queries: np.ndarray, groups: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
        """(query, node) of all pairs of a group that differ in at most radius bits; only edges within reach are followed."""
        at = np.searchsorted(self.groups, groups)
        known = at < len(self.groups)
        known[known] = self.groups[at[known]] == groups[known]
        query, node = np.flatnonzero(known), self.roots[at[known]]
        found = []
        while query.size:
            apart = np.bitwise_count(queries[query] ^ self.values[node]).astype(np.int64)
            near = apart <= radius
            found.append((query[near], node[near]))
            further = []
            for step in range(-radius, radius + 1):
                label = apart + step
                edge = node * 65 + label
                spot = np.searchsorted(self.edge, edge)
                there = (label > 0) & (label <= 64) & (spot < len(self.edge))
                there[there] = self.edge[spot[there]] == edge[there]
                further.append((query[there], self.child[spot[there]]))
            query, node = (np.concatenate(x) for x in zip(*further))
        if not found:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        return tuple(np.concatenate(x) for x in zip(*found))


def _cells(rows: np.ndarray, queries_only: np.ndarray, cell: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links of whole cells; rows flagged queries_only are searched for but aren't in the tree."""
    tree = np.flatnonzero(~queries_only)
    forest = Forest(rows[tree], cell[tree])
    alone = np.isin(cell, cell[queries_only])  # a cell of two slices: its tree's own links are found elsewhere
    asked = np.flatnonzero(queries_only | ~alone)
    query, node = forest.within(rows[asked], cell[asked], radius)
    left, right = asked[query], tree[node]
    other = left != right
    root = forest_of(left[other], right[other], len(rows))
    joined = np.flatnonzero(root != np.arange(len(rows)))
    return rows[joined], rows[root[joined]]


def links(distinct: DataFrame, radius: int = RADIUS, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """Edges (a, b: long) that connect the fingerprints of distinct (fp) exactly as all links within radius do.

    Keys get shorter and more with the radius: (radius + 2) (radius + 1) / 2 of about 128 / (radius + 2) bits.
    """
    if not 0 <= radius <= 14:
        raise ValueError("radius must be 0 to 14")
    edges = [64 * k // (radius + 2) for k in range(radius + 3)]
    block = lambda k: F.shiftrightunsigned("fp", edges[k]).bitwiseAND(F.lit((1 << edges[k + 1] - edges[k]) - 1))
    pairs = [(i, j) for i in range(radius + 2) for j in range(i + 1, radius + 2)]
    # The bits of both blocks, and the number of the pair: in the bits above where there is room, else hashed together.
    width = [edges[k + 1] - edges[k] for k in range(radius + 2)]
    both = lambda i, j: F.shiftleft(block(i).cast("long"), width[j]) + block(j).cast("long")
    keys = F.array(*[F.lit(k << 56).cast("long") + both(i, j) if width[i] + width[j] <= 56 else F.xxhash64(F.lit(k), both(i, j)) for k, (i, j) in enumerate(pairs)])
    keyed = distinct.select("fp", F.explode(keys).alias("shard"))
    shared = keyed.groupBy("shard").agg(F.count("*").alias("n")).filter("n > 1").select("shard", F.ceil(F.col("n") / shard_rows).cast("int").alias("slices"))
    placed = keyed.join(own_exchange(shared, "shard"), "shard").withColumn("own", F.pmod(F.xxhash64("fp"), F.col("slices")).cast("int"))
    cell = F.transform(F.sequence(F.lit(0), F.col("slices") - 1), lambda t: F.struct(F.least("own", t).alias("tree"), F.greatest("own", t).alias("asked")))
    cells = placed.select("fp", "shard", "own", F.explode(cell).alias("cell")).select("fp", "shard", F.col("cell.tree").alias("tree"), F.col("cell.asked").alias("asked"), (F.col("own") != F.col("cell.tree")).alias("query"))
    cells = cells.repartition("shard", "tree", "asked").sortWithinPartitions("shard", "tree", "asked", "query", "fp")

    def run(batches: Iterator[pa.RecordBatch]):
        held: list[tuple[np.ndarray, ...]] = []
        size = 0

        def flush(last: bool):
            nonlocal held, size
            fp, shard, tree, asked, query = (np.concatenate(x) for x in zip(*held))
            new = np.ones(len(fp), bool)
            new[1:] = (shard[1:] != shard[:-1]) | (tree[1:] != tree[:-1]) | (asked[1:] != asked[:-1])
            cell = np.cumsum(new)
            whole = len(fp) if last else int(np.flatnonzero(new)[-1])
            held = [tuple(x[whole:] for x in (fp, shard, tree, asked, query))]
            size = len(fp) - whole
            if whole:
                a, b = _cells(fp[:whole].view(np.uint64), query[:whole], cell[:whole], radius)
                return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            for i in range(0, batch.num_rows, 2 * shard_rows):  # bounded pieces, so bounded lists of pairs
                piece = batch.slice(i, 2 * shard_rows)
                held.append(tuple(piece.column(k).to_numpy(zero_copy_only=False) for k in range(5)))
                size += piece.num_rows
                if size >= 2 * shard_rows and (out := flush(False)) is not None:
                    yield out
        if held and (out := flush(True)) is not None:
            yield out

    return cells.select("fp", "shard", "tree", "asked", "query").mapInArrow(run, "a long, b long")


def classes(prints: DataFrame, doc_id: str = "doc_id", radius: int = RADIUS, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(fp, component_id): the smallest id of all documents reachable from each fingerprint."""
    distinct = prints.groupBy("fp").agg(F.min(doc_id).alias("least"))
    roots = components(links(distinct.select("fp"), radius, shard_rows))
    named = distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    smallest = named.groupBy("root").agg(F.min("least").alias("component_id"))
    return named.join(own_exchange(smallest, "root"), "root").select("fp", "component_id")


def near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = SHINGLE, radius: int = RADIUS, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(doc_id, fp, component_id) of every row of docs."""
    prints = cut(fingerprints(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), keep=["doc_id"], shingle=shingle))
    return prints.join(classes(prints, radius=radius, shard_rows=shard_rows), "fp").select("doc_id", "fp", "component_id")


def one_of_each(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", find=near_duplicates, **options) -> DataFrame:
    """docs with one document of each component that find gives: that with the smallest id, and of rows with equal ids the one whose text has the smallest hash.

    A row is known by its id and text, so that only rows of one component are merged; of rows equal in both, any one stays. Rows without an
    id are kept only where no row with an id is like them.
    """
    plain, name = unnamed(docs)
    own, words = F.col(name[doc_id]), F.col(name[text])
    key = F.struct(own.isNull().alias("none"), own.alias("id"), *[F.xxhash64(F.lit(seed), F.coalesce(words, F.lit(""))).alias(seed) for seed in ("one", "two")])
    keyed = plain.withColumn("row_key", key)
    found = find(keyed, name[text], "row_key", **options)
    chosen = found.filter(F.col("doc_id") == F.col("component_id")).select(F.col("doc_id").alias("row_key")).distinct()
    return renamed(keyed.join(chosen, "row_key", "left_semi").dropDuplicates(["row_key"]), docs)


def op9_simhash_bktree(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
