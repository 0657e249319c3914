"""Near-duplicates by the Jaccard similarity of their sets of five-word shingles: candidates by SimHash and min-hash, exact comparison.

SimHash fingerprints of the same shingles are linked by the BK-trees of `simhash` within RADIUS bits, texts of one fingerprint among
them. At a similarity of 0.8 fingerprints differ in about ten bits, out of the trees' reach, so min-hashes widen it: a document's 40 bands of 5 minima give it 40 keys; two documents of similarity s share none with probability (1 - s^5)^40, which
is 1.3e-7 at 0.8 and less above. Documents of a key are tied to its smallest one, so that a key makes no pairs, and the components
of these ties are groups. All pairs of a group are compared by their whole sets: a group over `cell_bytes` is cut into slices
and each two slices meet in a cell, within which a search from document to document leaves out what it has reached.

Nodes are 64-bit hashes of the lower-cased words; texts of equal words are one node. Texts without words are all one node.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import cut, mix, own_exchange, rolling, tidy, utf8, word_hashes
from .components import components

SHINGLE = 5
#: Least similarity, as a fraction of whole numbers so that equality is exact.
SIMILARITY = (4, 5)
BANDS, ROWS = 40, 5
#: Bits in which linked fingerprints differ at most; 15 shard keys of about 21 bits.
RADIUS = 4
CELL_BYTES = 4 << 20
MULTIPLIER = 0x9E3779B97F4A7C15
_DRAWN = mix(np.arange(1, 2 * BANDS * ROWS + 1, dtype=np.uint64) * np.uint64(MULTIPLIER))
FACTORS, ADDENDS = (_DRAWN[: BANDS * ROWS] | np.uint64(1)).astype(np.uint32), _DRAWN[BANDS * ROWS :].astype(np.uint32)


def words_of(text: bytes | None) -> list[bytes]:
    return (text or b"").lower().split()  # on bytes: A-Z only, and \x20 \x09-\x0D only


def shingles(words: list[bytes], width: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of the runs of width words; fewer words are one run."""
    return np.unique(rolling(word_hashes(words), min(width, len(words)), MULTIPLIER)) if words else np.empty(0, np.uint64)


def keys(tokens: np.ndarray) -> np.ndarray:
    """The 40 band keys of a set that isn't empty."""
    low = (tokens >> np.uint64(32)).astype(np.uint32)
    least = np.full(BANDS * ROWS, 0xFFFFFFFF, np.uint32)
    for i in range(0, len(low), 1024):
        np.minimum(least, (low[i : i + 1024, None] * FACTORS + ADDENDS).min(0), out=least)
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for r in range(ROWS):
        key = mix(key * np.uint64(MULTIPLIER) ^ least[r::ROWS])
    return key


def sketches(docs: DataFrame) -> DataFrame:
    """(doc_id, node, fp, keys) of docs (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            nodes, prints, ends, found = [], [], [0], []
            for text in utf8(batch.column("text")):
                words = words_of(text)
                prints.append(simhash.fingerprint(text, SHINGLE))
                nodes.append(xxhash.xxh3_64_intdigest(b" ".join(words)))
                if words:
                    found.append(keys(shingles(words)))
                ends.append(BANDS * len(found))
            values = pa.array(np.concatenate(found).view(np.int64) if found else np.empty(0, np.int64))
            lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), values)
            ids = batch.column(batch.schema.get_field_index("doc_id"))
            longs = [pa.array(np.array(x, np.uint64).view(np.int64)) for x in (nodes, prints)]
            yield pa.RecordBatch.from_arrays([ids, *longs, lists], names=["doc_id", "node", "fp", "keys"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, node long, fp long, keys array<long>")


def texts(docs: DataFrame) -> DataFrame:
    """(node, text) of docs (text), one text of each node."""

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            values = utf8(batch.column("text"))
            nodes = np.fromiter((xxhash.xxh3_64_intdigest(b" ".join(words_of(t))) for t in values), np.uint64, len(values))
            yield pa.RecordBatch.from_arrays([pa.array(nodes.view(np.int64)), batch.column("text")], names=["node", "text"])

    return docs.select("text").mapInArrow(run, "node long, text string").groupBy("node").agg(F.first("text").alias("text"))


def ties(nodes: DataFrame) -> DataFrame:
    """Edges (a, b) that tie each node (node, keys) to the smallest node with which it shares a key."""
    keyed = nodes.select("node", F.explode("keys").alias("key"))
    least = keyed.groupBy("key").agg(F.min("node").alias("least"), F.count("*").alias("n")).filter("n > 1").select("key", "least")
    return keyed.join(own_exchange(least, "key"), "key").filter("node <> least").select(F.col("node").alias("a"), F.col("least").alias("b")).distinct()


def print_ties(prints: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Edges (a, b) that tie the nodes of prints (node, fp) as the trees link their fingerprints; nodes of one fingerprint are tied too."""
    first = cut(prints.groupBy("fp").agg(F.min("node").alias("least"), F.count("*").alias("n")))
    shared = own_exchange(first.filter("n > 1").select("fp", "least"), "fp")
    same = prints.join(shared, "fp").filter("node <> least").select(F.col("node").alias("a"), F.col("least").alias("b"))
    one, two = (first.select(F.col("fp").alias(c), F.col("least").alias(f"node_{c}")) for c in ("a", "b"))
    linked = simhash.links(first.select("fp"), radius).join(one, "a").join(two, "b").select(F.col("node_a").alias("a"), F.col("node_b").alias("b"))
    return same.unionByName(linked)


def similar(sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """A spanning forest of the pairs of sets whose similarity is SIMILARITY at least, all pairs considered."""
    over, under = SIMILARITY
    sizes = np.array([len(s) for s in sets], np.int64)
    values, number = np.unique(np.concatenate(sets), return_inverse=True)
    starts = np.cumsum(sizes) - sizes
    marked = np.zeros(len(values), bool)
    left, rows = np.arange(len(sets)), number  # those not reached yet, and their numbers one behind another
    found, waiting = [], []
    while left.size:
        if not waiting:
            waiting.append(int(left[0]))
            rows, left = rows[sizes[left[0]] :], left[1:]
            continue
        at = waiting.pop()
        own = number[starts[at] : starts[at] + sizes[at]]
        marked[own] = True
        lengths = sizes[left]
        common = np.add.reduceat(marked[rows], np.cumsum(lengths) - lengths, dtype=np.int64)
        marked[own] = False
        near = (over + under) * common >= over * (lengths + sizes[at])
        if near.any():
            reached = left[near]
            found += [(at, int(k)) for k in reached]
            waiting += reached.tolist()
            rows, left = rows[np.repeat(~near, lengths)], left[~near]
    return found


def links(members: DataFrame, cell_bytes: int = CELL_BYTES) -> DataFrame:
    """Edges (a, b) that connect the nodes of each group of members (root, node, text) exactly as all similar pairs do."""
    sized = members.withColumn("bytes", F.octet_length("text"))
    groups = sized.groupBy("root").agg(F.ceil(F.sum("bytes") / cell_bytes).cast("int").alias("slices"))
    placed = sized.join(own_exchange(groups, "root"), "root").withColumn("own", F.pmod(F.xxhash64("node"), F.col("slices")).cast("int"))
    others = F.filter(F.sequence(F.lit(0), F.col("slices") - 1), lambda t: (F.col("slices") == 1) | (t != F.col("own")))
    cell = F.transform(others, lambda t: F.struct(F.least("own", t).alias("one"), F.greatest("own", t).alias("two")))
    cells = placed.select("root", "node", "text", F.explode(cell).alias("cell")).select("root", "cell.one", "cell.two", "node", "text")
    cells = cells.repartition("root", "one", "two").sortWithinPartitions("root", "one", "two", "node")

    def run(batches: Iterator[pa.RecordBatch]):
        now, nodes, sets = None, [], []

        def compared():
            pairs = [(nodes[i], nodes[j]) for i, j in similar(sets)] if len(nodes) > 1 else []
            a, b = zip(*pairs) if pairs else ((), ())
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

        for batch in batches:
            root, one, two, node = (batch.column(k).to_pylist() for k in range(4))
            for at, n, text in zip(zip(root, one, two), node, utf8(batch.column(4))):
                if at != now:
                    yield compared()
                    now, nodes, sets = at, [], []
                nodes.append(n)
                sets.append(shingles(words_of(text)))
        yield compared()

    return cells.mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", cell_bytes: int = CELL_BYTES) -> DataFrame:
    """(doc_id, node, component_id) of every row of docs: the smallest id that is reached by steps of similar texts."""
    given = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    rows = cut(sketches(given))
    near = print_ties(rows.select("node", "fp").distinct())
    groups = cut(components(near.unionByName(ties(rows.groupBy("node").agg(F.first("keys").alias("keys"))))))
    tidy(docs.sparkSession)
    members = texts(given).join(own_exchange(groups, "node"), "node").select("root", "node", "text")
    roots = components(links(members, cell_bytes))
    tidy(docs.sparkSession)
    named = rows.groupBy("node").agg(F.min("doc_id").alias("least")).join(roots, "node", "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    smallest = named.groupBy("root").agg(F.min("least").alias("component_id"))
    found = named.join(own_exchange(smallest, "root"), "root").select("node", "component_id")
    return rows.select("doc_id", "node").join(own_exchange(found, "node"), "node").select("doc_id", "node", "component_id")
