"""Benchmark decontamination: Wu-Manber multi-pattern search for the word windows of test items.

A text is lower-cased (A-Z) and read as words `[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`; written with one space around each
word, a window of an item occurs where its bytes do. The patterns are split into classes by length, so that one short item
doesn't shorten the jumps for all others. For each class a table gives, for the hash of the last few bytes under the
search position, how far the search may jump; where it may not, the patterns filed under that hash are compared with the
text. Thousands of search positions advance together in numpy.

Null and empty texts and items have no words: nothing is hit and nothing searched. Items with equal windows are all
reported. Repeated rows are judged each by itself. Columns of the documents named as a result column are replaced.
"""

from __future__ import annotations

import pickle
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import chunks, cut, extended, renamed, table, unnamed, utf8, with_columns

WINDOW = 10
#: Bytes of item text that are tried as one automaton, and the most bytes that a built one may have to be sent to the executors.
#: Every word begins a window, so that an automaton has tens of times the bytes of its text.
PATTERN_BYTES, BUILT_BYTES = 4 << 20, 256 << 20
LANES = 8192
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)

#: Separators become a space, A-Z the small letter, all other bytes stay.
FOLDED = bytes(32 if b < 0x30 or 0x3A <= b <= 0x40 or 0x5B <= b <= 0x60 or 0x7B <= b <= 0x7F else b + 32 if 0x41 <= b <= 0x5A else b for b in range(256))


def words_of(text: bytes) -> list[bytes]:
    return text.translate(FOLDED).split()


class PatternClass:
    """Patterns whose lengths lie within a factor of two: shift table, suffix buckets, and the bytes to compare with."""

    def __init__(self, patterns: list[bytes]):
        self.patterns = patterns
        self.least = min(map(len, patterns))
        self.block = min(8, max(1, self.least // 2))
        self.bits = int(np.clip(np.ceil(np.log2(max(1, len(patterns)) * self.least)) + 3, 12, 22))
        self.mask = np.uint64((1 << 8 * self.block) - 1)
        self.shift = np.full(1 << self.bits, self.least - self.block + 1, np.int32)
        heads = np.frombuffer(b"".join(p[: self.least] for p in patterns), np.uint8).reshape(-1, self.least)
        for end in range(self.block, self.least + 1):
            key = np.zeros(len(patterns), np.uint64)
            for k in range(self.block):
                key |= heads[:, end - self.block + k].astype(np.uint64) << np.uint64(8 * k)
            at = self.slot(key)
            self.shift[at] = np.minimum(self.shift[at], self.least - end)
        order = np.argsort(at, kind="stable")  # the last block ends the head: its slot is the bucket
        self.members = order
        self.bucket, first = np.unique(at[order], return_index=True)
        self.first = np.append(first, len(order))
        prefix = np.frombuffer(b"".join(p[: min(8, self.least)].ljust(8, b"\0") for p in patterns), "<u8")
        self.prefix, self.prefix_mask = prefix, np.uint64((1 << 8 * min(8, self.least)) - 1)

    def slot(self, key: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((key * MULTIPLIER) >> np.uint64(64 - self.bits)).astype(np.int64)

    def search(self, data: bytes, length: int) -> Iterator[tuple[int, int]]:
        """(position, pattern) of every occurrence; data holds length bytes of text and eight more."""
        if length < self.least:
            return
        eight = np.ndarray((length,), "<u8", data, 0, (1,))  # the eight bytes from each position on
        begin, end = self.least - self.block, length - self.block + 1  # positions of the block that ends the head
        lanes = max(1, min(LANES, (end - begin) // 64))
        edges = np.linspace(begin, end, lanes + 1).astype(np.int64)
        at, stop, found = edges[:-1].copy(), edges[1:], []
        live = at < stop
        at, stop = at[live], stop[live]
        while at.size:
            slot = self.slot(eight[at] & self.mask)
            jump = self.shift[slot]
            zero = jump == 0
            if zero.any():
                found.append(np.stack((at[zero], slot[zero])))
                jump = np.maximum(jump, 1)
            at = at + jump
            live = at < stop
            if not live.all():
                at, stop = at[live], stop[live]
        if not found:
            return
        at, slot = np.concatenate(found, axis=1)
        start = at - begin
        bucket = np.searchsorted(self.bucket, slot)
        bucket = np.minimum(bucket, len(self.bucket) - 1)
        hit = self.bucket[bucket] == slot
        start, bucket = start[hit], bucket[hit]
        size = self.first[bucket + 1] - self.first[bucket]
        head = eight[start] & self.prefix_mask
        for turn in range(int(size.max(initial=0))):  # the bucket's patterns in turn, for all positions at once
            more = size > turn
            start, bucket, size, head = start[more], bucket[more], size[more], head[more]
            which = self.members[self.first[bucket] + turn]
            same = self.prefix[which] == head
            for s, k in zip(start[same].tolist(), which[same].tolist()):
                pattern = self.patterns[k]
                if data[s : s + len(pattern)] == pattern:
                    yield s, k


class Automaton:
    """All windows of some items, in classes of like length."""

    def __init__(self, items: list[tuple[str, bytes]], window: int):
        owners: dict[bytes, set[str]] = defaultdict(set)
        for item, text in items:
            words = words_of(text)
            for i in range(max(1, len(words) - window + 1) if words else 0):
                owners[b" " + b" ".join(words[i : i + window]) + b" "].add(item)
        by_length: dict[int, list[bytes]] = defaultdict(list)
        for pattern in owners:
            by_length[len(pattern).bit_length()].append(pattern)
        self.owners = {p: sorted(v) for p, v in owners.items()}
        self.classes = [PatternClass(sorted(p)) for _, p in sorted(by_length.items())]

    def scan(self, texts: list[bytes]) -> tuple[np.ndarray, list[np.ndarray], list[set[str]]]:
        """For each text: number of words, word positions hit, items that occur."""
        raw = b"\0".join(b" " + t.translate(FOLDED) + b" " for t in texts) + b"\0"
        flat = np.frombuffer(raw, np.uint8)
        space = flat == 32
        again = np.empty(len(flat), bool)
        again[0] = False
        np.logical_and(space[1:], space[:-1], out=again[1:])
        flat = flat[~again]
        data, length = flat.tobytes() + b"\0" * 8, len(flat)
        word = np.zeros(length, bool)
        word[1:] = (flat[:-1] == 32) & (flat[1:] != 32) & (flat[1:] != 0)
        number = np.cumsum(word)  # words begun up to and with each byte
        ends = np.flatnonzero(flat == 0)
        upto = number[ends]
        before = np.concatenate(([0], upto[:-1]))
        hits: dict[int, list[tuple[int, int]]] = defaultdict(list)
        items: dict[int, set[str]] = defaultdict(set)
        for group in self.classes:
            for start, k in group.search(data, length):
                doc = int(np.searchsorted(ends, start))
                pattern = group.patterns[k]
                first = int(number[start + 1]) - 1 - int(before[doc])
                hits[doc].append((first, pattern.count(b" ") - 1))
                items[doc].update(self.owners[pattern])
        positions = []
        for doc in range(len(texts)):
            positions.append(np.unique(np.concatenate([np.arange(a, a + n) for a, n in hits[doc]])) if doc in hits else np.empty(0, np.int64))
        return upto - before, positions, [items.get(d, set()) for d in range(len(texts))]


def automata(items: DataFrame, window: int, pattern_bytes: int, built_bytes: int) -> Iterator[Automaton]:
    """Automata of items (item, text), one after another: each of at most pattern_bytes of text on average, and at most built_bytes as sent."""
    size = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    parts = int(size // pattern_bytes) + 1
    for part in range(parts):
        rows = items.filter(F.pmod(F.xxhash64("item", "text"), F.lit(parts)) == part).collect() if parts > 1 else items.collect()
        waiting = [sorted((r.item, r.text.encode()) for r in rows)]
        while waiting:
            some = waiting.pop()
            built = Automaton(some, window)
            if len(some) > 1 and len(pickle.dumps(built, pickle.HIGHEST_PROTOCOL)) > built_bytes:
                waiting += [some[: len(some) // 2], some[len(some) // 2 :]]
            else:
                yield built


def search(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, text: str = "text", item: str = "item_id", item_text: str = "text", keep: list[str] | None = None, pattern_bytes: int = PATTERN_BYTES, built_bytes: int = BUILT_BYTES) -> DataFrame:
    """docs (or its columns in keep) with n_words, hit_words (positions, ascending) and hit_items (ids, ascending).

    The items are cut into as many parts as needed; each part's automaton is broadcast, and the documents pass through the parts
    one after another without a shuffle. Between parts they are checkpointed, so that a task holds one automaton at a time.
    """
    session = docs.sparkSession
    items = benchmark.select(F.col(item).cast("string").alias("item"), F.col(item_text).alias("text")).filter("item is not null and text is not null").distinct()
    added = "n_words long, hit_words array<int>, hit_items array<string>"
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("n_words", "hit_words", "hit_items")]
    columns = list(dict.fromkeys([*kept, text]))
    out = None
    for automaton in automata(items, window, pattern_bytes, built_bytes):
        shipped = session.sparkContext.broadcast(automaton)

        def run(batches, shipped=shipped, first=out is None):
            for batch in batches:
                words, hits, found = [], [], []
                for _, piece in chunks(utf8(batch.column(text))):
                    n, where, which = shipped.value.scan(piece)
                    words.extend(n.tolist())
                    hits.extend(where)
                    found.extend(which)
                if not first:
                    hits = [np.union1d(a, np.asarray(b, np.int64)) for a, b in zip(hits, batch.column("hit_words").to_pylist())]
                    found = [a | set(b) for a, b in zip(found, batch.column("hit_items").to_pylist())]
                made = {
                    "n_words": pa.array(words, pa.int64()),
                    "hit_words": pa.array([h.astype(np.int32) for h in hits], pa.list_(pa.int32())),
                    "hit_items": pa.array([sorted(f) for f in found], pa.list_(pa.string())),
                }
                yield with_columns(batch, made, columns)

        before = docs.select(*columns) if out is None else cut(out)
        out = before.mapInArrow(run, extended(docs, added, columns))
    return out.select(*kept, "n_words", "hit_words", "hit_items")


def decontaminated(docs: DataFrame, benchmark: DataFrame, text: str = "text", **options) -> DataFrame:
    """The documents without any occurrence of a window, with their own columns."""
    plain, name = unnamed(docs)
    return renamed(search(plain, benchmark, text=name[text], **options).filter(F.size("hit_words") == 0), docs)


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = search(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), keep=["doc_id"])
    return found.select(
        "doc_id",
        "n_words",
        F.size("hit_words").cast("long").alias("n_hit"),
        F.size("hit_items").cast("long").alias("n_items"),
        F.sha2(F.array_join("hit_items", ","), 256).alias("items_sha256"),
        (F.size("hit_words") > 0).alias("contaminated"),
    )


OP8_SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), b AS (
  SELECT CAST(item_id AS VARCHAR) AS item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), p AS (
  SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS s
  FROM (SELECT item_id, w, unnest(range(1, greatest(1, len(w) - 9) + 1)) AS i FROM b WHERE len(w) > 0)
), lengths AS (SELECT DISTINCT n FROM p), g AS (
  SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS s
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, lengths WHERE len(w) >= n)
), o AS (SELECT g.doc_id, g.i, g.n, p.item_id FROM g JOIN p USING (n, s)),
h AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS pos FROM o) GROUP BY doc_id),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM o) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(h.n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(t.n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(t.ids, '')) AS items_sha256, coalesce(h.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)
"""
