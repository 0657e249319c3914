"""Substring dedup: words under a window of 35 words that also starts elsewhere are removed.

A count-min sketch keeps most windows out of the shuffle. Every window holds a gram of 16 words whose hash is least among
the window's grams; equal windows hold equal least grams, so the count of a window's least gram bounds the window's own
count from above, and there are ten times fewer such grams than windows. The sketch is cut into shards by the gram's hash, and their
number follows the input, so that its load doesn't grow. Each task counts the grams that it meets into saturating counters (0, 1, many);
the partial sketches are merged shard by shard, and a window is estimated repeated where all of its counters say many. Up to
BROADCAST_BYTES the sketch is sent to all tasks, which look their windows up; beyond it the texts' grams are sent to the shards, and each
text gets back those that are estimated repeated. A second pass groups exactly only the windows estimated repeated, by a 128-bit
digest of their words, and finds those that are single after all; the last pass removes what is estimated repeated and not among
these. False alarms cost shuffle, not right results; nothing that repeats is lost.

Null and empty texts and texts of fewer than 35 words have no window and keep all words. Repeated rows are each other's
repetition. Texts are known by a 128-bit hash of them, never by doc_id: equal texts have no single window, and ids may be null or
equal without rows gathering in one group.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import chain, compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import chunks, covered, cut, extended, mix, rolling, table, unnamed, utf8, with_columns, word_hashes

WINDOW = 35
GRAM = 16
DEPTH = 4
#: log2 of the counters of a shard's row, at most and at least. A shard of 4 rows of 2**22 has 2 MB, one bit a counter.
SHARD_BITS, LEAST_BITS = 22, 16
#: Bytes of text for each counter of a row, at most: 2.5 to 5 counters for each gram, so that 0.1 to 1.2 % of the single ones are let through.
TEXT_PER_COUNTER = 32
#: Largest sketch that is sent to all tasks: enough for 4 GB of text.
BROADCAST_BYTES = 64 << 20
#: Parts into which a shard's look-ups are dealt, each with a copy of the shard, so that a gram in a third of all texts is split.
SALTS = 4
#: Below this many false alarms (rows of a text, a position and a digest) they are broadcast, beyond it they are joined.
BROADCAST_ROWS = 500_000
GRAM_FACTOR = 0xD6E8FEB86659FD93


def _sliding(values: np.ndarray, width: int, best) -> np.ndarray:
    """best (np.minimum or np.maximum) over each run of width values."""
    size = 1
    while 2 * size <= width:
        values = best(values[:-size], values[size:])
        size *= 2
    return best(values[: len(values) - (width - size)], values[width - size :]) if width > size else values


class Piece:
    """Some texts as one run of words, so that numpy works on thousands of short texts at once.

    least: least gram of the window at each word; starts: the words at which a window lies within one text, ascending.
    """

    def __init__(self, texts: list[bytes], window: int, gram: int):
        self.split = [t.split() for t in texts]
        self.sizes = np.fromiter(map(len, self.split), np.int64, len(texts))
        self.ends = np.cumsum(self.sizes)
        self.flat = list(chain.from_iterable(self.split))
        n = len(self.flat)
        each = rolling(word_hashes(self.flat), gram, GRAM_FACTOR)
        span = window - gram + 1
        if len(each) < span:
            self.least, self.starts, self.each = np.empty(0, np.uint64), np.empty(0, np.int64), each
        else:
            self.least = _sliding(each, span, np.minimum)
            left = np.repeat(self.ends, self.sizes) - np.arange(n)  # words from each one to its text's end
            self.starts = np.flatnonzero(left[: len(self.least)] >= window)
            self.each = each
        self.window, self.span = window, span

    def chosen(self) -> np.ndarray:
        """The words at which a gram begins that is the least of some window."""
        if not len(self.starts):
            return np.empty(0, np.int64)
        padded = np.zeros(len(self.each) + self.span - 1, np.uint64)
        padded[self.starts + self.span - 1] = self.least[self.starts]
        return np.flatnonzero(_sliding(padded, self.span, np.maximum) == self.each)  # a gram is never below the least of its windows

    def suspects(self, estimate: Sketch | Listed) -> np.ndarray:
        """Words at which a window starts that is estimated repeated."""
        least = self.least[self.starts]
        if not len(least):
            return self.starts
        change = np.flatnonzero(np.concatenate(([True], least[1:] != least[:-1])))  # neighbours mostly share their least gram
        return self.starts[np.repeat(estimate.repeated(least[change]), np.diff(np.append(change, len(least))))]

    def digests(self, starts: np.ndarray) -> np.ndarray:
        """128-bit digests of the windows' words, as pairs of longs."""
        import xxhash

        joined = b" ".join(self.flat)
        lengths = np.fromiter(map(len, self.flat), np.int64, len(self.flat))
        ends = np.cumsum(lengths + 1) - 1
        begins = (ends - lengths)[starts].tolist()
        digest = xxhash.xxh3_128_digest
        return np.frombuffer(b"".join([digest(joined[b:e]) for b, e in zip(begins, ends[starts + self.window - 1].tolist())]), "<i8").reshape(-1, 2)

    def places(self, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Text and position in it of each of starts."""
        text = np.searchsorted(self.ends, starts, side="right")
        return text, starts - (self.ends - self.sizes)[text]


def slots(keys: np.ndarray, row: int, bits: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return (mix(keys + np.uint64(0x632BE59BD9B4E019) * np.uint64(row + 1)) >> np.uint64(64 - bits)).astype(np.int64)


class Shape:
    """2**shard_bits shards of DEPTH rows of 2**bits counters."""

    def __init__(self, text_bytes: int, most_bits: int = SHARD_BITS, least_bits: int = LEAST_BITS):
        whole = max(least_bits, int(text_bytes // TEXT_PER_COUNTER).bit_length())
        self.bits = min(whole, most_bits)
        self.shard_bits = whole - self.bits

    @property
    def shard_bytes(self) -> int:
        return DEPTH << self.bits >> 3

    @property
    def bytes(self) -> int:
        return self.shard_bytes << self.shard_bits

    def shard(self, keys: np.ndarray) -> np.ndarray:
        return (mix(keys ^ np.uint64(GRAM_FACTOR)) >> np.uint64(64 - self.shard_bits)).astype(np.int64) if self.shard_bits else np.zeros(len(keys), np.int64)

    def counters(self, keys: np.ndarray) -> np.ndarray:
        """The counters of each key in its shard, a row each."""
        return np.stack([slots(keys, row, self.bits) + (row << self.bits) for row in range(DEPTH)])


class Sketch:
    """The merged counters' second bit: many, that is met more than once, of all shards or of one."""

    def __init__(self, shape: Shape, many: np.ndarray):
        self.shape, self.many = shape, many

    def repeated(self, keys: np.ndarray, shard: int | None = None) -> np.ndarray:
        base = (self.shape.shard(keys) if shard is None else np.zeros(len(keys), np.int64)) * (8 * self.shape.shard_bytes)
        out = np.ones(len(keys), bool)
        for at in self.shape.counters(keys):
            at = at + base
            out &= (self.many[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1
        return out


class Listed:
    """Grams that the shards have estimated repeated, of some texts."""

    def __init__(self, lists: pa.Array):
        self.grams = np.unique(lists.drop_null().flatten().to_numpy(zero_copy_only=False).astype(np.int64, copy=False).view(np.uint64))

    def repeated(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.grams):
            return np.zeros(len(keys), bool)
        return self.grams[np.minimum(np.searchsorted(self.grams, keys), len(self.grams) - 1)] == keys


def shards(texts: DataFrame, shape: Shape, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(shard, many): the merged sketch of the least grams of all texts."""

    def count(batches: Iterator[pa.RecordBatch]):
        held: list[np.ndarray] = []
        size = 0

        def flush():
            """The counters met so far, shard by shard: those met once and those met more often, as gaps."""
            keys = np.concatenate(held)
            which = shape.shard(keys)
            order = np.argsort(which, kind="stable")
            keys, which = keys[order], which[order]
            numbers, first = np.unique(which, return_index=True)
            once, many = [], []
            for begin, end in zip(first, [*first[1:], len(keys)]):
                at, times = np.unique(shape.counters(keys[begin:end]), return_counts=True)
                once.append(_gaps(at[times == 1]))
                many.append(_gaps(at[times > 1]))
            return pa.RecordBatch.from_arrays([pa.array(numbers, pa.int64()), pa.array(once, pa.binary()), pa.array(many, pa.binary())], names=["shard", "once", "many"])

        for batch in batches:
            for _, piece in chunks(utf8(batch.column(0))):
                found = Piece(piece, window, gram)
                held.append(found.each[found.chosen()])
                size += len(held[-1])
                if size >= 4_000_000:
                    yield flush()
                    held, size = [], 0
        if size:
            yield flush()

    def merge(batches: Iterator[pa.RecordBatch]):
        now, seen, more = None, None, None
        for batch in batches:
            for shard, once, many in zip(*(batch.column(k).to_pylist() for k in range(3))):
                if shard != now:
                    if now is not None:
                        yield finished(now, more)
                    now, seen, more = shard, np.zeros(8 * shape.shard_bytes, bool), np.zeros(8 * shape.shard_bytes, bool)
                for at, twice in ((_ungapped(once), False), (_ungapped(many), True)):
                    more[at] |= seen[at] | twice
                    seen[at] = True
        if now is not None:
            yield finished(now, more)

    def finished(shard: int, more: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([shard], pa.int64()), pa.array([np.packbits(more).tobytes()], pa.binary())], names=["shard", "many"])

    parts = texts.select("text").mapInArrow(count, "shard long, once binary, many binary")
    return parts.repartition("shard").sortWithinPartitions("shard").mapInArrow(merge, "shard long, many binary")


def gathered(merged: DataFrame, shape: Shape) -> Sketch:
    """The whole sketch on the driver, where it is no larger than BROADCAST_BYTES."""
    whole = np.zeros(shape.bytes, np.uint8)
    for row in merged.collect():
        whole[row.shard * shape.shard_bytes : (row.shard + 1) * shape.shard_bytes] = np.frombuffer(row.many, np.uint8)
    return Sketch(shape, whole)


def looked_up(texts: DataFrame, merged: DataFrame, shape: Shape, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(k0, k1, grams): for each text that has any, its least grams that are estimated repeated. Grams go to the shards, not shards to the texts."""

    def grams(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            k0, k1 = (batch.column(k).to_numpy(zero_copy_only=False) for k in (1, 2))
            for first, piece in chunks(utf8(batch.column(0))):
                found = Piece(piece, window, gram)
                at = found.chosen()
                if len(at):
                    pairs = np.unique(np.stack((found.places(at)[0].astype(np.uint64), found.each[at])), axis=1)
                    row, keys = first + pairs[0].astype(np.int64), pairs[1]
                    yield pa.RecordBatch.from_arrays([pa.array(shape.shard(keys)), pa.array((k0[row] & (SALTS - 1)).astype(np.int64)), pa.array(k0[row]), pa.array(k1[row]), pa.array(keys.view(np.int64))], names=["shard", "salt", "k0", "k1", "gram"])

    def answer(batches: Iterator[pa.RecordBatch]):
        now, held = None, None
        for batch in batches:
            shard, many = (batch.column(k) for k in (0, 2))
            edges = np.flatnonzero(np.diff(shard.to_numpy(), prepend=-1) | many.is_valid().to_numpy(zero_copy_only=False))
            for begin, end in zip([0, *edges[edges > 0]], [*edges[edges > 0], batch.num_rows]):
                part = batch.slice(begin, end - begin)
                if many[begin].is_valid:
                    now, held = shard[begin].as_py(), Sketch(shape, np.frombuffer(many[begin].as_py(), np.uint8))
                    part = part.slice(1)
                if part.num_rows and held is not None and shard[begin].as_py() == now:
                    keys = part.column(5).to_numpy().view(np.uint64)
                    yield pa.RecordBatch.from_arrays([part.column(k).filter(pa.array(held.repeated(keys, now))) for k in (3, 4, 5)], names=["k0", "k1", "gram"])

    copies = merged.select("shard", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))).alias("salt"), "many", *[F.lit(None).cast("long").alias(k) for k in ("k0", "k1", "gram")])
    asked = texts.select("text", "k0", "k1").mapInArrow(grams, "shard long, salt long, k0 long, k1 long, gram long").select("shard", "salt", F.lit(None).cast("binary").alias("many"), "k0", "k1", "gram")
    met = copies.unionByName(asked).repartition("shard", "salt").sortWithinPartitions("shard", "salt", F.col("many").isNull())
    return met.mapInArrow(answer, "k0 long, k1 long, gram long").distinct().groupBy("k0", "k1").agg(F.collect_list("gram").alias("grams"))


def _gaps(ascending: np.ndarray) -> bytes:
    """Ascending whole numbers as 7-bit groups of their gaps, low groups first; the last group of each has the high bit."""
    gap = np.diff(ascending, prepend=-1) - 1
    groups = np.ones(len(gap), np.int64)
    for k in range(1, 5):
        groups += gap >= 1 << 7 * k
    ends = np.cumsum(groups)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    begins = ends - groups
    for k in range(5):
        has = groups > k
        out[begins[has] + k] = (gap[has] >> 7 * k) & 127
    out[ends - 1] |= 128
    return out.tobytes()


def _ungapped(packed: bytes) -> np.ndarray:
    data = np.frombuffer(packed, np.uint8)
    if not len(data):
        return np.empty(0, np.int64)
    last = data >= 128
    begins = np.flatnonzero(np.concatenate(([True], last[:-1])))
    place = np.arange(len(data)) - np.repeat(begins, np.diff(np.append(begins, len(data))))
    gap = np.add.reduceat((data & 127).astype(np.int64) << (7 * place), begins)
    return np.cumsum(gap + 1) - 1


def false_alarms(texts: DataFrame, estimate, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(k0, k1, singles): for each text the positions and digests of windows estimated repeated that start nowhere else."""

    def run(batches):
        for batch in batches:
            k0, k1 = batch.column("k0"), batch.column("k1")
            for first, piece in chunks(utf8(batch.column("text"))):
                found = Piece(piece, window, gram)
                starts = found.suspects(estimate(batch, first, len(piece)))
                if len(starts):
                    both, (row, at) = found.digests(starts), found.places(starts)
                    row = pa.array(first + row)
                    yield pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1]), k0.take(row), k1.take(row), pa.array(at.astype(np.int32))], names=["d0", "d1", "k0", "k1", "start"])

    alike = texts.mapInArrow(run, "d0 long, d1 long, k0 long, k1 long, start int").groupBy("d0", "d1")
    single = alike.agg(F.count("*").alias("n"), F.min("k0").alias("k0"), F.min("k1").alias("k1"), F.min("start").alias("start")).filter("n = 1")
    return single.groupBy("k0", "k1").agg(F.collect_list(F.struct("start", "d0")).alias("singles"))


def deduplicated(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, text: str = "text", keep: list[str] | None = None, shape: Shape | None = None, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """docs (or its columns in keep) with n_words, n_removed and kept_text, the words left joined by one space."""
    return _finished(docs, window, gram, text, keep, shape, broadcast_bytes, digest=False)


def _finished(docs, window, gram, text, keep, shape, broadcast_bytes, digest: bool) -> DataFrame:
    plain, name = unnamed(docs)
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("n_words", "n_removed", "kept_text", "kept_sha256")]
    own = [name[c] for c in kept]
    words = F.col(name[text])
    # Hashes of the text with two seeds; a hash of a hash would add nothing.
    rows = plain.select(*own, words.alias("text"), *[F.xxhash64(F.lit(seed), words).alias(k) for k, seed in (("k0", "one"), ("k1", "two"))])
    source = rows.select("text", "k0", "k1")
    shape = shape or Shape(docs.agg(F.coalesce(F.sum(F.octet_length(text)), F.lit(0))).first()[0])
    merged = shards(source, shape, window, gram)
    if shape.bytes <= broadcast_bytes:
        shipped = docs.sparkSession.sparkContext.broadcast(gathered(merged, shape))
        estimate = lambda batch, first, n: shipped.value
    else:
        lists = cut(looked_up(source, cut(merged), shape, window, gram))
        rows, source = (frame.join(lists, ["k0", "k1"], "left") for frame in (rows, source))
        estimate = lambda batch, first, n: Listed(batch.column("grams").slice(first, n))
    alarms = cut(false_alarms(source, estimate, window, gram))
    few = alarms.agg(F.coalesce(F.sum(F.size("singles")), F.lit(0)) + F.count("*")).first()[0] <= BROADCAST_ROWS
    joined = rows.join(F.broadcast(alarms) if few else alarms, ["k0", "k1"], "left")
    last = "kept_sha256" if digest else "kept_text"

    def run(batches):
        for batch in batches:
            singles = batch.column("singles")
            count, removed, left = [], [], []
            for first, piece in chunks(utf8(batch.column("text"))):
                found = Piece(piece, window, gram)
                starts = found.suspects(estimate(batch, first, len(piece)))
                some = singles.slice(first, len(piece))
                if len(starts) and some.null_count < len(piece):
                    row = np.flatnonzero(some.is_valid().to_numpy(zero_copy_only=False))
                    each = some.drop_null().flatten()
                    row = np.repeat(row, some.drop_null().value_lengths().to_numpy())
                    at = (found.ends - found.sizes)[row] + each.field("start").to_numpy()
                    mine = np.isin(at, starts)
                    at, value = at[mine], each.field("d0").to_numpy()[mine]
                    if len(at):
                        starts = np.setdiff1d(starts, at[found.digests(at)[:, 0] == value])
                gone = covered(starts, window, len(found.flat)) if len(starts) else None
                for split, end in zip(found.split, found.ends.tolist()):
                    n = len(split)
                    if gone is not None and (mask := gone[end - n : end]).any():
                        split = list(compress(split, (~mask).tolist()))
                    count.append(n)
                    removed.append(n - len(split))
                    whole = b" ".join(split)
                    left.append(hashlib.sha256(whole).hexdigest() if digest else whole.decode("utf-8", "replace"))
            yield with_columns(batch, {"n_words": pa.array(count, pa.int64()), "n_removed": pa.array(removed, pa.int64()), last: pa.array(left, pa.string())}, own)

    found = joined.mapInArrow(run, extended(plain, f"n_words long, n_removed long, {last} string", own))
    return found.select(*[F.col(name[c]).alias(c) for c in kept], "n_words", "n_removed", last)


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _finished(table(spark, sf_dir, "documents"), WINDOW, GRAM, "text", ["doc_id"], None, BROADCAST_BYTES, digest=True).select("doc_id", "n_words", "n_removed", "kept_sha256")


OP10_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS (SELECT doc_id, i, sha256(array_to_string(w[i : i + 34], ' ')) AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM d WHERE len(w) >= 35)),
r AS (SELECT s FROM g GROUP BY s HAVING count(*) > 1),
c AS (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS pos FROM g JOIN r USING (s)),
p AS (SELECT doc_id, w[pos] AS word, pos FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS pos FROM d)),
k AS (SELECT p.doc_id, string_agg(word, ' ' ORDER BY p.pos) AS kept, count(*) AS n FROM p LEFT JOIN c USING (doc_id, pos) WHERE c.pos IS NULL GROUP BY p.doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(len(d.w) - coalesce(k.n, 0) AS BIGINT) AS n_removed, sha256(coalesce(k.kept, '')) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)
"""
