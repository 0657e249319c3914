"""What the operators of this subpackage share: tables, lineage cuts, Arrow helpers, held-out folds."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Text is handed to numpy in pieces of about this many bytes, so that a worker's memory doesn't follow the batch size.
CHUNK_BYTES = 2 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the folder that the cluster shares.

    The session removes a checkpoint with its last use where spark.cleaner.referenceTracking.cleanCheckpoints is set.
    """
    context = df.sparkSession.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(shared_folder(df.sparkSession, "quadinv-checkpoint"))
    return df.checkpoint(eager=True)


def tidy(spark: SparkSession) -> None:
    """Have the driver's JVM collect its garbage: its heap shrinks, and the cleaner removes shuffles and checkpoints of frames that are gone."""
    spark.sparkContext._jvm.System.gc()


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder under the session's spark.checkpoint.dir.

    Where that is unset, a temporary one on a local master, whose executors see it; on a cluster that is an error.
    """
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared:
        return f"{shared.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return tempfile.mkdtemp(prefix=f"{name}-")


def fold(doc_id: str, modulus: int, remainder: int) -> Column:
    """True for rows of the held-out fold; a null id is of no fold and so counts as held out (never learned from)."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(modulus)) == remainder, F.lit(True))


def bounded_sample(rows: DataFrame, key: str, n: int) -> DataFrame:
    """At most n rows, those whose hashed key is smallest: the same rows on every run, spread over the table."""
    return rows.orderBy(F.xxhash64(F.col(key), F.lit("sample")), F.col(key)).limit(n)


def unnamed(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs with columns of neutral names, which clash with no operator's own, and the new name of each column."""
    name = {c: f"column_{k}_" for k, c in enumerate(docs.columns)}
    return docs.toDF(*name.values()), name


def renamed(found: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of docs, by their own names, from what an operator made of unnamed(docs)."""
    return found.select(*[F.col(f"column_{k}_").alias(c) for k, c in enumerate(docs.columns)])


def utf8(column: pa.Array) -> list[bytes | None]:
    """A string column's values as UTF-8 bytes, without decoding."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def with_columns(batch: pa.RecordBatch, columns: dict[str, pa.Array], keep: list[str] | None = None) -> pa.RecordBatch:
    names = [n for n in (batch.schema.names if keep is None else keep) if n not in columns]
    arrays = [batch.column(batch.schema.get_field_index(n)) for n in names]
    return pa.RecordBatch.from_arrays(arrays + list(columns.values()), names=names + list(columns))


def extended(df: DataFrame, added: str, keep: list[str] | None = None) -> T.StructType:
    """df's schema (or its columns in keep) with the DDL columns of added behind it, which replace those of the same name."""
    extra = T._parse_datatype_string(added)
    new = {f.name.lower() for f in extra}
    return T.StructType([f for f in df.schema if f.name.lower() not in new and (keep is None or f.name in keep)] + list(extra))


def chunks(values: list[bytes | None], limit: int = CHUNK_BYTES) -> Iterator[tuple[int, list[bytes]]]:
    """(first row, texts) in pieces of about limit bytes; a null text becomes an empty one."""
    begin, size, piece = 0, 0, []
    for i, value in enumerate(values):
        value = value or b""
        if piece and size + len(value) > limit:
            yield begin, piece
            begin, size, piece = i, 0, []
        piece.append(value)
        size += len(value)
    if piece:
        yield begin, piece


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit values (splitmix finaliser)."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_hashes(words: list[bytes]) -> np.ndarray:
    """64-bit hash of each word. Hashing anew is quicker than a table: a seventh of the words of a text is met once only."""
    import xxhash

    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def rolling(h: np.ndarray, width: int, multiplier: int) -> np.ndarray:
    """Hash of each run of width consecutive values: powers of an odd multiplier, by doubling, modulo 2**64."""
    n = len(h) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    with np.errstate(over="ignore"):
        total, have, block, size, power = np.zeros(n, np.uint64), 0, h, 1, np.uint64(multiplier)
        scale = np.uint64(1)
        rest = width
        while rest:
            if rest & 1:
                total = total + block[have : have + n] * scale
                have += size
                scale = scale * power
            rest >>= 1
            if rest:
                block = block[:-size] + block[size:] * power if len(block) > size else block[:0]
                size *= 2
                power = power * power
    return mix(total)


def covered(starts: np.ndarray, width: int, n: int) -> np.ndarray:
    """Which of n positions lie in a run of width that begins at one of starts."""
    change = np.bincount(starts, minlength=n + 1) - np.bincount(np.minimum(starts + width, n), minlength=n + 1)
    return np.cumsum(change[:-1]) > 0


def own_exchange(aggregated: DataFrame, key: str) -> DataFrame:
    """An aggregated side of a join with its long key as a computed column.

    The optimizer then shuffles this (smaller) side once more by the key, and with a plain exchange on both sides a join can
    split a hot key of the other side at run time, which it can't where one side is read straight from an aggregate.
    """
    return aggregated.withColumn(key, F.col(key).bitwiseXOR(F.lit(0).cast("long")))
