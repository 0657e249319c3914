"""Matrices accumulated from streams, and inverses that follow them."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.blocks import from_coo
from ..operators.invert import InvertOptions, quad_inverse
from ..plans.lineage import shared_folder
from ..sources.matrices import damped

EVENTS_DDL = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream of its files; with one file, one micro-batch."""
    schema = spark.read.parquet(path).schema
    folder, name = path.rstrip("/").rsplit("/", 1)
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", name).parquet(folder)
    return source.withColumn("ts", instant("ts")) if schema["ts"].dataType.typeName() == "timestamp_ntz" else source


def micros(ts: str) -> Column:
    """Microseconds of a time without zone since 1970, whatever the session's zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', {ts})")


def instant(ts: str) -> Column:
    """A time without zone as the instant that it names in UTC; watermarks need an instant."""
    return F.timestamp_micros(micros(ts))


def plain(ts: str) -> Column:
    """The time without zone of an instant in UTC."""
    return F.expr(f"timestampadd(MICROSECOND, unix_micros({ts}), TIMESTAMP_NTZ '1970-01-01 00:00:00')")


def tumbling_counts(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(start, event_type, n) for each window."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding_counts(events: DataFrame, width: str = "1 day", step: str = "12 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """(user_id, start, stop, n) for each session of a user."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("stop"), "n")


def gram_stream(rows: DataFrame, features: list[str], width: str, late: str = "1 hour") -> DataFrame:
    """(start, i, j, x): cells of Z'Z for each window of a stream with ts; the state holds one number a cell and window."""
    pairs = [F.struct(F.lit(i).cast("long").alias("i"), F.lit(j).cast("long").alias("j"), (F.col(p) * F.col(q)).alias("x")) for i, p in enumerate(features) for j, q in enumerate(features)]
    cells = rows.withWatermark("ts", late).select("ts", F.explode(F.array(*pairs)).alias("c"))
    return cells.groupBy(F.window("ts", width), "c.i", "c.j").agg(F.sum("c.x").alias("x")).select(F.col("window.start").alias("start"), "i", "j", "x")


def transition_stream(events: DataFrame) -> DataFrame:
    """(event_type, next): one row for each step of a user; the state is the last event met.

    Events of one micro-batch are put in order; those that come in a later one are taken to be later.
    """

    def steps(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        parts = list(frames)
        met = parts[0] if len(parts) == 1 else pd.concat(parts)
        order = np.lexsort((met["event_id"].to_numpy(), met["ts"].to_numpy()))
        types = met["event_type"].to_numpy()[order].tolist()
        if state.exists:
            types = [state.get[0], *types]
        state.update((types[-1],))
        yield pd.DataFrame({"event_type": types[:-1], "next": types[1:]}, dtype=object)

    known = events.filter("event_type is not null").select("user_id", "ts", "event_id", "event_type")
    return known.groupBy("user_id").applyInPandasWithState(steps, "event_type string, next string", "event_type string", "append", GroupStateTimeout.NoTimeout)


def rank_one_inverse(vectors: DataFrame, width: int) -> DataFrame:
    """For a stream of (key, x: array of width values): (key, n, inverse) of I + sum of x x' after each micro-batch.

    The inverse is kept up by the rank-one update; the state is one matrix a key.
    """

    def updated(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, flat = state.get if state.exists else (0, np.eye(width).ravel().tolist())
        m = np.array(flat).reshape(width, width)
        for frame in frames:
            for x in frame["x"]:
                x = np.asarray(x, float)
                y = m @ x
                m = m - np.outer(y, y) / (1.0 + x @ y)
                n += 1
        state.update((n, m.ravel().tolist()))
        yield pd.DataFrame({"key": [key[0]], "n": [n], "inverse": [m.ravel().tolist()]})

    kind = vectors.schema["key"].dataType.simpleString()
    return vectors.groupBy("key").applyInPandasWithState(updated, f"key {kind}, n long, inverse array<double>", "n long, m array<double>", "update", GroupStateTimeout.NoTimeout)


def invert_each_batch(shares: DataFrame, n: int, block: int, sink: Callable[[DataFrame, int], None], opts: InvertOptions | None = None):
    """A writer that inverts I - 0.9 P for the cells of each micro-batch and hands the inverse's cells to sink.

    Set its checkpointLocation to a folder that all executors share.
    """
    from ..operators.blocks import to_coo

    def run(batch: DataFrame, number: int) -> None:
        sink(to_coo(quad_inverse(from_coo(damped(batch), n, block), opts)), number)

    return shares.writeStream.foreachBatch(run)


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """What a stream gives from all that is there now. Rows go to files of the folder that the cluster shares, not through the driver.

    Complete results replace each other, so the last micro-batch's is the result. Updates are kept in memory (for results of bounded size).
    """
    spark = stream.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True)
    if mode == "update":
        writer.format("memory").start().awaitTermination()
        return spark.table(name)
    if mode == "append":
        writer.format("parquet").option("path", f"{folder}/rows").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/rows")
    last: list[str] = []

    def kept(batch: DataFrame, number: int) -> None:
        path = f"{folder}/rows-{number}"
        batch.write.mode("overwrite").parquet(path)
        last[:] = [path]

    writer.foreachBatch(kept).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(*last) if last else spark.createDataFrame([], stream.schema)
