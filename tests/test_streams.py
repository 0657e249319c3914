"""Streams answer as batches do; late rows and running inverses."""

import datetime as dt
import uuid

import numpy as np

from quadinv.streaming import streams


def write(spark, folder, number, rows, ddl):
    spark.createDataFrame(rows, ddl).coalesce(1).write.mode("append").parquet(str(folder))


def test_rank_one_inverse(spark, tmp_path):
    draw = np.random.default_rng(3)
    x = draw.random((6, 3))
    for part in (x[:3], x[3:]):
        write(spark, tmp_path / "v", 0, [("k", [float(v) for v in row]) for row in part], "key string, x array<double>")
    source = spark.readStream.schema("key string, x array<double>").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "v"))
    out = streams.drained(streams.rank_one_inverse(source, 3), f"r{uuid.uuid4().hex}", "update").collect()
    last = max(out, key=lambda r: r.n)
    assert last.n == 6 and np.allclose(np.array(last.inverse).reshape(3, 3), np.linalg.inv(np.eye(3) + x.T @ x))


def test_late_rows_are_dropped(spark, tmp_path):
    day = dt.datetime(2024, 1, 1)
    first = [(1, day + dt.timedelta(days=5), 1, "view", 1.0, None)]
    late = [(2, day, 1, "view", 1.0, None)]
    folder = tmp_path / "e"
    write(spark, folder, 0, first, streams.EVENTS_DDL)
    source = spark.readStream.schema(streams.EVENTS_DDL).option("maxFilesPerTrigger", 1).parquet(str(folder))
    name, check = f"t{uuid.uuid4().hex}", str(tmp_path / "c")
    out = str(tmp_path / "out")

    def turn():
        q = streams.tumbling_counts(source, "1 day", "1 hour").writeStream.format("parquet").option("checkpointLocation", check).outputMode("append").trigger(availableNow=True).start(out)
        q.awaitTermination()

    turn()
    write(spark, folder, 1, late, streams.EVENTS_DDL)
    write(spark, folder, 2, [(3, day + dt.timedelta(days=9), 1, "view", 1.0, None)], streams.EVENTS_DDL)
    turn()
    turn()
    days = {r.start.day for r in spark.read.parquet(out).collect()}
    assert 1 not in days and name


def test_inverse_of_each_batch(spark, tmp_path):
    rows = [(i, j, 0.5) for i in range(2) for j in range(2)]
    write(spark, tmp_path / "p", 0, rows, "i long, j long, x double")
    source = spark.readStream.schema("i long, j long, x double").parquet(str(tmp_path / "p"))
    seen = []
    writer = streams.invert_each_batch(source, 2, 1, lambda cells, k: seen.append({(r.i, r.j): r.x for r in cells.collect()}))
    writer.trigger(availableNow=True).start().awaitTermination()
    want = np.linalg.inv(np.eye(2) - 0.9 * np.full((2, 2), 0.5))
    assert np.allclose([[seen[0][i, j] for j in range(2)] for i in range(2)], want)


def test_drained_rows_do_not_go_through_the_driver(spark, tmp_path):
    day = dt.datetime(2024, 1, 1)
    folder = tmp_path / "d"
    for k in range(2):
        write(spark, folder, k, [(5 * k + i, day + dt.timedelta(hours=5 * k + i), i % 2, "view" if i % 3 else "click", 1.0, None) for i in range(5)], streams.EVENTS_DDL)
    source = spark.readStream.schema(streams.EVENTS_DDL).option("maxFilesPerTrigger", 1).parquet(str(folder))
    name = f"n{uuid.uuid4().hex}"
    steps = streams.drained(streams.transition_stream(source), name)
    counts = streams.drained(streams.tumbling_counts(source), f"{name}c", "complete")
    assert not spark.catalog.tableExists(name) and not spark.catalog.tableExists(f"{name}c")
    assert steps.count() == 8 and sum(r.n for r in counts.collect()) == 10
    assert len(counts.collect()) == 2
