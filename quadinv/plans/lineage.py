"""Where the result of a node of the recursion is kept, so that plans stay small and lost executors don't replay the tree."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

MODES = ("reliable", "parquet", "persist")
#: Random doubles don't compress, and dictionaries of them only cost time.
PARQUET = {"compression": "uncompressed", "parquet.enable.dictionary": "false"}


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster shares for checkpoints: the session's spark.checkpoint.dir.

    Where none is set, a temporary one on a local master, whose executors see it; on a cluster that is an error.
    """
    context = spark.sparkContext
    current = context._jsc.sc().getCheckpointDir()
    if current.isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="quadinv-checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def materialize(df: DataFrame, mode: str = "reliable", by: str | None = None) -> DataFrame:
    """df computed once and cut off from its plan.

    `reliable`: a checkpoint in the shared folder; the session removes it with its last use where
    spark.cleaner.referenceTracking.cleanCheckpoints is set. `parquet`: a table there (disk between all steps, as on a MapReduce
    system), with a folder for each value of `by`, so that a filter on it reads nothing else; removed when the interpreter
    ends or by `clear`. `persist`: memory and local disk only; the logical plan is cut, for it would double with every level, but
    lost parts are computed again from what came before.
    """
    if mode not in MODES:
        raise ValueError(f"unknown mode {mode!r}")
    spark = df.sparkSession
    if mode == "persist":
        held = df.persist()._jdf
        return DataFrame(spark._jsparkSession.internalCreateDataFrame(held.queryExecution().toRdd(), held.schema(), False), spark)
    folder = shared_folder(spark)
    if mode == "reliable":
        return df.checkpoint(eager=True)
    path = f"{folder}/blocks-{uuid.uuid4().hex}"
    writer = df.write.options(**PARQUET)
    (writer.partitionBy(by) if by else writer).parquet(path)
    WRITTEN.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


#: Tables written by `parquet` and not yet removed.
WRITTEN: list[tuple[SparkSession, str]] = []


@atexit.register
def clear() -> None:
    """Remove the tables of `parquet` whose results are no longer wanted (all of them)."""
    while WRITTEN:
        spark, path = WRITTEN.pop()
        try:
            target = spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(target, True)
        except Exception:  # the session has ended, and with it the way to its file system
            return
