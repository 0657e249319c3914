"""Matrices in files: Parquet block stores with their metadata, and cells as Parquet, CSV or JSON."""

from __future__ import annotations

from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession

from ..operators.blocks import COO_DDL, BlockFrame, MatrixMeta, to_coo

META_DDL = "logical_rows long, logical_cols long, block int, grid_rows long, grid_cols long, symmetric boolean"


def save(a: BlockFrame, path: str, mode: str = "errorifexists") -> None:
    """Blocks and metadata under path, on any file system that Spark writes."""
    a.df.write.mode(mode).parquet(f"{path}/blocks")
    a.spark.createDataFrame([tuple(asdict(a.meta).values())], META_DDL).coalesce(1).write.mode(mode).json(f"{path}/meta")


def load(spark: SparkSession, path: str) -> BlockFrame:
    meta = spark.read.schema(META_DDL).json(f"{path}/meta").first()
    return BlockFrame(spark.read.parquet(f"{path}/blocks"), MatrixMeta(**meta.asDict()))


def save_coo(a: BlockFrame, path: str, form: str = "parquet", mode: str = "errorifexists") -> None:
    to_coo(a).write.mode(mode).format(form).save(path)


def load_coo(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    return spark.read.schema(COO_DDL).format(form).load(path)


def noop(df: DataFrame) -> None:
    """Compute df and keep nothing (benchmarks)."""
    df.write.format("noop").mode("overwrite").save()
